"""SQL names for the functions: ``register(spark)`` makes them known to ``spark.sql``."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from .hashing import MODULUS


def commutative_print():
    """Grouped aggregate: the sum of own hashes modulo the print's modulus, whatever the order."""

    @F.pandas_udf("long")
    def summed(own: pd.Series) -> int:
        return int(sum(int(x) for x in own) % MODULUS)

    return summed


def register(spark: SparkSession) -> None:
    from ..sources import java

    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cp_complexity(v DOUBLE, cc DOUBLE, loc DOUBLE) RETURNS DOUBLE RETURN 5.2D * ln(greatest(v, 1D)) + 0.23D * cc + 16.2D * ln(greatest(loc, 1D))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cp_own_hash(x STRING) RETURNS BIGINT RETURN cast(conv(substr(md5(x), 1, 15), 16, 10) AS BIGINT)")

    @F.pandas_udf("int")
    def cyclomatic(body: pd.Series) -> pd.Series:
        return body.map(lambda b: 1 + sum(t in java.BRANCH for _, t, _ in java.lex(b or ""))).astype("int32")

    spark.udf.register("cp_cyclomatic", cyclomatic)
    spark.udf.register("cp_commutative_print", commutative_print())

    @udtf(returnType="class_name string, kind string, fn_name string, pos int, loc int, cc int, error string")
    class JavaUnits:
        def eval(self, text: str):
            for r in java.parse("", text):
                yield tuple(r[c] for c in ("class_name", "kind", "fn_name", "pos", "loc", "cc", "error"))

    spark.udtf.register("cp_java_units", JavaUnits)
