"""The driver contract, and every SQL twin on the smallest tables."""

import math

import __spark_entry__ as entry
import pytest

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def test_contract(spark):
    queries, oracle = entry.queries(), entry.oracle_sql()
    assert set(oracle) <= set(queries) and len(queries) > 120
    assert entry.entry(spark).columns == ["subject", "component", "n_evidence"]


def norm(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(round(v, 5) + 0.0)
    return v if v is None else str(v).replace("T", " ")


@pytest.mark.parametrize("name", ["study_granularity", "study_conjugate_matching", "study_similar_pairs_prefix", "extract_linked", "extract_print_additive", "refine_origin_shuffled", "refine_percentile", "detect_flagship", "detect_versions", "detect_full", "rq1_accuracy", "study_associated_similar", "study_minhash_recall", "java_detect", "truth_union", "rq3_improvement_trade", "truth_contains", "rel_asof", "stream_index", "stream_late", "stream_windows_session"])
def test_sql_twin(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    df = entry.queries()[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted(tuple(str(norm(v)) for v in r) for r in df.select(*cols).collect())
    want = sorted(tuple(str(norm(v)) for v in r) for r in con.sql(f"select {', '.join(cols)} from ({entry.oracle_sql()[name]})").fetchall())
    assert got == want
