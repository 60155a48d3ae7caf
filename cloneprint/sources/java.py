"""Java front end: a lexer and a structural parser that give classes, functions, labels and internal calls.

It needs no compiler: comments and literals are told apart by one pattern, classes and functions by braces. Files that do not
balance give one row with ``error`` and nothing else; no file stops the job.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# The language's reserved words that matter here.
CONTROL = frozenset("if for while switch catch synchronized return new throw else do try super this assert case".split())
TYPES = frozenset("boolean byte char short int long float double void".split())
KEYWORDS = CONTROL | TYPES | frozenset("abstract class const continue break default enum extends final finally goto implements import instanceof interface native package private protected public static strictfp throws transient volatile record var null true false".split())
BRANCH = frozenset(("if", "for", "while", "case", "catch", "&&", "||", "?"))
_LEX = re.compile(r"""(?P<skip>\s+|//[^\n]*|/\*.*?\*/)|(?P<text>\"{3}.*?\"{3}|"(?:\\.|[^"\\\n])*"|'(?:\\.|[^'\\\n])*')|(?P<num>\.?\d[\w.]*)|(?P<id>[A-Za-z_$][\w$]*)|(?P<op>&&|\|\||[-+*/%&|^<>=!]=|\+\+|--|->|::|\S)""", re.S)
SCHEMA = "path string, class_name string, kind string, fn_name string, pos int, loc int, cc int, hv double, labels array<string>, calls array<string>, error string"


def lex(source: str) -> Iterator[tuple[str, str, int]]:
    """(kind, token, line) of everything but blanks and comments."""
    line = 1
    for m in _LEX.finditer(source):
        if m.lastgroup != "skip":
            yield m.lastgroup, m.group(), line
        line += m.group().count("\n")


def label(kind: str, token: str, own_types: set[str]) -> str:
    """Skeleton label: names and values give way to their kinds; class names of the file stay."""
    if kind == "text":
        return "LITERAL_TEXT"
    if kind == "num":
        return "LITERAL_NUMBER"
    if kind == "id" and token not in KEYWORDS:
        return token if token in own_types else "NAME"
    return "PRIMITIVE" if token in TYPES else token


def halstead(tokens: list[tuple[str, str, int]]) -> float:
    """Volume: length times the logarithm of the vocabulary."""
    return len(tokens) * math.log2(max(2, len({t for _, t, _ in tokens}))) if tokens else 0.0


def parse(path: str, source: str | None) -> list[dict]:
    """Rows of SCHEMA: one per function, or one with a null function for a class without any."""
    toks = list(lex(source or ""))
    depth = 0
    for _, t, _ in toks:
        depth += (t == "{") - (t == "}")
        if depth < 0:
            break
    if depth:
        return [_row(path, error="braces do not balance")]
    own = {toks[k + 1][1] for k in range(len(toks) - 1) if toks[k][1] in ("class", "interface", "enum", "record") and toks[k + 1][0] == "id"}
    rows: list[dict] = []
    classes: list[dict] = []  # open ones, innermost last
    depth, k, pending = 0, 0, None
    while k < len(toks):
        kind, t, line = toks[k]
        if t in ("class", "interface", "enum", "record") and k + 1 < len(toks) and toks[k + 1][0] == "id" and (k == 0 or toks[k - 1][1] != "."):
            outer = classes[-1]["name"] + "." if classes else ""
            pending = {"name": outer + toks[k + 1][1], "kind": t, "n": 0}
            k += 2
            continue
        if t == "{":
            depth += 1
            if pending:
                classes.append(pending | {"depth": depth})
                pending = None
        elif t == "}":
            if classes and classes[-1]["depth"] == depth:
                done = classes.pop()
                if not done["n"]:
                    rows.append(_row(path, class_name=done["name"], kind=done["kind"]))
            depth -= 1
        elif kind == "id" and t not in KEYWORDS and not pending and classes and depth == classes[-1]["depth"] and k + 1 < len(toks) and toks[k + 1][1] == "(":
            close = _matching(toks, k + 1, "(", ")")
            body = close + 1
            while body < len(toks) and toks[body][1] not in ("{", ";", "}", "="):
                body += 1
            if body < len(toks) and toks[body][1] == "{" and (k == 0 or toks[k - 1][1] != "new"):
                end = _matching(toks, body, "{", "}")
                inner = toks[body + 1 : end]
                callees = [inner[i][1] for i in range(len(inner) - 1) if inner[i][0] == "id" and inner[i][1] not in KEYWORDS and inner[i + 1][1] == "(" and not (i and inner[i - 1][1] in (".", "new") and not (inner[i - 1][1] == "." and i > 1 and inner[i - 2][1] == "this"))]
                whole = toks[k + 1 : end]
                rows.append(
                    _row(path, class_name=classes[-1]["name"], kind=classes[-1]["kind"], fn_name=t, pos=classes[-1]["n"], loc=toks[end][2] - line + 1, cc=1 + sum(x in BRANCH for _, x, _ in inner), hv=halstead(toks[k : end + 1]), labels=[label(a, b, own) for a, b, _ in whole], calls=callees)
                )
                classes[-1]["n"] += 1
                k = end + 1
                continue
            k = close
        k += 1
    return rows


def _row(path: str, **values) -> dict:
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    return dict.fromkeys(names) | {"path": path} | values


def _matching(toks: list, at: int, left: str, right: str) -> int:
    depth = 0
    for k in range(at, len(toks)):
        depth += (toks[k][1] == left) - (toks[k][1] == right)
        if not depth:
            return k
    return len(toks) - 1


def _parsed(batches):
    kinds = [pa.string()] * 4 + [pa.int32()] * 3 + [pa.float64(), pa.list_(pa.string()), pa.list_(pa.string()), pa.string()]
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    for batch in batches:
        rows = [r for p, s in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) for r in parse(p, s)]
        yield pa.RecordBatch.from_arrays([pa.array([r[n] for r in rows], t) for n, t in zip(names, kinds, strict=True)], names)


def units(files: DataFrame) -> DataFrame:
    """Function rows of files (path, text)."""
    return files.select("path", "text").mapInArrow(_parsed, SCHEMA)


def parse_report(parsed: DataFrame) -> DataFrame:
    """One row: files, files with an error."""
    return parsed.agg(F.count_distinct("path").alias("n_files"), F.count_distinct(F.when(F.col("error").isNotNull(), F.col("path"))).alias("n_errors"))


def functions(parsed: DataFrame, kind: str = "portable") -> DataFrame:
    """class_id, fn, name, loc, own as the print operators take them."""
    from ..functions import hashing as H

    return parsed.where("fn_name is not null").select(F.concat_ws("#", "path", "class_name").alias("class_id"), F.col("pos").alias("fn"), F.col("fn_name").alias("name"), "loc", H.bag_hash(F.col("labels"), kind).alias("own"))


def calls(parsed: DataFrame) -> DataFrame:
    """class_id, caller, callee, n of calls to functions of the same class; an overloaded name stands for its first function."""
    fns = parsed.where("fn_name is not null").select(F.concat_ws("#", "path", "class_name").alias("class_id"), F.col("pos").alias("caller"), "fn_name", "calls")
    named = fns.groupBy("class_id", F.col("fn_name").alias("name")).agg(F.min("caller").alias("callee"))
    uses = fns.select("class_id", "caller", F.explode("calls").alias("name")).groupBy("class_id", "caller", "name").agg(F.count("*").alias("k"))
    return uses.join(named, ["class_id", "name"]).groupBy("class_id", "caller", "callee").agg(F.sum("k").alias("n"))


def read_tree(spark: SparkSession, path: str) -> DataFrame:
    """(path, text) of all .java files under a folder."""
    return spark.read.option("recursiveFileLookup", "true").option("pathGlobFilter", "*.java").option("wholetext", "true").text(path).select(F.input_file_name().alias("path"), F.col("value").alias("text"))
