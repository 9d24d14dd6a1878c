"""A second front end: operations in Spark SQL texts, read by the session's own parser; and a place to register more.

The parser lives in the driver, so this is for programs' SQL scripts (thousands of statements), not for tables of texts.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Front ends by name: (session, files as rows) -> operations.
FRONTENDS: dict[str, Callable[[SparkSession, list], list[tuple]]] = {}

_RELATION = re.compile(r"UnresolvedRelation \[([^\]]+)\]")
_KINDS = (("InsertIntoStatement", "I"), ("UpdateTable", "U"), ("DeleteFromTable", "D"), ("MergeIntoTable", "U"), ("CreateTable", "I"))


def register_frontend(name: str, fn: Callable[[SparkSession, list], list[tuple]]) -> None:
    FRONTENDS[name] = fn


def statements(text: str) -> list[str]:
    """Statements of a script: split at semicolons that stand outside strings and comments."""
    parts = re.findall(r"'(?:[^']|'')*'|\"[^\"]*\"|--[^\n]*|/\*.*?\*/|;|[^;'\"\-/]+|.", text, re.S)
    out = [""]
    for p in parts:
        if p == ";":
            out.append("")
        elif not p.startswith(("--", "/*")):
            out[-1] += p
    return [s.strip() for s in out if s.strip()]


def sql_operations(spark: SparkSession, files: list) -> list[tuple]:
    """(app_id, path, seq, kind, container, n_joins, error) of each statement and table it touches."""
    parser, out = spark._jsparkSession.sessionState().sqlParser(), []
    for f in files:
        for seq, text in enumerate(statements(f["content"] or "")):
            try:
                plan = parser.parsePlan(text).toString()
            except Exception as e:  # a statement of another dialect; the others still count
                out.append((f["app_id"], f["path"], seq, None, None, 0, str(e).split("\n")[0][:200]))
                continue
            kind = next((k for name, k in _KINDS if name in plan), "R")
            names = [n.replace(", ", ".").split(".,")[0].split(",")[0] for n in _RELATION.findall(plan)]
            for i, name in enumerate(dict.fromkeys(names)):
                out.append((f["app_id"], f["path"], seq, kind if i == 0 else "R", name.strip().rstrip("."), plan.count("Join "), None))
    return out


register_frontend("sql", sql_operations)


def operations(files: DataFrame, language: str = "sql") -> DataFrame:
    """Operations that a registered front end finds in ``files``; the driver reads each distinct text once."""
    spark = files.sparkSession
    files = files.select("app_id", "path", "content").withColumn("digest", F.sha2(F.coalesce("content", F.lit("")), 256))
    texts = files.groupBy("digest").agg(F.min(F.struct("app_id", "path", "content")).alias("x")).select("digest", "x.*").collect()  # scripts of a program
    rows = [(r["digest"], *found[2:]) for r in texts for found in FRONTENDS[language](spark, [r])]
    found = spark.createDataFrame(rows, "digest string, seq int, kind string, container string, n_joins int, error string")
    return files.join(found, "digest").select("app_id", "path", "seq", "kind", "container", "n_joins", "error")
