"""Column functions that the operators share."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def singular(name: Column) -> Column:
    """The singular of an English plural, by its ending."""
    return (
        F.when(name.rlike("(?i)ies$"), F.regexp_replace(name, "(?i)ies$", "y"))
        .when(name.rlike("(?i)(ses|xes|zes|ches|shes)$"), F.regexp_replace(name, "(?i)es$", ""))
        .when(name.rlike("(?i)[^s]s$"), F.regexp_replace(name, "(?i)s$", ""))
        .otherwise(name)
    )


def singular_text(name: str) -> str:
    if name.endswith("ies"):
        return name[:-3] + "y"
    if name.endswith(("ses", "xes", "zes", "ches", "shes")):
        return name[:-2]
    return name[:-1] if name.endswith("s") and not name.endswith("ss") else name


def stem(name: Column) -> Column:
    """A column's name without a table prefix, a key suffix and its plural: what name heuristics compare."""
    base = F.regexp_replace(F.lower(name), "^[a-z]{1,2}_", "")
    return singular(F.regexp_replace(base, "(_?(id|key)s?)$", ""))


def name_similarity(a: Column, b: Column) -> Column:
    """1 minus the edit distance over the longer length, to three digits."""
    return F.round(1 - F.levenshtein(a, b) / F.greatest(F.length(a), F.length(b)), 3)


def steps_path(steps: Column) -> Column:
    """The names of a path's property steps, joined with dots."""
    return F.array_join(F.transform(F.filter(steps, lambda s: s["kind"] == "prop"), lambda s: s["name"]), ".")


def digest_of(values: Column) -> Column:
    return F.sha2(F.array_join(F.sort_array(F.collect_set(values)), ","), 256)
