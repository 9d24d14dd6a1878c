"""One call for the whole chain."""

from __future__ import annotations

from pyspark.sql import DataFrame

from .operators import joins, logical
from .operators.access import Access
from .operators.models import Models
from .plans import Options
from .store import written


def analyze(files: DataFrame, options: Options = Options(), api: list | None = None) -> Access:  # noqa: B008
    """Program files (app_id, version, path, content, sha, lang) to their access model."""
    return Access(Models(files), options, api)


def logical_schema(files: DataFrame, options: Options = Options()) -> DataFrame:  # noqa: B008
    return logical.to_logical(analyze(files, options))


def plans(files: DataFrame, options: Options = Options()) -> DataFrame:  # noqa: B008
    return joins.removal_plans(analyze(files, options))


def remove_join(a: Access, schema: DataFrame, frames: dict[str, DataFrame], plan_id: str, force: bool = False) -> tuple[DataFrame, DataFrame, dict[str, DataFrame]]:
    """One removal on all three layers: (changed files, schema, collections).

    A plan that isn't safe, or whose code can't be changed without a look at it, is refused unless forced, so the layers stay consistent.
    """
    from .operators.migrate import apply_to_data, duplication_of
    from .operators.rewrite import apply_to_code

    found = joins.select_plans(joins.removal_plans(a), ids=[plan_id])
    row = found.first()  # one plan
    if row is None or not (row["safe"] or force):
        raise ValueError(f"plan {plan_id} is unknown or not safe")
    code = written(apply_to_code(a.m.files, found, a.ops), "code")
    if not force and not code.where("review").isEmpty():
        raise ValueError(f"the code of plan {plan_id} can't be changed without a look at it")
    data = {**frames, row["host"]: apply_to_data(frames[row["host"]], frames[row["referenced"]], duplication_of(row))}
    return code, joins.apply_to_schema(schema, found), data
