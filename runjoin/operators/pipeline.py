"""The two ways to use a summary: compute, store and reuse; or compute, expand and forget."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..plans.spec import JoinQuery
from ..sources import store
from . import baselines, expand
from .eliminate import build_generator, sizes_of
from .summary import RunSummary, generate

#: A join whose steps never have over so many rows for one row of the largest table goes by a binary plan.
FAN = 1.5


def summarise(query: JoinQuery, cut: bool = False, **options) -> RunSummary:
    return generate(build_generator(query, **{"reached": True, "once": options.get("project") == "skip", **options}), cut)


def summarise_to(query: JoinQuery, path: str, format: str = "parquet", **options) -> None:
    """Summary to files; rows of the join are never made. Each conditional is placed by itself: what all of them take from
    deleted variables is computed once."""
    store.write(summarise(query, **{"once": True, **options}), path, format)


def reload(spark: SparkSession, path: str) -> DataFrame:
    """Files to rows."""
    return expand.from_columns(store.read(spark, path))


def plan(query: JoinQuery) -> str:
    """``binary`` where joining rows is expected to make no step larger than FAN times the largest table, else ``summary``.

    Foreign-key joins are of the first kind: each table after the first is (nearly) unique on what it shares with those
    before it, so nothing is redundant. Rows and distinct keys come from one pass over the tables.
    """
    sizes = sizes_of(query.tables)
    largest = max(sizes, key=lambda t: sizes[t][0])
    names = baselines.connected(query, [largest, *(t for t in query.tables if t != largest)])
    seen, fan = set(query.scopes[names[0]]), 1.0
    for t in names[1:]:
        rows, distinct = sizes[t]
        keys = 1.0
        for v in seen & set(query.scopes[t]):
            keys *= distinct[v]
        fan *= max(1.0, rows / min(keys, max(1, rows)))
        seen |= set(query.scopes[t])
    return "binary" if fan <= FAN else "summary"


def join(query: JoinQuery, method: str = "summary", spread: bool | None = None, **options) -> DataFrame:
    """Rows of the join, lazily: through the summary, by a binary plan, or by what ``plan`` says (``auto``)."""
    if method == "auto":
        method = plan(query)
    if method == "binary":
        return baselines.binary(query)
    return expand.flatten(summarise(query, **options), spread).select(*query.output)
