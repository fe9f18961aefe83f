"""What the summary is compared with: binary plans, worst-case optimal joins of rows, flat files."""

from __future__ import annotations

import random
import uuid
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.spec import JoinQuery
from ..sources import store
from .bagjoin import dealt_out, potential_join

_HINTS = {"shuffle_hash": "shuffle_hash", "merge": "merge", "broadcast": "broadcast", "nested_loop": "shuffle_replicate_nl"}

#: Rows of a table beyond which the ``broadcast`` plan shuffles and merges it: every process, the driver too, would have to hold it whole.
BROADCAST_ROWS = 1 << 18

#: Rows of a last table for one value of its key from which the rows that meet them are dealt out and sorted first.
FAN_OUT = 64


def fans(query: JoinQuery, names: list[str], keys: dict[str, list[str]]) -> dict[str, float]:
    """Rows of each table for one value of its key (distinct keys are counted approximately), in one pass."""
    made = []
    for t in names:
        values = F.approx_count_distinct(F.struct(*keys[t])) if keys[t] else F.lit(1).cast("long")
        made.append(query.tables[t].agg(F.count(F.lit(1)).alias("rows"), values.alias("values")).select(F.lit(t).alias("t"), "rows", "values"))
    return {r["t"]: r["rows"] / max(1, r["values"]) for r in reduce(lambda a, b: a.unionByName(b), made).collect()}  # one row a table


def _in_order(query: JoinQuery, order: list[str] | None) -> list[str]:
    left, out, seen = list(order or query.tables), [], set()
    while left:
        t = left[0] if order else next((x for x in left if seen & set(query.scopes[x])), left[0])
        left.remove(t)
        out.append(t)
        seen |= set(query.scopes[t])
    return out


def steps(query: JoinQuery, algo: str = "auto", order: list[str] | None = None) -> list[DataFrame]:
    """Every intermediate of a left-deep binary plan; ``algo`` is a join hint, or Catalyst's choice."""
    names = _in_order(query, order)
    out, made = query.tables[names[0]], []
    for t in names[1:]:
        right = query.tables[t]
        on = [v for v in out.columns if v in right.columns]
        how = "merge" if algo == "broadcast" and right.count() > BROADCAST_ROWS else algo
        hinted = right.hint(_HINTS[how]) if how in _HINTS else right
        out = out.join(hinted, on) if on else out.crossJoin(hinted)
        made.append(out)
    return made or [out]


def binary(query: JoinQuery, algo: str = "auto", order: list[str] | None = None) -> DataFrame:
    """Rows of the last step. Where Catalyst chooses how to join and each row of the step before meets many of the last table,
    the former are dealt out and sorted first (no more columns than asked for)."""
    names = _in_order(query, order)
    seen = {v for t in names[:-1] for v in query.scopes[t]}
    on = [v for v in query.scopes[names[-1]] if v in seen]
    if algo == "auto" and len(names) > 2 and on and fans(query, names[-1:], {names[-1]: on})[names[-1]] >= FAN_OUT:
        kept = list(dict.fromkeys([*on, *[v for v in query.output if v in seen]]))
        before = JoinQuery({t: query.tables[t] for t in names[:-1]}, kept)
        rows = dealt_out(steps(before, algo, names[:-1])[-1].select(*kept), kept)
        return rows.join(query.tables[names[-1]], on).select(*query.output)
    return steps(query, algo, order)[-1].select(*query.output)


def bucketed(query: JoinQuery, path: str, buckets: int = 8, order: list[str] | None = None) -> DataFrame:
    """Binary sort-merge plan over tables that lie bucketed and sorted by a join column, as a stand-in for indexes built
    beforehand: each table by the variable it shares with those before it, so the first join needs no shuffle."""
    names, seen, stored = _in_order(query, order), set(), {}
    for i, t in enumerate(names):
        own = query.scopes[t]
        before = seen if i else set(query.scopes[names[1]]) if len(names) > 1 else set()
        keys = [v for v in own if v in before] or [v for v in own if v in query.joined]
        name = f"bucketed_{t}_{uuid.uuid4().hex}"
        writer = query.tables[t].write.option("path", f"{path}/{t}").mode("overwrite")
        (writer.bucketBy(buckets, keys[0]).sortBy(keys[0]) if keys else writer).saveAsTable(name)
        stored[t] = query.tables[t].sparkSession.table(name)
        seen |= set(own)
    return binary(JoinQuery(stored, query.output), "merge", names)


def wcoj(query: JoinQuery, variant: str = "generic", order: list[str] | str | None = None, seed: int = 0) -> DataFrame:
    """Variable-at-a-time join of rows: copies stay apart, told by a row number private to each table.

    ``generic`` grows prefixes with DataFrame joins; ``leapfrog`` and ``hash_trie`` join sorted levels or levels of hash tables
    in the cells of a grid, which number their rows themselves; ``heavy_light`` splits a join variable's values at the square root of the rows. If not given
    an order, ``generic`` binds join variables first, then what a table alone holds, its row number too, the table last that
    has most rows for one key: prefixes so multiply once, at the end.
    """
    if variant == "heavy_light":
        return heavy_light(query)
    numbered = {t: df.withColumn(f"row_{t}", F.monotonically_increasing_id()).withColumn("n", F.lit(1).cast("long")) for t, df in query.tables.items()}
    variables = query.variables
    if order == "random":
        variables = random.Random(seed).sample(variables, len(variables))
    elif order:
        variables = list(order)
    full = [*variables, *[f"row_{t}" for t in numbered]]
    safe = set(full) - query.joined
    phis = list(numbered.values())
    if variant == "generic":
        dealt = None
        if not order:
            private = {t: [v for v in s if v not in query.joined] for t, s in query.scopes.items()}
            fan = fans(query, list(numbered), {t: [v for v in s if v in query.joined] for t, s in query.scopes.items()})
            last = sorted(numbered, key=lambda t: fan[t])
            full = [*[v for v in variables if v in query.joined], *[v for t in last for v in (*private[t], f"row_{t}")]]
            if fan[last[-1]] >= FAN_OUT:
                dealt = f"row_{last[-1]}", [*[v for v in query.scopes[last[-1]] if v in query.joined], *query.output]
        out = potential_join(phis, full, "extend", safe, dealt=dealt)
    elif variant in ("leapfrog", "hash_trie"):
        shared = [v for v in variables if v in query.joined][:3]
        shares = {v: 2 if v in shared else 1 for v in variables}
        counted = [df.withColumn("n", F.lit(1).cast("long")) for df in query.tables.values()]
        out = potential_join(counted, variables, "hypercube", safe, shares, "sorted" if variant == "leapfrog" else "hash", rows=[f"row_{t}" for t in numbered])
    else:
        raise ValueError(f"no variant {variant}")
    return out.select(*query.output)


def wcoj_csv(query: JoinQuery, path: str, variant: str = "generic") -> DataFrame:
    """The same join without an engine's tables: inputs are parsed from CSV files, the result is a CSV file, read again."""
    spark, tables = next(iter(query.tables.values())).sparkSession, {}
    for t, df in query.tables.items():
        store.write_csv(df, f"{path}/in/{t}")
        tables[t] = store.csv(spark, f"{path}/in/{t}", df.schema)
    out = wcoj(JoinQuery(tables, query.output, query.order), variant)
    store.write_csv(out, f"{path}/out")
    return store.csv(spark, f"{path}/out", out.schema)


def heavy_light(query: JoinQuery) -> DataFrame:
    """Two join orders, by how often the first table holds a value of the pivot (the variable most tables share).

    Values of over sqrt(rows) rows (so at most sqrt(rows) values) are joined last: the other tables first, then each of
    their rows with at most that many heavy values. Light values are joined first: each row of the second table meets at
    most sqrt(rows) rows of the first. For a triangle both stay below rows^1.5; longer cycles get the same two orders
    without that bound.
    """
    pivot = max(sorted(query.joined), key=lambda v: sum(v in s for s in query.scopes.values()))
    with_pivot = [t for t, s in query.scopes.items() if pivot in s]
    others = [t for t in query.tables if t not in with_pivot]
    if not others:
        return binary(query)
    counts = query.tables[with_pivot[0]].groupBy(pivot).agg(F.count(F.lit(1)).alias("c"))
    bound = counts.agg(F.sqrt(F.coalesce(F.sum("c"), F.lit(0))).alias("bound"))
    heavy = counts.crossJoin(F.broadcast(bound)).filter(F.col("c") > F.col("bound")).select(pivot)
    parts = []
    for how, order in (("left_semi", others + with_pivot), ("left_anti", with_pivot + others)):
        tables = {t: df.join(heavy, pivot, how) if pivot in df.columns else df for t, df in query.tables.items()}
        parts.append(binary(JoinQuery(tables, query.output), order=connected(query, order)))
    return parts[0].unionByName(parts[1])


def connected(query: JoinQuery, order: list[str]) -> list[str]:
    """The order wished for, but each table that can be shares a variable with those before it."""
    left, out, seen = list(order), [], set()
    while left:
        t = next((x for x in left if seen & set(query.scopes[x])), left[0])
        left.remove(t)
        out.append(t)
        seen |= set(query.scopes[t])
    return out


def materialise_flat(query: JoinQuery, path: str, format: str = "parquet") -> None:
    """The flat result to files, as systems without summaries store it."""
    binary(query).write.mode("overwrite").format(format).save(path)


def reload_flat(spark: SparkSession, path: str, schema: str | None = None, format: str = "parquet") -> DataFrame:
    reader = spark.read.format(format)
    return (reader.schema(schema) if schema else reader).load(path)
