"""Run summaries: for each output column the runs of the sorted join result, made without the join."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.scratch import materialise
from .eliminate import Conditional, Generator
from .potentials import joined


#: Rows of a conditional up to which it goes to all tasks, so that prefixes stay where they are.
SENT = 1 << 20


@dataclass
class RunSummary:
    """Prefix frames, one a variable: v0..vi, freq (and what is needed to go on). Rows of frame i are the runs of
    column i, split at the runs of the columns before it."""

    variables: list[str]
    shown: list[str]
    frames: dict[str, DataFrame]
    starts: dict[str, DataFrame] = field(default_factory=dict)
    kept: bool = False  # whether the frames lie on shared files
    gen: Generator | None = None  # what starts are made from; without it, from the runs

    def runs(self, column: str) -> DataFrame:
        """Prefix runs of a column: its prefix and ``freq``."""
        at = self.variables.index(column)
        return self.frames[column].select(*self.variables[: at + 1], "freq")

    @property
    def deepest(self) -> DataFrame:
        return self.runs(self.variables[-1])

    def placed(self, column: str) -> DataFrame:
        """Runs with ``start``: rows of the sorted result before them. From the generator (see ``place``) no runs are
        sorted; else by a prefix sum over the runs in their order.

        Where a later column has been placed by such a sum before, a run starts where the first run below it does, and is
        as long as these are together: a sum over what is there, without another sort.
        """
        if column not in self.starts and self.gen:
            self.starts |= place(self.gen, column, self.starts)
        if column not in self.starts:
            at = self.variables.index(column)
            own = self.variables[: at + 1]
            deeper = next((self.starts[v] for v in self.variables[at + 1 :] if v in self.starts), None)
            if deeper is not None:
                # kept, so that the columns above this one go on from it and not from the deepest again
                self.starts[column] = materialise(deeper.groupBy(*own).agg(F.min("start").alias("start"), F.sum("freq").alias("freq")))
            else:
                self.starts[column] = prefix_sum(self.runs(column), own, "freq", "start").select(*own, "start", "freq")
        return self.starts[column]

    def column(self, name: str) -> DataFrame:
        """start, freq, value: the column alone, aligned by position."""
        return self.placed(name).select("start", "freq", F.col(name).alias("value"))


class Levels(dict):
    """Prefix frames by variable, grown as far as they are asked for; with ``cut`` each is kept on shared files."""

    def __init__(self, psis: list[Conditional], safe: set[str], cut: bool) -> None:
        super().__init__()
        self.psis, self.safe, self.cut = psis, safe, cut
        self.prefix: DataFrame | None = None
        self.open_ones: list[str] = []

    def __missing__(self, wanted: str) -> DataFrame:
        if all(psi.variable != wanted for psi in self.psis):
            raise KeyError(wanted)
        for psi in self.psis[len(self) :]:
            v = psi.variable
            if self.prefix is None:
                prefix = psi.frame
            else:
                bucketed = psi.frame.withColumnRenamed("bucket", "bucket__b")
                prefix = joined(self.prefix, bucketed, psi.given, self.safe).withColumn("bucket", F.col("bucket") * F.col("bucket__b")).drop("bucket__b")
            self.open_ones = [c for c in self.open_ones if c != v] + psi.children
            variables = [p.variable for p in self.psis[: len(self) + 1]]
            prefix = prefix.select(*variables, "bucket", *[f"m_{c}" for c in self.open_ones])
            self.prefix = materialise(prefix) if self.cut else prefix
            self[v] = self.prefix.withColumn("freq", _times(self.open_ones))
            if v == wanted:
                break
        return self[wanted]


def _times(open_ones: list[str]) -> Column:
    """Rows below a prefix: its bucket times the messages of the branches not expanded yet."""
    return reduce(lambda a, c: a * F.col(f"m_{c}"), open_ones, F.col("bucket"))


def generate(gen: Generator, cut: bool = False, sequence: list[str] | None = None) -> RunSummary:
    """Expand the generator a variable at a time from the root: one set-wise join a level.

    Each prefix row holds the product of the buckets of what it has expanded and, as columns, the messages of the
    branches it has not; the run length is the product of all these. With ``cut`` each level that is asked for is
    checkpointed, so that plans stay short and no level is computed twice. ``sequence``: another order of the variables,
    in which each still comes after all that it depends on.
    """
    psis = [gen.by(v) for v in sequence] if sequence else gen.conditionals
    variables = [psi.variable for psi in psis]
    return RunSummary(variables, [v for v in variables if v in gen.query.output], Levels(psis, gen.safe, cut), kept=cut, gen=None if sequence else gen)


def place(gen: Generator, column: str, done: dict[str, DataFrame]) -> dict[str, DataFrame]:
    """Runs and starts of the columns down to ``column`` that are not among ``done``.

    Below a prefix, the values of the next variable come in order, and each takes as many rows as its conditional says,
    times what the prefix has besides this branch. So a run starts at its prefix's start plus that many times the
    branch's rows before it: a prefix sum over each conditional, never over the (far more numerous) runs.

    Prefixes that would have to be shuffled to meet a conditional do not meet it one by one: the conditionals of a branch
    are placed by themselves first, and meet the prefixes above the branch at once (see ``_split``).
    """
    prefixes: list[Prefix] = []
    out, most = {}, 1
    for at, psi in enumerate(gen.conditionals):
        v = psi.variable
        _, rows, fan = _offsets(psi, gen.safe)
        first, sent = _split(gen, at) if psi.given and min(rows, most) > SENT else (at, "below" if rows <= SENT else None)
        if not prefixes:
            prefix = _branch(gen, at, at)
        else:
            above, branch = prefixes[first - 1], _branch(gen, first, at)
            # few given values may have most of the runs: what meets the sent side is dealt out, and stays where it is from here
            if sent == "above":
                branch = branch.dealt()
            elif sent and (first < at or most <= SENT < most * fan * 16):
                above = above.dealt()
            prefix = _below(above, gen.conditionals[first], branch, gen.safe, sent)
        most *= fan
        prefixes.append(prefix)
        if v not in done:
            out[v] = prefix.frame.select(*prefix.variables, "start", _times(prefix.open_ones).alias("freq"))
        if v == column:
            return out
    raise KeyError(column)


@dataclass
class Prefix:
    """Placed prefixes: their variables (and what the branch is given), start, bucket, and the messages of branches not expanded yet."""

    frame: DataFrame
    variables: list[str]
    open_ones: list[str]

    def dealt(self) -> Prefix:
        tasks = int(self.frame.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        return Prefix(self.frame.repartition(tasks, *self.variables), self.variables, self.open_ones)


def _below(above: Prefix, psi: Conditional, branch: Prefix, safe: set[str], sent: str | None) -> Prefix:
    """Prefixes and a branch that begins with the conditional ``psi``, placed by itself, as longer prefixes. ``sent``: which
    of both goes to all tasks, if any."""
    held = branch.frame.withColumnsRenamed({"start": "start__b", "bucket": "bucket__b"})
    frame = joined(F.broadcast(above.frame) if sent == "above" else above.frame, F.broadcast(held) if sent == "below" else held, psi.given, safe)
    before = _times([c for c in above.open_ones if c != psi.variable])
    frame = frame.withColumn("start", F.col("start") + before * F.col("start__b")).withColumn("bucket", F.col("bucket") * F.col("bucket__b"))
    open_ones = [c for c in above.open_ones if c != psi.variable] + branch.open_ones
    variables = [*above.variables, *[v for v in branch.variables if v not in above.variables]]
    return Prefix(frame.select(*variables, "start", "bucket", *[f"m_{c}" for c in open_ones]), variables, open_ones)


def _branch(gen: Generator, first: int, last: int) -> Prefix:
    """The conditionals from ``first`` to ``last``, all below the first one, placed under the values that it is given."""
    top = gen.conditionals[first]
    branch = Prefix(_offsets(top, gen.safe)[0].withColumnRenamed("within__", "start"), [*top.given, top.variable], top.children)
    for at in range(first + 1, last + 1):
        sent = "below" if _offsets(gen.conditionals[at], gen.safe)[1] <= SENT else None
        branch = _below(branch, gen.conditionals[at], _branch(gen, at, at), gen.safe, sent)
    return branch


def _split(gen: Generator, at: int) -> tuple[int, str | None]:
    """Where the branch begins that prefixes should meet at once, down to the conditional ``at``: of those that hold all
    conditionals from there on, the one with fewest rows above and in it. Also which of both can go to all tasks."""
    found = []
    for first in range(at, 0, -1):
        below = {gen.conditionals[first].variable}
        for psi in gen.conditionals[first : at + 1]:
            below |= set(psi.children) if psi.variable in below else set()
        if gen.conditionals[first].given and all(psi.variable in below for psi in gen.conditionals[first : at + 1]):
            found.append((run_count(gen, 0, first), run_count(gen, first, at + 1), first))
    above, under, first = min(found, key=lambda x: x[0] + x[1])
    return first, None if min(above, under) > SENT else "above" if above <= under else "below"


def _offsets(psi: Conditional, safe: set[str]) -> tuple[DataFrame, int, int]:
    """The conditional with ``within__``: rows of the values before, under the same given values. Made once, and kept.
    Also its rows, and the most that it has under one given value."""
    if psi.offsets is None:
        weighed = psi.frame.withColumn("weight__", reduce(lambda a, c: a * F.col(f"m_{c}"), psi.children, F.col("bucket")))
        try:
            summed = prefix_sum(weighed, [*psi.given, psi.variable], "weight__", "sum__")
        except OverflowError:
            if not psi.given:
                raise
            # values that no result holds may bring all groups together beyond 64 bits, where none of them is
            w = Window.partitionBy(*psi.given).orderBy(F.col(psi.variable).asc_nulls_first()).rowsBetween(Window.unboundedPreceding, -1)
            summed = weighed.withColumn("sum__", F.coalesce(F.sum("weight__").over(w), F.lit(0)))
        groups = summed.groupBy(*psi.given).agg(F.min("sum__").alias("first__"), F.count(F.lit(1)).alias("fan__"))
        rows, fan = groups.agg(F.coalesce(F.sum("fan__"), F.lit(0)), F.coalesce(F.max("fan__"), F.lit(0))).first()
        if psi.given:
            groups = groups.drop("fan__")
            summed = joined(summed, F.broadcast(groups) if rows <= SENT else groups, psi.given, safe)
        within = F.col("sum__") - (F.col("first__") if psi.given else F.lit(0))
        psi.offsets = summed.select(*psi.frame.columns, within.cast("long").alias("within__")), rows, fan
    return psi.offsets


def run_count(gen: Generator, first: int = 0, end: int | None = None) -> float:
    """Runs of the last column, by elimination alone: a branch's rows where each value is counted once. Or rows of the
    conditionals ``first`` to ``end`` (exclusive) alone, all but the first below it, under all that this one is given."""
    below: dict[str, DataFrame] = {}
    psis = gen.conditionals[first:end]
    for psi in psis[::-1]:
        frame = psi.frame.select(*psi.given, psi.variable, F.lit(1.0).alias("runs__"))
        for c in [c for c in psi.children if c in below]:
            own = below[c].withColumnRenamed("runs__", "runs__b")
            frame = joined(frame, own, gen.by(c).given, gen.safe).withColumn("runs__", F.col("runs__") * F.col("runs__b")).drop("runs__b")
        below[psi.variable] = frame.groupBy(*psi.given).agg(F.sum("runs__").alias("runs__"))
    return below[psis[0].variable].agg(F.sum("runs__")).first()[0] or 0.0


def skipped(gen: Generator) -> DataFrame:
    """Runs of the shown variables and ``freq``, in no order: hidden variables are passed through and not written.

    The conditionals that hold a hidden variable are joined, and rows that differ in it alone are added up, before the
    prefixes meet them: no prefix is multiplied by values that nobody sees. What is added up is kept on shared files.
    """
    factors = [([*psi.given, psi.variable], psi.frame.select(*psi.given, psi.variable, "bucket")) for psi in gen.conditionals]

    def times(a: tuple[list[str], DataFrame], b: tuple[list[str], DataFrame]) -> tuple[list[str], DataFrame]:
        both = joined(a[1], b[1].withColumnRenamed("bucket", "bucket__b"), [v for v in b[0] if v in a[0]], gen.safe)
        own = [*a[0], *[v for v in b[0] if v not in a[0]]]
        return own, both.select(*own, (F.col("bucket") * F.col("bucket__b")).alias("bucket"))

    for v in [psi.variable for psi in gen.conditionals[::-1] if psi.variable not in gen.query.output]:
        at = next(i for i, f in enumerate(factors) if v in f[0])
        own, held = reduce(times, [f for f in factors if v in f[0]])
        own = [x for x in own if x != v]
        summed = materialise(held.groupBy(*own).agg(F.sum("bucket").alias("bucket")))
        factors = [(own, summed) if i == at else f for i, f in enumerate(factors) if i == at or v not in f[0]]
    shown, runs = reduce(times, factors)
    return runs.filter(F.col("bucket") > 0).select(*shown, F.col("bucket").alias("freq"))


def composite(gen: Generator) -> list[tuple[list[str], DataFrame]]:
    """Levels with all variables of one depth: (new variables, prefix frame with freq), none left out.

    Below one parent key the values of a level's siblings multiply out: the product of their conditionals, which have
    the key in common and nothing else.
    """
    levels = gen.levels()
    summary = generate(gen, sequence=[v for level in levels for v in level])
    return [(level, summary.runs(level[-1])) for level in levels]


def from_rows(df: DataFrame, columns: list[str], runs: str = "prefix") -> dict[str, DataFrame]:
    """The definition itself: sort the flat rows and count equal neighbours, per column. For tests and comparison."""
    out = {}
    for i, c in enumerate(columns):
        prefix = df.groupBy(*columns[: i + 1]).agg(F.count(F.lit(1)).alias("freq"))
        placed = prefix_sum(prefix, columns[: i + 1], "freq", "start")
        column = placed.select("start", "freq", F.col(c).alias("value"))
        out[c] = merge_runs(column) if runs == "maximal" else column
    return out


def prefix_sum(df: DataFrame, order: list[str], value: str, name: str) -> DataFrame:
    """Exclusive running sum in a global order, without one task that sees all rows.

    Rows are range-partitioned, sorted and kept; the sums of the partitions (one number each) are added up on the driver,
    and each partition goes on from its offset, where it lies. A total beyond 64 bits raises.
    """
    keys = [F.col(c).asc_nulls_first() for c in order]
    ranged = materialise(df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("pid__", F.spark_partition_id()))
    sums = sorted((r[0], r[1]) for r in ranged.groupBy("pid__").agg(F.sum(F.col(value).cast("decimal(38,0)"))).collect())
    offset, before = {}, 0
    for pid, s in sums:
        offset[pid], before = before, before + int(s or 0)
    if before >= 1 << 63:
        raise OverflowError(f"{before} rows are beyond 64-bit positions")
    kept, at = df.columns, df.columns.index(value)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            if total is None and batch.num_rows:
                total = offset[batch.column(len(kept))[0].as_py()]
            values = batch.column(at).to_numpy(zero_copy_only=False).astype(np.int64)
            ends = (total or 0) + np.cumsum(values)
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(kept)], pa.array(ends - values, pa.int64())], [*kept, name])
            total = int(ends[-1]) if len(ends) else total

    schema = ranged.drop("pid__").withColumn(name, F.lit(0).cast("long")).schema
    return ranged.mapInArrow(run, schema)


def merge_runs(column: DataFrame) -> DataFrame:
    """Prefix runs (start, freq, value) to maximal ones: neighbours of equal value become one run."""
    ranged = materialise(column.repartitionByRange("start").withColumn("pid__", F.spark_partition_id()))
    w = Window.partitionBy("pid__").orderBy("start")
    edges = ranged.groupBy("pid__").agg(F.max_by(F.struct("value"), "start").alias("last"))
    ids = sorted(r[0] for r in edges.select("pid__").collect())
    follow = ranged.sparkSession.createDataFrame([(b, a) for a, b in zip(ids, ids[1:], strict=False)] or [(-1, -1)], "next__ int, pid__ int")
    carried = edges.join(F.broadcast(follow), "pid__").select(F.col("next__").alias("pid__"), F.col("last").alias("carried"))
    lagged = ranged.withColumn("prev", F.lag(F.struct("value")).over(w)).join(F.broadcast(carried), "pid__", "left")
    before = F.coalesce(F.col("prev"), F.col("carried"))
    fresh = lagged.withColumn("fresh", F.when(before.isNotNull() & before["value"].eqNullSafe(F.col("value")), 0).otherwise(1).cast("long"))
    numbered = prefix_sum(fresh.select("start", "freq", "value", "fresh"), ["start"], "fresh", "seen")
    island = F.col("seen") + F.col("fresh")
    return numbered.groupBy(island.alias("island")).agg(F.min("start").alias("start"), F.sum("freq").alias("freq"), F.min_by("value", "start").alias("value")).drop("island")


def aggregate(summary: RunSummary, by: list[str], **wanted: tuple[str, str]) -> DataFrame:
    """Weighted aggregates without expanding: name=(function, column) with count, sum, avg, min or max."""
    needed = [*by, *[c for _, c in wanted.values() if c != "*"]]
    last = max((summary.variables.index(c) for c in needed), default=0)
    frame = summary.runs(summary.variables[last])
    w = F.col("freq")
    made = {
        "count": lambda c: F.sum(w if c == "*" else F.when(F.col(c).isNotNull(), w).otherwise(0)),
        "sum": lambda c: F.sum(F.col(c) * w),
        "avg": lambda c: F.sum(F.col(c) * w) / F.sum(F.when(F.col(c).isNotNull(), w)),
        "min": lambda c: F.min(c),
        "max": lambda c: F.max(c),
    }
    return frame.groupBy(*by).agg(*[made[f](c).alias(name) for name, (f, c) in wanted.items()])
