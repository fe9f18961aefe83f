"""From runs back to rows: all of them, a range, or a sample."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from .summary import RunSummary, run_count, skipped

#: Rows that one piece of a run expands to at most, and pieces of a block.
PIECE, BLOCK = 1 << 16, 1 << 16
#: Rows of a joint piece at most: Spark holds copies of all rows of one while it hands them on.
STEP = 1 << 10
#: More partitions than there are.
FENCE = 1 << 30
#: Length of a run from which the pieces of a stored summary are dealt out evenly before they are repeated.
HEAVY = 1 << 22
#: Rows for one run from which the pieces of a lazy summary are dealt out: the shuffle has so many times fewer of them.
LONG = 64


def _numbers(n: Column) -> Column:
    """0 to n - 1, none if n is 0."""
    return F.explode(F.when(n > 0, F.sequence(F.lit(0).cast("long"), n - 1)))


def _repeated(runs: DataFrame, columns: list[str], spread: bool = False) -> DataFrame:
    """Runs cut into blocks and these into pieces, which are dealt out with ``spread``, and cut into steps; then each piece's rows.

    No array is longer than a block has pieces or a piece rows, however long the run.
    """
    size = PIECE * BLOCK
    blocks = runs.select(*columns, "freq", _numbers(F.ceil(F.col("freq") / size)).alias("block__"))
    sized = blocks.select(*columns, F.least(F.lit(size), F.col("freq") - F.col("block__") * size).alias("freq"))
    pieces = sized.select(*columns, "freq", _numbers(F.ceil(F.col("freq") / PIECE)).alias("piece__"))
    short = pieces.select(*columns, F.least(F.lit(PIECE), F.col("freq") - F.col("piece__") * PIECE).cast("int").alias("times__"))
    if spread:
        short = short.repartition(max(1, int(runs.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
        steps = short.select(*columns, "times__", F.explode(F.sequence(F.lit(0), F.col("times__") - 1, F.lit(STEP))).alias("step__"))
        short = steps.select(*columns, F.least(F.lit(STEP), F.col("times__") - F.col("step__")).alias("times__"))
        # tasks stay as they are, but generated code ends here: else it would hold the rows of a whole piece again
        short = short.coalesce(FENCE)
    return _copies(short, columns)


def _copies(pieces: DataFrame, columns: list[str]) -> DataFrame:
    return pieces.select(*columns, F.explode(F.sequence(F.lit(1), F.col("times__"))).alias("copy__")).drop("copy__")


def flatten(summary: RunSummary, spread: bool | None = None) -> DataFrame:
    """The join result. With ``spread`` pieces of runs are dealt out evenly over tasks (a shuffle of pieces, not of rows).

    Left open, a summary whose frames lie on shared files is spread if its longest run has over HEAVY rows. The runs of a
    lazy one are not looked at (that would compute them twice): its generator tells how many rows and runs there are. It
    is spread if it has over HEAVY rows, and LONG times as many as runs; few runs are made by few tasks. Of a lazy summary
    with variables that are not shown (``project='skip'``) runs are made without these, and counted.
    """
    merged = summary.gen is not None and not summary.kept and len(summary.shown) < len(summary.variables)
    runs = skipped(summary.gen) if merged else summary.deepest
    if spread is None and summary.kept:
        spread = (runs.agg(F.max("freq")).first()[0] or 0) > HEAVY
    elif spread is None and summary.gen:
        rows = summary.gen.root.agg(F.sum(F.col("n").cast("double"))).first()[0] or 0.0
        spread = rows > HEAVY and rows > LONG * (runs.count() if merged else run_count(summary.gen))
    return _repeated(runs, summary.shown, spread)


def slice_rows(summary: RunSummary, start: int, length: int) -> DataFrame:
    """Rows start .. start + length - 1 of the sorted result, from the runs that overlap them."""
    runs = summary.placed(summary.variables[-1])
    end = start + length
    cut = runs.filter((F.col("start") < end) & (F.col("start") + F.col("freq") > start))
    low, high = F.greatest(F.col("start"), F.lit(start)), F.least(F.col("start") + F.col("freq"), F.lit(end))
    return _repeated(cut.withColumn("freq", high - low), summary.shown)


def sample(summary: RunSummary, n: int, seed: int = 0, chunk: int = 1 << 20) -> DataFrame:
    """``n`` rows drawn with replacement: positions are hashed, and meet the runs of their chunk of positions."""
    runs = summary.placed(summary.variables[-1])
    total = runs.agg(F.coalesce(F.sum("freq"), F.lit(0))).first()[0]
    if not total:
        return runs.select(*summary.shown)
    spots = runs.sparkSession.range(n).select("id", F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(total)).alias("spot"))
    spots = spots.withColumn("chunk", F.floor(F.col("spot") / chunk))
    first = F.floor(F.col("start") / chunk)
    chunks = F.floor((F.col("start") + F.col("freq") - 1) / chunk) - first + 1
    blocks = runs.withColumn("block", _numbers(F.ceil(chunks / BLOCK)))
    within = blocks.withColumn("within", _numbers(F.least(F.lit(BLOCK), chunks - F.col("block") * BLOCK)))
    spread = within.withColumn("chunk", first + F.col("block") * BLOCK + F.col("within"))
    hit = spots.join(spread, "chunk").filter((F.col("spot") >= F.col("start")) & (F.col("spot") < F.col("start") + F.col("freq")))
    return hit.select(*summary.shown)


def from_columns(columns: dict[str, DataFrame], chunk: int = PIECE) -> DataFrame:
    """Rows from columns stored apart (start, freq, value): runs are cut at chunk borders, columns meet on the chunk, and
    where any of them begins a run they are cut into joint pieces, which are repeated without leaving the JVM.

    Chunks are dealt out to a set number of tasks: stored runs are few, and adaptive plans would give all to one task.
    """
    parts = []
    for i, df in enumerate(columns.values()):
        end = F.col("start") + F.col("freq")
        first = F.floor(F.col("start") / chunk)
        spanned = df.filter("freq > 0").select("start", end.alias("stop"), "value", first.alias("first"), (F.floor((end - 1) / chunk) - first + 1).alias("chunks"))
        blocks = spanned.withColumn("block", _numbers(F.ceil(F.col("chunks") / BLOCK)))
        within = _numbers(F.least(F.lit(BLOCK), F.col("chunks") - F.col("block") * BLOCK)).alias("within")
        cut = blocks.select("start", "stop", "value", "first", "block", within).withColumn("chunk", F.col("first") + F.col("block") * BLOCK + F.col("within"))
        low, high = F.greatest(F.col("start"), F.col("chunk") * chunk), F.least(F.col("stop"), (F.col("chunk") + 1) * chunk)
        piece = F.struct((low - F.col("chunk") * chunk).alias("at"), (high - low).alias("times"), F.col("value"))
        dealt = cut.repartition(max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))), "chunk")
        parts.append(dealt.groupBy("chunk").agg(F.sort_array(F.collect_list(piece)).alias(f"c{i}")))
    both = reduce(lambda a, b: a.join(b, "chunk"), parts).drop("chunk")
    names = list(columns)
    schema = StructType([*[StructField(n, df.schema["value"].dataType) for n, df in columns.items()], StructField("times__", IntegerType())])

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                runs = [column.slice(row, 1).flatten() for column in batch.columns]
                starts = [r.field("at").to_numpy(zero_copy_only=False) for r in runs]
                stop = int(starts[0][-1]) + runs[0].field("times")[-1].as_py()
                joint = np.unique(np.concatenate([*starts, np.arange(0, stop, STEP)]))
                times = np.diff(joint, append=stop).astype(np.int32)
                out = [r.field("value").take(pa.array(np.searchsorted(at, joint, "right") - 1)) for r, at in zip(runs, starts, strict=True)]
                yield pa.RecordBatch.from_arrays([*out, pa.array(times)], [*names, "times__"])

    return _copies(both.mapInArrow(pieces, schema), names)
