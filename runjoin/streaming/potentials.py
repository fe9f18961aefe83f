"""Potentials of streams: counts kept up to date, in windows, and merged with stored ones."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.potentials import add
from ..sources.scratch import folder, remove


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files, its time with a zone, as watermarks need it."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def potential(stream: DataFrame, variables: list[str]) -> DataFrame:
    """Running counts (complete or update mode)."""
    return stream.groupBy(*variables).agg(F.count(F.lit(1)).alias("n"))


def windowed(stream: DataFrame, variables: list[str], width: str, slide: str | None = None, late: str = "1 hour", time: str = "ts") -> DataFrame:
    """Counts in tumbling or sliding windows; rows later than the watermark are dropped."""
    marked = stream.withWatermark(time, late)
    return marked.groupBy(F.window(time, width, slide), *variables).agg(F.count(F.lit(1)).alias("n"))


def sessions(stream: DataFrame, variables: list[str], gap: str, late: str = "1 hour", time: str = "ts") -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.session_window(time, gap), *variables).agg(F.count(F.lit(1)).alias("n"))


def distinct_events(stream: DataFrame, key: str, late: str = "1 hour", time: str = "ts") -> DataFrame:
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark([key])


def per_key_counts(stream: DataFrame, key: str) -> DataFrame:
    """Arbitrary state: rows seen so far of each key, told at every batch."""

    def step(k: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((seen,))
        yield pd.DataFrame({key: [k[0]], "n": [seen]})

    return stream.groupBy(key).applyInPandasWithState(step, f"{key} long, n long", "n long", "update", "NoTimeout")


def merged(stream: DataFrame, base: DataFrame, variables: list[str], path: str, compact_every: int = 16) -> str:
    """Add the counts of every micro-batch to a stored potential; returns where the sum lies at the end.

    Each batch writes its own counts only, under its number, so a batch that runs again replaces its own output. Every
    ``compact_every`` batches (and at the end) base and deltas become a new base, named by the batch, and the files it was
    made from go.
    """
    spark = stream.sparkSession
    state = {"base": f"{path}/base", "deltas": []}
    base.write.mode("overwrite").parquet(state["base"])

    def compact(name: str) -> None:
        if not state["deltas"]:
            return
        old = [state["base"], *state["deltas"]]
        add(*[spark.read.parquet(p) for p in old]).write.mode("overwrite").parquet(f"{path}/{name}")
        state["base"], state["deltas"] = f"{path}/{name}", []
        for p in old:
            remove(p)

    def fold(batch: DataFrame, number: int) -> None:
        batch.groupBy(*variables).agg(F.count(F.lit(1)).alias("n")).write.mode("overwrite").parquet(f"{path}/delta-{number}")
        state["deltas"].append(f"{path}/delta-{number}")
        if len(state["deltas"]) >= compact_every:
            compact(f"base-{number}")

    stream.writeStream.foreachBatch(fold).trigger(availableNow=True).option("checkpointLocation", f"{path}/progress").start().awaitTermination()
    compact("base-end")
    return state["base"]


def drained(stream: DataFrame, mode: str = "complete", keys: list[str] = (), path: str | None = None) -> DataFrame:
    """Run to the end of what is there; the result lies on shared files, none of it on the driver.

    ``complete``: each batch replaces the result. ``append``: batches lie one beside another. ``update``: of each of ``keys``
    the row of the last batch counts. A batch that runs again replaces its own files.
    """
    spark = stream.sparkSession
    path = path or folder(spark, "drained")
    schema = stream.schema

    def keep(batch: DataFrame, number: int) -> None:
        part = "all" if mode == "complete" else f"batch={number}"
        batch.write.mode("overwrite").parquet(f"{path}/rows/{part}")

    stream.writeStream.foreachBatch(keep).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/progress").start().awaitTermination()
    if mode == "complete":
        return spark.read.schema(schema).parquet(f"{path}/rows/all")
    rows = spark.read.schema(schema.add("batch", "long") if mode == "update" else schema).option("basePath", f"{path}/rows").parquet(f"{path}/rows")
    if mode == "append":
        return rows.select(*schema.names)
    names = [c for c in schema.names if c != "batch"]
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*names), "batch").alias("r"))
    return last.select("r.*")
