"""Run-length functions for SQL users."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


@udtf(returnType="value string")
class RleExpand:
    """Rows of parallel arrays: each value as often as its frequency."""

    def eval(self, values: list[str], freqs: list[int]):
        for v, f in zip(values or [], freqs or [], strict=True):
            for _ in range(f):
                yield (v,)


def rle_encode(df: DataFrame, group: str, order: str, value: str) -> DataFrame:
    """Runs of ``value`` in ``order`` inside each group: group, start, freq, value. Sorted and counted in the JVM, which
    spills; a group is never held whole."""
    w = Window.partitionBy(group).orderBy(order, value)
    before = F.lag(F.struct(value)).over(w)
    fresh = F.when(before.isNull() | ~before[value].eqNullSafe(F.col(value)), 1).otherwise(0)
    marked = df.select(group, F.col(value).alias("value__"), (F.row_number().over(w) - 1).cast("long").alias("at__"), fresh.alias("fresh__"))
    island = F.sum("fresh__").over(Window.partitionBy(group).orderBy("at__").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    runs = marked.withColumn("island__", island).groupBy(group, "island__")
    return runs.agg(F.min("at__").alias("start"), F.count(F.lit(1)).alias("freq"), F.first("value__").alias("value")).drop("island__")


def register(spark: SparkSession) -> None:
    """rle_expand (table function) and run_sum (SQL function)."""
    spark.udtf.register("rle_expand", RleExpand)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION run_sum(runs ARRAY<STRUCT<value: BIGINT, freq: BIGINT>>) RETURNS BIGINT RETURN aggregate(runs, 0L, (s, r) -> s + r.value * r.freq)")


def join_size_sql(spark: SparkSession, sql: str) -> DataFrame:
    """One row ``join_size`` of a conjunctive equi-join over the session's views, without joining rows."""
    from ..operators.eliminate import join_size
    from . import sqlfront

    names = {t.name for t in spark.catalog.listTables()}
    return join_size(sqlfront.parse(sql, {n: spark.table(n) for n in names}))
