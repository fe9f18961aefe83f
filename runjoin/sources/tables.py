"""Input tables and the relations derived from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def plays(spark: SparkSession, sf_dir: str, user: str, art: str) -> DataFrame:
    """User and item of view events."""
    ev = table(spark, sf_dir, "events").filter("event_type = 'view'")
    return ev.select(F.col("user_id").alias(user), F.regexp_extract("props", "[0-9]+", 0).cast("long").alias(art))


def follows(spark: SparkSession, sf_dir: str, src: str, dst: str) -> DataFrame:
    """Users of neighbouring purchases."""
    ev = table(spark, sf_dir, "events").filter("event_type = 'purchase'").select("event_id", "user_id")
    a = ev.select((F.col("event_id") + 1).alias("event_id"), F.col("user_id").alias(src))
    return a.join(ev.withColumnRenamed("user_id", dst), "event_id").filter(F.col(src) != F.col(dst)).select(src, dst)


PLAYS_SQL = "(SELECT user_id, CAST(regexp_extract(props, '[0-9]+') AS BIGINT) AS art FROM events WHERE event_type = 'view')"
FOLLOWS_SQL = "(SELECT a.user_id AS src, b.user_id AS dst FROM events a JOIN events b ON b.event_id = a.event_id + 1 WHERE a.event_type = 'purchase' AND b.event_type = 'purchase' AND a.user_id <> b.user_id)"
