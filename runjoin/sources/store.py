"""Summaries and generators on disk: a dataset a column, and a manifest."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..operators.eliminate import Conditional, Generator
from ..operators.summary import RunSummary, merge_runs
from ..plans.spec import JoinQuery

_CSV = {"header": "true", "nullValue": "\\N", "emptyValue": "", "quote": '"', "escape": '"', "multiLine": "true", "ignoreLeadingWhiteSpace": "false", "ignoreTrailingWhiteSpace": "false"}


def _manifest(spark: SparkSession, path: str, content: dict) -> None:
    spark.createDataFrame([(json.dumps(content),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def _contents(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.text(f"{path}/manifest").first()[0])


def write(summary: RunSummary, path: str, format: str = "parquet", runs: str = "prefix") -> None:
    """One dataset a shown column: start, freq, value. The deepest runs are made and placed once, the other columns' from them."""
    schemas = {}
    summary.placed(summary.variables[-1])
    for name in summary.shown[::-1]:
        column = summary.column(name)
        column = merge_runs(column) if runs == "maximal" else column
        schemas[name] = column.schema.json()
        column.write.mode("overwrite").options(**(_CSV if format == "csv" else {})).format(format).save(f"{path}/col={name}")
    spark = summary.frames[summary.variables[0]].sparkSession
    first = read_column(spark, path, summary.shown[0], format, schemas[summary.shown[0]])
    total = first.agg(F.coalesce(F.sum("freq"), F.lit(0)).cast("long")).first()[0]
    _manifest(spark, path, {"columns": summary.shown, "format": format, "schemas": schemas, "rows": total})


def read_column(spark: SparkSession, path: str, name: str, format: str, schema: str) -> DataFrame:
    reader = spark.read.schema(StructType.fromJson(json.loads(schema))).options(**(_CSV if format == "csv" else {}))
    return reader.format(format).load(f"{path}/col={name}")


def read(spark: SparkSession, path: str) -> dict[str, DataFrame]:
    """Columns (start, freq, value) by name; expand them with ``expand.from_columns``."""
    m = _contents(spark, path)
    return {n: read_column(spark, path, n, m["format"], m["schemas"][n]) for n in m["columns"]}


def write_generator(gen: Generator, path: str) -> None:
    """The conditionals, shared by all prefixes: often far smaller than the summary."""
    for c in gen.conditionals:
        c.frame.write.mode("overwrite").parquet(f"{path}/psi={c.variable}")
    spark = gen.conditionals[0].frame.sparkSession
    _manifest(spark, path, {
        "order": gen.order, "output": gen.query.output, "safe": sorted(gen.safe),
        "psi": [{"variable": c.variable, "given": c.given, "children": c.children, "schema": c.frame.schema.json()} for c in gen.conditionals],
    })


def read_generator(spark: SparkSession, path: str) -> Generator:
    m = _contents(spark, path)
    psis = [
        Conditional(p["variable"], p["given"], spark.read.schema(StructType.fromJson(json.loads(p["schema"]))).parquet(f"{path}/psi={p['variable']}"), p["children"])
        for p in m["psi"]
    ]
    shape = JoinQuery({}, [])
    shape.output = m["output"]
    return Generator(shape, m["order"], psis, {}, set(m["safe"]))


def csv(spark: SparkSession, path: str, schema: str | StructType) -> DataFrame:
    return spark.read.schema(schema).options(**_CSV).csv(path)


def write_csv(df: DataFrame, path: str) -> None:
    df.select(*[F.col(c) for c in df.columns]).write.mode("overwrite").options(**_CSV).csv(path)
