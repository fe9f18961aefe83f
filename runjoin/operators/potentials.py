"""Potentials: exact frequency tables, unique on their variables, with a count ``n``."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.spec import JoinQuery

COUNT = "n"


def scope(phi: DataFrame) -> list[str]:
    return [c for c in phi.columns if c != COUNT]


def build(df: DataFrame, variables: list[str]) -> DataFrame:
    """Distinct tuples and how often each occurs: one scan, summed in each task before the shuffle."""
    return df.groupBy(*variables).agg(F.count(F.lit(1)).alias(COUNT))


def of_query(query: JoinQuery) -> dict[str, DataFrame]:
    """Potentials of all tables; aliases of one scan plan share it (the exchange is reused)."""
    return {name: build(df, list(query.scopes[name])) for name, df in query.tables.items()}


def joined(left: DataFrame, right: DataFrame, on: list[str], safe: set[str] = frozenset(), how: str = "inner") -> DataFrame:
    """Equi-join on variables; those in ``safe`` (never join variables) match nulls too."""
    if not on:
        return left.crossJoin(right) if how == "inner" else left
    if not safe & set(on):
        return left.join(right, on, how)
    keys = right.select(*[F.col(c).alias(f"{c}__r") if c in on else F.col(c) for c in right.columns])
    same = reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(f"{c}__r")) if c in safe else F.col(c) == F.col(f"{c}__r") for c in on])
    return left.join(keys, same, how).drop(*[f"{c}__r" for c in on])


def product(*phis: DataFrame, safe: set[str] = frozenset()) -> DataFrame:
    """Counts multiplied over matching variables; disjoint scopes multiply out."""

    def two(a: DataFrame, b: DataFrame) -> DataFrame:
        on = [c for c in scope(a) if c in scope(b)]
        both = joined(a, b.withColumnRenamed(COUNT, "n__b"), on, safe)
        return both.withColumn(COUNT, F.col(COUNT) * F.col("n__b")).drop("n__b")

    return reduce(two, phis)


def sum_out(phi: DataFrame, variable: str) -> DataFrame:
    """Counts summed over one variable."""
    return marginal(phi, [c for c in scope(phi) if c != variable])


def marginal(phi: DataFrame, variables: list[str]) -> DataFrame:
    """The narrower potential over ``variables``."""
    return phi.groupBy(*variables).agg(F.sum(COUNT).alias(COUNT))


def restrict(phi: DataFrame, seen: dict[str, object] | DataFrame) -> DataFrame:
    """Rows that agree with observed values, or with a frame of them."""
    if isinstance(seen, DataFrame):
        return phi.join(seen.distinct(), [c for c in seen.columns if c in phi.columns], "left_semi")
    return reduce(lambda df, kv: df.filter(F.col(kv[0]).eqNullSafe(F.lit(kv[1]))), seen.items(), phi)


def conditionalise(phi: DataFrame, on: list[str]) -> DataFrame:
    """Nested form: for each key the list of (other variables, n), in order."""
    rest = [c for c in phi.columns if c not in on]
    return phi.groupBy(*on).agg(F.sort_array(F.collect_list(F.struct(*rest))).alias("entries"))


def joint(conditional: DataFrame) -> DataFrame:
    """The flat form again."""
    return conditional.select(*[c for c in conditional.columns if c != "entries"], F.inline("entries"))


def probability(phi: DataFrame, on: list[str]) -> DataFrame:
    """Share of each tuple among those of its key."""
    return phi.withColumn("p", F.col(COUNT) / F.sum(COUNT).over(Window.partitionBy(*on))).drop(COUNT)


def add(*phis: DataFrame) -> DataFrame:
    """Potential of the tables one under the other."""
    return marginal(reduce(lambda a, b: a.unionByName(b), phis), scope(phis[0]))


def subtract(phi: DataFrame, gone: DataFrame) -> DataFrame:
    """Potential after rows have gone; tuples without rows leave it."""
    return add(phi, gone.withColumn(COUNT, -F.col(COUNT))).filter(F.col(COUNT) > 0)


def joint_distribution(query: JoinQuery, normalise: bool = False) -> DataFrame:
    """Every distinct result tuple over all variables with its frequency (or share)."""
    phis = of_query(query)
    left = dict(query.scopes)
    name = next(iter(left))
    out, seen = phis[name], set(left.pop(name))
    while left:
        name = next((t for t in left if seen & set(left[t])), next(iter(left)))
        out, seen = product(out, phis[name]), seen | set(left.pop(name))
    if normalise:
        total = out.agg(F.sum(COUNT).alias("total"))
        out = out.crossJoin(F.broadcast(total)).withColumn("p", F.col(COUNT) / F.col("total")).drop("total")
    return out


def wide(phis: dict[str, DataFrame]) -> dict[str, DataFrame]:
    """The same potentials with 38-digit counts, for results beyond 64 bits."""
    return {t: p.withColumn(COUNT, F.col(COUNT).cast("decimal(38,0)")) for t, p in phis.items()}


class Catalog:
    """Potentials built once and kept as Parquet, for queries to come, for narrower ones and for later sessions.

    A potential lies under its table's name and its variables; it is whole once its folder holds Spark's success mark.
    ``built`` names those that this catalog had to build. Tables that change need another name (or ``forget``).
    """

    def __init__(self, path: str) -> None:
        self.path, self.built = path.rstrip("/"), []

    def _where(self, name: str, variables: list[str]) -> str:
        return f"{self.path}/{name}/{'+'.join(sorted(variables))}"

    def stored(self, spark: SparkSession, name: str) -> list[list[str]]:
        """Variables of the table's potentials that lie here."""
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
        if not fs.exists(path):
            return []
        found = [s.getPath() for s in fs.listStatus(path)]
        return [p.getName().split("+") for p in found if fs.exists(spark._jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS"))]

    def get_or_build(self, name: str, df: DataFrame, variables: list[str]) -> DataFrame:
        """Read; or sum up a stored wider potential; or scan the table."""
        spark = df.sparkSession
        there = self.stored(spark, name)
        if not any(sorted(x) == sorted(variables) for x in there):
            wider = min((x for x in there if set(variables) <= set(x)), key=len, default=None)
            source = marginal(spark.read.parquet(self._where(name, wider)), list(variables)) if wider else build(df, list(variables))
            source.write.mode("overwrite").parquet(self._where(name, variables))
            self.built.append((name, tuple(variables), "wider" if wider else "scan"))
        return spark.read.parquet(self._where(name, variables)).select(*variables, COUNT)

    def of_query(self, query: JoinQuery, names: dict[str, str] | None = None) -> dict[str, DataFrame]:
        """Potentials of all tables of a query; aliases that ``names`` gives the same name (and that have the same variables) share one."""
        return {t: self.get_or_build((names or {}).get(t, t), df, list(query.scopes[t])) for t, df in query.tables.items()}

    def marginal(self, name: str, df: DataFrame, variables: list[str], subset: list[str]) -> DataFrame:
        return marginal(self.get_or_build(name, df, variables), subset)
