"""Costs of plans and summaries, as counted or timed."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import cover, graph
from ..plans.spec import JoinQuery
from . import baselines
from .eliminate import marginal
from .potentials import of_query
from .summary import RunSummary


def intermediates(query: JoinQuery, order: list[str] | None = None) -> DataFrame:
    """Rows of every step of a binary plan: step, rows."""
    made = [df.agg(F.count(F.lit(1)).alias("rows")).select(F.lit(i + 1).alias("step"), "rows") for i, df in enumerate(baselines.steps(query, order=order))]
    out = made[0]
    for m in made[1:]:
        out = out.unionByName(m)
    return out


def uir(query: JoinQuery, order: list[str] | None = None) -> DataFrame:
    """Intermediate tuples of each step that no result tuple extends: step, uir.

    A tuple is extended if what it shares with the tables to come is in their join. So the step is counted by the
    variables it shares with them, and each group of tables that hang together besides these says which values it has.
    """
    names = baselines._in_order(query, order)
    out = None
    for i in range(1, len(names) - 1):
        done, rest = names[: i + 1], names[i + 1 :]
        seen = {v for t in done for v in query.scopes[t]}
        shared = [v for v in query.variables if v in seen and any(v in query.scopes[t] for t in rest)]
        step = marginal(JoinQuery({t: query.tables[t] for t in done}, shared), shared)
        kept = step
        for group in _groups({t: set(query.scopes[t]) - seen for t in rest}):
            own = [v for v in shared if any(v in query.scopes[t] for t in group)]
            have = marginal(JoinQuery({t: query.tables[t] for t in group}, own), own).filter(F.col("n") > 0).select(*own)
            kept = kept.join(have, own, "left_semi") if own else kept.join(have, how="left_semi")
        sums = [df.agg(F.coalesce(F.sum("n"), F.lit(0)).alias(name)) for df, name in ((step, "made"), (kept, "used"))]
        row = sums[0].crossJoin(sums[1]).select(F.lit(i).alias("step"), (F.col("made") - F.col("used")).cast("long").alias("uir"))
        out = row if out is None else out.unionByName(row)
    return out


def _groups(scopes: dict[str, set[str]]) -> list[list[str]]:
    """Tables that are linked by variables."""
    out: list[tuple[list[str], set[str]]] = []
    for t, s in scopes.items():
        met = [g for g in out if g[1] & s]
        out = [g for g in out if g not in met] + [([*(x for g in met for x in g[0]), t], s.union(*(g[1] for g in met)))]
    return [g[0] for g in out]


def uir_in_summary(summary: RunSummary, query: JoinQuery) -> DataFrame:
    """Prefixes that the summary emits though the join lacks them: expected none."""
    runs = summary.deepest
    flat = baselines.steps(query)[-1].select(*summary.variables).distinct()
    marked = flat.select(*[F.col(c).alias(f"{c}__r") for c in flat.columns])
    return runs.join(marked, [F.col(c).eqNullSafe(F.col(f"{c}__r")) for c in flat.columns], "left_anti")


def redundancy(summary: RunSummary) -> DataFrame:
    """Per column: rows of the join, runs, and rows a run."""
    out = None
    for i, c in enumerate(summary.variables):
        row = summary.runs(c).agg(F.coalesce(F.sum("freq"), F.lit(0)).cast("long").alias("total"), F.count(F.lit(1)).alias("runs"))
        row = row.select(F.lit(i).alias("position"), F.lit(c).alias("column"), "total", "runs")
        out = row if out is None else out.unionByName(row)
    return out


def check(summary: RunSummary) -> bool:
    """Do the frequencies of all columns add up to one number, each at least 1?"""
    totals = {r["total"] for r in redundancy(summary).collect()}
    return len(totals) == 1 and all(not summary.runs(c).filter(F.col("freq") < 1).head(1) for c in summary.variables)


def plan_stats(query: JoinQuery) -> dict[str, object]:
    """Numbers of the plan: shape, cover, bounds, largest bag, fill-ins, largest table and potential."""
    phis = of_query(query)
    sizes = {t: p.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first() for t, p in phis.items()}
    rho, weights = cover.fractional_edge_cover(query.scopes)
    g = graph.build(query.scopes)
    order = graph.min_fill(g)
    return {
        "shape": graph.classify(query.scopes),
        "rho": rho,
        "largest_potential": max(s[0] for s in sizes.values()),
        "largest_table": max(s[1] for s in sizes.values()),
        "set_bound": cover.agm_bound({t: s[0] for t, s in sizes.items()}, cover.weighted_cover(query.scopes, {t: s[0] for t, s in sizes.items()})),
        "bag_bound": cover.bag_bound(phis, weights),
        "largest_bag": max(len(b) for b in graph.bags_of(g, order)),
        "fill_ins": len(graph.triangulate(g, order)[1]),
    }


def conditional_independence(query: JoinQuery, a: str, b: str, given: str) -> DataFrame:
    """Tuples for which n(a,b,given) * n(given) differs from n(a,given) * n(b,given), counted by elimination: no rows are joined.

    There are none where ``given`` separates the two in the query graph; elsewhere there may be.
    """
    q = JoinQuery(query.tables, [a, b, given])
    # as wide as 64-bit counts are long, so that the products fit 38 digits
    count = lambda *columns: marginal(q, list(columns)).withColumn("n", F.col("n").cast("decimal(19,0)"))
    abc, c = count(a, b, given), count(given).withColumnRenamed("n", "n_c")
    pairs = count(a, given).withColumnRenamed("n", "n_ac").join(count(b, given).withColumnRenamed("n", "n_bc"), given).join(c, given)
    met = pairs.join(abc, [a, b, given], "left")
    return met.filter(F.coalesce("n", F.lit(0)) * F.col("n_c") != F.col("n_ac") * F.col("n_bc"))


def timed(spark: SparkSession, run: Callable[[], object], repeats: int = 5, cap_s: float | None = None, cap_bytes: int | None = None, path: str | None = None) -> tuple[float, str]:
    """Mean seconds, and ``done``, ``time`` or ``bytes`` (its jobs were cancelled at the cap) or the name of its error.

    ``cap_bytes`` bounds the files under ``path`` while it runs.
    """
    spent = []
    for _ in range(repeats):
        tag, ended, why = f"timed-{uuid.uuid4().hex}", threading.Event(), []
        began = time.perf_counter()

        def watch(tag=tag, ended=ended, why=why, began=began) -> None:
            while not ended.wait(0.2):
                late = cap_s is not None and time.perf_counter() - began > cap_s
                large = cap_bytes is not None and path is not None and stored_bytes(path) > cap_bytes
                if late or large:
                    why.append("time" if late else "bytes")
                    spark.sparkContext.cancelJobsWithTag(tag)
                    if ended.wait(1):
                        return

        guard = threading.Thread(target=watch, daemon=True)
        spark.sparkContext.addJobTag(tag)
        guard.start()
        try:
            run()
        except Exception as failed:  # noqa: BLE001  a run that fails is a result here
            why.append(type(failed).__name__)
        finally:
            ended.set()
            guard.join()
            spark.sparkContext.removeJobTag(tag)
        spent.append(time.perf_counter() - began)
        if why:
            return spent[-1], why[0]
    return sum(spent) / len(spent), "done"


def traffic(spark: SparkSession, run: Callable[[], object]) -> dict[str, int]:
    """Stages, tasks, and bytes read from files, written to shuffles and spilled by the jobs of ``run``."""
    context, tag = spark.sparkContext, f"traffic-{uuid.uuid4().hex}"
    context.addJobTag(tag)
    try:
        run()
    finally:
        context.removeJobTag(tag)
    context._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    store, tracker = context._jsc.sc().statusStore(), context._jsc.sc().statusTracker()
    out = dict.fromkeys(("stages", "tasks", "input_bytes", "shuffle_bytes", "shuffle_rows", "spilled_bytes"), 0)
    for job in tracker.getJobIdsForTag(tag):
        for stage in tracker.getJobInfo(job).get().stageIds():
            try:
                s = store.lastStageAttempt(stage)
            except Exception:  # noqa: BLE001, S112  a stage that was skipped has no attempt
                continue
            for k, v in (("stages", int(s.numCompleteTasks() > 0)), ("tasks", s.numCompleteTasks()), ("input_bytes", s.inputBytes()), ("shuffle_bytes", s.shuffleWriteBytes()), ("shuffle_rows", s.shuffleWriteRecords()), ("spilled_bytes", s.diskBytesSpilled())):
                out[k] += v
    return out


def stored_bytes(path: str) -> int:
    """Bytes of the files under an address."""
    import pyarrow.fs as pafs

    fs, root = pafs.FileSystem.from_uri(path)
    return sum(f.size or 0 for f in fs.get_file_info(pafs.FileSelector(root, recursive=True, allow_not_found=True)) if f.is_file)


def phases(query: JoinQuery) -> dict[str, float]:
    """Seconds of scanning into potentials, inference, generation and expansion, each made to run to its end."""
    from .eliminate import build_generator
    from .expand import flatten
    from .summary import generate
    from ..sources.scratch import materialise

    out, began = {}, time.perf_counter()

    def mark(name: str) -> None:
        nonlocal began
        now = time.perf_counter()
        out[name], began = now - began, now

    phis = {t: materialise(p) for t, p in of_query(query).items()}
    mark("scan")
    gen = build_generator(query, phis=phis)
    for c in gen.conditionals:
        c.frame = materialise(c.frame)
    mark("inference")
    summary = generate(gen, cut=True)
    mark("generation")
    flatten(summary).write.mode("overwrite").format("noop").save()
    mark("expansion")
    return out


def phase_shares(query: JoinQuery) -> dict[str, float]:
    spent = phases(query)
    return {k: v / sum(spent.values()) for k, v in spent.items()}


def ratio(other: float, own: float) -> float:
    return other / own if own else float("inf")


def scenarios(spark: SparkSession, query: JoinQuery, path: str, repeats: int = 1, cap_s: float | None = None, methods: tuple[str, ...] = ("summary", "binary", "wcoj")) -> DataFrame:
    """Both scenarios by each method: method, phase (store, load, memory), seconds, ended, bytes, ratio.

    Reuse: compute and store, then load and (for the summary) expand. Forget: compute all rows in memory. Rows are made
    but go nowhere. ``bytes`` are those of the stored files; ``ratio`` is the method's seconds over the summary's.
    """
    from . import pipeline

    sink = lambda df: df.write.mode("overwrite").format("noop").save()
    flat = {"binary": lambda: baselines.binary(query), "wcoj": lambda: baselines.wcoj(query)}
    rows = []
    for m in methods:
        if m == "summary":
            store, load, memory = (lambda: pipeline.summarise_to(query, f"{path}/{m}")), (lambda: sink(pipeline.reload(spark, f"{path}/{m}"))), (lambda: sink(pipeline.join(query)))  # noqa: B023
        else:
            store, load, memory = (lambda: flat[m]().write.mode("overwrite").parquet(f"{path}/{m}")), (lambda: sink(spark.read.parquet(f"{path}/{m}"))), (lambda: sink(flat[m]()))  # noqa: B023
        for phase, run in (("store", store), ("load", load), ("memory", memory)):
            seconds, ended = timed(spark, run, repeats, cap_s)
            rows.append((m, phase, seconds, ended, stored_bytes(f"{path}/{m}")))
    own = {p: s for m, p, s, _, _ in rows if m == methods[0]}
    return spark.createDataFrame([(*r, ratio(r[2], own[r[1]])) for r in rows], "method string, phase string, seconds double, ended string, bytes long, ratio double")
