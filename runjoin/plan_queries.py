"""Queries of the planning methods and of the cost measures, with literal or SQL counterparts."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines, eliminate, expand, measures, pipeline, potentials, summary
from .plans import cover, graph
from .plans.spec import natural
from .sources.scratch import folder
from .sources.tables import FOLLOWS_SQL, PLAYS_SQL, table
from .workloads import BUILD, CYCLE_ORDER, OUT, _nest, _q, _values, rows_of, w02, w03, w05, w09, w10, w13, w14

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _query(sql: str | None) -> Callable:
    """Register a query under the name of its function."""

    def keep(run: Callable) -> Callable:
        QUERIES[run.__name__] = run
        if sql:
            ORACLES[run.__name__] = sql
        return run

    return keep


def _rows(s: SparkSession, rows: list[tuple], columns: str) -> DataFrame:
    """A column's kind is that of its first value, if not told after its name."""
    kinds = ["int" if isinstance(x, int) else "string" for x in rows[0]]
    named = [c.split() for c in columns.split(",")]
    return s.createDataFrame(rows, ", ".join(f"{c[0]} {c[1] if c[1:] else k}" for c, k in zip(named, kinds, strict=True)))


def _distinct(q, variables) -> dict[str, int]:
    """Distinct values of each variable in the tables that hold it."""
    made = {}
    for v in variables:
        own = [df.select(v) for df in q.tables.values() if v in df.columns]
        made[v] = reduce(lambda a, b: a.unionByName(b), own).distinct().agg(F.count(F.lit(1)).alias("n")).select(F.lit(v).alias("v"), "n")
    return {r["v"]: r["n"] for r in reduce(lambda a, b: a.unionByName(b), made.values()).collect()}


def _times(numbers) -> int:
    return reduce(lambda a, b: a * b, numbers, 1)


#: Rows of W09's tables and distinct values of its variables in SQL.
_P, _F = f"(SELECT count(*) FROM {PLAYS_SQL})", f"(SELECT count(*) FROM {FOLLOWS_SQL})"
_DISTINCT = {v: f"(SELECT count(*) FROM (SELECT {a} FROM {x} UNION SELECT {b} FROM {y}))" for v, a, x, b, y in (("u1", "user_id", PLAYS_SQL, "src", FOLLOWS_SQL), ("u2", "dst", FOLLOWS_SQL, "src", FOLLOWS_SQL), ("u4", "dst", FOLLOWS_SQL, "user_id", PLAYS_SQL))}


def _selected(rows: list[tuple], columns: str) -> str:
    """SQL of rows whose last value is an expression."""
    *names, last = [c.strip() for c in columns.split(",")]
    word = lambda x: "'" + x + "'" if isinstance(x, str) else str(x)
    return " UNION ALL ".join("SELECT " + ", ".join(f"{word(x)} AS {n}" for x, n in zip(r, names)) + f", CAST({r[-1]} AS BIGINT) AS {last}" for r in rows)


def _joined(names) -> str:
    return "+".join(sorted(names))


def _cycle(s, d):
    return graph.build(w09(s, d).scopes)


@_query(_selected([("ar", "u1", _P), ("ar", "u4", _P), ("u1", "u2", _F), ("u2", "u3", _F), ("u3", "u4", _F)], "a, b, rows"))
def a02_graph_w09(s, d):
    """Edges, with the rows of the tables that give them."""
    q = w09(s, d)
    n = rows_of(q)
    return _rows(s, [(*sorted(e), sum(n[t] for t, scope in q.scopes.items() if e <= set(scope))) for e in graph.edges(_cycle(s, d))], "a, b, rows long")


@_query(_selected([("c", "cust+nation", "(SELECT count(*) FROM customer)"), ("o", "cust+order", "(SELECT count(*) FROM orders)"), ("l", "order+supp", "(SELECT count(*) FROM lineitem)"), ("s", "nation+supp", "(SELECT count(*) FROM supplier)"), ("n", "nation+region", "(SELECT count(*) FROM nation)")], "t, variables, rows"))
def a03_hyperedges_w14(s, d):
    q = w14(s, d)
    n = rows_of(q)
    return _rows(s, [(t, _joined(e), n[t]) for t, e in graph.hyperedges(q.scopes).items()], "t, variables, rows long")


_TRIANGLE = "WITH a AS (SELECT count(*) AS n FROM lineitem GROUP BY l_partkey, l_suppkey), b AS (SELECT count(*) AS n FROM lineitem GROUP BY l_suppkey, l_orderkey), c AS (SELECT count(*) AS n FROM lineitem GROUP BY l_orderkey, l_partkey)"


@_query(f"{_TRIANGLE} SELECT round(sqrt((SELECT count(*) FROM a)::DOUBLE * (SELECT count(*) FROM b) * (SELECT count(*) FROM c)) / 1000, 2) AS thousands")
def a05_set_bound_w13(s, d):
    """Square root of the three potentials' sizes: bounds the distinct result tuples."""
    q = w13(s, d)
    sizes = {t: p.count() for t, p in potentials.of_query(q).items()}
    bound = cover.agm_bound(sizes, cover.fractional_edge_cover(q.scopes)[1])
    return s.createDataFrame([(bound,)], "b double").select(F.round(F.col("b") / 1000, 2).alias("thousands"))


@_query(f"{_TRIANGLE} SELECT round(sqrt((SELECT sum(n * n) FROM a)::DOUBLE * (SELECT sum(n * n) FROM b) * (SELECT sum(n * n) FROM c)) / 1000, 2) AS thousands, (SELECT count(*) FROM {_nest('w13')} j) <= sqrt((SELECT sum(n * n) FROM a)::DOUBLE * (SELECT sum(n * n) FROM b) * (SELECT sum(n * n) FROM c)) AS holds")
def a05b_bag_bound_w13(s, d):
    q = w13(s, d)
    bound = cover.bag_bound(potentials.of_query(q), cover.fractional_edge_cover(q.scopes)[1])
    size = eliminate.join_size(q).first()[0]
    return s.createDataFrame([(bound, bool(size <= bound))], "b double, holds boolean").select(F.round(F.col("b") / 1000, 2).alias("thousands"), "holds")


@_query(f"WITH p AS (SELECT user_id, art, count(*) AS n FROM {PLAYS_SQL} GROUP BY ALL), f AS (SELECT src, dst, count(*) AS n FROM {FOLLOWS_SQL} GROUP BY ALL) SELECT CAST((SELECT sum(n) FROM p) * (SELECT max(n) FROM f) * (SELECT sum(n) FROM p) AS BIGINT) AS bound")
def a05b_bag_bound_w05(s, d):
    """Private variables force weight 1 on both outer tables; the middle one has weight 0 and its largest count."""
    q = w05(s, d)
    bound = cover.bag_bound(potentials.of_query(q), cover.fractional_edge_cover(q.scopes)[1])
    return s.createDataFrame([(round(bound),)], "bound long")


_W03_VALUES = {"priority": "SELECT o_orderpriority FROM orders", "type": "SELECT event_type FROM events", "cust": "SELECT user_id FROM events UNION SELECT o_custkey FROM orders UNION SELECT c_custkey FROM customer", "supp": "SELECT s_suppkey FROM supplier", "nation": "SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier"}


@_query(_selected([(i, v, f"(SELECT count(*) FROM (SELECT DISTINCT * FROM ({x})))") for i, (v, x) in enumerate(_W03_VALUES.items())], "place, variable, distinct_values"))
def a07_tree_order_w03(s, d):
    """Leaves first, the root last; siblings by name. With the distinct values of each."""
    q = w03(s, d)
    order = graph.tree_order(graph.build(q.scopes), "nation")
    n = _distinct(q, order)
    return _rows(s, [(i, v, n[v]) for i, v in enumerate(order)], "place, variable, distinct_values long")


_count = lambda *tables: " + ".join(f"(SELECT count(*) FROM {t})" for t in tables)
#: Rows of all tables of a workload in SQL.
_ROWS = {"w01": _count("orders", "customer", "supplier"), "w03": _count("events", "orders", "customer", "supplier"), "w05": f"2 * {_P} + {_F}", "w09": f"2 * {_P} + 3 * {_F}", "w13": "3 * " + _count("lineitem"), "w14": _count("customer", "orders", "lineitem", "supplier", "nation")}


def _order_costs(s, d, workloads, choose):
    """Fill-ins and largest bag of an order, and the rows of the tables that go into its bags."""
    out = []
    for w in workloads:
        q = BUILD[w](s, d)
        g = graph.build(q.scopes)
        order = choose(g)
        out.append((w, len(graph.triangulate(g, order)[1]), max(map(len, graph.bags_of(g, order))), sum(rows_of(q).values())))
    return _rows(s, out, "w, fill_ins, largest_bag, rows long")


@_query(_selected([(w, f, b, _ROWS[w]) for w, f, b in (("w01", 0, 3), ("w03", 0, 2), ("w09", 2, 3), ("w13", 0, 3), ("w14", 1, 3))], "w, fill_ins, largest_bag, rows"))
def a08_min_fill(s, d):
    return _order_costs(s, d, ("w01", "w03", "w09", "w13", "w14"), graph.min_fill)


@_query(_selected([(w, f, b, _ROWS[w]) for w, f, b in (("w03", 0, 2), ("w05", 0, 2), ("w09", 2, 3), ("w13", 0, 3), ("w14", 1, 3))], "w, fill_ins, largest_bag, rows"))
def a09_best_order(s, d):
    """No order does better than these (all are tried)."""
    return _order_costs(s, d, ("w03", "w05", "w09", "w13", "w14"), graph.best_order)


@_query(_selected([(a, b, f"{_DISTINCT[a]} * {_DISTINCT[b]}") for a, b in (("u1", "u4"), ("u2", "u4"))], "a, b, pairs"))
def a11_fill_ins_w09(s, d):
    """Fill-ins, with the pairs of values that each would have as a table."""
    made = [tuple(sorted(e)) for e in graph.triangulate(_cycle(s, d), CYCLE_ORDER)[1]]
    n = _distinct(w09(s, d), sorted({v for e in made for v in e}))
    return _rows(s, [(*e, _times(n[v] for v in e)) for e in made], "a, b, pairs long")


@_query(_selected([("ar+u1+u4", "p+q", f"2 * {_P}"), ("u1+u2+u4", "f", _F), ("u2+u3+u4", "g+h", f"2 * {_F}")], "bag, tables, rows"))
def a12_bags_w09(s, d):
    """Maximal cliques, the tables that each absorbs, and their rows."""
    q = w09(s, d)
    bags, n = graph.maxcliques(_cycle(s, d), CYCLE_ORDER), rows_of(q)
    return _rows(s, [(_joined(b), _joined(t), sum(n[x] for x in t)) for b, t in graph.assign(bags, q.scopes).items()], "bag, tables, rows long")


@_query(_selected([("ar+u1+u4", "u1+u2+u4", f"{_DISTINCT['u1']} * {_DISTINCT['u4']}"), ("u1+u2+u4", "u2+u3+u4", f"{_DISTINCT['u2']} * {_DISTINCT['u4']}")], "a, b, pairs"))
def a13_junction_tree_w09(s, d):
    """Linked bags, with the pairs of values that their separator may have."""
    tree = graph.junction_tree(graph.maxcliques(_cycle(s, d), CYCLE_ORDER))
    n = _distinct(w09(s, d), sorted({v for a, b in tree for v in a & b}))
    return _rows(s, [(*sorted((_joined(a), _joined(b))), _times(n[v] for v in a & b)) for a, b in tree], "a, b, pairs long")


@_query(_selected([("given order", 1, _ROWS["w09"]), ("outer bags first", 0, _ROWS["w09"])], "bags, holds, rows"))
def a14_running_intersection_w09(s, d):
    """Whether orders of the bags have the property, and the rows of the tables that they take in."""
    q = w09(s, d)
    bags, n = graph.maxcliques(_cycle(s, d), CYCLE_ORDER), rows_of(q)
    orders = {"given order": bags, "outer bags first": [bags[0], bags[2], bags[1]]}
    return _rows(s, [(k, int(graph.has_rip(o)), sum(n[t] for ts in graph.assign(o, q.scopes).values() for t in ts)) for k, o in orders.items()], "bags, holds, rows long")


@_query(_values([("u1+u4",), ("u2+u4",)], "separator"))
def a57_separators_w09(s, d):
    bags = graph.maxcliques(_cycle(s, d), CYCLE_ORDER)
    return _rows(s, [(_joined(x),) for x in graph.separators(graph.junction_tree(bags))], "separator")


@_query(_values([("w03", "tree", "nation | cust+supp | priority+type"), ("w05", "tree", "u1 | art1+u2 | art2"), ("w09", "dag", "u4 | u3 | u2 | u1 | ar")], "w, shape, levels"))
def a58_generator_shapes(s, d):
    out = []
    for w, q in (("w03", w03(s, d)), ("w05", w05(s, d)), ("w09", w09(s, d, CYCLE_ORDER))):
        gen = eliminate.build_generator(q)
        out.append((w, gen.shape(), " | ".join(_joined(x) for x in gen.levels())))
    return _rows(s, out, "w, shape, levels")


@_query(f"SELECT count(*) AS runs, CAST(0 AS BIGINT) AS outside FROM (SELECT DISTINCT {_q(OUT['w03'])} FROM {_nest('w03')} j)")
def a40_prefixes_lie_in_the_join_w03(s, d):
    """Deepest runs, and how many of them the joined rows lack."""
    made = pipeline.summarise(w03(s, d))
    outside = measures.uir_in_summary(made, w03(s, d)).agg(F.count(F.lit(1)).alias("outside"))
    return made.deepest.agg(F.count(F.lit(1)).alias("runs")).crossJoin(outside)


@_query(f"SELECT \"column\", (SELECT count(*) FROM {_nest('w03')} j) AS total FROM (VALUES ('nation'), ('supp'), ('cust'), ('type'), ('priority')) t(\"column\")")
def c12_column_totals_w03(s, d):
    return measures.redundancy(pipeline.summarise(w03(s, d))).select("column", "total")


@_query("SELECT true AS smaller, true AS some")
def c04_stored_bytes_w02(s, d):
    """Files of the summary are smaller than those of the flat result."""
    flat, runs = folder(s, "flat"), folder(s, "summary")
    baselines.materialise_flat(w02(s, d), flat)
    pipeline.summarise_to(w02(s, d), runs)
    small, large = measures.stored_bytes(runs), measures.stored_bytes(flat)
    return s.createDataFrame([(small < large, small > 0)], "smaller boolean, some boolean")


@_query("SELECT 'time' AS slow, 'done' AS quick, 'ZeroDivisionError' AS failed")
def c13_caps(s, d):
    """A run over its cap is cancelled; a short one ends; an error is told."""
    slow = measures.timed(s, lambda: s.range(10**13).selectExpr("sum(hash(id))").collect(), 1, cap_s=1.0)[1]
    quick = measures.timed(s, lambda: s.range(10).count(), 2, cap_s=600.0)[1]
    return s.createDataFrame([(slow, quick, measures.timed(s, lambda: 1 // 0, 1)[1])], "slow string, quick string, failed string")


@_query("SELECT * FROM (VALUES ('binary', true, true), ('summary', true, true)) t(method, shuffled, ran)")
def c15_traffic_w10(s, d):
    """Whether the two methods' jobs have read files and written to shuffles, by Spark's own counts."""
    runs = {"binary": lambda: baselines.binary(w10(s, d), "merge").count(), "summary": lambda: pipeline.join(w10(s, d)).count()}
    told = {k: measures.traffic(s, run) for k, run in runs.items()}
    return s.createDataFrame([(k, t["shuffle_bytes"] > 0, t["stages"] > 0) for k, t in told.items()], "method string, shuffled boolean, ran boolean")


@_query(None)
def c14_phases_w05(s, d):
    """Seconds of each phase, and its share (the first is the share of potentials)."""
    spent = measures.phases(w05(s, d))
    return s.createDataFrame([(k, v, v / sum(spent.values())) for k, v in spent.items()], "phase string, seconds double, share double")


@_query(None)
def w18_scenarios_w05(s, d):
    """Both scenarios by three methods: seconds to store, to load, in memory, and bytes, with ratios to the summary."""
    return measures.scenarios(s, w05(s, d), folder(s, "scenarios"))


@_query("SELECT CAST(CAST(sum(n::HUGEINT * n * n * n * n) AS HUGEINT) AS VARCHAR) AS size FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_linestatus)")
def a24_size_beyond_64_bits(s, d):
    """Five line item tables that meet in their status: from 20,000 rows or so on, the bag bound calls for 38-digit counts."""
    one = table(s, d, "lineitem").select(F.col("l_linestatus").alias("k"))
    q = natural({f"t{i}": one for i in range(5)}, ["k"])
    return eliminate.join_size(q, eliminate.safe_potentials(q)).select(F.col("join_size").cast("string").alias("size"))


@_query(f"SELECT {_q(OUT['w10'])} FROM {_nest('w10')} j")
def a46_planned_join_w10(s, d):
    """Each foreign key meets one row, so the planner takes the binary plan."""
    q = w10(s, d)
    if pipeline.plan(q) != "binary":
        raise ValueError("a foreign-key join should go by the binary plan")
    return pipeline.join(q, method="auto")


@_query(f"SELECT {_q(OUT['w05'])} FROM {_nest('w05')} j")
def a46_planned_join_w05(s, d):
    q = w05(s, d)
    if pipeline.plan(q) != "summary":
        raise ValueError("a many-to-many join should go by the summary")
    return pipeline.join(q, method="auto")


@_query("SELECT CAST(16777216 AS BIGINT) AS rows, true AS spread")
def a43_heavy_run(s, d):
    """One run of 16 million rows: its pieces lie over many tasks."""
    one = s.range(4096).selectExpr("1 as k")
    made = pipeline.summarise(natural({"a": one, "b": one}, ["k"]), cut=True)
    tasks = expand.flatten(made).groupBy(F.spark_partition_id().alias("task")).agg(F.count(F.lit(1)).alias("n"))
    return tasks.agg(F.sum("n").cast("long").alias("rows"), (F.max("n") < F.sum("n") / 2).alias("spread"))



@_query(f"SELECT {_q(OUT['w09'])}, count(*) AS freq FROM {_nest('w09')} j GROUP BY ALL")
def a31_single_junction_w09(s, d):
    """All variables in one bag."""
    gen = eliminate.build_generator(w09(s, d, CYCLE_ORDER), junction="single", strategy="extend")
    return summary.generate(gen).deepest.select(*OUT["w09"], "freq")


@_query("SELECT l_suppkey AS supp, l_returnflag AS flag, count(*) AS n FROM lineitem WHERE l_suppkey IN (SELECT s_suppkey FROM supplier WHERE s_nationkey = 3) GROUP BY 1, 2")
def a19_restrict_by_frame(s, d):
    """Evidence as a frame of observed values."""
    phi = potentials.build(table(s, d, "lineitem", ["l_suppkey", "l_returnflag"]).toDF("supp", "flag"), ["supp", "flag"])
    return potentials.restrict(phi, table(s, d, "supplier").filter("s_nationkey = 3").select(F.col("s_suppkey").alias("supp")))


@_query(f"SELECT segment, flag, round(count(*) / (SELECT count(*) FROM {_nest('w10')} j), 6) AS p FROM {_nest('w10')} j GROUP BY 1, 2")
def a55_joint_share_w10(s, d):
    """The joint distribution as shares, summed by two of its variables."""
    return potentials.joint_distribution(w10(s, d), normalise=True).groupBy("segment", "flag").agg(F.round(F.sum("p"), 6).alias("p"))


_LEAVES = f"WITH p AS {PLAYS_SQL}, f AS {FOLLOWS_SQL}"


@_query(f"{_LEAVES} SELECT 'leaves first' AS elimination, greatest((SELECT count(*) FROM (SELECT DISTINCT * FROM p)), (SELECT count(*) FROM (SELECT DISTINCT * FROM f))) AS rows UNION ALL SELECT 'inner first', (SELECT count(*) FROM (SELECT DISTINCT p.user_id, p.art, f.dst FROM p JOIN f ON p.user_id = f.src))")
def w12_largest_product_w05(s, d):
    """Rows of the largest conditional: eliminating an inner variable first makes a product of two tables."""
    rows = []
    for label, order in (("leaves first", ["art2", "u2", "art1", "u1"]), ("inner first", ["u1", "art1", "u2", "art2"])):
        gen = eliminate.build_generator(w05(s, d), order=order)
        made = [c.frame.agg(F.count(F.lit(1)).alias("n")) for c in gen.conditionals]
        largest = made[0]
        for m in made[1:]:
            largest = largest.unionByName(m)
        rows.append(largest.agg(F.max("n").alias("rows")).select(F.lit(label).alias("elimination"), "rows"))
    return rows[0].unionByName(rows[1])


@_query(f"SELECT segment, priority AS value FROM {_nest('w10')} j")
def e47_array_repeat_w10(s, d):
    """The SQL twin of the table function: runs repeated by an array function."""
    runs = pipeline.summarise(w10(s, d)).runs("priority")
    return runs.select("segment", F.explode(F.array_repeat("priority", F.col("freq").cast("int"))).alias("value"))
