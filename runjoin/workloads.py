"""Experiment workloads on the given tables, and every query with its SQL counterpart."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import sqlfront, udfs
from .operators import baselines, eliminate, expand, measures, pipeline, potentials, summary
from .operators.bagjoin import potential_join
from .plans import cover, graph
from .plans.spec import JoinQuery, natural, restrict
from .sources import datasource, store
from .sources.scratch import folder as _folder
from .sources.tables import FOLLOWS_SQL, PLAYS_SQL, follows, plays, table
from .streaming import potentials as streams

Query = Callable[[SparkSession, str], DataFrame]


def _orders(s, d, cust="cust", **more):
    return table(s, d, "orders").select(F.col("o_custkey").alias(cust), *[F.col(v).alias(k) for k, v in more.items()])


def _customers(s, d, **more):
    return table(s, d, "customer").select(F.col("c_custkey").alias("cust"), *[F.col(v).alias(k) for k, v in more.items()])


def _suppliers(s, d):
    return table(s, d, "supplier").select(F.col("s_nationkey").alias("nation"), F.col("s_suppkey").alias("supp"))


def _items(s, d, **columns):
    return table(s, d, "lineitem").select(*[F.col(v).alias(k) for k, v in columns.items()])


def w01(s, d):
    return natural({"o": _orders(s, d, priority="o_orderpriority"), "c": _customers(s, d, nation="c_nationkey", segment="c_mktsegment"), "s": _suppliers(s, d)}, ["nation", "supp", "segment", "priority"])


def w02(s, d):
    return natural({"a": _items(s, d, part="l_partkey", flag1="l_returnflag"), "b": _items(s, d, part="l_partkey", flag2="l_returnflag")}, ["part", "flag1", "flag2"])


def w03(s, d):
    ev = table(s, d, "events").select(F.col("user_id").alias("cust"), F.col("event_type").alias("type"))
    return natural({"e": ev, "o": _orders(s, d, priority="o_orderpriority"), "c": _customers(s, d, nation="c_nationkey"), "s": _suppliers(s, d)}, ["nation", "supp", "cust", "type", "priority"])


def w04(s, d):
    return natural({
        "a": _items(s, d, part1="l_partkey", flag1="l_returnflag"), "b": _items(s, d, part1="l_partkey", supp="l_suppkey"),
        "c": _items(s, d, supp="l_suppkey", part2="l_partkey"), "d": _items(s, d, part2="l_partkey", flag4="l_returnflag"),
    }, ["supp", "flag1", "flag4"])


def w05(s, d, top=None, times=1):
    def again(df):
        out = df
        for _ in range(times - 1):
            out = out.unionAll(df)
        return out

    right = plays(s, d, "u2", "art2")
    right = right.filter(F.col("art2") < top) if top else right
    return natural({"p": again(plays(s, d, "u1", "art1")), "f": again(follows(s, d, "u1", "u2")), "q": again(right)}, ["u1", "art1", "u2", "art2"])


def w06(s, d):
    return w05(s, d, times=2)


def w07(s, d):
    return natural({"p": plays(s, d, "u1", "art1"), "f": follows(s, d, "u1", "u2"), "g": follows(s, d, "u2", "u3"), "q": plays(s, d, "u3", "art2")}, ["u1", "art1", "u2", "u3", "art2"])


def w08(s, d):
    return natural({"p": plays(s, d, "u1", "art1"), "f": follows(s, d, "u1", "u2"), "g": follows(s, d, "u2", "u3"), "h": follows(s, d, "u3", "u4"), "q": plays(s, d, "u4", "art2")}, ["u1", "art1", "u2", "u3", "u4", "art2"])


#: Elimination order that gives W09's columns in the order of its output.
CYCLE_ORDER = ["ar", "u1", "u2", "u3", "u4"]


def w09(s, d, order=None):
    return natural({"p": plays(s, d, "u1", "ar"), "f": follows(s, d, "u1", "u2"), "g": follows(s, d, "u2", "u3"), "h": follows(s, d, "u3", "u4"), "q": plays(s, d, "u4", "ar")}, ["u4", "u3", "u2", "u1", "ar"], order)


def w10(s, d):
    return natural({"l": _items(s, d, order="l_orderkey", flag="l_returnflag"), "o": _orders(s, d, order="o_orderkey", priority="o_orderpriority"), "c": _customers(s, d, segment="c_mktsegment")}, ["segment", "priority", "flag"])


def w10k(s, d):
    return natural({"l": _items(s, d, order="l_orderkey", line="l_linenumber", part="l_partkey"), "o": _orders(s, d, order="o_orderkey"), "c": _customers(s, d, segment="c_mktsegment")}, ["segment", "cust", "order", "line", "part"])


def w11(s, d):
    part = table(s, d, "part").select(F.col("p_partkey").alias("part"), F.col("p_brand").alias("brand"))
    nation = table(s, d, "nation").select(F.col("n_nationkey").alias("nation"), F.col("n_name").alias("nation_name"), F.col("n_regionkey").alias("region"))
    region = table(s, d, "region").select(F.col("r_regionkey").alias("region"), F.col("r_name").alias("region_name"))
    return natural({"l": _items(s, d, part="l_partkey", supp="l_suppkey", status="l_linestatus"), "p": part, "s": _suppliers(s, d), "n": nation, "r": region}, ["region_name", "nation_name", "brand", "status"])


def w13(s, d):
    return natural({"a": _items(s, d, part="l_partkey", supp="l_suppkey"), "b": _items(s, d, supp="l_suppkey", order="l_orderkey"), "c": _items(s, d, order="l_orderkey", part="l_partkey")}, ["supp", "part", "order"])


def w14(s, d):
    nation = table(s, d, "nation").select(F.col("n_nationkey").alias("nation"), F.col("n_regionkey").alias("region"))
    return natural({"c": _customers(s, d, nation="c_nationkey"), "o": _orders(s, d, order="o_orderkey"), "l": _items(s, d, order="l_orderkey", supp="l_suppkey"), "s": _suppliers(s, d), "n": nation}, ["region", "nation", "supp", "cust", "order"])


def w15(s, d=None):
    """Running example of three tables with 12 rows each."""
    rows = lambda x: [(a, b) for a, b, n in x for _ in range(n)]
    t1 = s.createDataFrame(rows([("a0", "b0", 3), ("a1", "b1", 2), ("a2", "b1", 1), ("a3", "b3", 2), ("a3", "b4", 4)]), "a string, b string")
    t2 = s.createDataFrame(rows([("b0", "c0", 2), ("b1", "c0", 3), ("b2", "c1", 3), ("b3", "c2", 1), ("b4", "c3", 2), ("b4", "c4", 1)]), "b string, c string")
    t3 = s.createDataFrame(rows([("c1", "d0", 4), ("c2", "d2", 4), ("c3", "d3", 2), ("c4", "d4", 2)]), "c string, d string")
    return natural({"t1": t1, "t2": t2, "t3": t3}, ["a", "b", "c", "d"])


def w15t(s, d):
    """The same chain over given tables."""
    buyers = table(s, d, "customer").select(F.col("c_nationkey").alias("c"), F.col("c_mktsegment").alias("d"))
    return natural({"t1": _items(s, d, a="l_returnflag", b="l_suppkey"), "t2": _suppliers(s, d).toDF("c", "b"), "t3": buyers}, ["a", "b", "c", "d"])


def rows_of(q: JoinQuery) -> dict[str, int]:
    """Rows of each table, in one pass."""
    return {r["t"]: r["n"] for r in _sizes(q).collect()}


_SOCIAL = f"WITH p AS {PLAYS_SQL}, f AS {FOLLOWS_SQL} "
_OSC = "FROM orders o JOIN customer c ON o_custkey = c_custkey JOIN supplier s ON c_nationkey = s_nationkey"
#: Join of each workload in SQL, all variables named.
JOINS = {
    "w01": f"SELECT c_nationkey AS nation, s_suppkey AS supp, c_mktsegment AS segment, o_orderpriority AS priority, o_custkey AS cust {_OSC}",
    "w02": "SELECT a.l_partkey AS part, a.l_returnflag AS flag1, b.l_returnflag AS flag2 FROM lineitem a JOIN lineitem b ON a.l_partkey = b.l_partkey",
    "w03": f"SELECT c_nationkey AS nation, s_suppkey AS supp, c_custkey AS cust, event_type AS type, o_orderpriority AS priority {_OSC} JOIN events e ON user_id = c_custkey",
    "w05": _SOCIAL + "SELECT p.user_id AS u1, p.art AS art1, q.user_id AS u2, q.art AS art2 FROM p JOIN f ON p.user_id = f.src JOIN p q ON q.user_id = f.dst",
    "w06": f"WITH p0 AS {PLAYS_SQL}, f0 AS {FOLLOWS_SQL}, p AS (SELECT * FROM p0 UNION ALL SELECT * FROM p0), f AS (SELECT * FROM f0 UNION ALL SELECT * FROM f0) SELECT p.user_id AS u1, p.art AS art1, q.user_id AS u2, q.art AS art2 FROM p JOIN f ON p.user_id = f.src JOIN p q ON q.user_id = f.dst",
    "w07": _SOCIAL + "SELECT p.user_id AS u1, p.art AS art1, f.dst AS u2, q.user_id AS u3, q.art AS art2 FROM p JOIN f ON p.user_id = f.src JOIN f g ON g.src = f.dst JOIN p q ON q.user_id = g.dst",
    "w08": _SOCIAL + "SELECT p.user_id AS u1, p.art AS art1, f.dst AS u2, g.dst AS u3, q.user_id AS u4, q.art AS art2 FROM p JOIN f ON p.user_id = f.src JOIN f g ON g.src = f.dst JOIN f h ON h.src = g.dst JOIN p q ON q.user_id = h.dst",
    "w09": _SOCIAL + "SELECT h.dst AS u4, g.dst AS u3, f.dst AS u2, p.user_id AS u1, p.art AS ar FROM p JOIN f ON p.user_id = f.src JOIN f g ON g.src = f.dst JOIN f h ON h.src = g.dst JOIN p q ON q.user_id = h.dst AND q.art = p.art",
    "w10": "SELECT c_mktsegment AS segment, o_orderpriority AS priority, l_returnflag AS flag, o_custkey AS cust FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey",
    "w10k": "SELECT c_mktsegment AS segment, c_custkey AS cust, l_orderkey AS \"order\", l_linenumber AS line, l_partkey AS part FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey",
    "w11": "SELECT r_name AS region_name, n_name AS nation_name, p_brand AS brand, l_linestatus AS status FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
    "w13": "SELECT a.l_suppkey AS supp, a.l_partkey AS part, b.l_orderkey AS \"order\" FROM lineitem a JOIN lineitem b ON a.l_suppkey = b.l_suppkey JOIN lineitem c ON c.l_orderkey = b.l_orderkey AND c.l_partkey = a.l_partkey",
    "w14": "SELECT n_regionkey AS region, n_nationkey AS nation, s_suppkey AS supp, c_custkey AS cust, o_orderkey AS \"order\" FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey JOIN nation ON n_nationkey = c_nationkey",
}
BUILD = {"w01": w01, "w02": w02, "w03": w03, "w04": w04, "w05": w05, "w06": w06, "w07": w07, "w08": w08, "w09": w09, "w10": w10, "w10k": w10k, "w11": w11, "w13": w13, "w14": w14}
OUT = {
    "w01": ["nation", "supp", "segment", "priority"], "w02": ["part", "flag1", "flag2"], "w03": ["nation", "supp", "cust", "type", "priority"],
    "w05": ["u1", "art1", "u2", "art2"], "w06": ["u1", "art1", "u2", "art2"], "w07": ["u1", "art1", "u2", "u3", "art2"], "w08": ["u1", "art1", "u2", "u3", "u4", "art2"],
    "w09": ["u4", "u3", "u2", "u1", "ar"], "w10": ["segment", "priority", "flag"], "w10k": ["segment", "cust", "order", "line", "part"],
    "w11": ["region_name", "nation_name", "brand", "status"], "w13": ["supp", "part", "order"], "w14": ["region", "nation", "supp", "cust", "order"],
}

QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, run: Query, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def _q(columns: list[str], alias: str = "") -> str:
    return ", ".join(f'{alias}"{c}"' for c in columns)


def _nest(w: str) -> str:
    return f"({JOINS[w]})"


def _wide(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("long") for c in columns})


# flat results, join sizes, runs of each column
for _w in OUT:
    if _w not in ("w02", "w06", "w08"):
        _add(f"a46_join_{_w}", lambda s, d, w=_w: pipeline.join(BUILD[w](s, d)), f"SELECT {_q(OUT[_w])} FROM {_nest(_w)} j")
    _add(f"a24_size_{_w}", lambda s, d, w=_w: _wide(eliminate.join_size(BUILD[w](s, d)), "join_size"), f"SELECT count(*) AS join_size FROM {_nest(_w)} j")
    _last = OUT[_w][-1]
    _add(f"a32_summary_{_w}_last", lambda s, d, w=_w: pipeline.summarise(BUILD[w](s, d)).deepest.select(*OUT[w], "freq"), f"SELECT {_q(OUT[_w])}, count(*) AS freq FROM {_nest(_w)} j GROUP BY {_q(OUT[_w])}")
for _w in ("w01", "w03", "w05", "w09", "w10"):
    for _i, _c in enumerate(OUT[_w]):
        _own = OUT[_w][: _i + 1]
        _add(
            f"a36_column_{_w}_{_c}", lambda s, d, w=_w, c=_c: pipeline.summarise(BUILD[w](s, d), cut=True, order=CYCLE_ORDER if w == "w09" else None).column(c),
            f"WITH r AS (SELECT {_q(_own)}, count(*) AS freq FROM {_nest(_w)} j GROUP BY {_q(_own)}) SELECT CAST(coalesce(sum(freq) OVER (ORDER BY {_q(_own)} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start, freq, \"{_c}\" AS value FROM r",
        )
_W04 = "WITH pf AS (SELECT l_partkey AS part, l_returnflag AS flag, count(*) AS n FROM lineitem GROUP BY 1, 2), ps AS (SELECT l_partkey AS part, l_suppkey AS supp, count(*) AS n FROM lineitem GROUP BY 1, 2), sf AS (SELECT supp, flag, sum(pf.n * ps.n) AS n FROM pf JOIN ps USING (part) GROUP BY 1, 2)"
_add("a48_early_projection_w04", lambda s, d: pipeline.summarise(w04(s, d)).deepest.select("supp", "flag1", "flag4", "freq"), f"{_W04} SELECT a.supp, a.flag AS flag1, b.flag AS flag4, CAST(a.n * b.n AS BIGINT) AS freq FROM sf a JOIN sf b USING (supp)")
_add("a24_size_w04", lambda s, d: _wide(eliminate.join_size(w04(s, d)), "join_size"), f"{_W04} SELECT CAST(sum(a.n * b.n) AS BIGINT) AS join_size FROM sf a JOIN sf b USING (supp)")
_add("a47_skip_projection_w01", lambda s, d: expand.flatten(pipeline.summarise(w01(s, d), project="skip")).select(*OUT["w01"]), f"SELECT {_q(OUT['w01'])} FROM {_nest('w01')} j")

# potentials
_add("a15_potential_plays", lambda s, d: potentials.build(plays(s, d, "u", "art"), ["u", "art"]), f"SELECT user_id AS u, art, count(*) AS n FROM {PLAYS_SQL} GROUP BY 1, 2")
_add("a15_potential_part_supp", lambda s, d: potentials.build(_items(s, d, part="l_partkey", supp="l_suppkey"), ["part", "supp"]), "SELECT l_partkey AS part, l_suppkey AS supp, count(*) AS n FROM lineitem GROUP BY 1, 2")
_PHI = "SELECT l_suppkey AS supp, l_returnflag AS flag, count(*) AS n FROM lineitem GROUP BY 1, 2"
_phi = lambda s, d: potentials.build(_items(s, d, supp="l_suppkey", flag="l_returnflag"), ["supp", "flag"])


def _a16(s, d):
    """The second catalog on a folder finds what the first has built, and sums a stored potential up for a narrower one."""
    path, items = _folder(s, "catalog"), _items(s, d, supp="l_suppkey", flag="l_returnflag")
    potentials.Catalog(path).get_or_build("lineitem", items, ["supp", "flag"])
    later = potentials.Catalog(path)
    found = later.get_or_build("lineitem", items, ["supp"])
    if later.built != [("lineitem", ("supp",), "wider")]:
        raise ValueError(f"the catalog scanned again: {later.built}")
    return found


def _warm(w):
    """Join size from potentials that another catalog has left on files."""

    def run(s, d):
        path, q = _folder(s, "catalog"), BUILD[w](s, d)
        potentials.Catalog(path).of_query(q)
        later = potentials.Catalog(path)
        phis = later.of_query(q)
        if later.built:
            raise ValueError(f"the catalog scanned again: {later.built}")
        return _wide(eliminate.join_size(q, phis=phis), "join_size")

    return run


def _warm_join(w):
    def run(s, d):
        q = BUILD[w](s, d)
        return pipeline.join(q, phis=potentials.Catalog(_folder(s, "catalog")).of_query(q))

    return run


_add("a16_catalog_marginal", _a16, "SELECT l_suppkey AS supp, count(*) AS n FROM lineitem GROUP BY 1")
_add("a17_conditional_round_trip", lambda s, d: potentials.joint(potentials.conditionalise(_phi(s, d), ["supp"])), _PHI)
_add("a18_probability", lambda s, d: potentials.probability(_phi(s, d), ["supp"]).withColumn("p", F.round("p", 6)), f"SELECT supp, flag, round(n / sum(n) OVER (PARTITION BY supp), 6) AS p FROM ({_PHI})")
_add("a19_restrict", lambda s, d: potentials.restrict(_phi(s, d), {"flag": "R"}), f"SELECT * FROM ({_PHI}) WHERE flag = 'R'")
_add("a20_product", lambda s, d: potentials.product(_phi(s, d), _suppliers(s, d).groupBy("supp", "nation").agg(F.count(F.lit(1)).alias("n"))), f"SELECT p.supp, p.flag, p.n, s_nationkey AS nation FROM ({_PHI}) p JOIN supplier ON s_suppkey = p.supp")
_add("a21_sum_out", lambda s, d: potentials.sum_out(_phi(s, d), "supp"), "SELECT l_returnflag AS flag, count(*) AS n FROM lineitem GROUP BY 1")
_add("a55_joint_w10", lambda s, d: potentials.joint_distribution(w10(s, d)).select("segment", "priority", "flag", "n").groupBy("segment", "priority", "flag").agg(F.sum("n").alias("n")), f"SELECT segment, priority, flag, count(*) AS n FROM {_nest('w10')} j GROUP BY 1, 2, 3")
_add("e34_add", lambda s, d: potentials.add(_phi(s, d), _phi(s, d)), f"SELECT supp, flag, 2 * n AS n FROM ({_PHI})")
_add("e34_subtract", lambda s, d: potentials.subtract(_phi(s, d), potentials.build(_items(s, d, supp="l_suppkey", flag="l_returnflag").filter("flag = 'R'"), ["supp", "flag"])), f"SELECT * FROM ({_PHI}) WHERE flag <> 'R'")

# elimination
_add("a23_marginal_w03_nation_type", lambda s, d: eliminate.marginal(w03(s, d), ["nation", "type"]), f"SELECT nation, type, count(*) AS n FROM {_nest('w03')} j GROUP BY 1, 2")
_add("a59_pair_marginal_w05", lambda s, d: eliminate.marginal(w05(s, d), ["art1", "art2"]), f"SELECT art1, art2, count(*) AS n FROM {_nest('w05')} j GROUP BY 1, 2")
_add("a60_column_marginal_w09", lambda s, d: eliminate.marginal(w09(s, d), ["ar"]), f"SELECT ar, count(*) AS n FROM {_nest('w09')} j GROUP BY 1")
_add("a25_conditional_w05_art2", lambda s, d: eliminate.build_generator(w05(s, d)).by("art2").table(), f"SELECT user_id AS u2, art AS art2, count(*) AS bucket, CAST(1 AS BIGINT) AS fac FROM {PLAYS_SQL} GROUP BY 1, 2")
_add("a25_conditional_w05_u2", lambda s, d: eliminate.build_generator(w05(s, d)).by("u2").table(), f"SELECT src AS u1, dst AS u2, count(*) AS bucket, any_value(k) AS fac FROM {FOLLOWS_SQL} f JOIN (SELECT user_id, count(*) AS k FROM {PLAYS_SQL} GROUP BY 1) ON user_id = dst GROUP BY 1, 2")
_add("a27_root_w05", lambda s, d: eliminate.build_generator(w05(s, d)).root, f"SELECT u1, count(*) AS n FROM {_nest('w05')} j GROUP BY 1")
_add("a28_message_w09_u1", lambda s, d: eliminate.build_generator(w09(s, d, CYCLE_ORDER)).messages["ar"].select("u1", "u4", "n"), f"WITH p AS {PLAYS_SQL} SELECT a.user_id AS u1, b.user_id AS u4, count(*) AS n FROM p a JOIN p b ON a.art = b.art GROUP BY 1, 2")
_add("a39_other_root_w05", lambda s, d: pipeline.join(w05(s, d), root="art2").select(*OUT["w05"]), f"SELECT {_q(OUT['w05'])} FROM {_nest('w05')} j")
_add("a10_bad_order_w05", lambda s, d: expand.flatten(summary.generate(eliminate.build_generator(w05(s, d), order=["u1", "art1", "u2", "art2"]))).select(*OUT["w05"]), f"SELECT {_q(OUT['w05'])} FROM {_nest('w05')} j")
_add("a50_estimate_from_catalog", _warm("w10"), f"SELECT count(*) AS join_size FROM {_nest('w10')} j")
for _w in ("w01", "w10"):
    _add(f"w19_stored_potentials_{_w}", _warm_join(_w), f"SELECT {_q(OUT[_w])} FROM {_nest(_w)} j")
_add("e15_reduced_w03", lambda s, d: _sizes(eliminate.reduce(w03(s, d))), "WITH c AS (SELECT * FROM customer WHERE c_custkey IN (SELECT user_id FROM events) AND c_custkey IN (SELECT o_custkey FROM orders) AND c_nationkey IN (SELECT s_nationkey FROM supplier)) SELECT 'e' AS t, count(*) AS n FROM events WHERE user_id IN (SELECT c_custkey FROM c) UNION ALL SELECT 'o', count(*) FROM orders WHERE o_custkey IN (SELECT c_custkey FROM c) UNION ALL SELECT 'c', count(*) FROM c UNION ALL SELECT 's', count(*) FROM supplier WHERE s_nationkey IN (SELECT c_nationkey FROM c)")
_INDEPENDENT = "WITH j AS ({join}), p AS (SELECT ac.a, bc.b, ac.g, ac.n AS n_ac, bc.n AS n_bc, c.n AS n_c FROM (SELECT type AS a, {g} AS g, count(*) AS n FROM j GROUP BY ALL) ac JOIN (SELECT priority AS b, {g} AS g, count(*) AS n FROM j GROUP BY ALL) bc USING (g) JOIN (SELECT {g} AS g, count(*) AS n FROM j GROUP BY ALL) c USING (g)) SELECT count(*) AS violations FROM p LEFT JOIN (SELECT type AS a, priority AS b, {g} AS g, count(*) AS n FROM j GROUP BY ALL) t USING (a, b, g) WHERE coalesce(t.n, 0) * n_c <> n_ac * n_bc"
for _g in ("cust", "nation"):  # the customer separates events from orders, the nation doesn't
    _add(f"a56_independence_given_{_g}", lambda s, d, g=_g: measures.conditional_independence(w03(s, d), "type", "priority", g).agg(F.count(F.lit(1)).alias("violations")), _INDEPENDENT.format(join=JOINS["w03"], g=_g))


def _sizes(q: JoinQuery) -> DataFrame:
    out = None
    for t, df in q.tables.items():
        row = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("t"), "n")
        out = row if out is None else out.unionByName(row)
    return out


# bag joins
_BAG = f"SELECT supp, part, \"order\", count(*) AS n FROM {_nest('w13')} j GROUP BY 1, 2, 3"
for _strategy in ("extend", "pairwise", "hypercube"):
    _add(f"a29_{_strategy}_w13", lambda s, d, k=_strategy: potential_join(list(potentials.of_query(w13(s, d)).values()), ["supp", "part", "order"], k).select("supp", "part", "order", "n"), _BAG)
_add("a31_single_bag_w09", lambda s, d: potential_join(list(potentials.of_query(w09(s, d)).values()), OUT["w09"], "extend").select(*OUT["w09"], "n"), f"SELECT {_q(OUT['w09'])}, count(*) AS n FROM {_nest('w09')} j GROUP BY ALL")
_add("e49_trie_cells_w13", lambda s, d: potential_join(list(potentials.of_query(w13(s, d)).values()), ["supp", "part", "order"], "hypercube", trie="sorted", shares={"supp": 2, "part": 4, "order": 1}), _BAG)

# summaries
_LEVELS = [["nation"], ["cust", "supp"], ["type", "priority"]]


def _level(k):
    """Level k of W03 with the customer above the event types: one composite run a tuple of the level and all before it."""

    def run(s, d):
        q = natural(w03(s, d).tables, ["nation", "cust", "type", "supp", "priority"])
        levels = summary.composite(eliminate.build_generator(q))
        if [set(names) for names, _ in levels] != [set(x) for x in _LEVELS]:
            raise ValueError(f"levels are {[names for names, _ in levels]}")
        return levels[k][1]

    return run


for _k in range(3):
    _own = [v for level in _LEVELS[: _k + 1] for v in level]
    _add(f"a35_composite_w03_level{_k}", _level(_k), f"SELECT {_q(_own)}, count(*) AS freq FROM {_nest('w03')} j GROUP BY ALL")
_MAX = "WITH j AS ({join}), o AS (SELECT \"{c}\" AS value, row_number() OVER (ORDER BY {own}) AS rn, lag(\"{c}\") OVER (ORDER BY {own}) AS p FROM j), g AS (SELECT value, rn, sum(CASE WHEN p IS NULL OR p <> value THEN 1 ELSE 0 END) OVER (ORDER BY rn) AS island FROM o) SELECT min(rn) - 1 AS start, count(*) AS freq, any_value(value) AS value FROM g GROUP BY island"
_add("a38_maximal_runs_w05_u2", lambda s, d: summary.merge_runs(pipeline.summarise(w05(s, d)).column("u2")), _MAX.format(join=JOINS["w05"], c="u2", own="u1, art1, u2"))
_add("a37_from_rows_w05_u2", lambda s, d: summary.from_rows(baselines.binary(w05(s, d)), ["u1", "art1", "u2"], "maximal")["u2"], _MAX.format(join=JOINS["w05"], c="u2", own="u1, art1, u2"))
_add("a53_aggregates_w01", lambda s, d: _wide(summary.aggregate(pipeline.summarise(w01(s, d)), ["nation", "segment"], rows=("count", "*"), total=("sum", "supp"), least=("min", "supp"), most=("max", "supp")), "rows", "total"), f"SELECT nation, segment, count(*) AS rows, CAST(sum(supp) AS BIGINT) AS total, min(supp) AS least, max(supp) AS most FROM {_nest('w01')} j GROUP BY 1, 2")
_add("a54_slice_w01", lambda s, d: expand.slice_rows(pipeline.summarise(w01(s, d)), 1000, 100), f"SELECT {_q(OUT['w01'])} FROM (SELECT *, row_number() OVER (ORDER BY {_q(OUT['w01'])}) AS rn FROM {_nest('w01')} j) WHERE rn > 1000 AND rn <= 1100")


def _sampled(s, d):
    """Rows drawn, and how many of them are rows of the join."""
    drawn = expand.sample(pipeline.summarise(w01(s, d)), 500, 3).withColumn("draw", F.monotonically_increasing_id())
    q = w01(s, d)  # a row is in the join if its customers' part is, and its supplier's; neither needs the joined rows
    buyers = q.tables["o"].distinct().join(q.tables["c"], "cust").select("priority", "nation", "segment").distinct()
    real = drawn.join(buyers, ["priority", "nation", "segment"], "left_semi").join(q.tables["s"], ["nation", "supp"], "left_semi")
    return real.agg(F.count(F.lit(1)).alias("members")).crossJoin(drawn.agg(F.count(F.lit(1)).alias("drawn")))


_add("a54_sample_w01", _sampled, "SELECT CAST(500 AS BIGINT) AS members, CAST(500 AS BIGINT) AS drawn")
_add("a52_cross_product", lambda s, d: pipeline.join(natural({"r": table(s, d, "region", ["r_name"]), "n": table(s, d, "nation", ["n_name", "n_regionkey"])}, ["r_name", "n_name", "n_regionkey"])), "SELECT r_name, n_name, n_regionkey FROM region, nation")
_add("e32_top_suppliers_w04", lambda s, d: eliminate.build_generator(w04(s, d), root="supp").root.orderBy(F.desc("n"), "supp").limit(5), f"{_W04} SELECT a.supp, CAST(sum(a.n * b.n) AS BIGINT) AS n FROM sf a JOIN sf b USING (supp) GROUP BY 1 ORDER BY n DESC, supp LIMIT 5")
_add("a15_worked_example_w15", lambda s, d: pipeline.summarise(w15t(s, d)).deepest.select("a", "b", "c", "d", "freq"), "SELECT a, b, c, d, x.n * y.n AS freq FROM (SELECT l_returnflag AS a, l_suppkey AS b, s_nationkey AS c, count(*) AS n FROM lineitem JOIN supplier ON s_suppkey = l_suppkey GROUP BY ALL) x JOIN (SELECT c_nationkey AS c, c_mktsegment AS d, count(*) AS n FROM customer GROUP BY ALL) y USING (c)")


# storage
def _stored(fmt: str, w=w01):
    def run(s, d):
        path = _folder(s, "summary")
        pipeline.summarise_to(w(s, d), path, fmt)
        return pipeline.reload(s, path)

    return run


def _stored_generator(s, d):
    path = _folder(s, "generator")
    store.write_generator(eliminate.build_generator(w05(s, d)), path)
    return expand.flatten(summary.generate(store.read_generator(s, path))).select(*OUT["w05"])


def _as_source(s, d):
    path = _folder(s, "summary")
    pipeline.summarise_to(w01(s, d), path)
    datasource.register(s)
    return s.read.format("runsummary").load(path)


def _flat_files(s, d):
    path = _folder(s, "flat")
    baselines.materialise_flat(w05(s, d), path)
    return baselines.reload_flat(s, path)


_add("a45_store_reload_w01", _stored("parquet"), f"SELECT {_q(OUT['w01'])} FROM {_nest('w01')} j")
_add("a41_csv_round_trip_w10", _stored("csv", w10), f"SELECT {_q(OUT['w10'])} FROM {_nest('w10')} j")
_add("a61_stored_generator_w05", _stored_generator, f"SELECT {_q(OUT['w05'])} FROM {_nest('w05')} j")
_add("e05_summary_source_w01", _as_source, f"SELECT {_q(OUT['w01'])} FROM {_nest('w01')} j")
_add("b10_flat_files_w05", _flat_files, f"SELECT {_q(OUT['w05'])} FROM {_nest('w05')} j")

# baselines
for _w, _algos in {"w10": ("shuffle_hash", "merge", "broadcast", "auto"), "w01": ("shuffle_hash", "merge", "auto"), "w03": ("auto",), "w05": ("shuffle_hash", "merge", "auto"), "w07": ("auto",), "w09": ("merge", "auto"), "w11": ("auto",)}.items():
    for _b in _algos:
        _add(f"b_binary_{_b}_{_w}", lambda s, d, w=_w, b=_b: baselines.binary(BUILD[w](s, d), b), f"SELECT {_q(OUT[_w])} FROM {_nest(_w)} j")
for _w in ("w05", "w10"):
    _add(f"b05_bucketed_{_w}", lambda s, d, w=_w: baselines.bucketed(BUILD[w](s, d), _folder(s, "bucketed")), f"SELECT {_q(OUT[_w])} FROM {_nest(_w)} j")
_add("b09_wcoj_csv_w09", lambda s, d: baselines.wcoj_csv(w09(s, d), _folder(s, "csv")), f"SELECT {_q(OUT['w09'])} FROM {_nest('w09')} j")
_add("b03_nested_loop_w14n", lambda s, d: baselines.binary(natural({"r": table(s, d, "region").select(F.col("r_regionkey").alias("k"), "r_name"), "n": table(s, d, "nation").select(F.col("n_regionkey").alias("k"), "n_name")}, ["r_name", "n_name"]), "nested_loop"), "SELECT r_name, n_name FROM region JOIN nation ON r_regionkey = n_regionkey")
for _w, _variants in {"w09": ("generic", "leapfrog", "hash_trie", "heavy_light"), "w13": ("generic", "leapfrog", "hash_trie", "heavy_light"), "w05": ("generic", "leapfrog"), "w01": ("generic",)}.items():
    for _b in _variants:
        _add(f"b07_wcoj_{_b}_{_w}", lambda s, d, w=_w, b=_b: baselines.wcoj(BUILD[w](s, d), b), f"SELECT {_q(OUT[_w])} FROM {_nest(_w)} j")
_add("b08_wcoj_random_order_w05", lambda s, d: baselines.wcoj(w05(s, d), "generic", "random", 3), f"SELECT {_q(OUT['w05'])} FROM {_nest('w05')} j")

# measures
_add("c08_uir_w03", lambda s, d: measures.uir(w03(s, d), ["o", "c", "s", "e"]), f"SELECT 1 AS step, (SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey WHERE NOT (c_custkey IN (SELECT user_id FROM events) AND c_nationkey IN (SELECT s_nationkey FROM supplier))) AS uir UNION ALL SELECT 2, (SELECT count(*) {_OSC} WHERE c_custkey NOT IN (SELECT user_id FROM events))")
_add("c09_intermediates_w01", lambda s, d: measures.intermediates(w01(s, d), ["o", "c", "s"]), f"SELECT 1 AS step, (SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey) AS rows UNION ALL SELECT 2, (SELECT count(*) {_OSC})")
_add("c10_redundancy_w01", lambda s, d: measures.redundancy(pipeline.summarise(w01(s, d))), " UNION ALL ".join(f"SELECT {i} AS position, '{c}' AS \"column\", (SELECT count(*) FROM {_nest('w01')} j) AS total, (SELECT count(*) FROM (SELECT DISTINCT {_q(OUT['w01'][: i + 1])} FROM {_nest('w01')} j)) AS runs" for i, c in enumerate(OUT["w01"])))
for _k in (100, 30, 10, 3):
    _add(f"w16_uir_dial_{_k}", lambda s, d, k=_k: _wide(eliminate.join_size(w05(s, d, top=k)), "join_size"), f"SELECT count(*) AS join_size FROM {_nest('w05')} j WHERE art2 < {_k}")
for _r in (1, 2, 4):
    _add(f"w17_redundancy_dial_{_r}", lambda s, d, r=_r: _wide(eliminate.join_size(w05(s, d, times=r)), "join_size"), f"SELECT {_r**3} * count(*) AS join_size FROM {_nest('w05')} j")


def _plan_table(s, d):
    rows = []
    for w, build in BUILD.items():
        q = build(s, d)
        g, rho = graph.build(q.scopes), cover.fractional_edge_cover(q.scopes)[0]
        order = graph.min_fill(g)
        rows.append((w, graph.classify(q.scopes), str(rho), max(map(len, graph.bags_of(g, order))), len(graph.triangulate(g, order)[1])))
    return s.createDataFrame(rows, "workload string, shape string, rho string, largest_bag int, fill_ins int")


#: Worked out by hand from the query graphs: shape, edge cover, variables of the largest bag, fill-ins.
_PLANS = {
    "w01": ("acyclic", "3", 3, 0), "w02": ("chain", "2", 2, 0), "w03": ("tree", "3", 2, 0), "w04": ("chain", "3", 2, 0), "w05": ("chain", "2", 2, 0), "w06": ("chain", "2", 2, 0),
    "w07": ("chain", "3", 2, 0), "w08": ("chain", "3", 2, 0), "w09": ("cyclic", "5/2", 3, 2), "w10": ("acyclic", "3", 3, 0), "w10k": ("acyclic", "2", 3, 0), "w11": ("acyclic", "4", 3, 0),
    "w13": ("cyclic", "3/2", 3, 0), "w14": ("cyclic", "3", 3, 1),
}


def _values(rows: list[tuple], columns: str) -> str:
    """SQL of literal rows."""
    word = lambda x: "'" + x + "'" if isinstance(x, str) else str(x)
    return "SELECT * FROM (VALUES " + ", ".join("(" + ", ".join(map(word, r)) + ")" for r in rows) + f") AS t({columns})"


_add("c11_plan_statistics", _plan_table, _values([(w, *x) for w, x in _PLANS.items()], "workload, shape, rho, largest_bag, fill_ins"))
_RHO = {"w09": "5/2", "w13": "3/2", "w05": "2", "w01": "3", "w14": "3"}
#: Rows of each workload's largest table in SQL.
_LARGEST = {w: f"(SELECT greatest((SELECT count(*) FROM {PLAYS_SQL}), (SELECT count(*) FROM {FOLLOWS_SQL})))" for w in ("w09", "w05")} | {"w13": "(SELECT count(*) FROM lineitem)", "w01": "(SELECT max(n) FROM (SELECT count(*) AS n FROM orders UNION ALL SELECT count(*) FROM customer UNION ALL SELECT count(*) FROM supplier))", "w14": "(SELECT count(*) FROM lineitem)"}


def _edge_cover(s, d):
    """The exponent, and its base: no result has more than ``largest`` to the power of ``rho`` distinct tuples."""
    made = {w: BUILD[w](s, d) for w in _RHO}
    rows = [(w, str(cover.fractional_edge_cover(q.scopes)[0]), max(rows_of(q).values())) for w, q in made.items()]
    return s.createDataFrame(rows, "w string, rho string, largest long")


_add("a04_edge_cover", _edge_cover, " UNION ALL ".join(f"SELECT '{k}' AS w, '{v}' AS rho, {_LARGEST[k]} AS largest" for k, v in _RHO.items()))

# operators around the methods
_add("e07_sql_front_w01", lambda s, d: pipeline.join(sqlfront.parse("SELECT c.c_nationkey, s.s_suppkey, o.o_orderpriority FROM orders o, customer c, supplier s WHERE o.o_custkey = c.c_custkey AND c.c_nationkey = s.s_nationkey AND c.c_mktsegment = 'BUILDING'", {t: table(s, d, t) for t in ("orders", "customer", "supplier")})).toDF("nation", "supp", "priority"), f"SELECT nation, supp, priority FROM {_nest('w01')} j WHERE segment = 'BUILDING'")
_add("e10_restrict_w01", lambda s, d: pipeline.join(restrict(w01(s, d), "nation", lambda c: c == 3)), f"SELECT {_q(OUT['w01'])} FROM {_nest('w01')} j WHERE nation = 3")
_add("e13_left_join", lambda s, d: table(s, d, "customer", ["c_custkey"]).join(table(s, d, "orders", ["o_custkey", "o_orderkey"]), F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", "o_orderkey"), "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey")
_add("e14_anti_join", lambda s, d: table(s, d, "customer", ["c_custkey"]).join(table(s, d, "events", ["user_id"]), F.col("c_custkey") == F.col("user_id"), "left_anti"), "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT user_id FROM events)")


def _asof(s, d):
    """Last event of each customer before an order: events and orders in one ordered window. Orders end in 2001 and
    events begin in 2024, so orders are moved by 23 years."""
    ev = table(s, d, "events").select(F.col("user_id").alias("cust"), F.col("ts").alias("at"), "event_id", F.lit(None).cast("long").alias("o_orderkey"))
    od = table(s, d, "orders").select(F.col("o_custkey").alias("cust"), (F.col("o_orderdate") + F.expr("INTERVAL 23 YEARS")).alias("at"), F.lit(None).cast("long").alias("event_id"), "o_orderkey")
    w = Window.partitionBy("cust").orderBy("at", F.col("o_orderkey").asc_nulls_first(), "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return ev.unionByName(od).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w)).filter("o_orderkey is not null and event_id is not null").select("o_orderkey", "event_id")


_add("e17_asof_join", _asof, "SELECT o_orderkey, event_id FROM (SELECT o_orderkey, event_id, row_number() OVER (PARTITION BY o_orderkey ORDER BY ts DESC, event_id DESC) AS k FROM orders JOIN events ON user_id = o_custkey AND ts <= o_orderdate + INTERVAL 23 YEAR) WHERE k = 1")
_add("e20_pricing", lambda s, d: table(s, d, "lineitem").filter("l_shipdate <= timestamp'1998-09-02'").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.count(F.lit(1)).alias("n")), "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY 1, 2")
_add("e22_distinct_parts", lambda s, d: table(s, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts")), "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
_add("e23_rollup_w10", lambda s, d: _wide(pipeline.summarise(w10(s, d)).deepest.rollup("segment", "priority").agg(F.sum("freq").alias("n")), "n"), f"SELECT segment, priority, count(*) AS n FROM {_nest('w10')} j GROUP BY ROLLUP (segment, priority)")
_add("e23_cube_w10", lambda s, d: _wide(pipeline.summarise(w10(s, d)).deepest.cube("segment", "flag").agg(F.sum("freq").alias("n")), "n"), f"SELECT segment, flag, count(*) AS n FROM {_nest('w10')} j GROUP BY CUBE (segment, flag)")
_add("e24_having", lambda s, d: table(s, d, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("l_returnflag") == "R").alias("returned")).filter("n > 600"), "SELECT l_suppkey, count(*) AS n, count(*) FILTER (WHERE l_returnflag = 'R') AS returned FROM lineitem GROUP BY 1 HAVING count(*) > 600")
_add("e25_pivot", lambda s, d: _pivot(s, d), f"SELECT segment, count(*) FILTER (WHERE flag = 'A') AS \"A\", count(*) FILTER (WHERE flag = 'N') AS \"N\", count(*) FILTER (WHERE flag = 'R') AS \"R\" FROM {_nest('w10')} j GROUP BY 1")


def _pivot(s, d):
    return _wide(pipeline.summarise(w10(s, d)).deepest.groupBy("segment").pivot("flag", ["A", "N", "R"]).agg(F.sum("freq")), "A", "N", "R")


_rank = lambda: Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")  # noqa: E731  a window needs a session
_add("e26_top_orders", lambda s, d: table(s, d, "orders").select("o_custkey", "o_orderkey", F.row_number().over(_rank()).cast("long").alias("k"), F.ntile(4).over(_rank()).cast("long").alias("q")).filter("k <= 3"), "SELECT o_custkey, o_orderkey, k, q FROM (SELECT o_custkey, o_orderkey, row_number() OVER w AS k, ntile(4) OVER w AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)) WHERE k <= 3")
_gap = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")
_add("e27_event_steps", lambda s, d: table(s, d, "events").select("event_id", F.lag("event_id").over(_gap()).alias("before"), F.lead("event_id").over(_gap()).alias("after")), "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
_add("e29_prefix_sum_w05", lambda s, d: summary.prefix_sum(pipeline.summarise(w05(s, d)).runs("art1"), ["u1", "art1"], "freq", "start"), f"SELECT u1, art1, freq, CAST(sum(freq) OVER (ORDER BY u1, art1) - freq AS BIGINT) AS start FROM (SELECT u1, art1, count(*) AS freq FROM {_nest('w05')} j GROUP BY 1, 2)")
_add("e33_intersect", lambda s, d: table(s, d, "customer").select(F.col("c_custkey").alias("k")).intersect(table(s, d, "events").select(F.col("user_id").alias("k"))), "SELECT c_custkey AS k FROM customer INTERSECT SELECT user_id FROM events")
_add("e33_except_all", lambda s, d: table(s, d, "orders").select(F.col("o_custkey").alias("k")).exceptAll(table(s, d, "customer").select(F.col("c_custkey").alias("k"))), "SELECT o_custkey AS k FROM orders EXCEPT ALL SELECT c_custkey FROM customer")
_add("e36_orders_a_month", lambda s, d: table(s, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count(F.lit(1)).alias("n")), "SELECT year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, count(*) AS n FROM orders GROUP BY 1, 2")
_add("e39_json_props", lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")), "SELECT event_id, CAST(props ->> '$.k' AS BIGINT) AS k FROM events")


def _udtf(s, d):
    udfs.register(s)
    runs = pipeline.summarise(w10(s, d)).runs("priority").groupBy("segment").agg(F.collect_list("priority").alias("v"), F.collect_list("freq").alias("f"))
    runs.createOrReplaceTempView("runs__w10")
    return s.sql("SELECT segment, value FROM runs__w10, LATERAL rle_expand(v, f)")


_add("e47_rle_expand_w10", _udtf, f"SELECT segment, priority AS value FROM {_nest('w10')} j")
_add("e48_rle_encode", lambda s, d: udfs.rle_encode(table(s, d, "events", ["user_id", "event_id", "event_type"]), "user_id", "event_id", "event_type"), "WITH o AS (SELECT user_id, event_type AS value, row_number() OVER w AS rn, lag(event_type) OVER w AS p FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)), g AS (SELECT *, sum(CASE WHEN p IS NULL OR p <> value THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY rn) AS i FROM o) SELECT user_id, min(rn) - 1 AS start, count(*) AS freq, any_value(value) AS value FROM g GROUP BY user_id, i")

# streams
_add("e41_stream_potential", lambda s, d: streams.drained(streams.potential(streams.events(s, d), ["user_id", "event_type"])), "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2")
_add("e42_stream_hours", lambda s, d: streams.drained(streams.windowed(streams.events(s, d), ["event_type"], "1 hour")).select(F.col("window.start").cast("timestamp_ntz").alias("hour"), "event_type", "n"), "SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS n FROM events GROUP BY 1, 2")
_add("e44_stream_state", lambda s, d: streams.drained(streams.per_key_counts(streams.events(s, d), "user_id"), "update", ["user_id"]), "SELECT user_id, count(*) AS n FROM events GROUP BY 1")
_add("e46_stream_distinct", lambda s, d: streams.drained(streams.distinct_events(streams.events(s, d), "event_id").select("event_id", "user_id"), "append"), "SELECT event_id, user_id FROM events")


def _merged_stream(s, d):
    base = potentials.build(table(s, d, "events", ["user_id"]), ["user_id"])
    return s.read.parquet(streams.merged(streams.events(s, d).select("user_id"), base, ["user_id"], _folder(s, "stream")))


_add("e43_stream_merge", _merged_stream, "SELECT user_id, 2 * count(*) AS n FROM events GROUP BY 1")
