"""Variable elimination on counts: marginals, join sizes and the generator of a run summary."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from functools import reduce as fold
from itertools import permutations

from ..plans import cover, graph
from ..plans.spec import JoinQuery
from ..sources.scratch import materialise
from .bagjoin import bag as bag_join
from .bagjoin import cheap_order, is_cyclic, potential_join, two_by_two
from .potentials import COUNT, of_query, scope, wide


@dataclass
class Conditional:
    """psi(variable | given): columns given, variable, bucket, and for each child message its value ``m_child``."""

    variable: str
    given: list[str]
    frame: DataFrame
    children: list[str]
    offsets: tuple[DataFrame, int, int] | None = None  # the frame with the rows before each value, and sizes; see summary.place

    def table(self) -> DataFrame:
        """given, variable, bucket, fac: own frequency and that of the sub-trees below (1 at a leaf)."""
        fac = F.lit(1).cast("long")
        for c in self.children:
            fac = fac * F.col(f"m_{c}")
        return self.frame.select(*self.given, self.variable, "bucket", fac.alias("fac"))


@dataclass
class Generator:
    """Conditionals in the order of generation (root first), and the messages that linked them."""

    query: JoinQuery
    order: list[str]
    conditionals: list[Conditional]
    messages: dict[str, DataFrame]
    safe: set[str]

    @property
    def root(self) -> DataFrame:
        """Root marginal: value and frequency."""
        t = self.conditionals[0].table()
        return t.select(self.conditionals[0].variable, (F.col("bucket") * F.col("fac")).alias(COUNT))

    def by(self, variable: str) -> Conditional:
        return next(c for c in self.conditionals if c.variable == variable)

    def levels(self) -> list[list[str]]:
        """Variables by the depth at which all they depend on is observed."""
        depth: dict[str, int] = {}
        for c in self.conditionals:
            depth[c.variable] = 1 + max((depth[g] for g in c.given), default=-1)
        return [[v for v, d in depth.items() if d == k] for k in range(max(depth.values()) + 1)]

    def shape(self) -> str:
        if any(len(c.given) > 1 for c in self.conditionals):
            return "dag"
        parents = [c.given[0] for c in self.conditionals if c.given]
        return "chain" if len(set(parents)) == len(parents) else "tree"


def order_for(query: JoinQuery, hidden: list[str], root: str | None = None) -> list[str]:
    """Hidden variables first, then the rest; least fill-ins in each part. The output's columns are generated in
    their own order where that costs no more fill-ins than the greedy order. (Cyclic queries: see ``order_by_size``.)"""
    g = graph.build(query.scopes)
    visible = [v for v in query.variables if v not in hidden]
    wanted = [v for v in query.output if v in visible]
    wanted += [v for v in visible if v not in wanted]
    if root:
        wanted = [root, *[v for v in wanted if v != root]]
    as_written = [*graph.min_fill(g, first=hidden, last=wanted[::-1])] if hidden else wanted[::-1]
    as_written = [v for v in as_written if v in hidden] + wanted[::-1]
    greedy = graph.min_fill(g, first=hidden, last=[root] if root else [])

    def cost(order: list[str]) -> tuple[int, int]:
        return max(len(b) for b in graph.bags_of(g, order)), len(graph.triangulate(g, order)[1])

    return as_written if cost(as_written) <= cost(greedy) else greedy


def sizes_of(frames: dict[str, DataFrame]) -> dict[str, tuple[int, dict[str, int]]]:
    """Rows and (approximate) distinct values of every column but the count, of all frames in one pass without a shuffle of rows."""
    made = []
    for t, df in frames.items():
        columns = scope(df)
        distinct = F.array(*[F.approx_count_distinct(c) for c in columns]) if columns else F.array().cast("array<long>")
        made.append(df.agg(F.count(F.lit(1)).alias("rows"), distinct.alias("distinct")).select(F.lit(t).alias("t"), "rows", "distinct"))
    rows = fold(lambda a, b: a.unionByName(b), made).collect()  # one a table
    return {r["t"]: (r["rows"], {c: max(1, n) for c, n in zip(scope(frames[r["t"]]), r["distinct"], strict=True)}) for r in rows}


#: Rows of a factor, and distinct values of each of its variables.
Size = tuple[float, dict[str, int]]


def _joint_size(own: list[Size], values: dict[str, int]) -> float:
    """Rows expected of a join: the product of its factors' rows over the values of each variable shared."""
    rows = fold(lambda a, f: a * f[0], own, 1.0)
    for v in set().union(*[d for _, d in own]):
        rows /= float(values[v]) ** (sum(v in d for _, d in own) - 1)
    return rows


def _message_size(joint: float, given: set[str], values: dict[str, int]) -> Size:
    return min(joint, fold(lambda a, x: a * values[x], given, 1.0)), {x: values[x] for x in given}


def _values(sizes: list[Size]) -> dict[str, int]:
    return {v: max(d[v] for _, d in sizes if v in d) for _, own in sizes for v in own}


def _base_sizes(sizes: list[Size]) -> list[Size]:
    """Distinct tuples are at most the rows and the product of the values."""
    return [(min(n, fold(lambda a, v: a * d[v], d, 1.0)), d) for n, d in sizes]


def order_by_size(query: JoinQuery, hidden: list[str] = (), sizes: list[Size] | None = None) -> list[str]:
    """The order whose bags and messages are expected to hold fewest rows; up to 7 variables, else least fill-ins.
    Hidden variables go first; ties go to the output's own column order."""
    variables = query.variables
    if len(variables) > 7:
        return graph.min_fill(graph.build(query.scopes), first=hidden)
    base = _base_sizes(sizes or list(sizes_of(query.tables).values()))
    values = _values(base)

    def cost(order: list[str]) -> float:
        factors, total = list(base), 0.0
        for v in order:
            bag = set().union(*[d for _, d in factors if v in d])
            own = [f for f in factors if f[1].keys() <= bag]
            joint = _joint_size(own, values)
            factors = [f for f in factors if not f[1].keys() <= bag] + [_message_size(joint, bag - {v}, values)]
            total += joint
        return total

    hidden = list(hidden)
    shown = [v for v in variables if v not in hidden]
    last = [v for v in query.output if v in shown]
    orders = ([*a, *b] for a in permutations(hidden) for b in permutations(shown))
    return min(orders, key=lambda o: (round(cost(o), 3), [last.index(v) if v in last else -1 for v in o[::-1]]))


#: How many times fewer rows than a bag its given values must be, for these to be looked up elsewhere first.
FEWER = 4.0


def _reach(given: list[str], own: list, others: list, values: dict[str, int]) -> tuple[set[str], DataFrame, None, Size] | None:
    """The given values of a bag that the factors outside it admit, each with count 1, as one more factor; None where no
    factor of the bag is spared much by it (or the values lie together in one table, which the joins to come look up anyway)."""
    outside = set().union(*[f[0] for f in others])
    if len(given) < 2 or not set(given) <= outside or any(set(given) <= f[0] for f in own):
        return None
    factors, most = [f[3] for f in others], 0.0
    for v in graph.min_fill(graph.build({str(i): tuple(f[1]) for i, f in enumerate(factors)}), last=given):
        if v not in given:
            bag = set().union(*[d for _, d in factors if v in d])
            held = [f for f in factors if f[1].keys() <= bag]
            joint = _joint_size(held, values)
            factors = [f for f in factors if not f[1].keys() <= bag] + [_message_size(joint, bag - {v}, values)]
            most = max(most, joint)
    size = _message_size(_joint_size(factors, values), set(given), values)
    if max(most, size[0]) * FEWER > _joint_size([f[3] for f in own], values):
        return None
    rest = JoinQuery({str(i): f[1].drop(COUNT) for i, f in enumerate(others) if f[0]}, given)
    return set(given), marginal(rest, given).withColumn(COUNT, F.lit(1).cast("long")), None, size


def build_generator(query: JoinQuery, order: list[str] | None = None, root: str | None = None, project: str = "early", phis: dict[str, DataFrame] | None = None, strategy: str = "auto", junction: str = "tree", reached: bool = False, once: bool = False) -> Generator:
    """Eliminate all variables, keeping a conditional for each that the output shows.

    Trees, chains and cycles go the same way: eliminating a variable joins the potentials and messages that hold it and
    all others that fit into its bag, so fill-ins never become tables. A cyclic bag is joined two by two where that is
    expected to stay well below the worst-case bound; else prefixes are grown, and the bag is computed here and kept on
    the shared folder. All else is lazy. ``project``: ``early`` deletes join variables
    that the output lacks before all others; ``skip`` keeps them in the generator, to be left out when runs are written.
    ``junction='single'`` puts all variables into one bag: the worst case, whose potential is the whole grouped result.
    ``reached``: where the tables outside a cyclic bag are expected to admit far fewer of its given values than the bag
    has, the bag is made for those only. Runs never hold others; messages then lack them. ``once``: messages of join
    variables that the output lacks are computed here and kept on the shared folder, as several conditionals go back to them.
    """
    if junction == "single":
        whole = potential_join(list((phis or of_query(query)).values()), query.variables, strategy, set(query.variables) - query.joined)
        return build_generator(query, order, root, project, {"all": materialise(whole)}, once=once)
    hidden = query.hidden if project == "early" else []
    phis = phis or of_query(query)
    safe = set(query.variables) - query.joined
    looped = strategy != "auto" or is_cyclic(set(scope(p)) for p in phis.values())
    sizes = list(sizes_of(query.tables if len(query.tables) == len(phis) else phis).values()) if looped else [(1.0, dict.fromkeys(scope(p), 1)) for p in phis.values()]
    order = order or query.order or (order_by_size(query, hidden, sizes) if looped and not root else order_for(query, hidden, root))
    values = _values(sizes)
    factors: list[tuple[set[str], DataFrame, str | None, Size]] = [(set(scope(p)), p, None, z) for p, z in zip(phis.values(), _base_sizes(sizes), strict=True)]
    conditionals, messages = [], {}
    for v in order:
        bag = set().union(*[f[0] for f in factors if v in f[0]])
        own = [f for f in factors if f[0] <= bag]
        factors = [f for f in factors if not f[0] <= bag]
        given = [x for x in order if x in bag and x != v]
        open_ones = [] if v in hidden else [f for f in own if f[2] is not None and f[2] not in hidden]
        base = [f for f in own if f not in open_ones]
        met = _reach(given, own, factors, values) if reached and looped and strategy == "auto" else None
        if met:
            own, base = [met, *own], [met, *base]
        parts = [(f[1].withColumnRenamed(COUNT, f"n__{i}"), f"n__{i}") for i, f in enumerate(base)]
        held = [*parts, *((f[1].withColumnRenamed(COUNT, f"m_{f[2]}"), f"m_{f[2]}") for f in open_ones)]
        cyclic = strategy != "auto" or is_cyclic(f[0] for f in own)
        grown = cyclic
        if cyclic and strategy == "auto" and (paired := two_by_two([f[3] for f in (*base, *open_ones)])):
            held, grown = [held[i] for i in paired], False
        names = cheap_order([f[3] for f in own if f[0]]) if grown else [v, *given]
        frame = bag_join(held, names, strategy if grown else "pairwise", safe) if len(held) > 1 else held[0][0]
        bucket = fold(lambda a, b: a * b, [F.col(n) for _, n in parts], F.lit(1).cast("long"))
        children = [f[2] for f in open_ones]
        frame = frame.select(*given, v, bucket.alias("bucket"), *[f"m_{c}" for c in children])
        if (grown or met) and v not in hidden:
            frame = materialise(frame)  # read by the message and by each level generated from it
        psi = Conditional(v, given, frame, children)
        t = psi.table().withColumn(COUNT, F.col("bucket") * F.col("fac"))
        message = t.groupBy(*given).agg(F.sum(COUNT).alias(COUNT)) if given else t.agg(F.sum(COUNT).alias(COUNT)).filter(F.col(COUNT).isNotNull())
        if once and v in query.hidden:
            message = materialise(message)
        factors.append((set(given), message, v, _message_size(_joint_size([f[3] for f in own], values), set(given), values)))
        if v not in hidden:
            conditionals.append(psi)
            messages[v] = message
    return Generator(query, order, conditionals[::-1], messages, safe)


def marginal(query: JoinQuery, variables: list[str], order: list[str] | None = None, phis: dict[str, DataFrame] | None = None) -> DataFrame:
    """Counts of the join result by ``variables``: all others are summed out, none of the join is built."""
    g = graph.build(query.scopes)
    others = [v for v in query.variables if v not in variables]
    if not order:
        looped = query.tables and is_cyclic(set(s) for s in query.scopes.values())
        order = order_by_size(query, others) if looped else graph.min_fill(g, first=others)
    order = [v for v in order if v not in variables]
    safe = set(query.variables) - query.joined
    factors = [(set(scope(p)), p) for p in (phis or of_query(query)).values()]
    for v in order:
        bag = set().union(*[s for s, _ in factors if v in s])
        own = [p for s, p in factors if s <= bag]
        factors = [(s, p) for s, p in factors if not s <= bag]
        given = [x for x in query.variables if x in bag and x != v]
        joint = potential_join(own, [*given, v], "auto", safe)
        factors.append((set(given), joint.groupBy(*given).agg(F.sum(COUNT).alias(COUNT)) if given else joint.agg(F.sum(COUNT).alias(COUNT))))
    return potential_join([p for _, p in factors], list(variables), "pairwise", safe).select(*variables, COUNT)


def join_size(query: JoinQuery, phis: dict[str, DataFrame] | None = None) -> DataFrame:
    """One row ``join_size``: rows of the join, without joining rows. Works on stored potentials too.

    Counts of 64 bits raise where a product overflows; potentials with ``potentials.wide`` counts go on to 38 digits.
    """
    total = marginal(query, [], phis=phis)
    return total.agg(F.coalesce(F.sum(COUNT), F.lit(0)).cast("decimal(38,0)").alias("join_size"))


def safe_potentials(query: JoinQuery, phis: dict[str, DataFrame] | None = None) -> dict[str, DataFrame]:
    """Potentials whose counts can't overflow: of 64 bits if the bag bound of the join lies below 2^62, else of 38 digits."""
    phis = phis or of_query(query)
    bound = cover.bag_bound(phis, cover.fractional_edge_cover({t: tuple(scope(p)) for t, p in phis.items()})[1])
    return phis if bound < 2**62 else wide(phis)


def reduce(query: JoinQuery) -> JoinQuery:
    """Semi-join pass over the tables, leaves to root and back: no row stays that an acyclic join doesn't need."""
    names, tables = list(query.tables), dict(query.tables)
    for sweep in (names, names[::-1]):
        for a in sweep:
            for b in names:
                on = [v for v in query.scopes[a] if v in query.scopes[b]]
                if a != b and on:
                    tables[a] = tables[a].join(tables[b].select(*on).distinct(), on, "left_semi")
    return JoinQuery(tables, query.output, query.order)
