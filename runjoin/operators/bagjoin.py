"""Join of the potentials of one bag: worst-case optimal, a variable at a time, on counts."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from functools import reduce
from itertools import permutations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import IntegralType, LongType, StructField, StructType

from ..plans import cover
from . import tries
from .potentials import COUNT, joined, scope

#: A frame and the name of its count column; all its other columns are variables.
Part = tuple[DataFrame, str]


def potential_join(phis: list[DataFrame], order: list[str] | None = None, strategy: str = "auto", safe: set[str] = frozenset(), shares: dict[str, int] | None = None, trie: str = "hash", dealt: tuple[str, list[str]] | None = None, rows: list[str] = ()) -> DataFrame:
    """One potential over all variables of ``phis``.

    ``pairwise`` lets Catalyst join two by two (a cycle in the order of least steps, after one pass of counts); ``extend`` grows prefixes a variable at a time, each from the potential
    with fewest matches for it; ``hypercube`` deals rows to a grid of cells in one shuffle and joins each cell alone, by
    tries of sorted levels or with a hash table a level (``trie``). ``auto`` is pairwise where each added potential shares a scope
    with what is there (no join can fan out beyond the bag), else ``extend``. ``dealt``: see ``_extend``. ``rows``: see ``_hypercube``.
    """
    if len(phis) == 1:
        return phis[0]
    order = order or list(dict.fromkeys(v for p in phis for v in scope(p)))
    if strategy == "hypercube":
        return _hypercube(phis, order, shares or dict.fromkeys(order, 2), trie, rows).select(*order, COUNT)
    if strategy == "pairwise" and 2 < len(phis) <= 6 and is_cyclic(set(scope(p)) for p in phis):
        from .eliminate import sizes_of

        sizes = list(sizes_of({str(i): p for i, p in enumerate(phis)}).values())
        phis = [phis[i] for i in paired_order(sizes)[0]]
    parts = [(p.withColumnRenamed(COUNT, f"n__{i}"), f"n__{i}") for i, p in enumerate(phis)]
    times = reduce(lambda a, b: a * b, [F.col(n) for _, n in parts])
    out = _extend(parts, order, safe, dealt) if dealt else bag(parts, order, strategy, safe)
    return out.select(*order, times.alias(COUNT))


def bag(parts: list[Part], order: list[str], strategy: str = "auto", safe: set[str] = frozenset()) -> DataFrame:
    """The join with the count columns of all parts side by side."""
    if strategy == "auto":
        strategy = "extend" if is_cyclic([_scope(p) for p in parts]) else "pairwise"
    if strategy == "pairwise":
        return _pairwise(parts, safe)
    if strategy == "extend":
        return _extend(parts, order, safe)
    raise ValueError(f"no strategy {strategy}")


def _scope(part: Part) -> set[str]:
    return {c for c in part[0].columns if c != part[1]}


#: How much larger than expected a step of a pairwise plan may get before the worst-case bound is passed.
MARGIN = 4.0


def paired_order(sizes: list[tuple[float, dict[str, int]]]) -> tuple[list[int], float]:
    """The order of joining parts two by two whose largest step is expected to be least, and that step's rows."""
    values = {v: max(d[v] for _, d in sizes if v in d) for _, own in sizes for v in own}

    def largest(order: tuple[int, ...]) -> float:
        most, rows, seen = 0.0, sizes[order[0]][0], set(sizes[order[0]][1])
        for i in order[1:]:
            n, own = sizes[i]
            if own and not seen & own.keys():
                return float("inf")
            rows *= n / float(np.prod([values[v] for v in seen & own.keys()]))
            most, seen = max(most, rows), seen | own.keys()
        return most

    best = min(permutations(range(len(sizes))), key=lambda o: (largest(o), o))
    return list(best), largest(best)


def two_by_two(sizes: list[tuple[float, dict[str, int]]]) -> list[int] | None:
    """The order in which to join a cyclic bag's parts two by two, if its largest step is expected to stay below the bag's
    worst-case bound by MARGIN; else None, and prefixes should be grown. ``sizes``: rows and distinct values of each part."""
    if not 2 < len(sizes) <= 6:
        return None
    best, most = paired_order(sizes)
    named = {str(i): tuple(d) for i, (_, d) in enumerate(sizes) if d}
    rows = {t: max(1, int(sizes[int(t)][0])) for t in named}
    bound = cover.agm_bound(rows, cover.weighted_cover(named, rows))
    return best if MARGIN * most <= bound else None


def _pairwise(parts: list[Part], safe: set[str]) -> DataFrame:
    left, out, seen = list(parts), None, set()
    while left:
        part = next((x for x in left if seen & _scope(x)), left[0])
        left = [x for x in left if x is not part]
        own = _scope(part)
        out = part[0] if out is None else joined(out, part[0], [c for c in out.columns if c in own], safe)
        seen |= own
    return out


def is_cyclic(scopes: Iterable[set[str]]) -> bool:
    """Whether ear removal leaves something."""
    left = list(scopes)
    while left:
        for i, e in enumerate(left):
            others = left[:i] + left[i + 1 :]
            shared = {v for v in e if any(v in o for o in others)}
            if not shared or any(shared <= o for o in others):
                left = others
                break
        else:
            return True
    return False


def dealt_out(rows: DataFrame, columns: list[str]) -> DataFrame:
    """Rows dealt out evenly, and sorted by ``columns`` in each task. What a sorted row fans out to comes again and again
    at a short distance, so files of it stay small, and no task has all the rows that fan out."""
    even = rows.repartition(max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    # Catalyst drops a sort below a join, unless it has to look at the tasks in between
    return even.sortWithinPartitions(*columns).filter(F.spark_partition_id() >= 0)


def _steps_of(order: list[str], parts: list[Part]) -> list[list[str]]:
    """Variables bound together: neighbours that one and the same part holds alone, as it offers all of them at once."""
    holders = {v: [i for i, p in enumerate(parts) if v in _scope(p)] for v in order}
    steps: list[list[str]] = []
    for v in order:
        if steps and len(holders[v]) == 1 and holders[steps[-1][-1]] == holders[v]:
            steps[-1].append(v)
        else:
            steps.append([v])
    return steps


def _extend(parts: list[Part], order: list[str], safe: set[str], dealt: tuple[str, list[str]] | None = None) -> DataFrame:
    """Prefixes of bound variables, a variable longer at each step (or several that one part alone knows). ``dealt``: the
    variable before which prefixes are dealt out evenly, and what they are sorted by.

    Where several parts know values for a prefix, it takes them from the one that has fewest: counts of the offers are
    looked up, the offers lie in one table under a hash of who offers and for which key, and each prefix meets the rows
    of its choice there. All other parts then confirm the value; a part whose variables are all bound confirms with its
    count. So a step is a fixed number of joins, and no prefix is computed twice.
    """
    prefix: DataFrame | None = None
    bound: list[str] = []
    for own in _steps_of(order, parts):
        v = own[0]
        if dealt and dealt[0] in own and prefix is not None:
            prefix = dealt_out(prefix, [c for c in dealt[1] if c in bound])
        holders = [p for p in parts if v in _scope(p)]
        near = [p for p in holders if _scope(p) & set(bound)]
        far = [p for p in holders if p not in near]
        domains = [p[0].select(*own).distinct() for p in far]
        done = [p for p in holders if _scope(p) <= {*bound, *own}]
        counted: list[Part] = []
        if not near:
            values = reduce(lambda a, b: joined(a, b, own, safe, "left_semi"), domains)
            prefix = values if prefix is None else prefix.crossJoin(values)
        else:
            keys = [[c for c in bound if c in _scope(p)] for p in near]
            offers = []
            for p, k in zip(near, keys, strict=True):
                offer = p[0] if p in done else p[0].select(*k, *own).distinct()
                offers.append(reduce(lambda a, d: joined(a, d, own, safe, "left_semi"), domains, offer))
            if len(near) == 1:
                prefix = joined(prefix, offers[0], keys[0], safe)
                counted = [p for p in near if p in done]
            else:
                prefix = _from_fewest(prefix, [o.select(*k, v) for o, k in zip(offers, keys, strict=True)], keys, v, safe)
                for p, o, k in zip(near, offers, keys, strict=True):
                    if p not in done:
                        prefix = joined(prefix, o, [*k, v], safe, "left_semi")
        for p in done:
            if p not in counted:
                prefix = joined(prefix, p[0], [c for c in p[0].columns if c != p[1]], safe)
        bound += own
    for p in parts:
        if not _scope(p):
            prefix = prefix.crossJoin(p[0])
    return prefix


def _from_fewest(prefix: DataFrame, offers: list[DataFrame], keys: list[list[str]], v: str, safe: set[str]) -> DataFrame:
    """Each prefix with the values of ``v`` from the offer that has fewest for it."""
    held = list(prefix.columns)
    for i, (o, k) in enumerate(zip(offers, keys, strict=True)):
        prefix = joined(prefix, o.groupBy(*k).agg(F.count(F.lit(1)).alias(f"fan__{i}")), k, safe)
    fans = [F.col(f"fan__{i}") for i in range(len(offers))]
    choice = reduce(lambda w, i: w.when(fans[i] == F.least(*fans), i), range(1, len(offers)), F.when(fans[0] == F.least(*fans), 0))
    spot = reduce(lambda w, i: w.when(F.col("choice__") == i, F.xxhash64(F.lit(i), *keys[i])), range(len(offers)), F)
    asking = prefix.withColumn("choice__", choice).withColumn("spot__", spot).select(*held, "choice__", "spot__")
    names = list(dict.fromkeys(c for k in keys for c in k))
    types = {c: prefix.schema[c].dataType for c in names}
    tables = [
        o.select(F.lit(i).alias("from__"), F.xxhash64(F.lit(i), *k).alias("at__"), *[(F.col(c) if c in k else F.lit(None)).cast(types[c]).alias(f"{c}__o") for c in names], v)
        for i, (o, k) in enumerate(zip(offers, keys, strict=True))
    ]
    table = reduce(lambda a, b: a.unionByName(b), tables)
    same = [(F.col("choice__") != i) | reduce(lambda a, b: a & b, [F.col(c).eqNullSafe(F.col(f"{c}__o")) for c in k]) for i, k in enumerate(keys)]
    met = asking.join(table, [F.col("spot__") == F.col("at__"), F.col("choice__") == F.col("from__"), *same])
    return met.select(*held, v)


def cheap_order(sizes: list[tuple[int, dict[str, int]]]) -> list[str]:
    """Variables in the order of fewest expected prefixes. ``sizes``: rows of each part, and distinct values of its variables."""
    variables = sorted({v for _, d in sizes for v in d})
    if len(variables) > 7:
        return variables

    def seen(part: tuple[int, dict[str, int]], bound: set[str]) -> float:
        n, d = part
        return min(n, float(np.prod([d[v] for v in d if v in bound])))

    def cost(order: tuple[str, ...]) -> float:
        total, prefixes, bound = 0.0, 1.0, set()
        for v in order:
            fans = [seen(p, bound | {v}) / max(1.0, seen(p, bound)) for p in sizes if v in p[1]]
            domain = max(p[1][v] for p in sizes if v in p[1])
            grown = prefixes * min(fans)
            prefixes = grown * float(np.prod([min(1.0, f / domain) for f in sorted(fans)[1:]]))
            total, bound = total + grown, bound | {v}
        return total

    return list(min(permutations(variables), key=lambda o: (cost(o), o)))


#: Values (rows times variables) that a cell of the grid is expected to hold at most.
CELL_VALUES = 16_000_000


def finer(rows: list[float], scopes: list[list[str]], shares: dict[str, int]) -> dict[str, int]:
    """Shares raised until a cell is expected to hold CELL_VALUES at most, each time where that sends fewest copies of rows.

    Only variables of several parts are cut: a cut of another one would send copies of all other parts.
    """
    shares = dict(shares)
    cut = [v for v in shares if sum(v in s for s in scopes) > 1]

    def held(x: dict[str, int]) -> float:
        return sum(n * len(s) / float(np.prod([x[v] for v in s])) for n, s in zip(rows, scopes, strict=True))

    def cells(x: dict[str, int]) -> int:
        return int(np.prod(list(x.values())))

    while cut and held(shares) > CELL_VALUES:
        steps = [shares | {v: shares[v] + 1} for v in cut]
        # copies sent for each value that a cell is spared
        shares = min(steps, key=lambda x: (held(x) * cells(x) - held(shares) * cells(shares)) / (held(shares) - held(x)))
    return shares


def _hypercube(phis: list[DataFrame], order: list[str], shares: dict[str, int], trie: str, rows: list[str] = ()) -> DataFrame:
    """Rows of each potential go to every cell that agrees with the hashes of its variables; cells are joined alone.

    Rows and distinct values are counted first. The grid is made as fine as its cells' memory asks for (``shares`` are the
    least), and the tries' levels follow the order of fewest expected prefixes. Rows are packed before they are dealt, many
    of a cell at once, so copies cost bytes and no steps a row. A cell is a partition. ``rows``: a variable a part, by
    which cells number the part's rows, so that equal ones stay apart; it is bound last.
    """
    from .eliminate import sizes_of

    sizes = list(sizes_of({str(i): p for i, p in enumerate(phis)}).values())
    order = cheap_order(sizes) if len(order) <= 7 else order
    types = {v: next(p.schema[v].dataType for p in phis if v in scope(p)) for v in order}
    kinds = {v: to_arrow_type(t) for v, t in types.items() if isinstance(t, IntegralType)}
    scopes = [[v for v in order if v in scope(p)] for p in phis]
    held = [[*s, *rows[i : i + 1]] for i, s in enumerate(scopes)]
    shares = finer([n for n, _ in sizes], held, {v: shares[v] for v in order} | dict.fromkeys(rows, 1))
    steps = {v: int(np.prod([shares[x] for x in order[k + 1 :]])) for k, v in enumerate(order)}
    dealt = []
    for i, p in enumerate(phis):
        columns = [F.col(v).cast(types[v]).alias(v) for v in scopes[i]]
        cell = reduce(lambda a, v: a + F.pmod(F.xxhash64(F.col(v).cast(types[v])), F.lit(shares[v])) * steps[v], scopes[i], F.lit(0).cast("long"))
        df = p.select(*columns, F.col(COUNT).cast("long").alias(COUNT), cell.alias("cell__")).mapInArrow(pack, "cell__ long, rows__ binary")
        for v in order:
            if v not in scopes[i] and shares[v] > 1:
                df = df.select(F.explode(F.array(*[F.col("cell__") + k * steps[v] for k in range(shares[v])])).alias("cell__"), "rows__")
        dealt.append(df.select("cell__", F.lit(i).alias("part__"), "rows__"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return join_cell(batches, order, scopes, trie, kinds, rows)

    schema = StructType([*[StructField(v, types[v]) for v in order], StructField(COUNT, LongType())])
    cells = reduce(lambda a, b: a.unionByName(b), dealt).repartitionById(int(np.prod(list(shares.values()))), F.col("cell__").cast("int"))
    return cells.drop("cell__").mapInArrow(run, schema)


#: Rows that are packed together, all cells' at once.
PACKED = 1 << 20


def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows with cell__ in; cell__ and its rows as one Arrow stream out, whole numbers in 32 bits where they fit."""
    held, size = [], 0

    def packed() -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(held).combine_chunks()
        cells = table["cell__"].to_numpy()
        table = table.drop_columns(["cell__"]).take(pa.array(np.argsort(cells, kind="stable")))
        found, first = np.unique(np.sort(cells), return_index=True)
        for name in table.column_names:
            column = _taken(table[name].combine_chunks())
            if isinstance(column, np.ndarray):
                table = table.set_column(table.column_names.index(name), name, pa.array(column))
        for cell, start, end in zip(found.tolist(), first.tolist(), [*first[1:].tolist(), len(cells)], strict=True):
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, table.schema) as writer:
                writer.write_table(table.slice(start, end - start).combine_chunks())
            yield pa.RecordBatch.from_arrays([pa.array([cell], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["cell__", "rows__"])

    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            size += batch.num_rows
        if size >= PACKED:
            yield from packed()
            held, size = [], 0
    if held:
        yield from packed()


#: Values of one variable in one part, batch by batch: whole numbers as such, all else as Arrow has it.
Chunks = list[np.ndarray | pa.Array]


def _taken(column: pa.Array) -> np.ndarray | pa.Array:
    if not pa.types.is_signed_integer(column.type) or column.null_count:
        return column
    values = column.to_numpy()
    return values if values.dtype == np.int32 else tries.narrow(values.astype(np.int64))


def _encode(held: list[dict[str, Chunks]], v: str, kind: pa.DataType) -> Callable[[np.ndarray], pa.Array]:
    """A function from codes back to values. Whole numbers are their own codes; else all values of the cell become their
    places in a dictionary (-1: null)."""
    owners = [own for own in held if v in own]
    if all(isinstance(c, np.ndarray) for own in owners for c in own[v]):
        return lambda codes: pa.array(codes.astype(np.int64)).cast(kind)
    arrays = [pa.array(c.astype(np.int64)).cast(kind) if isinstance(c, np.ndarray) else c for own in owners for c in own[v]]
    encoded = pa.chunked_array(arrays, kind).combine_chunks().dictionary_encode()
    codes, at = encoded.indices.fill_null(-1).to_numpy(zero_copy_only=False), 0
    for own in owners:
        size = sum(map(len, own[v]))
        own[v], at = [codes[at : at + size]], at + size
    return lambda codes: encoded.dictionary.take(pa.array(codes, mask=codes < 0))


def join_cell(batches: Iterator[pa.RecordBatch], order: list[str], scopes: list[list[str]], trie: str, kinds: dict[str, pa.DataType], rows: list[str] = ()) -> Iterator[pa.RecordBatch]:
    """One cell's join: part__ and its packed rows in, batches of rows out. ``kinds``: types of variables that are whole numbers."""
    held: list[dict[str, Chunks]] = [{x: [] for x in (*own, COUNT)} for own in scopes]
    kinds = dict(kinds)
    for batch in batches:
        for i, packed in zip(batch["part__"].to_pylist(), batch["rows__"], strict=True):
            with pa.ipc.open_stream(packed.as_buffer()) as reader:
                for own in reader:
                    for v in held[i]:
                        # copied, as the buffer of all packed rows goes
                        column = _taken(own[v])
                        held[i][v].append(column.copy() if isinstance(column, np.ndarray) else pa.concat_arrays([column, column[:0]]))
                        kinds.setdefault(v, own[v].type)
    if not all(own[COUNT] for own in held):
        return
    values = {v: _encode(held, v, kinds[v]) for v in order}
    made = []
    for own in held:
        counts, names = np.concatenate(own.pop(COUNT)), list(own)
        columns = [np.concatenate(own.pop(v)) for v in names]
        if rows:
            names.append(rows[len(made)])
            columns.append(np.arange(len(counts), dtype=np.int32))
        made.append((names, (tries.SortedTrie if trie == "sorted" else tries.HashTrie)(columns, counts)))
        del columns, counts
    for columns, n in tries.batches([*order, *rows], made):
        yield pa.RecordBatch.from_arrays([*(values[v](c) for v, c in zip(order, columns, strict=False)), pa.array(n, pa.int64())], [*order, COUNT])
