"""Near duplicates: MinHash signatures joined coordinate by coordinate through inverted lists."""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, listed, looked_up, met_in_place, numbered, picked, rows_of, table, text_rows

#: Signature coordinates, and how many of them a pair must share. A pair at 0.8 shares Bin(64, 0.8) of them: 51 on
#: average, and fewer than 36 with probability 4e-6; a pair at 0.85 with 7e-9.
COORDINATES, AGREE = 64, 36
#: Shingles of a block of full sets in the last merge.
BLOCK_SHINGLES = 400_000
_SEEDS = np.random.default_rng(20240229).integers(0, 1 << 63, (2, COORDINATES, 1), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_STIR = [np.uint64(x) for x in np.random.default_rng(11).integers(1 << 62, 1 << 63, 3)]


def shingles(words: list[bytes], width: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of all runs of ``width`` words; a shorter text is one run, no word gives none."""
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=len(words))
    span = min(width, len(words))
    n = len(words) - span + 1
    out = np.full(n, np.uint64(span), np.uint64)
    for k in range(span):
        out = (out ^ h[k : k + n]) * _STIR[0]
        out ^= out >> np.uint64(29)
    out = out * _STIR[1]
    out ^= out >> np.uint64(32)
    return np.unique(out)


def signature(found: np.ndarray) -> np.ndarray:
    """Smallest value of the set under each of the seeded orders, 32 bits each."""
    low = np.full(COORDINATES, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(found), 4096):
        part = (found[None, at : at + 4096] ^ _SEEDS[0]) * _SEEDS[1]
        low = np.minimum(low, part.min(axis=1))
    return (low >> np.uint64(32)).astype(np.uint32).view(np.int32)


def _words(text: str) -> list[bytes]:
    return text.encode().lower().split()  # of bytes: A to Z only, ASCII white space only


_SIGNED = "row long, doc_id long, n_shingles long, key binary, signature array<int>, text string"


def _sign(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[pa.RecordBatch]:
    for batch, texts in text_rows(batches):
        counts, keys, signs = [], [], []
        for text in texts:
            found = shingles(_words(text), width)
            counts.append(len(found))
            keys.append(xxhash.xxh3_128_digest(found.tobytes()) if len(found) else None)
            signs.append(signature(found) if len(found) else None)
        made = [batch.column(0), batch.column(1), pa.array(counts, pa.int64()), pa.array(keys, pa.binary()), pa.array(signs, pa.list_(pa.int32())), batch.column(2)]
        yield pa.RecordBatch.from_arrays(made, ["row", "doc_id", "n_shingles", "key", "signature", "text"])


def components(scratch: Scratch, edges: DataFrame, name: str) -> DataFrame:
    """Smallest reachable id of every node that has an edge: (id, root). ``edges``: columns a, b.

    Each round links nodes to the least neighbour of their neighbourhood (large-star and small-star steps), which
    takes a number of rounds logarithmic in the longest chain; rounds are written to shared files. The edges of a node
    with very many are summed before they are shuffled and then meet its one row of results in a plain inner join,
    which adaptive execution splits.
    """
    pairs = scratch.save(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct(), f"{name}-0")
    seen, step = None, 0
    while True:
        step += 1
        # large star: neighbours above a node point to the least of its neighbourhood
        both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("low"))
        large = both.join(least, "a").filter("b > a").select(F.col("b").alias("a"), F.col("low").alias("b"))
        # small star: the node and its lower neighbours point to the least of them
        low = large.groupBy("a").agg(F.min("b").alias("low"))
        small = large.join(low, "a").select(F.col("b").alias("a"), F.col("low").alias("b")).filter("a <> b").unionByName(low.select("a", F.col("low").alias("b")))
        pairs = scratch.save(small.distinct(), f"{name}-{step}")
        state = pairs.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        scratch.drop(f"{name}-{step - 1}")
        if tuple(state) == seen:
            return pairs.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("root")).unionByName(pairs.select(F.col("b").alias("id"), F.col("b").alias("root")).distinct())
        seen = tuple(state)


def _agreeing(a: Column, b: Column) -> Column:
    """Coordinates on which two signatures agree."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)


def _linked(scratch: Scratch, pairs: DataFrame, sides: DataFrame, agree: int, percent: int, name: str) -> DataFrame:
    """Pairs (a, b) that share enough coordinates and, on their full sets, enough shingles. Only the sets of pairs that
    agree on their coordinates travel."""
    left, right = (sides.select(F.col("id").alias(k), F.col("signature").alias(f"s{k}")) for k in "ab")
    close = pairs.join(left, "a").join(right, "b").filter(_agreeing(F.col("sa"), F.col("sb")) >= agree).select("a", "b")
    close = scratch.save(close, f"close-{name}")
    # sets of a go from where they lie to those of b, which are fewer: b is a hub
    lists = listed(scratch, close, f"asked-{name}")
    sent = met_in_place(sides.select(F.col("id").alias("a"), F.col("found").alias("fa"), F.col("id").alias("row")), "row", close, lists)
    hubs = rows_of(sides.select(F.col("id").alias("b"), F.col("found").alias("fb"), F.col("id").alias("row")), "row", listed(scratch, close.select("b").distinct(), f"hubs-{name}"))
    inter = F.size(F.array_intersect("fa", "fb"))
    both = sent.join(hubs, "b")
    links = scratch.save(both.filter(100 * inter >= percent * (F.size("fa") + F.size("fb") - inter)).select("a", "b"), f"links-{name}")
    scratch.drop(f"close-{name}", f"asked-{name}", f"hubs-{name}")
    return links


def _possible(size_a: Column, own_a: Column, size_b: Column, own_b: Column, percent: int) -> Column:
    """Whether sets of these sizes can reach the threshold when ``own`` members of each lie in no other set."""
    most = F.least(size_a - own_a, size_b - own_b)
    return 100 * most >= percent * (size_a + size_b - most)


def _hubs(hits: DataFrame, keep: int) -> DataFrame:
    """The ``keep`` partners b that meet each a most often."""
    counted = hits.groupBy("a", "b").agg(F.count(F.lit(1)).alias("hits"))
    best = counted.groupBy("a").agg(F.slice(F.sort_array(F.collect_list(F.struct((-F.col("hits")).alias("minus"), "b"))), 1, keep).alias("h"))
    return best.select("a", F.explode("h").alias("h")).select("a", "h.b")


def _mixed(scratch: Scratch, placed: DataFrame, name: str) -> DataFrame:
    """Rows of the lists that hold several components, with the list's largest one as ``main``. A hot list's rows stay in place."""
    placed = scratch.save(placed, f"placed-{name}")
    per_root = placed.groupBy("token", "root").agg(F.count(F.lit(1)).alias("c"))
    main = per_root.groupBy("token").agg(F.count(F.lit(1)).alias("roots"), F.sum("c").alias("rows"), F.max(F.struct("c", (-F.col("root")).alias("minus"))).alias("m"))
    several = scratch.save(main.filter("roots > 1").select("token", "rows", (-F.col("m.minus")).alias("main")), f"several-{name}")
    return looked_up(placed, several, "token", "rows")


def _met(scratch: Scratch, left: DataFrame, sides: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) between classes of different roots that stand in lists of one largest component ``main``.

    For each main, rows outside it meet all rows: both sides are dealt into blocks of about BLOCK_SHINGLES by a hash,
    and every pair of blocks is counted in a task of its own. Full sets go to their blocks from where they lie.
    """
    side = left.withColumn("odd", F.col("root") != F.col("main"))
    size = side.groupBy("main").agg(F.sum("n").alias("all_n"), F.sum(F.when(F.col("odd"), F.col("n"))).alias("odd_n")).filter("odd_n > 0")
    blocks = size.select("main", F.ceil(F.col("all_n") / BLOCK_SHINGLES).alias("all_b"), F.ceil(F.col("odd_n") / BLOCK_SHINGLES).alias("odd_b"))
    dealt = side.join(blocks, "main").withColumn("h", F.xxhash64("id"))
    to = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), n - 1))
    asking = dealt.filter("odd").select("id", "main", "root", F.lit(True).alias("asks"), F.pmod("h", "odd_b").alias("x"), to(F.col("all_b")).alias("y"))
    asked = dealt.select("id", "main", "root", F.lit(False).alias("asks"), to(F.col("odd_b")).alias("x"), F.pmod("h", "all_b").alias("y"))
    listing = asking.unionByName(asked)
    rows = met_in_place(sides.select("id", "found", F.col("id").alias("row")), "row", listing, listed(scratch, listing, "blocks"))

    def run(block: pa.Table) -> pa.Table:
        return _count_block(block, percent)

    return rows.groupBy("main", "x", "y").applyInArrow(run, "a long, b long").distinct()


def _count_block(rows: pa.Table, percent: int) -> pa.Table:
    """Shared shingles of every asking and asked class of a block, by an inverted list of the asking ones."""
    asks = rows["asks"].to_numpy(zero_copy_only=False)
    ids, roots = rows["id"].to_numpy(), rows["root"].to_numpy()
    sets = rows["found"].combine_chunks()
    values, ends = sets.flatten().to_numpy(), np.concatenate([[0], np.cumsum(sets.value_lengths().to_numpy())])
    ours, theirs = np.flatnonzero(asks), np.flatnonzero(~asks)
    sizes = np.diff(ends)
    held = np.concatenate([values[ends[i] : ends[i + 1]] for i in ours]) if len(ours) else values[:0]
    owner = np.repeat(np.arange(len(ours)), sizes[ours])
    order = np.argsort(held, kind="stable")
    held, owner = held[order], owner[order]
    a, b = [], []
    for i in theirs:
        mine = values[ends[i] : ends[i + 1]]
        low, high = np.searchsorted(held, mine), np.searchsorted(held, mine, side="right")
        runs = high - low
        spots = np.repeat(low - np.cumsum(runs) + runs, runs) + np.arange(runs.sum())
        inter = np.bincount(owner[spots], minlength=len(ours))
        close = np.flatnonzero((100 * inter >= percent * (sizes[ours] + sizes[i] - inter)) & (roots[ours] != roots[i]))
        a += ids[ours[close]].tolist()
        b += [int(ids[i])] * len(close)
    return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})


def _named_rows(scratch: Scratch, rows: DataFrame, width: int, percent: int, agree: int) -> DataFrame:
    """row, doc_id, n_shingles, root, component_id of every row of ``rows`` (row, doc_id, text); root: a row number of the component, null without words."""
    signed = scratch.save(rows.mapInArrow(partial(_sign, width=width), _SIGNED), "signed")
    # aggregates of fixed size only, so that copies collapse in hash aggregation before the shuffle; a class goes by the number of its first row
    heads = scratch.save(signed.filter("key is not null").groupBy("key").agg(F.min("row").alias("id"), F.min("doc_id").alias("low"), F.count(F.lit(1)).alias("rows")), "heads")
    classes = scratch.save(
        signed.filter("key is not null").join(heads.select(F.col("id").alias("row")), "row", "left_semi").select(F.col("row").alias("id"), F.col("n_shingles").alias("n"), "key", "signature"), "classes"
    )
    posted = classes.select("id", "n", F.posexplode("signature").alias("place", "value")).select("id", "n", (F.shiftleft(F.col("place").cast("long"), 32) + F.col("value").bitwiseAND(F.lit(0xFFFFFFFF).cast("long"))).alias("token"))
    shared = posted.groupBy("token").agg(F.count(F.lit(1)).alias("held"), F.min("id").alias("hub")).filter("held > 1")
    lists = posted.join(shared, "token").groupBy("id").agg(F.first("n").alias("n"), F.sort_array(F.collect_list(F.struct("held", "token", "hub"))).alias("tokens"))
    reach = F.greatest(F.lit(0), F.lit(1 - agree) + F.size("tokens"))  # coordinates less those held alone, less agree, plus 1
    ranked = scratch.save(lists.filter(F.size("tokens") >= agree).select("id", "n", F.slice("tokens", F.lit(1), reach).alias("tokens")), "ranked")
    prefixes = ranked.select("id", "n", F.explode("tokens").alias("t")).select("id", "n", "t.token", "t.hub")
    # first merge: hubs of each class
    stars = scratch.save(_hubs(prefixes.filter("hub <> id").select(F.col("id").alias("a"), F.col("hub").alias("b")), 2), "stars")
    wanted = prefixes.groupBy("token").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").select("token")
    active = prefixes.join(wanted, "token").select("id").unionByName(stars.select(F.col("a").alias("id"))).unionByName(stars.select(F.col("b").alias("id"))).distinct()
    # full sets of these classes, made where their texts lie
    run = partial(_sets_of, width=width, lists=listed(scratch, active, "active"))
    sides = scratch.save(signed.select("row", "signature", "text").mapInArrow(run, "id long, signature array<int>, found array<long>"), "sides")
    first = _linked(scratch, stars, sides, agree, percent, "1")
    roots = scratch.save(components(scratch, first, "early"), "roots-1")
    mixed = scratch.save(_mixed(scratch, prefixes.select("id", "n", "token").join(roots, "id", "left").withColumn("root", F.coalesce("root", "id")), "1").drop("rows"), "mixed-1")
    # shingles that one class in question has alone
    asked = mixed.select("id").distinct()
    in_question = rows_of(sides.select("id", "found", F.col("id").alias("row")), "row", listed(scratch, asked, "in-question"))
    alone = in_question.select("id", F.explode("found").alias("g")).groupBy("g").agg(F.count(F.lit(1)).alias("c"), F.min("id").alias("id")).filter("c = 1")
    owned = asked.join(alone.groupBy("id").agg(F.count(F.lit(1)).alias("own")), "id", "left").select("id", F.coalesce("own", F.lit(0)).alias("own"))
    known = scratch.save(owned, "known")
    # second merge: the plainest class of each list
    weighed = scratch.save(mixed.join(known.select("id", "own"), "id"), "weighed")
    plain = scratch.save(weighed.groupBy("token").agg(F.min(F.struct("own", "id", "root", "n")).alias("p"), F.count(F.lit(1)).alias("rows")), "plain")
    toward = looked_up(weighed, plain, "token", "rows").filter((F.col("root") != F.col("p.root")) & _possible(F.col("n"), F.col("own"), F.col("p.n"), F.col("p.own"), percent))
    nearer = scratch.save(_hubs(toward.select(F.col("id").alias("a"), F.col("p.id").alias("b")), 4), "pairs-2")
    second = _linked(scratch, nearer, sides, agree, percent, "2")
    merged = scratch.save(components(scratch, first.unionByName(second), "middle"), "roots-2")
    # last merge: all that may still be linked
    left = _mixed(scratch, mixed.select("id", "n", "token").join(merged, "id", "left").withColumn("root", F.coalesce("root", "id")), "2").join(known, "id")
    left = scratch.save(left.filter(100 * (F.col("n") - F.col("own")) >= percent * F.col("n")).groupBy("main", "id", "n", "root").agg(F.count(F.lit(1)).alias("lists")), "mixed-2")
    third = scratch.save(_met(scratch, left, sides, percent), "links-3")
    named = scratch.save(components(scratch, first.unionByName(second).unionByName(third), "late"), "roots-3")
    # components by their smallest doc_id; a hot class or component is not joined in one task
    rooted = scratch.save(heads.join(named, "id", "left").select("key", "low", "rows", F.coalesce("root", "id").alias("root")), "rooted")
    lows = rooted.groupBy("root").agg(F.min("low").alias("component_id"), F.count(F.lit(1)).alias("classes"))
    owner = scratch.save(looked_up(rooted.select("key", "rows", "root"), lows, "root", "classes").select("key", "root", "component_id", "rows"), "owner")
    slim = signed.select("row", "doc_id", "n_shingles", "key")
    grouped = looked_up(slim.filter("key is not null"), owner, "key", "rows").select("row", "doc_id", "n_shingles", "root", "component_id")
    wordless = slim.filter("key is null").select("row", "doc_id", "n_shingles", F.lit(None).cast("long").alias("root"), F.col("doc_id").alias("component_id"))
    out = scratch.save(grouped.unionByName(wordless), "rows")
    done = ["signed", "heads", "classes", "ranked", "mixed-1", "mixed-2", "placed-1", "placed-2", "several-1", "several-2", "weighed", "plain", "known", "stars", "active", "in-question", "blocks", "pairs-2", "links-1", "links-2", "links-3", "sides", "roots-1", "roots-2", "roots-3", "rooted", "owner"]
    scratch.drop(*done)
    return out


def near_groups(docs: DataFrame, width: int = 5, percent: int = 80, agree: int = AGREE) -> DataFrame:
    """Groups of near duplicates: doc_id, n_shingles, component_id, kept, for every row.

    A text's set holds the distinct runs of ``width`` words (A-Z lower-cased; words end at a space or tab to carriage
    return); shorter texts are one run; texts without words, null ones too, are linked with nothing. Two texts are
    linked when 100 * intersection >= percent * union; a component is what links reach; its id is its smallest doc_id,
    and that row is kept. Repeated rows share a component and are all kept if their id is the smallest. Different texts
    under one id (or under none) are texts like others: rows go by a number of their own. A row with a null doc_id
    never stands for others while its group holds an id; a group without any has a null component_id. Extra columns
    are ignored; an empty table gives no rows.

    1. One scan signs every text; texts with equal sets collapse to one class before anything is joined.
    2. Every class posts itself under its coordinate values; values of one class only are dropped. Values are ordered
       by how many classes hold them, rarest first: two classes that agree on ``agree`` of the coordinates must share
       one of each other's first COORDINATES - agree + 1, so only these are merged. With ``agree=1`` every list is
       merged whole and a pair is missed only if its signatures agree nowhere.
    3. A first merge links each class with the least classes of its lists (at most two), chosen by shared values; in
       lists that still hold several components a second one does so with the class of fewest shingles of its own
       (likely what the others were copied from). These links are linear in the classes.
    4. A last merge takes what is left, without loss: classes outside the largest component of a list are counted
       against all classes of the lists with that largest component, in blocks of bounded size that hold full sets
       and give links only. Two unlinked components have a member outside the largest one, so no link between
       components is missed, and no list is expanded into its pairs. A class whose own shingles (held by no other
       class in question) leave too few for the threshold has no partner.
    5. Pairs of the first two merges must agree on ``agree`` coordinates, then are confirmed on full sets, which are
       built for classes with a candidate only, where their texts lie.
    """
    scratch = Scratch(docs.sparkSession, "near")
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    out = _named_rows(scratch, rows, width, percent, agree)
    return out.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def _sets_of(batches: Iterator[pa.RecordBatch], width: int, lists: str) -> Iterator[pa.RecordBatch]:
    """Full sets of the listed rows."""
    test = picked(lists)
    for batch in batches:
        for chosen, texts in text_rows(iter([batch.filter(pa.array(test(batch.column(0).to_numpy())))])):
            sets = pa.array([shingles(_words(x), width).view(np.int64) for x in texts], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([chosen.column(0), chosen.column(1), sets], ["id", "signature", "found"])


def drop_near_copies(docs: DataFrame, width: int = 5, percent: int = 80, agree: int = AGREE) -> DataFrame:
    """One row of every group of near duplicates, with all columns; rows without words all stay.

    Of a group's rows with its smallest doc_id (all rows, if none has an id) the first of the table stays. Groups are of
    rows, not of ids: rows of one id with unlike texts lie in different groups.
    """
    scratch = Scratch(docs.sparkSession, "near-drop")
    saved, row = numbered(scratch, docs, "docs")
    found = _named_rows(scratch, saved.select(F.col(row).alias("row"), F.col("doc_id").cast("long").alias("doc_id"), "text"), width, percent, agree)
    first = found.filter("root is not null and doc_id <=> component_id").groupBy("root").agg(F.min("row").alias("row")).select("row")
    lists = listed(scratch, found.filter("root is null").select("row").unionByName(first), "kept")
    scratch.drop("rows")
    return rows_of(saved, row, lists)


def op6_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its component of near duplicates on runs of four words."""
    return near_groups(table(spark, sf_dir, "documents", "doc_id", "text"), width=4)


OP6_SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w
  FROM documents),
sets AS (
  SELECT doc_id, list_distinct(list_transform(range(1, greatest(2, len(w) - 2)), lambda i: array_to_string(w[i:i + 3], ' '))) AS s
  FROM words WHERE len(w) > 0),
sized AS (SELECT doc_id, len(s) AS n, s FROM sets),
flat AS (SELECT doc_id, n, unnest(s) AS g FROM sized),
meet AS (
  SELECT a.doc_id AS a, b.doc_id AS b, a.n AS na, b.n AS nb, count(*) AS i
  FROM flat a JOIN flat b ON a.g = b.g AND a.doc_id <> b.doc_id AND 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n)
  GROUP BY 1, 2, 3, 4),
links AS (SELECT a, b FROM meet WHERE 100 * i >= 80 * (na + nb - i)),
reach(id, other) AS (
  SELECT doc_id, doc_id FROM documents
  UNION
  SELECT r.id, l.b FROM reach r JOIN links l ON r.other = l.a)
SELECT d.doc_id, coalesce(z.n, 0) AS n_shingles, c.component_id, d.doc_id = c.component_id AS kept
FROM documents d
JOIN (SELECT id, min(other) AS component_id FROM reach GROUP BY id) c ON c.id = d.doc_id
LEFT JOIN sized z ON z.doc_id = d.doc_id
"""
