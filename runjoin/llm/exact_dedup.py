"""Exact duplicates through an extendible-hash index kept on shared files."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, listed, numbered, picked, rows_of, table, text_rows, unused

#: Bits of a key, and of its longest prefix in the directory, which bounds the directory and the histogram the driver reads.
KEY_BITS, MAX_DEPTH = 60, 16
#: Bytes of texts that a scanning task holds to collapse copies before it writes its classes.
ROOM = 32 << 20
#: Bits of a class's number below the number of its task.
CLASS_BITS = 36
_BLANKS = b" \t\n\x0b\x0c\r"


def directory(counts: dict[int, int], capacity: int, max_depth: int = MAX_DEPTH) -> tuple[int, np.ndarray]:
    """Grow an extendible-hash directory over key-prefix counts.

    ``counts``: entries for each prefix of ``max_depth`` bits. Buckets over ``capacity`` are split on their next
    bit; a bucket as deep as the directory first doubles it. Returns the global depth and, for every directory
    slot, its bucket number (buckets are numbered in key order, so each owns one range of keys). A bucket that
    ``max_depth`` bits can't split stays overfull: its owner task streams it.
    """
    below = np.zeros(1 << max_depth, dtype=np.int64)
    for prefix, n in counts.items():
        below[prefix] = n
    total = np.concatenate([[0], np.cumsum(below)])
    depth, slots = 0, [(0, 0)]  # slot: (local depth, prefix of that many bits)
    pending = [(0, 0)]
    while pending:
        local, prefix = pending.pop()
        first, width = prefix << (max_depth - local), 1 << (max_depth - local)
        if local == max_depth or total[first + width] - total[first] <= capacity:
            continue
        if local == depth:  # double: each slot is written twice
            slots = [bucket for bucket in slots for _ in (0, 1)]
            depth += 1
        halves = [(local + 1, prefix << 1), (local + 1, prefix << 1 | 1)]
        run = 1 << (depth - local - 1)
        at = prefix << (depth - local)
        slots[at : at + 2 * run] = [halves[0]] * run + [halves[1]] * run
        pending += halves
    numbers = {bucket: i for i, bucket in enumerate(dict.fromkeys(slots))}
    return depth, np.array([numbers[b] for b in slots], dtype=np.int64)


_SCAN = "key long, ref long, row long, doc_id long, size long, n long, digest binary, plain binary"
_SCAN_ARROW = pa.schema([(x.split()[0], pa.int64() if x.endswith("long") else pa.binary()) for x in _SCAN.split(", ")])


def _rank(doc_id: int | None, size: int, row: int) -> tuple:
    """Larger for the row that stays."""
    return size, doc_id is not None, -(doc_id or 0), -row


def _collapse(batches: Iterator[pa.RecordBatch], key_bits: int, room: int) -> Iterator[pa.RecordBatch]:
    """A member row (no key) for each document, and an entry (with key) for each class of equal texts that the task met.

    Texts of one digest are compared by their bytes. Classes are written whenever their texts exceed ``room``.
    """
    task = TaskContext.get().partitionId() << CLASS_BITS
    classes: dict[bytes, list[list]] = {}
    made, held = 0, 0

    def entries() -> Iterator[pa.RecordBatch]:
        whole = [(digest, *c) for digest, chain in classes.items() for c in chain]
        classes.clear()
        for at in range(0, len(whole), 4096):
            digests, plains, refs, counts, ids, sizes, rows, _ = zip(*whole[at : at + 4096], strict=True)
            keys = [int.from_bytes(d[:8], "big") >> 64 - key_bits for d in digests]
            yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip((keys, refs, rows, ids, sizes, counts, digests, plains), _SCAN_ARROW, strict=True)], schema=_SCAN_ARROW)

    for batch, texts in text_rows(batches):
        ids, rows, refs, sizes = batch.column(1).to_pylist(), batch.column(0).to_pylist(), [], []
        for doc_id, row, text in zip(ids, rows, texts, strict=True):
            plain = text.encode().translate(None, _BLANKS)
            chain = classes.setdefault(hashlib.sha256(plain).digest(), [])
            rank = _rank(doc_id, len(text), row)
            found = next((c for c in chain if c[0] == plain), None)
            if found is None:
                found = [plain, task | made, 0, doc_id, len(text), row, rank]
                chain.append(found)
                made, held = made + 1, held + len(plain) + 400
            found[2] += 1
            if rank > found[6]:
                found[3:] = [doc_id, len(text), row, rank]
            refs.append(found[1])
            sizes.append(len(text))
        none = pa.nulls(len(refs), pa.int64())
        empty = pa.nulls(len(refs), pa.binary())
        members = [none, pa.array(refs, pa.int64()), batch.column(0), pa.array(ids, pa.int64()), pa.array(sizes, pa.int64()), none, empty, empty]
        yield pa.RecordBatch.from_arrays(members, schema=_SCAN_ARROW)
        if held > room:
            yield from entries()
            held = 0
    yield from entries()


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Classes whose key another class of the owner's range has too. Rows come by key."""
    last_key, last_ref, told = None, None, False
    for batch in batches:
        out = []
        for key, ref in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if key == last_key:
                out += [ref] if told else [last_ref, ref]
                told = True
            else:
                told = False
            last_key, last_ref = key, ref
        yield pa.RecordBatch.from_arrays([pa.array(out, pa.int64())], ["ref"])


def _with_texts(batches: Iterator[pa.RecordBatch], lists: str) -> Iterator[pa.RecordBatch]:
    """Entries as they are, but the texts of classes that are not listed stay behind."""
    test = picked(lists, CLASS_BITS)
    at = _SCAN_ARROW.get_field_index("plain")
    for batch in batches:
        plain = batch.column(at)
        wanted = pa.array(test(batch.column(1).to_numpy()))
        kept = pa.array([x if w else None for x, w in zip(plain, wanted.to_pylist(), strict=True)], pa.binary()) if wanted.true_count else pa.nulls(len(plain), pa.binary())
        yield pa.RecordBatch.from_arrays([*batch.columns[:at], kept], schema=_SCAN_ARROW)


def _own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """An owner walks its range in key order. The classes of one key form a chain of links, each a different text.

    A class joins the link whose bytes equal its own; the link sums sizes of groups and keeps the best row. Held at a
    time: one text a link and two numbers a class of the key at hand.
    """
    names = ["ref", "group", "link", "keep_id", "keep_size", "group_size", "digest"]
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
    done: list[tuple] = []
    key, chain, refs = None, [], []

    def close() -> None:
        for ref, place in refs:
            _, digest, n, doc_id, size, _, group = chain[place]
            done.append((ref, group, place, doc_id, size, n, digest))

    def told() -> pa.RecordBatch:
        out = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*done, strict=True)) or [()] * 7, kinds, strict=True)], names)
        done.clear()
        return out

    for whole in batches:
        for at in range(0, whole.num_rows, 1024):
            for k, ref, row, doc_id, size, n, digest, plain in zip(*(c.to_pylist() for c in whole.slice(at, 1024).columns), strict=True):
                if k != key:
                    close()
                    key, chain, refs = k, [], []
                rank = _rank(doc_id, size, row)
                place = next((i for i, link in enumerate(chain) if link[0] == plain), None)
                if place is None:
                    place = len(chain)
                    chain.append([plain, digest, 0, doc_id, size, rank, ref])
                link = chain[place]
                link[2] += n
                if rank > link[5]:
                    link[3:6] = [doc_id, size, rank]
                refs.append((ref, place))
            if len(done) > 20_000:
                yield told()
    close()
    yield told()


def _index(scratch: Scratch, rows: DataFrame, bucket_entries: int, key_bits: int, room: int) -> tuple[DataFrame, DataFrame]:
    """Members (ref, row, doc_id, size) and the index (ref, group, link, keep_id, keep_size, group_size, digest). ``rows``: row, doc_id, text."""
    spark = rows.sparkSession
    scan = scratch.save(rows.mapInArrow(partial(_collapse, key_bits=key_bits, room=room), _SCAN), "scan")
    entries = scan.filter("key is not null")
    top = min(MAX_DEPTH, key_bits)
    prefix = F.shiftright("key", key_bits - top).cast("int")
    histogram = {r[0]: r[1] for r in entries.groupBy(prefix.alias("p")).count().collect()}  # 2^16 rows at most
    depth, slots = directory(histogram, max(bucket_entries, sum(histogram.values()) >> (MAX_DEPTH - 2)), top)
    bucket_of = F.broadcast(spark.createDataFrame([(i, int(b)) for i, b in enumerate(slots)], "slot int, bucket long"))
    owners = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))

    def owned(df: DataFrame, *columns: str) -> DataFrame:
        placed = df.withColumn("slot", F.shiftright("key", key_bits - depth).cast("int")).join(bucket_of, "slot")
        return placed.repartition(owners, "bucket").sortWithinPartitions("bucket", "key", "ref").select(*columns)

    lists = listed(scratch, owned(entries.select("key", "ref"), "key", "ref").mapInArrow(_shared, "ref long"), "shared", CLASS_BITS)
    full = entries.mapInArrow(partial(_with_texts, lists=lists), _SCAN)
    index = scratch.save(owned(full, *_SCAN_ARROW.names).mapInArrow(_own, "ref long, group long, link int, keep_id long, keep_size long, group_size long, digest binary"), "index")
    return scan.filter("key is null").select("ref", "row", "doc_id", "size"), index


def exact_groups(docs: DataFrame, bucket_entries: int = 1024, key_bits: int = KEY_BITS, room: int = ROOM) -> DataFrame:
    """Groups of equal texts: doc_id, keep_id, group_size, kept, text_sha256 for every row.

    Texts are equal when identical after deleting white space (space and tab to carriage return). The row with
    the most code points in its original text stays, then the one with the smallest doc_id. A null text counts
    as empty; empty texts form one group; rows repeated with the same doc_id count as members each and are all
    kept when their id is the one that stays; a null id ranks after all others. Extra columns are ignored; an
    empty table gives an empty result.

    1. Each scanning task collapses equal texts (digest, then bytes) to classes; a hot text costs an entry a task.
    2. The directory of the extendible hash grows from the prefix counts of the entries' keys (the first ``key_bits``
       of the SHA-256): overfull buckets split and double it. Buckets are key ranges; each has one owner task.
    3. Owners first name the classes whose key occurs again; only the texts of these are shuffled.
    4. Owners walk their keys, chain different texts of one key by comparing bytes, and give every class its group's
       size and the row that stays. This index lies on shared files; members meet it by the number of their class,
       of which no number has more rows than a task collapses at a time.
    """
    scratch = Scratch(docs.sparkSession, "exact-index")
    rows = docs.select(F.lit(0).cast("long").alias("row"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    members, index = _index(scratch, rows, bucket_entries, key_bits, room)
    found = members.join(index, "ref").select(
        "doc_id",
        "keep_id",
        "group_size",
        F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )
    return scratch.last(found, "scan", "shared", "index")


def drop_exact_copies(docs: DataFrame, key_bits: int = KEY_BITS) -> DataFrame:
    """One row of every group of equal texts, with all columns of the input, whatever the ids of its rows.

    A group's row is one of its keep_id, the longest of these. Further ties go by the columns in their order, maps
    left out, then by the place of the row, so that task order decides nothing. Rows are told apart by a number of
    their own; texts are read for ties and shuffled for keys that several classes share, and otherwise stay in place.
    """
    scratch = Scratch(docs.sparkSession, "exact-drop")
    saved, row = numbered(scratch, docs, "docs")
    rows = saved.select(F.col(row).alias("row"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    members, index = _index(scratch, rows, 1024, key_bits, ROOM)
    best = members.join(index, "ref").filter(F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("size") == F.col("keep_size"))).select("row", "group")
    best = scratch.save(best, "best")
    counted = scratch.save(best.groupBy("group").agg(F.count(F.lit(1)).alias("n"), F.min("row").alias("row")), "counted")
    tied = best.join(counted.filter("n > 1").select("group"), "group", "left_semi")
    columns = [F.col(f"`{f.name}`") for f in docs.schema.fields if "map<" not in f.dataType.simpleString() and "variant" not in f.dataType.simpleString()]
    place = unused(saved, "place_of_row")
    tied_docs = rows_of(saved.withColumn(place, F.col(row)), row, listed(scratch, tied.select("row"), "tied"))
    ranked = tied_docs.select(F.col(place).alias("row"), F.struct(*columns, place).alias("order")).join(tied, "row")
    first = ranked.groupBy("group").agg(F.min_by("row", "order").alias("row")).select("row")
    lists = listed(scratch, counted.filter("n = 1").select("row").unionByName(first), "kept")
    scratch.drop("scan", "shared", "index", "best", "counted", "tied")
    return rows_of(saved, row, lists)


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its group of equal texts."""
    return exact_groups(table(spark, sf_dir, "documents", "doc_id", "text"))


OP2_SQL = r"""
WITH n AS (
  SELECT doc_id, length(coalesce(text, '')) AS size,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS text_sha256
  FROM documents)
SELECT doc_id,
       first_value(doc_id) OVER (PARTITION BY text_sha256 ORDER BY size DESC, doc_id) AS keep_id,
       count(*) OVER (PARTITION BY text_sha256) AS group_size,
       doc_id = first_value(doc_id) OVER (PARTITION BY text_sha256 ORDER BY size DESC, doc_id) AS kept,
       text_sha256
FROM n
"""
