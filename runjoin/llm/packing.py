"""Sequences of bounded length: first-fit decreasing on a tournament tree, in randomised groups of documents."""

from __future__ import annotations

import zlib
from array import array
from collections.abc import Iterator
from functools import lru_cache, partial

import numpy as np
import pandas as pd
import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import CACHED_CHARS, Scratch, Splitter, byte_level, odd_characters, table, text_rows

#: Rest pieces a group holds on average; small enough for one task, large enough for tight bins.
GROUP_PIECES = 2048


class Pieces(dict):
    """Short pre-token to the bytes of its ids by the tokenizers library; forgotten when full.

    The library splits by the same pattern and merges inside each match only, so a text's ids are those of its matches;
    these go to the library's model directly, in its byte letters.
    """

    def __init__(self, path: str, odd: dict[int, str], room: int = 500_000) -> None:
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.encode_special_tokens = True
        self.model = self.library.model
        self.split = Splitter(public_tokenizers.PATTERN, odd)
        self.room = room

    def __missing__(self, piece: str) -> bytes:
        packed = array("I", [t.id for t in self.model.tokenize(byte_level(piece))]).tobytes()
        if len(piece) <= CACHED_CHARS:
            if len(self) >= self.room:
                self.clear()
            self[piece] = packed
        return packed

    def encode(self, text: str) -> bytes:
        return b"".join(map(self.__getitem__, self.split(text)))


@lru_cache(maxsize=1)
def odd_of_library() -> dict[int, str]:
    """Characters that the tokenizers library's pattern engine sees otherwise than ours; two seconds, on the driver."""
    from tokenizers import Regex, pre_tokenizers

    return odd_characters(lambda pattern, text: {x for x, _ in pre_tokenizers.Split(Regex(pattern), "removed", invert=True).pre_tokenize_str(text)})


_CODERS: dict[str, Pieces] = {}


def pieces_of(path: str, odd: dict[int, str] | None = None) -> Pieces:
    """One coder a process and vocabulary."""
    if path not in _CODERS:
        _CODERS[path] = Pieces(path, odd_of_library() if odd is None else odd)
    return _CODERS[path]


class Bins:
    """Tournament tree over the room left in bins: finds the first bin with enough room in log time."""

    def __init__(self, n: int, capacity: int) -> None:
        self.width = 1 << max(0, (n - 1).bit_length())
        self.room = [capacity] * (2 * self.width)

    def place(self, size: int) -> tuple[int, int]:
        """Put ``size`` into the leftmost bin that takes it; returns the bin and the room it had."""
        room, node = self.room, 1
        while node < self.width:
            node *= 2
            if room[node] < size:
                node += 1
        had = room[node]
        room[node] = had - size
        place = node - self.width
        node //= 2
        while node:
            room[node] = max(room[2 * node], room[2 * node + 1])
            node //= 2
        return place, had


def first_fit_decreasing(sizes: list[int], capacity: int) -> list[tuple[int, int]]:
    """Bin and offset of every item, largest items first, ties in the order given."""
    out, tree = [(0, 0)] * len(sizes), Bins(len(sizes), capacity)
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        place, had = tree.place(sizes[i])
        out[i] = (place, capacity - had)
    return out


def _cut(batches: Iterator[pa.RecordBatch], path: str, odd: dict[int, str], end_id: int, limit: int) -> Iterator[pa.RecordBatch]:
    """Pieces of every document: full ones of ``limit`` ids, then the rest."""
    coder, end = pieces_of(path, odd), np.array([end_id], dtype="<u4").tobytes()
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
    for batch, texts in text_rows(batches):
        rows = []
        for doc_id, text in zip(batch.column(0).to_pylist(), texts, strict=True):
            ids = coder.encode(text) + end
            for at in range(0, len(ids), 4 * limit):
                piece = ids[at : at + 4 * limit]
                rows.append((doc_id, at // 4, len(piece) // 4, zlib.crc32(piece), len(ids) // 4))
        columns = list(zip(*rows, strict=True)) or [()] * 5
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names)


def _pack(group: pd.DataFrame, limit: int) -> pd.DataFrame:
    group = group.sort_values(["length", "doc_id", "start", "ids_crc32"], ascending=[False, True, True, True], kind="stable")
    placed = first_fit_decreasing(group["length"].tolist(), limit)
    group["sequence_id"] = (group["pack"].to_numpy() << 24) + np.array([b for b, _ in placed], dtype=np.int64)
    group["offset"] = np.array([o for _, o in placed], dtype=np.int64)
    return group.drop(columns="pack")


def pack(docs: DataFrame, limit: int = 1024, end_id: int = 0, path: str | None = None, group_pieces: int = GROUP_PIECES) -> DataFrame:
    """Cut documents into pieces and lay these into sequences of at most ``limit`` ids.

    Returns a row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset. A document longer than
    ``limit`` gives full pieces, each a sequence of its own, and a rest. Rests are dealt by a hash of their id and
    content into groups of about ``group_pieces``, and every group is packed alone by first-fit decreasing; the
    number of groups follows the number of rests. A null or empty text is its end id alone; repeated rows are packed
    each; a null doc_id is kept; extra columns are ignored; an empty table gives no pieces.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "packing")
    run = partial(_cut, path=path or public_tokenizers.path("byte_bpe_50k.json"), odd=odd_of_library(), end_id=end_id, limit=limit)
    pieces = scratch.save(docs.select("doc_id", "text").mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"), "pieces")
    rests = pieces.filter(F.col("length") < limit)
    groups = -(-rests.count() // group_pieces) or 1
    dealt = rests.withColumn("pack", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32", F.monotonically_increasing_id() % 64), F.lit(groups)) + 1)

    def lay(group: pd.DataFrame) -> pd.DataFrame:
        return _pack(group, limit)

    packed = dealt.groupBy("pack").applyInPandas(lay, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
    full = pieces.filter(F.col("length") == limit).withColumns({"sequence_id": -1 - F.monotonically_increasing_id(), "offset": F.lit(0).cast("long")})
    return scratch.last(packed.unionByName(full), "pieces")


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of 1024."""
    return pack(table(spark, sf_dir, "documents", "doc_id", "text"))
