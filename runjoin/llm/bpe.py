"""Byte-level BPE by two tiers: a minimal perfect hash for whole pre-tokens, a heap over linked bytes for the rest."""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterator
from functools import lru_cache, partial
from heapq import heapify, heappop, heappush

import numpy as np
import public_tokenizers
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession

from .common import CACHED_CHARS, Splitter, odd_characters, table, text_rows

_MASK = (1 << 64) - 1
_MIX = 0x9E3779B97F4A7C15


class PerfectHash:
    """Minimal perfect hash of byte strings: n keys fill n slots, one probe and one comparison a look-up.

    Keys are thrown into groups by one half of a 64-bit hash; large groups first try seeds until all their keys fall
    on free slots; groups of one key then take the slots left over, their seed naming the slot itself.
    """

    def __init__(self, keys: list[bytes], load: int = 4) -> None:
        n = len(keys)
        self.n, self.groups = n, max(1, n // load)
        hashes = [xxhash.xxh3_64_intdigest(k) for k in keys]
        members: list[list[int]] = [[] for _ in range(self.groups)]
        for i, h in enumerate(hashes):
            members[(h >> 32) % self.groups].append(i)
        self.seeds, self.slots = [0] * self.groups, [-1] * n
        order = sorted(range(self.groups), key=lambda g: -len(members[g]))
        for g in order:
            if len(members[g]) < 2:
                break
            seed = 1
            while True:
                at = {self._slot(hashes[i], seed) for i in members[g]}
                if len(at) == len(members[g]) and all(self.slots[s] < 0 for s in at):
                    break
                seed += 1
            self.seeds[g] = seed
            for i in members[g]:
                self.slots[self._slot(hashes[i], seed)] = i
        free = iter([s for s in range(n) if self.slots[s] < 0])
        for g in order:
            if len(members[g]) == 1:
                s = next(free)
                self.seeds[g], self.slots[s] = -s - 1, members[g][0]
        self.keys = keys

    def _slot(self, h: int, seed: int) -> int:
        return (((h ^ (seed * _MIX)) * 0xD6E8FEB86659FD93 & _MASK) >> 32) * self.n >> 32

    def find(self, key: bytes) -> int:
        """The key's number, or -1."""
        if not self.n:
            return -1
        h = xxhash.xxh3_64_intdigest(key)
        seed = self.seeds[(h >> 32) % self.groups]
        i = self.slots[-seed - 1 if seed < 0 else self._slot(h, seed)]
        return i if i >= 0 and self.keys[i] == key else -1


class ByteBpe(dict):
    """Encoder and decoder of one rank file. As a dictionary: short pre-token to its ids' bytes, forgotten when full."""

    def __init__(self, path: str, pattern: str, odd: dict[int, str], room: int = 500_000) -> None:
        with open(path, "rb") as lines:
            pairs = [line.split() for line in lines if line.strip()]
        self.ranks = {base64.b64decode(a): int(b) for a, b in pairs}
        self.words = PerfectHash(list(self.ranks))
        self.rank_of = list(self.ranks.values())
        self.bytes_of = {r: b for b, r in self.ranks.items()}
        self.split = Splitter(pattern, odd)
        self.room = room

    def __missing__(self, piece: str) -> bytes:
        raw = piece.encode()
        hit = self.words.find(raw)
        ids = [self.rank_of[hit]] if hit >= 0 else self.merge(raw)
        packed = array("I", ids).tobytes()
        if len(piece) <= CACHED_CHARS:
            if len(self) >= self.room:
                self.clear()
            self[piece] = packed
        return packed

    def merge(self, raw: bytes) -> list[int]:
        """Merge the adjacent pair of lowest rank, leftmost first, until none is in the vocabulary.

        Bytes are a doubly linked list of spans; the heap holds (rank, start) of pairs and drops stale ones on sight:
        n log n for a pre-token of any length.
        """
        n, get = len(raw), self.ranks.get
        after, before = list(range(1, n + 2)), list(range(-1, n))
        pair = [get(raw[i : i + 2]) for i in range(n - 1)] + [None]
        heap = [(r, i) for i, r in enumerate(pair) if r is not None]
        heapify(heap)
        while heap:
            rank, i = heappop(heap)
            if pair[i] != rank:
                continue
            j = after[i]
            end = after[j]
            pair[j], after[i] = None, end
            pair[i] = None
            if end < n:
                before[end] = i
                if (r := get(raw[i : after[end]])) is not None:
                    pair[i] = r
                    heappush(heap, (r, i))
            if (p := before[i]) >= 0:
                pair[p] = r = get(raw[p:end])
                if r is not None:
                    heappush(heap, (r, p))
        ids, i = [], 0
        while i < n:
            ids.append(self.ranks[raw[i : after[i]]])
            i = after[i]
        return ids

    def encode(self, text: str) -> bytes:
        """Ids of a whole text as little-endian unsigned 32-bit integers."""
        return b"".join(map(self.__getitem__, self.split(text)))

    def decode(self, ids: bytes) -> bytes:
        """Bytes of the text that the ids stand for."""
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))


@lru_cache(maxsize=1)
def _odd() -> dict[int, str]:
    """Characters that the tiktoken library's pattern engine sees otherwise than ours; found in a tenth of a second."""
    import tiktoken

    def matched(pattern: str, text: str) -> set[str]:
        single = tiktoken.Encoding("bytes", pat_str=pattern, mergeable_ranks={bytes([b]): b for b in range(256)}, special_tokens={})
        return set(bytes(single.encode_ordinary(text)).decode())

    return odd_characters(matched)


@lru_cache(maxsize=2)
def coder(path: str, pattern: str) -> ByteBpe:
    """One coder a worker process."""
    return ByteBpe(path, pattern, _odd())


def _digests(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    bpe = coder(path, pattern)
    for batch, texts in text_rows(batches):
        rows = []
        for text in texts:
            ids = bpe.encode(text)
            rows.append((len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(bpe.decode(ids)).hexdigest()))
        columns = list(zip(*rows, strict=True)) or [(), (), ()]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.string()), pa.array(columns[2], pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])


def _ids(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    bpe = coder(path, pattern)
    for batch, texts in text_rows(batches):
        ids = [np.frombuffer(bpe.encode(x), dtype="<i4") for x in texts]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])


def _texts(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    bpe = coder(path, pattern)
    for batch in batches:
        raw = [bpe.decode(np.array(x or [], dtype="<u4").tobytes()) for x in batch.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x.decode("utf-8", "replace") for x in raw], pa.string())], ["doc_id", "text"])


def default_ranks() -> str:
    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def encode(docs: DataFrame, path: str | None = None, pattern: str = public_tokenizers.PATTERN) -> DataFrame:
    """doc_id and ids (array of int) of every whole text; null and empty texts give an empty array.

    Rows stay where they are (no shuffle); ties and repeated rows are rows like others; extra columns are ignored.
    """
    return docs.select("doc_id", "text").mapInArrow(partial(_ids, path=path or default_ranks(), pattern=pattern), "doc_id long, ids array<int>")


def decode(ids: DataFrame, path: str | None = None, pattern: str = public_tokenizers.PATTERN) -> DataFrame:
    """doc_id and text of arrays of ids; a null array gives an empty text, an id out of the vocabulary an error."""
    return ids.select("doc_id", "ids").mapInArrow(partial(_texts, path=path or default_ranks(), pattern=pattern), "doc_id long, text string")


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document encoded and decoded again: counts and digests."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    run = partial(_digests, path=default_ranks(), pattern=public_tokenizers.PATTERN)
    return docs.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
