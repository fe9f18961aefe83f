"""Token ids on disk: frequency-ranked, byte-aligned variable length, control bytes apart from data bytes."""

from __future__ import annotations

import json
import struct
import zlib
from array import array
from collections.abc import Iterator
from functools import lru_cache, partial

import numpy as np
import public_tokenizers
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import CACHED_CHARS, Scratch, byte_level, commit_file, opened, table, text_rows

MAGIC = b"VBYTEID1"
#: Ids of a block after which a new one starts; a block holds whole documents.
BLOCK_IDS = 1 << 19
_LENGTHS = (np.arange(256)[:, None] >> np.array([0, 2, 4, 6]) & 3) + 1


def pack_ids(ranks: np.ndarray) -> tuple[bytes, bytes]:
    """Control bytes (two bits an id: its data bytes less one, four ids a byte) and data bytes (little-endian)."""
    ranks = np.ascontiguousarray(ranks, dtype="<u4")
    size = 1 + (ranks >= 1 << 8).astype(np.uint8) + (ranks >= 1 << 16) + (ranks >= 1 << 24)
    control = np.zeros(-(-len(ranks) // 4) * 4, dtype=np.uint8)
    control[: len(ranks)] = size - 1
    control = control.reshape(-1, 4)
    packed = control[:, 0] | control[:, 1] << 2 | control[:, 2] << 4 | control[:, 3] << 6
    data = ranks.view(np.uint8).reshape(-1, 4)[np.arange(4) < size[:, None]]
    return packed.astype(np.uint8).tobytes(), data.tobytes()


def unpack_ids(control: bytes, data: bytes, n: int) -> np.ndarray:
    """The ranks again: lengths come from a table of all control bytes, bytes are gathered at once."""
    size = _LENGTHS[np.frombuffer(control, dtype=np.uint8)].reshape(-1)[:n]
    start = np.concatenate([[0], np.cumsum(size)[:-1]]) if n else size
    raw = np.frombuffer(data + b"\0\0\0", dtype=np.uint8)
    out = np.zeros(n, dtype=np.uint32)
    for place in range(4):
        out |= np.where(size > place, raw[np.minimum(start + place, len(raw) - 1)], 0).astype(np.uint32) << np.uint32(8 * place)
    return out


class WordPieces(dict):
    """Short chunk without white space to the bytes of its ids by the tokenizers library; forgotten when full.

    The word tokenizer drops white space and merges inside words only, and its normaliser works letter by letter, so
    a text's ids are those of its chunks one after another.
    """

    def __init__(self, path: str, room: int = 900_000) -> None:
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.encode_special_tokens = True
        self.model = self.library.model
        # two bytes an id on the way to the files, if these do
        self.kind = "H" if self.library.get_vocab_size() <= 1 << 16 else "I"
        self.room = room

    def __missing__(self, chunk: str) -> bytes:
        """Ids of a chunk. A-Z are lower-cased as the tokenizer does; a mark after a letter is a word of its own."""
        if not chunk:
            return b""
        plain = chunk.lower() if chunk.isascii() else chunk[0].lower() + chunk[1:] if chunk[0].isascii() else chunk
        if plain != chunk:
            packed = self[plain]
        elif len(chunk) > 1 and chunk[-1] in ".," and chunk[-2].lower().isalpha():
            packed = self[chunk[:-1]] + self[chunk[-1]]
        elif chunk.isalpha() and max(chunk) <= "\xff":  # one word of Latin-1 letters: only its case is normalised
            packed = array(self.kind, [t.id for t in self.model.tokenize(byte_level(chunk.lower()))]).tobytes()
        else:
            packed = array(self.kind, self.library.encode(chunk, add_special_tokens=False).ids).tobytes()
        if len(chunk) <= CACHED_CHARS:
            if len(self) >= self.room:
                self.clear()
            self[chunk] = packed
        return packed

    def encode(self, text: str) -> bytes:
        # Python's white space is the tokenizer's, but for four separators
        odd = any(c in text for c in "\x1c\x1d\x1e\x1f")
        return b"".join(map(self.__getitem__, text.replace("\n", " ").split(" ") if odd else text.split()))


@lru_cache(maxsize=2)
def word_pieces(path: str) -> WordPieces:
    return WordPieces(path)


def _tokenise(batches: Iterator[pa.RecordBatch], path: str, end_id: int) -> Iterator[pa.RecordBatch]:
    coder = word_pieces(path)
    end = array(coder.kind, [end_id]).tobytes()
    for batch, texts in text_rows(batches):
        ids = [coder.encode(x) + end for x in texts]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.binary())], ["doc_id", "ids"])


def _count(batches: Iterator[pa.RecordBatch], kind: str) -> Iterator[pa.RecordBatch]:
    total = np.zeros(0, dtype=np.int64)
    for batch in batches:
        for ids in batch.column(0).to_pylist():
            found = np.bincount(np.frombuffer(ids, dtype=kind))
            if len(found) > len(total):
                total = np.concatenate([total, np.zeros(len(found) - len(total), dtype=np.int64)])
            total[: len(found)] += found
    used = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(used, pa.int64()), pa.array(total[used], pa.int64())], ["id", "n"])


def _block(doc_ids: list[int | None], arrays: list[np.ndarray]) -> bytes:
    ranks = np.concatenate(arrays)
    control, data = pack_ids(ranks)
    index = np.array([0 if d is None else d for d in doc_ids], dtype="<i8").tobytes()
    nulls = np.array([d is None for d in doc_ids], dtype=np.uint8).tobytes()
    lengths = np.array([len(a) for a in arrays], dtype="<i8").tobytes()
    body = index + nulls + lengths + control + data
    return struct.pack("<qqqqI", len(doc_ids), len(ranks), len(control), len(data), zlib.crc32(body)) + body


def _write(batches: Iterator[pa.RecordBatch], base: str, rank_of: np.ndarray, kind: str) -> Iterator[pa.RecordBatch]:
    """One shard a task: blocks of documents in the order they come in (ascending doc_id)."""
    task = TaskContext.get()
    shard, docs, ids = task.partitionId(), 0, 0
    name = f"shard-{shard:06d}.vbyte"

    def blocks(out: pa.NativeFile) -> None:
        nonlocal docs, ids
        out.write(MAGIC)
        held, arrays, size = [], [], 0
        for batch in batches:
            for doc_id, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                held.append(doc_id)
                arrays.append(rank_of[np.frombuffer(raw, dtype=kind)])
                size += len(arrays[-1])
                if size >= BLOCK_IDS:
                    out.write(_block(held, arrays))
                    docs, ids = docs + len(held), ids + size
                    held, arrays, size = [], [], 0
        if held:
            out.write(_block(held, arrays))
            docs, ids = docs + len(held), ids + size

    commit_file(f"{base}/{name}", f"_{name}.{task.taskAttemptId()}", blocks)
    yield pa.RecordBatch.from_pylist([{"shard": shard, "file": name, "n_docs": docs, "n_ids": ids}])


def read_blocks(uri: str) -> Iterator[tuple[list[int | None], np.ndarray, np.ndarray]]:
    """Blocks of one shard: doc ids, lengths and ranks; a damaged block raises ValueError."""
    fs, path = opened(uri)
    with fs.open_input_stream(path, compression=None, buffer_size=1 << 20) as f:
        if f.read(len(MAGIC)) != MAGIC:
            raise ValueError(f"{uri} is not a token shard")
        while head := f.read(36):
            docs, ids, control, data, crc = struct.unpack("<qqqqI", head)
            body = f.read(docs * 17 + control + data)
            if zlib.crc32(body) != crc:
                raise ValueError(f"{uri} holds a damaged block")
            names = np.frombuffer(body, dtype="<i8", count=docs).tolist()
            nulls = np.frombuffer(body, dtype=np.uint8, count=docs, offset=8 * docs)
            lengths = np.frombuffer(body, dtype="<i8", count=docs, offset=9 * docs)
            at = 17 * docs
            yield [None if n else d for d, n in zip(names, nulls, strict=True)], lengths, unpack_ids(body[at : at + control], body[at + control :], ids)


def _read(batches: Iterator[pa.RecordBatch], base: str, id_of: np.ndarray) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for shard in batch.to_pylist():
            at = shard["base"]
            for names, lengths, ranks in read_blocks(f"{base}/{shard['file']}"):
                ids = id_of[ranks]
                ends = np.cumsum(lengths)
                crcs = [zlib.crc32(ids[e - n : e].tobytes()) for e, n in zip(ends.tolist(), lengths.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(at + ends - lengths), pa.array(lengths), pa.array(crcs, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])
                at += int(ends[-1])


def write_ids(docs: DataFrame, uri: str, path: str | None = None, end_id: int = 2) -> None:
    """Tokenise documents and write shards, ranks and a manifest under ``uri``.

    Each document's ids end with ``end_id``; documents lie in ascending doc_id order (null ids first) over the shards
    and inside them. A null or empty text is the end id alone; rows with the same doc_id are neighbours, ordered by
    their ids; extra columns are ignored; an empty table gives a manifest without rows. Ids are replaced by their
    rank in the corpus's own frequencies (counted over all documents; ties by id), so frequent ids take one byte.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "token-ids")
    path = path or public_tokenizers.path("word_bpe_49k.json")
    run, kind = partial(_tokenise, path=path, end_id=end_id), word_pieces(path).kind
    ids = scratch.save(docs.select("doc_id", "text").mapInArrow(run, "doc_id long, ids binary"), "ids")
    counts = ids.select("ids").mapInArrow(partial(_count, kind=kind), "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    order = [r[0] for r in counts.orderBy(F.desc("n"), "id").collect()]  # as many rows as the vocabulary has ids
    id_of = np.array(order, dtype="<u4")
    rank_of = np.zeros(max(order, default=0) + 1, dtype="<u4")
    rank_of[id_of] = np.arange(len(order), dtype="<u4")
    shards = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ordered = ids.repartitionByRange(shards, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "ids")
    written = scratch.save(ordered.mapInArrow(partial(_write, base=uri, rank_of=rank_of, kind=kind), "shard long, file string, n_docs long, n_ids long"), "written")
    manifest, base = [], 0
    for row in written.orderBy("shard").collect():  # one row a shard
        manifest.append(row.asDict() | {"base": base})
        base += row["n_ids"]
    commit_file(f"{uri}/manifest.json", "_manifest.json", lambda out: out.write(json.dumps({"shards": manifest, "id_of_rank": order}).encode()))
    scratch.drop()


def read_ids(spark: SparkSession, uri: str) -> DataFrame:
    """Per document of the files: doc_id, start, n_tokens, ids_crc32 (of the original ids)."""
    fs, path = opened(f"{uri}/manifest.json")
    with fs.open_input_stream(path) as f:
        manifest = json.loads(f.read())
    shards = spark.createDataFrame([(s["shard"], s["file"], s["base"]) for s in manifest["shards"] if s["n_docs"]], "shard long, file string, base long")
    spread = shards.repartitionByRange(max(1, len(manifest["shards"])), "shard")
    run = partial(_read, base=uri, id_of=np.array(manifest["id_of_rank"], dtype="<u4"))
    return spread.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op5_token_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents written to token files and read back."""
    scratch = Scratch(spark, "token-files")
    write_ids(table(spark, sf_dir, "documents", "doc_id", "text"), scratch.path("ids"))
    return scratch.last(read_ids(spark, scratch.path("ids")), "ids")
