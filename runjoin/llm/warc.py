"""Web archives: deterministic sharded writer with duplicate payloads as revisits, and its reader."""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, commit_file, looked_up, opened, table

#: Compressed bytes after which a file is closed; payload bytes from which equal payloads become revisits.
ROLL_BYTES, REVISIT_BYTES = 64 << 20, 1000
#: Ranges of page_id whose payload bytes are counted to cut shards of like size.
RANGES = 4096
#: Payload bytes of a shard before more shards are cut.
SHARD_BYTES = 256 << 20
_EPOCH = "2000-01-01T00:00:00Z"
# Record version and the profile of revisit records in the archive standard.
_VERSION = b"WARC/1.1"
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _sha1(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data, usedforsecurity=False).digest()).decode()


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """One gzip member. A revisit keeps the HTTP head, with the full length and digest, and no payload."""
    revisit = refers_to is not None
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if revisit else http + payload
    name = "none" if page_id is None else str(page_id)
    head = [
        ("WARC-Type", "revisit" if revisit else "response"),
        ("WARC-Record-ID", f"<urn:page:{name}>"),
        ("WARC-Date", _EPOCH),
        ("WARC-Payload-Digest", _sha1(payload)),
        ("WARC-Block-Digest", _sha1(block)),
        ("Content-Type", "application/http; msgtype=response"),
    ]
    if url:
        head.insert(3, ("WARC-Target-URI", url.replace("\r", "%0D").replace("\n", "%0A")))
    if revisit:
        head += [("WARC-Refers-To", f"<urn:page:{refers_to}>"), ("WARC-Profile", _PROFILE)]
    head.append(("Content-Length", str(len(block))))
    lines = _VERSION + b"\r\n" + b"".join(f"{k}: {v}\r\n".encode() for k, v in head) + b"\r\n"
    pack = zlib.compressobj(6, zlib.DEFLATED, 31)
    return pack.compress(lines + block + b"\r\n\r\n") + pack.flush()


def _write(batches: Iterator[pa.RecordBatch], base: str, roll: int) -> Iterator[pa.RecordBatch]:
    """Files of the shards this task owns. Rows come by shard, page and kind: decisions stand before their page."""
    attempt = TaskContext.get().taskAttemptId()
    shard, held, size, number, decided = None, [], 0, 0, (None, {})
    done: list[dict] = []

    def close() -> None:
        nonlocal held, size, number
        if held:
            name = f"part-{shard:06d}-{number:04d}.warc.gz"
            members = held
            commit_file(f"{base}/{name}", f"_{name}.{attempt}", lambda out: [out.write(m) for m in members] and None)
            done.append({"shard": shard, "number": number, "file": name, "n_records": len(held), "n_bytes": size})
            held, size, number = [], 0, number + 1

    for batch in batches:
        for row in batch.to_pylist():
            if row["shard"] != shard:
                close()
                shard, number = row["shard"], 0
            if row["kind"] == 0:
                if decided[0] != row["page_id"]:
                    decided = (row["page_id"], {})
                decided[1][row["digest"]] = row["refers_to"]
                continue
            refers = decided[1].get(row["digest"]) if row["page_id"] is not None and decided[0] == row["page_id"] else None
            held.append(record(row["page_id"], row["url"], (row["html"] or "").encode(), refers))
            size += len(held[-1])
            if size >= roll:
                close()
    close()
    if done:
        yield pa.RecordBatch.from_pylist(done, pa.schema([("shard", pa.int64()), ("number", pa.int64()), ("file", pa.string()), ("n_records", pa.int64()), ("n_bytes", pa.int64())]))


def _members(stream: pa.NativeFile) -> Iterator[bytes]:
    """Plain bytes of each gzip member."""
    rest = b""
    while True:
        pack, parts = zlib.decompressobj(31), []
        while not pack.eof:
            data = rest or stream.read(1 << 20)
            rest = b""
            if not data:
                if parts:
                    raise ValueError("an archive ends inside a record")
                return
            parts.append(pack.decompress(data))
            rest = pack.unused_data
        yield b"".join(parts)


def parse(data: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and block of a record; a damaged one raises ValueError."""
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    fields = dict(line.split(": ", 1) for line in lines[1:])
    block = rest[: int(fields["Content-Length"])]
    if lines[0].encode() != _VERSION or _sha1(block) != fields["WARC-Block-Digest"] or rest[len(block) :] != b"\r\n\r\n":
        raise ValueError("a record is damaged")
    return fields, block


def _page(urn: str | None) -> int | None:
    name = urn[10:-1] if urn else "none"
    return None if name == "none" else int(name)


def _read(batches: Iterator[pa.RecordBatch], base: str) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for name in batch.column(0).to_pylist():
            fs, path = opened(f"{base}/{name}")
            rows = []
            with fs.open_input_stream(path, compression=None) as stream:
                for data in _members(stream):
                    fields, block = parse(data)
                    http, _, payload = block.partition(b"\r\n\r\n")
                    length = int(http.rsplit(b"Content-Length: ", 1)[1].split(b"\r\n")[0])
                    kind = fields["WARC-Type"]
                    if kind == "response" and (len(payload) != length or _sha1(payload) != fields["WARC-Payload-Digest"]):
                        raise ValueError("a payload is damaged")
                    digest = base64.b32decode(fields["WARC-Payload-Digest"][5:]).hex()
                    rows.append((_page(fields["WARC-Record-ID"]), length, digest, kind, _page(fields.get("WARC-Refers-To"))))
            columns = list(zip(*rows, strict=True))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])


def revisits(pages: DataFrame, least: int = REVISIT_BYTES) -> DataFrame:
    """Decisions (page_id, digest, refers_to): pages whose payload an equal one with a larger page_id carries.

    Payloads are equal when their SHA-1, their SHA-256 and their lengths are; bytes are not compared.
    """
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    slim = pages.filter("page_id is not null").select("page_id", F.sha1(payload).alias("digest"), F.sha2(payload, 256).alias("strong"), F.octet_length(payload).alias("size"))
    slim = slim.filter(F.col("size") >= least)
    key = ["digest", "strong", "size"]
    top = slim.groupBy(*key).agg(F.max("page_id").alias("refers_to"), F.min("page_id").alias("low"), F.count(F.lit(1)).alias("pages")).filter("low < refers_to")
    return looked_up(slim, top, key, "pages").filter("page_id < refers_to").select("page_id", "digest", "refers_to").distinct()


def shard_of(pages: DataFrame, shards: int) -> tuple[int, int, np.ndarray]:
    """Least page_id, width of a range, and the shard of each of RANGES ranges, balanced by payload bytes.

    There are more than ``shards`` of them where these would hold over SHARD_BYTES each.

    Counts are exact, so the same table is cut the same way on any cluster.
    """
    ends = pages.agg(F.min("page_id"), F.max("page_id")).first()
    low, high = (ends[0] or 0), (ends[1] or 0)
    width = (high - low) // RANGES + 1
    place = F.floor((F.col("page_id") - low) / width).cast("int")
    weights = np.zeros(RANGES)
    for r in pages.filter("page_id is not null").groupBy(place.alias("p")).agg(F.sum(F.octet_length(F.coalesce("html", F.lit(""))) + 500).alias("w")).collect():
        weights[r["p"]] = r["w"]
    shards = max(shards, int(weights.sum() // SHARD_BYTES))
    before = np.cumsum(weights) - weights
    return low, width, np.minimum(shards - 1, before * shards // max(1.0, weights.sum())).astype(int)


def write_archives(pages: DataFrame, uri: str, shards: int | None = None, roll: int = ROLL_BYTES) -> DataFrame:
    """Write one record a row under ``uri``; returns the manifest (shard, number, file, n_records, n_bytes).

    Records lie in ascending page_id over the shards; each shard's files are closed once they hold ``roll`` compressed
    bytes. Of records with equal payloads of at least ``REVISIT_BYTES`` bytes, the one with the largest page_id carries
    it and the others refer to it. Files are written under a temporary name and then moved; the manifest is written
    after all of them and names the files that count. A null html is an empty payload; a null url leaves its header
    out; rows with a null page_id go to the first shard, are never revisits and are never referred to; rows repeated
    with one page_id are written each; extra columns are ignored; an empty table gives an empty manifest.
    """
    spark = pages.sparkSession
    pages = pages.select("page_id", "url", "html")
    shards = shards or max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    low, width, cuts = shard_of(pages, shards)
    lookup = F.split(F.lit(",".join(map(str, cuts))), ",").cast("array<long>")
    shard = F.coalesce(F.get(lookup, F.floor((F.col("page_id") - low) / width).cast("int")), F.lit(0).cast("long"))
    digest = F.sha1(F.coalesce(F.col("html"), F.lit("")).cast("binary"))
    rows = pages.select(shard.alias("shard"), "page_id", F.lit(1).alias("kind"), digest.alias("digest"), F.lit(None).cast("long").alias("refers_to"), "url", "html")
    decisions = revisits(pages).select(shard.alias("shard"), "page_id", F.lit(0).alias("kind"), "digest", "refers_to", F.lit(None).cast("string").alias("url"), F.lit(None).cast("string").alias("html"))
    # a shard a task, by its number: hashes of the numbers would leave some tasks empty and give others several shards
    dealt = rows.unionByName(decisions).repartitionById(max(shards, int(cuts.max()) + 1), F.col("shard").cast("int")).sortWithinPartitions("shard", F.col("page_id").asc_nulls_first(), "kind", "digest", F.col("url").asc_nulls_first())
    made = dealt.mapInArrow(partial(_write, base=uri, roll=roll), "shard long, number long, file string, n_records long, n_bytes long")
    schema = made.schema
    made.write.mode("overwrite").parquet(f"{uri}/manifest")
    return spark.read.schema(schema).parquet(f"{uri}/manifest")


def read_archives(spark: SparkSession, uri: str) -> DataFrame:
    """A row a record of the files the manifest names: page_id, payload_bytes, payload_digest, record_type, refers_to.

    Digests of blocks and payloads are computed again and compared.
    """
    files = spark.read.schema("shard long, number long, file string, n_records long, n_bytes long").parquet(f"{uri}/manifest")
    tasks = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    spread = files.repartitionById(tasks, F.pmod(F.col("shard") + F.col("number"), F.lit(tasks)).cast("int")).select("file")
    return spread.mapInArrow(partial(_read, base=uri), "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages written to archives and read back."""
    scratch = Scratch(spark, "archives")
    write_archives(table(spark, sf_dir, "pages", "page_id", "url", "html"), scratch.path("warc"))
    return scratch.last(read_archives(spark, scratch.path("warc")), "warc")


OP8_SQL = """
WITH p AS (
  SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest
  FROM pages),
q AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest, payload_bytes) AS top FROM p)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 1000 AND page_id < top THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 1000 AND page_id < top THEN top END AS refers_to
FROM q
"""
