"""Things that several text operators share: reading tables, the shared scratch folder, file access."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.dataset as pads
import pyarrow.fs as pafs
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: White space of the contracts: a space and the five ASCII controls from tab to carriage return.
BLANKS = r"[\x20\x09-\x0D]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """One table of a data folder, only the named columns."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def fold(doc_id: Column) -> Column:
    """crc32 of the id as text, modulo 5; a null id counts as the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 5


def lower_ascii(text: Column) -> Column:
    """Lower-case A to Z only, other letters stay; null becomes the empty text."""
    return F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER)


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Bind ``value`` once for ``body``: a lambda's free column would be computed again per element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share. Only a session on one machine may do without: it gets a local one."""
    context = spark.sparkContext
    root = context.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not root:
        if not (context.master or "").startswith("local") or context.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = "file:///tmp/checkpoints"
        context.setCheckpointDir(root)
    return root.rstrip("/")


def opened(uri: str) -> tuple[pafs.FileSystem, str]:
    """The file system of an address (file, hdfs, s3, ...) and the path in it."""
    return pafs.FileSystem.from_uri(uri)


class Scratch:
    """A folder of its own under the shared root, for tables that cut lineage and files of tasks.

    Tables that a returned (lazy) frame still reads stay until the driver's Python ends; all others go by ``drop``.
    """

    def __init__(self, spark: SparkSession, label: str) -> None:
        self.spark = spark
        self.base = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"
        atexit.register(_delete, self.base)

    def path(self, name: str) -> str:
        return f"{self.base}/{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        """Write a table and read it back: every later use starts from files that outlive executors."""
        schema = df.schema
        df.write.mode("overwrite").option("compression", "zstd").parquet(self.path(name))
        return self.spark.read.schema(schema).parquet(self.path(name))

    def drop(self, *names: str) -> None:
        """Delete tables no later plan reads; where the store can't be reached they stay for its own clean-up."""
        for name in names or ("",):
            _delete(self.path(name).rstrip("/"))

    def last(self, df: DataFrame, *done: str) -> DataFrame:
        """Save a result and delete all that only led to it."""
        out = self.save(df, "result")
        self.drop(*done)
        return out


def _delete(uri: str) -> None:
    try:
        fs, path = opened(uri)
        fs.delete_dir(path)
    except (OSError, pa.ArrowException):
        pass


def unused(df: DataFrame, name: str) -> str:
    """A column name that ``df`` does not have, whatever its case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def numbered(scratch: Scratch, df: DataFrame, name: str) -> tuple[DataFrame, str]:
    """The table kept on shared files with a number for every row, and that column's name.

    Rows are told apart by it whatever their ids are. Its upper bits (from ROW_BITS) name the task that wrote the row.
    """
    row = unused(df, "row_number")
    return scratch.save(df.withColumn(row, F.monotonically_increasing_id()), name), row


#: Bits of ``monotonically_increasing_id`` below the number of the partition.
ROW_BITS = 33


def listed(scratch: Scratch, numbers: DataFrame, name: str, bits: int = ROW_BITS) -> str:
    """Row numbers (the first column) as lists on shared files, one for each task that gave the numbers; returns where.

    Numbers, with what other columns there are, travel to their lists; the (far larger) rows that they name stay where
    they are: see ``picked`` and ``met_in_place``.
    """
    own = numbers.withColumnRenamed(numbers.columns[0], "number")
    parts = max(1, int(scratch.spark.conf.get("spark.sql.shuffle.partitions")))
    apart = own.withColumn("task", F.shiftright("number", bits)).repartition(parts, "task")
    apart.write.mode("overwrite").partitionBy("task").parquet(scratch.path(name))
    return scratch.path(name)


def _list_of(lists: str) -> Callable[[int], pa.Table | None]:
    """The list of a task by number; the last one is held."""
    fs, root = opened(lists)
    held: dict[int, pa.Table | None] = {}

    def of(task: int) -> pa.Table | None:
        if task not in held:
            held.clear()
            path = f"{root}/task={task}"
            there = fs.get_file_info(path).type == pafs.FileType.Directory
            held[task] = pads.dataset(path, filesystem=fs, format="parquet").to_table().sort_by("number") if there else None
        return held[task]

    return of


def picked(lists: str, bits: int = ROW_BITS) -> Callable[[np.ndarray], np.ndarray]:
    """A test of row numbers against ``listed`` ones, for use in a task; it holds the list of one task at a time."""
    of = _list_of(lists)

    def test(numbers: np.ndarray) -> np.ndarray:
        out = np.zeros(len(numbers), bool)
        tasks = numbers >> bits
        for t in np.unique(tasks).tolist():
            if (held := of(t)) is not None:
                here = tasks == t
                out[here] = np.isin(numbers[here], held["number"].to_numpy())
        return out

    return test


def met_in_place(saved: DataFrame, row: str, listing: DataFrame, lists: str) -> DataFrame:
    """Inner join of ``saved`` on its ``row`` numbers with the rows that ``listing`` has been ``listed`` as: only those move.

    Columns: those of ``listing`` but the number, then those of ``saved`` but the number.
    """
    payload = [c for c in listing.columns[1:]]
    kept = [c for c in saved.columns if c != row]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = _list_of(lists)
        for batch in batches:
            numbers = batch.column(batch.num_columns - 1).to_numpy()
            tasks = numbers >> ROW_BITS
            for t in np.unique(tasks).tolist():
                if (held := of(t)) is None:
                    continue
                here = np.flatnonzero(tasks == t)
                own = held["number"].to_numpy()
                low = np.searchsorted(own, numbers[here])
                n = np.searchsorted(own, numbers[here], side="right") - low
                left, right = np.repeat(here, n), np.repeat(low - np.cumsum(n) + n, n) + np.arange(n.sum())
                found, rows = held.take(pa.array(right)), batch.take(pa.array(left))
                yield pa.RecordBatch.from_arrays([*(found[c].combine_chunks() for c in payload), *rows.columns[:-1]], [*payload, *kept])

    schema = StructType([*(listing.schema[c] for c in payload), *(saved.schema[c] for c in kept)])
    return saved.select(*kept, row).mapInArrow(run, schema)


def rows_of(saved: DataFrame, row: str, lists: str) -> DataFrame:
    """Rows of a ``numbered`` table whose numbers are ``listed``, without that column; nothing is shuffled."""
    kept = [c for c in saved.columns if c != row]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        test = picked(lists)
        for batch in batches:
            mask = test(batch.column(batch.num_columns - 1).to_numpy())
            rest = batch.filter(pa.array(mask))
            yield pa.RecordBatch.from_arrays(rest.columns[:-1], schema=pa.schema(list(rest.schema)[:-1]))

    columns = [F.col(f"`{c}`") for c in kept]
    return saved.select(*columns, row).mapInArrow(run, saved.select(*columns).schema)


def looked_up(rows: DataFrame, found: DataFrame, key: str | list[str], weight: str) -> DataFrame:
    """Inner join with ``found``, whose ``weight`` says how many of the rows hold each ``key``.

    Keys of over 1 in HOT_SHARE rows are at most HOT_SHARE many: they are broadcast and their rows stay where they are.
    All other keys meet in a shuffle, where none is hot.
    """
    total = found.agg(F.sum(weight)).first()[0] or 0
    bar = max(1000, total // HOT_SHARE)
    hot, cold = found.filter(F.col(weight) > bar), found.filter(F.col(weight) <= bar)
    near = rows.join(F.broadcast(hot), key)
    names = [key] if isinstance(key, str) else key
    return near.unionByName(rows.join(F.broadcast(hot.select(*names)), key, "left_anti").join(cold, key))


#: See ``looked_up``.
HOT_SHARE = 4096


def commit_file(uri: str, temporary: str, write: Callable[[pa.NativeFile], None]) -> None:
    """Write under a temporary name, then move to the final one, so readers only see whole files.

    The content depends on the input alone, so an attempt that is run again replaces a file by its equal.
    """
    fs, path = opened(uri)
    parent = path.rsplit("/", 1)[0]
    fs.create_dir(parent, recursive=True)
    draft = f"{parent}/{temporary}"
    with fs.open_output_stream(draft, compression=None) as out:
        write(out)
    fs.move(draft, path)


def text_rows(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Parts of batches with their texts as Python strings, null as the empty text; few rows are held at a time."""
    for whole in batches:
        for at in range(0, max(1, whole.num_rows), rows):
            batch = whole.slice(at, rows)
            texts = batch.column(batch.schema.get_field_index("text")).to_pylist()
            yield batch, [x or "" for x in texts]


#: Pre-tokens of more characters are worked out anew each time: a cache of so many entries then has a bound in bytes.
CACHED_CHARS = 64
#: Class of a pattern, and a character that `regex` and the libraries put into it (the last one: into none).
_STAND_INS = {r"\p{L}": "\u00aa", r"\p{N}": "\u00b2", r"\s": "\u3000", "": "\u00a7"}


def odd_characters(matched: Callable[[str, str], set[str]]) -> dict[int, str]:
    """Characters that a library's tables put into another class than `regex` does, with a stand-in of the library's class.

    ``matched(pattern, text)``: characters of the text that the library matches with a pattern of one character.
    """
    every = "".join(map(chr, (*range(0xD800), *range(0xE000, 0x110000))))
    ours, theirs = {}, {}
    for pattern in [p for p in _STAND_INS if p]:
        ours |= dict.fromkeys(regex.findall(pattern, every), pattern)
        theirs |= dict.fromkeys(matched(pattern, every), pattern)
    return {ord(c): _STAND_INS[theirs.get(c, "")] for c in ours.keys() | theirs.keys() if ours.get(c) != theirs.get(c)}


class Splitter:
    """Matches of a pattern of letter, number and space classes in a text, as the library with these odd characters finds them."""

    def __init__(self, pattern: str, odd: dict[int, str]) -> None:
        compiled = regex.compile(pattern)
        self.find, self.spans, self.odd = compiled.findall, compiled.finditer, odd
        self.set, self.latin = frozenset(map(chr, odd)), min(odd, default=0x110000) > 0xFF

    def __call__(self, text: str) -> list[str]:
        if self.latin:
            try:
                text.encode("latin-1")
                return self.find(text)
            except UnicodeEncodeError:
                pass
        if self.set.isdisjoint(text):
            return self.find(text)
        return [text[m.start() : m.end()] for m in self.spans(text.translate(self.odd))]


def _byte_letters() -> dict[int, str]:
    """Byte-level vocabularies write printable Latin-1 bytes as themselves, the others as letters from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    other = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(other)}


_BYTE_LETTERS = str.maketrans({chr(b): letter for b, letter in _byte_letters().items()})


def byte_level(text: str) -> str:
    """A text's bytes in the letters of byte-level vocabularies."""
    return text.encode().decode("latin-1").translate(_BYTE_LETTERS)
