"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata."""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, fold, table, text_rows

#: Word buckets; statistics follow with BINS buckets each.
WORDS, BINS, STATS = 1 << 16, 16, 10
#: Labelled rows that a model is fitted on at most, and features of all of them together: bounds of the driver's memory
#: (16 bytes a feature at most), not of the rows scored.
FIT_ROWS, FIT_FEATURES = 8000, 1 << 25
_CLASSES = np.zeros(256, dtype=np.int64)
_CLASSES[list(range(65, 91))] = 1
_CLASSES[list(range(97, 123))] = 2
_CLASSES[list(range(48, 58))] = 3
_CLASSES[[32, 9, 10, 11, 12, 13]] = 4
_CLASSES[list(range(128, 256))] = 5


def features(text: str, n_chars: int | None) -> tuple[np.ndarray, np.ndarray]:
    """Feature numbers and values of one whole text: its distinct word buckets share weight 1, each statistic has 1."""
    raw = text.encode()
    words = raw.split()
    lines = [x for x in raw.split(b"\n") if x.strip()]
    distinct = set(words)
    kinds = np.bincount(_CLASSES[np.frombuffer(raw, dtype=np.uint8)], minlength=6) / max(1, len(raw))
    shares = (
        kinds[1], kinds[3], kinds[0], kinds[5],
        len(distinct) / max(1, len(words)) if words else 0.0,
        1 - len(set(lines)) / len(lines) if lines else 0.0,
    )
    sizes = (len(words), (len(raw) - kinds[4] * len(raw)) / max(1, len(words)) * 8, len(lines), n_chars or 0)
    bins = [min(BINS - 1, int(np.ceil(s * (BINS - 1)))) for s in shares] + [min(BINS - 1, int(np.log2(1 + max(0, s)))) for s in sizes]
    index = np.unique(np.fromiter(map(zlib.crc32, distinct), dtype=np.uint32, count=len(distinct)) % WORDS).astype(np.int32)
    value = np.full(len(index) + STATS, 1.0, dtype=np.float32)
    value[: len(index)] = 1 / np.sqrt(max(1, len(index)))
    return np.concatenate([index, WORDS + np.arange(STATS, dtype=np.int32) * BINS + np.array(bins, dtype=np.int32)]), value


@dataclass
class FactorMachine:
    """bias + sum of weights + pairwise factor products, the last in linear time.

    For every factor the sum over all pairs is half of (square of the sum less sum of the squares).
    """

    bias: float
    weight: np.ndarray
    factor: np.ndarray

    def raw(self, index: np.ndarray, value: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Logits of rows laid end to end, and the factor sums of each row."""
        part = self.factor[index] * value[:, None]
        sums = np.add.reduceat(part, starts, axis=0)
        squares = np.add.reduceat(part * part, starts, axis=0)
        linear = np.add.reduceat(self.weight[index] * value, starts)
        return self.bias + linear + 0.5 * (sums * sums - squares).sum(axis=1), sums

    def score(self, index: np.ndarray, value: np.ndarray, starts: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(index, value, starts)[0].astype(np.float64), -35, 35)))


def fit(rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, factors: int = 8, epochs: int = 8, rate: float = 0.1, decay: float = 1e-5, seed: int = 7) -> FactorMachine:
    """AdaGrad on the logistic loss in mini-batches; no rows give a model that answers one half everywhere."""
    size, rng = WORDS + STATS * BINS, np.random.default_rng(seed)
    model = FactorMachine(0.0, np.zeros(size, np.float32), rng.normal(0, 0.02, (size, factors)).astype(np.float32))
    if not rows:
        model.factor[:] = 0
        return model
    share = float(np.clip(labels.mean(), 0.02, 0.98))
    model.bias = float(np.log(share / (1 - share)))
    grown = np.full((size, factors + 1), 1e-3, np.float32)
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for at in range(0, len(order), 128):
            chosen = order[at : at + 128]
            lengths = np.array([len(rows[i][0]) for i in chosen])
            starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
            index = np.concatenate([rows[i][0] for i in chosen])
            value = np.concatenate([rows[i][1] for i in chosen])
            logits, sums = model.raw(index, value, starts)
            miss = (1 / (1 + np.exp(-np.clip(logits, -35, 35))) - labels[chosen]).astype(np.float32)
            owner = np.repeat(np.arange(len(chosen)), lengths)
            slope = (miss[owner] * value)[:, None]
            steep = np.concatenate([slope, slope * (sums[owner] - model.factor[index] * value[:, None])], axis=1)
            used, place = np.unique(index, return_inverse=True)
            grad = np.stack([np.bincount(place, weights=steep[:, k], minlength=len(used)) for k in range(factors + 1)], axis=1).astype(np.float32) / len(chosen)
            grad[:, 0] += decay * model.weight[used]
            grad[:, 1:] += decay * model.factor[used]
            grown[used] += grad * grad
            step = rate * grad / np.sqrt(grown[used])
            model.weight[used] -= step[:, 0]
            model.factor[used] -= step[:, 1:]
            model.bias -= rate * 0.1 * float(miss.mean())
    return model


def _featurise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch, texts in text_rows(batches):
        made = [features(x, n) for x, n in zip(texts, batch.column(2).to_pylist(), strict=True)]
        sizes = pa.array([len(m[0]) for m in made], pa.int64())
        parts = [pa.array([m[k].tobytes() for m in made], pa.binary()) for k in (0, 1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(3), sizes, *parts], ["doc_id", "label", "size", "index", "value"])


def _scores(model: FactorMachine, texts: list[str], n_chars: list[int | None]) -> np.ndarray:
    """Scores of texts, some hundred at a time."""
    out = [np.zeros(0)]
    for at in range(0, len(texts), 256):
        made = [features(x, n) for x, n in zip(texts[at : at + 256], n_chars[at : at + 256], strict=True)]
        starts = np.concatenate([[0], np.cumsum([len(m[0]) for m in made])[:-1]]).astype(np.int64)
        out.append(model.score(np.concatenate([m[0] for m in made]), np.concatenate([m[1] for m in made]), starts))
    return np.concatenate(out)


def _score(batches: Iterator[pa.RecordBatch], model: FactorMachine) -> Iterator[pa.RecordBatch]:
    for batch, texts in text_rows(batches):
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(_scores(model, texts, batch.column(2).to_pylist()), pa.float64())], ["doc_id", "score"])


def train(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, fit_features: int = FIT_FEATURES) -> FactorMachine:
    """Fit on labelled rows outside the held-out fold: at most ``fit_rows``, the first by a hash of the id.

    A doc_id with several labels takes the largest; of several rows with one doc_id the one with the least features
    (then their bytes) counts; null labels and null ids are left out. Only features of the chosen rows reach the driver:
    as many rows, in the order of the hash, as have ``fit_features`` features together.
    """
    scratch = Scratch(docs.sparkSession, "fit")
    order = F.xxhash64("doc_id")
    chosen = (
        labels.filter(F.col("quality").isNotNull() & F.col("doc_id").isNotNull() & (fold(F.col("doc_id")) != 0))
        .groupBy("doc_id").agg(F.max("quality").alias("label"))
        .orderBy(order, "doc_id").limit(fit_rows)
    )
    rows = docs.select("doc_id", "text", "n_chars").join(F.broadcast(chosen), "doc_id").select(F.col("doc_id").cast("long").alias("doc_id"), "text", "n_chars", F.col("label").cast("int").alias("label"))
    made = scratch.save(rows.mapInArrow(_featurise, "doc_id long, label int, size long, index binary, value binary"), "features")
    sizes = made.groupBy("doc_id").agg(F.min("size").alias("size")).orderBy(order, "doc_id").collect()  # fit_rows at most
    total = np.cumsum([r["size"] for r in sizes])
    wanted = [r["doc_id"] for r in sizes[: int(np.searchsorted(total, fit_features, side="right"))]]
    one = made.groupBy("doc_id").agg(F.min(F.struct("size", "index", "value", "label")).alias("r"))
    picked = one.join(F.broadcast(docs.sparkSession.createDataFrame([(i,) for i in wanted], "doc_id long")), "doc_id").select("r.*").collect()
    scratch.drop()
    picked.sort(key=lambda r: (bytes(r["index"]), r["label"]))
    pairs = [(np.frombuffer(r["index"], np.int32), np.frombuffer(r["value"], np.float32)) for r in picked]
    return fit(pairs, np.array([min(1, max(0, r["label"])) for r in picked], dtype=np.float32))


def score(docs: DataFrame, model: FactorMachine) -> DataFrame:
    """doc_id and score of every whole text (0 to 1, higher: better).

    A null text counts as empty and has a score too; a null n_chars counts as 0; repeated rows are scored each;
    extra columns are ignored; an empty table gives no rows.
    """
    return docs.select("doc_id", "text", "n_chars").mapInArrow(partial(_score, model=model), "doc_id long, score double")


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """Rows of ``docs`` whose text scores at least ``threshold``, all columns kept."""
    model = train(docs, labels)
    judge = F.pandas_udf(_judge(model), "double")
    n_chars = F.coalesce(F.col("n_chars").cast("long"), F.lit(0))
    return docs.filter(judge(F.coalesce("text", F.lit("")), n_chars) >= threshold)


def _judge(model: FactorMachine):
    def scores(texts: pd.Series, n_chars: pd.Series) -> pd.Series:
        return pd.Series(_scores(model, texts.tolist(), [int(n) for n in n_chars]), dtype="float64")

    return scores


def op1_quality_fm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document scored by a machine fitted on the labelled rows of the same folder."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "n_chars")
    scored = score(docs, train(docs, table(spark, sf_dir, "labels", "doc_id", "quality")))
    return scored.select("doc_id", (fold(F.col("doc_id")) == 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
