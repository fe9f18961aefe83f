"""Quality rules: hashed n-gram log-likelihood ratio between trusted and raw text, and plain counts. DataFrame functions only."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from .common import BLANKS, fold, let, table

#: Buckets of the multinomials and pseudo-count of each.
BUCKETS, PRIOR = 1 << 13, 1.0
#: Share of trusted documents that may fall below the least mean log ratio, and steps of one in which it is set.
LOST, STEPS = 0.01, 1000


def words_of(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), BLANKS), lambda w: w != "")


def gram_buckets(words: Column) -> Column:
    """Bucket of every word and of every pair of neighbours. ``words`` must be bound (see ``let``)."""
    bucket = lambda *w: F.xxhash64(*w).bitwiseAND(F.lit(BUCKETS - 1).cast("long")).cast("int")
    first = F.slice(words, F.lit(1), F.greatest(F.lit(0), F.size(words) - 1))
    return F.concat(F.transform(words, lambda w: bucket(w)), F.transform(first, lambda w, i: bucket(w, F.get(words, i + 1))))


def repeated_words(words: Column) -> Column:
    """Words inside runs of three that occur twice or more in the text.

    Runs are hashed and sorted with their places; runs equal to a neighbour in that order are repeated. Their places
    in text order each cover three words, less what the next one covers too. n log n for a text of any length.
    """
    spots = F.transform(F.sequence(F.lit(1), F.size(words) - 2), lambda i: F.struct(F.xxhash64(F.get(words, i - 1), F.get(words, i), F.get(words, i + 1)).alias("h"), i.alias("at")))

    def covered(s: Column) -> Column:
        twice = F.filter(s, lambda x, i: (F.get(s, i - 1)["h"] == x["h"]) & (i > 0) | F.coalesce(F.get(s, i + 1)["h"] == x["h"], F.lit(False)))
        return let(F.sort_array(F.transform(twice, lambda x: x["at"])), lambda p: F.aggregate(p, F.struct(F.lit(0).cast("long").alias("n"), F.lit(-9).alias("last")), lambda a, x: F.struct((a["n"] + F.least(F.lit(3), x - a["last"])).alias("n"), x.alias("last")), lambda a: a["n"]))

    return F.when(F.size(words) >= 4, let(F.sort_array(spots), covered)).otherwise(F.lit(0).cast("long"))


def bucket_counts(docs: DataFrame, trusted: DataFrame, broadcast_ids: int = 1 << 20) -> DataFrame:
    """Rows (bucket, raw, good, fit): grams of all documents, of the trusted ones and of those not set apart. At most BUCKETS rows.

    Up to ``broadcast_ids`` trusted ids are broadcast, so the scan is counted where it is; beyond that they meet the
    documents in a shuffle join. Either way grams are summed by bucket before they leave a task.
    """
    chosen = _chosen(trusted, broadcast_ids).withColumn("good", F.lit(1)).withColumn("fit", (~_apart()).cast("int"))
    flagged = docs.select("doc_id", "text").join(chosen, "doc_id", "left")
    flags = [F.coalesce(x, F.lit(0)).alias(x) for x in ("good", "fit")]
    grams = flagged.select(*flags, F.explode(let(words_of(F.col("text")), gram_buckets)).alias("bucket"))
    return grams.groupBy("bucket").agg(F.count(F.lit(1)).alias("raw"), F.sum("good").alias("good"), F.sum("fit").alias("fit"))


def _apart() -> Column:
    """Whether a trusted document is one that only sets the least ratio."""
    return fold(F.col("doc_id")) == 1


def _chosen(trusted: DataFrame, broadcast_ids: int) -> DataFrame:
    ids = trusted.filter(F.col("doc_id").isNotNull()).select("doc_id").distinct()
    return F.broadcast(ids) if ids.count() <= broadcast_ids else ids


def log_ratios(counts: list[Row], of: str = "good") -> list[float]:
    """log(trusted share / raw share) of every bucket, with PRIOR added to each count; no trusted text: all 0."""
    raw, good = [PRIOR] * BUCKETS, [PRIOR] * BUCKETS
    for r in counts:
        raw[r["bucket"]] += r["raw"]
        good[r["bucket"]] += r[of]
    if all(g == PRIOR for g in good):
        return [0.0] * BUCKETS
    shift = math.log(sum(raw)) - math.log(sum(good))
    return [round(math.log(g) - math.log(r) + shift, 5) for g, r in zip(good, raw, strict=True)]


def measured(text: Column, ratios: list[float]) -> Column:
    """Struct of n_words, n_repeat_words and llr. The words are bound once, so that no rewrite splits a text again."""
    # one constant-folded array: BUCKETS doubles whatever the corpus
    known = F.split(F.lit(",".join(map(str, ratios))), ",").cast("array<double>")

    def of(words: Column) -> Column:
        n = F.size(words).cast("long")
        total = F.aggregate(gram_buckets(words), F.lit(0.0), lambda s, b: s + F.get(known, b))
        return F.struct(n.alias("n_words"), repeated_words(words).alias("n_repeat_words"), F.when(n > 0, total / (2 * n - 1)).otherwise(F.lit(0.0)).alias("llr"))

    return let(words_of(text), of)


def _failed(m: Column) -> Column:
    return (m["n_words"] < 50) | (100 * m["n_repeat_words"] > 50 * m["n_words"])


def least_ratio(docs: DataFrame, trusted: DataFrame, ratios: list[float], broadcast_ids: int = 1 << 20) -> float:
    """The ratio that all but LOST of the trusted documents set apart reach, rounded down to a step.

    ``ratios`` must not have counted these documents: a document's own grams raise its ratio, the more the fewer texts
    are trusted, and those never labelled have no such help. Documents the counts fail don't vote. Without voters
    nothing can be told, and no ratio is too low.
    """
    voters = _chosen(trusted.filter(_apart()), broadcast_ids)
    # null for failed ones: a filter would move below the join and measure every document
    step = let(measured(F.col("text"), ratios), lambda m: F.when(~_failed(m), F.floor(m["llr"] * STEPS)))
    votes = docs.select("doc_id", "text").join(voters, "doc_id", "left_semi").groupBy(step.alias("step")).count().collect()  # some 10,000 rows at most
    steps = sorted((r[0], r[1]) for r in votes if r[0] is not None)
    left = int(LOST * sum(n for _, n in steps))
    for step, n in steps:
        left -= n
        if left < 0:
            return step / STEPS
    return -math.inf


def _learned(docs: DataFrame, trusted: DataFrame, least: float | None) -> tuple[list[float], float]:
    """Ratios of all trusted text, and the least one unless it is given."""
    counts = bucket_counts(docs, trusted).collect()
    if least is None:
        least = least_ratio(docs, trusted, log_ratios(counts, "fit")) if any(r["fit"] for r in counts) else -math.inf
    return log_ratios(counts), least


def judge(docs: DataFrame, trusted: DataFrame, least: float | None = None) -> DataFrame:
    """Counts, score and verdict of every document.

    Columns: doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, llr. ``trusted``
    names (doc_id) the documents whose grams make the target multinomial; all documents make the raw one. ``llr`` is
    the mean log ratio over the words and word pairs of the whole text, 0 without words. A row stays unless it has
    fewer than 50 words, more than half of its words lie in repeated runs, or ``llr`` is below ``least`` (without one,
    what ``least_ratio`` finds by trusted documents that a fit leaves out). Null texts have no words; repeated rows are judged each; extra columns are ignored; an empty table gives no rows.
    """
    ratios, least = _learned(docs, trusted, least)
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = F.filter(F.split(text, "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    m = F.col("m")
    return docs.select(
        "doc_id",
        measured(F.col("text"), ratios).alias("m"),
        F.length(F.regexp_replace(text, BLANKS, "")).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
    ).select(
        "doc_id", m["n_words"].alias("n_words"), "word_chars", "n_symbols", "n_dup_lines", m["n_repeat_words"].alias("n_repeat_words"),
        _failed(m).alias("base_failed"), (~_failed(m) & (m["llr"] >= least)).alias("kept"), m["llr"].alias("llr"),
    )


def keep_ruled(docs: DataFrame, trusted: DataFrame, least: float | None = None) -> DataFrame:
    """Rows the rules keep, all columns, without a shuffle."""
    ratios, least = _learned(docs, trusted, least)
    return docs.filter(let(measured(F.col("text"), ratios), lambda m: ~_failed(m) & (m["llr"] >= least)))


def trusted_of(labels: DataFrame) -> DataFrame:
    """Documents labelled as good and by no row as bad."""
    return labels.groupBy("doc_id").agg(F.min("quality").alias("q")).filter("q = 1").select("doc_id")


def op9_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document judged against the labelled good ones."""
    return judge(table(spark, sf_dir, "documents", "doc_id", "text"), trusted_of(table(spark, sf_dir, "labels", "doc_id", "quality")))
