"""Licence scan by diagonal voting: word pairs joined to template places, votes summed by offset."""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import lower_ascii, table

#: Words are what lies between ASCII characters other than letters and digits.
GAPS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Words of a gram; the shortest phrases have as many.
GRAM = 2
#: Diagonals this near are one passage (words put in or left out); share of a template's grams that makes a match;
#: templates of fewer grams must stand word for word.
DRIFT, ENOUGH, LOOSE = 2, 0.7, 5

# The phrases of the base scan and their labels.
BASE = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}
# Names and well-known passages of public licences that the method adds.
ADDED = {
    "gnu lesser general public license": "lgpl",
    "gnu affero general public license": "agpl",
    "mozilla public license": "mpl",
    "eclipse public license": "epl",
    "boost software license": "bsl",
    "bsd license": "bsd",
    "isc license": "isc",
    "creative commons attribution": "cc-by",
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files": "mit",
    "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license": "apache",
    "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met": "bsd",
    "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation": "gpl",
    "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted": "isc",
}


def template_rows(base: dict[str, str], added: dict[str, str]) -> list[tuple[int, str, bool, int, int, int, str]]:
    """(template, label, is base, grams, place, its bit, gram) of every place; a template has at most 62 grams."""
    rows = []
    for number, (phrase, label, is_base) in enumerate([(p, x, True) for p, x in base.items()] + [(p, x, False) for p, x in added.items()]):
        words = phrase.split()
        grams = [" ".join(words[i : i + GRAM]) for i in range(len(words) - GRAM + 1)]
        if not 1 <= len(grams) <= 62:
            raise ValueError(f"a template needs 2 to 63 words: {phrase}")
        rows += [(number, label, is_base, len(grams), i, 1 << i, g) for i, g in enumerate(grams)]
    return rows


def in_order(bits: dict[int, int], grams: int) -> tuple[int, int, int]:
    """Most grams that stand in the template's order in the text, and the span of these: its first word and the one after its last.

    ``bits``: template places by diagonal (word of the text less place). Votes count once a place, and each must lie
    behind the one before it in the text: the longest rising chain of votes sorted by place.
    """
    ends: list[int] = []
    best: list[tuple[int, int]] = []  # the chain's last word so far and its first one, by length
    for place in range(grams):
        for at in sorted((d + place for d, b in bits.items() if b >> place & 1), reverse=True):
            k = bisect_left(ends, at)
            first = best[k - 1][1] if k else at
            ends[k : k + 1], best[k : k + 1] = [at], [(at, first)]
    return (len(ends), best[-1][1], best[-1][0] + GRAM) if ends else (0, 0, 0)


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["doc_id", "mark", "template", "label", "base", "start", "stop", "share", "hit"]
    for batch in batches:
        found = [in_order({p["diagonal"]: p["bits"] for p in pool}, g) for pool, g in zip(batch.column(6).to_pylist(), batch.column(5).to_pylist(), strict=True)]
        shares = [n / g for (n, _, _), g in zip(found, batch.column(5).to_pylist(), strict=True)]
        made = [pa.array([f[1] for f in found], pa.int64()), pa.array([f[2] for f in found], pa.int64()), pa.array(shares, pa.float64()), pa.array([s >= ENOUGH for s in shares], pa.bool_())]
        yield pa.RecordBatch.from_arrays([*batch.columns[:5], *made], names)


def _worded(docs: DataFrame) -> DataFrame:
    text = lower_ascii(F.col("text"))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("mark"), F.filter(F.split(text, GAPS), lambda w: w != "").alias("w"))


def _places(docs: DataFrame, base: dict[str, str], added: dict[str, str]) -> DataFrame:
    """Diagonals with votes: doc_id, mark, template, label, base, start, stop, share, hit (verified; start and stop for hits)."""
    templates = docs.sparkSession.createDataFrame(template_rows(base, added), "template int, label string, base boolean, grams int, place int, bit long, gram string")
    templates = F.broadcast(templates.withColumn("hash", F.xxhash64("gram")))
    # neighbours are zipped, not indexed: one pass over the words
    tail = F.greatest(F.lit(0), F.size("w") - 1)
    pairs = F.transform(F.arrays_zip(F.slice("w", F.lit(1), tail).alias("a"), F.slice("w", F.lit(2), tail).alias("b")), lambda p: F.concat_ws(" ", p["a"], p["b"]))
    rolled = _worded(docs).select("doc_id", "mark", F.posexplode(pairs).alias("at", "text_gram"))
    met = rolled.withColumn("hash", F.xxhash64("text_gram")).join(templates, "hash").filter("gram = text_gram")
    who = ["doc_id", "mark", "template", "label", "base"]
    votes = met.groupBy(*who, "grams", (F.col("at") - F.col("place")).alias("diagonal")).agg(F.bit_or("bit").alias("bits"))
    near = Window.partitionBy("doc_id", "mark", "template").orderBy("diagonal").rangeBetween(-DRIFT, DRIFT)
    pooled = votes.withColumn("pool", F.collect_list(F.struct("diagonal", "bits")).over(near))
    strict = F.col("grams") < LOOSE
    own = F.when(strict, F.col("bits")).otherwise(F.aggregate("pool", F.lit(0).cast("long"), lambda s, p: s.bitwiseOR(p["bits"])))
    pooled = pooled.withColumn("share", F.bit_count(own) / F.col("grams"))
    asked = ~strict & (F.col("share") >= ENOUGH)
    none = F.lit(None).cast("long")
    hit = strict & (F.col("share") == 1)
    start, stop = F.col("diagonal").cast("long"), (F.col("diagonal") + F.col("grams") + GRAM - 1).cast("long")
    plain = pooled.filter(~asked).select(*who, F.when(hit, start).otherwise(none).alias("start"), F.when(hit, stop).otherwise(none).alias("stop"), "share", hit.alias("hit"))
    checked = pooled.filter(asked).select(*who, "grams", "pool").mapInArrow(_verify, "doc_id long, mark long, template int, label string, base boolean, start long, stop long, share double, hit boolean")
    return plain.unionByName(checked)


def spans(docs: DataFrame, base: dict[str, str] = BASE, added: dict[str, str] = ADDED) -> DataFrame:
    """Passages found: doc_id, mark (hash of the text), label, phrase, start, stop (words, from 0, stop excluded), share.

    Neighbouring diagonals of one passage give one row: hits of a template that overlap are merged, the largest share
    stands. Cases as in ``scan``; a text without passages has no row.
    """
    names = docs.sparkSession.createDataFrame(list(enumerate([*base, *added])), "template int, phrase string")
    hits = _places(docs, base, added).filter("hit")
    order = Window.partitionBy("doc_id", "mark", "template").orderBy("start", "stop")
    before = F.max("stop").over(order.rowsBetween(Window.unboundedPreceding, -1))
    fresh = hits.withColumn("fresh", F.when(F.col("start") < before, 0).otherwise(1))
    numbered = fresh.withColumn("island", F.sum("fresh").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    merged = numbered.groupBy("doc_id", "mark", "template", "label", "island").agg(F.min("start").alias("start"), F.max("stop").alias("stop"), F.max("share").alias("share"))
    return merged.join(F.broadcast(names), "template").select("doc_id", "mark", "label", "phrase", "start", "stop", "share")


def scan(docs: DataFrame, base: dict[str, str] = BASE, added: dict[str, str] = ADDED) -> DataFrame:
    """Licence labels of every whole text.

    Columns: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score. All rolling pairs of words
    meet the template places by hash in a broadcast join (the templates are a fixed list) and are compared as text;
    votes are kept as bits of template places, summed by document, template and diagonal. A base phrase, or any
    template of fewer than LOOSE grams, needs every vote on one diagonal. Longer templates pool diagonals up to ``DRIFT``
    apart; where these hold ENOUGH of the grams, the span is verified: so many of them must stand in the template's
    order, each once. The score is the largest share of a template found. Null and empty texts have no words, no labels
    (empty strings) and score 0; repeated rows are reported each; extra columns are ignored; an empty table gives no
    rows. A text of any length is one row's arrays in one task; its votes are summed elsewhere.
    """
    exact = F.col("base") & F.col("hit")
    joined = lambda c: F.array_join(F.array_sort(F.collect_set(c)), ",")
    found = _places(docs, base, added).groupBy("doc_id", "mark").agg(
        F.count_if(exact).alias("n_base"),
        F.min(F.when(exact, F.col("start"))).alias("first_word"),
        F.max(F.when(exact, F.col("start"))).alias("last_word"),
        joined(F.when(exact, F.col("label"))).alias("base_labels"),
        joined(F.when(F.col("hit"), F.col("label"))).alias("labels"),
        F.max("share").alias("score"),
    )
    slim = _worded(docs).select("doc_id", "mark", F.size("w").cast("long").alias("n_words"))
    all_rows = slim.join(found, (slim["doc_id"].eqNullSafe(found["doc_id"])) & (slim["mark"] == found["mark"]), "left")
    return all_rows.select(
        slim["doc_id"], "n_words", F.coalesce("n_base", F.lit(0)).cast("long").alias("n_base"), "first_word", "last_word",
        F.coalesce("base_labels", F.lit("")).alias("base_labels"), F.coalesce("labels", F.lit("")).alias("labels"), F.coalesce("score", F.lit(0.0)).alias("score"),
    )


def brute_base(text: str | None) -> tuple[int, int, list[int], str]:
    """Words, places, starts and labels of the base phrases, by looking at every place (for tests)."""
    lowered = (text or "").encode().lower().decode()
    words = [w for w in re.split(GAPS, lowered) if w]
    starts, labels = [], set()
    for phrase, label in BASE.items():
        p = phrase.split()
        hits = [i for i in range(len(words) - len(p) + 1) if words[i : i + len(p)] == p]
        starts += hits
        labels |= {label} if hits else set()
    return len(words), len(starts), sorted(starts), ",".join(sorted(labels))


def op7_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document scanned for licences."""
    return scan(table(spark, sf_dir, "documents", "doc_id", "text"))
