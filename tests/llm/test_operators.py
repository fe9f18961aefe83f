"""Text operators against brute force, on small tables with nulls, empty texts, ties, repeats and extra columns."""

import base64
import gzip
import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F

from runjoin.llm import bpe, exact_dedup, factor_machine, license_scan, near_dedup, packing, quality_rules, recurrent_lm, token_store, warc

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept int, id long, row string, n int"


@pytest.fixture(scope="module")
def docs(spark):
    base = "the mit license and the gnu general public license are here " + " ".join(f"word{i}" for i in range(80))
    texts = [None, "", " \n\t", base, base + " more", base.upper(), "a b", "a  b", "É é ß 日本 <|endoftext|>", "x" * 5000, "one line\n" * 60, base, "ab\x0bc"]
    rows = [(i, t, "en", "s", len(t or ""), 1, 7, "r", 2) for i, t in enumerate(texts)] + [(3, base, None, None, None, 1, 7, "r", 2), (None, base, None, None, None, 1, 7, "r", 2)]
    return spark.createDataFrame(rows, SCHEMA)


def rows(df, *columns):
    return sorted((tuple(r) for r in df.select(*columns).collect()), key=str)


def test_exact_groups(spark, docs):
    got = exact_dedup.exact_groups(docs).collect()
    assert len(got) == docs.count()
    plain = lambda t: re.sub(r"[\x20\x09-\x0D]", "", t or "")
    texts = [(r["doc_id"], r["text"]) for r in docs.collect()]
    size = Counter(plain(t) for _, t in texts)
    sha = {hashlib.sha256(k.encode()).hexdigest(): n for k, n in size.items()}
    for r in got:
        assert r["group_size"] == sha[r["text_sha256"]]
    keep = {r["doc_id"]: r["keep_id"] for r in got}
    assert keep[6] == 7 and keep[7] == 7 and keep[0] == keep[1] == keep[2] == 2 and keep[11] == keep[3] == keep[None] == 3
    assert exact_dedup.exact_groups(docs.limit(0)).count() == 0
    kept = exact_dedup.drop_exact_copies(docs)
    assert kept.columns == docs.columns and kept.count() == len(size)


def test_one_row_of_every_group_stays(spark):
    data = [(None, "one text"), (None, "other text"), (None, "onetext"), (None, None), (1, "a b c"), (1, "d e f"), (1, "abc"), (2, "abc"), (2, "g  h"), (2, "g   h"), (3, "other text"), (4, " "), (5, "gh")]
    df = spark.createDataFrame([(i, t, n) for n, (i, t) in enumerate(data)], "doc_id long, text string, n int").repartition(4)
    best = {}
    for n, (i, t) in enumerate(data):
        rank = (-len(t or ""), i is None, i or 0, t or "", n)
        key = re.sub(r"[\x20\x09-\x0D]", "", t or "")
        best[key] = min(best.get(key, (rank, n)), (rank, n))
    assert sorted(r["n"] for r in exact_dedup.drop_exact_copies(df).collect()) == sorted(n for _, n in best.values())


def test_rows_meet_in_place(spark):
    """Lists of row numbers against plain joins; numbers of many tasks, some without a list, repeated and missing ones."""
    from runjoin.llm.common import Scratch, listed, looked_up, met_in_place, numbered, rows_of

    scratch = Scratch(spark, "test")
    df = spark.range(1000).selectExpr("id", "concat('v', id) as text", "array(id) as list", "id as Row_Number").repartition(7)
    saved, row = numbered(scratch, df, "docs")
    assert row not in df.columns and saved.select(row).distinct().count() == 1000
    wanted = saved.filter("id % 9 = 0 and id < 500").select(row)
    want = sorted(r["id"] for r in saved.join(wanted, row, "left_semi").collect())
    got = rows_of(saved, row, listed(scratch, wanted, "wanted"))
    assert got.columns == df.columns and sorted(r["id"] for r in got.collect()) == want
    listing = wanted.unionByName(wanted).select(row, F.col(row).alias("again"), F.lit("x").alias("mark"))
    met = met_in_place(saved.select("id", "text", row), row, listing, listed(scratch, listing, "pairs")).collect()
    assert sorted(r["id"] for r in met) == sorted(want * 2) and all(r["mark"] == "x" and r["text"] == f"v{r['id']}" for r in met)
    assert rows_of(saved, row, listed(scratch, wanted.limit(0), "none")).count() == 0
    keyed = spark.range(20_000).selectExpr("if(id % 3 = 0, 0, id) as k", "id")
    found = keyed.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.max("id").alias("top"))
    assert rows(looked_up(keyed, found, "k", "n"), "k", "id", "top") == rows(keyed.join(found, "k"), "k", "id", "top")


def test_directory_splits():
    depth, slots = exact_dedup.directory({0: 5, 1: 5, 8: 1, 15: 1}, 6, 4)
    assert depth == 4 and len(slots) == 16 and slots[0] != slots[1] and slots[8] == slots[15]
    assert exact_dedup.directory({}, 6, 4)[0] == 0
    assert exact_dedup.directory({3: 100}, 6, 4)[0] == 4


def test_owners_chain_texts_of_one_key():
    import pyarrow as pa

    rows = [(1, 10, 0, 5, 3, 2, b"A", b"abc"), (1, 11, 0, 4, 9, 1, b"B", b"abd"), (1, 12, 0, 2, 3, 4, b"A", b"abc"), (2, 13, 0, None, 1, 1, b"C", None)]
    batch = pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*rows), exact_dedup._SCAN_ARROW)], schema=exact_dedup._SCAN_ARROW)
    got = [r for b in exact_dedup._own(iter([batch])) for r in b.to_pylist()]
    assert {r["ref"]: (r["group"], r["link"], r["keep_id"], r["group_size"]) for r in got} == {10: (10, 0, 2, 6), 11: (11, 1, 4, 1), 12: (10, 0, 2, 6), 13: (13, 0, None, 1)}
    assert [r for b in exact_dedup._shared(iter([batch.select(["key", "ref"])])) for r in b.to_pylist()] == [{"ref": 10}, {"ref": 11}, {"ref": 12}]


def test_short_keys_collide_and_change_nothing(spark, docs):
    """Three key bits throw unlike texts into one chain; a room of one byte makes every batch write its classes."""
    want = rows(exact_dedup.exact_groups(docs), "doc_id", "keep_id", "group_size", "kept", "text_sha256")
    assert rows(exact_dedup.exact_groups(docs.repartition(5), bucket_entries=2, key_bits=3, room=1), "doc_id", "keep_id", "group_size", "kept", "text_sha256") == want
    assert exact_dedup.drop_exact_copies(docs, key_bits=1).count() == exact_dedup.drop_exact_copies(docs).count()


def test_clashing_columns_survive(spark):
    df = spark.createDataFrame([(1, "a b", 5, {"k": 1}), (1, "a  b", 6, None), (2, None, 7, {}), (None, "c", 8, {})], "doc_id int, text string, row_number int, place_of_row map<string,int>")
    for drop in (exact_dedup.drop_exact_copies, near_dedup.drop_near_copies):
        got = drop(df)
        assert got.columns == df.columns and got.count() == 3


def test_bpe_is_tiktoken(spark, docs):
    import tiktoken

    c = bpe.coder(bpe.default_ranks(), public_tokenizers.PATTERN)
    own = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=c.ranks, special_tokens={})
    got = bpe.encode(docs).join(docs.select("doc_id", "text").distinct(), "doc_id").collect()
    for r in got:
        assert r["ids"] == own.encode_ordinary(r["text"] or "")
    back = {r["doc_id"]: r["text"] for r in bpe.decode(bpe.encode(docs)).collect()}
    assert back[9] == "x" * 5000 and back[0] == ""
    keys = [f"k{i}".encode() for i in range(500)]
    found = bpe.PerfectHash(keys)
    assert [found.find(k) for k in keys] == list(range(500)) and found.find(b"none") == -1 and sorted(found.slots) == list(range(500))


def test_token_files(spark, docs, tmp_path):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    t.encode_special_tokens = True
    token_store.write_ids(docs, f"file://{tmp_path}/ids")
    got = sorted(token_store.read_ids(spark, f"file://{tmp_path}/ids").collect(), key=lambda r: r["start"])
    assert [r["doc_id"] for r in got] == sorted((r["doc_id"] for r in docs.collect()), key=lambda d: (d is not None, d or 0))
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    at = 0
    for r in got:
        ids = np.array([*t.encode(texts[r["doc_id"]] or "", add_special_tokens=False).ids, 2], dtype="<u4")
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    token_store.write_ids(docs.limit(0), f"file://{tmp_path}/none")
    assert token_store.read_ids(spark, f"file://{tmp_path}/none").count() == 0
    wide = np.array([0, 255, 256, 65535, 65536, 2**24, 2**32 - 1], dtype="<u4")
    assert (token_store.unpack_ids(*token_store.pack_ids(wide), 7) == wide).all()


def test_packing_keeps_every_id(spark, docs):
    pieces = packing.pack(docs, limit=64).collect()
    per_doc, per_seq = Counter(), {}
    for p in pieces:
        per_doc[p["doc_id"]] += p["length"]
        per_seq.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
    coder = packing.pieces_of(public_tokenizers.path("byte_bpe_50k.json"))
    for d in docs.groupBy("doc_id", "text").count().collect():
        assert per_doc[d["doc_id"]] == d["count"] * (len(coder.encode(d["text"] or "")) // 4 + 1)
    for spans in per_seq.values():
        at = 0
        for o, n in sorted(spans):
            assert o == at
            at += n
        assert at <= 64
    assert packing.pack(docs.limit(0)).count() == 0
    sizes = [5, 4, 3, 3, 2, 2, 1]
    bins: Counter = Counter()
    for (b, _), n in zip(packing.first_fit_decreasing(sizes, 10), sizes, strict=True):
        bins[b] += n
    assert bins == {0: 10, 1: 10}


def test_near_groups_are_exact(spark):
    rng = np.random.default_rng(3)
    texts, words = [], [f"w{i}" for i in range(400)]
    for _ in range(12):
        base = list(rng.choice(words, 120))
        for _ in range(6):
            copy = list(base)
            for k in rng.choice(120, rng.integers(0, 7), replace=False):
                copy[k] = "new" + str(rng.integers(1e9))
            texts.append(" ".join(copy))
    texts += [None, "", "one two", "one two", "One  Two"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sets = [frozenset(tuple(w[i : i + 4]) for i in range(len(w) - 3)) if len(w) >= 4 else frozenset([tuple(w)] if w else []) for w in ((t or "").lower().split() for t in texts)]
    root = list(range(len(texts)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            k = len(sets[i] & sets[j])
            if sets[i] and 100 * k >= 80 * (len(sets[i]) + len(sets[j]) - k) and sets[j]:
                a, b = sorted((top(i), top(j)))
                root[b] = a
    got = {r["doc_id"]: r for r in near_dedup.near_groups(df, width=4).collect()}
    assert {d: r["component_id"] for d, r in got.items()} == {i: top(i) for i in range(len(texts))}
    assert all(r["n_shingles"] == len(sets[d]) and r["kept"] == (d == r["component_id"]) for d, r in got.items())


def brute_near(data, width=5, percent=80):
    """Root (place of the first row) of every (doc_id, text)."""
    def shingles(t):
        w = (t or "").lower().split()
        return frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])

    sets, root = [shingles(t) for _, t in data], list(range(len(data)))
    for i in range(len(data)):
        for j in range(i):
            k = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * k >= percent * (len(sets[i]) + len(sets[j]) - k):
                a, b = sorted((root[i], root[j]))
                root = [a if r == b else r for r in root]
    return root, sets


def test_near_copies_go_by_row_not_by_id(spark):
    words = lambda k, n=60: [f"{k}{i}" for i in range(n)]
    near = lambda k: " ".join([*words(k)[:58], "x", "y"])
    text = {k: " ".join(words(k)) for k in "abcdefgh"}
    data = [
        (None, text["a"]), (None, text["b"]), (None, text["c"]), (5, text["d"]), (5, text["e"]), (3, near("d")), (7, text["f"]), (7, text["f"]), (7, near("f")), (8, text["f"]),
        (None, text["g"]), (None, near("g")), (9, text["h"]), (None, near("h")), (4, None), (4, ""), (4, " \n"), (None, None), (6, "one two"), (6, "one  two"), (6, "One three"),
    ]
    root, sets = brute_near(data)
    low = {}
    for (i, _), r in zip(data, root):
        low[r] = min(low.get(r, 99), 99 if i is None else i)
    df = spark.createDataFrame([(i, t, n) for n, (i, t) in enumerate(data)], "doc_id long, text string, n int")
    got = sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in near_dedup.near_groups(df.repartition(3)).collect()), key=str)
    want = [(i, len(sets[n]), (None if low[root[n]] == 99 else low[root[n]]) if sets[n] else i) for n, (i, _) in enumerate(data)]
    assert got == sorted(want, key=str)
    kept = [r["n"] for r in near_dedup.drop_near_copies(df.repartition(3)).collect()]
    wordless = {n for n, s in enumerate(sets) if not s}
    assert wordless <= set(kept) and sorted(root[n] for n in kept if n not in wordless) == sorted({r for n, r in enumerate(root) if n not in wordless})
    assert all(data[n][0] == (None if low[root[n]] == 99 else low[root[n]]) for n in kept if n not in wordless)
    assert rows(near_dedup.near_groups(df, agree=1), "doc_id", "component_id") == rows(near_dedup.near_groups(df), "doc_id", "component_id")


def test_near_groups_edges(spark, docs):
    got = near_dedup.near_groups(docs)
    assert got.count() == docs.count() and near_dedup.near_groups(docs.limit(0)).count() == 0
    assert near_dedup.drop_near_copies(docs).columns == docs.columns


def test_block_count_finds_links_across_roots():
    import pyarrow as pa

    t = pa.table({"asks": [True, False, False], "id": [1, 2, 3], "root": [1, 2, 1], "found": pa.array([[1, 2, 3, 4, 5], [1, 2, 3, 4, 5, 6], [1, 2, 3, 4, 5]], pa.list_(pa.int64()))})
    assert near_dedup._count_block(t, 80).to_pylist() == [{"a": 1, "b": 2}]


def test_license_scan(spark, docs):
    got = license_scan.scan(docs).collect()
    assert len(got) == docs.count()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in got:
        n, places, starts, labels = license_scan.brute_base(texts[r["doc_id"]])
        assert (r["n_words"], r["n_base"], r["base_labels"]) == (n, places, labels)
        assert (r["first_word"], r["last_word"]) == ((starts[0], starts[-1]) if starts else (None, None))
    apache = "Licensed under the Apache License, Version 2.0 (the License); you may surely not use this file except in compliance with the License."
    one = license_scan.scan(spark.createDataFrame([(1, apache)], "doc_id long, text string")).first()
    assert one["labels"] == "apache" and one["n_base"] == 1


def brute_licences(text):
    """Labels and score by looking at every diagonal of every template."""
    words = [w for w in re.split(license_scan.GAPS, (text or "").encode().lower().decode()) if w]
    pairs, labels, score = {}, set(), 0.0
    for i, p in enumerate(zip(words, words[1:])):
        pairs.setdefault(p, []).append(i)
    for phrase, label in [*license_scan.BASE.items(), *license_scan.ADDED.items()]:
        p = phrase.split()
        grams = list(zip(p, p[1:]))
        votes = [(k, i) for k, g in enumerate(grams) for i in pairs.get(g, [])]
        for d in {i - k for k, i in votes}:
            reach = 0 if len(grams) < license_scan.LOOSE else license_scan.DRIFT
            pool = sorted((k, i) for k, i in votes if abs(i - k - d) <= reach)
            share = len({k for k, _ in pool}) / len(grams)
            if reach and share >= license_scan.ENOUGH:
                longest = [1] * len(pool)
                for x, (k, i) in enumerate(pool):
                    longest[x] = 1 + max((longest[y] for y in range(x) if pool[y][0] < k and pool[y][1] < i), default=0)
                share = max(longest) / len(grams)
            score = max(score, share)
            if share >= (license_scan.ENOUGH if reach else 1):
                labels.add(label)
    return ",".join(sorted(labels)), score


def test_licence_spans_are_verified(spark):
    phrase = next(p for p in license_scan.ADDED if p.startswith("redistribution"))
    w = phrase.split()
    rng = np.random.default_rng(5)
    texts = [phrase, " ".join([*w[:5], "surely", *w[5:]]), " ".join(w[:9] + w[11:]), " ".join(w[10:] + w[:10]), " ".join(["x"] * 30 + w + ["y"] * 9 + w), " ".join(w[::-1]), "and use in " * 40, None, ""]
    texts += [" ".join(x for k in range(len(w)) for x in ([w[k]] if rng.random() < 0.9 else [w[k], "extra"] if rng.random() < 0.5 else [])) for _ in range(25)]
    texts += [" ".join(rng.choice(w, 60)) for _ in range(10)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in license_scan.scan(df).collect()}
    for i, t in enumerate(texts):
        labels, score = brute_licences(t)
        assert got[i]["labels"] == labels and np.isclose(got[i]["score"], score)
    found = sorted((r["start"], r["stop"]) for r in license_scan.spans(df).filter("doc_id = 4 and label = 'bsd'").collect())
    n = len(w)
    assert found == [(30, 30 + n), (39 + n, 39 + 2 * n)]
    # votes on neighbouring diagonals in the wrong order are no chain
    assert license_scan.in_order({0: 0b10, 2: 0b01}, 2)[0] == 1 and license_scan.in_order({0: 0b11}, 2) == (2, 0, 3)


def odd_texts():
    rng = np.random.default_rng(8)
    stable = "ab Z9 \u00e9\u00df\u65e5\u672c\u3000\n\t's'll!?\u0416\u0661\U0001f600"
    odd = [chr(c) for c in sorted(packing.odd_of_library())]
    return ["\U00018e76\u6d8e"] + ["".join(rng.choice(list(stable) + list(rng.choice(odd, 6)), rng.integers(1, 40))) for _ in range(1500)]


def test_splits_are_the_libraries():
    import tiktoken
    from tokenizers import Tokenizer

    c = bpe.coder(bpe.default_ranks(), public_tokenizers.PATTERN)
    own = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=c.ranks, special_tokens={})
    path = public_tokenizers.path("byte_bpe_50k.json")
    library, pieces = Tokenizer.from_file(path), packing.pieces_of(path)
    library.encode_special_tokens = True
    for text in odd_texts():
        assert np.frombuffer(c.encode(text), "<u4").tolist() == own.encode_ordinary(text)
        assert np.frombuffer(pieces.encode(text), "<u4").tolist() == library.encode(text, add_special_tokens=False).ids
    c.encode("q" * 70)
    assert max(map(len, c)) <= 64


def test_packing_is_the_library(spark, docs):
    """Every piece holds the library's ids, sequences are gapless and short of the limit only by less than a piece."""
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    library.encode_special_tokens = True
    table = spark.createDataFrame([(n, r["text"]) for n, r in enumerate(docs.collect())] + [(100 + n, t) for n, t in enumerate(odd_texts()[:40])], "doc_id long, text string")
    limit, cut, sequences = 64, {}, {}
    for p in packing.pack(table, limit=limit).collect():
        cut.setdefault(p["doc_id"], []).append(p)
        sequences.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
    for r in table.collect():
        ids = np.array([*library.encode(r["text"] or "", add_special_tokens=False).ids, 0], "<u4")
        at = 0
        for p in sorted(cut[r["doc_id"]], key=lambda p: p["start"]):
            assert (p["start"], p["doc_tokens"]) == (at, len(ids)) and p["ids_crc32"] == zlib.crc32(ids[at : at + p["length"]].tobytes())
            at += p["length"]
        assert at == len(ids)
    filled = [sum(n for _, n in s) for s in sequences.values()]
    assert max(filled) <= limit and sum(x < limit // 2 for x in filled) <= 1


def test_quality_rules(spark, docs):
    got = quality_rules.judge(docs, docs.filter("doc_id = 3")).collect()
    assert len(got) == docs.count()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in got:
        t = texts[r["doc_id"]] or ""
        words = [x for x in re.split(r"[\x20\x09-\x0D]+", t) if x]
        windows = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
        covered = {i + k for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for k in range(3)}
        lines = [x for x in t.split("\n") if x.strip(" \t\n\r\x0b\x0c")]
        want = (len(words), sum(map(len, words)), sum(t.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered))
        assert tuple(r[k] for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")) == want
        assert r["base_failed"] == (len(words) < 50 or 100 * len(covered) > 50 * len(words))
    assert quality_rules.keep_ruled(docs, docs.limit(0)).columns == docs.columns


def test_least_ratio_parts_labels(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    got = quality_rules.judge(docs, quality_rules.trusted_of(labels)).join(labels, "doc_id").filter("not base_failed").collect()
    good, bad = ([r["kept"] for r in got if r["quality"] == q] for q in (1, 0))
    assert np.mean(good) > 0.97 and np.mean(bad) < 0.2


def test_ratios_and_verdict_by_brute_force(spark):
    rng = np.random.default_rng(4)
    texts = [" ".join(rng.choice([f"{kind}{i}" for i in range(300)], 80)) for kind in "ab" for _ in range(60)] + ["a1 a2", None, "a1 " * 90]
    trusted = set(range(40)) | {120, 121}
    words = [(t or "").split() for t in texts]
    h = lambda w, seed=42: xxhash.xxh64_intdigest(w.encode(), seed)
    size = quality_rules.BUCKETS
    grams = [[h(w) % size for w in ws] + [h(v, h(w)) % size for w, v in zip(ws, ws[1:])] for ws in words]
    apart = {d for d in trusted if zlib.crc32(str(d).encode()) % 5 == 1}

    def means(chosen):
        raw, good = np.ones(size), np.ones(size)
        for d, g in enumerate(grams):
            np.add.at(raw, g, 1)
            np.add.at(good, g, int(d in chosen))
        ratio = np.log(good / good.sum()) - np.log(raw / raw.sum())
        return [ratio[g].mean() if g else 0.0 for g in grams]

    voters = sorted(x for d, x in enumerate(means(trusted - apart)) if d in apart and len(words[d]) >= 50)
    least = np.floor(voters[int(0.01 * len(voters))] * 1000) / 1000
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    ids = spark.createDataFrame([(d,) for d in [*trusted, None]], "doc_id long")
    got = {r["doc_id"]: r for r in quality_rules.judge(df, ids).collect()}
    own = means(trusted)
    for d, r in got.items():
        assert np.isclose(r["llr"], own[d], atol=1e-4) and r["kept"] == (len(words[d]) >= 50 and d != 122 and own[d] >= least)
    assert {r["doc_id"] for r in quality_rules.keep_ruled(df, ids).collect()} == {d for d, r in got.items() if r["kept"]} != set()
    # no trusted document is set apart: the ratio fails none
    one = quality_rules.judge(df, ids.filter(f"doc_id = {min(trusted - apart)}")).collect()
    assert all(r["kept"] != r["base_failed"] for r in one)


def test_archives(spark, tmp_path):
    big, pages = "<p>" + "x" * 2000, None
    pages = spark.createDataFrame([(1, "http://a", big), (2, None, big), (3, "http://c\r\n", "small"), (4, "u", None), (5, "u", big), (None, "u", big), (6, "u", "small")], "page_id long, url string, html string")
    uri = f"file://{tmp_path}/warc"
    manifest = warc.write_archives(pages, uri, shards=2, roll=1)
    got = {r["page_id"]: r for r in warc.read_archives(spark, uri).collect()}
    assert got[1]["refers_to"] == got[2]["refers_to"] == 5 and got[5]["record_type"] == "response" == got[3]["record_type"] == got[None]["record_type"]
    assert got[2]["payload_bytes"] == 2003 and got[4]["payload_digest"] == hashlib.sha1(b"").hexdigest()
    files = [r["file"] for r in manifest.collect()]
    first = gzip.decompress(open(f"{tmp_path}/warc/{sorted(files)[0]}", "rb").read())
    assert first.startswith(b"WARC/1.1\r\n") and len(files) == 7
    assert base64.b32encode(hashlib.sha1(big.encode()).digest()) in b"".join(gzip.decompress(open(f"{tmp_path}/warc/{f}", "rb").read()) for f in files)
    again = warc.write_archives(pages, f"file://{tmp_path}/again", shards=2, roll=1)
    read = lambda where, f: open(f"{tmp_path}/{where}/{f}", "rb").read()
    assert all(read("warc", r["file"]) == read("again", r["file"]) for r in again.collect())


def test_factor_machine(spark, docs):
    rng = np.random.default_rng(0)
    model = factor_machine.FactorMachine(0.1, rng.normal(0, 1, 9).astype("f4"), rng.normal(0, 1, (9, 3)).astype("f4"))
    index, value = np.array([1, 4, 7]), np.array([1.0, 0.5, 2.0], "f4")
    pairs = sum(model.factor[a] @ model.factor[b] * x * y for i, (a, x) in enumerate(zip(index, value)) for b, y in list(zip(index, value))[:i])
    assert np.isclose(model.raw(index, value, np.array([0]))[0][0], 0.1 + (model.weight[index] * value).sum() + pairs, atol=1e-4)
    labels = spark.createDataFrame([(3, 1), (9, 0), (10, 0), (4, 1), (None, 1)], "doc_id long, quality int")
    got = factor_machine.score(docs, factor_machine.train(docs, labels)).collect()
    assert len(got) == docs.count() and all(0 <= r["score"] <= 1 for r in got)


def test_fit_rows_are_bounded(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(factor_machine, "fit", lambda pairs, labels: seen.append((len(pairs), sum(len(i) for i, _ in pairs))))
    docs = spark.createDataFrame([(i % 50, f"word{i} " * 5 + " ".join(f"w{k}" for k in range(i % 7)), 9) for i in range(500)], "doc_id long, text string, n_chars long")
    labels = spark.createDataFrame([(i, i % 2) for i in range(50)], "doc_id long, quality int")
    for bounds in ({}, {"fit_rows": 20}, {"fit_features": 100}):
        factor_machine.train(docs, labels, **bounds)
    free = sum(zlib.crc32(str(i).encode()) % 5 != 0 for i in range(50))
    assert seen[0][0] == free and seen[1][0] == 20 and 0 < seen[2][1] <= 100


def test_classifier_held_out(spark):
    d = "/root/testdata/sf0.1"
    got = factor_machine.op1_quality_fm(spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").filter("held_out")
    n, right = got.count(), got.filter("predicted = quality").count()
    assert right / n > 0.95


def test_language_model(spark, docs):
    got = recurrent_lm.lm_scores(docs, start_docs=5, held_words=20).collect()
    assert len(got) == docs.count()
    texts = [(r["doc_id"], r["text"] or "") for r in docs.collect()]
    counts: Counter = Counter()
    for d, t in texts:
        if zlib.crc32(("" if d is None else str(d)).encode()) % 5 != 1:
            counts.update(recurrent_lm.tokens(t))
    n, v, by = sum(counts.values()), len(counts), dict(texts)
    for r in got:
        words = recurrent_lm.tokens(by[r["doc_id"]])
        assert r["train_tokens"] == n and r["n_tokens"] == len(words) and r["n_known"] == sum(counts[w] > 0 for w in words)
        assert np.isclose(r["base_score"], sum(np.log10((counts[w] + 0.5) / (n + 0.5 * (v + 1))) for w in words)) and r["score"] < 0
    assert recurrent_lm.lm_scores(docs.limit(0)).count() == 0


def slow_score(model, words):
    """Log probability of a stream, a step at a time in plain 64-bit arithmetic."""
    m = {k: v.astype(np.float64) for k, v in model.items()}
    h, size, state, total, last = recurrent_lm.HIDDEN, recurrent_lm.MEMBERS, np.zeros(recurrent_lm.HIDDEN), 0.0, 0
    for w in words.tolist():
        x, again = m["embed"][last] + m["bias"], state @ m["update"]
        z, r = (1 / (1 + np.exp(-(x[i * h : (i + 1) * h] + again[i * h : (i + 1) * h]))) for i in (0, 1))
        state = (1 - z) * np.tanh(x[2 * h :] + r * again[2 * h :]) + z * state
        kinds = np.exp(state @ m["class_w"] + m["class_b"])
        inside = np.exp(state @ m["word_w"][w // size] + m["word_b"][w // size])
        total += np.log(kinds[w // size] / kinds.sum() * inside[w % size] / inside.sum())
        last = w
    return total


def grown_model(seed=2):
    rng = np.random.default_rng(seed)
    return {k: (v + rng.normal(0, 0.3, v.shape)).astype(np.float32) for k, v in recurrent_lm.fresh().items()}


def test_scores_by_a_slow_reference():
    rng, model = np.random.default_rng(0), grown_model()
    streams = [rng.integers(0, 1024, n).astype(np.int32) for n in (1, 15, 16, 17, 50, 333, 2, 64)]
    got = recurrent_lm.score_streams(model, streams, lanes=3)
    assert np.allclose(got, [slow_score(model, s) for s in streams], rtol=1e-4)


def test_windows_carry_every_stream():
    rng = np.random.default_rng(1)
    streams = [rng.integers(0, 1024, n).astype(np.int32) for n in rng.integers(1, 120, 40)]
    heard, read, owner, begun = {}, {}, {}, 0
    for live, fresh, ids, goals in recurrent_lm.windows(iter(streams), 5, 100):
        assert ids.shape == goals.shape and len(ids) == recurrent_lm.WINDOW
        for column, (lane, new) in enumerate(zip(live.tolist(), fresh.tolist())):
            if new:
                owner[lane], begun = begun, begun + 1
            real = goals[:, column] >= 0
            heard.setdefault(owner[lane], []).extend(goals[real, column].tolist())
            read.setdefault(owner[lane], []).extend(ids[real, column].tolist())
    assert [heard[i] for i in range(40)] == [s.tolist() for s in streams]
    assert [read[i] for i in range(40)] == [[0, *s[:-1].tolist()] for s in streams]


def test_gradients_by_differences():
    rng, model = np.random.default_rng(3), {k: v.astype(np.float64) for k, v in grown_model().items()}
    ids, goals = rng.integers(0, 1024, (5, 3)).astype(np.int32), rng.integers(0, 1024, (5, 3)).astype(np.int32)
    goals[3:, 1] = -1
    state = rng.normal(0, 0.5, (3, recurrent_lm.HIDDEN)).astype(np.float32)
    real = goals >= 0

    def loss(m):
        out, _ = recurrent_lm.forward({k: v.astype(np.float32) for k, v in m.items()}, ids, state)
        return -float(recurrent_lm.log_probs(m, out[real].astype(np.float64), goals[real]).sum()) / real.sum()

    grads, _, total = recurrent_lm.gradients({k: v.astype(np.float32) for k, v in model.items()}, ids, goals, state)
    assert np.isclose(total / real.sum(), loss(model), rtol=1e-4)
    for name, g in grads.items():
        for at in np.argsort(-np.abs(g).reshape(-1))[:4]:
            step = 1e-2
            up, down = ({k: v.copy() for k, v in model.items()} for _ in (0, 1))
            up[name].reshape(-1)[at] += step
            down[name].reshape(-1)[at] -= step
            assert np.isclose((loss(up) - loss(down)) / (2 * step), g.reshape(-1)[at], rtol=0.05, atol=2e-4), name


def test_windows_of_one_step_go_back_together():
    """300 words on a lane alone are 19 windows but one step; their gradients were made a window at a time, and are the same."""
    rng = np.random.default_rng(3)
    stream, learner = rng.integers(0, 1024, 300).astype(np.int32), recurrent_lm.Learner(recurrent_lm.fresh(), 0.01)
    taken, passes, backward = [], [], recurrent_lm._backward
    learner._step = taken.append
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(recurrent_lm, "_backward", lambda *a: passes.append(1) or backward(*a))
        loss, words = learner.learn([stream])
    assert len(passes) == len(taken) == 1 and words == 300
    want, total, state = {}, 0.0, np.zeros((1, recurrent_lm.HIDDEN), np.float32)
    for _, _, ids, goals in recurrent_lm.windows(iter([stream]), 1):
        grads, state, part = recurrent_lm.gradients(learner.model, ids, goals, state, recurrent_lm.LANES * recurrent_lm.WINDOW)
        want, total = {k: g + want.get(k, 0) for k, g in grads.items()}, total + part
    assert abs(loss - total) < 1e-2 and all(np.allclose(taken[0][k], g, atol=1e-6) for k, g in want.items())


def test_sums_by_word():
    rng = np.random.default_rng(4)
    ids, rows = np.append(rng.integers(0, 90, 300), [7] * 200).astype(np.int32), rng.normal(size=(500, 6)).astype(np.float32)
    want, got = np.zeros((100, 6)), np.zeros((100, 6), np.float32)
    np.add.at(want, ids, rows)
    recurrent_lm._add_by_word(got, ids, rows)
    assert np.allclose(got, want, atol=1e-4)


def test_a_long_text_takes_little_memory():
    import tracemalloc

    model, long_text = recurrent_lm.fresh(), np.random.default_rng(0).integers(0, 1024, 120_000).astype(np.int32)
    tracemalloc.start()
    recurrent_lm.score_streams(model, [long_text, *[long_text[:9]] * 600])
    assert tracemalloc.get_traced_memory()[1] < 60e6
    tracemalloc.stop()


def test_pipeline_by_brute_force(spark, tmp_path):
    """Every stage's rows, on its own input, against plain Python; ids are null, shared by different texts and repeated."""
    import corpus_pipeline
    from tokenizers import Tokenizer

    sf = str(tmp_path)
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    labels.write.parquet(f"{sf}/labels.parquet")
    given = spark.read.parquet(f"{SF}/documents.parquet")
    long_ones = [r["text"] for r in given.filter("length(text) > 600").orderBy("doc_id").limit(12).collect()]
    odd = [(None, long_ones[0] + " x1"), (None, long_ones[1] + " x2"), (5, long_ones[2]), (5, long_ones[3] + " x3"), (7, long_ones[4]), (7, long_ones[4]), (None, long_ones[5]), (0, None), (None, ""), (3, " ".join(long_ones))]
    more = spark.createDataFrame([(i, t, "en", "odd", len(t or "")) for i, t in odd], given.schema)
    given.unionByName(more).repartition(3).withColumn("n", F.monotonically_increasing_id()).write.parquet(f"{sf}/documents.parquet")
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    plain = lambda t: re.sub(r"[\x20\x09-\x0D]", "", t or "")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = docs.collect()
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns
        out.write.parquet(f"{sf}/{name}")
        docs = spark.read.parquet(f"{sf}/{name}")
        kept = sorted(r["n"] for r in docs.collect())
        if name == "quality_rules":
            verdicts = quality_rules.judge(spark.read.parquet(f"{sf}/documents.parquet"), quality_rules.trusted_of(labels)).collect()
            assert Counter(r["doc_id"] for r in docs.collect()) == Counter(r["doc_id"] for r in verdicts if r["kept"])
            for r in before:
                words = (r["text"] or "").split()
                assert len(words) >= 50 or r["n"] not in kept
        elif name == "quality_classifier":
            model = factor_machine.train(spark.createDataFrame(before, docs.schema), labels)
            index = [factor_machine.features(r["text"] or "", r["n_chars"]) for r in before]
            brute = [model.bias + (model.weight[i] * v).sum() + ((p := model.factor[i] * v[:, None]) @ p.T)[np.triu_indices(len(i), 1)].sum() for i, v in index]
            assert kept == sorted(r["n"] for r, x in zip(before, brute) if 1 / (1 + np.exp(-x)) >= 0.3)
        elif name == "exact_dedup":
            best = {}
            for r in before:
                rank = (-len(r["text"] or ""), r["doc_id"] is None, r["doc_id"] or 0, r["text"] or "", r["lang"] or "", r["source"] or "", r["n_chars"] or 0, r["n"])
                best[plain(r["text"])] = min(best.get(plain(r["text"]), (rank, r["n"])), (rank, r["n"]))
            assert kept == sorted(n for _, n in best.values())
        else:
            root, sets = brute_near([(r["doc_id"], r["text"]) for r in before])
            groups = {}
            for r, k, s in zip(before, root, sets):
                groups.setdefault(k if s else ("alone", r["n"]), []).append((r["doc_id"] is None, r["doc_id"] or 0, r["n"]))
            assert len(kept) == len(groups) and len(groups) < len(before)
            assert all(sum(n in kept for _, _, n in g) == 1 and next(x[:2] for x in g if x[2] in kept) == min(g)[:2] for g in groups.values())
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    library.encode_special_tokens = True
    whole = Counter()
    for p in corpus_pipeline.packing(spark, docs, sf).collect():
        whole[p["doc_id"]] += p["length"]
    want = Counter()
    for r in docs.collect():
        want[r["doc_id"]] += len(library.encode(r["text"] or "", add_special_tokens=False).ids) + 1
    assert whole == want and corpus_pipeline.run(spark, sf).count() > 0


def test_pipeline(spark):
    import corpus_pipeline

    assert [n for n, _ in corpus_pipeline.STAGES][-1] == "packing"
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    ruled = corpus_pipeline.quality_rules(spark, docs, SF)
    assert ruled.columns == docs.columns and 0 < ruled.count() < docs.count()
    assert corpus_pipeline.run(spark, SF).count() > 0
