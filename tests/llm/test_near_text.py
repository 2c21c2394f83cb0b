"""Near-duplicate texts against brute-force Jaccard of five-word shingles."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from optjoin.llm import near_text
from optjoin.llm.session import cut
from optjoin.llm.simhash import fingerprints_of


def shingles(text):
    w = (text or "").lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def kept_by_force(rows):
    sets = [(d, shingles(t)) for d, t in rows if d is not None]
    root = {d: d for d, _ in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, (d, a) in enumerate(sets):
        for e, b in sets[:i]:
            if a and b and len(a & b) / len(a | b) >= 0.8:
                x, y = find(d), find(e)
                root[max(x, y)] = min(x, y)
    return sorted(((d, t) for d, t in rows if d is None or find(d) == d), key=str)


def near_pairs(seed, pairs, length, span=(0.7, 0.9)):
    """Pairs (ids 2i and 2i + 1) of texts of about `length` words, the second cut at its end to a similarity in this span."""
    draw = random.Random(seed)
    out = []
    for i in range(pairs):
        n = draw.randrange(length // 2, length * 3 // 2)
        w = [f"p{i}w{draw.randrange(10**6)}" for _ in range(n)]
        share = draw.uniform(*span)
        extra = draw.randrange(1, n)
        other = w[: max(1, round((n - 4) * share) + 4)] if draw.random() < 0.5 else w + [f"q{i}w{j}" for j in range(round((n - 4) * (1 / share - 1)))]
        if draw.random() < 0.3:
            other = other[:extra] + other[extra:]
        out += [(2 * i, " ".join(w)), (2 * i + 1, " ".join(other))]
    return out


def kept(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    return sorted(((r.doc_id, r.text) for r in near_text.distinct_texts(docs).collect()), key=str)


@pytest.mark.parametrize("span", [(0.76, 0.8), (0.8, 0.84)])
def test_decisions_near_the_threshold(spark, span):
    rows = near_pairs(1, 120, 1000, span)
    assert kept(spark, rows) == kept_by_force(rows)


def test_exact_links_of_chains_and_copies():
    draw = np.random.default_rng(3)
    base = np.unique(draw.integers(0, 1 << 62, 400).astype(np.uint64))
    sets = [base[i * 15 : i * 15 + 200] for i in range(12)] + [base[:200], base[:0], base[:0]]
    first = np.concatenate([[0], np.cumsum([len(x) for x in sets])])
    found = near_text.exact_links(np.concatenate(sets), first, 0.8)
    ids = np.arange(len(sets)) + 100
    assert near_text.repeats(ids, found) and sorted(near_text.repeats(ids, found)) == [*range(101, 113)]
    assert near_text.exact_links(np.concatenate(sets), first, 0.95) == [(0, 12)]


def short_texts(seed, pairs):
    """Pairs of texts of 12 to 60 words with an edit in the middle, among many that share a passage, and copies."""
    draw = random.Random(seed)
    common = " ".join(f"licence{i}" for i in range(12))
    out = []
    for i in range(pairs):
        w = [f"s{i}w{draw.randrange(10**6)}" for _ in range(draw.randrange(12, 61))]
        other = list(w)
        if draw.random() < 0.8:
            other[draw.choice([0, 1, -1, len(w) // 2])] = "edit"
        tail = " " + common if draw.random() < 0.4 else ""
        out += [(2 * i, " ".join(w) + tail), (2 * i + 1, " ".join(other).upper() + tail)]
    return [*out, (9001, common), (9000, common), (9002, None), (9003, " "), (None, common), (9004, "one two"), (9005, "One  two"), (9005, "one two three")]


@pytest.mark.parametrize("shard_bytes", [4 << 20, 20_000])
def test_all_candidates_are_found(spark, shard_bytes):
    rows = short_texts(2, 400)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    found = near_text.distinct_texts(docs, shard_bytes=shard_bytes).collect()
    assert sorted(((r.doc_id, r.text) for r in found), key=str) == kept_by_force(rows)
    assert near_text.distinct_texts(docs.limit(0)).count() == 0


def bits_apart(a, b):
    flat = [np.frombuffer(t.encode(), np.uint8) for t in (a, b)]
    one, two = fingerprints_of(np.concatenate(flat), np.cumsum([0, *map(len, flat)]))
    return int(np.bitwise_count(one ^ two))


def test_documents_are_linked_by_fingerprints_and_by_texts(spark):
    import corpus_pipeline

    draw = random.Random(66)
    base = [f"w{draw.randrange(10**6)}" for _ in range(600)]
    spread = [f"e{i}" if i % 38 == 0 else w for i, w in enumerate(base)]
    short = ["the", "of", "and", *(f"word{i}" for i in range(120))]
    edit = ["other" if w == "word60" else w for w in short]
    texts = {1: base, 2: spread, 3: short, 4: edit, 5: [f"t{i}" for i in range(90)], 6: base, 7: [*base, "x"], 8: [*spread, "y"]}
    texts = {d: " ".join(w) for d, w in texts.items()} | {9: None, 10: " ", 11: "\t"}
    assert bits_apart(texts[3], texts[4]) > 4 >= bits_apart(texts[1], texts[2])
    one, two, three, four = (shingles(texts[d]) for d in (1, 2, 3, 4))
    assert len(one & two) / len(one | two) < 0.8 <= len(three & four) / len(three | four)
    docs = spark.createDataFrame([(d, t, "en", "s", 0) for d, t in texts.items()] + [(None, texts[1], "en", "s", 0)], "doc_id long, text string, lang string, source string, n_chars long")
    kept = sorted((r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()), key=str)
    assert kept == sorted([1, 3, 5, 9, 10, 11, None], key=str)


def shuffle_files(spark):
    """Name and bytes of the shuffle files that are on disk."""
    found = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    files = [found.apply(i) for i in range(found.size())]
    return {f.getName(): f.length() for f in files if f.getName().startswith("shuffle_")}


def test_cut_gives_up_the_shuffle_files(spark):
    docs = spark.range(1000).selectExpr("id % 50 AS a").groupBy("a").count().join(spark.range(50).repartition(7, "id"), F.col("a") == F.col("id"))
    before = {*shuffle_files(spark)}
    rows = cut(docs)
    assert not {*shuffle_files(spark)} - before
    assert sorted(rows.collect()) == sorted(docs.collect()) and rows.count() == 50


def test_near_duplicates_leave_no_shuffled_texts(spark):
    import corpus_pipeline

    draw = random.Random(5)
    texts = [" ".join(f"w{draw.randrange(10**6)}" for _ in range(300)) for _ in range(200)]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate([*texts, *texts[:50]])], "doc_id long, text string, lang string, source string, n_chars long")
    before = {*shuffle_files(spark)}
    out = corpus_pipeline.near_duplicates(spark, docs, "")
    left = sum(n for name, n in shuffle_files(spark).items() if name not in before)
    assert left < sum(map(len, texts)) // 20
    assert out.count() == 200
