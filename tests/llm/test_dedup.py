"""Deduplication operators against brute force, with nulls, ties, repeated rows, long and empty texts."""

import hashlib
import random
import re

import numpy as np
import pytest
import xxhash

from optjoin.llm import simhash
from optjoin.llm.rolling import word_bounds
from optjoin.llm.simhash import near_duplicates
from optjoin.llm.substring_dedup import remove_repeated_windows
from optjoin.llm.suffix_dedup import remove_repeats, sort_suffixes

WORDS = ["the", "and", "of", "lorem", "ipsum", "dolor", "sit", "éa", "x", "\n", "zzz", "a\tb", "sesquipedalian"]
LAST = 2**63 - 1


def rows(seed):
    draw = random.Random(seed)
    text = lambda n: " ".join(draw.choice(WORDS) for _ in range(n))
    base = [text(150) for _ in range(5)]
    out = []
    for i in range(70):
        b = draw.choice(base)
        a, c = draw.randrange(len(b)), draw.randrange(len(b))
        out.append((3 * i, draw.choice([b, b[a:] + text(5) + b[:c], text(30), b[min(a, c) : max(a, c)] * 2, "aaaa" * draw.randrange(40), None, "", b[:c] + text(3) + b[c:]])))
    return [*out, (6, base[0]), (6, base[0]), (None, base[1]), (9, text(50)), (10_000, text(3000))]


def frame(spark, data):
    from pyspark.sql import functions as F

    return spark.createDataFrame(data, "doc_id long, text string").withColumns({"src": F.lit("x"), "body": F.lit(1), "bucket": F.lit(None).cast("int")})


def key(i):
    return LAST if i is None else i


@pytest.mark.parametrize(("shard_bytes", "hot"), [(1 << 22, 4096), (3000, 4096), (3000, 3), (3000, 0)])
def test_suffix_dedup(spark, shard_bytes, hot):
    data, size = rows(1), 50
    first = {}
    for d, t in data:
        b = (t or "").encode()
        for i in range(len(b) - size + 1):
            first[b[i : i + size]] = min(first.get(b[i : i + size], LAST), key(d))
    want = []
    for d, t in data:
        b = (t or "").encode()
        gone = [False] * len(b)
        for i in range(len(b) - size + 1):
            if first[b[i : i + size]] < key(d):
                gone[i : i + size] = [True] * size
        spans = sum(g and not (i and gone[i - 1]) for i, g in enumerate(gone))
        want.append((d, len(b), sum(gone), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone, strict=True) if not g)).hexdigest()))
    got = [(r.doc_id, r.n_bytes, r.n_removed, r.n_spans, hashlib.sha256(r.kept).hexdigest()) for r in remove_repeats(frame(spark, data), shard_bytes=shard_bytes, hot=hot).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
    assert sum(x[2] for x in got) > 0


@pytest.mark.parametrize("slots", [1, 8])
def test_substring_dedup(spark, slots):
    data, size = rows(2), 50
    words = [re.findall(r"[^\x20\x09-\x0D]+", t or "") for _, t in data]
    first = {}
    for (d, _), w in zip(data, words, strict=True):
        for i in range(len(w) - size + 1):
            first[tuple(w[i : i + size])] = min(first.get(tuple(w[i : i + size]), LAST), key(d))
    want = []
    for (d, _), w in zip(data, words, strict=True):
        gone = [False] * len(w)
        for i in range(len(w) - size + 1):
            if first[tuple(w[i : i + size])] < key(d):
                gone[i : i + size] = [True] * size
        want.append((d, len(w), sum(gone), " ".join(x for x, g in zip(w, gone, strict=True) if not g)))
    got = [tuple(r) for r in remove_repeated_windows(frame(spark, data), shard_bytes=4000, slots_per_key=slots).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
    assert sum(x[2] for x in got) > 0


def test_suffix_sort_is_a_sort():
    text = np.frombuffer(b"banana_bandana_banana_bandana", np.uint8)
    order, equal = sort_suffixes(text, np.arange(len(text)), 6)
    cut = [bytes(text[i : i + 6]) for i in order]
    assert cut == sorted(cut)
    assert equal.tolist() == [i > 0 and cut[i] == cut[i - 1] for i in range(len(cut))]


def test_golay_keys_find_all_within_four_bits():
    draw = np.random.default_rng(1)
    p = draw.integers(0, 1 << 63, 2000).astype(np.uint64)
    q = p.copy()
    for _ in range(4):
        q ^= np.uint64(1) << draw.integers(0, 64, len(p)).astype(np.uint64)
    every = np.unique(np.concatenate([p, q]))
    row, keys, target = simhash.fuzzy_keys(every)
    a, b = simhash.link_groups(keys, every[row], target)
    found = set(zip(a.tolist(), b.tolist(), strict=True))
    assert {(min(x, y), max(x, y)) for x, y in zip(p.tolist(), q.tolist(), strict=True) if x != y} <= found


def fingerprint(text):
    text = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    shingles = [" ".join(w[i : i + 4]) for i in range(len(w) - 3)] if len(w) >= 4 else ([" ".join(w)] if w else [])
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def test_near_duplicates(spark):
    data = [(d, t) for d, t in rows(3) if d not in (None, 6, 9)]  # without ids of several texts
    data += [(5000 + i, t + " tail") for i, (_, t) in enumerate(data) if t]
    prints = {d: fingerprint(t) for d, t in data}
    got = {r.doc_id: r for r in near_duplicates(frame(spark, data)).collect()}
    assert {d: int(r.fingerprint, 16) for d, r in got.items()} == prints
    root = {d: d for d in prints}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(prints)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if (prints[a] ^ prints[b]).bit_count() <= 4:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    assert {d: r.component_id for d, r in got.items()} == {d: find(d) for d in ids}


@pytest.mark.parametrize("operator", [remove_repeats, remove_repeated_windows, near_duplicates])
def test_empty_table(spark, operator):
    assert operator(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_words_of_bytes():
    start, end = word_bounds(np.frombuffer(b"\t one  tw\xc2\xa0o\n", np.uint8))
    assert list(zip(start.tolist(), end.tolist(), strict=True)) == [(2, 5), (7, 12)]
