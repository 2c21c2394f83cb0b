"""SimHash near-duplicates by fuzzy keys of the binary Golay code.

A 64-bit fingerprint is cut into segments of 22, 21 and 21 bits, each taken as a word of the perfect
(23, 12) Golay code. Every word lies within 3 bits of one codeword, so
- words up to 2 bits apart have a common codeword within 4 bits of both, and
- words up to 1 bit apart: one has the other's nearest codeword within 4 bits.
A word has 1 or 6 codewords within 4 bits. By pigeonhole, fingerprints up to 4 bits apart either agree
in one segment and differ by at most 2 bits in another, or differ by 1 bit in each of two segments;
so they share a key made of an exact segment and a codeword, or of two codewords. Rows of a key are
compared exactly; a key's links are emitted as a spanning forest, never as all its pairs.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shards as sh
from .rolling import CHUNK, Memo, U, mix, word_bounds
from .session import cut

SEED, WORDS, DISTANCE = 42, 4, 4
SEGMENTS = ((0, 22), (22, 21), (43, 21))
_GENERATOR = 0b101011100011  # x^11 + x^9 + x^7 + x^6 + x^5 + x + 1
_tables = Memo()


def _remainder(word: int) -> int:
    for bit in range(22, 10, -1):
        if word >> bit & 1:
            word ^= _GENERATOR << (bit - 11)
    return word


def golay_errors() -> tuple[np.ndarray, np.ndarray]:
    """The remainder of each single bit, and for each of the 2048 remainders its error of at most 3 bits."""
    if "golay" not in _tables:
        unit = np.array([_remainder(1 << i) for i in range(23)], dtype=np.uint32)
        errors = np.zeros(2048, dtype=np.uint32)
        for a in range(23):
            errors[unit[a]] = 1 << a
            for b in range(a):
                errors[unit[a] ^ unit[b]] = 1 << a | 1 << b
                for c in range(b):
                    errors[unit[a] ^ unit[b] ^ unit[c]] = 1 << a | 1 << b | 1 << c
        _tables["golay"] = unit, errors
    return _tables["golay"]


def nearest(words: np.ndarray) -> np.ndarray:
    """The 12-bit index of the nearest codeword of each 23-bit word."""
    unit, errors = golay_errors()
    rest = np.zeros(len(words), dtype=np.uint32)
    for i in range(23):
        rest ^= np.where(words >> np.uint32(i) & np.uint32(1), unit[i], np.uint32(0)).astype(np.uint32)
    return (words ^ errors[rest]) >> np.uint32(11)


def codewords_within_4(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, index) of every codeword within 4 bits: the nearest, and those of the words one bit away."""
    near = np.stack([nearest(words ^ np.uint32(1 << i if i < 23 else 0)) for i in range(24)], axis=1)
    near.sort(axis=1)
    first = np.ones(near.shape, dtype=bool)
    first[:, 1:] = near[:, 1:] != near[:, :-1]
    row, col = np.nonzero(first)
    return row, near[row, col]


def _product(n: int, a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each row, all combinations of its values in a and in b (rows ascending in both)."""
    in_b = np.bincount(b[0], minlength=n)
    start = np.cumsum(in_b) - in_b
    times = in_b[a[0]]
    left = np.repeat(np.arange(len(a[0])), times)
    right = np.arange(int(times.sum())) - np.repeat(np.cumsum(times) - times, times) + np.repeat(start[a[0]], times)
    return a[0][left], a[1][left], b[1][right]


def fuzzy_keys(prints: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, key, whether others look for the row under this key) of every fingerprint."""
    n = len(prints)
    words = [(prints >> U(at) & U((1 << bits) - 1)).astype(np.uint32) for at, bits in SEGMENTS]
    near = [codewords_within_4(w) for w in words]
    rows, keys, found = [], [], []

    def add(row: np.ndarray, tag: int, a: np.ndarray, b: np.ndarray, target: bool) -> None:
        rows.append(row)
        keys.append(mix(U(tag << 56) | a.astype(np.uint64) << U(24) | b.astype(np.uint64)))
        found.append(np.full(len(row), target))

    for i in range(3):
        for j in range(3):
            if i != j:
                add(near[j][0], 3 * i + j, words[i][near[j][0]], near[j][1], True)
            if i < j:
                row, a, b = _product(n, near[i], near[j])
                target = (a == nearest(words[i])[row]) & (b == nearest(words[j])[row])
                rows.append(row)
                keys.append(mix(U((9 + 3 * i + j) << 56) | a.astype(np.uint64) << U(24) | b.astype(np.uint64)))
                found.append(target)
    return np.concatenate(rows), np.concatenate(keys), np.concatenate(found)


def _forest(prints: np.ndarray, distance: int) -> list[tuple[int, int]]:
    """A spanning forest of the links in one group: a wave takes in what it reaches, so dense groups cost little."""
    left, out = np.arange(len(prints)), []
    while len(left):
        wave, left = left[:1], left[1:]
        while len(wave) and len(left):
            node, wave = wave[0], wave[1:]
            near = np.bitwise_count(prints[left] ^ prints[node]) <= distance
            out += [(int(node), int(x)) for x in left[near]]
            wave, left = np.concatenate([wave, left[near]]), left[~near]
    return out


def link_groups(key: np.ndarray, prints: np.ndarray, target: np.ndarray, distance: int = DISTANCE, small: int = 6) -> tuple[np.ndarray, np.ndarray]:
    """Links (a < b) that connect what is linked within each key that has a target; distinct."""
    order = np.lexsort((prints, key))
    key, prints, target = key[order], prints[order], target[order]
    head = np.flatnonzero(sh.first_of_runs(key))
    size = np.diff(head, append=len(key))
    useful = (size > 1) & np.logical_or.reduceat(target, head) if len(head) else np.zeros(0, bool)
    found_a, found_b = [], []
    for step in range(1, small):  # pairs at each step apart, for all small groups at once
        at = np.flatnonzero(np.repeat(useful & (size <= small), size))
        ends = np.repeat(head + size, size)[at]
        at = at[at + step < ends]
        near = np.bitwise_count(prints[at] ^ prints[at + step]) <= distance
        found_a.append(prints[at[near]])
        found_b.append(prints[at[near] + step])
    for h, n in zip(head[useful & (size > small)], size[useful & (size > small)], strict=True):
        group = np.unique(prints[h : h + n])
        if len(group) > 1 and (pairs := _forest(group, distance)):
            a, b = np.array(pairs).T
            found_a.append(group[a])
            found_b.append(group[b])
    a, b = (np.concatenate(x) if x else np.zeros(0, np.uint64) for x in (found_a, found_b))
    a, b = np.minimum(a, b), np.maximum(a, b)
    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    keep = np.ones(len(a), dtype=bool)
    keep[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    keep &= a != b
    return a[keep], b[keep]


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 0x20


def fingerprints_of(flat: np.ndarray, offsets: np.ndarray, words: int = WORDS, seed: int = SEED) -> np.ndarray:
    """The 64-bit fingerprint of each text: bit set if set in over half its shingles' XXH64 values."""
    out = np.zeros(len(offsets) - 1, dtype=np.uint64)
    lo = 0
    while lo < len(out):
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + CHUNK, side="right")) - 1)
        out[lo:hi] = _fingerprints(_LOWER[flat[offsets[lo] : offsets[hi]]], offsets[lo : hi + 1] - offsets[lo], words, seed)
        lo = hi
    return out


def _fingerprints(flat: np.ndarray, offsets: np.ndarray, words: int, seed: int) -> np.ndarray:
    # A space after each text, so that words end with it.
    docs = len(offsets) - 1
    spaced = np.full(len(flat) + docs, 0x20, np.uint8)
    spaced[np.arange(len(flat)) + np.repeat(np.arange(docs), np.diff(offsets))] = flat
    start, end = word_bounds(spaced)
    first = np.searchsorted(start, offsets + np.arange(docs + 1))
    size = end - start + 1
    at = np.cumsum(size) - size  # of each word in the words joined by spaces
    joined = spaced[np.repeat(start - at, size) + np.arange(int(size.sum()))]
    joined[at + size - 1] = 0x20
    text = joined.tobytes()
    count = np.diff(first)
    shingles = np.where(count >= words, count - words + 1, np.minimum(count, 1))
    owner = np.repeat(np.arange(docs), shingles)
    begin = np.repeat(first[:-1], shingles) + np.arange(int(shingles.sum())) - np.repeat(np.cumsum(shingles) - shingles, shingles)
    last = begin + np.minimum(words, count[owner]) - 1
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(text[a:b], seed) for a, b in zip(at[begin].tolist(), (at[last] + size[last] - 1).tolist(), strict=True)], dtype=np.uint64)
    result = np.zeros(docs, dtype=np.uint64)
    has = np.flatnonzero(shingles)
    if len(has):
        heads = (np.cumsum(shingles) - shingles)[has]
        ones = np.zeros((len(has), 64), dtype=np.int64)
        bits = np.unpackbits(hashes.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        np.add.reduceat(bits, heads, axis=0, dtype=np.int64, out=ones)
        packed = np.packbits(2 * ones > shingles[has][:, None], axis=1, bitorder="little")
        result[has] = packed.view("<u8").ravel()
    return result


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, seed: int = SEED) -> DataFrame:
    """(id, print): the fingerprint of every row as a signed long. A text without words has 0."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            flat, offsets = sh.utf8(batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fingerprints_of(flat, offsets, words, seed).view(np.int64))], ["id", "print"])

    return docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{text_col}`").cast("string").alias("text")).mapInArrow(work, "id long, print long")


def near_links(prints: DataFrame, count: int, distance: int = DISTANCE) -> DataFrame:
    """Links (a, b) between distinct fingerprints (column print), enough to connect all that are linked."""
    if not 0 <= distance <= 4:
        raise ValueError("the keys cover distances up to 4")
    buckets = max(1, count * 120 // 250_000)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = batch.column(0).to_numpy().view(np.uint64)
            for lo in range(0, len(own), 10_000):
                part = own[lo : lo + 10_000]
                row, key, target = fuzzy_keys(part)
                order = np.argsort(key, kind="stable")
                row, key, target = row[order], key[order], target[order]
                rows = [(b, sh.frames(sh.pack_sorted(key[s]), part[row[s]].tobytes(), np.packbits(target[s]).tobytes())) for b, s in sh.cut_by_bucket(key, buckets)]
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], ["bucket", "body"])

    def join(table: pa.Table) -> pa.Table:
        parts = [sh.unframes(x) for x in table["body"].to_pylist()]
        keys = [sh.unpack_sorted(p[0]) for p in parts]
        target = np.concatenate([np.unpackbits(np.frombuffer(p[2], np.uint8), count=len(k)) for k, p in zip(keys, parts, strict=True)]).astype(bool)
        a, b = link_groups(np.concatenate(keys), np.concatenate([np.frombuffer(p[1], np.uint64) for p in parts]), target, distance)
        return pa.table({"a": a.view(np.int64), "b": b.view(np.int64)})

    return prints.select("print").mapInArrow(deal, "bucket int, body binary").groupBy("bucket").applyInArrow(join, "a long, b long").distinct()


def components(links: DataFrame) -> DataFrame:
    """(node, root) of every node of an undirected graph (columns a, b): the smallest node reachable.

    Alternates stars around larger and smaller neighbours until nothing changes; each round is cut
    into the shared folder. Rounds grow with the logarithm of the graph.
    """
    edges = cut(links.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    state = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(down.select("u", F.col("m").alias("v"))).distinct()
        edges = cut(small)
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == state:
            roots = edges.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
            return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())
        state = now


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, distance: int = DISTANCE, seed: int = SEED) -> DataFrame:
    """(id, fingerprint, component_id) of every row.

    Rows whose fingerprints differ in at most `distance` bits are linked; component_id is the smallest
    id that links lead to. Null and blank texts have fingerprint 0 and are linked like others. A null
    id keeps its row and doesn't name a component unless it is alone (then null); repeated rows are
    returned as often as they stand; an empty table gives no rows. Other columns are ignored.
    """
    marks = cut(fingerprints(docs, id_col, text_col, words, seed))
    nodes = cut(marks.groupBy("print").agg(F.min("id").alias("least")))
    roots = components(near_links(nodes, nodes.count(), distance))
    rooted = nodes.join(roots, nodes["print"] == roots["node"], "left").select("print", "least", F.coalesce("root", "print").alias("root"))
    rooted = cut(rooted)
    named = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    labels = cut(rooted.join(named, "root").select("print", "component_id"))
    return marks.join(labels, "print").select(F.col("id").alias(id_col), F.lower(F.lpad(F.hex("print"), 16, "0")).alias("fingerprint"), "component_id")
