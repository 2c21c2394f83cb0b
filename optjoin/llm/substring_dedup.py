"""Removal of word windows that repeat in a smaller document, behind a count-min prefilter.

Pass 1: every shard counts its windows in a sketch. A window is counted under the minimizer of its
word shingles, so a shard has one increment for a run of windows, and a window's estimate, the least
of its counters, is never below the number of places where it stands. The counters are cut into
ranges; a shard sends, per range, the counters it raises (a partition sketch, in sparse form), and
the ranges are merged where they meet. Nothing is broadcast, and the width follows the input.
Pass 2: windows whose estimate is two or more are sent by a hash of all their words and grouped
exactly, on 128 bits; each learns the smallest document that has it. Pass 3 removes.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import shards as sh
from .rolling import CHUNK, SPACE, U, PrefixHash, anchored_runs, mix, stream, word_bounds

LENGTH, SHINGLE, DEPTH = 50, 20, 2
SLOTS_PER_KEY = 8


class Words:
    """The words of a shard's documents: byte spans, independent hashes (two, or one for each seed), and each document's range."""

    def __init__(self, flat: np.ndarray, offsets: np.ndarray, seeds: tuple[int, ...] = (21, 22)):
        parts = []
        lo, n = 0, len(flat)
        inner = offsets[1:-1]
        while lo < n:
            hi = self._cut(flat, inner, lo, min(n, lo + CHUNK))
            part = flat[lo:hi]
            start, end = word_bounds(part)
            start, end = self._split(start, end, inner[(inner > lo) & (inner < hi)] - lo)
            parts.append((start + lo, end + lo, *(mix(PrefixHash(part, s).spans(start, end)) for s in seeds)))
            lo = hi
        none = np.zeros(0, np.int64), np.zeros(0, np.int64), *(np.zeros(0, np.uint64) for _ in seeds)
        self.start, self.end, self.first, *rest = (np.concatenate(x) for x in zip(*parts, strict=True)) if parts else none
        self.second = rest[0] if rest else None
        self.offsets = np.searchsorted(self.start, offsets)

    @staticmethod
    def _cut(flat: np.ndarray, inner: np.ndarray, lo: int, hi: int) -> int:
        """The first place from hi on that isn't within a word."""
        while hi < len(flat):
            part = flat[hi : hi + 4096]
            space = np.flatnonzero(SPACE[part])
            i = np.searchsorted(inner, hi)
            bound = int(inner[i]) if i < len(inner) else len(flat)
            best = min(hi + int(space[0]) if len(space) else len(flat), bound)
            if len(space) or bound <= hi + len(part):
                return best
            hi += len(part)
        return len(flat)

    @staticmethod
    def _split(start: np.ndarray, end: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Words end with their document, also where no space stands between two documents."""
        at = np.searchsorted(start, cuts, side="right") - 1
        held = at >= 0
        inside = cuts[held][(start[at[held]] < cuts[held]) & (end[at[held]] > cuts[held])]
        return (np.sort(np.concatenate([start, np.unique(inside)])), np.sort(np.concatenate([end, np.unique(inside)]))) if len(inside) else (start, end)

    def windows(self, first: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
        """128 bits for the windows that start at these words (ascending)."""
        out = []
        for tokens, seed in ((self.first, 31), (self.second, 32)):
            part = np.zeros(len(first), np.uint64)
            cuts = np.searchsorted(first, np.arange(0, len(tokens) + CHUNK, CHUNK))
            for i, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                if a < b:
                    base = i * CHUNK
                    at = first[a:b] - base
                    part[a:b] = mix(PrefixHash(tokens[base : base + CHUNK + length], seed).spans(at, at + length))
            out.append(part)
        return out[0], out[1]


class _Runs:
    def __init__(self, shard: sh.Shard, length: int, shingle: int):
        self.words = w = Words(shard.flat, shard.offsets)
        self.doc_end = np.repeat(w.offsets[1:], np.diff(w.offsets))
        self.first, self.count, _, self.key = anchored_runs(w.first, self.doc_end, length, shingle, seed=41)

    def counters(self, width: int, depth: int) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Per row of the sketch: the raised counters, ascending, by how much, and each run's."""
        out = []
        for row in range(depth):
            slot = mix(self.key ^ stream(1, 50 + row)[0])
            slot = (slot >> U(32)) * U(width) >> U(32) if width < 1 << 32 else slot % U(width)
            found, which, count = np.unique(slot, return_inverse=True, return_counts=True)
            out.append((found, count, which))
        return out

    def repeated(self, replies: list[bytes], depth: int, width: int) -> np.ndarray:
        """For each run, whether its estimate is two or more."""
        rows = [np.zeros(0, np.uint8)] * depth
        for body in replies:
            for row, (n, bits) in enumerate(sh.unframes(x) for x in sh.unframes(body)):
                rows[row] = np.concatenate([rows[row], np.unpackbits(np.frombuffer(bits, np.uint8), count=int(n))])
        least = np.ones(len(self.key), dtype=bool)
        for bits, (_, _, which) in zip(rows, self.counters(width, depth), strict=True):
            least &= bits[which].astype(bool) if len(bits) else False
        return least


def sketch_messages(runs: _Runs, width: int, depth: int, ranges: int) -> Iterable[tuple[int, bytes]]:
    rows = runs.counters(width, depth)
    cuts = [np.searchsorted(found, range_bounds(width, ranges)) for found, _, _ in rows]
    for r in range(ranges):
        if any(c[r] < c[r + 1] for c in cuts):
            yield r, sh.frames(*(sh.frames(sh.pack_sorted(found[c[r] : c[r + 1]]), np.packbits(count[c[r] : c[r + 1]] > 1).tobytes()) for (found, count, _), c in zip(rows, cuts, strict=True)))


def range_bounds(width: int, ranges: int) -> np.ndarray:
    return np.array([width * i // ranges for i in range(ranges + 1)], dtype=np.uint64)


def merge_sketches(bodies: list[bytes], depth: int, low: int, high: int) -> list[bytes]:
    """Adds the partition sketches of one range of counters (stopping at 2); for each counter sent, whether it holds two or more."""
    parts = [[sh.unframes(x) for x in sh.unframes(b)] for b in bodies]
    out: list[list[bytes]] = [[] for _ in bodies]
    for row in range(depth):
        total = np.zeros(high - low, dtype=np.uint8)
        slots = [(sh.unpack_sorted(p[row][0]) - U(low)).astype(np.int64) for p in parts]
        for at, p in zip(slots, parts, strict=True):
            total[at] = np.minimum(total[at] + 1 + np.unpackbits(np.frombuffer(p[row][1], np.uint8), count=len(at)), 2)
        for body, at in zip(out, slots, strict=True):
            body.append(sh.frames(str(len(at)).encode(), np.packbits(total[at] > 1).tobytes()))
    return [sh.frames(*x) for x in out]


class _Windows:
    """The distinct windows of one shard that may repeat, by their hash, with the smallest document of each."""

    def __init__(self, shard: sh.Shard, runs: _Runs, repeated: np.ndarray, length: int):
        at = np.flatnonzero(repeated)
        n = runs.count[at]
        self.start = np.repeat(runs.first[at], n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        a, b = runs.words.windows(self.start, length)
        self.doc = np.searchsorted(runs.words.offsets, self.start, side="right") - 1
        order = np.lexsort((b, a))
        same = np.zeros(len(order), dtype=bool)
        same[1:] = (a[order][1:] == a[order][:-1]) & (b[order][1:] == b[order][:-1])
        self.order, self.which = order, np.cumsum(~same) - 1
        chosen = order[~same]
        self.a, self.b, self.least = a[chosen], b[chosen], shard.ids[self.doc[chosen]]


def _window_messages(w: _Windows, buckets: int) -> Iterable[tuple[int, bytes]]:
    for bucket, part in sh.cut_by_bucket(w.a, buckets):
        ids, which = np.unique(w.least[part], return_inverse=True)
        small = which.astype(np.uint16 if len(ids) < 1 << 16 else np.uint32)
        yield bucket, sh.frames(sh.pack_sorted(w.a[part]), w.b[part].tobytes(), ids.tobytes(), sh.squeeze(small.tobytes()))


def group_windows(bodies: list[bytes]) -> list[bytes]:
    """For each window sent, whether a smaller document has it."""
    parts = [sh.unframes(x) for x in bodies]
    a = [sh.unpack_sorted(p[0]) for p in parts]
    b = np.concatenate([np.frombuffer(p[1], np.uint64) for p in parts])
    ids = [np.frombuffer(p[2], np.int64) for p in parts]
    doc = np.concatenate([i[np.frombuffer(sh.unsqueeze(p[3]), np.uint16 if len(i) < 1 << 16 else np.uint32)] for i, p in zip(ids, parts, strict=True)])
    cuts = np.cumsum([len(x) for x in a])[:-1]
    a = np.concatenate(a)
    order = np.lexsort((b, a))
    head = np.ones(len(order), dtype=bool)
    head[1:] = (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1])
    head = np.flatnonzero(head)
    least = np.empty(len(order), np.int64)
    least[order] = np.repeat(np.minimum.reduceat(doc[order], head), np.diff(head, append=len(order)))
    return [sh.frames(str(len(x)).encode(), np.packbits(x).tobytes()) for x in np.split(least < doc, cuts)]


def removed_words(shard: sh.Shard, runs: _Runs, windows: _Windows, replies: list[bytes], length: int) -> np.ndarray:
    parts = [sh.unframes(x) for x in replies]
    change = np.zeros(len(runs.words.start) + 1, dtype=np.int32)
    if parts:
        flags = np.concatenate([np.unpackbits(np.frombuffer(b, np.uint8), count=int(n)) for n, b in parts]).astype(bool)
        gone = flags[windows.which] | (shard.ids[windows.doc[windows.order]] > windows.least[windows.which])
        start = windows.start[windows.order][gone]
        np.add.at(change, start, 1)
        np.add.at(change, start + length, -1)
    return np.cumsum(change[:-1]) > 0


def remove_repeated_windows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, shingle: int = SHINGLE, depth: int = DEPTH, keep: Iterable[str] = (), shard_bytes: int = sh.SHARD_BYTES, slots_per_key: int = SLOTS_PER_KEY) -> DataFrame:
    """Without every word that a window of `length` words covers which also starts in a smaller document.

    Returns per row: the id, n_words, n_removed, kept (the remaining words joined by one space) and
    the columns of `keep`. Words are runs of characters other than space and U+0009 to U+000D, taken
    unchanged; windows lie in one document and are judged on the input. A null text has no words; a
    null id counts as larger than all others; rows that share an id count as one document; an empty
    table gives no rows. A narrower sketch (slots_per_key) sends more windows to pass 2 and never
    changes the result.
    """
    if not 0 < shingle <= length:
        raise ValueError("0 < shingle <= length must hold")
    keep = list(keep)
    size = sh.text_bytes(docs, text_col)
    number = max(1, size // shard_bytes)
    keys = max(64, size // 90)  # about: a run of windows spans 16 words of 6 bytes
    width = 1 << (slots_per_key * keys - 1).bit_length()
    ranges, many = max(1, width >> 22), max(1, size // shard_bytes)
    parts = sh.shard(docs, id_col, text_col, number, keep)
    bounds = [int(x) for x in range_bounds(width, ranges)]

    def merge(table: pa.Table) -> pa.Table:
        order = np.argsort(table["src"].to_numpy(), kind="stable").tolist()
        src, body, bucket = table["src"].to_pylist(), table["body"].to_pylist(), table["bucket"][0].as_py()
        made = merge_sketches([body[i] for i in order], depth, bounds[bucket], bounds[bucket + 1])
        return sh.message_table([(src[i], 1, bucket, x) for i, x in zip(order, made, strict=True)])

    sketch = sh.send(parts, None, lambda s, _: sketch_messages(_Runs(s, length, shingle), width, depth, ranges), 1)
    estimates = sketch.groupBy("bucket").applyInArrow(merge, sh.MESSAGE)

    def ask(s: sh.Shard, got: pa.Table | None) -> Iterable[tuple[int, bytes]]:
        runs = _Runs(s, length, shingle)
        return _window_messages(_Windows(s, runs, runs.repeated(sh.replies_of(got, 1), depth, width), length), many)

    grouped = sh.answer(sh.send(parts, estimates, ask, 2), group_windows, 2)

    def finish(_: int, s: sh.Shard, got: pa.Table | None) -> pa.Table:
        runs = _Runs(s, length, shingle)
        windows = _Windows(s, runs, runs.repeated(sh.replies_of(got, 1), depth, width), length)
        gone = removed_words(s, runs, windows, sh.replies_of(got, 2), length)
        w = runs.words
        total = np.concatenate([[0], np.cumsum(gone)])
        left = np.flatnonzero(~gone)
        size = w.end[left] - w.start[left]
        # Each kept word with a space before it; the first of a document loses that space.
        out = np.full(int(size.sum()) + len(left), 0x20, np.uint8)
        at = np.cumsum(size + 1) - size
        out[np.repeat(at - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))] = s.flat[np.repeat(w.start[left] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))]
        bounds_ = np.searchsorted(left, w.offsets)
        ends = np.concatenate([[0], np.cumsum(size + 1)])[bounds_]
        texts = [out[a + 1 : b].tobytes() if a < b else b"" for a, b in zip(ends[:-1], ends[1:], strict=True)]
        own = s.kept()
        return pa.table({"id": own.pop("id"), "n_words": np.diff(w.offsets), "n_removed": np.diff(total[w.offsets]), "kept": pa.array(texts, pa.binary()), **own})

    types = {f.name: f.dataType.simpleString() for f in docs.schema}
    schema = ", ".join(["id long, n_words long, n_removed long, kept binary", *(f"k{i} {types[c]}" for i, c in enumerate(keep))])
    out = sh.over(parts, estimates.unionByName(grouped), finish, schema)
    return out.withColumn("kept", out["kept"].cast("string")).toDF(id_col, "n_words", "n_removed", "kept", *keep)
