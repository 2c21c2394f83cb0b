"""Near-duplicate texts at a similarity of 0.8 of their five-word shingles, by a prefix filter and exact comparison.

One fingerprint of a whole text differs in 6 to 13 of 64 bits at this similarity, beyond what keys for
4 errors find, and fingerprints of parts of a text change with any edit in them. So candidates are found
on the shingles. A first pass counts the texts that hold each shingle, and finds the smallest id of each
set of shingles: of equal sets only that row goes on, so a group of copies costs one row. A text has a
partner only if other texts hold 0.8 of its shingles; such texts are looked up under their rarest shingles,
so many that two similar texts share one. Rows of a key are linked loosely, by a sketch of their shingles
well below the similarity, and the links of a key are emitted as a spanning forest. So a pair that is
similar lies in one component of the loose links; in each component all texts are compared on their whole
sets of shingles.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shards as sh
from .rolling import CHUNK, U, mix
from .session import cut, release
from .simhash import components, near_duplicates
from .substring_dedup import Words

WORDS, SIMILARITY, LOOSE, BINS = 5, 0.8, 0.6, 256
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 0x20


def shingle_hashes(flat: np.ndarray, offsets: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all shingles of consecutive words and the first of each text; a shorter text is one shingle."""
    w = Words(_LOWER[flat], offsets)
    count = np.diff(w.offsets)
    number = np.where(count >= words, count - words + 1, np.minimum(count, 1))
    first = np.concatenate([[0], np.cumsum(number)])
    begin = np.repeat(w.offsets[:-1] - first[:-1], number) + np.arange(first[-1])
    last = np.minimum(begin + words, np.repeat(w.offsets[1:], number))
    out = np.zeros(int(first[-1]), np.uint64)
    for i in range(words):
        at = begin + i
        there = at < last
        out = mix(out * U(0x9E3779B97F4A7C15) + np.where(there, w.first[np.minimum(at, max(0, len(w.first) - 1))], U(i))) if len(out) else out
    return out, first


def distinct_shingles(hashes: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The set of each text's hashes, ascending, and the first of each text."""
    text = np.repeat(np.arange(len(first) - 1), np.diff(first))
    order = np.lexsort((hashes, text))
    hashes, text = hashes[order], text[order]
    new = sh.first_of_runs(hashes) | sh.first_of_runs(text)
    return hashes[new], np.concatenate([[0], np.cumsum(np.bincount(text[new], minlength=len(first) - 1))]).astype(np.int64)


def sets_of(shard: sh.Shard, words: int) -> tuple[np.ndarray, np.ndarray]:
    """The set of shingle hashes of each row of a shard, and the first of each row."""
    got, lo = [], 0
    while lo < len(shard):
        hi = max(lo + 1, int(np.searchsorted(shard.offsets, shard.offsets[lo] + CHUNK, side="right")) - 1)
        got.append(distinct_shingles(*shingle_hashes(shard.flat[shard.offsets[lo] : shard.offsets[hi]], shard.offsets[lo : hi + 1] - shard.offsets[lo], words)))
        lo = hi
    size = np.concatenate([np.diff(g[1]) for g in got]) if got else np.zeros(0, np.int64)
    return np.concatenate([g[0] for g in got]) if got else np.zeros(0, np.uint64), np.concatenate([[0], np.cumsum(size)]).astype(np.int64)


def prefixes(hashes: np.ndarray, first: np.ndarray, held: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """(row, key): the rarest shingles of each set that may have a partner; held is the number of texts with each shingle.

    Of a set of n, a partner holds at least `need` = ceil(similarity * n). So a set with fewer shingles that others
    hold has none, and of any order common to all sets, two partners share one of their first n - need + 1 elements.
    """
    size = np.diff(first)
    row = np.repeat(np.arange(len(size)), size)
    need = np.ceil(similarity * size - 1e-6).astype(np.int64)
    may = np.bincount(row[held > 1], minlength=len(size)) >= need
    order = np.lexsort((hashes, held, row))
    rank = np.arange(len(row)) - np.repeat(first[:-1], size)
    use = order[(rank < (size - need + 1)[row]) & may[row]]
    use = use[held[use] > 1]
    return row[use], hashes[use]


def sketches(hashes: np.ndarray, first: np.ndarray, bins: int) -> np.ndarray:
    """One byte for each bin of each text: of its least shingle hash; 0 if the bin is empty."""
    out = np.zeros((len(first) - 1, bins), dtype=np.uint8)
    if len(hashes):
        cell = np.repeat(np.arange(len(first) - 1), np.diff(first)) * bins + (hashes >> U(32) & U(bins - 1)).astype(np.int64)
        order = np.lexsort((hashes, cell))
        head = sh.first_of_runs(cell[order])
        out.ravel()[cell[order][head]] = (mix(hashes[order][head]) % U(255) + U(1)).astype(np.uint8)
    return out


def similar(one: np.ndarray, many: np.ndarray, least: float) -> np.ndarray:
    """Whether the sketches agree in at least this share of the bins that either has; empty texts equal each other."""
    same = ((many == one) & (one != 0)).sum(axis=1)
    used = ((many != 0) | (one != 0)).sum(axis=1)
    return same >= least * used


def _forest(ids: np.ndarray, marks: np.ndarray, least: float) -> list[tuple[int, int]]:
    left, out = np.arange(len(ids)), []
    while len(left):
        wave, left = [left[0]], left[1:]
        while wave and len(left):
            node = wave.pop()
            near = similar(marks[node], marks[left], least)
            out += [(int(ids[node]), int(ids[x])) for x in left[near]]
            wave += left[near].tolist()
            left = left[~near]
    return out


def link_key(ids: np.ndarray, marks: np.ndarray, least: float, large: int = 256) -> list[tuple[int, int]]:
    """Links that connect the similar rows of one key. A large group is looked up again by four bins at a time."""
    if len(ids) <= large:
        return _forest(ids, marks, least)
    out = []
    for b in range(0, marks.shape[1], 4):
        band = np.ascontiguousarray(marks[:, b : b + 4]).view(np.uint32).ravel()
        order = np.argsort(band, kind="stable")
        heads = np.flatnonzero(sh.first_of_runs(band[order]))
        for a, n in zip(heads, np.diff(heads, append=len(order)), strict=True):
            if n > 1 and band[order[a]]:
                out += _forest(ids[order[a : a + n]], marks[order[a : a + n]], least)
    return out


def exact_links(hashes: np.ndarray, first: np.ndarray, least: float) -> list[tuple[int, int]]:
    """Links that connect the texts whose sets of shingles have at least this Jaccard similarity; none for empty sets."""
    size = np.diff(first)
    seen: dict[bytes, int] = {}
    out, left = [], []
    for i in np.flatnonzero(size).tolist():
        other = seen.setdefault(hashes[first[i] : first[i + 1]].tobytes(), i)
        if other == i:
            left.append(i)
        else:
            out.append((other, i))
    token = np.unique(hashes, return_inverse=True)[1]
    held = np.zeros(len(hashes), dtype=bool)
    wave: list[int] = []
    rows = np.array(left, dtype=np.int64)
    kept = token, first[:-1][rows], rows
    while len(rows):
        if not wave:
            wave, rows = [int(rows[0])], rows[1:]
        node = wave.pop()
        if len(rows) and len(rows) <= len(kept[2]) // 2 or kept[0] is token:  # only the texts that are left
            n = size[rows]
            start = np.cumsum(n) - n
            kept = token[np.repeat(first[:-1][rows] - start, n) + np.arange(int(n.sum()))], start, rows
        if not len(rows):
            break
        mine = token[first[node] : first[node + 1]]
        held[mine] = True
        both = np.add.reduceat(held[kept[0]], kept[1], dtype=np.int64)[np.searchsorted(kept[2], rows)]
        held[mine] = False
        near = both / (size[node] + size[rows] - both) >= least
        out += [(node, x) for x in rows[near].tolist()]
        wave += rows[near].tolist()
        rows = rows[~near]
    return out


def rooted(ids: np.ndarray, links: Iterable[tuple[int, int]]) -> list[tuple[int, int]]:
    """(id, the smallest that links between rows lead to) of the ids that aren't it; rows that share an id are one."""
    root: dict[int, int] = {}

    def find(x: int) -> int:
        while (up := root.setdefault(x, x)) != x:
            root[x] = root[up]
            x = up
        return x

    for i, j in links:
        a, b = find(int(ids[i])), find(int(ids[j]))
        root[max(a, b)] = min(a, b)
    return [(x, find(x)) for x in root if find(x) != x]


def repeats(ids: np.ndarray, links: Iterable[tuple[int, int]]) -> list[int]:
    """The ids that links between rows lead to a smaller id."""
    return [x for x, _ in rooted(ids, links)]


def set_digests(hashes: np.ndarray, first: np.ndarray) -> np.ndarray:
    """128 bits of each set of hashes; of an empty set zeros."""
    out = np.zeros((len(first) - 1, 2), np.uint64)
    has = np.flatnonzero(np.diff(first))
    for i, odd in enumerate((0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)):
        if len(has):
            out[has, i] = mix(np.add.reduceat(mix(hashes * U(odd)), first[:-1][has]))
    return out


def _spread(keys: np.ndarray) -> np.ndarray:
    """The rarest shingles are often those of the least hashes; mixed once more they spread over the buckets."""
    return mix(keys ^ U(0x6A09E667F3BCC909))


def loose_links(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, similarity: float = SIMILARITY, loose: float = LOOSE, bins: int = BINS, shard_bytes: int = sh.SHARD_BYTES) -> DataFrame:
    """Links (a, b, copy) of ids that connect what may be near-duplicates; copy: b is the smallest id with the shingles of a.

    Rows without an id or without words have none. Rows that share an id are all looked up.
    """
    buckets = max(1, sh.text_bytes(docs, text_col) // shard_bytes)
    shards = sh.shard(docs.filter(F.col(f"`{id_col}`").isNotNull()), id_col, text_col, buckets)

    def distinct_sets(shard: sh.Shard, hashes: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Rows with words, by digest and then id; their digests; which of them stands first of its digest."""
        marks = set_digests(hashes, first)
        rows = np.flatnonzero(np.diff(first))
        rows = rows[np.lexsort((shard.ids[rows], marks[rows, 1], marks[rows, 0]))]
        return rows, marks[rows], sh.first_of_runs(marks[rows, 0]) | sh.first_of_runs(marks[rows, 1])

    def ask(shard: sh.Shard, _: pa.Table | None) -> Iterator[tuple[int, bytes]]:
        hashes, first = sets_of(shard, words)
        rows, marks, head = distinct_sets(shard, hashes, first)
        marks, least = marks[head], shard.ids[rows[head]]
        keys, count = np.unique(hashes, return_counts=True)
        of_keys, of_sets = (dict(sh.cut_by_bucket(k, buckets)) for k in (keys, marks[:, 0]))
        for b in sorted({*of_keys, *of_sets}):
            s, t = of_keys.get(b, slice(0)), of_sets.get(b, slice(0))
            yield b, sh.frames(sh.pack_sorted(keys[s]), sh.squeeze(count[s].astype(np.uint32).tobytes()), sh.pack_sorted(marks[t, 0]), marks[t, 1].tobytes(), least[t].tobytes())

    def count(bodies: list[bytes]) -> list[bytes]:
        got = [sh.unframes(x) for x in bodies]
        keys = [sh.unpack_sorted(g[0]) for g in got]
        every, where = np.unique(np.concatenate(keys), return_inverse=True)
        total = np.bincount(where, np.concatenate([np.frombuffer(sh.unsqueeze(g[1]), np.uint32) for g in got]), len(every)).astype(np.uint32)[where]
        ends = np.cumsum([len(k) for k in keys])
        one = [sh.unpack_sorted(g[2]) for g in got]
        ids = np.concatenate([np.frombuffer(g[4], np.int64) for g in got])
        cuts, one = np.cumsum([len(x) for x in one])[:-1], np.concatenate(one)
        two = np.concatenate([np.frombuffer(g[3], np.uint64) for g in got])
        order = np.lexsort((ids, two, one))
        head = np.flatnonzero(sh.first_of_runs(one[order]) | sh.first_of_runs(two[order]))
        least = np.empty(len(ids), np.int64)
        least[order] = np.repeat(ids[order][head], np.diff(head, append=len(ids)))
        return [sh.frames(sh.squeeze(x.tobytes()), sh.squeeze(y.tobytes())) for x, y in zip(np.split(total, ends[:-1]), np.split(least, cuts), strict=True)]

    def deal(_: int, shard: sh.Shard, got: pa.Table) -> pa.Table:
        hashes, first = sets_of(shard, words)
        replies = [sh.unframes(x) for x in sh.replies_of(got, 1)]
        counts = b"".join(sh.unsqueeze(r[0]) for r in replies)
        held = np.frombuffer(counts, np.uint32)[np.unique(hashes, return_inverse=True)[1]] if len(hashes) else np.zeros(0, np.uint32)
        rows, _, head = distinct_sets(shard, hashes, first)
        least = np.frombuffer(b"".join(sh.unsqueeze(r[1]) for r in replies), np.int64)
        least = least[np.cumsum(head) - 1] if len(rows) else np.zeros(0, np.int64)
        ids = shard.ids[rows]
        alone = ~np.isin(ids, shard.ids[1:][shard.ids[1:] == shard.ids[:-1]])
        copies = np.zeros(len(shard), dtype=bool)
        copy = alone & (least < ids)
        copies[rows[copy]] = True
        row, key = prefixes(hashes, first, held, similarity)
        row, key = row[~copies[row]], _spread(key[~copies[row]])
        used, row = np.unique(row, return_inverse=True)
        size = np.diff(first)[used]
        start = np.cumsum(size) - size
        inside = hashes[np.repeat(first[used] - start, size) + np.arange(int(size.sum()))]
        marks, ids = sketches(inside, np.concatenate([start, [len(inside)]]), bins), shard.ids[used]
        links = np.stack([shard.ids[rows[copy]], least[copy]], axis=1)
        order = np.lexsort((ids[row], key))
        row, key = row[order], key[order]
        out = []
        for b, s in sh.cut_by_bucket(key, buckets):
            rows, at = np.unique(row[s], return_inverse=True)
            out.append((b, sh.frames(sh.pack_sorted(key[s]), sh.squeeze(at.astype(np.uint32).tobytes()), ids[rows].tobytes(), sh.squeeze(marks[rows].tobytes()), b"")))
        if len(links):
            none = np.zeros(0, np.uint64)
            out.append((int(shard.ids[0]) % buckets, sh.frames(sh.pack_sorted(none), sh.squeeze(b""), b"", sh.squeeze(b""), links.tobytes())))
        return pa.table({"bucket": pa.array([x[0] for x in out], pa.int32()), "body": pa.array([x[1] for x in out], pa.binary())})

    def join(table: pa.Table) -> pa.Table:
        got = [sh.unframes(x) for x in table["body"].to_pylist()]
        key = np.concatenate([sh.unpack_sorted(g[0]) for g in got])
        names = [np.frombuffer(g[2], np.int64) for g in got]
        base = np.cumsum([0, *map(len, names)])
        at = np.concatenate([np.frombuffer(sh.unsqueeze(g[1]), np.uint32) + b for g, b in zip(got, base[:-1], strict=True)])
        names = np.concatenate(names)
        marks = np.frombuffer(b"".join(sh.unsqueeze(g[3]) for g in got), np.uint8).reshape(-1, bins)
        copies = np.frombuffer(b"".join(g[4] for g in got), np.int64).reshape(-1, 2)
        links = []
        order = np.lexsort((names[at], key))
        key, at = key[order], at[order]
        head = np.flatnonzero(sh.first_of_runs(key))
        size = np.diff(head, append=len(key))
        seen = set()
        for a, n in zip(head[size > 1], size[size > 1], strict=True):
            rows = at[a : a + n]
            if (group := rows.tobytes()) not in seen:  # near copies share many keys
                seen.add(group)
                links += link_key(names[rows], marks[rows], loose)
        pairs = np.array(list(set(links)), dtype=np.int64).reshape(-1, 2)
        release()
        both = np.concatenate([pairs, copies])
        return pa.table({"a": both[:, 0], "b": both[:, 1], "copy": np.arange(len(both)) >= len(pairs)})

    counts = sh.answer(sh.send(shards, None, ask, 0), count, 1)
    return sh.over(shards, counts, deal, "bucket int, body binary").groupBy("bucket").applyInArrow(join, "a long, b long, copy boolean")


def similar_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, similarity: float = SIMILARITY, **options) -> DataFrame:
    """(a, b): each id that similar pairs of texts connect to a smaller one, and such a smaller one.

    All groups are connected by these links. Rows that share an id are one document. Texts of equal shingles are told by 128 bits. Null and blank
    texts, and rows without an id, have no link.
    """
    buckets = max(1, sh.text_bytes(docs, text_col) // (4 << 20))
    links = cut(loose_links(docs, id_col, text_col, words, similarity, **options))
    roots = components(links.filter("not copy").select("a", "b"))

    def verify(table: pa.Table) -> pa.Table:
        table = sh.large(table).sort_by([("root", "ascending"), ("id", "ascending")])
        ids, root = table["id"].to_numpy(), table["root"].to_numpy()
        hashes, first = distinct_shingles(*shingle_hashes(*sh.utf8(table["text"]), words))
        heads = np.flatnonzero(sh.first_of_runs(root))
        found: list[tuple[int, int]] = []
        for a, b in zip(heads, [*heads[1:], len(root)], strict=True):
            found += rooted(ids[a:b], exact_links(hashes[first[a] : first[b]], first[a : b + 1] - first[a], similarity))
        release()
        both = np.array(found, dtype=np.int64).reshape(-1, 2)
        return pa.table({"a": both[:, 0], "b": both[:, 1]})

    texts = docs.select(F.col(f"`{id_col}`").cast("long").alias("node"), F.col(f"`{text_col}`").cast("string").alias("text"))
    rows = texts.join(roots, "node").select("root", F.col("node").alias("id"), "text", F.pmod(F.xxhash64("root"), F.lit(buckets)).alias("bucket"))
    return rows.groupBy("bucket").applyInArrow(verify, "a long, b long").unionByName(links.filter("copy").select("a", "b"))


def distinct_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: Iterable[str] = (), words: int = WORDS, similarity: float = SIMILARITY, **options) -> DataFrame:
    """The rows of docs (id, text and the columns of `keep`) without near-duplicates of a smaller id.

    Of each group of texts that similar pairs connect the smallest id stays; rows that share an id are
    one document and stay or go together. Null and blank texts, and rows without an id, always stay. An empty table gives no rows.
    """
    gone = similar_texts(docs, id_col, text_col, words, similarity, **options).select(F.col("a").alias(id_col))
    return docs.select(id_col, text_col, *keep).join(gone, id_col, "left_anti")


def distinct_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: Iterable[str] = (), **options) -> DataFrame:
    """The rows of docs (id, text and the columns of `keep`) without near-duplicates of a smaller id, by fingerprints and by texts.

    Documents are linked where their fingerprints differ in few bits, as `near_duplicates` finds them by its fuzzy keys.
    Those keys end at 4 bits, and a similarity of 0.8 may take more; so texts that are similar are linked as well, as
    `similar_texts` finds them. Of each group that links of either kind connect the smallest id stays. Rows that share an
    id, null and blank texts and rows without an id are as in `distinct_texts`.
    """
    told = docs.filter(F.col(f"`{id_col}`").isNotNull() & F.col(f"`{text_col}`").rlike(r"[^\x20\x09-\x0D]"))
    marks = near_duplicates(told, id_col, text_col).select(F.col(f"`{id_col}`").alias("id"), "component_id")
    own = cut(marks.groupBy("id").agg(F.min("component_id").alias("group"), F.collect_set("component_id").alias("every")))
    texts = similar_texts(docs, id_col, text_col, **options)
    # Copies are in one group by their fingerprints, so they are one row once the group stands for a.
    texts = texts.join(own.select(F.col("id").alias("a"), F.col("group").alias("u")), "a").select("u", "b").distinct()
    texts = texts.join(own.select(F.col("id").alias("b"), F.col("group").alias("v")), "b").select("u", "v")
    shared = own.filter(F.size("every") > 1).select(F.col("group").alias("u"), F.explode("every").alias("v"))
    roots = components(texts.unionByName(shared).select(F.col("u").alias("a"), F.col("v").alias("b")))
    gone = own.join(roots, F.col("group") == F.col("node"), "left").filter(F.coalesce("root", "group") != F.col("id")).select(F.col("id").alias(id_col))
    return docs.select(id_col, text_col, *keep).join(gone, id_col, "left_anti")
