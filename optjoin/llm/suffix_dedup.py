"""Removal of long repeated substrings, by a suffix sort whose comparisons use prefix hashes.

`sort_suffixes` is a mergesort of suffixes. Two suffixes are compared by binary search for their
longest common extension, on equality of prefix polynomial hashes, and then by the byte that follows;
neighbours that hashes call equal are verified byte by byte, and a collision repeats the sort under
another base.

`remove_repeats` runs it over all documents without moving all suffixes. Every window of `length`
bytes is held by the minimizer of its shingles (its anchor), at the same offset wherever the window
stands. Pass 1 counts anchors; those in one document only hold no repeat. An anchor under which more
than `hot` different texts stand (the edge of a passage that very many documents quote) is not sent as
a whole: pass 2 counts its windows by a hash of their bytes, and those that repeat are sent one by one.
Pass 3 sends, for the other anchors, the text of the windows they hold, once per shard. There, texts of
one anchor are sorted as suffixes, so that equal ones meet; texts that differ are cut into windows,
sorted as suffixes again, and each window learns the smallest document that has it. Pass 4 removes
what the replies cover. So no group grows with the number of documents, only with that of shards.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import shards as sh
from .rolling import U, PrefixHash, anchored_runs, mix

LENGTH, SHINGLE = 50, 25
STEP_BYTES = 1 << 20
HOT = 4096


def _hash(prefix: PrefixHash, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    return prefix.spans(start, start + size)


def compare_suffixes(text: np.ndarray, prefix: PrefixHash, a: np.ndarray, b: np.ndarray, limit: int | np.ndarray) -> np.ndarray:
    """-1, 0 or 1 for each pair of suffixes, cut to `limit` bytes (one number, or one for each pair): log2(limit) hash comparisons each."""
    n = len(text)
    most = np.minimum(limit, np.minimum(n - a, n - b))
    out = np.zeros(len(a), dtype=np.int8)
    open_ = np.flatnonzero(_hash(prefix, a, most) != _hash(prefix, b, most))
    low, high = np.zeros(len(open_), np.int64), most[open_]  # equal up to low, different at high
    x, y = a[open_], b[open_]
    for _ in range(int(high.max(initial=0)).bit_length()):
        mid = (low + high) >> 1
        same = _hash(prefix, x, mid) == _hash(prefix, y, mid)
        low, high = np.where(same, mid, low), np.where(same, high, np.maximum(mid, low + 1))
    out[open_] = np.where(text[x + low] < text[y + low], -1, 1)
    equal = np.ones(len(a), dtype=bool)
    equal[open_] = False
    short = np.minimum(limit, n - a) - np.minimum(limit, n - b)  # a proper prefix stands first
    out[equal] = np.sign(short[equal])
    return out


def _merge_sort(text: np.ndarray, prefix: PrefixHash, starts: np.ndarray, group_start: np.ndarray, group_end: np.ndarray, limit: np.ndarray) -> np.ndarray:
    """The starts, sorted as suffixes within their groups: blocks double, and each element's place is its rank in the block beside it."""
    order, width = starts.copy(), 1
    longest = int((group_end - group_start).max(initial=0))
    while width < longest:
        at = np.flatnonzero(group_end - group_start > width)
        begin, end = group_start[at], group_end[at]
        block = (at - begin) // width
        low = np.minimum(begin + (block ^ 1) * width, end)
        first, high = low.copy(), np.minimum(low + width, end)
        right, mine, most = block & 1 == 1, order[at], limit[at]
        todo = np.flatnonzero(low < high)
        while len(todo):
            mid = (low[todo] + high[todo]) >> 1
            sign = compare_suffixes(text, prefix, order[mid], mine[todo], most[todo])
            below = (sign < 0) | ((sign == 0) & right[todo])
            low[todo] = np.where(below, mid + 1, low[todo])
            high[todo] = np.where(below, high[todo], mid)
            todo = todo[low[todo] < high[todo]]
        place = begin + (block & ~1) * width + (at - begin - block * width) + (low - first)
        moved = order.copy()
        moved[place] = mine
        order, width = moved, 2 * width
    return order


def _same_bytes(text: np.ndarray, a: np.ndarray, b: np.ndarray, size: int) -> bool:
    for lo in range(0, len(a), 1 << 16):
        x, y = a[lo : lo + (1 << 16)], b[lo : lo + (1 << 16)]
        for i in range(size):
            if (text[x + i] != text[y + i]).any():
                return False
    return True


def sort_suffixes(text: np.ndarray, starts: np.ndarray, limit: int | np.ndarray, groups: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes cut to `limit` bytes in ascending order, and whether each equals the one before it.

    groups: ascending labels; suffixes are then sorted within their group only, and `limit` may be an
    array that is constant in a group. Every suffix that counts as equal to its neighbour has been
    compared byte by byte.
    """
    groups = np.zeros(len(starts), np.int64) if groups is None else groups
    limit = np.broadcast_to(np.asarray(limit, np.int64), starts.shape)
    first = np.flatnonzero(sh.first_of_runs(groups))
    sizes = np.diff(first, append=len(starts))
    begin, end = np.repeat(first, sizes), np.repeat(first + sizes, sizes)
    seed = 11
    while True:
        prefix = PrefixHash(text, seed)
        order = _merge_sort(text, prefix, starts.astype(np.int64), begin, end, limit)
        equal = np.zeros(len(order), dtype=bool)
        inner = np.flatnonzero(begin[1:] == begin[:-1]) + 1 if len(order) else np.zeros(0, np.int64)
        equal[inner] = compare_suffixes(text, prefix, order[inner - 1], order[inner], limit[inner]) == 0
        at = np.flatnonzero(equal)
        size = np.minimum(limit[at], len(text) - np.maximum(order[at], order[at - 1]))
        if all(_same_bytes(text, order[at[size == s]], order[at[size == s] - 1], int(s)) for s in np.unique(size)):
            return order, equal
        seed += 1


class _Keyed:
    """Keys of the runs or windows of one shard, with the documents they stand in, grouped by key."""

    def __init__(self, key: np.ndarray, doc: np.ndarray):
        self.key, self.doc = key, doc
        self.order = np.argsort(key, kind="stable")
        ascending = key[self.order]
        self.heads = np.flatnonzero(sh.first_of_runs(ascending))
        self.keys = ascending[self.heads]
        self.number = np.diff(self.heads, append=len(key))

    def several(self) -> np.ndarray:
        """For each distinct key, whether two documents of this shard have it."""
        doc = self.doc[self.order]
        return doc[self.heads] != doc[self.heads + self.number - 1] if len(doc) else np.zeros(0, bool)

    def spread(self, replies: list[bytes], part: int) -> np.ndarray:
        """For each run or window, the bit that the replies hold for its key."""
        out = np.zeros(len(self.key), dtype=bool)
        bits = [sh.unframes(x) for x in replies]
        if bits and len(out):
            flags = np.concatenate([np.unpackbits(np.frombuffer(b[1 + part], np.uint8), count=int(b[0])).astype(bool) for b in bits])
            out[self.order] = np.repeat(flags, self.number)
        return out


class _Found:
    """The anchored runs of one shard and its distinct anchors, ascending."""

    def __init__(self, shard: sh.Shard, length: int, shingle: int):
        doc_end = np.repeat(shard.offsets[1:].astype(np.int32 if len(shard.flat) < 1 << 31 else np.int64), np.diff(shard.offsets))
        self.flat, self.length = shard.flat, length
        self.first, self.count, self.anchor, key = anchored_runs(shard.flat, doc_end, length, shingle)
        self.doc = np.searchsorted(shard.offsets, self.first, side="right") - 1
        # A minimizer is the least of many hashes; mixed once more, anchors spread evenly over the buckets.
        self.keyed = _Keyed(mix(key ^ U(0x9E6C63D0876A9A47)), self.doc)

    def content(self, at: np.ndarray) -> np.ndarray:
        """A hash of the text of these runs (ascending) and of the anchor's place in it."""
        return _span_hash(self.flat, self.first[at], self.count[at] + self.length - 1) ^ mix((self.anchor[at] - self.first[at]).astype(np.uint64))

    def texts_of_keys(self) -> np.ndarray:
        """The number of different texts under each distinct anchor; where only a few runs have it, their number."""
        k, out = self.keyed, self.keyed.number.copy()
        many = np.repeat(k.number >= 4, k.number)
        at = k.order[many]
        ascending = np.sort(at)
        content = np.empty(len(at), np.uint64)
        content[np.argsort(at)] = self.content(ascending)
        label = np.repeat(np.arange(len(k.number)), k.number)[many]
        order = np.lexsort((content, label))
        new = sh.first_of_runs(content[order]) | sh.first_of_runs(label[order])
        out[k.number >= 4] = np.bincount(label[order][new], minlength=len(out))[k.number >= 4]
        return out


def anchor_messages(found: _Found, buckets: int) -> Iterable[tuple[int, bytes]]:
    yield from count_messages(found.keyed, found.texts_of_keys(), buckets)


def count_messages(keyed: _Keyed, number: np.ndarray, buckets: int) -> Iterable[tuple[int, bytes]]:
    several, number = keyed.several(), np.minimum(number, 65535).astype(np.uint16)
    for bucket, part in sh.cut_by_bucket(keyed.keys, buckets):
        yield bucket, sh.frames(sh.pack_sorted(keyed.keys[part]), np.packbits(several[part]).tobytes(), sh.squeeze(number[part].tobytes()))


def count_keys(bodies: list[bytes], hot: int) -> list[bytes]:
    """For each message's keys, two bits: two documents or more have it; more than `hot` texts stand under it."""
    parts = [sh.unframes(x) for x in bodies]
    keys = [sh.unpack_sorted(p[0]) for p in parts]
    several = np.concatenate([np.unpackbits(np.frombuffer(p[1], np.uint8), count=len(k)) for k, p in zip(keys, parts, strict=True)])
    number = np.concatenate([np.frombuffer(sh.unsqueeze(p[2]), np.uint16) for p in parts])
    cuts = np.cumsum([len(k) for k in keys])[:-1]
    every = np.concatenate(keys)
    order = np.argsort(every, kind="stable")
    head = np.flatnonzero(sh.first_of_runs(every[order]))
    size = np.diff(head, append=len(every))
    shared, over = np.zeros(len(every), dtype=bool), np.zeros(len(every), dtype=bool)
    shared[order] = np.repeat((size > 1) | np.maximum.reduceat(several[order], head).astype(bool), size)
    over[order] = np.repeat(np.add.reduceat(number[order], head, dtype=np.int64) > hot, size)
    return [sh.frames(str(len(x)).encode(), np.packbits(x).tobytes(), np.packbits(y).tobytes()) for x, y in zip(np.split(shared, cuts), np.split(over, cuts), strict=True)]


def hot_windows(found: _Found, got: pa.Table) -> tuple[np.ndarray, _Keyed]:
    """The starts of all windows under hot anchors, ascending, and their keys by a hash of their bytes."""
    replies = sh.replies_of(got, 1)
    runs = np.flatnonzero(found.keyed.spread(replies, 1))
    n = found.count[runs]
    start = np.repeat(found.first[runs] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
    return start, _Keyed(mix(_span_hash(found.flat, start, np.full(len(start), found.length)) ^ U(0x2545F4914F6CDD1D)), np.repeat(found.doc[runs], n))


class _Spans:
    """What a shard sends: the runs of shared anchors, and under hot ones each shared window as a run of its own."""

    def __init__(self, found: _Found, got: pa.Table | None, length: int):
        replies = sh.replies_of(got, 1) if got is not None else []
        hot = found.keyed.spread(replies, 1)
        at = np.flatnonzero(found.keyed.spread(replies, 0) & ~hot)
        first, count, rel, key, doc = found.first[at], found.count[at], (found.anchor - found.first)[at], found.keyed.key[at], found.doc[at]
        if hot.any():
            start, keyed = hot_windows(found, got)
            use = np.flatnonzero(keyed.spread(sh.replies_of(got, 3), 0))
            more = start[use], np.ones(len(use), np.int64), np.zeros(len(use), np.int64), keyed.key[use], keyed.doc[use]
            first, count, rel, key, doc = (np.concatenate(x) for x in zip((first, count, rel, key, doc), more, strict=True))
            order = np.argsort(first, kind="stable")
            first, count, rel, key, doc = (x[order] for x in (first, count, rel, key, doc))
        self.first, self.count, self.rel, self.key, self.doc = first, count, rel, key, doc


class _Texts:
    """The distinct texts of the spans of one shard, ordered by key: each with its smallest document."""

    def __init__(self, shard: sh.Shard, spans: _Spans, length: int):
        self.spans = spans
        key, first = spans.key, spans.first
        size = spans.count + length - 1
        content = _span_hash(shard.flat, first, size) ^ mix(spans.rel.astype(np.uint64))
        order = np.lexsort((content, key))  # stable: the smallest document of equal texts stands first
        same = np.zeros(len(order), dtype=bool)
        same[1:] = (key[order][1:] == key[order][:-1]) & (content[order][1:] == content[order][:-1])
        head = np.maximum.accumulate(np.where(same, 0, np.arange(len(order)))) if len(order) else np.zeros(0, np.int64)
        same &= _equal_spans(shard.flat, first[order], size[order], first[order][head], size[order][head])
        self.runs, self.heads = order, np.flatnonzero(~same)
        self.which = np.cumsum(~same) - 1
        chosen = order[self.heads]
        self.key, self.first, self.count, self.rel, self.doc = key[chosen], first[chosen], spans.count[chosen], spans.rel[chosen], spans.doc[chosen]


def _span_hash(flat: np.ndarray, first: np.ndarray, size: np.ndarray, seed: int = 3) -> np.ndarray:
    """Hashes of spans, ascending by their start, in chunks of the text."""
    out, step = np.zeros(len(first), np.uint64), 1 << 19
    cuts = np.searchsorted(first, np.arange(0, len(flat) + step, step))
    for i, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
        if a < b:
            base = i * step
            prefix = PrefixHash(flat[base : int((first[a:b] + size[a:b]).max())], seed)
            out[a:b] = prefix.spans(first[a:b] - base, first[a:b] - base + size[a:b])
    return out


def _equal_spans(flat: np.ndarray, a: np.ndarray, a_size: np.ndarray, b: np.ndarray, b_size: np.ndarray) -> np.ndarray:
    """Whether the bytes of two spans are the same, for each pair."""
    equal = a_size == b_size
    for i in range(int(a_size.max(initial=0))):
        at = np.flatnonzero(equal & (a != b) & (a_size > i))
        equal[at] &= flat[a[at] + i] == flat[b[at] + i]
    return equal


def gather(flat: np.ndarray, first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The bytes of all spans, one after another."""
    offset = np.cumsum(size) - size
    return flat[np.repeat(first - offset, size) + np.arange(int(size.sum()))]


def _text_messages(shard: sh.Shard, texts: _Texts, length: int, buckets: int) -> Iterable[tuple[int, bytes]]:
    for bucket, part in sh.cut_by_bucket(texts.key, buckets):
        data = gather(shard.flat, texts.first[part], texts.count[part] + length - 1)
        small = [sh.squeeze(x.tobytes()) for x in (texts.count[part].astype(np.uint16), texts.rel[part].astype(np.uint16), shard.ids[texts.doc[part]])]
        yield bucket, sh.frames(sh.pack_sorted(texts.key[part]), *small, sh.squeeze(data.tobytes(), 3))


def resolve_texts(bodies: list[bytes], length: int) -> list[bytes]:
    """For each text sent, which of its windows also start in a smaller document: one bit each."""
    parts = [sh.unframes(x) for x in bodies]
    number = [len(sh.unsqueeze(p[1])) // 2 for p in parts]
    key = np.concatenate([sh.unpack_sorted(p[0]) for p in parts])
    count, rel, doc = (np.concatenate([np.frombuffer(sh.unsqueeze(p[i]), kind) for p in parts]) for i, kind in ((1, np.uint16), (2, np.uint16), (3, np.int64)))
    flat = np.frombuffer(b"".join(sh.unsqueeze(p[4]) for p in parts), np.uint8)
    count, rel = count.astype(np.int64), rel.astype(np.int64)
    size = count + length - 1
    first = np.cumsum(size) - size

    flag_at = np.cumsum(count) - count
    flags = np.zeros(int(count.sum()), dtype=bool)
    by_key = np.argsort(key, kind="stable")
    before = np.cumsum(size[by_key]) - size[by_key]
    heads = np.flatnonzero(sh.first_of_runs(key[by_key]))
    cuts = np.append(heads[sh.first_of_runs(before[heads] // STEP_BYTES)], len(by_key))  # anchors stay whole
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        part = by_key[a:b]
        text = gather(flat, first[part], size[part])
        found = repeated_windows(text, key[part], count[part], rel[part], doc[part], length)
        n = count[part]
        flags[np.repeat(flag_at[part] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))] = found
    out, i = [], 0
    for n in number:
        a, b = (int(flag_at[i]), int(flag_at[i + n - 1] + count[i + n - 1])) if n else (0, 0)
        out.append(sh.frames(str(b - a).encode(), sh.squeeze(np.packbits(flags[a:b]).tobytes())))
        i += n
    return out


def repeated_windows(flat: np.ndarray, key: np.ndarray, count: np.ndarray, rel: np.ndarray, doc: np.ndarray, length: int) -> np.ndarray:
    """For texts of whole anchors, one after another in `flat`: which windows of each a smaller document has."""
    size = count + length - 1
    first = np.cumsum(size) - size
    by = np.lexsort((count, rel, key))
    label = np.cumsum(sh.first_of_runs(key[by]) | sh.first_of_runs(rel[by]) | sh.first_of_runs(count[by]))
    starts, same = sort_suffixes(flat, first[by], size[by], label)
    order = np.searchsorted(first, starts)
    heads = np.flatnonzero(~same)
    text_of = np.empty(len(order), np.int64)  # of each entry, its distinct text
    text_of[order] = np.cumsum(~same) - 1
    least = np.minimum.reduceat(doc[order], heads)
    chosen = order[heads]

    anchor_first = sh.first_of_runs(key[chosen])
    anchor = np.cumsum(anchor_first) - 1
    alone = np.bincount(anchor)[anchor] == 1
    windows = np.where(alone, 0, count[chosen])  # of each distinct text, those to sort
    at = np.cumsum(windows) - windows
    owner = np.repeat(np.arange(len(chosen)), windows)
    inner = np.arange(int(windows.sum())) - at[owner]
    smaller = np.zeros(0, np.int64)
    if len(owner):
        offset = rel[chosen][owner] - inner
        label = anchor[owner] * (length + 1) + offset
        by_group = np.argsort(label, kind="stable")
        start = first[chosen][owner] + inner
        sorted_, equal = sort_suffixes(flat, start[by_group], length, label[by_group])
        back = np.empty(len(flat), np.int64)  # distinct texts don't overlap, so a start names its window
        back[start] = np.arange(len(start))
        window = back[sorted_]
        runs = np.flatnonzero(~equal)
        smaller = np.empty(len(owner), np.int64)
        smaller[window] = np.repeat(np.minimum.reduceat(least[owner[window]], runs), np.diff(runs, append=len(window)))

    mine = least[text_of]
    bits = count.copy()
    flags = np.zeros(int(bits.sum()), dtype=bool)
    flag_at = np.cumsum(bits) - bits
    later = doc > mine
    entry = np.repeat(np.arange(len(doc)), bits)
    flags |= later[entry]
    sortable = np.flatnonzero(~later & (windows[text_of] > 0))
    if len(sortable):
        n = count[sortable]
        step = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        flags[np.repeat(flag_at[sortable], n) + step] = smaller[np.repeat(at[text_of[sortable]], n) + step] < np.repeat(doc[sortable], n)
    return flags


def covered(shard: sh.Shard, texts: _Texts, got: pa.Table | None, length: int) -> np.ndarray:
    """Which bytes of the shard a repeated window covers."""
    replies = [sh.unframes(x) for x in sh.replies_of(got, 2)] if got is not None else []
    flags = np.concatenate([np.unpackbits(np.frombuffer(sh.unsqueeze(b), np.uint8), count=int(n)) for n, b in replies]) if replies else np.zeros(0, np.uint8)
    change = np.zeros(len(shard.flat) + 1, dtype=np.int32)
    if len(flags):
        spans = texts.spans
        flag_at = np.cumsum(texts.count) - texts.count
        # Rows that repeat an id count as one document.
        later = shard.ids[spans.doc[texts.runs]] > shard.ids[texts.doc[texts.which]]
        n = spans.count[texts.runs]
        step = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        gone = (flags[np.repeat(flag_at[texts.which], n) + step] == 1) | np.repeat(later, n)
        start = (np.repeat(spans.first[texts.runs], n) + step)[gone]
        np.add.at(change, start, 1)
        np.add.at(change, start + length, -1)
    return np.cumsum(change[:-1], dtype=np.int32) > 0


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, shingle: int = SHINGLE, keep: Iterable[str] = (), shard_bytes: int = sh.SHARD_BYTES, characters: bool = False, hot: int = HOT) -> DataFrame:
    """Without every byte that a string of `length` bytes covers which also starts in a smaller document.

    Returns per row: the id, n_bytes, n_removed, n_spans (maximal removed runs), kept (the remaining
    bytes), and the columns of `keep`. Strings are judged on the input; matches never cross documents.
    A null text is empty; a null id counts as larger than all others; rows that share an id count as
    one document, so they don't remove each other's text; texts shorter than `length` stay whole; an
    empty table gives no rows. Columns other than those named are ignored. With `characters`, removed runs
    are widened to whole characters. `hot` says from how many different texts on an anchor's windows are
    sent one by one; it moves work and memory, never the result.
    """
    if not 0 < shingle <= length < 1000:
        raise ValueError("0 < shingle <= length < 1000 must hold")
    keep = list(keep)
    size = sh.text_bytes(docs, text_col)
    number = max(1, size // shard_bytes)
    few, many = max(1, size // (2 * shard_bytes)), max(1, size // shard_bytes)
    parts = sh.shard(docs, id_col, text_col, number, keep)

    first = sh.send(parts, None, lambda s, _: anchor_messages(_Found(s, length, shingle), few), 1)
    counts = sh.answer(first, lambda b: count_keys(b, hot), 1)

    def windows(s: sh.Shard, got: pa.Table | None) -> Iterable[tuple[int, bytes]]:
        if got is not None and any(any(sh.unframes(x)[2]) for x in sh.replies_of(got, 1)):
            _, keyed = hot_windows(_Found(s, length, shingle), got)
            yield from count_messages(keyed, keyed.number, few)

    counts = counts.unionByName(sh.answer(sh.send(parts, counts, windows, 3), lambda b: count_keys(b, hot), 3))

    def texts(s: sh.Shard, got: pa.Table | None) -> Iterable[tuple[int, bytes]]:
        return _text_messages(s, _Texts(s, _Spans(_Found(s, length, shingle), got, length), length), length, many)

    found = sh.answer(sh.send(parts, counts, texts, 2), lambda b: resolve_texts(b, length), 2)

    def finish(_: int, s: sh.Shard, got: pa.Table | None) -> pa.Table:
        gone = covered(s, _Texts(s, _Spans(_Found(s, length, shingle), got, length), length), got, length)
        if characters and len(gone):
            head = (s.flat & 0xC0) != 0x80
            head[s.offsets[:-1][s.offsets[:-1] < len(gone)]] = True
            at = np.flatnonzero(head)
            gone = np.repeat(np.logical_or.reduceat(gone, at), np.diff(at, append=len(gone)))
        total = np.zeros(len(gone) + 1, np.int64)
        np.cumsum(gone, out=total[1:])
        begins = gone.copy()
        begins[1:] &= ~gone[:-1]
        inner = s.offsets[:-1][s.offsets[:-1] < len(gone)]
        begins[inner] = gone[inner]  # a run ends with its document
        spans = np.zeros(len(gone) + 1, np.int64)
        np.cumsum(begins, out=spans[1:])
        offsets = s.offsets - total[s.offsets]
        kept = s.flat[~gone]
        column = pa.Array.from_buffers(pa.large_binary(), len(s), [None, pa.py_buffer(offsets.astype(np.int64)), pa.py_buffer(np.ascontiguousarray(kept))]).cast(pa.binary())
        own = s.kept()
        return pa.table({"id": own.pop("id"), "n_bytes": np.diff(s.offsets), "n_removed": np.diff(total[s.offsets]), "n_spans": np.diff(spans[s.offsets]), "kept": column, **{c: v for c, v in own.items()}})

    types = {f.name: f.dataType.simpleString() for f in docs.schema}
    schema = ", ".join(["id long, n_bytes long, n_removed long, n_spans long, kept binary", *(f"k{i} {types[c]}" for i, c in enumerate(keep))])
    out = sh.over(parts, counts.unionByName(found), finish, schema)
    return out.toDF(id_col, "n_bytes", "n_removed", "n_spans", "kept", *keep)
