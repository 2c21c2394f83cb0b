"""Stupid-backoff scores of documents under n-gram counts of the whole corpus.

The relational form: n-gram count tables, partitioned by hash, are joined to each document's exploded
n-grams and summed per document. The count table's rows, the join and its keys travel as blobs: a
shard sends its distinct n-grams with their counts to the partition of their hash, which adds them up
and answers with the totals. A document's own occurrences are taken off, so that it isn't scored by
what it says itself. The empty n-gram counts all words.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import shards as sh
from .rolling import U, mix, stream
from .substring_dedup import Words

ORDER, ALPHA = 3, 0.4
LM_SHARD = 2 * sh.SHARD_BYTES  # the more text in a shard, the fewer distinct n-grams a byte of it sends


class NGrams:
    """The n-grams of a shard: for each order their places, which distinct one each is, and how often its own document has it."""

    def __init__(self, shard: sh.Shard, order: int):
        words = Words(shard.flat, shard.offsets, seeds=(21,))
        token, self.offsets = words.first, words.offsets
        del words
        self.total = n = len(token)
        per_doc = np.diff(self.offsets)
        self.doc = np.repeat(np.arange(len(shard), dtype=np.int32), per_doc)
        end = np.repeat(self.offsets[1:], per_doc)
        key = np.full(n, stream(1, 60)[0])
        self.at, self.which, self.own, keys, counts = [], [], [], [], []
        for size in range(1, order + 1):
            key = mix(key[: max(0, n - size + 1)] * U(0x9E3779B97F4A7C15) + token[size - 1 :] if n >= size else key[:0])
            at = np.flatnonzero(np.arange(len(key)) + size <= end[: len(key)]).astype(np.int32 if n < 1 << 31 else np.int64)
            order_ = np.argsort(key[at], kind="stable")  # documents ascend under each key
            every, doc = key[at][order_], self.doc[at][order_]
            head = sh.first_of_runs(every)
            first = np.flatnonzero(head)
            keys.append(every[first])
            counts.append(np.diff(first, append=len(every)).astype(np.uint32))
            which, own = np.empty(len(every), np.int32), np.empty(len(every), np.int32)
            which[order_] = np.cumsum(head) - 1
            own_first = np.flatnonzero(head | sh.first_of_runs(doc))
            own_size = np.diff(own_first, append=len(every)).astype(np.int32)
            own[order_] = np.repeat(own_size, own_size)
            self.at.append(at)
            self.which.append(which)
            self.own.append(own)
        # One ascending list of the distinct n-grams of all orders.
        every = np.concatenate(keys)
        merge = np.argsort(every, kind="stable")
        self.distinct, self.count = every[merge], np.concatenate(counts)[merge]
        rank = np.empty(len(every), np.int32)
        rank[merge] = np.arange(len(every))
        base = 0
        for i, k in enumerate(keys):
            self.which[i] = rank[base : base + len(k)][self.which[i]]
            base += len(k)


EMPTY = U(0)  # the key of the empty n-gram


def count_messages(grams: NGrams, buckets: int) -> Iterable[tuple[int, bytes]]:
    keys = np.concatenate([[EMPTY], grams.distinct]).astype(np.uint64)
    counts = np.concatenate([[grams.total], grams.count]).astype(np.uint32)
    for bucket, part in sh.cut_by_bucket(keys, buckets):
        yield bucket, sh.frames(sh.pack_sorted(keys[part]), sh.pack_planes(counts[part], 3))


def add_counts(bodies: list[bytes]) -> list[bytes]:
    parts = [sh.unframes(x) for x in bodies]
    keys = [sh.unpack_sorted(p[0]) for p in parts]
    counts = np.concatenate([sh.unpack_planes(p[1], np.uint32) for p in parts])
    cuts = np.cumsum([len(k) for k in keys])[:-1]
    every = np.concatenate(keys)
    order = np.argsort(every, kind="stable")
    head = np.flatnonzero(sh.first_of_runs(every[order]))
    total = np.empty(len(every), np.int64)
    total[order] = np.repeat(np.add.reduceat(counts[order], head, dtype=np.int64), np.diff(head, append=len(every)))
    return [sh.pack_planes(x, 3) for x in np.split(total, cuts)]


def log_scores(grams: NGrams, totals: np.ndarray, order: int, alpha: float) -> np.ndarray:
    """The logarithm of each word's score; totals: the corpus count of each distinct n-gram, the empty one first."""
    n = grams.total
    words_of = np.diff(grams.offsets)
    counts = np.maximum(totals[0] - words_of[grams.doc], 1).astype(np.float64) if n else np.zeros(0)
    score = np.zeros(n)
    for size in range(1, order + 1):
        at = grams.at[size - 1]
        own = np.zeros(n)
        own[at] = totals[1:][grams.which[size - 1]] - grams.own[size - 1]
        last = at + (size - 1)
        if size == 1:
            score = np.maximum(own, 0.5) / counts
        else:
            with np.errstate(divide="ignore", invalid="ignore"):
                score[last] = np.where(own[at] > 0, own[at] / counts[at], alpha * score[last])
        counts = own
    return np.log(score)


def score_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", order: int = ORDER, alpha: float = ALPHA, shard_bytes: int = LM_SHARD) -> DataFrame:
    """(id, n_words, log_score, perplexity) of every row.

    A word's score is the relative frequency of the longest n-gram that ends in it and is found in
    other documents, times alpha for each shorter order; a word found nowhere else counts a half.
    Rows are told apart by their place: of repeated rows each counts for the others. Texts without
    words (null, empty) score 0 and have no perplexity; a null id stays null; an empty table gives no
    rows. Words are runs of characters other than space and U+0009 to U+000D. Other columns are ignored.
    """
    if order < 1:
        raise ValueError("order must be at least 1")
    size = sh.text_bytes(docs, text_col)
    number = max(1, size // shard_bytes)
    parts = sh.shard(docs, id_col, text_col, number, level=3)
    buckets = max(1, 2 * order * size // (3 * shard_bytes))
    counts = sh.answer(sh.send(parts, None, lambda s, _: count_messages(NGrams(s, order), buckets), 1), add_counts, 1)

    def finish(_: int, s: sh.Shard, got: pa.Table | None) -> pa.Table:
        grams = NGrams(s, order)
        totals = np.concatenate([sh.unpack_planes(x, np.int64) for x in sh.replies_of(got, 1)])
        scores = log_scores(grams, totals, order, alpha)
        n = np.diff(grams.offsets)
        per_doc = np.array([scores[a:b].sum() for a, b in zip(grams.offsets[:-1], grams.offsets[1:], strict=True)])
        perplexity = pa.array(np.exp(-per_doc / np.maximum(n, 1)), mask=n == 0)
        return pa.table({"id": s.kept()["id"], "n_words": n.astype(np.int64), "log_score": per_doc.astype(np.float64), "perplexity": perplexity})

    return sh.over(parts, counts, finish, "id long, n_words long, log_score double, perplexity double").withColumnRenamed("id", id_col)
