"""Packing of tokenised documents into sequences of a fixed length, online and in bounded space.

Each partition keeps a fixed number of open windows. A document's whole windows leave at once; what
remains goes into the open window that it fits best. When none has room, the fullest is filled up by
a cut and emitted. Open windows left at the end of the partitions are merged in groups.
"""

from __future__ import annotations

import base64
import bisect
import json
import re
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import Remembered, once
from .session import cut as cut_lineage

SIZE, OPEN, CACHE = 2048, 128, 500_000
PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


class ByteBpe:
    """Ids of a byte-level BPE vocabulary in its `tokenizers` form, by the same vocabulary's ranks.

    Texts are split at the literals of added tokens, and the rest is cut before a space that follows a
    character other than white space. No pre-token spans such a place, so ids of the parts, which repeat
    and are remembered, join to the ids of the text.
    """

    def __init__(self, ranks_path: str, pattern: str, cache: int = CACHE, added: dict[str, int] | None = None):
        import tiktoken

        with open(ranks_path, "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        self.encoding = tiktoken.Encoding("byte_bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.known = Remembered(lambda part: np.array(self.encoding.encode_ordinary(part), dtype="<u4").tobytes(), cache)
        self.added = {t: np.array([i], dtype="<u4").tobytes() for t, i in (added or {}).items()}
        self.literals = re.compile("(" + "|".join(map(re.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None

    @staticmethod
    def parts(text: str) -> list[str]:
        out, held = [], ""
        pieces = text.split(" ")
        if "" not in pieces and not any(p[-1].isspace() for p in pieces):
            return [pieces[0], *[" " + p for p in pieces[1:]]]
        for i, p in enumerate(pieces):
            if i and held and not held[-1].isspace():
                out.append(held)
                held = " " + p
            else:
                held += " " + p if i else p
        return [*out, held] if held else out

    def encode(self, text: str) -> np.ndarray:
        pieces = self.literals.split(text) if self.literals else [text]
        return np.frombuffer(b"".join(self.added[p] if i % 2 else b"".join(map(self.known.__getitem__, self.parts(p))) for i, p in enumerate(pieces) if p), dtype="<u4")


def added_tokens(path: str) -> dict[str, int]:
    """The literals that a vocabulary in `tokenizers` form takes out of a text as they stand, and their ids."""
    with open(path, encoding="utf-8") as file:
        found = json.load(file)["added_tokens"]
    if any(t[flag] for t in found for flag in ("single_word", "lstrip", "rstrip", "normalized")):
        raise ValueError("only added tokens that match literally are known")
    return {t["content"]: t["id"] for t in found}


def public_byte_bpe() -> ByteBpe:
    """The public 50k byte-level vocabulary, found by its package."""
    import public_tokenizers

    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    return once(("byte_bpe", path), lambda: ByteBpe(path, public_tokenizers.PATTERN, added=added_tokens(public_tokenizers.path("byte_bpe_50k.json"))))


class OpenWindows:
    """At most `limit` windows with room. Pieces are (doc_id, start, length, crc, doc_tokens)."""

    def __init__(self, size: int, limit: int, emit: Callable[[list[tuple]], None]):
        self.size, self.limit, self.emit = size, limit, emit
        self.rooms: list[tuple[int, int]] = []  # (room, serial), ascending
        self.held: dict[int, list[tuple]] = {}
        self.serial = 0

    def put(self, length: int, cut: Callable[[int, int], tuple]) -> None:
        """A piece of this length; cut(a, b) makes the piece of its part."""
        done = 0
        while done < length:
            left = length - done
            i = bisect.bisect_left(self.rooms, (left, -1))
            if left >= self.size:
                self.emit([cut(done, done + self.size)])
                done += self.size
            elif i < len(self.rooms):
                room, serial = self.rooms.pop(i)
                self.held[serial].append(cut(done, length))
                self._close(room - left, serial)
                done = length
            elif len(self.rooms) < self.limit:
                self.held[self.serial] = [cut(done, length)]
                self._close(self.size - left, self.serial)
                self.serial += 1
                done = length
            else:
                room, serial = self.rooms.pop(0)
                self.held[serial].append(cut(done, done + room))
                self._close(0, serial)
                done += room

    def _close(self, room: int, serial: int) -> None:
        if room:
            bisect.insort(self.rooms, (room, serial))
        else:
            self.emit(self.held.pop(serial))


def _table(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows, strict=True), schema, strict=True)] if rows else [pa.array([], f.type) for f in schema], schema=schema)


_SCHEMA = pa.schema([(x, pa.int64()) for x in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")])
_OPEN = _SCHEMA.append(pa.field("open", pa.bool_()))


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer: Callable[[], ByteBpe] = public_byte_bpe, size: int = SIZE, open_windows: int = OPEN, end_id: int = 1, merge_groups: int | None = None) -> DataFrame:
    """One row per piece: where it lies in its document (start, length, doc_tokens) and where it is packed (sequence_id, offset).

    A document is its ids and then `end_id`; a null or empty text is `end_id` alone; a null id stays
    null; rows are packed each for itself, also repeated ones; an empty table gives no rows. Only the
    last window of each merge group can stay short. Other columns are ignored.
    """
    groups = merge_groups

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, base = tokenizer(), TaskContext.get().partitionId() << 32
        rows: list[tuple] = []
        number = 0

        def emit(pieces: list[tuple], open_: bool = False) -> None:
            nonlocal number
            at = 0
            for p in pieces:
                rows.append((*p, base + number, at, open_))
                at += p[2]
            number += 1

        windows = OpenWindows(size, open_windows, emit)
        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.append(coder.encode(text.as_py() or ""), np.uint32(end_id)).astype("<u4")

                def cut(a: int, b: int, ids: np.ndarray = ids, key: int | None = key) -> tuple:
                    return key, a, b - a, zlib.crc32(ids[a:b]), len(ids)

                windows.put(len(ids), cut)
            if len(rows) > 20_000:
                yield _table(rows, _OPEN)
                rows.clear()
        for pieces in windows.held.values():
            emit(pieces, True)
        yield _table(rows, _OPEN)

    chosen = docs.select(F.col(f"`{id_col}`").cast("long").alias("i"), F.col(f"`{text_col}`").cast("string").alias("t"))
    pieces = cut_lineage(chosen.mapInArrow(work, PIECE + ", open boolean"))
    if groups is None:
        open_count = pieces.filter("open").count()
        groups = max(1, open_count // 20_000)

    def merge(table: pa.Table) -> pa.Table:
        group = table["g"][0].as_py()
        rows: list[tuple] = []
        number = 0

        def emit(found: list[tuple]) -> None:
            nonlocal number
            at = 0
            for p in found:
                rows.append((*p, (1 << 62) + (group << 32) + number, at))
                at += p[2]
            number += 1

        # Whole pieces, longest first: their ids aren't at hand any more, so none is cut.
        windows = OpenWindows(size, len(table) + 1, emit)
        cols = [table[c].to_pylist() for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")]
        for p in sorted(zip(*cols, strict=True), key=lambda p: (-p[2], p[0] is None, p[0] or 0, p[1], p[3])):
            windows.put(p[2], lambda a, b, p=p: p)
        for found in windows.held.values():
            emit(found)
        return pa.Table.from_batches([_table(rows, _SCHEMA)])

    loose = pieces.filter("open").drop("open").withColumn("g", F.pmod(F.shiftright("sequence_id", 32), F.lit(groups)))
    return pieces.filter("not open").drop("open").unionByName(loose.groupBy("g").applyInArrow(merge, PIECE)).withColumnRenamed("doc_id", id_col)
