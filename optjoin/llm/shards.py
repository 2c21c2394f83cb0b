"""Documents in shards, and compact messages between shards and buckets of hashes.

Operators that compare every document with all others work in passes. Documents are dealt once into
shards of a few MB by a hash of their id, as compressed Arrow; each pass sends, per shard and bucket
of the hash space, one blob of what the shard has there (each key once, however often it occurs, so
that a hot key costs a shard one entry), and gets one blob back in the same order. Both numbers grow
with the bytes of the input, so a task's memory doesn't. Passes are one lazy plan: Spark reuses the
exchange of the shards, and a lost executor costs what it had.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .rolling import U, mix
from .session import release

SHARD_BYTES = 4 << 20
PENDING_BYTES = 12 << 20
MESSAGE = "src int, kind int, bucket int, body binary"
LAST = np.iinfo(np.int64).max


def squeeze(data: bytes | memoryview, level: int = 1) -> bytes:
    return zstandard.ZstdCompressor(level=level).compress(data)


def unsqueeze(data: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(data)


def pack_sorted(values: np.ndarray) -> bytes:
    """Ascending 64-bit values as byte planes of their differences."""
    gaps = np.diff(values, prepend=U(0))
    return squeeze(np.ascontiguousarray(gaps.view(np.uint8).reshape(-1, 8).T).data)


def pack_planes(values: np.ndarray, level: int = 1) -> bytes:
    """Integers as byte planes."""
    return squeeze(np.ascontiguousarray(values.view(np.uint8).reshape(-1, values.itemsize).T).data, level)


def unpack_planes(data: bytes, kind: type) -> np.ndarray:
    planes = np.frombuffer(unsqueeze(data), dtype=np.uint8).reshape(np.dtype(kind).itemsize, -1)
    return np.ascontiguousarray(planes.T).view(kind).ravel()


def unpack_sorted(data: bytes) -> np.ndarray:
    planes = np.frombuffer(unsqueeze(data), dtype=np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view(np.uint64).ravel(), dtype=np.uint64)


def frames(*parts: bytes) -> bytes:
    """Several byte strings as one."""
    return np.array([len(parts), *map(len, parts)], dtype=np.int64).tobytes() + b"".join(parts)


def unframes(data: bytes) -> list[bytes]:
    n = int(np.frombuffer(data, np.int64, 1)[0])
    ends = 8 * (n + 1) + np.cumsum(np.frombuffer(data, np.int64, n, 8))
    return [data[b - size : b] for b, size in zip(ends, np.frombuffer(data, np.int64, n, 8), strict=True)]


def utf8(column: pa.ChunkedArray | pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string or binary column and the offset of each row; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], column.type)
    column = column.cast(pa.large_binary()).fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, 8 * column.offset) if len(column) else np.zeros(1, np.int64)
    data = column.buffers()[2]
    flat = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return flat[offsets[0] : offsets[-1]], offsets - offsets[0]


def large(table: pa.Table) -> pa.Table:
    """With 64-bit offsets, so that joining parts can't overflow."""
    wide = {pa.string(): pa.large_string(), pa.binary(): pa.large_binary()}
    return table.cast(pa.schema([pa.field(f.name, wide.get(f.type, f.type)) for f in table.schema]))


def text_bytes(docs: DataFrame, text: str) -> int:
    """Bytes of a text column: one narrow scan; sizes shards and buckets, never the result."""
    return int(docs.agg(F.sum(F.octet_length(F.col(text).cast("string")))).first()[0] or 0)


def shard(docs: DataFrame, id_col: str, text_col: str, shards: int, keep: Iterable[str] = (), level: int = 1) -> DataFrame:
    """Rows (src, body): the id, the text and the kept columns of a few documents of one shard.

    Columns are renamed to id, text, k0, k1 and so on, so names can't clash.
    """
    cols = [F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{text_col}`").cast("string").alias("text")]
    cols += [F.col(f"`{c}`").alias(f"k{i}") for i, c in enumerate(keep)]

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        size = 0

        def flush() -> pa.RecordBatch:
            table = large(pa.Table.from_batches(held))
            key = mix(table["id"].fill_null(LAST).to_numpy().astype(np.int64).view(np.uint64))
            src = ((key >> U(32)) * U(shards) >> U(32)).astype(np.int32)
            order = np.argsort(src, kind="stable")
            table = table.take(pa.array(order))
            cuts = np.flatnonzero(np.diff(src[order], prepend=-1))
            bodies = []
            for a, b in zip(cuts, [*cuts[1:], len(order)], strict=True):
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, table.schema) as out:
                    out.write_table(table.slice(a, b - a).combine_chunks())
                bodies.append(squeeze(sink.getvalue(), level))
            return pa.RecordBatch.from_arrays([pa.array(src[order][cuts], pa.int32()), pa.array(bodies, pa.binary())], ["src", "body"])

        for batch in batches:
            step = max(1, batch.num_rows * PENDING_BYTES // max(1, batch.nbytes))
            for lo in range(0, batch.num_rows, step):
                held.append(batch.slice(lo, step))
                size += held[-1].nbytes
                if size >= PENDING_BYTES:
                    yield flush()
                    held, size = [], 0
        if held:
            yield flush()
        del held[:]
        release()

    return docs.select(*cols).mapInArrow(deal, "src int, body binary")


class Shard:
    """The documents of one shard, ordered by id (null last) and then by text, as flat bytes."""

    def __init__(self, bodies: Iterable[bytes]):
        tables = [pa.ipc.open_stream(unsqueeze(x)).read_all() for x in bodies]
        table = pa.concat_tables(tables)
        flat, offsets = utf8(table["text"])
        ids = table["id"].fill_null(LAST).to_numpy()
        tie = np.zeros(len(ids), dtype=object)
        _, where, count = np.unique(ids, return_inverse=True, return_counts=True)
        for i in np.flatnonzero(count[where] > 1):
            tie[i] = flat[offsets[i] : offsets[i + 1]].tobytes()
        order = np.argsort(ids, kind="stable")
        if (count > 1).any():
            order = np.array(sorted(order, key=lambda i: (ids[i], tie[i] or b"")))
        if (order != np.arange(len(order))).any():
            table = table.take(pa.array(order))
            flat, offsets = utf8(table["text"])
        self.table, self.flat, self.offsets, self.ids = table, flat, offsets, ids[order]

    def __len__(self) -> int:
        return len(self.ids)

    def kept(self) -> dict[str, pa.ChunkedArray]:
        usual = {pa.large_string(): pa.string(), pa.large_binary(): pa.binary()}
        return {c: self.table[c].cast(usual.get(self.table[c].type, self.table[c].type)) for c in self.table.column_names if c != "text"}


def buckets_of(keys: np.ndarray, buckets: int) -> np.ndarray:
    """The bucket of each key; ascending in the key."""
    return ((keys >> U(32)) * U(buckets) >> U(32)).astype(np.int64)


def cut_by_bucket(keys: np.ndarray, buckets: int) -> Iterator[tuple[int, slice]]:
    """The slices of ascending keys, one for each bucket that has some; none without keys."""
    if not len(keys):
        return
    where = buckets_of(keys, buckets)
    cuts = np.flatnonzero(np.diff(where, prepend=-1))
    for a, b in zip(cuts, [*cuts[1:], len(keys)], strict=True):
        yield int(where[a]), slice(int(a), int(b))


def message_table(rows: list[tuple[int, int, int, bytes]]) -> pa.Table:
    src, kind, bucket, body = zip(*rows, strict=True) if rows else ([], [], [], [])
    return pa.table({"src": pa.array(src, pa.int32()), "kind": pa.array(kind, pa.int32()), "bucket": pa.array(bucket, pa.int32()), "body": pa.array(body, pa.binary())})


def replies_of(table: pa.Table, kind: int) -> list[bytes]:
    """The replies of one kind, by bucket."""
    rows = [(b, x) for k, b, x in zip(table["kind"].to_pylist(), table["bucket"].to_pylist(), table["body"].to_pylist(), strict=True) if k == kind]
    return [x for _, x in sorted(rows, key=lambda r: r[0])]


def send(shards: DataFrame, replies: DataFrame | None, work: Callable[[Shard, pa.Table | None], Iterable[tuple[int, bytes]]], kind: int) -> DataFrame:
    """Messages (bucket, blob) of every shard; work sees the shard and the replies so far."""
    rows = lambda src, shard, got: message_table([(src, kind, b, x) for b, x in work(shard, got)])
    return over(shards, replies, rows, MESSAGE)


def over(shards: DataFrame, replies: DataFrame | None, work: Callable[[int, Shard, pa.Table | None], pa.Table], schema: str) -> DataFrame:
    """What work returns for every shard and the replies it got."""
    if replies is None:

        def alone(table: pa.Table) -> pa.Table:
            out = work(table["src"][0].as_py(), Shard(table["body"].to_pylist()), None)
            release()
            return out

        return shards.groupBy("src").applyInArrow(alone, schema)

    def both(left: pa.Table, right: pa.Table) -> pa.Table:
        out = work(left["src"][0].as_py(), Shard(left["body"].to_pylist()), right)
        release()
        return out

    return shards.groupBy("src").cogroup(replies.groupBy("src")).applyInArrow(both, schema)


def answer(messages: DataFrame, work: Callable[[list[bytes]], list[bytes]], kind: int) -> DataFrame:
    """For every bucket, a reply to each of its messages. Messages are taken in the order of their shards."""

    def reply(table: pa.Table) -> pa.Table:
        order = np.argsort(table["src"].to_numpy(), kind="stable").tolist()
        src, body = table["src"].to_pylist(), table["body"].to_pylist()
        bucket = table["bucket"][0].as_py()
        out = message_table([(src[i], kind, bucket, x) for i, x in zip(order, work([body[i] for i in order]), strict=True)])
        release()
        return out

    return messages.groupBy("bucket").applyInArrow(reply, MESSAGE)


def first_of_runs(keys: np.ndarray) -> np.ndarray:
    """True where a value of ascending keys stands first."""
    first = np.ones(len(keys), dtype=bool)
    first[1:] = keys[1:] != keys[:-1]
    return first
