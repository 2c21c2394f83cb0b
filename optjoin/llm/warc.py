"""A deterministic sharded WARC writer, and its reader.

Records are sorted by id over ranges of ids. The ranges follow from the ids and the payload sizes alone,
so equal tables give equal archives, whatever the cluster. Each range is written as gzip members, one
per record, in files rolled by compressed size, with every header and digest made anew from the payload.
A file is written under a temporary name of its attempt and renamed to one that holds the digest of its
contents; it counts only once the manifest names it, so repeated and abandoned attempts do no harm.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import cut

ROLL_BYTES, DATE = 64 << 20, "2000-01-01T00:00:00Z"
RANGE_BYTES, MOST_RANGES, SAMPLES = 16 << 20, 1 << 14, 64
MANIFEST = "file string, records long, bytes long, sha1 string"
RECORD = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"
_NAMESPACE = uuid.UUID("6f2b7a5e-94f4-5b0e-9d54-3a1f6f1f0c11")


def digest32(data: bytes) -> str:
    """SHA-1 in base 32."""
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def _clean(url: str | None, key: int | None) -> str:
    if not url:
        return f"urn:page:{key}"
    return re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url)


def record_id(key: int | None, digest: str, copy: int = 0) -> str:
    """The identity of a record; rows that share an id and a payload are told apart by their number."""
    return f"<urn:uuid:{uuid.uuid5(_NAMESPACE, f'{key} {digest} {copy}' if copy else f'{key} {digest}')}>"


def record(key: int | None, url: str | None, payload: bytes, refers_to: int | None, date: str = DATE, copy: int = 0) -> bytes:
    """One record: a response with its HTTP block, or a revisit with the HTTP header alone."""
    digest = digest32(payload)
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    head = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: {record_id(key, digest, copy)}",
        f"WARC-Date: {date}",
        f"WARC-Target-URI: {_clean(url, key)}",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"WARC-Block-Digest: sha1:{digest32(block)}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(refers_to, digest)}", f"WARC-Refers-To-Page: {refers_to}"]
    if key is not None:
        head.append(f"WARC-Page: {key}")
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


class _Files:
    """Rolls, names and commits the files of one range of ids."""

    def __init__(self, folder: str, number: int, roll_bytes: int):
        self.fs, self.folder = pa.fs.FileSystem.from_uri(folder)
        self.range, self.roll_bytes, self.number, self.out = number, roll_bytes, 0, None
        self.done: list[tuple[str, int, int, str]] = []

    def add(self, data: bytes) -> None:
        gz = zlib.compressobj(6, zlib.DEFLATED, 31)
        member = gz.compress(data) + gz.flush()
        if self.out is None:
            self.name = f"{self.folder}/_temporary-{self.range:06d}-{self.number:05d}-{uuid.uuid4().hex}"
            self.out, self.records, self.size, self.sha1 = self.fs.open_output_stream(self.name, compression=None), 0, 0, hashlib.sha1()
        self.out.write(member)
        self.sha1.update(member)
        self.records += 1
        self.size += len(member)
        if self.size >= self.roll_bytes:
            self.close()

    def close(self) -> None:
        if self.out is not None:
            self.out.close()
            final = f"{self.range:06d}-{self.number:05d}-{self.sha1.hexdigest()[:16]}.warc.gz"
            self.fs.move(self.name, f"{self.folder}/{final}")
            self.done.append((final, self.records, self.size, self.sha1.hexdigest()))
            self.out, self.number = None, self.number + 1


def revisits(pages: DataFrame, id_col: str, payload_col: str, min_bytes: int = 0) -> DataFrame:
    """(id, sha1, first): the rows whose payload a smaller id has, and that id. Texts aren't shuffled."""
    payload = F.coalesce(F.encode(F.col(f"`{payload_col}`").cast("string"), "UTF-8"), F.lit(b""))
    keys = pages.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.sha1(payload).alias("sha1"), F.length(payload).alias("n")).filter(F.col("n") >= min_bytes)
    keys = cut(keys.select("id", "sha1"))
    least = cut(keys.groupBy("sha1").agg(F.min("id").alias("first"), F.count("*").alias("n")).filter("n > 1").drop("n"))
    return keys.join(least, "sha1").filter("id is null or id > first").select("id", "sha1", "first").distinct()


def id_ranges(pages: DataFrame, id_col: str, payload_col: str, range_bytes: int = RANGE_BYTES) -> np.ndarray:
    """The first id of each range but the first, for ranges of about range_bytes of payload; at most MOST_RANGES ranges.

    Bounds are quantiles, by bytes, of the ids that a hash of the id chooses, some SAMPLES for a range (all ids
    where there are fewer): a function of the table, not of its partitions. Only they reach the driver.
    """
    key, size = F.col(f"`{id_col}`").cast("long"), F.octet_length(F.col(f"`{payload_col}`").cast("string"))
    sizes = pages.select(key.alias("id"), (F.coalesce(size, F.lit(0)) + 200).cast("long").alias("n")).filter("id is not null")
    rows, total = sizes.agg(F.count("*"), F.sum("n")).first()
    ranges = min(MOST_RANGES, (total or 0) // range_bytes + 1)
    if ranges == 1:
        return np.zeros(0, np.int64)
    every = max(1, rows // (SAMPLES * ranges))
    chosen = sizes.filter(F.pmod(F.xxhash64("id"), F.lit(every)) == 0).groupBy("id").agg(F.sum("n").alias("n")).toArrow().sort_by("id")
    ids, upto = chosen["id"].to_numpy(), np.cumsum(chosen["n"].to_numpy())
    at = np.searchsorted(upto, upto[-1] * np.arange(1, ranges) / ranges) if len(ids) else np.zeros(0, np.int64)
    return np.unique(ids[at])


def write_warc(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", min_bytes: int = 0, roll_bytes: int = ROLL_BYTES, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """Writes a record per row into `folder` (a URI all executors reach) and returns the manifest.

    Of equal payloads of at least min_bytes, the smallest id's is a response and the others revisit
    it; rows that share an id and a payload are both responses, with record ids of their own. A null
    payload is empty; a null id sorts first, and such a row revisits if an id has its payload; a null URL
    gets a URN. An empty table writes nothing. The manifest is stored beside the files, as Parquet.
    Equal tables give files of equal names and contents, however they are partitioned.
    """
    spark = pages.sparkSession
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(folder)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).mkdirs(hadoop)
    cols = [F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{url_col}`").cast("string").alias("url"), F.col(f"`{payload_col}`").cast("string").alias("payload")]
    rows = pages.select(*cols, F.lit(None).cast("string").alias("sha1"), F.lit(None).cast("long").alias("first"), F.lit(1).alias("kind"))
    known = revisits(pages, id_col, payload_col, min_bytes).select("id", F.lit(None).cast("string").alias("url"), F.lit(None).cast("string").alias("payload"), "sha1", "first", F.lit(0).alias("kind"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files: _Files | None = None
        done: list[tuple[str, int, int, str]] = []
        now, firsts, last, copy = object(), {}, None, 0
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                for key, url, text, sha1, first, kind, number in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    if files is None or files.range != number:
                        if files is not None:
                            files.close()
                            done += files.done
                        files, now = _Files(folder, number, roll_bytes), object()
                    if key != now:
                        now, firsts, last = key, {}, None
                    if kind == 0:
                        firsts[sha1] = first
                        continue
                    payload = (text or "").encode()
                    copy = copy + 1 if payload == last else 0  # equal payloads of an id stand together
                    last = payload
                    refers = firsts.get(hashlib.sha1(payload).hexdigest()) if firsts else None
                    files.add(record(key, url, payload, refers, copy=copy))
        if files is not None:
            files.close()
            done += files.done
        if done:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*done, strict=True)], ["file", "records", "bytes", "sha1"])

    bounds = id_ranges(pages, id_col, payload_col, range_bytes)

    @F.pandas_udf("int")
    def range_of(ids: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(bounds, ids.to_numpy(np.int64), side="right").astype(np.int32))

    number = F.when(F.col("id").isNull(), 0).otherwise(range_of(F.coalesce("id", F.lit(0))))
    every = rows.unionByName(known).withColumn("range", number if len(bounds) else F.lit(0))
    ordered = every.repartitionById(len(bounds) + 1, F.col("range").cast("int")).sortWithinPartitions("range", "id", "kind", F.coalesce("payload", F.lit("")), "url")
    ordered.mapInArrow(work, MANIFEST).write.mode("overwrite").parquet(f"{folder}/manifest")
    return spark.read.parquet(f"{folder}/manifest")


def parse_records(read) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, block) of each gzip member; read(n) gives bytes. One record is in memory at a time."""
    data = b""
    while True:
        member = zlib.decompressobj(31)
        parts = []
        while not member.eof:
            data = data or read(1 << 20)
            if not data:
                if parts:
                    raise ValueError("the archive ends within a record")
                return
            parts.append(member.decompress(data))
            data = member.unused_data
        head, _, rest = b"".join(parts).partition(b"\r\n\r\n")
        lines = head.decode().split("\r\n")
        fields = dict(x.split(": ", 1) for x in lines[1:])
        block = rest[: int(fields["Content-Length"])]
        if not lines[0].startswith("WARC/") or rest[len(block) :] != b"\r\n\r\n" or fields["WARC-Block-Digest"] != "sha1:" + digest32(block):
            raise ValueError("a damaged record")
        yield fields, block


def read_warc(manifest: DataFrame, folder: str, payloads: bool = False) -> DataFrame:
    """A row per record of the files that the manifest names; every digest is checked. As many tasks as files."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())])
        fs, base = pa.fs.FileSystem.from_uri(folder)
        for batch in batches:
            for name, count in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows, n = [], 0
                with fs.open_input_stream(f"{base}/{name}", compression=None) as file:
                    for f, block in parse_records(file.read):
                        head, _, payload = block.partition(b"\r\n\r\n")
                        size = int(re.search(rb"Content-Length: (\d+)", head)[1])
                        digest = f["WARC-Payload-Digest"].removeprefix("sha1:")
                        if f["WARC-Type"] == "response" and (len(payload) != size or digest32(payload) != digest):
                            raise ValueError(f"a damaged payload in {name}")
                        page, first = f.get("WARC-Page"), f.get("WARC-Refers-To-Page")
                        rows.append((page and int(page), f["WARC-Target-URI"], size, digest, f["WARC-Type"], first and int(first), payload if payloads else None))
                        n += 1
                        if len(rows) == 2000:
                            yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)
                            rows = []
                if n != count:
                    raise ValueError(f"{name} has {n} records, its manifest {count}")
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    return manifest.select("file", "records").repartition(max(1, manifest.count())).mapInArrow(work, RECORD)
