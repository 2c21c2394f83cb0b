"""Bit masks of keys, in buckets of 32768 bits, and the codes of single bit rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fold_bits(df: DataFrame, var: str) -> DataFrame:
    """(bucket, bits): the values of a non-negative integer variable."""
    return df.groupBy(F.expr(f"bitmap_bucket_number(`{var}` + 1)").alias("bucket")).agg(F.expr(f"bitmap_construct_agg(bitmap_bit_position(`{var}` + 1))").alias("bits"))


def mask_and(a: DataFrame, b: DataFrame) -> DataFrame:
    """The intersection of two masks; buckets in both only."""
    both = a.unionByName(b).groupBy("bucket").agg(F.count("*").alias("n"), F.expr("bitmap_and_agg(bits)").alias("bits"))
    return both.filter("n = 2").select("bucket", "bits")


def positions(mask: DataFrame, var: str) -> DataFrame:
    """The values that a mask holds, by built-in functions."""
    byte = mask.select("bucket", F.posexplode(F.expr("transform(sequence(1, length(bits)), i -> cast(conv(hex(substring(bits, i, 1)), 16, 10) as int))")).alias("i", "byte")).filter("byte > 0")
    bit = byte.select("bucket", "i", F.explode(F.expr("filter(sequence(0, 7), j -> shiftright(byte, j) & 1 = 1)")).alias("j"))
    return bit.select(F.expr("cast((bucket - 1) * 32768 + 8 * i + j as bigint)").alias(var))


def popcount(mask: DataFrame) -> DataFrame:
    return mask.agg(F.coalesce(F.sum(F.expr("bitmap_count(bits)")), F.lit(0)).alias("n"))


def bloom_filter(left: DataFrame, keys: DataFrame, on: list[str], log2_bits: int = 27) -> DataFrame:
    """left without most rows that have no partner: one bit for each hash of a key, so none with a partner is lost.

    The bitmap has 2**log2_bits bits, which bounds what is moved whatever the number of keys.
    """
    hashed = F.pmod(F.xxhash64(*on), F.lit(1 << log2_bits))
    return unfold(left.withColumn("_hash", hashed), fold_bits(keys.select(hashed.alias("_hash")), "_hash"), "_hash").drop("_hash")


def unfold(df: DataFrame, mask: DataFrame, var: str) -> DataFrame:
    """Rows whose value is set in the mask: a join on the bucket and a bit test."""
    place = f"bitmap_bit_position(`{var}` + 1)"
    byte = f"conv(hex(substring(bits, cast({place} div 8 + 1 as int), 1)), 16, 10)"
    marked = df.withColumn("bucket", F.expr(f"bitmap_bucket_number(`{var}` + 1)")).join(mask, "bucket")
    return marked.filter(F.expr(f"(shiftright(cast({byte} as int), cast({place} % 8 as int)) & 1) = 1")).drop("bucket", "bits")


def run_lengths(bits: str) -> list[int]:
    """First bit, then the lengths of its runs."""
    out, last = [int(bits[0])], 0
    for i in range(1, len(bits) + 1):
        if i == len(bits) or bits[i] != bits[i - 1]:
            out.append(i - last)
            last = i
    return out


def hybrid(bits: str) -> tuple[str, list[int]]:
    """Positions of set bits (from 1) where they are fewer than the run lengths, else the runs."""
    runs = run_lengths(bits)
    ones = [i + 1 for i, b in enumerate(bits) if b == "1"]
    return ("positions", ones) if len(ones) < len(runs) - 1 else ("runs", runs)


def decode(kind: str, data: list[int], size: int) -> str:
    if kind == "positions":
        held = set(data)
        return "".join("1" if i + 1 in held else "0" for i in range(size))
    bit, out = data[0], ""
    for n in data[1:]:
        out += str(bit) * n
        bit = 1 - bit
    return out
