"""Readers and sinks of other formats: triples as lines of text, CSV, JSON, ORC, bucketed tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_LINE = r'^\s*<([^<>]*)>\s+<([^<>]*)>\s+(?:<([^<>]*)>|"((?:[^"\\]|\\.)*)"(?:\^\^<[^<>]*>|@[A-Za-z0-9-]+)?)\s*\.\s*$'


def read_nt(spark: SparkSession, path: str) -> DataFrame:
    """(s, p, o) of a text with a triple per line. Blank lines and comments are skipped; any other line fails the read."""
    line = F.col("value")
    rows = spark.read.text(path).filter(~line.rlike(r"^\s*(#.*)?$"))
    part = lambda i: F.regexp_extract(line, _LINE, i)
    text = part(4)
    for escaped, plain in (("\\\\", "\u0001"), ("\\n", "\n"), ("\\r", "\r"), ("\\t", "\t"), ('\\"', '"'), ("\u0001", "\\")):
        text = F.replace(text, F.lit(escaped), F.lit(plain))
    rows = rows.filter(F.when(line.rlike(_LINE), F.lit(True)).otherwise(F.raise_error(F.concat(F.lit("not a triple: "), line)).cast("boolean")))
    return rows.select(part(1).alias("s"), part(2).alias("p"), F.when(line.rlike(r"^\s*<[^<>]*>\s+<[^<>]*>\s+<"), part(3)).otherwise(text).alias("o"))


def write_nt(df: DataFrame, path: str, node=None) -> None:
    """A line per triple of (s, p, o); node: whether o is a node, not text. U+0001 in texts isn't allowed."""
    o = F.col("o")
    for plain, escaped in (("\\", "\\\\"), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t"), ('"', '\\"')):
        o = F.replace(o, F.lit(plain), F.lit(escaped))
    text = F.concat(F.lit('"'), o, F.lit('"'))
    value = text if node is None else F.when(node, F.concat(F.lit("<"), F.col("o"), F.lit(">"))).otherwise(text)
    line = F.concat(F.lit("<"), F.col("s"), F.lit("> <"), F.col("p"), F.lit("> "), value, F.lit(" ."))
    df.select(line.alias("value")).write.mode("overwrite").text(path)


def read_any(spark: SparkSession, path: str, fmt: str, schema) -> DataFrame:
    """CSV (with a header), JSON lines, ORC or Parquet under a given schema: no pass to infer it."""
    reader = spark.read.schema(schema).format(fmt)
    return (reader.option("header", True).option("mode", "FAILFAST").option("enforceSchema", False) if fmt == "csv" else reader).load(path)


def write_any(df: DataFrame, path: str, fmt: str) -> None:
    (df.write.option("header", True) if fmt == "csv" else df.write).mode("overwrite").format(fmt).save(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int, path: str | None = None) -> DataFrame:
    """A table in buckets of a key, sorted inside: groups and joins on the key need no exchange."""
    writer = df.write.mode("overwrite").format("parquet").bucketBy(buckets, key).sortBy(key)
    (writer.option("path", path) if path else writer).saveAsTable(name)
    return df.sparkSession.table(name)
