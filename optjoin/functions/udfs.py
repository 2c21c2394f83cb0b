"""The engine's functions in Python form, for users of SQL and for cross-checks. The engine itself uses built-in functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bits import hybrid


def encode_row_udf():
    """A row of 0 and 1 as the text of its hybrid code: its kind, then its integers. Null and empty rows give null."""

    def encode(rows: pd.Series) -> pd.Series:
        codes = (hybrid(b) if b else None for b in rows)
        return pd.Series([" ".join([c[0], *map(str, c[1])]) if c else None for c in codes], dtype=object)

    encode.__annotations__ = {"rows": pd.Series, "return": pd.Series}
    return F.pandas_udf(encode, "string")


def rle_agg():
    """How many runs of neighbours the distinct integers of a group form."""

    def runs(values: pd.Series) -> int:
        held = np.unique(values.dropna().to_numpy())
        return int((np.diff(held) != 1).sum()) + int(len(held) > 0)

    runs.__annotations__ = {"values": pd.Series, "return": int}
    return F.pandas_udf(runs, "int")


class RowToTriples:
    """A subject and parallel arrays of predicates and objects, as triples; null objects make none."""

    def eval(self, subject: str, predicates: list, objects: list) -> Iterator[tuple[str, str, str]]:
        for p, o in zip(predicates, objects, strict=True):
            if o is not None:
                yield subject, p, o


class DecodePositions:
    """The values that a bucket of a mask holds."""

    def eval(self, bucket: int, bits: bytes) -> Iterator[tuple[int]]:
        for i, byte in enumerate(bits):
            for j in range(8):
                if byte >> j & 1:
                    yield ((bucket - 1) * 32768 + 8 * i + j,)


def register_functions(spark: SparkSession) -> None:
    """row_code, run_count, row_to_triples and decode_positions for SQL texts of this session."""
    spark.udf.register("row_code", encode_row_udf())
    spark.udf.register("run_count", rle_agg())
    spark.udtf.register("row_to_triples", F.udtf(RowToTriples, returnType="s string, p string, o string"))
    spark.udtf.register("decode_positions", F.udtf(DecodePositions, returnType="value long"))


def bestmatch_group(df: DataFrame, core: list[str]) -> DataFrame:
    """Without subsumed rows and equal copies, a group of one core binding at a time.

    A cross-check: a core binding with very many rows is one group in one task. The window form has no such bound.
    """
    names = df.columns

    def work(table: pa.Table) -> pa.Table:
        rows = set(zip(*(table[c].to_pylist() for c in names), strict=True))
        bound = lambda r: tuple(i for i, x in enumerate(r) if x is not None)
        masks = {bound(r) for r in rows}
        better = {m: {tuple(r[i] for i in m) for r in rows if set(m) < set(bound(r))} for m in masks}
        left = [r for r in rows if tuple(r[i] for i in bound(r)) not in better[bound(r)]]
        return pa.table([pa.array(c, table.schema.field(i).type) for i, c in enumerate(zip(*left, strict=True))], names=names)

    return df.groupBy(*core).applyInArrow(work, df.schema)
