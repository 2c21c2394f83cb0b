"""Where intermediate results go."""

from __future__ import annotations

import ctypes
import sys
import tempfile
import types
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The shared folder that the cluster names in spark.checkpoint.dir. Where that is unset: the context's, or on a local master one of this machine."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = f"{tempfile.gettempdir()}/checkpoints"
    return named


def cut(df: DataFrame) -> DataFrame:
    """The rows of df without their lineage, in the shared folder. The shuffle files that made them are given up."""
    context = df.sparkSession.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        context.setCheckpointDir(shared_dir(df.sparkSession))
    rows = df.checkpoint()
    drop_shuffles(df)
    return rows


def drop_shuffles(df: DataFrame) -> None:
    """Removes the shuffle files of a plan that has run; else they stay until the driver happens to collect its garbage.

    They stay registered, so Spark makes them anew if the same plan runs again.
    """
    plan = df._jdf.queryExecution().executedPlan()
    if plan.getClass().getSimpleName() == "AdaptiveSparkPlanExec":
        driver = df.sparkSession.sparkContext._jsc.sc().shuffleDriverComponents()
        for shuffle in list(plan.context().shuffleIds().keySet()):
            driver.removeShuffle(shuffle, True)


def once(key: tuple, make: Callable):
    """What make() gives, made once per process: Python workers live longer than their tasks."""
    held = sys.modules.setdefault("_held_by_worker", types.ModuleType("_held_by_worker")).__dict__.setdefault("items", {})
    if key not in held:
        held[key] = make()
    return held[key]


class Remembered(dict):
    """The values of a function of strings; short ones are kept, up to a number of them."""

    def __init__(self, function: Callable[[str], bytes], limit: int, longest: int = 48):
        super().__init__()
        self.function, self.limit, self.longest = function, limit, longest

    def __missing__(self, key: str) -> bytes:
        value = self.function(key)
        if len(key) <= self.longest and len(self) < self.limit:
            self[key] = value
        return value


def release() -> None:
    """Gives freed memory back to the system: idle Python workers stay alive beside the busy ones."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)
