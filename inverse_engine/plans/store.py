"""Written steps: small tables that several parts of a plan read, and indexes. All executors see the folder."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid
from collections.abc import Callable, Sequence
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession

PLAIN = {"parquet.enable.dictionary": "false"}
_written: list[tuple[SparkSession, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; a temporary one only where the session names none and all runs on one machine."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    own = getattr(spark.sparkContext, "_inverse_engine_steps", None)
    if own is None:
        own = "file://" + tempfile.mkdtemp(prefix="inverse-engine-steps-")
        spark.sparkContext._inverse_engine_steps = own
    return own


def _delete_all() -> None:
    for spark, path in _written:
        if spark.sparkContext._jsc is not None:
            place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
    _written.clear()


def new_path(spark: SparkSession, name: str) -> str:
    """A path for a step; it goes when the driver's process ends."""
    if not _written:
        atexit.register(_delete_all)
    _written.append((spark, f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"))
    return _written[-1][1]


def stored(df: DataFrame, name: str, plain: bool = False) -> DataFrame:
    """Write a step as Parquet and read it back; what is stored already stays as it is. plain: without dictionaries, which for columns
    of many different numbers take longer to build than they save."""
    if getattr(df, "_is_stored", False):
        return df
    path = new_path(df.sparkSession, name)
    df.write.options(**(PLAIN if plain else {})).parquet(path)
    step = df.sparkSession.read.schema(df.schema).parquet(path)
    step._is_stored = True
    return step


#: Runs that go side by side.
MOST_TOGETHER = 4


def together(spark: SparkSession, runs: Sequence[Callable[[], DataFrame]], name: str) -> list[DataFrame]:
    """The written results of independent runs, in their order. Each run is a series of jobs that are mostly too small for all cores, and
    planning them takes longer than their tasks: so runs go side by side. An error is raised when those that had begun have ended."""
    one = inheritable_thread_target(spark)(lambda run: stored(run(), name))
    with ThreadPoolExecutor(MOST_TOGETHER) as pool:
        return list(pool.map(one, runs))
