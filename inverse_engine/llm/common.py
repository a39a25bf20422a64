"""Things the training-data operators share: table access, materialised steps, shipping of this package to workers."""

from __future__ import annotations

import atexit
import gc
import os
import re
import tempfile
import time
import uuid
import zipfile
from functools import cache

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The six ASCII white-space characters that separate words.
SPACES = " \t\n\x0b\x0c\r"
#: A word, for Python's re.
WORD = r"[^\x20\x09-\x0D]+"
#: What separates words, for Java's regular expressions.
GAP = r"[\x20\x09-\x0D]+"

_written: list[tuple[SparkSession, str]] = []
_shipped: set[int] = set()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where the session names none and all runs on one machine."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    own = getattr(spark.sparkContext, "_inverse_engine_dir", None)
    if own is None:
        own = "file://" + tempfile.mkdtemp(prefix="inverse-engine-")
        spark.sparkContext._inverse_engine_dir = own
    return own


def _delete(spark: SparkSession, path: str) -> None:
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


def _delete_all() -> None:
    for spark, path in _written:
        if spark.sparkContext._jsc is not None:
            _delete(spark, path)
    _written.clear()


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write a step as Parquet to the shared folder and read it back: lineage is cut, and lost executors lose nothing.

    The files go by discard(), or when the driver's process ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    if not _written:
        atexit.register(_delete_all)
    _written.append((spark, path))
    df.write.parquet(path)
    step = spark.read.schema(df.schema).parquet(path)
    step._step_path = path
    return step


def discard(*steps: DataFrame) -> None:
    """Delete written steps that nothing reads any more."""
    gone = {step._step_path for step in steps}
    for spark, path in [w for w in _written if w[1] in gone]:
        _delete(spark, path)
        _written.remove((spark, path))


def steps() -> frozenset[str]:
    """The steps that there are, for discard_since."""
    return frozenset(path for _, path in _written)


def discard_since(before: frozenset[str], *kept: DataFrame) -> None:
    """Delete the steps that were written after `before` was taken, but for `kept`."""
    safe = before | {step._step_path for step in kept}
    for spark, path in [w for w in _written if w[1] not in safe]:
        _delete(spark, path)
        _written.remove((spark, path))


def release(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of finished steps. It does so when the driver's JVM collects what refers to them, which a
    large heap puts off for long after their results are written."""
    for pause in (1, 0):  # Python's handles and the listeners' queue hold the last step for a moment
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(pause)


def ship(spark: SparkSession) -> None:
    """Send this package's sources to the Python workers, once for each Spark context."""
    context = spark.sparkContext
    if id(context) in _shipped:
        return
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    target = os.path.join(tempfile.mkdtemp(prefix="inverse-engine-src-"), "inverse_engine_src.zip")
    with zipfile.ZipFile(target, "w") as out:
        for folder, _, names in os.walk(os.path.join(root, "inverse_engine")):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    out.write(full, os.path.relpath(full, root))
    context.addPyFile(target)
    _shipped.add(id(context))


@cache
def one_thread() -> None:
    """Matrix products of this process run on one thread: a worker has one core, and threads of many workers get in each other's way."""
    import ctypes
    import glob

    import numpy

    for path in glob.glob(os.path.join(os.path.dirname(numpy.__file__), "..", "numpy.libs", "*openblas*")):
        library = ctypes.CDLL(path)
        for name in ("scipy_openblas_set_num_threads64_", "openblas_set_num_threads64_", "scipy_openblas_set_num_threads", "openblas_set_num_threads"):
            if hasattr(library, name):
                getattr(library, name)(1)
                break


def fold(column: str, parts: int) -> Column:
    """The remainder that splits rows into folds: crc32 of the id as text, modulo parts; a null id counts as an empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")), F.lit(parts))


def labelled_sample(labels: DataFrame, target: str, most: int) -> DataFrame:
    """(doc_id, y): one label for each id, thinned by a hash of the id to about `most` rows. Null ids or labels take no part."""
    clean = labels.where(F.col("doc_id").isNotNull() & F.col(target).isNotNull()).groupBy("doc_id").agg(F.max(target).cast("int").alias("y"))
    total = labels.count()
    share = max(1, -(-total // most))
    return clean.where(F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(share)) == 0)


def labelled_by_class(labels: DataFrame, target: str, most: int) -> tuple[DataFrame, dict[int, int]]:
    """(doc_id, y) as labelled_sample, but each of the two kinds is thinned by itself, to about half of `most`: a rare kind stays whole.
    Beside it, one row in how many was taken of each kind."""
    clean = labels.where(F.col("doc_id").isNotNull() & F.col(target).isNotNull()).groupBy("doc_id").agg(F.max(target).cast("int").alias("y"))
    shares = {r["y"]: max(1, -(-r["count"] // max(1, most // 2))) for r in clean.groupBy("y").count().collect()}  # two rows
    share = F.lit(1)
    for y, k in shares.items():
        share = F.when(F.col("y") == y, k).otherwise(share)
    return clean.where(F.pmod(F.xxhash64("doc_id", F.lit(17)), share) == 0), shares
