"""Helpers that the corpus operators share: tables, shared folders, text rules."""

from __future__ import annotations

import atexit
import ctypes
import functools
import gc
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes that end a word: space and the five ASCII controls from tab to carriage return.
WORD_SPACE = b" \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share, from ``spark.checkpoint.dir``.

    A local session without that setting gets a folder of its own, removed at exit;
    any other session without it is refused, as a machine-local folder would not be seen
    by all executors.
    """
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if root:
        if not spark.sparkContext.getCheckpointDir():
            spark.sparkContext.setCheckpointDir(root)
        return root.rstrip("/")
    held = spark.sparkContext.getCheckpointDir()
    if held:
        return held.rstrip("/")
    if not spark.sparkContext.master.split("[")[0] == "local":
        raise ValueError("spark.checkpoint.dir has to name a folder that all executors share")
    made = tempfile.mkdtemp(prefix="setdiff-shared-")
    atexit.register(shutil.rmtree, made, ignore_errors=True)
    spark.sparkContext.setCheckpointDir(f"file://{made}")
    return spark.sparkContext.getCheckpointDir().rstrip("/")


def scratch(spark: SparkSession, tag: str) -> str:
    """A path under the shared folder that nothing else uses."""
    return f"{shared_root(spark)}/{tag}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def keep(df: DataFrame, tag: str) -> DataFrame:
    """Writes ``df`` to the shared folder and reads it back: lineage ends, losses of executors don't matter."""
    path = scratch(df.sparkSession, tag)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.kept_at = path
    return out


def discard(*kept: DataFrame) -> None:
    """Removes tables that ``keep`` wrote, once all that is worked out from them is written itself."""
    for df in kept:
        remove(df.sparkSession, df.kept_at)


def stowed(docs: DataFrame) -> DataFrame:
    """(_row): every row as one struct, so that no column of its own can clash with those an operator adds; ``select("_row.*")`` brings them back."""
    return docs.select(F.struct(*[F.col("`" + c.replace("`", "``") + "`") for c in docs.columns]).alias("_row"))


def small(batches: Iterable, rows: int = 512) -> Iterator:
    """The batches in slices of a few rows, so that a Python worker holds few texts at a time."""
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


def give_back() -> None:
    """Returns memory that this process no longer uses to the system: garbage, Arrow's pool, the C heap."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def lean(run: Callable[[Iterator], Iterator], *forget: Callable[[], object]) -> Callable[[Iterator], Iterator]:
    """``run`` as a task that leaves nothing behind in the worker, which Spark uses again for the tasks of other operators.

    ``forget`` drop what the module keeps for the process; they run when the task ends, fails or is given up.
    """

    @functools.wraps(run)
    def task(batches: Iterator) -> Iterator:
        try:
            yield from run(batches)
        finally:
            for f in forget:
                f()
            give_back()

    return task


def id_crc_mod(column: str, n: int) -> Column:
    """crc32 of the id as decimal text, modulo ``n``; null for a null id."""
    return F.crc32(F.col(column).cast("string")) % n


def bounded_broadcast(df: DataFrame, bound: int) -> DataFrame:
    """Marks ``df`` for broadcast only after its row count is seen to be within ``bound``."""
    return F.broadcast(df) if df.limit(bound + 1).count() <= bound else df
