"""Helpers shared by the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import functools
import gc
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator
from typing import TYPE_CHECKING

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

if TYPE_CHECKING:
    import pyarrow as pa

#: ASCII white space that separates words in most contracts: space, tab, LF, VT, FF, CR.
WORD = r"[^\x20\x09-\x0D]+"
#: Octets of texts that go to a Python worker at once.
BATCH_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@functools.cache
def _own_dir() -> str:
    return "file://" + tempfile.mkdtemp(prefix="shared-")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Where it is unset, a temporary one, on one machine only."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not folder:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        folder = known.get() if known.isDefined() else None
    if not folder and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return folder or _own_dir()


def materialise(df: DataFrame) -> DataFrame:
    """Cut the lineage: computed once, written to the shared folder and read again.

    A written table, unlike a checkpoint, comes back with its real size: a checkpoint keeps the estimates of
    its plan, which square in every round of a loop, and no side is then known to be small."""
    return written(df, "step")


def written(df: DataFrame, name: str) -> DataFrame:
    """As Parquet in the shared folder under a name of its own, and read again."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.written_to = path
    return out


def forget(df: DataFrame) -> None:
    """Deletes the files of a table that ``written`` made, once nothing that is still to be computed reads it."""
    jvm = df.sparkSession.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(df.written_to)
    path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def lowest(df: DataFrame, column: str, limit: int) -> DataFrame:
    """The ``limit`` rows of the smallest hashes of a column, without every task sending that many.

    Rows are first held to a share of the hash range that holds about twice as many as are asked for; where
    repeated values leave too few in it, to a larger one."""
    n = df.count()
    share = min(1.0, (2 * limit + 1000) / max(1, n))
    while share < 1:
        near = df.where(F.xxhash64(column) < F.lit(int(-(2**63) + share * 2**64)))
        if near.count() >= min(limit, n):
            return near.orderBy(F.xxhash64(column), *df.columns).limit(limit)
        share = min(1.0, 4 * share)
    return df.orderBy(F.xxhash64(column), *df.columns).limit(limit)


def release(spark: SparkSession) -> None:
    """Lets Spark drop the shuffle files of steps whose results are written, and executors hand back heap and direct buffers.

    An executor's heap, once touched, stays with it beside the Python workers; only a whole collection makes it smaller."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    executors = spark.sparkContext._jsc.sc().getExecutorMemoryStatus().size() - 1  # but the driver
    if executors > 0:
        spark.range(0, executors, 1, executors).select(F.expr("reflect('java.lang.System', 'gc')")).write.format("noop").mode("overwrite").save()


def trim() -> None:
    """Hand freed memory back to the system: Python workers live on beside the next stage's heap."""
    import pyarrow

    pyarrow.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other C libraries have no such call
        ctypes.CDLL(None).malloc_trim(0)


_kept: dict[str, Callable[[], None]] = {}


def alone(name: str, drop: Callable[[], None] | None = None) -> None:
    """Drops what other operators keep in this Python worker between tasks; ``drop`` gives up what ``name`` keeps."""
    others = [k for k in _kept if k != name]
    for other in others:
        _kept.pop(other)()
    if others:
        gc.collect()
        trim()
    if drop is not None:
        _kept[name] = drop


def over_batches(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str, name: str = "", drop: Callable[[], None] | None = None) -> DataFrame:
    """``mapInArrow`` in batches of at most BATCH_BYTES and a row, in a worker that keeps nothing of other operators.

    The session's limit is lowered and stays so: a batch is held several times over, by the JVM and by the worker."""
    spark = df.sparkSession
    if not 0 < spark._jsparkSession.sessionState().conf().arrowMaxBytesPerBatch() <= BATCH_BYTES:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))

    def in_worker(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        alone(name, drop)
        yield from run(batches)

    return df.mapInArrow(in_worker, schema)
