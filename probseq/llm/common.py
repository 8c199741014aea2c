"""Helpers shared by the training-data operators: settled tables, Arrow text views, bounded caches."""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

EOS_ORDER = (1 << 63) - 1  # stands for a null id: it sorts after every real one


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share, as the session names it; a temporary one only where none is named."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        named = found.get() if found.isDefined() else None
    if not named:
        named = "file://" + (local := tempfile.mkdtemp(prefix="probseq-"))
        atexit.register(shutil.rmtree, local, True)
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def settle(df: DataFrame, tag: str, last: bool = False) -> DataFrame:
    """Writes `df` to the shared folder and reads it back, which cuts its lineage and survives lost executors.

    `last`: a large step ends here, and what it held is swept.
    """
    spark, schema = df.sparkSession, df.schema
    path = f"{shared_folder(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    del df  # its plan holds the shuffle files that are swept
    if last:
        sweep(spark)
    out = spark.read.schema(schema).parquet(path)
    out._settled = path
    return out


def discard(*tables: DataFrame) -> None:
    """Deletes settled tables that nothing reads any more; the caller has settled all that came of them."""
    for df in tables:
        at = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df._settled)
        at.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


def trim(collect: bool = True) -> None:
    """Gives freed memory of this Python process back to the system."""
    if collect:
        gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not glibc
        pass


def sweep(spark: SparkSession) -> None:
    """Frees what steps that are written need no more.

    Spark drops shuffle files and broadcasts of a finished plan only when the driver's JVM has collected the plan. A driver
    that allocates little collects rarely, so between two large steps it is asked to; what holds a plan goes in the first
    collection, the plan in the second. Its many threads also leave freed native memory behind, which a diagnostic command
    of the JVM gives back where there is one.
    """
    trim()
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    jvm.System.gc()
    try:
        named = jvm.java.lang.Class.forName
        kinds = gateway.new_array(jvm.java.lang.Class, 4)
        for k, kind in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
            kinds[k] = named(kind)
        given = gateway.new_array(jvm.java.lang.Object, 4)
        given[0], given[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        named("javax.management.MBeanServer").getMethod("invoke", kinds).invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), given)
    except Py4JError:  # another JVM
        pass
    jvm.System.gc()


def in_one_task(rows: DataFrame, make: Callable[[Iterator[pa.RecordBatch]], bytes | None]) -> bytes | None:
    """What `make` returns for all `rows` together, made in one task: for samples of bounded size only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        if (out := make(batches)) is not None:
            yield pa.RecordBatch.from_arrays([pa.array([out], pa.binary())], ["made"])
        trim()

    got = rows.repartition(1).mapInArrow(run, "made binary").collect()
    return bytes(got[0]["made"]) if got else None


def by_sort(a: DataFrame, b: DataFrame, on, how: str = "inner") -> DataFrame:
    """A join of two sides that both grow with the input: sorted and merged, never sent through the driver."""
    return a.join(b.hint("merge"), on, how)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def order_key(col: str = "doc_id") -> Column:
    """An id that is never null: null ids come after all others."""
    return F.coalesce(F.col(col), F.lit(EOS_ORDER))


def utf8(batch: pa.RecordBatch, name: str) -> tuple[np.ndarray, np.ndarray]:
    """(bytes of all values joined, n + 1 offsets) of a string or binary column without copying; null is empty."""
    a = batch.column(batch.schema.get_field_index(name))
    if isinstance(a, pa.ChunkedArray):
        a = a.combine_chunks()
    wide = pa.types.is_large_string(a.type) or pa.types.is_large_binary(a.type)
    n = len(a)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = a.buffers()
    off = np.frombuffer(off, np.int64 if wide else np.int32)[a.offset : a.offset + n + 1].astype(np.int64)
    body = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return body, off - off[0]


def slices(batch: pa.RecordBatch, column: str, most: int) -> Iterator[pa.RecordBatch]:
    """Consecutive parts of a batch with about `most` bytes in `column`; a longer value makes a part by itself."""
    _, off = utf8(batch, column)
    at, n = 0, batch.num_rows
    while at < n:
        to = int(np.searchsorted(off, off[at] + most, side="right")) - 1
        to = min(n, max(to, at + 1))
        yield batch.slice(at, to - at)
        at = to


_resident: dict[str, object] = {}


def resident(owner: str, make: Callable[[], object]) -> object:
    """An object that a worker keeps from task to task, as long as no task of another operator comes between."""
    release(owner)
    if owner not in _resident:
        _resident[owner] = make()
    return _resident[owner]


def release(but: str | None = None) -> None:
    """Lets go what a worker keeps for other operators, and gives the memory back."""
    others = [k for k in _resident if k != but]
    for k in others:
        del _resident[k]
    trim(bool(others))


def map_parts(df: DataFrame, column: str, fn: Callable[[pa.RecordBatch], pa.RecordBatch | None], schema: str, most: int = 4 << 20, owner: str | None = None) -> DataFrame:
    """mapInArrow over parts of bounded size, so that Python memory does not follow the row count of a batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release(owner)
        for batch in batches:
            for part in slices(batch, column, most):
                if (out := fn(part)) is not None and out.num_rows:
                    yield out

    return df.mapInArrow(run, schema)


def list_array(values: np.ndarray, lengths: np.ndarray, kind: pa.DataType) -> pa.ListArray:
    off = np.zeros(len(lengths) + 1, np.int64)
    np.cumsum(lengths, out=off[1:])
    return pa.ListArray.from_arrays(pa.array(off.astype(np.int32)), pa.array(values, kind))


def gather(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Positions of the concatenation of ranges [start, start + length)."""
    total = int(lengths.sum())
    before = np.cumsum(lengths) - lengths
    return np.repeat(starts - before, lengths) + np.arange(total)


def numbered(df: DataFrame, group: list[str], spread: Column, order: list[Column], out: str, parts: int | None = None) -> DataFrame:
    """Gapless numbers from 0 within `group`, without a task that holds a whole group.

    Rows are dealt into `parts` sub-groups by `spread`; only (group, sub-group) counts meet, and their running
    sums shift the numbers that each sub-group makes by itself.
    """
    from pyspark.sql import Window

    parts = parts or partitions(df.sparkSession)
    d = df.withColumn("_sub", F.pmod(F.xxhash64(spread), F.lit(parts)).cast("int"))
    counts = d.groupBy(*group, "_sub").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(*group).orderBy("_sub").rowsBetween(Window.unboundedPreceding, -1)
    shifts = counts.select(*group, "_sub", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_shift"))
    own = Window.partitionBy(*group, "_sub").orderBy(*order)
    ranked = d.withColumn("_own", F.row_number().over(own) - 1)
    return ranked.join(shifts, [*group, "_sub"], "left").withColumn(out, (F.col("_own") + F.col("_shift")).cast("long")).drop("_sub", "_own", "_shift")
