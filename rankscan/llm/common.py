"""Small helpers shared by the corpus operators."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Above so many rows a side is no longer broadcast.
BROADCAST_ROWS = 1_000_000
#: What this Python worker keeps between tasks, by the operator that it serves.
_KEPT: dict[str, object] = {}


def kept(owner: str, make: Callable[[], object]) -> object:
    """The worker's state of ``owner``, made once; a worker holds the state of one operator at a time (see ``lean``)."""
    if owner not in _KEPT:
        _KEPT[owner] = make()
    return _KEPT[owner]


def _enter(owner: str | None) -> None:
    for name in [x for x in _KEPT if x != owner]:
        del _KEPT[name]


def _leave() -> None:
    """Memory that a task has freed goes back to the system, not into the pools of a worker that lives on."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def lean(run: Callable, owner: str | None = None) -> Callable:
    """``run`` for mapInArrow in a worker that serves many operators in turn: drops what other operators kept before it
    begins, and gives freed memory back when it ends."""

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _enter(owner)
        try:
            yield from run(batches)
        finally:
            _leave()

    return task


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: ``spark.checkpoint.dir``, else the checkpoint folder that the
    session already has. Only a session on a single machine (``local[..]``, as in tests) may go without and takes a
    temporary one."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            found = held.get().rsplit("/", 1)[0]
        elif spark.sparkContext.master.startswith("local["):
            found = f"file://{tempfile.gettempdir()}/rankscan-shared"
        else:
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared folder and drop the lineage; Spark's cleaner removes the files with the plan."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def tidy(spark: SparkSession) -> None:
    """Files of shuffles and checkpoints that nothing refers to go when the driver's JVM collects garbage, which by itself
    may be long after; this asks for it before a step that needs much disk or has many tasks, whose events fill the
    driver's heap, and gives what the driver has freed back to the system."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    trim_driver(spark)


def trim_driver(spark: SparkSession) -> bool:
    """The driver's JVM gives native memory that its compiler threads have freed back to the system, beside a heap that
    many stages' events have filled. False on a JVM without that command (before 17.0.9, or not on Linux's malloc)."""
    gateway, jvm = spark.sparkContext._gateway, spark.sparkContext._jvm
    try:
        named = jvm.java.lang.Class.forName
        kinds = gateway.new_array(jvm.java.lang.Class, 4)
        for i, x in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
            kinds[i] = named(x)
        given = gateway.new_array(jvm.java.lang.Object, 4)
        given[0], given[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        given[2], given[3] = gateway.new_array(jvm.java.lang.Object, 1), gateway.new_array(jvm.java.lang.String, 1)
        given[2][0], given[3][0] = gateway.new_array(jvm.java.lang.String, 0), "[Ljava.lang.String;"
        # by the interface's method, as the server's own class is closed to reflection
        named("javax.management.MBeanServer").getMethod("invoke", kinds).invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), given)
    except Py4JError:
        return False
    return True


def lighten(spark: SparkSession) -> None:
    """The driver (see ``tidy``) and the executors' JVMs collect their garbage and give the heap's empty part back to the system, so that what earlier steps
    left there does not stand beside the memory of the Python workers to come. A task for each core, all at once; an
    executor that none of them meets keeps its heap as it is."""
    tidy(spark)
    cores = spark.sparkContext.defaultParallelism
    spark.range(0, cores, 1, cores).selectExpr("reflect('java.lang.System', 'gc') AS done").write.format("noop").mode("overwrite").save()


@contextmanager
def small_batches(spark: SparkSession, rows: int) -> Iterator[None]:
    """Arrow batches of at most ``rows`` rows for what is executed inside; rows with whole texts or sets are large."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    was = spark.conf.get(name)
    spark.conf.set(name, str(rows))
    try:
        yield
    finally:
        spark.conf.set(name, was)


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z alone. ``lower`` does just that on pure ASCII, and is far cheaper than ``translate``."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, UPPER.lower()))


def held_out(doc_id: Column) -> Column:
    """True for the fifth of the rows from which no label is learned; a null id counts as held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def maybe_broadcast(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    return F.broadcast(df) if rows <= limit else df


def without(docs: DataFrame, gone: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` less the rows that ``gone`` names by id and hash of the text (``text_key``).

    ``gone`` is cut first; it is broadcast if it has at most BROADCAST_ROWS rows of two longs, else joined by shuffle.
    """
    gone = cut(gone.select(F.col(id_col).alias("_gone_id"), F.col("text_key").alias("_gone_key")).distinct())
    few = maybe_broadcast(gone, gone.count())
    return docs.join(few, docs[id_col].eqNullSafe(few["_gone_id"]) & (F.xxhash64(docs[text_col]) == few["_gone_key"]), "left_anti")
