"""What every job needs from the session it is given: shared storage and shipped code.

Nothing here changes a setting that is fixed at start; the session is used as given.
"""

from __future__ import annotations

import ctypes
import gc
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()

#: Bytes of an Arrow batch: they bound what a task holds outside the heap when texts or sets are long.
BATCH_BYTES = 2 << 20


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application, as a zip of its sources.

    Also turns off, for this session, the planner's reuse of a partitioning that both
    sides of a union share: adaptive execution may coalesce the sides differently, and an
    aggregate or window above then sees the rows of one key in two partitions (seen in
    Spark 4.1.2; ``tests/test_queries.py`` has queries that come out wrong with it on).
    """
    spark.conf.set("spark.sql.unionOutputPartitioning", "false")
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    here = os.path.dirname(os.path.abspath(__file__))
    if os.path.isdir(here):  # else it already runs from a shipped zip
        path = os.path.join(tempfile.mkdtemp(prefix="ship"), f"{os.path.basename(here)}.zip")
        with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
            for top, _, names in os.walk(here):
                for n in sorted(names):
                    if n.endswith(".py"):
                        full = os.path.join(top, n)
                        z.write(full, os.path.relpath(full, os.path.dirname(here)))
        spark.sparkContext.addPyFile(path)
    _SHIPPED.add(app)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` if set.

    Without it, a local session uses ``/tmp/checkpoints`` and a cluster the warehouse.
    """
    at = spark.conf.get("spark.checkpoint.dir", None)
    if at:
        return at.rstrip("/")
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        return "file:///tmp/checkpoints"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_lineage"


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str = "step") -> DataFrame:
    """Write ``df`` as Parquet to shared storage and read it back: cuts lineage, survives executors."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Let go what finished jobs have left: shuffle files, and memory that the driver holds but does not use.

    Spark deletes the shuffle files once their plans are collected on the driver.
    """
    give_back()
    spark.sparkContext._jvm.System.gc()
    trim_jvm(spark)


def trim_jvm(spark: SparkSession) -> str | None:
    """Return memory outside the heap that the driver's JVM has freed, such as its compiler's, to the system.

    What the JVM says about it; None from a JVM that has no such command, which is left as it is.
    """
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway

    def array(kind, items: list):
        a = gateway.new_array(kind, len(items))
        for i, x in enumerate(items):
            if x is not None:
                a[i] = x
        return a

    try:  # through the public interface: the server's own class is closed to reflection
        named = jvm.java.lang.Class.forName
        takes = [named(k) for k in ("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")]
        invoke = named("javax.management.MBeanServer").getMethod("invoke", array(jvm.java.lang.Class, takes))
        commands = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        beans = jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer()
        return invoke.invoke(beans, array(jvm.java.lang.Object, [commands, "systemTrimNativeHeap", None, None]))
    except Py4JError:
        return None


def bound_batches(spark: SparkSession, most: int = BATCH_BYTES) -> None:
    """Arrow batches of this session hold ``most`` bytes or a row; a lower bound stays.

    A task holds a batch several times, in the JVM outside its heap and in the Python worker.
    The bound is read when a plan runs, so it stays set for frames that are returned unrun.
    """
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.sparkContext._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(key))
    if not 0 < now <= most:
        spark.conf.set(key, str(most))


def give_back() -> None:
    """Return memory that this process has freed to the system; allocators keep it otherwise."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # only glibc has it
        pass


Batches = Iterator[pa.RecordBatch]


def sparing(run: Callable[[Batches], Batches]) -> Callable[[Batches], Batches]:
    """``run`` for mapInArrow; its worker, which waits for the next task, gives its memory back at the end."""

    def task(batches: Batches) -> Batches:
        try:
            yield from run(batches)
        finally:
            give_back()

    return task


def path_exists(spark: SparkSession, path: str) -> bool:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(at)


def drop_path(spark: SparkSession, df_or_path: DataFrame | str) -> None:
    """Delete a materialized table that nothing reads any more."""
    jvm = spark.sparkContext._jvm
    paths = [df_or_path] if isinstance(df_or_path, str) else {f.rsplit("/", 1)[0] for f in df_or_path.inputFiles()}
    root = shared_dir(spark).removeprefix("file://").rstrip("/")
    for p in paths:
        if root in p:  # only ever below the shared folder
            at = jvm.org.apache.hadoop.fs.Path(p)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
