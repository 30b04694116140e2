"""Cut the lineage of an intermediate result with a table in the folder that all executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from functools import partial

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}
#: Rows up to which a written table may be broadcast, and the alias that marks larger ones. A row takes the driver 66 to 140 bytes.
BROADCAST_ROWS, MANY = 100_000, "many_rows"
#: MB by which the driver's heap may grow between two written tables before it is collected, and by application what was left of it then.
GARBAGE_MB, _KEPT = 100, {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that the session names for checkpoints; without one the warehouse, or, where all runs on one machine, a temporary folder."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        local = spark.sparkContext.master.startswith("local")
        base = _OWN.setdefault("temporary", tempfile.mkdtemp(prefix="refresh-")) if local else spark.conf.get("spark.sql.warehouse.dir")
    return base.rstrip("/")


def work_dir(spark: SparkSession) -> str:
    """This application's folder for intermediate tables, which goes when the driver ends."""
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        _OWN[app] = f"{shared_dir(spark)}/refresh-{app}"
        atexit.register(remove, spark, _OWN[app])
    return _OWN[app]


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder by the file system that Spark uses; nothing happens where the session is gone."""
    sc = spark.sparkContext
    if sc._jsc is not None and not sc._jsc.sc().isStopped():
        target = sc._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(sc._jsc.hadoopConfiguration()).delete(target, True)


def cut(df: DataFrame, probed: bool = False) -> DataFrame:
    """``df`` as a written table, marked where it has too many rows to be broadcast (see ``beside``). ``probed`` tables are looked up in by others and are never marked."""
    spark, path = df.sparkSession, f"{work_dir(df.sparkSession)}/{uuid.uuid4().hex}"
    tidy(spark)
    df.write.parquet(path)
    tidy(spark)
    rows = spark.read.schema(df.schema).parquet(path)
    # a row of distinct ids takes a byte of a file at least, so small files need no count
    return rows.alias(MANY) if not probed and _bytes(spark, path) > BROADCAST_ROWS and rows.count() > BROADCAST_ROWS else rows


def tidy(spark: SparkSession) -> None:
    """Collect what plans of earlier tables left in the driver's heap, and give back what was freed outside of it.

    A refresh makes gigabytes of such garbage whatever the tables' size, and a collector that waits until the heap is full
    makes the whole heap resident, for about 100 MB that are in use. Compiling what plans run through frees native memory
    that stays resident too, 200 MB after two refreshes. Where tasks share the heap it is left alone.
    """
    sc = spark.sparkContext
    if _alone(sc):
        return
    heap = sc._jvm.java.lang.Runtime.getRuntime()
    if _used(heap) - _KEPT.get(sc.applicationId, 0) > GARBAGE_MB:
        sc._jvm.java.lang.System.gc()
        trim(sc)
        _KEPT[sc.applicationId] = _used(heap)


def trim(sc) -> str:
    """Give freed native memory of the driver's JVM back to the system; what the JVM says of it, nothing where it has no such command."""
    find, array = sc._jvm.java.lang.Class.forName, partial(_array, sc)
    try:
        # by the interface: the server's own class is closed to reflection
        kinds = [find(x) for x in ("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")]
        invoke = find("javax.management.MBeanServerConnection").getMethod("invoke", array("Class", *kinds))
        commands = sc._jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        server = sc._jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer()
        return invoke.invoke(server, array("Object", commands, "systemTrimNativeHeap", array("Object"), array("String")))
    except Py4JError:
        return ""


def _array(sc, kind: str, *items):
    out = sc._gateway.new_array(getattr(sc._jvm.java.lang, kind), len(items))
    for i, x in enumerate(items):
        out[i] = x
    return out


def _alone(sc) -> bool:
    return sc._jsc.sc().isLocal()


def _used(heap) -> int:
    return (heap.totalMemory() - heap.freeMemory()) // 2**20


def _bytes(spark: SparkSession, path: str) -> int:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(target).getLength()


def beside(df: DataFrame) -> DataFrame:
    """``df`` as a join's other side: a marked table is shuffled, whatever size its files have.

    Spark goes by the bytes of the files, but what the driver builds of a compressed id is over ten times as large.
    """
    return df.hint("merge") if f"SubqueryAlias {MANY}" in df._jdf.queryExecution().analyzed().toString() else df
