"""Session helpers: a local builder, the shared scratch folder and shipping the package to workers."""

from __future__ import annotations

import atexit
import gc
import hashlib
import os
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

PACKAGE = Path(__file__).resolve().parent
HEAP_SHARE = 0.5  # of the driver's heap, beyond which garbage is collected after a table is written


def local_session(cores: int = 8, shuffle_partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A session for tests and the bench; a cluster brings its own."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("tangentia")
        .config("spark.sql.shuffle.partitions", shuffle_partitions)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def ship_package(spark: SparkSession) -> None:
    """Make this package importable in Python workers, wherever they run (once per context)."""
    sc = spark.sparkContext
    if getattr(sc, "_tangentia_shipped", False):
        return
    sources = sorted(PACKAGE.rglob("*.py"))
    digest = hashlib.sha1(b"".join(p.read_bytes() for p in sources)).hexdigest()[:12]
    folder = tempfile.mkdtemp(prefix="tangentia")
    path = os.path.join(folder, f"tangentia_{digest}.zip")
    with zipfile.ZipFile(path, "w") as z:
        for p in sources:
            z.write(p, p.relative_to(PACKAGE.parent))
    sc.addPyFile(path)
    sc._tangentia_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Only a local session, whose executors are this machine, gets one of our own where it is unset."""
    sc = spark.sparkContext
    folder = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not folder:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="tangentia-checkpoint")
        atexit.register(shutil.rmtree, folder, True)
        sc.setCheckpointDir(folder)
    return folder.rstrip("/")


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/tangentia/{name}-{uuid.uuid4().hex}"


def broadcast_if_small(df: DataFrame, rows: int = 100_000) -> DataFrame:
    """``df`` with a broadcast hint if it is counted to have at most ``rows`` rows, else as it is: joins then shuffle."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def table_frame(spark: SparkSession, frame, schema: str) -> DataFrame:
    """A pandas frame, with numpy arrays in cells, as a DataFrame (by Arrow, whatever the session's settings)."""
    import pyarrow as pa

    return spark.createDataFrame(pa.Table.from_pandas(frame, preserve_index=False), schema)


def free_driver(spark: SparkSession, above: float = 0.0) -> None:
    """Collect the driver's garbage, Python's first, whose references hold the JVM's: what earlier plans left goes, broadcasts and shuffle files on executors too, and the heap shrinks.

    Not where the heap has at most the share ``above`` of what it may have. Freed native memory goes back to the system in any case.
    """
    jvm = spark.sparkContext._jvm
    runtime = jvm.java.lang.Runtime.getRuntime()
    if runtime.totalMemory() > above * runtime.maxMemory():
        gc.collect()
        jvm.System.gc()
    trim_native(spark)


def trim_native(spark: SparkSession) -> bool:
    """Return the memory that the driver's JVM has freed, but its C library still holds, to the system; False where the JVM has no such command.

    Compiled plans, collections and buffers are made by many threads, each with an arena of its own, of which the library gives little back unasked.
    """
    sc = spark.sparkContext
    jvm = sc._jvm

    def array(kind, *items):
        out = sc._gateway.new_array(kind, len(items))
        for i, x in enumerate(items):
            out[i] = x
        return out

    name = lambda s: jvm.java.lang.Class.forName(s)
    texts = array(jvm.java.lang.String)
    try:  # the server's own class is not open to calls, its interface is
        types = array(jvm.java.lang.Class, name("javax.management.ObjectName"), name("java.lang.String"), name("[Ljava.lang.Object;"), name("[Ljava.lang.String;"))
        call = name("javax.management.MBeanServer").getMethod("invoke", types)
        commands = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        call.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), array(jvm.java.lang.Object, commands, "systemTrimNativeHeap", array(jvm.java.lang.Object), texts))
    except Py4JError:
        return False
    return True


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write a table to the shared folder and read it back: lineage is cut, a lost executor costs no recompute, and the driver's memory is freed where much of it is taken."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    free_driver(spark, HEAP_SHARE)
    return spark.read.schema(df.schema).parquet(path)
