"""Parquet tables in, shared intermediate tables out.

Intermediate results are written to the folder named by ``spark.checkpoint.dir``, which every executor of a cluster can
read; nothing here relies on a disk of one machine.
"""

from __future__ import annotations

import atexit
import os
import tempfile
import threading
import uuid
import weakref
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

TABLES = (
    "region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events",
    "documents", "embeddings", "pages", "benchmark", "labels", "conversations",
)

_REPO = Path(__file__).resolve().parents[2]
_folders: dict[str, str] = {}
_shipped: set[str] = set()
_stored: dict[int, str] = {}
_settled: dict[str, int] = {}

#: Seconds between looks at the driver's heap while a table is written.
WATCH_S = 0.5


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """One table of ``sf_dir``; only ``columns`` are read where they are given."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def register_views(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    """The tables as temporary views, for SQL users."""
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def shared_dir(spark: SparkSession) -> str:
    """A folder of this application under ``spark.checkpoint.dir``; where that is unset (tests), under a temporary one."""
    app = spark.sparkContext.applicationId
    if app not in _folders:
        root = spark.conf.get("spark.checkpoint.dir", None)
        if not root:
            current = spark.sparkContext._jsc.sc().getCheckpointDir()
            if not current.isDefined() and not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("spark.checkpoint.dir is not set: on a cluster it must name a folder that every executor reaches")
            root = current.get() if current.isDefined() else f"file://{tempfile.mkdtemp(prefix='taskmesh-')}"
        _folders[app] = f"{root.rstrip('/')}/taskmesh-{uuid.uuid4().hex[:12]}"
        atexit.register(_remove, spark, _folders[app])
    return _folders[app]


def _remove(spark: SparkSession, folder: str) -> None:
    try:
        path = spark._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    except Exception:  # noqa: BLE001  the session has ended already; its folder is the cluster's to clean
        return


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Writes ``df`` once as a table in the shared folder and reads it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:8]}"
    with watched(spark):
        df.write.option("compression", "zstd").parquet(path)
    relieve(spark)
    out = spark.read.schema(df.schema).parquet(path)
    _stored[id(out)] = path
    weakref.finalize(out, _stored.pop, id(out), None)
    return out


def relieve(spark: SparkSession, share: float = 0.25) -> bool:
    """Collects the driver's garbage where more than ``share`` of its heap is in use or the heap is swollen, most of it plans and
    task metrics that are done with; the heap then shrinks and gives memory back, which it does not before it is nearly full.
    Whether it did. Free native memory goes back in any case, which takes some milliseconds."""
    heap = spark._jvm.java.lang.Runtime.getRuntime()
    full = heap.totalMemory() - heap.freeMemory() > share * heap.maxMemory() or swollen(spark, max(share, 0.5))
    if full:
        collect(spark)
    trim(spark)
    return full


def swollen(spark: SparkSession, share: float = 0.5) -> bool:
    """Whether the heap holds more than ``share`` of its most from the system, in use or not, and a quarter more than after the
    last collection, so that a heap full of live data is not collected over and over."""
    heap = spark._jvm.java.lang.Runtime.getRuntime()
    return heap.totalMemory() > max(share * heap.maxMemory(), 1.25 * _settled.get(spark.sparkContext.applicationId, 0))


def collect(spark: SparkSession) -> None:
    """Collects the driver's garbage and notes what the heap keeps."""
    spark._jvm.java.lang.System.gc()
    _settled[spark.sparkContext.applicationId] = spark._jvm.java.lang.Runtime.getRuntime().totalMemory()


def trim(spark: SparkSession) -> None:
    """The JVM's own command that hands free native memory, mostly its compiler's, to the system. It is called by way of the public
    interface, since the gateway looks at the server's own class, which is hidden. JVMs without the command keep that memory."""
    try:
        java, array = spark._jvm.java.lang, spark.sparkContext._gateway.new_array
        kinds, given = array(java.Class, 4), array(java.Object, 4)
        for at, kind in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
            kinds[at] = java.Class.forName(kind)
        given[0] = spark._jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        given[1], given[2], given[3] = "systemTrimNativeHeap", array(java.Object, 0), array(java.String, 0)
        invoke = java.Class.forName("javax.management.MBeanServerConnection").getMethod("invoke", kinds)
        invoke.invoke(java.management.ManagementFactory.getPlatformMBeanServer(), given)
    except Exception:  # noqa: BLE001
        return


@contextmanager
def watched(spark: SparkSession) -> Iterator[None]:
    """Meanwhile the driver's heap is looked at again and again: one job of many tasks can fill it before its table is stored."""
    done = threading.Event()

    def look() -> None:
        while not done.wait(WATCH_S):
            try:
                if swollen(spark):
                    collect(spark)
                    trim(spark)
            except Exception:  # noqa: BLE001  the session ends; the job itself will say so
                return

    thread = threading.Thread(target=look, name="taskmesh-heap", daemon=True)
    thread.start()
    try:
        yield
    finally:
        done.set()
        thread.join()


def discard(df: DataFrame) -> None:
    """Removes the files of a table that ``materialise`` stored, when nothing reads it any more."""
    path = _stored.pop(id(df), None)
    if path:
        _remove(df.sparkSession, path)


def ship_package(spark: SparkSession) -> None:
    """Makes this package importable in Python workers that do not have the repository on their path."""
    app = spark.sparkContext.applicationId
    on_path = [os.path.realpath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    at_hand = str(_REPO) in on_path or (spark.sparkContext.master.startswith("local[") and os.getcwd() == str(_REPO))
    if app in _shipped or at_hand:
        return
    path = Path(tempfile.mkdtemp(prefix="taskmesh-")) / "taskmesh_code.zip"
    with zipfile.ZipFile(path, "w") as out:
        for file in sorted((_REPO / "taskmesh").rglob("*.py")):
            out.write(file, file.relative_to(_REPO))
    spark.sparkContext.addPyFile(str(path))
    _shipped.add(app)
