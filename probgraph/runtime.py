"""Session helpers: where intermediate tables may live and how lineage is cut."""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side of a join is broadcast only up to this many rows (checked by a count of the aggregated side).
BROADCAST_ROWS = 200_000

_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """Folder that all executors see: the session's ``spark.checkpoint.dir``; a temporary one only where none is set."""
    sc = spark.sparkContext
    place = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not place:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        place = "file://" + tempfile.mkdtemp(prefix="probgraph-")
        sc.setCheckpointDir(place)
    elif not sc.getCheckpointDir():
        sc.setCheckpointDir(place)
    return place


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give the package to the Python workers, wherever they run and whatever their path is."""
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    _shipped.add(sc.applicationId)
    root = Path(__file__).resolve().parent
    name = tempfile.mkdtemp(prefix="probgraph-py-") + "/probgraph.zip"  # the driver serves it from there as long as it runs
    with zipfile.ZipFile(name, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    sc.addPyFile(name)
    atexit.register(shutil.rmtree, Path(name).parent, ignore_errors=True)


def stage(df: DataFrame) -> DataFrame:
    """Write ``df`` as a compressed Parquet table in the shared folder and read it again.

    Survives the loss of executors, keeps column pruning, and is dropped when the session ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/stage-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Have the shuffle files of frames that nothing refers to any more deleted now, not when the driver happens to collect its garbage.

    Executors collect theirs too: else a heap that earlier steps filled keeps its largest size, beside the Python workers of the next ones.
    A task for each executor does that; one that gets none, as it is busy, keeps its heap."""
    gc.collect()
    spark._jvm.System.gc()
    executors = spark.sparkContext._jsc.sc().getExecutorMemoryStatus().size() - 1  # the driver is one of them
    if executors:
        spark.range(0, executors, 1, executors).selectExpr("reflect('java.lang.System', 'gc')").collect()


def lean() -> None:
    """To be called first in a task: workers are used again and would keep what earlier tasks freed. Gives that back, and has large arrays given back as soon as they are freed."""
    import pyarrow as pa

    try:
        libc = ctypes.CDLL(None)
        for option, value in ((-3, 1 << 20), (-1, 1 << 20), (-8, 2)):  # mapped on their own from 1 MB on, the heap's end given back from 1 MB on, two heaps
            libc.mallopt(option, value)
        libc.malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass
    pa.default_memory_pool().release_unused()


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint, for small tables inside loops."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """Mark a side for broadcast if it is measured to be small; else leave the choice to the optimizer.

    ``df`` should already be cut, so that the count costs little."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def fresh(df: DataFrame, name: str) -> str:
    """A column name that ``df`` does not have."""
    have = {c.lower() for c in df.columns}
    while name.lower() in have:
        name = "_" + name
    return name


@atexit.register
def _drop() -> None:
    for spark, path in _written:
        try:
            p = spark._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # noqa: BLE001 - the session has ended already
            return
