"""Tables written to the folder that all executors share, to cut lineage and fix an order."""

from __future__ import annotations

import atexit
import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_OWN = uuid.uuid4().hex
_FOLDERS: set[str] = set()
#: Lists of the paths made in the open `passing` blocks of each thread.
_PASSING = threading.local()


def shared_folder(spark: SparkSession) -> str:
    """The folder of `spark.checkpoint.dir`. Where a local session has none, a temporary one is set;
    a cluster without one is an error, since its executors share no local folder."""
    sc = spark.sparkContext
    folder = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not folder:
        if not sc.master.split("[")[0] == "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        folder = tempfile.mkdtemp(prefix="rowloom-")
        sc.setCheckpointDir(folder)
    return folder


def _remove(spark: SparkSession, folder: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    except Exception:  # noqa: BLE001 - the session may be gone when the process ends
        pass


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder; it goes when the Python process ends."""
    top = f"{shared_folder(spark).rstrip('/')}/rowloom-tables-{_OWN}"
    if top not in _FOLDERS:
        _FOLDERS.add(top)
        atexit.register(_remove, spark, top)
    path = f"{top}/{name}-{uuid.uuid4().hex[:12]}"
    for made in getattr(_PASSING, "open", []):
        made.append(path)
    return path


@contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """Tables that this thread writes inside go at the end of the block, with the shuffle files that
    nothing refers to any more: only what was collected inside stays."""
    made: list[str] = []
    _PASSING.open = [*getattr(_PASSING, "open", []), made]
    try:
        yield
    finally:
        _PASSING.open = _PASSING.open[:-1]
        for path in made:
            _remove(spark, path)
        spark.sparkContext._jvm.System.gc()


def stays(spark: SparkSession, name: str) -> str:
    """A path whose table outlives the innermost open `passing` block and goes with the one around it."""
    path = scratch_path(spark, name)
    _PASSING.open[-1].remove(path)
    return path


def written(df: DataFrame, name: str = "table", path: str | None = None) -> DataFrame:
    """`df` as a Parquet table in the shared folder."""
    path = path or scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
