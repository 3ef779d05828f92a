"""Tables in the folder that the driver and all executors share.

``cut`` writes a frame there and reads it back: lineage ends, the rows are computed once, and a lost executor
costs a re-read only.  The folder comes from the session (``spark.checkpoint.dir``, else the context's checkpoint
directory); a temporary one is set only where neither exists and all tasks run in this process, as in local tests.

Shuffle files of an execution stay until the driver's garbage collector meets its plan, which in a quiet driver is
never; ``cut`` asks for a collection at most every ``SWEEP_S`` seconds.  ``release`` deletes tables that nothing reads any more.
"""

from __future__ import annotations

import atexit
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession

_made: list[tuple[SparkSession, str]] = []
SWEEP_S = 4.0
_swept = [0.0]


def shared_dir(spark: SparkSession) -> str:
    """The shared folder of this session."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = held.get() if held.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = tempfile.mkdtemp(prefix="evenpart-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Write ``df`` to the shared folder as Parquet and return it as a scan of what was written."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/evenpart-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _made.append((spark, path))
    if time.monotonic() - _swept[0] >= SWEEP_S:
        spark.sparkContext._jvm.java.lang.System.gc()
        _swept[0] = time.monotonic()
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def release(*frames: DataFrame) -> None:
    """Delete the tables behind frames that ``cut`` returned; other frames are left alone.  Nothing may read them later."""
    paths = {df.__dict__.get("_scratch") for df in frames}
    for held in [m for m in _made if m[1] in paths]:
        _delete(*held)
        _made.remove(held)


def _delete(spark: SparkSession, path: str) -> None:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _clean() -> None:
    """Remove what ``cut`` wrote, if the session still runs when the program ends."""
    for spark, path in _made:
        try:
            _delete(spark, path)
        except Exception:  # noqa: BLE001  the JVM may be gone already
            return
