"""Written intermediate results: lineage ends at a Parquet table in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, SparkSession

_written: list[tuple[weakref.ref, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or in a local session without one a temporary folder."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not getattr(spark, "_floorwalk_folder", None):
        spark._floorwalk_folder = tempfile.mkdtemp(prefix="floorwalk-")
    return "file://" + spark._floorwalk_folder


def materialize(frame: DataFrame) -> DataFrame:
    spark = frame.sparkSession
    path = f"{shared_folder(spark)}/floorwalk-{uuid.uuid4().hex}"
    frame.write.parquet(path)
    _written.append((weakref.ref(spark), path))
    out = spark.read.schema(frame.schema).parquet(path)
    out._floorwalk_path = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def discard(frame: DataFrame) -> None:
    """Deletes a written table that nothing will read again, such as the round before in a loop."""
    path = getattr(frame, "_floorwalk_path", None)
    if path:
        _delete(frame.sparkSession, path)
        _written[:] = [w for w in _written if w[1] != path]


def _remove() -> None:
    for ref, path in _written:
        try:
            _delete(ref(), path)
        except Exception:  # noqa: BLE001  the session has ended
            return


atexit.register(_remove)
