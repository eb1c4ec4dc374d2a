"""Written intermediate tables: they cut lineage and survive lost executors."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Written tables of at most so many rows are broadcast; the rows of smaller files are not counted for that.
SMALL_ROWS, SMALL_BYTES = 1_500_000, 1 << 20
#: Garbage is collected after so many bytes of tables were let go.
SWEPT_BYTES = 32 << 20

_own: dict[str, str] = {}


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir as the cluster sets it; where it is unset, a temporary folder, but only if all runs on this machine."""
    conf = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if conf:
        return conf.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    if "folder" not in _own:
        _own["folder"] = "file://" + tempfile.mkdtemp(prefix="hgpart-")
    return _own["folder"]


def materialize(df: DataFrame, label: str = "frame") -> DataFrame:
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}.parquet"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_at = path
    return out


def _file(df: DataFrame) -> tuple:
    """The written table's file system, its path, and its bytes."""
    context = df.sparkSession.sparkContext
    path = context._jvm.org.apache.hadoop.fs.Path(df.written_at)
    fs = path.getFileSystem(context._jsc.hadoopConfiguration())
    return fs, path, fs.getContentSummary(path).getLength()


def small(df: DataFrame) -> DataFrame:
    """df, to be broadcast if it is a written table of few rows; else it is shuffled as any other."""
    few = getattr(df, "written_at", None) and (_file(df)[2] <= SMALL_BYTES or df.count() <= SMALL_ROWS)
    return F.broadcast(df) if few else df


def forget(*frames: DataFrame) -> None:
    """Deletes tables that materialize wrote and that nothing will read again; after large ones, lets go the shuffle files of jobs that are done."""
    gone = 0
    for df in frames:
        fs, path, size = _file(df)
        fs.delete(path, True)
        gone += size
    if gone >= SWEPT_BYTES:
        sweep(frames[0].sparkSession)


def sweep(spark: SparkSession) -> None:
    """Collects the driver's garbage: until then the shuffle files of jobs that are done stay on the executors' disks."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
