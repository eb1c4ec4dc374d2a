"""Input and intermediate tables shared by the corpus operators."""

from __future__ import annotations

import functools
import gc
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The cluster's checkpoint folder; where none is set, a temporary one, but only if all runs on this machine."""
    conf = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if conf:
        return conf.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    if not hasattr(shared_folder, "own"):
        shared_folder.own = "file://" + tempfile.mkdtemp(prefix="hgpart-")
    return shared_folder.own


def written(df: DataFrame, label: str = "stage") -> DataFrame:
    """df as a table in the shared folder: cuts lineage, survives the loss of executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}.parquet"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def swept(df: DataFrame) -> DataFrame:
    """df, once the driver's garbage is collected: until then the shuffle files of jobs that are done stay on the executors' disks."""
    gc.collect()
    df.sparkSession.sparkContext._jvm.System.gc()
    return df


#: While long SQL expressions are read, the parser's tables are let go once they have so many states; else they stay in the
#: driver's heap for good, well over 100 MB of them.
_LEAN = {"spark.sql.parser.manageParserCaches": "true", "spark.sql.parser.parserDfaCacheFlushThreshold": "2000"}


def lean_parser(f):
    """f, whose first argument is a DataFrame, with a parser that forgets."""

    @functools.wraps(f)
    def run(df: DataFrame, *args, **opts):
        conf = df.sparkSession.conf
        before = {k: conf.get(k, None) for k in _LEAN}
        for k, v in _LEAN.items():
            conf.set(k, v)
        try:
            return f(df, *args, **opts)
        finally:
            for k, v in before.items():
                conf.unset(k) if v is None else conf.set(k, v)

    return run
