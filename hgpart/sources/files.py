"""Hypergraph files: plain edge lines, columnar and row formats, and a data source of packed sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

FORMATS = ("parquet", "orc", "json", "csv")


def write_pins(pins: DataFrame, path: str, kind: str = "parquet") -> None:
    writer = pins.write.mode("overwrite")
    (writer.option("header", True) if kind == "csv" else writer).format(kind).save(path)


def read_pins(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    reader = spark.read.schema("e bigint, n bigint, is_src boolean, is_dst boolean")
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


def write_edge_lines(pins: DataFrame, path: str) -> None:
    """One hyperedge a line: its id, its pins in order, a source marked by a trailing s, a destination by d, both by sd."""
    mark = F.concat(F.col("n").cast("string"), F.when(F.col("is_src"), "s").otherwise(""), F.when(F.col("is_dst"), "d").otherwise(""))
    lines = pins.groupBy("e").agg(F.array_sort(F.collect_list(F.struct("n", mark.alias("t")))).alias("p"))
    lines.select(F.concat(F.col("e").cast("string"), F.lit(": "), F.array_join(F.transform("p", lambda x: x["t"]), " "))).write.mode("overwrite").text(path)


def read_edge_lines(spark: SparkSession, path: str) -> DataFrame:
    cut = F.split("value", ": ")
    rows = spark.read.text(path).select(cut[0].cast("bigint").alias("e"), F.explode(F.split(cut[1], " ")).alias("t"))
    return rows.select("e", F.regexp_extract("t", r"^\d+", 0).cast("bigint").alias("n"), F.col("t").contains("s").alias("is_src"), F.col("t").contains("d").alias("is_dst"))


def write_bucketed(pins: DataFrame, table: str, path: str, buckets: int = 8) -> None:
    """pins as an external table bucketed and sorted by hyperedge: joins and aggregates on e need no shuffle."""
    pins.write.mode("overwrite").bucketBy(buckets, "e").sortBy("e").option("path", path).saveAsTable(table)


def write_levels(pins_by_level: DataFrame, path: str) -> None:
    pins_by_level.write.mode("overwrite").partitionBy("level").parquet(path)


def write_packed(sets: DataFrame, path: str) -> None:
    """sets (id, items) as columnar files that format("hgpart") reads."""
    sets.select("id", "items").write.mode("overwrite").parquet(path)


class PackedPartition(InputPartition):
    def __init__(self, file: str):
        self.file = file


class PackedReader(DataSourceReader):
    """One task a file; a file's row groups come one after the other as Arrow batches."""

    def __init__(self, options):
        if not options.get("path"):
            raise ValueError('format("hgpart") needs a path')
        self.path = options["path"]

    def _open(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith("file:") else (fs.LocalFileSystem(), self.path)

    def partitions(self):
        from pyarrow import fs

        system, at = self._open()
        found = system.get_file_info(fs.FileSelector(at, recursive=True))
        return [PackedPartition(x.path) for x in found if x.is_file and x.extension == "parquet" and not x.base_name.startswith((".", "_"))]

    def read(self, partition):
        import pyarrow as pa
        import pyarrow.parquet as pq

        kind = pa.schema([("id", pa.int64()), ("items", pa.list_(pa.int64()))])
        with self._open()[0].open_input_file(partition.file) as raw:
            file = pq.ParquetFile(raw)
            for group in range(file.num_row_groups):
                yield from file.read_row_group(group, columns=["id", "items"]).cast(kind).to_batches()


class PackedSource(DataSource):
    """format("hgpart"): the packed sets (id, items) that write_packed left under `path`."""

    @classmethod
    def name(cls):
        return "hgpart"

    def schema(self):
        return "id bigint, items array<bigint>"

    def reader(self, schema):
        return PackedReader(self.options)
