"""Versioned metadata tables, compressed sinks, and a source that restores text as it is read."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class MetadataStore:
    """Dictionaries, grids, unigram tables and metrics by name and version, as Parquet."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def put(self, name: str, version: int, df: DataFrame) -> None:
        df.write.mode("overwrite").parquet(f"{self.path}/{name}/version={int(version)}")

    def latest(self, name: str, below: int | None = None) -> int | None:
        """The newest version that has files (below ``below`` if given), in any file system; None without one."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        fs = path.getFileSystem(self.spark.sparkContext._jsc.sc().hadoopConfiguration())
        found = []
        for folder in fs.listStatus(path) if fs.exists(path) else ():
            kind, _, version = folder.getPath().getName().partition("=")
            if kind == "version" and (below is None or int(version) < below) and any(f.getPath().getName()[0] not in "_." for f in fs.listStatus(folder.getPath())):
                found.append(int(version))
        return max(found, default=None)

    def get(self, name: str, version: int | None = None) -> DataFrame:
        """A version, the newest by default; only its own files are read."""
        version = self.latest(name) if version is None else version
        if version is None:
            raise ValueError(f"no version of {name} in {self.path}")
        return self.spark.read.parquet(f"{self.path}/{name}/version={int(version)}")


def write_compressed(df: DataFrame, path: str, dictionary: DataFrame, by: str | None = None) -> None:
    """Abbreviated texts, partitioned by a column if given, and the dictionary beside them."""
    w = df.write.mode("overwrite")
    (w.partitionBy(by) if by else w).parquet(f"{path}/texts")
    dictionary.write.mode("overwrite").parquet(f"{path}/dictionary")


def read_restored(spark: SparkSession, path: str) -> DataFrame:
    from ctxpress.operators.abbrev import as_mapping, restore

    return restore(spark.read.parquet(f"{path}/texts"), as_mapping(spark.read.parquet(f"{path}/dictionary")), "short", "text")


class RestoringSource(DataSource):
    """format("ctxpress"): files of abbreviated text (doc_id, short) in any folder that pyarrow can open (a path, or a URI as of hdfs or s3), restored on read."""

    @classmethod
    def name(cls) -> str:
        return "ctxpress"

    def schema(self) -> str:
        return "doc_id long, text string"

    def reader(self, schema) -> DataSourceReader:
        return _RestoringReader(self.options["path"])


class _RestoringReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def opened(self):
        """The file system and the folder in it."""
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.path) if ":" in self.path.split("/")[0] else (fs.LocalFileSystem(), self.path)

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        files, folder = self.opened()
        found = files.get_file_info(fs.FileSelector(f"{folder}/texts", recursive=True))
        return [InputPartition(p) for p in sorted(f.path for f in found if f.is_file and f.path.endswith(".parquet") and f.base_name[0] not in "_.")]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        import pyarrow.parquet as pq

        from ctxpress.operators.abbrev import Codec

        files, folder = self.opened()
        d = pq.read_table(f"{folder}/dictionary", filesystem=files).to_pydict()
        decode = Codec(dict(zip(d["gram"], d["placeholder"]))).decoder()
        for b in pq.ParquetFile(partition.value, filesystem=files).iter_batches(columns=["doc_id", "short"]):
            for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                yield i, decode(t)
