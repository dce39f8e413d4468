"""A saved filter as a data source of its own: spark.read.format("regionfilter").load(path).

A file of words is a task; the option ``region`` reads the folder of one region only. Files are read by Arrow, from any
store that it knows by the path's scheme.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..schemas import WORDS


class WordsFile(InputPartition):
    """One Parquet file of a region's words."""

    def __init__(self, path: str, region: int):
        super().__init__((path, region))
        self.path, self.region = path, region


def _files(at: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(at if "://" in at else f"file://{at.removeprefix('file:')}")


class WordsReader(DataSourceReader):
    def __init__(self, options: dict):
        self.at = f"{options['path'].rstrip('/')}/words"
        self.region = int(options["region"]) if "region" in options else None

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        store, root = _files(self.at)
        out: list[InputPartition] = []
        for f in store.get_file_info(fs.FileSelector(root, recursive=True)):
            folder = f.path.rsplit("/", 2)[-2]
            if f.is_file and f.path.endswith(".parquet") and folder.startswith("region="):
                region = int(folder.removeprefix("region="))
                if self.region in (None, region):
                    out.append(WordsFile(f.path, region))
        return out or [WordsFile("", 0)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        from pyarrow import parquet

        if not partition.path:
            return
        store, _ = _files(self.at)
        with parquet.ParquetFile(store.open_input_file(partition.path)) as f:
            for b in f.iter_batches(columns=["word", "bits"]):
                yield pa.RecordBatch.from_arrays([pa.array([partition.region] * b.num_rows, pa.int32()), b.column("word"), b.column("bits")], ["region", "word", "bits"])


class SavedFilter(DataSource):
    @classmethod
    def name(cls) -> str:
        return "regionfilter"

    def schema(self) -> str:
        return WORDS

    def reader(self, schema) -> DataSourceReader:
        return WordsReader(dict(self.options))


def register(spark: SparkSession) -> None:
    """Make the format known to this session."""
    spark.dataSource.register(SavedFilter)
