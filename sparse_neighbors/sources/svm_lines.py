"""Vectors as text lines `id d:w d:w`: a writer, and a reader as a Python data source."""

from __future__ import annotations

from pyarrow import fs as arrow_fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def write_lines(v: DataFrame, path: str) -> None:
    packed = v.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("d", "w"))).alias("f"))
    features = F.transform("f", lambda x: F.concat_ws(":", x["d"], x["w"]))
    packed.select(F.concat_ws(" ", F.col("id").cast("string"), F.array_join(features, " ")).alias("value")).write.text(path)


class SvmLines(DataSource):
    """spark.read.format("svm_lines").load(folder) -> (id, d, w), one partition a file."""

    @classmethod
    def name(cls) -> str:
        return "svm_lines"

    def schema(self) -> str:
        return "id bigint, d bigint, w bigint"

    def reader(self, schema) -> DataSourceReader:
        return SvmReader(self.options["path"])


class SvmReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def _open(self):
        if "://" in self.path or self.path.startswith("file:"):
            return arrow_fs.FileSystem.from_uri(self.path)
        return arrow_fs.LocalFileSystem(), self.path

    def partitions(self):
        system, path = self._open()
        files = system.get_file_info(arrow_fs.FileSelector(path))
        return [InputPartition(f.path) for f in files if f.is_file and f.base_name.startswith("part-")]

    def read(self, partition):
        system, _ = self._open()
        with system.open_input_stream(partition.value) as stream:
            for line in stream.read().decode().splitlines():
                id, *features = line.split()
                for f in features:
                    d, w = f.split(":")
                    yield int(id), int(d), int(w)
