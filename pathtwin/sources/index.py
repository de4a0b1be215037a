"""Stored path indexes and a data source of generated method files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def write_index(encoded: DataFrame, table: str, buckets: int = 64) -> None:
    """Encoded paths as a table bucketed by fragment, so later joins on fragments read it without an exchange."""
    encoded.write.mode("overwrite").bucketBy(buckets, "fragment_id").sortBy("fragment_id").saveAsTable(table)


def read_index(spark: SparkSession, table: str) -> DataFrame:
    return spark.table(table)


class MethodFiles(DataSource):
    """``spark.read.format("method_files")``: generated methods; options ``files`` and ``partitions``."""

    @classmethod
    def name(cls) -> str:
        return "method_files"

    def schema(self) -> str:
        return "fragment_id long, functionality int, kind string, content string"

    def reader(self, schema) -> DataSourceReader:
        return _MethodReader(int(self.options.get("files", 430)), int(self.options.get("partitions", 4)))


class _MethodReader(DataSourceReader):
    def __init__(self, files: int, parts: int):
        self.files, self.parts = files, parts

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition: InputPartition):
        from pathtwin.corpus.methods import FUNCTIONALITIES, KINDS, mutate, template

        for s in range(partition.value, self.files, self.parts):
            kind = KINDS[s // FUNCTIONALITIES % len(KINDS)]
            yield s, s % FUNCTIONALITIES, kind, mutate(template(s % FUNCTIONALITIES), kind, s)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(MethodFiles)
