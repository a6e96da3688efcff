"""The given tables, and a data source that makes synthetic parties for load tests."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class PartySource(DataSource):
    """spark.read.format("party").option("rows", n): ids and names by rule, in partitions of a given size."""

    @classmethod
    def name(cls) -> str:
        return "party"

    def schema(self) -> str:
        return "rec_id string, entity_id long, given string, surname string"

    def reader(self, schema) -> DataSourceReader:
        return PartyReader(int(self.options.get("rows", 1000)), int(self.options.get("perpartition", 10_000)), self.options.get("party", "A"))


class PartyReader(DataSourceReader):
    def __init__(self, rows: int, size: int, party: str):
        self.rows, self.size, self.party = rows, size, party

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(start) for start in range(0, self.rows, self.size)] or [InputPartition(0)]

    def read(self, partition: InputPartition):
        import hashlib

        for i in range(partition.value, min(self.rows, partition.value + self.size)):
            code = hashlib.md5(str(i).encode()).hexdigest()
            name = code.translate(str.maketrans("0123456789", "ghijklmnop"))
            yield f"{self.party}-{i}", i, name[:6], name[6:13]
