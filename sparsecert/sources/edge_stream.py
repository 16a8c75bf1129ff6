"""An ordered stream of edges from a Parquet edge list: the offset is the number of edges told so far."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, InputPartition, SimpleDataSourceStreamReader


class EdgeStreamReader(SimpleDataSourceStreamReader):
    def __init__(self, options: dict[str, str]):
        self.path, self.step = options["path"], int(options.get("edgesPerBatch", "1000"))
        self.rows: list[tuple] | None = None

    def _all(self) -> list[tuple]:
        if self.rows is None:
            import pyarrow.dataset as ds

            table = ds.dataset(self.path).to_table(columns=["u", "v", "w", "eid", "seq"]).sort_by("seq")
            self.rows = list(zip(*(table.column(c).to_pylist() for c in table.column_names), strict=True))
        return self.rows

    def initialOffset(self) -> dict:
        return {"edges": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = min(start["edges"] + self.step, len(self._all()))
        return iter(self._all()[start["edges"] : end]), {"edges": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return iter(self._all()[start["edges"] : end["edges"]])

    def commit(self, end: dict) -> None:
        pass


class EdgeStream(DataSource):
    """Format edge_stream, options path and edgesPerBatch; for tests and small replays, as the driver reads it."""

    @classmethod
    def name(cls) -> str:
        return "edge_stream"

    def schema(self) -> str:
        return "u bigint, v bigint, w bigint, eid bigint, seq bigint"

    def simpleStreamReader(self, schema) -> EdgeStreamReader:
        return EdgeStreamReader(self.options)

    def partitions(self) -> list[InputPartition]:
        return []


def register(spark: SparkSession) -> None:
    spark.dataSource.register(EdgeStream)
