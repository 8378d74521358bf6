"""A data source that replays tables as a round-robin stream of signed changes."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceStreamReader, InputPartition


class _Slice(InputPartition):
    def __init__(self, path: str, start: int, stop: int, sign: int):
        self.path, self.start, self.stop, self.sign = path, start, stop, sign


class _Reader(DataSourceStreamReader):
    """Offsets count turns; at turn t table t mod n gives its next ``batch`` rows."""

    def __init__(self, paths: list[str], columns: list[str], batch: int, turns: int, sign: int):
        self.paths, self.columns, self.batch, self.turns, self.sign = paths, columns, batch, turns, sign
        self.at = 0

    def initialOffset(self) -> dict:
        return {"turn": 0}

    def latestOffset(self) -> dict:
        self.at = min(self.at + 1, self.turns)
        return {"turn": self.at}

    def partitions(self, start: dict, end: dict) -> list[InputPartition]:
        n = len(self.paths)
        return [_Slice(self.paths[t % n], t // n * self.batch, (t // n + 1) * self.batch, self.sign) for t in range(start["turn"], end["turn"])]

    def read(self, partition: _Slice) -> Iterator[tuple]:
        import pyarrow.dataset as ds

        row = 0
        for b in ds.dataset(partition.path).to_batches(columns=self.columns):
            if row + b.num_rows > partition.start:
                part = b.slice(max(0, partition.start - row), partition.stop - max(row, partition.start))
                for values in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    yield (*values, partition.sign)
            row += b.num_rows
            if row >= partition.stop:
                return

    def commit(self, end: dict) -> None:
        return None


class UpdateSource(DataSource):
    """format('ringview_updates'): options ``paths`` (JSON list; tables with the same columns), ``batch``, ``turns``, ``sign``.

    The columns are those of the schema given to the reader, without the last, ``__m``.
    """

    @classmethod
    def name(cls) -> str:
        return "ringview_updates"

    def schema(self) -> str:
        raise ValueError("give the schema: the table's columns, and __m int last")

    def streamReader(self, schema) -> DataSourceStreamReader:
        o = self.options
        return _Reader(json.loads(o["paths"]), [f.name for f in schema.fields[:-1]], int(o.get("batch", 1000)), int(o.get("turns", 10)), int(o.get("sign", 1)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(UpdateSource)
