"""A data source of simulated nodes: profiles in batch, availability by round as a stream."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader
from pyspark.sql.types import StructType

from taskmesh.functions.draws import uniform_for


class _Profiles(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.nodes, self.parts = int(options.get("nodes", 10)), int(options.get("partitions", 2))
        self.seed, self.drop = int(options.get("seed", 0)), float(options.get("drop", 0.1))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for t in range(partition.value, self.nodes, self.parts):
            yield t, 0.25 + 0.75 * uniform_for("speed", self.seed, t), 0.5 + uniform_for("net", self.seed, t), self.drop


class _Rounds(SimpleDataSourceStreamReader):
    def __init__(self, options: dict) -> None:
        self.nodes, self.seed = int(options.get("nodes", 10)), int(options.get("seed", 0))
        self.drop, self.rounds = float(options.get("drop", 0.1)), int(options.get("rounds", 5))

    def initialOffset(self) -> dict:  # noqa: N802
        return {"round": 0}

    def _of(self, low: int, high: int) -> list[tuple]:
        return [(h, t, uniform_for("drop", self.seed, 0, h, t) < self.drop) for h in range(low, high) for t in range(self.nodes)]

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = min(start["round"] + 1, self.rounds)
        return iter(self._of(start["round"], end)), {"round": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:  # noqa: N802
        return iter(self._of(start["round"], end["round"]))


class NodeSimulator(DataSource):
    """spark.read.format("node_simulator").option("nodes", 100): task_id, speed, comm_scale, drop_p.
    spark.readStream.format("node_simulator").schema("round long, task_id long, dropped boolean"): one round a batch."""

    @classmethod
    def name(cls) -> str:
        return "node_simulator"

    def schema(self) -> str:
        return "task_id long, speed double, comm_scale double, drop_p double"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Profiles(self.options)

    def simpleStreamReader(self, schema: StructType) -> SimpleDataSourceStreamReader:  # noqa: N802
        return _Rounds(self.options)
