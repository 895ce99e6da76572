"""The simulator as a data source: spark.read.format("spikes").options(...).load(), or readStream."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

from ..model import STREAM


class SpikeSource(DataSource):
    """options: n (units), seconds, datasets, seed, order (comma-separated units of a planted order),
    rates (unit:rate, comma-separated, of units that don't fire at the usual rate)."""

    @classmethod
    def name(cls) -> str:
        return "spikes"

    def schema(self) -> str:
        return STREAM

    def reader(self, schema) -> DataSourceReader:
        return SpikeReader(self.options)

    def streamReader(self, schema) -> DataSourceStreamReader:
        return SpikeStream(self.options)


class SpikeReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.seconds = int(options.get("n", "26")), float(options.get("seconds", "5"))
        self.datasets, self.seed = int(options.get("datasets", "1")), int(options.get("seed", "1"))
        self.own = {int(i): float(x) for i, x in (p.split(":") for p in options.get("rates", "").split(",") if p)}
        self.order = [int(x) for x in options.get("order", "").split(",") if x]

    def partitions(self):
        return [InputPartition(k) for k in range(self.datasets)]

    def read(self, partition):
        from episodeflow.operators.simulator import TICKS, Network, _fire, plant

        net = Network(self.n, own=dict(self.own))
        if self.order:
            plant(net, [[i] for i in self.order])
        units, times = _fire(net, self.seconds, self.seed * 100_003 + partition.value)
        for k, i in enumerate(times.argsort(kind="stable").tolist()):
            yield str(partition.value), str(units[i]), int(times[i] * TICKS), k


class SpikeStream(SpikeReader, DataSourceStreamReader):
    """A stream of data sets: an offset is how many of them have been read, and all that there are can be read at once."""

    def initialOffset(self) -> dict:
        return {"datasets": 0}

    def latestOffset(self) -> dict:
        return {"datasets": self.datasets}

    def partitions(self, start: dict, end: dict):
        return [InputPartition(k) for k in range(start["datasets"], end["datasets"])]

    def commit(self, end: dict) -> None:
        """Data sets come from their seeds: nothing to let go of."""


def register(spark) -> None:
    spark.dataSource.register(SpikeSource)
