"""A simulated fleet as a data source: ``spark.read.format("simulated_fleet")``.

Options: ``devices`` (25), ``epochs`` (100), ``macs``, ``bits``, ``seed``. Partitions are
runs of epochs; draws are the keyed hashes of ``latency.sample``, so a retried partition gives the same rows.
"""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "epoch int, device int, total_s double"


class _Run(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class FleetReader(DataSourceReader):
    def __init__(self, options):
        get = options.get
        self.devices, self.epochs, self.seed = int(get("devices", 25)), int(get("epochs", 100)), str(get("seed", "1"))
        self.macs, self.bits, self.size = float(get("macs", 4e7)), float(get("bits", 960000)), int(get("run", 50))

    def partitions(self):
        return [_Run(a, min(a + self.size, self.epochs + 1)) for a in range(1, self.epochs + 1, self.size)]

    def read(self, partition):
        import math

        from padgrad.functions.keys import np_prf60
        from padgrad.operators.latency import class_rates, sends_from_uniform
        from padgrad.sources.devices import DOWN_RATE, FAILURE, HEADER, UP_RATE

        rates, wire = class_rates(self.devices), self.bits * (1 + HEADER)
        for epoch in range(partition.first, partition.last):
            for device, tau in enumerate(rates):
                setup, up, down = ((np_prf60(self.seed, epoch, device, k) + 0.5) / 2.0**60 for k in ("setup", "up", "down"))
                work = self.macs / tau
                links = sends_from_uniform(up, FAILURE) * wire / UP_RATE + sends_from_uniform(down, FAILURE) * wire / DOWN_RATE
                yield epoch, device, float(work - math.log(setup) * work / 2 + links)


class FleetSource(DataSource):
    @classmethod
    def name(cls):
        return "simulated_fleet"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return FleetReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(FleetSource)
