"""Batch times of modelled workers as a data source: format ``virtual_cluster``, a partition for each run and worker."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.sql import worker_times
from ..operators.clock import ParetoClock


class WorkerPartition(InputPartition):
    def __init__(self, run: int, worker: int):
        super().__init__((run, worker))
        self.run, self.worker = run, worker


class ClusterReader(DataSourceReader):
    def __init__(self, options):
        self.k, self.r = int(options.get("workers", 5)), int(options.get("redundancy", 1))
        self.rounds, self.runs, self.seed = int(options.get("rounds", 100)), int(options.get("runs", 1)), int(options.get("seed", 42))
        self.law = ParetoClock(float(options.get("unit_mean", 0.1)), float(options.get("tail", 1.2)))

    def partitions(self):
        return [WorkerPartition(run, w) for run in range(1, self.runs + 1) for w in range(1, self.k + 1)]

    def read(self, partition):
        yield from worker_times(partition.run, partition.worker, self.r, self.rounds, self.law, self.seed)


class VirtualCluster(DataSource):
    """Options: workers, redundancy, rounds, runs, seed, unit_mean, tail."""

    @classmethod
    def name(cls):
        return "virtual_cluster"

    def schema(self):
        return "run int, worker int, round int, dt double, done_at double"

    def reader(self, schema):
        return ClusterReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(VirtualCluster)
