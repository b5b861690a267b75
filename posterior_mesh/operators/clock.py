"""Batch times, completion times, and how many rounds are ready when."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.rng import uniform_of


@dataclass(frozen=True)
class ParetoClock:
    """Batches of r shards take unit_mean * r in the mean; never less than their scale."""

    unit_mean: float = 0.1
    tail: float = 1.2

    def scale(self, r: float) -> float:
        return self.unit_mean * r * (self.tail - 1) / self.tail

    def time(self, u: Column, r) -> Column:
        return F.lit(self.unit_mean * (self.tail - 1) / self.tail) * r * F.pow(u, F.lit(-1 / self.tail))

    def rounds_needed(self, t_max: float, r: float) -> int:
        """So many rounds cover t_max whatever is drawn."""
        return math.floor(t_max / self.scale(r) + 1e-9)


@dataclass(frozen=True)
class ExponentialClock:
    """Batches take ``shift`` of their mean at least; without a shift their number has no bound."""

    unit_mean: float = 0.1
    shift: float = 0.0

    def time(self, u: Column, r) -> Column:
        return F.lit(self.unit_mean) * r * (F.lit(self.shift) - F.lit(1 - self.shift) * F.ln(u))

    def rounds_needed(self, t_max: float, r: float) -> int:
        """So many rounds aren't all done by t_max, but with a chance under 1e-12 for each worker (a Chernoff bound of a Poisson count)."""
        mean = t_max / (self.unit_mean * r * (1 - self.shift)) if self.shift < 1 else 0.0
        rounds = math.ceil(mean) + 1
        while mean and rounds - mean - rounds * math.log(rounds / mean) > math.log(1e-12):
            rounds = math.ceil(rounds * 1.02) + 1
        most = math.floor(t_max / (self.unit_mean * r * self.shift) + 1e-9) if self.shift else rounds
        return min(rounds, most)


@dataclass(frozen=True)
class ConstantClock:
    unit_mean: float = 0.1

    def time(self, u: Column, r) -> Column:
        return F.lit(self.unit_mean) * r + 0 * u

    def rounds_needed(self, t_max: float, r: float) -> int:
        return math.floor(t_max / (self.unit_mean * r) + 1e-9)


def batch_times(spark: SparkSession, k: int, r: int, rounds: int, runs: int = 1, law=None, seed: int = 42, alloc: DataFrame | None = None, tail_cost: str = "r") -> DataFrame:
    """run, worker, round, dt, done_at. ``tail_cost="held"`` charges a worker for the shards it holds, not for r."""
    law = law or ParetoClock()
    grid = spark.range(runs * k).selectExpr(f"CAST(id DIV {k} + 1 AS int) AS run", f"CAST(id % {k} + 1 AS int) AS worker")
    cost = F.lit(float(r))
    if tail_cost == "held":
        grid = grid.join(F.broadcast(alloc.groupBy("worker").agg(F.count("*").cast("double").alias("held"))), "worker")
        cost = F.col("held")
    each = grid.withColumn("round", F.explode(F.sequence(F.lit(1), F.lit(rounds))))
    return with_done_at(each.select("run", "worker", "round", law.time(uniform_of(F.lit("t"), "run", "worker", "round", seed=seed), cost).alias("dt")))


def with_done_at(times: DataFrame) -> DataFrame:
    return times.withColumn("done_at", F.sum("dt").over(W.partitionBy("run", "worker").orderBy("round").rowsBetween(W.unboundedPreceding, 0)))


def trace_clock(events: DataFrame, k: int) -> DataFrame:
    """A clock of real arrivals: worker is user modulo k, rounds in order of time, done_at in seconds since 2024."""
    worker = (F.pmod("user_id", F.lit(k)) + 1).cast("int").alias("worker")
    seconds = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6 - 1704067200.0
    order = W.partitionBy("worker").orderBy("done_at", "event_id")
    each = events.select(F.lit(1).alias("run"), worker, seconds.alias("done_at"), "event_id")
    each = each.withColumn("round", F.row_number().over(order))
    return each.withColumn("dt", F.col("done_at") - F.coalesce(F.lag("done_at").over(order), F.lit(0.0))).drop("event_id")


def worker_rounds(clock: DataFrame, k: int, grid: list[float]) -> DataFrame:
    """run, worker, as_of, n: batches finished by each time of the grid, in one pass; workers without any have 0."""
    counts = F.array(*[F.count_if(F.col("done_at") <= t) for t in grid])
    got = clock.groupBy("run", "worker").agg(counts.alias("c"))
    every = clock.select("run").distinct().withColumn("worker", F.explode(F.sequence(F.lit(1), F.lit(k))))
    whole = every.join(got, ["run", "worker"], "left").withColumn("c", F.coalesce("c", F.array(*[F.lit(0).cast("long")] * len(grid))))
    times = F.array(*[F.lit(float(t)) for t in grid])
    return whole.select("run", "worker", F.posexplode("c").alias("i", "n")).select("run", "worker", times[F.col("i")].alias("as_of"), "n")


def group_of(r: int) -> Column:
    return F.expr(f"CAST((worker - 1) DIV {r} + 1 AS int)")


def ready_rounds(clock: DataFrame, scheme: str, k: int, r: int, grid: list[float]) -> DataFrame:
    """run, as_of, rounds: how many global draws can be made by then."""
    each = worker_rounds(clock, k, grid)
    if scheme == "replica_group":
        each = each.groupBy("run", "as_of", group_of(r).alias("grp")).agg(F.sum("n").alias("n"))
    if scheme == "coded_sum":
        return each.groupBy("run", "as_of").agg(F.sort_array(F.collect_list("n"))[r - 1].alias("rounds"))
    return each.groupBy("run", "as_of").agg(F.min("n").alias("rounds"))


def group_sequence(clock: DataFrame, r: int) -> DataFrame:
    """run, grp, seq, worker, round, done_at: all batches of a group in the order in which they are finished."""
    held = clock.withColumn("grp", group_of(r))
    return held.withColumn("seq", F.row_number().over(W.partitionBy("run", "grp").orderBy("done_at", "worker", "round"))).select("run", "grp", "seq", "worker", "round", "done_at")


def early(clock: DataFrame, k: int, r: int) -> DataFrame:
    """The first k - r + 1 arrivals of each round; later ones aren't used."""
    rank = F.row_number().over(W.partitionBy("run", "round").orderBy("done_at", "worker"))
    return clock.withColumn("rank", rank).where(F.col("rank") <= k - r + 1)


def arrival_patterns(clock: DataFrame, k: int, r: int) -> DataFrame:
    """run, round, pattern (workers in order of number), ready_at, of complete rounds."""
    each = early(clock, k, r).groupBy("run", "round").agg(F.sort_array(F.collect_list("worker")).alias("pattern"), F.max("done_at").alias("ready_at"))
    return each.where(F.size("pattern") == k - r + 1)


def ready_at(clock: DataFrame, scheme: str, k: int, r: int) -> DataFrame:
    """run, round, ready_at: when each global draw can be made first."""
    if scheme == "coded_sum":
        return arrival_patterns(clock, k, r).select("run", "round", "ready_at")
    parts = -(-k // r) if scheme == "replica_group" else k
    each = group_sequence(clock, r).select("run", F.col("seq").alias("round"), "done_at") if scheme == "replica_group" else clock.select("run", "round", "done_at")
    return each.groupBy("run", "round").agg(F.max("done_at").alias("ready_at"), F.count("*").alias("n")).where(F.col("n") == parts).drop("n")


def straggler_profile(clock: DataFrame) -> DataFrame:
    """run, round, gap between first and last arrival, and who is last."""
    return clock.groupBy("run", "round").agg((F.max("done_at") - F.min("done_at")).alias("gap"), F.max_by("worker", F.struct("done_at", "worker")).alias("last"))


def mean_batch_time(clock: DataFrame) -> DataFrame:
    """run, n, mean: how long a batch takes in the mean; the laws say unit_mean times the shards that are held."""
    return clock.groupBy("run").agg(F.count("*").alias("n"), F.avg("dt").alias("mean"))


def clock_check(clock: DataFrame, law: ParetoClock, r: float, times: tuple[float, ...] = (1.5, 2.0, 4.0, 8.0)) -> DataFrame:
    """least, median, mean and, for each multiple of the scale, the share of batches that take longer, beside what the law says."""
    scale = law.scale(r)
    got = clock.agg(F.min("dt").alias("least"), F.percentile("dt", F.lit(0.5)).alias("median"), F.avg("dt").alias("mean"), *[F.avg((F.col("dt") > c * scale).cast("double")).alias(f"p{i}") for i, c in enumerate(times)])
    said = [("least", scale), ("median", scale * 2 ** (1 / law.tail)), ("mean", law.unit_mean * r), *((f"longer_{c:g}", c**-law.tail) for c in times)]
    names = ["least", "median", "mean", *(f"p{i}" for i in range(len(times)))]
    each = F.array(*[F.struct(F.lit(n).alias("what"), F.col(c).alias("got"), F.lit(float(v)).alias("law")) for (n, v), c in zip(said, names)])
    return got.select(F.explode(each).alias("x")).select("x.*")


def timeline(clock: DataFrame, k: int, t: float) -> DataFrame:
    """run, worker, n, begun, ended, blocked: each worker's batches by ``t``, and whether the next global draw without redundancy waits for it."""
    done = clock.where(F.col("done_at") <= t).groupBy("run", "worker").agg(F.count("*").alias("n"), F.max("done_at").alias("ended"))
    every = clock.select("run").distinct().withColumn("worker", F.explode(F.sequence(F.lit(1), F.lit(k))))
    held = every.join(done, ["run", "worker"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    return held.withColumn("blocked", F.col("n") == F.min("n").over(W.partitionBy("run")))
