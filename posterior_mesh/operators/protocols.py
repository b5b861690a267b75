"""What the collector can say at each time, under the three protocols."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.linalg import covariance, matvec, outer, spd_inverse, spd_solve, vector_sum
from .clock import ParetoClock, arrival_patterns, batch_times, group_sequence, ready_at, ready_rounds
from .coding import GradientCode, decode, encode
from .draws import drawn
from .layout import allocation


@dataclass(frozen=True)
class ProtocolSpec:
    """One protocol: ``weights`` are plugin, exact, uniform or diagonal; ``refresh`` is query_time or last_round.

    Of coded_sum: ``warmup`` rounds are left out, ``recompute`` weights all rounds with the newest total, and
    ``ridge_total`` is the collector's own regulariser (None: the workers'). ``redraw``: runs have their own times and draws (both),
    or their own times and the same draws (times).
    """

    scheme: str
    k: int
    r: int = 1
    d: int = 5
    runs: int = 1
    ridge: float = 1e-3
    law: object = field(default_factory=ParetoClock)
    code: GradientCode | None = None
    weights: str = "plugin"
    refresh: str = "query_time"
    warmup: int = 0
    recompute: bool = False
    ridge_total: float | None = None
    tail_cost: str = "r"
    redraw: str = "both"
    seed: int = 42


def bucket_of(done: Column, grid: list[float]) -> Column:
    """Index of the first time of the grid that isn't before ``done``, from 0; the grid's length if there is none."""
    return sum((F.when(done > t, 1).otherwise(0) for t in grid), F.lit(0))


def arrivals(clock: DataFrame, alloc: DataFrame, sub: DataFrame, spec: ProtocolSpec) -> DataFrame:
    """run, shard, round (of the protocol), done_at, x: draws when they reach the collector; grouped ones in their group's order.

    Only batches that the clock has are drawn, where the clock's rows are; with ``redraw="times"`` all runs draw what run 1 does.
    """
    if spec.scheme == "replica_group":
        clock = group_sequence(clock, spec.r)
        own = ["seq"]
    else:
        own = []
    held = clock.select("run", "worker", "round", "done_at", *own).join(F.broadcast(alloc.select("worker", "shard")), "worker")
    if spec.redraw == "times":
        held = held.withColumnRenamed("run", "_run").withColumn("run", F.lit(1))
    got = drawn(held, sub, spec.d, seed=spec.seed)
    if spec.redraw == "times":
        got = got.drop("run").withColumnRenamed("_run", "run")
    return got.select("run", "shard", F.col("seq" if own else "round").alias("round"), "done_at", "x")


def shard_moments(came: DataFrame, grid: list[float], d: int) -> DataFrame:
    """run, as_of, shard, n, s1, s2 of all draws that came by each time: one pass, then sums over the grid's few buckets."""
    part = came.withColumn("b", bucket_of(F.col("done_at"), grid)).where(F.col("b") < len(grid))
    sums = part.groupBy("run", "shard", "b").agg(F.count("*").alias("n"), vector_sum(F.col("x"), d).alias("s1"), vector_sum(outer(F.col("x"), d), d * d).alias("s2"))
    times = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(float(t)).alias("as_of")) for i, t in enumerate(grid)])
    each = sums.withColumn("g", F.explode(times)).where("b <= g.i")
    return each.groupBy("run", F.col("g.as_of").alias("as_of"), "shard").agg(F.sum("n").alias("n"), vector_sum(F.col("s1"), d).alias("s1"), vector_sum(F.col("s2"), d * d).alias("s2"))


def last_round_times(ready: DataFrame, at: DataFrame) -> DataFrame:
    """run, times (moments of the last global draw before each time of the grid, in order, with that time)."""
    each = ready.join(at, (ready["run"] == at["run"]) & (ready["rounds"] == at["round"])).select(ready["run"], F.struct("ready_at", "as_of").alias("t"))
    return each.groupBy("run").agg(F.sort_array(F.collect_list("t")).alias("times"))


def moments_at(came: DataFrame, times: DataFrame, d: int) -> DataFrame:
    """As ``shard_moments``, of draws that came by each run's own times: a run's times are few, so they are sent along."""
    late = F.size(F.filter("times", lambda t: t["ready_at"] < F.col("done_at")))
    part = came.join(F.broadcast(times), "run").withColumn("b", late).where(F.col("b") < F.size("times"))
    sums = part.groupBy("run", "shard", "b").agg(F.count("*").alias("n"), vector_sum(F.col("x"), d).alias("s1"), vector_sum(outer(F.col("x"), d), d * d).alias("s2"))
    each = sums.join(F.broadcast(times), "run").select("run", "shard", "b", "n", "s1", "s2", F.posexplode("times").alias("p", "t")).where("b <= p")
    return each.groupBy("run", F.col("t.as_of").alias("as_of"), "shard").agg(F.sum("n").alias("n"), vector_sum(F.col("s1"), d).alias("s1"), vector_sum(F.col("s2"), d * d).alias("s2"))


def shard_precisions(moments: DataFrame, spec: ProtocolSpec, sub: DataFrame) -> DataFrame:
    """run, as_of, shard, p: what a shard's draws are multiplied by."""
    d = spec.d
    if spec.weights == "exact":
        return moments.select("run", "as_of", "shard").join(F.broadcast(sub.select("shard", F.col("prec").alias("p"))), "shard")
    if spec.weights == "uniform":
        return moments.select("run", "as_of", "shard", F.array(*[F.lit(float(i == j)) for i in range(d) for j in range(d)]).alias("p"))
    c = covariance(F.col("n"), F.col("s1"), F.col("s2"), spec.ridge, d)
    if spec.weights == "diagonal":
        c = F.array(*[c[i * d + j] if i == j else F.lit(0.0) for i in range(d) for j in range(d)])
    return moments.select("run", "as_of", "shard", spd_inverse(c).alias("p"))


def combined(came: DataFrame, precisions: DataFrame, ready: DataFrame, spec: ProtocolSpec) -> DataFrame:
    """run, as_of, round, x: all global draws up to the ready round, weighted with what is known at that time."""
    d, k = spec.d, spec.k
    total = precisions.groupBy("run", "as_of").agg(vector_sum(F.col("p"), d * d).alias("total")).withColumn("v", spd_inverse("total")).drop("total")
    used = came.join(F.broadcast(ready.where("rounds > 0")), "run").where(F.col("round") <= F.col("rounds"))
    each = used.join(F.broadcast(precisions), ["run", "as_of", "shard"]).withColumn("y", matvec(F.col("p"), F.col("x"), d))
    sums = each.groupBy("run", "as_of", "round").agg(vector_sum(F.col("y"), d).alias("y"), F.count("*").alias("c")).where(F.col("c") == k)
    return sums.join(F.broadcast(total), ["run", "as_of"]).select("run", "as_of", "round", matvec(F.col("v"), F.col("y"), d).alias("x"))


#: Rounds of a block of running sums.
BLOCK = 256


def prefix_moments(d: DataFrame, size: int, keys: tuple[str, ...] = ("run", "shard"), column: str = "x") -> DataFrame:
    """The rows with n, s1, s2 over the rounds up to each: running sums in blocks of rounds, after the sums of the blocks before.

    So a long run isn't one task; only a row for each block passes through the window of a whole run.
    """
    x, block = F.col(column), F.expr(f"CAST((round - 1) DIV {BLOCK} AS int)")
    parts = {"n": F.lit(1).cast("long"), **{f"_a{i}": x[i] for i in range(size)}, **{f"_b{i}_{j}": x[i] * x[j] for i in range(size) for j in range(i, size)}}
    held = d.withColumn("_block", block)
    sums = held.groupBy(*keys, "_block").agg(*[F.sum(c).alias(k) for k, c in parts.items()])
    earlier = W.partitionBy(*keys).orderBy("_block").rowsBetween(W.unboundedPreceding, -1)
    before = sums.select(*keys, "_block", *[F.coalesce(F.sum(k).over(earlier), F.lit(0)).alias(f"{k}_0") for k in parts])
    run = W.partitionBy(*keys, "_block").orderBy("round").rowsBetween(W.unboundedPreceding, 0)
    inner = held.select("*", *[F.sum(c).over(run).alias(k) for k, c in parts.items()]).join(before, [*keys, "_block"])
    total = lambda k: F.col(k) + F.col(f"{k}_0")
    s1 = F.array(*[total(f"_a{i}") for i in range(size)])
    s2 = F.array(*[total(f"_b{min(i, j)}_{max(i, j)}") for i in range(size) for j in range(size)])
    return inner.select(*d.columns, total("n").alias("n"), s1.alias("s1"), s2.alias("s2"))


def processed_draws(shared: DataFrame, spec: ProtocolSpec) -> DataFrame:
    """run, shard, round, x: each draw times the inverse of the covariance of its shard's draws so far."""
    held = prefix_moments(shared, spec.d)
    c = covariance(F.col("n"), F.col("s1"), F.col("s2"), spec.ridge, spec.d)
    return held.select("run", "shard", "round", spd_solve(c, F.col("x")).alias("x"))


def coded_draws(phi: DataFrame, ready: DataFrame, spec: ProtocolSpec) -> DataFrame:
    """run, as_of, round, x: global draws of decoded sums, each with the total known at its round; newest total with ``recompute``."""
    ridge = spec.ridge if spec.ridge_total is None else spec.ridge_total
    kept = phi.where(F.col("round") > spec.warmup)
    held = prefix_moments(kept, spec.d, ("run",), "phi")
    total = covariance(F.col("n"), F.col("s1"), F.col("s2"), ridge, spec.d)
    if not spec.recompute:
        own = held.select("run", "round", spd_solve(total, F.col("phi")).alias("x"))
        return own.join(F.broadcast(ready), "run").where(F.col("round") <= F.col("rounds")).select("run", "as_of", "round", "x")
    newest = held.select("run", F.col("round").alias("rounds"), total.alias("total"))
    last = ready.join(newest, ["run", "rounds"]).select("run", "as_of", "rounds", "total")
    return kept.join(F.broadcast(last), "run").where(F.col("round") <= F.col("rounds")).select("run", "as_of", "round", spd_solve("total", "phi").alias("x"))


class PosteriorMesh:
    """Lazy frames of one protocol: subposteriors, allocation, clock, draws, ready, weights, global_draws, errors, curve, explain."""

    def __init__(self, spark: SparkSession, spec: ProtocolSpec, subposteriors: DataFrame, t_max: float, clock: DataFrame | None = None):
        if spec.refresh not in ("query_time", "last_round") or spec.redraw not in ("both", "times") or spec.weights not in ("plugin", "exact", "uniform", "diagonal"):
            raise ValueError(f"no such refresh, redraw or weights: {spec.refresh}, {spec.redraw}, {spec.weights}")
        if spec.scheme != "one_shot" and not 1 <= spec.r <= spec.k:
            raise ValueError(f"redundancy {spec.r} is outside 1 to {spec.k}")
        self.spark, self.spec, self.subposteriors = spark, spec, subposteriors
        self.code = spec.code or (GradientCode(spec.k, spec.r) if spec.scheme == "coded_sum" else None)
        self.r = 1 if spec.scheme == "one_shot" else spec.r
        self.allocation = allocation(spark, spec.scheme, spec.k, self.r, self.code)
        if clock is None:
            rounds = spec.law.rounds_needed(t_max, 1 if spec.tail_cost == "held" else self.r)
            clock = batch_times(spark, spec.k, self.r, rounds, spec.runs, spec.law, spec.seed, self.allocation, spec.tail_cost)
        self.clock = clock.where(F.col("done_at") <= t_max)

    @property
    def draws(self) -> DataFrame:
        """run, worker, shard, round, x of the batches that the clock has; coded workers' draws once, as of worker 0, of complete rounds."""
        if self.spec.scheme == "coded_sum":
            return self._shared()
        held = self.clock.select("run", "worker", "round").join(F.broadcast(self.allocation.select("worker", "shard")), "worker")
        return drawn(held.select("run", "worker", "shard", "round"), self.subposteriors, self.spec.d, seed=self.spec.seed)

    def _shared(self) -> DataFrame:
        most = self.patterns().groupBy("run").agg(F.max("round").alias("most"))
        rounds = most.withColumn("round", F.explode(F.sequence(F.lit(1), F.col("most")))).select("run", "round").repartition("run", F.expr(f"round DIV {BLOCK}"))
        each = rounds.crossJoin(F.broadcast(self.subposteriors.select("shard").withColumn("worker", F.lit(0))))
        if self.spec.redraw == "times":
            each = each.withColumnRenamed("run", "_run").withColumn("run", F.lit(1))
        got = drawn(each, self.subposteriors, self.spec.d, True, self.spec.seed)
        got = got.drop("run").withColumnRenamed("_run", "run") if self.spec.redraw == "times" else got
        return got.select("run", "worker", "shard", "round", "x")

    def patterns(self) -> DataFrame:
        return arrival_patterns(self.clock, self.spec.k, self.r)

    def ready(self, grid: list[float]) -> DataFrame:
        return ready_rounds(self.clock, self.spec.scheme, self.spec.k, self.r, grid)

    def messages(self) -> DataFrame:
        """run, worker, round, msg: what coded workers send."""
        return encode(processed_draws(self._shared(), self.spec), self.allocation, self.spec.d)

    def decoded(self) -> DataFrame:
        """run, round, phi: the sums that the collector decodes from the first workers' messages."""
        return decode(self.messages(), self.patterns(), self.code, self.spec.d)

    def direct_sums(self) -> DataFrame:
        """run, round, phi: what encoding and decoding must come to; for tests."""
        return processed_draws(self._shared(), self.spec).groupBy("run", "round").agg(vector_sum(F.col("x"), self.spec.d).alias("phi"))

    def arrivals(self) -> DataFrame:
        return arrivals(self.clock, self.allocation, self.subposteriors, self.spec)

    def moments(self, grid: list[float]) -> DataFrame:
        """run, as_of, shard, n, s1, s2 of what had come by then, or by the last global draw before then."""
        if self.spec.refresh == "last_round":
            at = ready_at(self.clock, self.spec.scheme, self.spec.k, self.r)
            return moments_at(self.arrivals(), last_round_times(self.ready(grid).where("rounds > 0"), at), self.spec.d)
        return shard_moments(self.arrivals(), grid, self.spec.d)

    def weights(self, grid: list[float]) -> DataFrame:
        """run, as_of, shard, p, w: what a shard's draws are multiplied by, and that after the inverse of all shards' sum."""
        p, d = shard_precisions(self.moments(grid), self.spec, self.subposteriors), self.spec.d
        total = p.groupBy("run", "as_of").agg(vector_sum(F.col("p"), d * d).alias("total")).withColumn("v", spd_inverse("total")).drop("total")
        w = F.array(*[sum((F.col("v")[i * d + m] * F.col("p")[m * d + j] for m in range(1, d)), F.col("v")[i * d] * F.col("p")[j]) for i in range(d) for j in range(d)])
        return p.join(F.broadcast(total), ["run", "as_of"]).select("run", "as_of", "shard", "p", w.alias("w"))

    def global_draws(self, grid: list[float]) -> DataFrame:
        ready = self.ready(grid)
        if self.spec.scheme == "coded_sum":
            return coded_draws(self.decoded(), ready, self.spec)
        return combined(self.arrivals(), shard_precisions(self.moments(grid), self.spec, self.subposteriors), ready, self.spec)

    def errors(self, grid: list[float], signed: bool = True) -> DataFrame:
        """run, as_of, rounds, err: a row for each run and time; err is null where no draw was ready. ``signed``: gaps are divided by the truth, not by its size."""
        from .metrics import every_run, second_moment_errors

        return every_run(second_moment_errors(self.global_draws(grid), self.subposteriors, self.spec.d, signed), self.spark, self.spec.runs, grid)

    def curve(self, grid: list[float]) -> DataFrame:
        from .metrics import error_curve

        return error_curve(self.errors(grid))

    def explain(self, grid: list[float]) -> None:
        self.global_draws(grid).explain("formatted")
