"""Errors over time, tolerated stragglers, storage and messages."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.linalg import covariance, spd_inverse
from .coding import GradientCode
from .models import exact_global


def second_moment_errors(globals_: DataFrame, sub: DataFrame, d: int, signed: bool = True) -> DataFrame:
    """run, as_of, rounds, err: gaps of mean products of two coordinates to the truth, relative, averaged over all pairs."""
    truth = exact_global(sub, d).select(F.array(*[F.col("cov")[i * d + j] + F.col("mean")[i] * F.col("mean")[j] for i in range(d) for j in range(d)]).alias("truth"))
    means = globals_.groupBy("run", "as_of").agg(F.count("*").alias("rounds"), F.array(*[F.avg(F.col("x")[i] * F.col("x")[j]) for i in range(d) for j in range(d)]).alias("m"))
    gap = lambda m, t: F.try_divide(F.abs(m - t), t if signed else F.abs(t))
    return means.crossJoin(F.broadcast(truth)).select("run", "as_of", "rounds", (F.aggregate(F.zip_with("m", "truth", gap), F.lit(0.0), lambda a, x: a + x) / (d * d)).alias("err"))


def every_run(errors: DataFrame, spark: SparkSession, runs: int, grid: list[float]) -> DataFrame:
    """The errors with a row for each run and time: no draws and a null error where there was none."""
    times = F.explode(F.array(*[F.lit(float(t)) for t in grid])).alias("as_of")
    every = spark.range(1, runs + 1).select(F.col("id").cast("int").alias("run"), times)
    return every.join(errors, ["run", "as_of"], "left").withColumn("rounds", F.coalesce("rounds", F.lit(0).cast("long")))


def error_curve(errors: DataFrame, band: float = 0.15, sd: str = "sample", by: tuple[str, ...] = ()) -> DataFrame:
    """as_of, mean_err, sd_err, lo, hi over the runs that have a draw, mean_rounds over all, runs, and runs_without a draw.

    The protocols' means are of the same runs only where none is without.
    """
    spread = F.coalesce(F.stddev_samp("err") if sd == "sample" else F.stddev_pop("err"), F.lit(0.0))
    got = errors.groupBy(*by, "as_of").agg(F.avg("err").alias("mean_err"), spread.alias("sd_err"), F.avg("rounds").alias("mean_rounds"), F.count("*").alias("runs"), F.count_if(F.col("err").isNull()).alias("runs_without"))
    return got.select(*by, "as_of", "mean_err", "sd_err", (F.col("mean_err") - band * F.col("sd_err")).alias("lo"), (F.col("mean_err") + band * F.col("sd_err")).alias("hi"), "mean_rounds", "runs", "runs_without")


def moment_error(moments: DataFrame, sub: DataFrame, d: int, ridge: float = 0.0) -> DataFrame:
    """run, as_of, shard, n, cov_err: how far a shard's covariance of draws is from the exact one, relative (Frobenius)."""
    got = moments.select("run", "as_of", "shard", "n", covariance(F.col("n"), F.col("s1"), F.col("s2"), ridge, d).alias("c"))
    exact = sub.select("shard", spd_inverse("prec").alias("t"))
    square = lambda c: F.aggregate(c, F.lit(0.0), lambda a, x: a + x * x)
    gap = F.sqrt(square(F.zip_with("c", "t", lambda a, b: a - b)) / square(F.col("t")))
    return got.join(F.broadcast(exact), "shard").select("run", "as_of", "shard", "n", gap.alias("cov_err"))


def resilience(scheme: str, k: int, r: int, worst: bool = False) -> int:
    """Stragglers that a protocol can bear: spread in the best way, or in the worst."""
    if scheme == "one_shot" or r == 1:
        return 0
    if scheme == "coded_sum":
        return r - 1
    last = k % r or r
    return min(r, last) - 1 if worst else (k // r) * (r - 1) + (k % r - 1 if k % r else 0)


def survives(scheme: str, k: int, r: int, lost: set[int], code: GradientCode | None = None) -> bool:
    if scheme == "one_shot":
        return not lost
    if scheme == "coded_sum":
        return (code or GradientCode(k, r)).survives(lost)
    return all(any(w not in lost for w in range(g, min(g + r, k + 1))) for g in range(1, k + 1, r))


def storage_rows(n: int, k: int, r: int) -> float:
    return n * r / k


def comm_cost(scheme: str, r: int, d: int) -> int:
    """Numbers that a worker sends for each batch."""
    return r * d if scheme == "replica_group" else d


def precision_gap(phi: DataFrame, sub: DataFrame, d: int, ridge: float = 0.0, warmup: int = 0) -> DataFrame:
    """run, round, gap: how far the covariance of decoded sums is from the total precision, relative (Frobenius)."""
    from .protocols import prefix_moments

    held = prefix_moments(phi.where(F.col("round") > warmup), d, ("run",), "phi").select("run", "round", covariance(F.col("n"), F.col("s1"), F.col("s2"), ridge, d).alias("c"))
    each = held.crossJoin(F.broadcast(exact_global(sub, d).select("prec")))
    square = lambda c: F.aggregate(c, F.lit(0.0), lambda a, x: a + x * x)
    return each.select("run", "round", F.sqrt(square(F.zip_with("c", "prec", lambda a, b: a - b)) / square(F.col("prec"))).alias("gap"))


def utilisation(clock: DataFrame, scheme: str, k: int, r: int, t: float) -> DataFrame:
    """run, computed, used: batches finished by t, and those that enter a global draw or its weights."""
    from .clock import early

    done = clock.where(F.col("done_at") <= t)
    all_ = done.groupBy("run").agg(F.count("*").alias("computed"))
    if scheme != "coded_sum":
        return all_.withColumn("used", F.col("computed"))
    return all_.join(early(done, k, r).groupBy("run").agg(F.count("*").alias("used")), "run", "left")


def rate_errors(globals_: DataFrame, sub: DataFrame) -> DataFrame:
    """run, as_of, rounds, err: relative gap of the mean global draw of a Gamma posterior to its true mean."""
    from .models import exact_rate

    means = globals_.groupBy("run", "as_of").agg(F.count("*").alias("rounds"), F.avg(F.col("x")[0]).alias("m"))
    truth = exact_rate(sub).select((F.col("shape") / F.col("rate")).alias("truth"))
    return means.crossJoin(F.broadcast(truth)).select("run", "as_of", "rounds", F.try_divide(F.abs(F.col("m") - F.col("truth")), F.col("truth")).alias("err"))


def share_errors(globals_: DataFrame, sub: DataFrame) -> DataFrame:
    """run, as_of, rounds, err: relative gap of the mean global draw of a Beta posterior to its true mean.

    Weighted means of Beta draws aren't draws of the product, whose mean they approach as the shards grow.
    """
    from .models import exact_share

    means = globals_.groupBy("run", "as_of").agg(F.count("*").alias("rounds"), F.avg(F.col("x")[0]).alias("m"))
    truth = exact_share(sub).select((F.col("alpha") / (F.col("alpha") + F.col("beta"))).alias("truth"))
    return means.crossJoin(F.broadcast(truth)).select("run", "as_of", "rounds", F.try_divide(F.abs(F.col("m") - F.col("truth")), F.col("truth")).alias("err"))


def curve_quantiles(errors: DataFrame, qs: tuple[float, ...] = (0.05, 0.5, 0.95), by: tuple[str, ...] = ("scheme",)) -> DataFrame:
    """as_of and exact quantiles of the error over runs."""
    names = [f"q{round(100 * q):02d}" for q in qs]
    got = errors.groupBy(*by, "as_of").agg(F.percentile("err", F.array(*[F.lit(q) for q in qs])).alias("q"))
    return got.select(*by, "as_of", *[F.col("q")[i].alias(n) for i, n in enumerate(names)])


def idle_spans(clock: DataFrame, width: float) -> DataFrame:
    """run, slot, worker, busy: time of each slot of ``width`` in which a worker computes a batch; each batch meets the slots that it overlaps."""
    begun = F.col("done_at") - F.col("dt")
    each = clock.withColumn("slot", F.explode(F.sequence(F.floor(begun / width), F.floor(F.col("done_at") / width))))
    part = F.least(F.col("done_at"), (F.col("slot") + 1) * width) - F.greatest(begun, F.col("slot") * width)
    return each.groupBy("run", "slot", "worker").agg(F.sum(F.greatest(part, F.lit(0.0))).alias("busy"))
