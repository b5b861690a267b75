"""Draws of subposteriors, keyed so that any task repeats them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.linalg import cholesky, spd_inverse
from ..functions.rng import beta_of, gamma_of, normal_of


def drawn(each: DataFrame, sub: DataFrame, d: int, share: bool = False, seed: int = 42) -> DataFrame:
    """The rows (run, worker, shard, round and others) with x, a draw of their shard's subposterior; ``share``: the worker isn't part of its key.

    Toeplitz subposteriors (a column rho) follow a recursion of one step; Gamma ones (shape, rate) and Beta ones
    (alpha, beta) have one dimension; others take the Cholesky factor of their covariance, worked out once for each shard.
    Draws are an expression of their keys, so that only rows that are asked for are drawn, and none is moved.
    """
    names = each.columns
    toeplitz = "rho" in sub.columns
    gamma, beta = {"shape", "rate"} <= set(sub.columns), {"alpha", "beta"} <= set(sub.columns)
    if (gamma or beta) and d != 1:
        raise ValueError("Gamma and Beta subposteriors have one dimension")
    if not (toeplitz or gamma or beta):
        # chol of the covariance and the mean, once a shard
        sub = sub.withColumn("_cov", spd_inverse("prec")).withColumn("_l", cholesky("_cov"))
        sub = sub.withColumn("_mean", F.array(*[sum((F.col("_cov")[i * d + j] * F.col("info")[j] for j in range(1, d)), F.col("_cov")[i * d] * F.col("info")[0]) for i in range(d)]))
    each = each.join(F.broadcast(sub), "shard")
    keys = ["run", "shard", "round"] if share else ["run", "worker", "shard", "round"]
    if gamma or beta:
        x = gamma_of(F.col("shape"), *keys, seed=seed) / F.col("rate") if gamma else beta_of(F.col("alpha"), F.col("beta"), *keys, seed=seed)
        return each.select(*names, F.array(x).alias("x"))
    each = each.withColumn("_z", F.array(*[normal_of(*keys, i, seed=seed) for i in range(1, d + 1)]))
    if toeplitz:
        step = lambda a, z: F.concat(a, F.array(F.col("rho") * F.element_at(a, -1) + F.sqrt(1 - F.col("rho") * F.col("rho")) * z))
        x = F.aggregate(F.slice("_z", 2, d - 1), F.slice("_z", 1, 1), step)
    else:
        x = F.array(*[F.col("_mean")[i] + sum((F.col("_l")[i * d + j] * F.col("_z")[j] for j in range(1, i + 1)), F.col("_l")[i * d] * F.col("_z")[0]) for i in range(d)])
    return each.select(*names, x.alias("x"))


def draws(sub: DataFrame, alloc: DataFrame, rounds: int, d: int, runs: int = 1, share: bool = False, seed: int = 42) -> DataFrame:
    """run, worker, shard, round, x of all rounds. ``share``: holders of a shard draw alike, so each draw is made once and has worker 0."""
    holders = sub.select("shard").withColumn("worker", F.lit(0)) if share else alloc.select("worker", "shard")
    each = sub.sparkSession.range(1, runs + 1).selectExpr("CAST(id AS int) AS run").crossJoin(F.broadcast(holders))
    each = each.withColumn("round", F.explode(F.sequence(F.lit(1), F.lit(rounds))))
    return drawn(each.select("run", "worker", "shard", "round"), sub, d, share, seed)


def share_draws(sub: DataFrame, rounds: int, runs: int = 1, seed: int = 42) -> DataFrame:
    """run, shard, round, category, x: Dirichlet draws of ``category_shares``, as shares of Gamma draws of each category."""
    each = sub.select("shard", "category", "alpha").withColumn("run", F.explode(F.sequence(F.lit(1), F.lit(runs)))).withColumn("round", F.explode(F.sequence(F.lit(1), F.lit(rounds))))
    each = each.withColumn("g", gamma_of(F.col("alpha"), "run", "shard", "round", "category", seed=seed))
    return each.select("run", "shard", "round", "category", (F.col("g") / F.sum("g").over(W.partitionBy("run", "shard", "round"))).alias("x"))
