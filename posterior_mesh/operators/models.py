"""Subposteriors: a tempered prior times the likelihood of a shard's rows, as parameters that add up over shards."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.linalg import matvec, spd_inverse, toeplitz_precision, vector_sum


def toeplitz_subposteriors(spark: SparkSession, k: int, d: int = 5) -> DataFrame:
    """shard, rho, prec, info: zero-mean Gaussians with covariances of powers of (shard - 1) / k."""
    shards = spark.range(1, k + 1).selectExpr("CAST(id AS int) AS shard", f"(id - 1) / {float(k)}D AS rho")
    return shards.select("shard", "rho", toeplitz_precision(F.col("rho"), d).alias("prec"), F.array(*[F.lit(0.0)] * d).alias("info"))


def every_shard(got: DataFrame, shards: int) -> DataFrame:
    """The sums with a row of nulls for each shard without rows: its subposterior is its share of the prior."""
    return got.sparkSession.range(1, shards + 1).selectExpr("CAST(id AS int) AS shard").join(got, "shard", "left").withColumn("n", F.coalesce("n", F.lit(0).cast("long")))


def complete(obs: DataFrame, columns: list[Column]) -> DataFrame:
    """The rows without a null among these."""
    return obs.where(reduce(Column.__and__, [c.isNotNull() for c in columns]))


def dropped_rows(obs: DataFrame, columns: list[Column]) -> DataFrame:
    """shard, n, dropped: rows, and those that the models leave out for a null."""
    null = reduce(Column.__or__, [c.isNull() for c in columns])
    return obs.groupBy("shard").agg(F.count("*").alias("n"), F.count_if(null).alias("dropped"))


def linear_subposteriors(obs: DataFrame, x: list[Column], y: Column, shards: int, noise_var: float = 1.0, prior_prec: float = 1.0) -> DataFrame:
    """shard, n, prec, info of a Gaussian regression: one pass, partial sums, d² numbers a shard. Rows with a null don't count at all."""
    d = len(x)
    sums = [F.sum(x[i] * x[j]) for i in range(d) for j in range(i, d)]
    at = {p: k for k, p in enumerate((i, j) for i in range(d) for j in range(i, d))}
    got = every_shard(complete(obs, [*x, y]).groupBy("shard").agg(F.count("*").alias("n"), F.array(*sums).alias("xx"), F.array(*[F.sum(v * y) for v in x]).alias("xy")), shards)
    none = F.lit(0.0)
    prec = F.array(*[F.coalesce(F.col("xx")[at[min(i, j), max(i, j)]], none) / noise_var + (prior_prec / shards if i == j else 0.0) for i in range(d) for j in range(d)])
    return got.select("shard", "n", prec.alias("prec"), F.array(*[F.coalesce(F.col("xy")[i], none) / noise_var for i in range(d)]).alias("info"))


def gaussian_mean(obs: DataFrame, x: list[Column], shards: int, noise_var: float | list[list[float]] = 1.0, prior_prec: float = 1.0) -> DataFrame:
    """shard, n, prec, info: the mean of Gaussians of a known variance, alike and independent or given as a covariance matrix."""
    d = len(x)
    known = np.linalg.inv(np.asarray(noise_var, float)) if np.ndim(noise_var) else np.eye(d) / noise_var
    got = every_shard(complete(obs, x).groupBy("shard").agg(F.count("*").alias("n"), F.array(*[F.sum(v) for v in x]).alias("s")), shards)
    if np.ndim(noise_var):
        prec = F.array(*[F.col("n") * float(known[i, j]) + (prior_prec / shards if i == j else 0.0) for i in range(d) for j in range(d)])
    else:  # one expression for all places, however many
        prec = F.transform(F.sequence(F.lit(0), F.lit(d * d - 1)), lambda i: F.when(i % (d + 1) == 0, F.col("n") / noise_var + prior_prec / shards).otherwise(F.lit(0.0)))
    total = [F.coalesce(F.col("s")[j], F.lit(0.0)) for j in range(d)]
    used = [[j for j in range(d) if known[i, j]] for i in range(d)]
    info = F.array(*[sum((total[j] * float(known[i, j]) for j in used[i][1:]), total[used[i][0]] * float(known[i, used[i][0]])) for i in range(d)])
    return got.select("shard", "n", prec.alias("prec"), info.alias("info"))


def of_all(got: DataFrame, shards: int, by: tuple[str, ...]) -> DataFrame:
    """Counts and sums for every shard, and for every value of ``by`` that any shard has; 0 where there are no rows."""
    if by:
        names = got.select(*by).distinct()
        every = got.sparkSession.range(1, shards + 1).selectExpr("CAST(id AS int) AS shard").crossJoin(F.broadcast(names))
        alike = [F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in ("shard", *by)]
        rest = [c for c in got.columns if c not in ("shard", *by)]
        got = every.alias("a").join(got.alias("b"), reduce(Column.__and__, alike), "left").select("a.shard", *[f"a.{c}" for c in by], *[f"b.{c}" for c in rest])
        return got.fillna(0, rest)
    got = every_shard(got, shards)
    return got.fillna(0, [c for c in got.columns if c != "shard"])


def exponential_rate(obs: DataFrame, x: Column, shards: int, a: float = 1.0, b: float = 1.0, by: tuple[str, ...] = ()) -> DataFrame:
    """shape and rate of Gamma subposteriors of an exponential rate; nulls don't count."""
    got = of_all(complete(obs, [x]).groupBy("shard", *by).agg(F.count("*").alias("n"), F.sum(x).alias("s")), shards, by)
    return got.select("shard", *by, "n", (1 + (a - 1) / shards + F.col("n")).alias("shape"), (b / shards + F.col("s")).alias("rate"))


def bernoulli_share(obs: DataFrame, success: Column, shards: int, a: float = 1.0, b: float = 1.0, by: tuple[str, ...] = ()) -> DataFrame:
    """Two shapes of Beta subposteriors of a share; nulls don't count."""
    got = of_all(complete(obs, [success]).groupBy("shard", *by).agg(F.count("*").alias("n"), F.count_if(success).alias("s")), shards, by)
    return got.select("shard", *by, "n", (1 + (a - 1) / shards + F.col("s")).alias("alpha"), (1 + (b - 1) / shards + F.col("n") - F.col("s")).alias("beta"))


def poisson_rate(obs: DataFrame, count: Column, shards: int, a: float = 1.0, b: float = 1.0) -> DataFrame:
    """shape and rate of Gamma subposteriors of a Poisson mean; nulls don't count."""
    got = of_all(complete(obs, [count]).groupBy("shard").agg(F.count("*").alias("n"), F.sum(count).alias("s")), shards, ())
    return got.select("shard", "n", (1 + (a - 1) / shards + F.col("s")).alias("shape"), (b / shards + F.col("n")).alias("rate"))


def category_shares(obs: DataFrame, value: Column, shards: int, a: float = 1.0) -> DataFrame:
    """Concentrations of Dirichlet subposteriors, for every shard and every category that any shard has; null is a category."""
    got = of_all(obs.groupBy("shard", value.alias("category")).agg(F.count("*").alias("n")), shards, ("category",))
    return got.select("shard", "category", "n", (1 + (a - 1) / shards + F.col("n")).alias("alpha"))


def exact_global(sub: DataFrame, d: int) -> DataFrame:
    """prec, cov, mean of the product of Gaussian subposteriors: parameters add up, one small solve follows."""
    total = sub.agg(vector_sum(F.col("prec"), d * d).alias("prec"), vector_sum(F.col("info"), d).alias("info"))
    return total.withColumn("cov", spd_inverse("prec")).select("prec", "cov", matvec(F.col("cov"), F.col("info"), d).alias("mean"))


def exact_rate(sub: DataFrame) -> DataFrame:
    """shape, rate of the product of Gamma subposteriors: what each shape has over 1 adds up, and so do the rates."""
    return sub.agg((1 + F.sum(F.col("shape") - 1)).alias("shape"), F.sum("rate").alias("rate"))


def exact_share(sub: DataFrame) -> DataFrame:
    """alpha, beta of the product of Beta subposteriors."""
    return sub.agg((1 + F.sum(F.col("alpha") - 1)).alias("alpha"), (1 + F.sum(F.col("beta") - 1)).alias("beta"))
