"""Shards of a data set, and which worker holds which shards."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .coding import GradientCode


def validate_layout(n: int, shards: int, r: int) -> None:
    if n % shards:
        raise ValueError(f"{shards} shards don't divide {n} rows")
    if not 1 <= r <= shards:
        raise ValueError(f"redundancy {r} is outside 1 to {shards}")


def assign_shards(df: DataFrame, shards: int, order: list[str], mode: str = "exact") -> DataFrame:
    """The rows with their shard, 1 to ``shards``.

    exact: equal sizes by a total order, through one sort that is dealt by range (not one task); hash: nearly
    equal sizes without a shuffle; column: the first order column modulo the number of shards.
    """
    if mode == "hash":
        return df.withColumn("shard", (F.pmod(F.xxhash64(*order), F.lit(shards)) + 1).cast("int"))
    if mode == "column":
        return df.withColumn("shard", (F.pmod(F.col(order[0]), F.lit(shards)) + 1).cast("int"))
    if mode != "exact":
        raise ValueError(f"no such mode: {mode}")
    # range partitions keep the order; each row's rank is its place in its partition after the counts of those before
    placed = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    placed = placed.withColumn("_part", F.shiftright("_at", 33).cast("int")).persist()  # bounds of ranges are sampled: both uses must see the same
    counts = placed.groupBy("_part").agg(F.count("*").alias("_n"))
    before = counts.withColumn("_before", F.sum("_n").over(W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)))
    rank = F.coalesce("_before", F.lit(0)) + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    return placed.join(F.broadcast(before), "_part").withColumn("shard", (F.pmod(rank, F.lit(shards)) + 1).cast("int")).drop("_at", "_part", "_n", "_before")


def allocation(spark: SparkSession, scheme: str, k: int, r: int = 1, code: GradientCode | None = None, tail: str = "short") -> DataFrame:
    """scheme, worker, shard, grp, coef: a row for each shard that a worker holds."""
    if scheme == "one_shot":
        return spark.range(1, k + 1).selectExpr("'one_shot' AS scheme", "CAST(id AS int) AS worker", "CAST(id AS int) AS shard", "CAST(id AS int) AS grp", "1.0D AS coef")
    if scheme == "replica_group":
        if k % r and tail == "error":
            raise ValueError(f"groups of {r} don't divide {k} workers")
        each = spark.range(1, k + 1).selectExpr("CAST(id AS int) AS worker", f"CAST((id - 1) DIV {r} + 1 AS int) AS grp")
        return each.join(each.withColumnRenamed("worker", "shard"), "grp").selectExpr("'replica_group' AS scheme", "worker", "shard", "grp", "1.0D AS coef")
    if scheme == "coded_sum":
        code = code or GradientCode(k, r)
        return spark.createDataFrame(code.rows(), "worker int, shard int, coef double").selectExpr("'coded_sum' AS scheme", "worker", "shard", "worker AS grp", "coef")
    raise ValueError(f"no such scheme: {scheme}")


def worker_storage(sharded: DataFrame, alloc: DataFrame) -> DataFrame:
    """worker, n: rows that a worker holds; rows aren't copied, counts of shards are."""
    sizes = sharded.groupBy("shard").agg(F.count("*").alias("n"))
    return alloc.join(F.broadcast(sizes), "shard").groupBy("worker").agg(F.sum("n").alias("n"))


def shard_rows(sharded: DataFrame, alloc: DataFrame) -> DataFrame:
    """The allocation with n: the rows of each shard, 0 where it has none."""
    sizes = sharded.groupBy("shard").agg(F.count("*").alias("n"))
    return alloc.join(F.broadcast(sizes), "shard", "left").withColumn("n", F.coalesce("n", F.lit(0).cast("long")))


def salted_sum(df: DataFrame, key: str, values: list[Column], salts: int) -> DataFrame:
    """Sums by a key of few values, in two steps, so that a large shard isn't one task."""
    names = [f"v{i}" for i in range(len(values))]
    parts = df.withColumn("_salt", F.pmod(F.spark_partition_id(), F.lit(salts))).groupBy(key, "_salt").agg(*[F.sum(v).alias(n) for v, n in zip(values, names)])
    return parts.groupBy(key).agg(*[F.sum(n).alias(n) for n in names])
