"""The collector as a streaming job: counts and moments of what has arrived, and rounds that become ready.

State is a row for each worker or shard, bounded by their number; the batch answer over the same rows is equal.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_arrivals(spark: SparkSession, path: str, schema, max_files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def worker_moments(arrivals: DataFrame, k: int, delay: str = "1 hour") -> DataFrame:
    """worker, n, s1, s2, last: late draws count too, as grouped workers' do; for update or complete mode."""
    timed = arrivals.withColumn("ts", F.col("ts").cast("timestamp"))
    if arrivals.isStreaming:
        timed = timed.withWatermark("ts", delay)
    worker = (F.pmod("user_id", F.lit(k)) + 1).cast("int")
    return timed.groupBy(worker.alias("worker")).agg(F.count("*").alias("n"), F.sum("value").alias("s1"), F.sum(F.col("value") * F.col("value")).alias("s2"), F.max("ts").alias("last"))


def rounds_of(moments: DataFrame, scheme: str, k: int, r: int) -> DataFrame:
    """rounds: how many global draws the counts allow; a static frame, as in foreachBatch."""
    each = moments.select("worker", "n")
    if scheme == "replica_group":
        groups = each.groupBy(F.expr(f"CAST((worker - 1) DIV {r} AS int)").alias("g")).agg(F.sum("n").alias("n"))
        return groups.agg(F.when(F.count("*") == -(-k // r), F.min("n")).otherwise(0).alias("rounds"))
    if scheme == "coded_sum":
        return each.agg(F.when(F.count("*") >= k - r + 1, F.get(F.sort_array(F.collect_list("n"), asc=False), F.lit(k - r))).otherwise(0).alias("rounds"))
    return each.agg(F.when(F.count("*") == k, F.min("n")).otherwise(0).alias("rounds"))


def run_to_table(arrivals: DataFrame, k: int, name: str, checkpoint: str | None = None):
    """All there is, into an in-memory table of a row for each worker; returns the query when it has ended. Without a folder, Spark chooses one."""
    writer = worker_moments(arrivals, k).writeStream.outputMode("complete").format("memory").queryName(name).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    return query
