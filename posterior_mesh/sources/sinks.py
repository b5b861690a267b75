"""Shards and results written once and read again by what they are keyed on."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_sharded(df: DataFrame, path: str, shards: int | None = None, table: str | None = None) -> None:
    """A folder for each shard, or, with ``table`` and ``shards``, a table in as many buckets, whose joins on shard need no shuffle.

    Partitions are evened out first (by AQE, which splits large ones), so that a large shard is several files and tasks.
    """
    df = df.hint("rebalance", "shard")
    if table:
        df.write.bucketBy(shards, "shard").sortBy("shard").mode("overwrite").option("path", path).saveAsTable(table)
    else:
        df.write.partitionBy("shard").mode("overwrite").parquet(path)


def save(df: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Draws, global draws or curves, in folders by scheme and run where they have these."""
    by = [c for c in ("scheme", "run") if c in df.columns and len(df.columns) > 2]
    (df.hint("rebalance", *by) if by else df).write.partitionBy(*by).mode(mode).parquet(path)
