"""Helpers that the training-data operators share."""

from __future__ import annotations

import ctypes
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import importable

#: Texts handed to numpy at once; a longer single text still goes whole.
SLICE_BYTES = 1 << 20


#: Rows of texts that travel to Python at once.
BATCH_ROWS = 2000


def ready(spark: SparkSession) -> SparkSession:
    """The session with this package importable and with batches of texts that fit a worker."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    return importable(spark)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ready(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage into the shared folder that the session names; where it names none, a temporary one, in local mode only."""
    spark = ready(df.sparkSession)
    context = spark.sparkContext
    if not context.getConf().get("spark.checkpoint.dir") and not context._jsc.sc().getCheckpointDir().isDefined():
        if not context.master.startswith("local[") and context.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="checkpoints-"))
    return df.checkpoint(eager=True)


def forget(*frames: DataFrame) -> None:
    """Delete what ``cut`` wrote for these frames, once nothing that is still to run reads them."""
    for df in frames:
        file = df._jdf.queryExecution().analyzed().rdd().getCheckpointFile()
        if file.isDefined():
            path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(file.get())
            path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)


def held_out(doc_id: Column) -> Column:
    """The fixed test fold: crc32 of the id's text is divisible by 5; a null id is in it."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Each batch in runs of at most ``most`` text bytes, one row at least; null texts come out empty."""
    for batch in batches:
        at = batch.schema.get_field_index(column)
        text = batch.column(at)
        if text.null_count:
            batch = batch.set_column(at, column, pc.fill_null(text, b"" if pa.types.is_binary(text.type) else ""))
        ends = np.cumsum(pc.binary_length(batch.column(at)).to_numpy(zero_copy_only=False), dtype=np.int64)
        first = 0
        while first < batch.num_rows:
            before = ends[first - 1] if first else 0
            last = max(first + 1, int(np.searchsorted(ends, before + most, "right")))
            yield batch.slice(first, last - first)
            first = last


def utf8(array: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string or binary array without nulls, and the offsets of its values in them."""
    offsets = np.frombuffer(array.buffers()[1], np.int32)[array.offset : array.offset + len(array) + 1].astype(np.int64)
    data = array.buffers()[2]
    whole = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


def marks(ids: DataFrame, log2: int) -> DataFrame:
    """_bucket, _words: a bitmap of the hashes of ``ids``, in rows of 32768 bits as 512 numbers."""
    place = hashed(ids.columns[0], log2)
    bits = ids.select(place.alias("p")).groupBy(F.shiftright("p", 15).alias("_bucket")).agg(F.bitmap_construct_agg(F.col("p") % 32768).alias("_bits"))
    return bits.select("_bucket", F.expr("transform(sequence(0, 511), i -> CAST(conv(hex(substring(_bits, 8 * i + 1, 8)), 16, -10) AS BIGINT))").alias("_words"))


def hashed(column: str, log2: int) -> Column:
    return F.pmod(F.xxhash64(column), F.lit(1 << log2))


def marked(df: DataFrame, column: str, ids: DataFrame, log2: int = 23) -> DataFrame:
    """The rows with _found: whether the value may be among ``ids``; without a shuffle.

    A bitmap of hashes goes out, of 2**log2 bits whatever the input's size. Some rows pass by chance, the more the
    fuller the bitmap; an exact join follows.
    """
    p = (hashed(column, log2) % 32768).cast("int")
    # the first byte of eight is the highest of its number
    bit = F.lit(56) - F.shiftright(p, 3).bitwiseAND(F.lit(7)) * 8 + p.bitwiseAND(F.lit(7))
    held = df.withColumn("_bucket", F.shiftright(hashed(column, log2), 15)).join(F.broadcast(marks(ids, log2)), "_bucket", "left")
    found = F.coalesce(F.getbit(F.get("_words", F.shiftright(p, 6)), bit) == 1, F.lit(False))
    return held.select(*df.columns, found.alias("_found"))


def sift(df: DataFrame, column: str, ids: DataFrame, log2: int = 23) -> DataFrame:
    """The rows whose value may be among ``ids``, as ``marked`` tells."""
    return marked(df, column, ids, log2).where("_found").drop("_found")


def give_back() -> None:
    """Hand memory that nothing holds back to the system: a worker lives on beside the tasks that follow."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # glibc's alone
        trim(0)


def mix(x: np.ndarray) -> np.ndarray:
    """A fixed 64-bit finaliser (shift, multiply), in place where it can."""
    x = x ^ (x >> np.uint64(32))
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xA0761D6478BD642F)
    x ^= x >> np.uint64(32)
    return x


#: Edges that a task joins at once.
EDGES = 1 << 20


def contracted(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Stars with the same components as the edges: each node but the smallest of its component, with that one."""
    nodes, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    a, b, label = at[: len(a)], at[len(a) :], np.arange(len(nodes))
    while len(a):
        low = np.minimum(label[a], label[b])
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
        apart = label[a] != label[b]
        a, b = a[apart], b[apart]
    kept = np.flatnonzero(label != np.arange(len(nodes)))
    return nodes[kept], nodes[label[kept]]


def contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For mapInArrow over (hi, lo): a task's own edges as stars, at most ``EDGES`` at a time."""

    def stars(held):
        hi, lo = (np.concatenate([b.column(k).to_numpy() for b in held]) for k in (0, 1))
        return pa.RecordBatch.from_arrays([pa.array(c) for c in contracted(hi, lo)], ["hi", "lo"])

    held, size = [], 0
    for batch in batches:
        held.append(batch)
        size += batch.num_rows
        if size >= EDGES:
            yield stars(held)
            held, size = [], 0
    if held:
        yield stars(held)


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root): each node of an edge with the smallest node it can reach.

    Tasks turn their own edges into stars. Until these are stars of the whole, a round points all larger neighbours
    of a node to the smallest node around it, then all smaller ones; a chain halves with each round. All state stays
    in the shuffle and in checkpoints. An empty input gives an empty result.
    """
    schema = "hi long, lo long"
    now = cut(edges.select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).where("hi <> lo").mapInArrow(contract, schema).repartition("hi").mapInArrow(contract, schema))
    while True:
        places = now.select(F.explode(F.array(F.struct(F.col("hi").alias("u"), F.lit(1).alias("up")), F.struct(F.col("lo").alias("u"), F.lit(0).alias("up")))).alias("x")).groupBy("x.u").agg(F.sum("x.up").alias("ups"), F.count("*").alias("n"))
        # in stars, a node that points up does so once, and none points to it
        if not places.where("ups > 0 AND n > 1").limit(1).count():
            break
        both = now.unionByName(now.select(F.col("lo").alias("hi"), F.col("hi").alias("lo"))).toDF("u", "v")
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo"))
        large = large.where("hi <> lo").distinct()
        least = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(least, "hi").select(F.explode(F.array(F.struct(F.col("hi"), F.col("m").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")))).alias("e")).select("e.*")
        before, now = now, cut(small.where("hi <> lo").distinct().repartition("lo").mapInArrow(contract, schema))
        forget(before)
    return now.select(F.col("hi").alias("node"), F.col("lo").alias("root")).unionByName(now.select(F.col("lo").alias("node"), F.col("lo").alias("root")).distinct())
