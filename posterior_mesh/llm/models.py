"""Small models that several operators train: bounded samples of labelled rows and logistic regression."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import held_out

#: Bounds of a fitting sample: rows of each class, and characters of all texts of a class together.
ROWS, CHARS = 1500, 8_000_000


def sample_of(docs: DataFrame, labels: DataFrame, label: str, rows: int = ROWS, chars: int = CHARS) -> pd.DataFrame:
    """doc_id, text, label: a fixed sample of the rows outside the test fold, at most so many of each class.

    The smallest hashes of ids are taken, so a sample doesn't depend on partitions. Where the texts of a class have
    more than ``chars`` characters, its longest are left out, whole. Null texts and labels are left out; rows that
    repeat count once. Classes may be as many as there are.
    """
    known = labels.select("doc_id", F.col(label).alias("label")).where("doc_id IS NOT NULL AND label IS NOT NULL").where(~held_out(F.col("doc_id"))).distinct()
    # the limit of ranks reaches the tasks before the shuffle, so a frequent class isn't sorted in one
    rank = F.row_number().over(W.partitionBy("label").orderBy(F.xxhash64("doc_id"), "doc_id"))
    picked = known.withColumn("rank", rank).where(F.col("rank") <= rows).drop("rank")
    texts = docs.select("doc_id", "text").where("text IS NOT NULL")
    got = texts.join(F.broadcast(picked), "doc_id").dropDuplicates(["doc_id", "label"])
    so_far = F.sum(F.length("text").cast("long")).over(W.partitionBy("label").orderBy(F.length("text"), F.xxhash64("doc_id"), "doc_id").rowsBetween(W.unboundedPreceding, 0))
    got = got.withColumn("so_far", so_far).where(F.col("so_far") <= chars).drop("so_far").toPandas()
    return got.sort_values(["doc_id", "label"], ignore_index=True)


def apart(texts: list[str]) -> np.ndarray:
    """Which texts aren't near copies of one before: none of three smallest hashes of five-word runs is shared."""
    seen: list[set] = [set(), set(), set()]
    keep = np.zeros(len(texts), bool)
    for i, text in enumerate(texts):
        words = text.lower().split()
        runs = {hash_of(" ".join(words[k : k + 5])) for k in range(max(1, len(words) - 4))}
        low = [min((h * m) & 0xFFFFFFFFFFFF for h in runs) for m in (0x9E3779B97F4B, 0xC2B2AE3D27D5, 0x165667B19E37)]
        keep[i] = not any(x in s for x, s in zip(low, seen))
        for x, s in zip(low, seen):
            s.add(x)
    return keep


def hash_of(text: str) -> int:
    import zlib

    raw = text.encode()
    return zlib.crc32(raw) << 16 | zlib.adler32(raw) & 0xFFFF


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, weights: np.ndarray | None = None, steps: int = 30) -> np.ndarray:
    """Weights, the last for the constant, by Newton's method; the constant isn't held back."""
    x = np.column_stack([x, np.ones(len(x))])
    w = np.zeros(x.shape[1])
    own = np.ones(len(x)) if weights is None else weights
    hold = np.full(x.shape[1], ridge * max(1.0, own.sum()))
    hold[-1] = 1e-6
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (own * p * (1 - p))[:, None]).T @ x + np.diag(hold + 1e-9), x.T @ (own * (y - p)) - hold * w)
        w += step
        if np.abs(step).max() < 1e-7:
            break
    return w


def logistic(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x @ w[:-1] + w[-1], -30, 30)))
