"""Language identification: multinomial naive Bayes over hashed n-grams of characters.

Letters are lower-cased and everything else is a space; the 1- to 3-grams of the resulting line are
hashed into ``BUCKETS`` columns of a matrix of log probabilities, which is broadcast. A batch is
scored in numpy: the columns of its n-grams are summed by text.

Defined cases: null texts and texts without a letter are ``und`` with score 0; ties go to the first
language by name; without a training row all texts are ``und``; repeated rows each give a row.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import held_out, load, mix, slices
from .models import sample_of

BUCKETS, ORDERS = 1 << 15, (1, 2, 3)
#: Rows of each language that the model is fitted on at most.
ROWS = 1000
NO_LETTERS = re.compile(r"[\W\d_]+")


def grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Buckets of all n-grams, order by order; the text of each; and whether a text has a letter."""
    lines = [NO_LETTERS.sub(" ", t.lower()) for t in texts]
    points = np.frombuffer("".join(f" {line} " for line in lines).encode("utf-32-le"), np.uint32)
    lengths = np.array([len(line) + 2 for line in lines])
    owner = np.repeat(np.arange(len(lines), dtype=np.int32), lengths)
    letters = np.array([bool(line.strip()) for line in lines], bool)
    buckets, owners = [], []
    wide = points.astype(np.uint64)
    for n in ORDERS:
        code = wide[: len(wide) - n + 1] + np.uint64(n << 40)
        keep = owner[: len(code)] == owner[n - 1 :]
        for k in range(1, n):
            code = code * np.uint64(0x2545F4914F6CDD1D) + wide[k : len(wide) - n + 1 + k]
        keep &= wide[(n - 1) // 2 : len(wide) - n + 1 + (n - 1) // 2] != 32  # its middle is a letter
        buckets.append((mix(code[keep]) & np.uint64(BUCKETS - 1)).astype(np.int32))
        owners.append(owner[: len(keep)][keep])
    return np.concatenate(buckets), np.concatenate(owners), letters


def fit(docs: DataFrame, rows: int = ROWS) -> dict:
    """langs and the matrix of log probabilities, from at most ``rows`` texts of each language outside the test fold."""
    known = sample_of(docs, docs.select("doc_id", "lang"), "lang", rows)
    langs = sorted(known["label"].unique().tolist())
    counts = np.full((BUCKETS, max(1, len(langs))), 0.1)
    for k, lang in enumerate(langs):
        texts = known.loc[known["label"] == lang, "text"].tolist()
        for at in range(0, len(texts), 500):
            counts[:, k] += np.bincount(grams(texts[at : at + 500])[0], minlength=BUCKETS)
    share = np.log(np.bincount(known["label"].map(langs.index).to_numpy(np.int64), minlength=max(1, len(langs))) + 1.0) if langs else np.zeros(1)
    return {"langs": langs, "matrix": np.log(counts / counts.sum(axis=0)).astype(np.float32), "prior": share}


def predict(texts: list[str], model: dict) -> tuple[list[str], np.ndarray]:
    bucket, owner, letters = grams(texts)
    langs, matrix = model["langs"], model["matrix"]
    if not langs:
        return ["und"] * len(texts), np.zeros(len(texts))
    sums = np.tile(model["prior"], (len(texts), 1))
    for k in range(len(langs)):
        sums[:, k] += np.bincount(owner, matrix[bucket, k], len(texts))
    best = sums.argmax(axis=1)
    score = 1 / np.exp(np.clip(sums - sums.max(axis=1, keepdims=True), -700, 0)).sum(axis=1)
    return [langs[b] if has else "und" for b, has in zip(best, letters)], np.where(letters, score, 0.0)




def identify(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, lang_pred, score: a row for each row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in slices(batches, most=1 << 20):
            lang, score = predict(batch.column(1).to_pylist(), sent.value)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lang, pa.string()), pa.array(score, pa.float64())], ["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, lang_pred string, score double")


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return identify(docs, fit(docs)).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
