"""Quality by co-training: a view of a text's content and a view of its page's metadata.

Each view has a logistic classifier of its own. Round by round, each is calibrated, labels the unlabelled rows that
it is surest of beyond the classes' own shares, and these go into the other view's training set; a view that tells nothing labels nothing. All unlabelled rows take part:
their features are worked out once, rounds score and fit over them in the tasks, and the driver
sees sums only. At the end both views are calibrated and combined by a logistic curve that is fitted on labelled rows which neither was
trained on.

Defined cases: null text is empty, null metadata is a value of its own, missing n_chars is the text's
length; with fewer than two classes among the labels all scores are that class's (0.5 with none);
repeated rows each give a row.
"""

from __future__ import annotations

import pickle
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, held_out, load, slices
from .models import ROWS, fit_logistic, logistic, sample_of

#: Rounds, and the share of all unlabelled rows that a view labels in a round (AT_LEAST rows, if there are so many).
ROUNDS, EACH, AT_LEAST = 5, 80 / 3000, 80
#: A view labels only rows whose odds are so many times those of the classes.
SURER = 4
#: Columns that languages and sources are hashed into, bins of a logit, steps of a fit over all rows at most.
LANGS, SOURCES, BINS, STEPS = 32, 128, 400, 8
CONTENT, META = 146, LANGS + SOURCES + 2

# Classes of bytes for the content view.
CLASSES = 12
CLASS = np.full(256, 10, np.int64)
CLASS[list(b" ")], CLASS[list(b"\n\r\t")], CLASS[list(b"abcdefghijklmnopqrstuvwxyz")], CLASS[list(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ")] = 0, 1, 2, 3
CLASS[list(b"0123456789")], CLASS[list(b".")], CLASS[list(b",;:")], CLASS[list(b"!?")], CLASS[list(b"|<>{}[]()/\\=_")], CLASS[list(b"#$%&*@^~+")] = 4, 5, 6, 7, 8, 9
CLASS[128:] = 11


def content_of(text: str) -> np.ndarray:
    """Shares of pairs of byte classes, of different words, and the mean word length."""
    raw = np.frombuffer(text.encode(), np.uint8)
    kinds = CLASS[raw]
    pairs = np.bincount(kinds[:-1] * CLASSES + kinds[1:], minlength=CLASSES * CLASSES) if len(kinds) > 1 else np.zeros(CLASSES * CLASSES)
    words = text.split()
    return np.append(np.sqrt(pairs / max(1, len(kinds) - 1)), [len({*words}) / max(1, len(words)), min(2.0, len(text) / max(1, len(words)) / 10)])


def metadata_of(lang, source, n_chars) -> np.ndarray:
    out = np.zeros(META)
    for value, first, width in ((lang, 0, LANGS), (source, LANGS, SOURCES)):
        out[first + zlib.crc32(b"\xff" if value is None else str(value).encode()) % width] = 1
    size = np.log1p(max(0, n_chars or 0))
    out[-2:] = size / 10, (size / 10) ** 2
    return out


def features(rows: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    content = np.array([content_of(t) for t in rows["text"]]).reshape(-1, CONTENT)
    sizes = [len(t) if n is None or n != n else n for n, t in zip(rows["n_chars"], rows["text"])]
    return content, np.array([metadata_of(a, b, n) for a, b, n in zip(rows["lang"], rows["source"], sizes)]).reshape(-1, META)


def logits_of(views: list[np.ndarray], models: list[np.ndarray]) -> list[np.ndarray]:
    return [x @ w[:-1] + w[-1] for x, w in zip(views, models)]


def given(views: list[np.ndarray], history: list) -> tuple[list[np.ndarray], np.ndarray]:
    """Labels that each view gets of the other in these rounds (nan: none), and which rows are free still.

    A round is the models of both views and, of each, the logits below and above which it labels.
    """
    got, free = [np.full(len(views[0]), np.nan) for _ in views], np.ones(len(views[0]), bool)
    for models, limits in history:
        taken = np.zeros(len(free), bool)
        for k, (z, (low, high)) in enumerate(zip(logits_of(views, models), limits)):
            for rows, label in ((free & (z <= low), 0.0), (free & (z >= high), 1.0)):
                got[1 - k][rows] = label
                taken |= rows
        free &= ~taken
    return got, free


def unlabelled(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """x: the features of all rows outside the test fold that have a text and no label."""

    def run(batches):
        for batch in slices(batches):
            content, meta = features(batch.to_pandas())
            x = np.column_stack([content, meta]).astype(np.float32)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([one.tobytes() for one in x], pa.binary())], ["doc_id", "x"])

    rest = docs.select("doc_id", "text", "lang", "source", "n_chars").where(F.col("text").isNotNull() & ~held_out(F.col("doc_id")))
    return rest.mapInArrow(run, "doc_id long, x binary").join(labels.select("doc_id").distinct(), "doc_id", "left_anti").select("x")


def summed(pool: DataFrame, work, size: int) -> np.ndarray:
    """The sum over all rows of what ``work`` makes of both views, in two steps, so that little reaches the driver."""

    def run(batches):
        out = np.zeros(size)
        for batch in batches:
            for first in range(0, batch.num_rows, 1000):
                x = np.frombuffer(b"".join(batch.column(0).slice(first, 1000).to_pylist()), np.float32).reshape(-1, CONTENT + META).astype(np.float64)
                out += work([x[:, :CONTENT], x[:, CONTENT:]])
        yield pa.RecordBatch.from_arrays([pa.array([out.tobytes()], pa.binary())], ["s"])

    def add(rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"s": [np.sum([np.frombuffer(s) for s in rows["s"]], axis=0).tobytes()]})

    parts = pool.mapInArrow(run, "s binary").withColumn("g", F.spark_partition_id() % 8)
    return sum((np.frombuffer(r["s"]) for r in parts.groupBy("g").applyInPandas(add, "s binary").collect()), np.zeros(size))


def sure_logits(z: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """The logits of a view below and above which, calibrated on rows it wasn't fitted on, the odds are ``SURER`` times those of the classes."""
    slope, constant = fit_logistic(np.clip(z, -15, 15)[:, None], y, 1e-3)
    prior = np.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5))
    if slope <= 0:
        return -np.inf, np.inf
    return (prior - np.log(SURER) - constant) / slope, (prior + np.log(SURER) - constant) / slope


def limits_of(pool: DataFrame, models: list, history: list, share: float, n: int, sure: list) -> tuple[list, list]:
    """For each view the logits below and above which it is surest, by counts of logits in bins, within ``sure``; and how many rows these are."""
    edges = np.linspace(-20, 20, BINS + 1)

    def count(views):
        _, free = given(views, history)
        return np.concatenate([np.bincount(np.clip(np.searchsorted(edges, z[free], "right") - 1, 0, BINS - 1), minlength=BINS) for z in logits_of(views, models)]).astype(float)

    limits, taken, most = [], [], max(AT_LEAST, EACH * n)
    for counts, (least, top) in zip(summed(pool, count, 2 * BINS).reshape(2, BINS), sure):
        low, high = np.cumsum(counts), np.cumsum(counts[::-1])
        k = max(int(np.searchsorted(low, most * (1 - share), "right")), int(np.argmax(low > 0)) + 1)
        j = max(int(np.searchsorted(high, most * share, "right")), int(np.argmax(high > 0)) + 1)
        down, up = edges[k] if k < BINS else np.inf, edges[BINS - j] if j < BINS else -np.inf
        limits.append((min(np.nextafter(down, -np.inf), least), max(up, top)))
        taken.append(int(counts[edges[1:] <= limits[-1][0] + 1e-9].sum() + counts[edges[:-1] >= limits[-1][1] - 1e-9].sum()))
    return limits, taken


def refit(pool: DataFrame, own: list, models: list, history: list, steps: int = STEPS) -> list:
    """Newton's steps for both views on their labelled rows and on all rows that the other view labelled.

    The latter weigh no more in all than the labelled ones do.
    """
    sizes = [(m + 1) * (m + 2) + 1 for m in (CONTENT, META)]

    def parts(x, y, w):
        """The loss, and the matrix and the right side of Newton's step."""
        x = np.column_stack([x, np.ones(len(x))])
        z = x @ w
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        return np.append((np.logaddexp(0, z) - y * z).sum(), np.column_stack([(x * (p * (1 - p))[:, None]).T @ x, x.T @ (y - p)]).ravel())

    tried = [w.copy() for w in models]
    best: list = [(np.inf, w.copy(), np.zeros(len(w))) for w in models]  # loss, weights, the step tried from there
    for _ in range(steps):
        now = [w.copy() for w in tried]

        def work(views, now=now):
            out = []
            for x, y, w in zip(views, given(views, history)[0], now):
                some = ~np.isnan(y)
                out += [[some.sum()], parts(x[some], y[some], w)]
            return np.concatenate(out)

        got, at, most = summed(pool, work, 2 + sum(sizes)), 0, 0.0
        for k, size in enumerate(sizes):
            n, more, w = got[at], got[at + 1 : at + 1 + size], tried[k]
            at += 1 + size
            x, y = own[k]
            weight = min(1.0, len(y) / max(1.0, n))
            hold = np.full(len(w), 1e-3 * max(1.0, len(y) + weight * n))
            hold[-1] = 1e-6
            both = parts(x, y, w) + weight * more
            loss = both[0] + (hold * w * w).sum() / 2
            if loss <= best[k][0]:
                whole = both[1:].reshape(len(w), -1)
                best[k] = loss, w, np.linalg.solve(whole[:, :-1] + np.diag(hold + 1e-9), whole[:, -1] - hold * w)
            else:  # too far
                best[k] = *best[k][:2], best[k][2] / 2
            tried[k] = best[k][1] + best[k][2]
            most = max(most, np.abs(best[k][2]).max())
        if most < 1e-3:
            return tried
    return [w for _, w, _ in best]


def co_train(content: np.ndarray, meta: np.ndarray, y: np.ndarray, pool: DataFrame, rounds: int = ROUNDS) -> dict:
    """Weights of both views, the curve that combines their logits, and how many rows each view labelled by round."""
    kept = np.arange(len(y)) % 4 == 3  # for calibration
    own = [(v[~kept], y[~kept]) for v in (content, meta)]
    share, n = y[~kept].mean(), pool.count()
    models, history, counts = [fit_logistic(x, t, 1e-3) for x, t in own], [], []
    for _ in range(rounds if n else 0):
        sure = [sure_logits(z, y[kept]) for z in logits_of([content[kept], meta[kept]], models)]
        limits, taken = limits_of(pool, models, history, share, n, sure)
        if not any(taken):
            break
        history = [*history, (models, limits)]
        counts.append(taken)
        models = refit(pool, own, models, history)
    logits = np.column_stack(logits_of([content[kept], meta[kept]], models))
    return {"models": models, "curve": fit_logistic(np.clip(logits, -15, 15), y[kept], 1e-3), "given": counts}


def fit(docs: DataFrame, labels: DataFrame, rows: int = ROWS) -> dict:
    """From at most ``rows`` labelled rows of each class outside the test fold and all unlabelled ones."""
    chosen = sample_of(docs, labels, "quality", rows)
    if chosen["label"].nunique() < 2:
        return {"constant": float(chosen["label"].iloc[0]) if len(chosen) else 0.5}
    spark = docs.sparkSession
    ids = spark.createDataFrame([(int(i),) for i in chosen["doc_id"].unique()], "doc_id long")
    about = docs.select("doc_id", "lang", "source", "n_chars").join(F.broadcast(ids), "doc_id").dropDuplicates(["doc_id"]).toPandas()
    chosen = chosen.merge(about, on="doc_id").sort_values(["doc_id", "label"], ignore_index=True)
    chosen = chosen.iloc[np.argsort([hash_key(i) for i in chosen["doc_id"]], kind="stable")].reset_index(drop=True)
    return co_train(*features(chosen), chosen["label"].to_numpy(np.float64), cut(unlabelled(docs, labels)))


def hash_key(number: int) -> int:
    return (int(number) * 0x9E3779B97F4A7C15) & 0xFFFFFFFFFFFFFFFF


def score(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, score, content_score, metadata_score."""
    raw = pickle.dumps(model)

    def run(batches):
        m = pickle.loads(raw)
        for batch in slices(batches):
            if "constant" in m:
                out = np.full((3, batch.num_rows), m["constant"])
            else:
                content, meta = features(batch.to_pandas())
                logits = logits_of([content, meta], m["models"])
                out = [logistic(np.clip(np.column_stack(logits), -15, 15), m["curve"]), *(1 / (1 + np.exp(-np.clip(v, -30, 30))) for v in logits)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(x, pa.float64()) for x in out)], ["doc_id", "score", "content_score", "metadata_score"])

    return docs.select("doc_id", "text", "lang", "source", "n_chars").mapInArrow(run, "doc_id long, score double, content_score double, metadata_score double")


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    scored = score(docs, fit(docs, load(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "content_score", "metadata_score")
