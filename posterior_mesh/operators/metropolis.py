"""Draws of shards whose subposterior has no closed form: logistic regression, by Metropolis steps.

Proposals don't depend on a chain's state, so the densities of all of a shard's proposals come out of one scan
of the rows, as partial sums; what follows in order is only a pass over these few numbers. Rows of a
shard never meet in one task, however many they are.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import vector_sum
from ..functions.rng import uniform_of
from .draws import draws
from .layout import allocation

#: Bytes of proposals that go to each task at most.
MOST_SENT = 64 << 20


def laplace(obs: DataFrame, d: int, shards: int, prior_prec: float = 1.0, steps: int = 25, tolerance: float = 1e-8) -> DataFrame:
    """shard, mode, prec, info, n: Gaussians at each shard's mode, by Newton steps. ``obs`` has shard, x (array), y (0 or 1).

    Each step is one scan that gives d + d² numbers a shard; shards are a bounded number. A shard without rows has none.
    """
    spark = obs.sparkSession
    own = obs.groupBy("shard").agg(F.count("*").alias("n")).toPandas().sort_values("shard")
    at = {int(s): np.zeros(d) for s in own["shard"]}
    prior = prior_prec / shards * np.eye(d)
    hess = dict.fromkeys(at, prior)
    for _ in range(steps):
        theta = spark.createDataFrame([(s, v.tolist()) for s, v in at.items()], "shard int, theta array<double>")
        fit = F.expr("aggregate(zip_with(x, theta, (a, b) -> a * b), 0D, (s, v) -> s + v)")
        each = obs.join(F.broadcast(theta), "shard").withColumn("p", 1 / (1 + F.exp(-fit)))
        x, w = F.col("x"), F.col("p") * (1 - F.col("p"))
        sums = each.groupBy("shard").agg(vector_sum(F.transform("x", lambda v: v * (F.col("y") - F.col("p"))), d).alias("g"), F.array(*[F.sum(w * x[i] * x[j]) for i in range(d) for j in range(d)]).alias("h")).collect()
        moved = 0.0
        for row in sums:
            s = row["shard"]
            hess[s] = np.array(row["h"]).reshape(d, d) + prior
            step = np.linalg.solve(hess[s], np.array(row["g"]) - prior @ at[s])
            at[s] = at[s] + step
            moved = max(moved, float(np.abs(step).max()))
        if moved < tolerance:
            break
    rows = [(int(s), at[int(s)].tolist(), hess[int(s)].ravel().tolist(), (hess[int(s)] @ at[int(s)]).tolist(), int(n)) for s, n in own.itertuples(index=False)]
    return spark.createDataFrame(rows, "shard int, mode array<double>, prec array<double>, info array<double>, n long")


def log_likelihoods(obs: DataFrame, proposals: dict[int, np.ndarray]) -> DataFrame:
    """shard, round, ll of every proposal (rounds by dimensions, by shard), in one scan; tasks send partial sums."""
    if sum(p.nbytes for p in proposals.values()) > MOST_SENT:
        raise ValueError("too many proposals to send; draw fewer rounds at once")
    sent = obs.sparkSession.sparkContext.broadcast(proposals)

    def run(batches):
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for shard, rows in batch.groupby("shard"):
                theta, x, y = sent.value[int(shard)], np.stack(rows["x"].to_numpy()), rows["y"].to_numpy(float)
                total = sums.setdefault(int(shard), np.zeros(len(theta)))
                for a in range(0, len(x), 512):
                    fit = x[a : a + 512] @ theta.T
                    total += (y[a : a + 512, None] * fit - np.logaddexp(0, fit)).sum(axis=0)
        for shard, total in sums.items():
            yield pd.DataFrame({"shard": np.int32(shard), "round": np.arange(1, len(total) + 1, dtype=np.int32), "ll": total})

    return obs.select("shard", "x", F.col("y").cast("double").alias("y")).mapInPandas(run, "shard int, round int, ll double").groupBy("shard", "round").agg(F.sum("ll").alias("ll"))


def logistic_draws(obs: DataFrame, d: int, shards: int, rounds: int, prior_prec: float = 1.0, widen: float = 1.3, seed: int = 42) -> DataFrame:
    """shard, round, x, accepted: a chain for each shard's subposterior, whose prior is N(0, 1/prior_prec) tempered by 1/shards.

    Proposals are of the Gaussian at the mode, ``widen`` times as wide; the first is where the chain starts.
    """
    fit = laplace(obs, d, shards, prior_prec)
    wide = fit.select("shard", F.transform("prec", lambda v: v / widen**2).alias("prec"), F.transform("info", lambda v: v / widen**2).alias("info"))
    spark = obs.sparkSession
    drawn = draws(wide, allocation(spark, "one_shot", shards), rounds, d, seed=seed).select("shard", "round", "x", uniform_of(F.lit("m"), "shard", "round", seed=seed).alias("u"))
    local = drawn.toPandas().sort_values(["shard", "round"])
    sent = {int(s): np.stack(rows["x"].to_numpy()) for s, rows in local.groupby("shard")}
    known = {int(r["shard"]): (np.array(r["mode"]), np.array(r["prec"]).reshape(d, d)) for r in fit.collect()}

    def chain(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("round")
        mode, prec = known[int(rows["shard"].iloc[0])]
        x = np.stack(rows["x"].to_numpy())
        gap = x - mode
        worth = rows["ll"].to_numpy() - prior_prec / shards / 2 * (x * x).sum(axis=1) + np.einsum("ni,ij,nj->n", gap, prec, gap) / (2 * widen**2)
        now, path, took = 0, [], []
        for i, bar in enumerate(np.log(rows["u"].to_numpy())):
            took.append(i == 0 or bar < worth[i] - worth[now])
            now = i if took[-1] else now
            path.append(now)
        return pd.DataFrame({"shard": rows["shard"].to_numpy(), "round": rows["round"].to_numpy(), "x": [x[i].tolist() for i in path], "accepted": took})

    scored = log_likelihoods(obs, sent).join(F.broadcast(spark.createDataFrame(local, "shard int, round int, x array<double>, u double")), ["shard", "round"])
    return scored.groupBy("shard").applyInPandas(chain, "shard int, round int, x array<double>, accepted boolean")
