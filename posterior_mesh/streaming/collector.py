"""The three collectors as stateful streams: arrivals in, global draws or round counts out.

Key is the run. A run's state is bounded by its workers and shards: sums, and messages of rounds that aren't
complete. Draws are numbered by their worker's own rounds; a resent one (same worker and round) is ignored.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.coding import GradientCode


def decoded_stream(messages: DataFrame, code: GradientCode, ridge: float = 1e-3, warmup: int = 0) -> DataFrame:
    """run, round, x of the coded protocol, appended once each, in the order of rounds. ``messages``: run, worker, round, msg, ts.

    A round is decoded from its first k - r + 1 messages by ts, then by worker, as they come; later ones are dropped.
    """
    need = code.k - code.r + 1

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState):
        known = pickle.loads(state.get[0]) if state.exists else {"open": {}, "ready": {}, "next": 1, "n": 0, "s1": 0.0, "s2": 0.0}
        rows = pd.concat(list(frames)).sort_values(["ts", "worker", "round"])
        for worker, k, msg in zip(rows["worker"], rows["round"], rows["msg"]):
            if k < known["next"] or k in known["ready"]:
                continue
            held = known["open"].setdefault(int(k), {})
            held.setdefault(int(worker), np.asarray(msg, float))
            if len(held) == need:
                own = known["open"].pop(int(k))
                known["ready"][int(k)] = sum(a * own[w] for w, a in code.decode(tuple(sorted(own))).items())
        out = []
        while known["next"] in known["ready"]:
            phi = known["ready"].pop(known["next"])
            if known["next"] > warmup:
                known["n"], known["s1"], known["s2"] = known["n"] + 1, known["s1"] + phi, known["s2"] + np.outer(phi, phi)
                mean = known["s1"] / known["n"]
                total = ridge * np.eye(len(phi)) + known["s2"] / known["n"] - np.outer(mean, mean)
                out.append((key[0], known["next"], np.linalg.solve(total, phi).tolist()))
            known["next"] += 1
        state.update((pickle.dumps(known),))
        yield pd.DataFrame(out, columns=["run", "round", "x"])

    return messages.groupBy("run").applyInPandasWithState(step, "run int, round int, x array<double>", "held binary", "append", GroupStateTimeout.NoTimeout)


def ready_stream(batches: DataFrame, scheme: str, k: int, r: int) -> DataFrame:
    """run, rounds, blocked_by: global draws that can be made, and the worker or group that holds up the next, after each trigger.

    ``batches``: run, worker, round, ts, a row for each finished batch; late ones count.
    """
    if scheme not in ("one_shot", "replica_group", "coded_sum"):
        raise ValueError(f"no such scheme: {scheme}")
    size = r if scheme == "replica_group" else 1

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState):
        # for each worker: rounds up to which all came, and those beyond
        known = pickle.loads(state.get[0]) if state.exists else {w: (0, set()) for w in range(1, k + 1)}
        for rows in frames:
            for worker, round_ in zip(rows["worker"], rows["round"]):
                upto, beyond = known[int(worker)]
                if round_ > upto:
                    beyond.add(int(round_))
                while upto + 1 in beyond:
                    upto += 1
                    beyond.discard(upto)
                known[int(worker)] = upto, beyond
        counts = [0] * -(-k // size)
        for w, (upto, beyond) in known.items():
            counts[(w - 1) // size] += upto + len(beyond)
        order = sorted(range(len(counts)), key=lambda i: (counts[i], i))
        at = order[r - 1 if scheme == "coded_sum" else 0]
        state.update((pickle.dumps(known),))
        yield pd.DataFrame({"run": [key[0]], "rounds": [counts[at]], "blocked_by": [at + 1]})

    return batches.groupBy("run").applyInPandasWithState(step, "run int, rounds long, blocked_by int", "held binary", "update", GroupStateTimeout.NoTimeout)


def idle_workers(arrivals: DataFrame, k: int, gap: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    """worker, begun, ended, n: spans in which a worker sends without a pause of ``gap``; append mode."""
    timed = arrivals.withColumn("ts", F.col("ts").cast("timestamp"))
    timed = timed.withWatermark("ts", delay) if arrivals.isStreaming else timed
    worker = (F.pmod("user_id", F.lit(k)) + 1).cast("int").alias("worker")
    each = timed.groupBy(worker, F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n"))
    return each.select("worker", F.col("s.start").alias("begun"), F.col("s.end").alias("ended"), "n")


def daily_rounds(arrivals: DataFrame, k: int, width: str = "1 day", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """worker, begun, n, mean: batches in windows of time, tumbling or, with ``slide``, overlapping; append or update mode."""
    timed = arrivals.withColumn("ts", F.col("ts").cast("timestamp"))
    timed = timed.withWatermark("ts", delay) if arrivals.isStreaming else timed
    worker = (F.pmod("user_id", F.lit(k)) + 1).cast("int").alias("worker")
    each = timed.groupBy(worker, (F.window("ts", width, slide) if slide else F.window("ts", width)).alias("w")).agg(F.count("*").alias("n"), F.avg("value").alias("mean"))
    return each.select("worker", F.col("w.start").alias("begun"), "n", "mean")
