"""Linear codes of the workers' sums, any r - 1 of which may be missing."""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# The pinned code of five workers with redundancy two; shard and coefficient by worker, from 1.
PINNED_5_2 = [[(1, 1.0), (2, -1.0)], [(2, 1.0), (3, -1.0)], [(3, 1.0), (4, -1.0)], [(4, 1.0), (5, 0.25)], [(5, 1.0), (1, 4.0)]]


class GradientCode:
    """``cyclic_ones`` and ``fractional`` (r divides k), ``cyclic_nullspace`` (any r), ``pinned_5_2``; default: the first that fits."""

    def __init__(self, k: int, r: int, kind: str | None = None, seed: int = 42):
        self.k, self.r = k, r
        self.kind = kind or ("pinned_5_2" if (k, r) == (5, 2) else "cyclic_ones" if k % r == 0 else "cyclic_nullspace")
        b = np.zeros((k, k))
        if self.kind in ("cyclic_ones", "fractional"):
            if k % r:
                raise ValueError(f"{self.kind} needs a redundancy that divides {k}")
            for w in range(k):
                first = w if self.kind == "cyclic_ones" else w // r * r
                b[w, [(first + i) % k for i in range(r)]] = 1
        elif self.kind == "pinned_5_2":
            if (k, r) != (5, 2):
                raise ValueError("pinned_5_2 has five workers and redundancy two")
            for w, row in enumerate(PINNED_5_2):
                for s, c in row:
                    b[w, s - 1] = c
        elif self.kind == "cyclic_nullspace":
            h = np.random.default_rng(seed).standard_normal((r - 1, k))
            if r > 1:
                h[:, -1] = -h[:, :-1].sum(axis=1)
            for w in range(k):
                held = [(w + i) % k for i in range(r)]
                b[w, held[0]] = 1
                if r > 1:
                    b[w, held[1:]] = -np.linalg.solve(h[:, held[1:]], h[:, held[0]])
        else:
            raise ValueError(f"no such code: {self.kind}")
        self.b = b

    @property
    def patterns(self) -> int:
        return math.comb(self.k, self.k - self.r + 1)

    def rows(self) -> list[tuple[int, int, float]]:
        return [(int(w) + 1, int(s) + 1, float(self.b[w, s])) for w, s in zip(*np.nonzero(self.b))]

    @lru_cache(4096)
    def decode(self, workers: tuple[int, ...]) -> dict[int, float]:
        """Coefficients by worker that turn the sums of these workers into the sum over all shards."""
        own = [w - 1 for w in workers]
        if self.kind in ("cyclic_ones", "fractional"):
            cycle = self.r if self.kind == "cyclic_ones" else None
            if cycle:
                for c in range(self.r):
                    need = set(range(c, self.k, self.r))
                    if need <= set(own):
                        return {w + 1: 1.0 for w in sorted(need)}
            else:
                first = {w // self.r: w for w in sorted(own, reverse=True)}
                if len(first) == self.k // self.r:
                    return {w + 1: 1.0 for w in sorted(first.values())}
            raise ValueError("too few workers to decode")
        a, *_ = np.linalg.lstsq(self.b[own].T, np.ones(self.k), rcond=None)
        if np.abs(a @ self.b[own] - 1).max() > 1e-6:
            raise ValueError("too few workers to decode")
        return {int(w): float(x) for w, x in zip(workers, a)}

    def survives(self, lost: set[int]) -> bool:
        try:
            self.decode(tuple(w for w in range(1, self.k + 1) if w not in lost))
        except ValueError:
            return False
        return True


def encode(processed: DataFrame, alloc: DataFrame, d: int) -> DataFrame:
    """run, worker, round, msg: coefficient-weighted sums of what a worker's shards gave; shards are drawn once, not once a holder."""
    held = processed.join(F.broadcast(alloc.select("worker", "shard", "coef")), "shard")
    return held.groupBy("run", "worker", "round").agg(F.array(*[F.sum(F.col("coef") * F.col("x")[i]) for i in range(d)]).alias("msg"))


def decode_rows(patterns: DataFrame, code: GradientCode) -> DataFrame:
    """pattern, worker, a: decoding coefficients of the patterns that occur, at most one for each round."""
    spark = patterns.sparkSession
    rows = [(p["pattern"], w, a) for p in patterns.select("pattern").distinct().toLocalIterator() for w, a in code.decode(tuple(p["pattern"])).items()]
    return spark.createDataFrame(rows, "pattern array<int>, worker int, a double")


def decode(messages: DataFrame, patterns: DataFrame, code: GradientCode, d: int) -> DataFrame:
    """run, round, phi: the sums over all shards, from the early workers' messages alone."""
    table = F.broadcast(decode_rows(patterns, code))
    used = patterns.join(table, "pattern").join(messages, ["run", "round", "worker"])
    return used.groupBy("run", "round").agg(F.array(*[F.sum(F.col("a") * F.col("msg")[i]) for i in range(d)]).alias("phi"))
