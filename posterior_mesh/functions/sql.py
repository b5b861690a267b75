"""The library for users of SQL: functions on arrays and tables that are generated, by name."""

from __future__ import annotations

import hashlib

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..operators.clock import ParetoClock
from ..operators.coding import GradientCode
from .linalg import cholesky, spd_inverse, spd_solve


def uniform(*keys, seed: int = 42) -> float:
    """As ``rng.uniform_of``, on the spot."""
    text = "|".join(str(k) for k in (seed, *keys))
    return (int(hashlib.md5(text.encode()).hexdigest()[:13], 16) + 0.5) / (1 << 52)


def worker_times(run: int, worker: int, r: int, rounds: int, law: ParetoClock, seed: int):
    """(run, worker, round, dt, done_at) of one worker, in order."""
    done = 0.0
    for k in range(1, rounds + 1):
        dt = law.scale(1.0) * r * uniform("t", run, worker, k, seed=seed) ** (-1 / law.tail)
        done += dt
        yield run, worker, k, dt, done


@udtf(returnType="worker int, round int, dt double, done_at double")
class LatencyTrace:
    def eval(self, k: int, r: int, eta: float, beta: float, rounds: int, seed: int):
        for worker in range(1, k + 1):
            for _, *row in worker_times(1, worker, r, rounds, ParetoClock(float(eta), float(beta)), seed):
                yield tuple(row)


@udtf(returnType="worker int, shard int, coef double")
class CodeRows:
    def eval(self, k: int, r: int, kind: str):
        yield from GradientCode(k, r, kind or None).rows()


@udtf(returnType="shard int, i int, j int, v double")
class ToeplitzCov:
    def eval(self, k: int, d: int):
        for s in range(1, k + 1):
            for i in range(1, d + 1):
                for j in range(1, d + 1):
                    yield s, i, j, ((s - 1) / k) ** abs(i - j)


SCALARS = {
    "mesh_uniform": ("key STRING", "DOUBLE", "(CAST(conv(substr(md5(key), 1, 13), 16, 10) AS BIGINT) + 0.5D) / 4503599627370496D"),
    "mesh_dot": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)"),
    "mesh_pareto_time": ("u DOUBLE, r DOUBLE, eta DOUBLE, beta DOUBLE", "DOUBLE", "eta * r * (beta - 1) / beta * pow(u, -1 / beta)"),
    "mesh_relative_error": ("got DOUBLE, truth DOUBLE", "DOUBLE", "try_divide(abs(got - truth), truth)"),
}


def register(spark: SparkSession) -> list[str]:
    """Names of the functions that SQL has from now on, in this session only."""
    for name, (takes, gives, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({takes}) RETURNS {gives} RETURN {body}")
    solvers = {"spd_inverse": spd_inverse, "spd_solve": spd_solve, "cholesky": cholesky}
    tables = {"latency_trace": LatencyTrace, "code_rows": CodeRows, "toeplitz_cov": ToeplitzCov}
    for name, f in solvers.items():
        spark.udf.register(name, f)
    for name, f in tables.items():
        spark.udtf.register(name, f)
    return [*SCALARS, *solvers, *tables]
