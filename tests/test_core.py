"""Cases that were silent once: empty shards, nulls, small shapes, any clock, runs without a draw; and the core's SQL."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from posterior_mesh import core_queries
from posterior_mesh.functions.linalg import spd_inverse, spd_solve
from posterior_mesh.functions.rng import gamma_of
from posterior_mesh.operators import models
from posterior_mesh.operators.clock import ConstantClock, ExponentialClock
from posterior_mesh.operators.draws import draws
from posterior_mesh.operators.layout import allocation
from posterior_mesh.operators.protocols import BLOCK, PosteriorMesh, ProtocolSpec, prefix_moments


def test_small_shapes_have_their_moments(spark):
    for shape in (0.3, 0.9):
        got = spark.range(20000).select(gamma_of(F.lit(shape), "id").alias("g")).agg(F.avg("g").alias("m"), F.var_samp("g").alias("v"), F.min("g").alias("low")).first()
        assert abs(got["m"] - shape) < 5 * (shape / 20000) ** 0.5 and abs(got["v"] / shape - 1) < 0.15 and got["low"] >= 0


def test_empty_shards_hold_their_share_of_the_prior(spark):
    obs = spark.createDataFrame([(1, 2.0, "a"), (1, 4.0, "b"), (3, 6.0, "a")], "shard int, x double, c string")
    got = {r["shard"]: (r["n"], r["prec"], r["info"]) for r in models.gaussian_mean(obs, [F.col("x")], 3).collect()}
    assert got == {1: (2, [2 + 1 / 3], [6.0]), 2: (0, [1 / 3], [0.0]), 3: (1, [1 + 1 / 3], [6.0])}
    truth = models.exact_global(models.gaussian_mean(obs, [F.col("x")], 3), 1).first()
    assert truth["prec"][0] == pytest.approx(4) and truth["mean"][0] == pytest.approx(3)
    assert models.category_shares(obs, F.col("c"), 3).count() == 6
    for sub, d in ((models.gaussian_mean(obs, [F.col("x")], 3), 1), (models.exponential_rate(obs, F.col("x"), 3), 1), (models.bernoulli_share(obs, F.col("c") == "a", 3), 1)):
        assert draws(sub, allocation(spark, "one_shot", 3), 2, d).where("x[0] IS NOT NULL AND NOT isnan(x[0])").count() == 6


def test_means_with_a_covariance(spark):
    obs, noise = spark.createDataFrame([(1, 1.0, 2.0), (1, 3.0, 1.0), (2, 0.0, 1.0)], "shard int, a double, b double"), [[2.0, 0.5], [0.5, 1.0]]
    got = {r["shard"]: r for r in models.gaussian_mean(obs, [F.col("a"), F.col("b")], 2, noise).collect()}
    assert np.allclose(got[1]["prec"], (2 * np.linalg.inv(noise) + np.eye(2) / 2).ravel()) and np.allclose(got[1]["info"], np.linalg.inv(noise) @ [4.0, 3.0])
    assert models.exact_global(models.gaussian_mean(obs, [F.col("a"), F.col("b")], 2), 2).first()["mean"] is not None


def test_rows_with_nulls_count_nowhere(spark):
    obs = spark.createDataFrame([(1, 1.0, 2.0), (1, None, 5.0), (1, 2.0, None)], "shard int, x double, y double")
    got = models.linear_subposteriors(obs, [F.col("x")], F.col("y"), 1).first()
    assert (got["n"], got["prec"], got["info"]) == (1, [2.0], [2.0])
    assert models.dropped_rows(obs, [F.col("x"), F.col("y")]).first()[:] == (1, 3, 2)


@pytest.mark.parametrize("law", [ExponentialClock(), ExponentialClock(shift=0.5), ConstantClock()])
def test_any_clock_covers_its_horizon(spark, law):
    for scheme in ("one_shot", "replica_group", "coded_sum"):
        mesh = PosteriorMesh(spark, ProtocolSpec(scheme, 4, 2, d=1, runs=3, law=law), models.toeplitz_subposteriors(spark, 4, 1), 3.0)
        most = mesh.clock.groupBy("run", "worker").agg(F.max("round").alias("n")).agg(F.max("n")).first()[0]
        assert most < law.rounds_needed(3.0, mesh.r) or isinstance(law, ConstantClock) or law.shift
        assert mesh.global_draws([3.0]).count() > 0


def test_runs_without_a_draw_are_counted(spark):
    mesh = PosteriorMesh(spark, ProtocolSpec("one_shot", 5, d=1, runs=4), models.toeplitz_subposteriors(spark, 5, 1), 1.0)
    rows = mesh.errors([0.02, 1.0]).collect()
    assert len(rows) == 8 and all(r["err"] is None and r["rounds"] == 0 for r in rows if r["as_of"] == 0.02)
    assert {r["as_of"]: (r["runs"], r["runs_without"]) for r in mesh.curve([0.02, 1.0]).collect()}[0.02] == (4, 4)


def test_running_sums_pass_the_ends_of_blocks(spark):
    n = BLOCK * 2 + 7
    rows = spark.range(1, n + 1).selectExpr("1 AS run", "CAST(id AS int) AS round", "array(sin(id), cos(id)) AS phi")
    got = prefix_moments(rows, 2, ("run",), "phi").orderBy("round").collect()
    x = np.array([[np.sin(i), np.cos(i)] for i in range(1, n + 1)])
    assert [r["n"] for r in got] == list(range(1, n + 1))
    assert np.allclose([r["s1"] for r in got], x.cumsum(axis=0)) and np.allclose([r["s2"] for r in got], np.einsum("ni,nj->nij", x, x).reshape(n, 4).cumsum(axis=0))


def test_coded_plans_hold_messages_and_coefficients(spark):
    mesh = PosteriorMesh(spark, ProtocolSpec("coded_sum", 5, 2, d=2), models.toeplitz_subposteriors(spark, 5, 2), 1.0)
    plan = mesh.global_draws([1.0])._jdf.queryExecution().optimizedPlan().toString()
    assert "coef" in plan and "pattern" in plan and "msg" in plan


def test_same_draws_with_other_times(spark):
    mesh = PosteriorMesh(spark, ProtocolSpec("one_shot", 3, d=1, runs=2, redraw="times"), models.toeplitz_subposteriors(spark, 3, 1), 1.0)
    assert mesh.arrivals().groupBy("shard", "round").agg(F.count_distinct("x").alias("n"), F.count_distinct("done_at").alias("t"), F.count("*").alias("c")).where("n <> 1 OR t <> c").count() == 0


def test_singular_matrices_have_an_answer(spark):
    rows = spark.createDataFrame([([1.0, 1.0, 1.0, 1.0], [2.0, 2.0]), ([2.0, 0.0, 0.0, 4.0], [2.0, 4.0])], "m array<double>, b array<double>")
    got = rows.select(spd_solve("m", "b").alias("x"), spd_inverse("m").alias("i")).collect()
    assert np.allclose(got[0]["x"], [1, 1]) and np.allclose(got[1]["x"], [1, 1]) and np.allclose(got[1]["i"], [0.5, 0, 0, 0.25])


@pytest.mark.parametrize("name", [n for n in core_queries.QUERIES if "one_shot" not in n])
def test_core_equals_sql(spark, sf, name):
    duckdb = pytest.importorskip("duckdb")
    with duckdb.connect() as db:
        for file in os.listdir(sf):
            db.execute(f"CREATE VIEW {file.split('.')[0]} AS SELECT * FROM '{sf}/{file}'")
        got = core_queries.QUERIES[name](spark, sf)
        names = sorted(got.columns)
        want = db.execute(f"SELECT {', '.join(names)} FROM ({core_queries.ORACLES[name]})").fetchall()
    tidy = lambda rows: sorted((tuple(round(v, 4) + 0.0 if isinstance(v, float) else v for v in r) for r in rows), key=repr)
    assert tidy(got.select(names).collect()) == tidy(want)
