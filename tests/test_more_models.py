"""Draws that aren't Gaussian, Metropolis chains, the SQL surface, sinks and stateful streams."""

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from posterior_mesh import experiments as ex
from posterior_mesh.functions import sql
from posterior_mesh.functions.rng import beta_of, gamma_of
from posterior_mesh.operators import models
from posterior_mesh.operators.clock import ParetoClock, batch_times, ready_rounds
from posterior_mesh.operators.coding import GradientCode
from posterior_mesh.operators.draws import draws, share_draws
from posterior_mesh.operators.layout import allocation
from posterior_mesh.operators.metropolis import laplace, logistic_draws
from posterior_mesh.operators.protocols import PosteriorMesh, ProtocolSpec
from posterior_mesh.sources import sinks, virtual_cluster
from posterior_mesh.streaming import collector


def test_gamma_and_beta_have_their_moments(spark):
    for shape in (1.0, 3.5, 400.0):
        got = spark.range(20000).select(gamma_of(F.lit(shape), "id").alias("g")).agg(F.avg("g").alias("m"), F.var_samp("g").alias("v")).first()
        assert abs(got["m"] - shape) < 5 * (shape / 20000) ** 0.5
        assert abs(got["v"] / shape - 1) < 0.1
    got = spark.range(20000).select(beta_of(F.lit(2.0), F.lit(6.0), "id").alias("b")).agg(F.avg("b").alias("m"), F.min("b").alias("lo"), F.max("b").alias("hi")).first()
    assert abs(got["m"] - 0.25) < 0.005 and 0 < got["lo"] and got["hi"] < 1


def test_beta_and_share_draws(spark):
    sub = spark.createDataFrame([(1, 3.0, 9.0), (2, 30.0, 10.0)], "shard int, alpha double, beta double")
    means = {r["shard"]: r["m"] for r in draws(sub, allocation(spark, "one_shot", 2), 4000, 1).groupBy("shard").agg(F.avg(F.col("x")[0]).alias("m")).collect()}
    assert abs(means[1] - 0.25) < 0.01 and abs(means[2] - 0.75) < 0.01
    shares = share_draws(spark.createDataFrame([(1, "a", 2.0), (1, "b", 6.0)], "shard int, category string, alpha double"), 3000)
    assert shares.groupBy("round").agg(F.sum("x").alias("s")).where("abs(s - 1) > 1e-9").count() == 0
    assert abs(shares.where("category = 'a'").agg(F.avg("x")).first()[0] - 0.25) < 0.01


def logistic_rows(n=3000):
    rng = np.random.default_rng(1)
    x = np.column_stack([np.ones(n), rng.normal(size=n)])
    y = (rng.random(n) < 1 / (1 + np.exp(-x @ [0.4, -1.0]))).astype(float)
    return pd.DataFrame({"shard": (np.arange(n) % 3 + 1).astype("int32"), "x": list(x.tolist()), "y": y})


def test_logistic_chain_agrees_with_a_grid(spark):
    rows = logistic_rows()
    obs = spark.createDataFrame(rows, "shard int, x array<double>, y double")
    got = logistic_draws(obs, 2, 3, 1500).toPandas()
    assert got.groupby("shard").size().tolist() == [1500] * 3
    assert got["accepted"].mean() > 0.5
    a = np.linspace(-1, 2, 121)
    b = np.linspace(-2.5, 0.5, 121)
    for shard, own in rows.groupby("shard"):
        x, y = np.stack(own["x"]), own["y"].to_numpy()
        grid = np.array([(u, v) for u in a for v in b])
        fit = grid @ x.T
        log = (y * fit - np.logaddexp(0, fit)).sum(axis=1) - (grid**2).sum(axis=1) / 6
        w = np.exp(log - log.max())
        w /= w.sum()
        mean = w @ grid
        sd = np.sqrt(w @ grid**2 - mean**2)
        drawn = np.stack(got[got["shard"] == shard]["x"])
        assert np.all(np.abs(drawn.mean(axis=0) - mean) < 0.25 * sd)
        assert np.all(np.abs(drawn.std(axis=0) / sd - 1) < 0.2)


def test_laplace_modes_have_no_slope(spark):
    rows = logistic_rows(600)
    fit = laplace(spark.createDataFrame(rows, "shard int, x array<double>, y double"), 2, 3).collect()
    for r in fit:
        own = rows[rows["shard"] == r["shard"]]
        x, y, mode = np.stack(own["x"]), own["y"].to_numpy(), np.array(r["mode"])
        assert np.abs(x.T @ (y - 1 / (1 + np.exp(-x @ mode))) - mode / 3).max() < 1e-6


def test_last_round_weights_use_what_had_come_by_that_round(spark):
    sub = models.toeplitz_subposteriors(spark, 4)
    for scheme in ("one_shot", "replica_group"):
        late = PosteriorMesh(spark, ProtocolSpec(scheme, 4, 2, runs=2, refresh="last_round"), sub, 3.0)
        got = {(r["run"], r["round"]): r["x"] for r in late.global_draws([3.0]).collect()}
        from posterior_mesh.operators.clock import ready_at

        ready = {r["run"]: r["rounds"] for r in late.ready([3.0]).collect()}
        when = {(r["run"], r["round"]): r["ready_at"] for r in ready_at(late.clock, scheme, 4, late.r).collect()}
        now = PosteriorMesh(spark, ProtocolSpec(scheme, 4, 2, runs=2), sub, 3.0)
        for run, rounds in ready.items():
            t = when[run, rounds]
            want = {r["round"]: r["x"] for r in now.global_draws([t]).where(F.col("run") == run).collect()}
            assert sorted(want) == list(range(1, rounds + 1)) == sorted(k for u, k in got if u == run)
            assert all(np.allclose(want[k], got[run, k]) for k in want)


def test_rate_errors_shrink(spark, sf):
    got = ex.event_rate_errors(spark, sf, runs=1, grid=(5.0,)).collect()
    assert {r["scheme"] for r in got} == set(ex.SCHEMES)
    assert all(r["err"] < 0.25 for r in got if r["scheme"] != "coded_sum")


def test_sql_surface_and_data_source(spark):
    names = sql.register(spark)
    assert "latency_trace" in names
    want = {(r["worker"], r["round"]): r["done_at"] for r in batch_times(spark, 5, 2, 30).collect()}
    trace = spark.sql("SELECT * FROM latency_trace(5, 2, 0.1D, 1.2D, 30, 42)").collect()
    assert len(trace) == 150 and all(abs(want[r["worker"], r["round"]] - r["done_at"]) < 1e-9 for r in trace)
    virtual_cluster.register(spark)
    source = spark.read.format("virtual_cluster").option("workers", 5).option("redundancy", 2).option("rounds", 30).load()
    assert all(abs(want[r["worker"], r["round"]] - r["done_at"]) < 1e-9 for r in source.collect())
    assert spark.sql("SELECT count(*) FROM code_rows(5, 2, 'pinned_5_2')").first()[0] == 10
    assert spark.sql("SELECT v FROM toeplitz_cov(5, 5) WHERE shard = 3 AND i = 1 AND j = 3").first()[0] == 0.4**2
    assert spark.sql("SELECT mesh_dot(array(1D, 2D), array(3D, 4D)), mesh_relative_error(5D, 4D), mesh_relative_error(5D, 0D)").first()[:] == (11.0, 0.25, None)
    assert np.allclose(spark.sql("SELECT spd_inverse(array(2D, 0D, 0D, 4D))").first()[0], [0.5, 0, 0, 0.25])


def test_sinks(spark, tmp_path):
    df = spark.range(100).selectExpr("CAST(id % 4 + 1 AS int) AS shard", "id AS v")
    sinks.write_sharded(df, str(tmp_path / "a"))
    assert spark.read.parquet(str(tmp_path / "a")).where("shard = 2").agg(F.count("*")).first()[0] == 25
    sinks.save(spark.range(10).selectExpr("'one_shot' AS scheme", "1 AS run", "id AS round"), str(tmp_path / "b"))
    assert (tmp_path / "b" / "scheme=one_shot" / "run=1").is_dir()


def streamed(spark, tmp_path, rows, schema, make, mode):
    src = str(tmp_path / "in")
    for i in range(3):
        spark.createDataFrame(rows[i::3], schema).coalesce(1).write.mode("append").parquet(src)
    arrivals = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(src)
    got = []
    query = make(arrivals).writeStream.outputMode(mode).option("checkpointLocation", str(tmp_path / "cp")).foreachBatch(lambda df, i: got.extend(df.collect())).trigger(availableNow=True).start()
    query.awaitTermination()
    return got


def test_streamed_codes_give_each_round_once(spark, tmp_path):
    code, rng, rounds = GradientCode(5, 2), np.random.default_rng(3), 12
    x = rng.normal(size=(rounds, 5, 2))
    rows = [(1, w + 1, l + 1, (code.b[w] @ x[l]).tolist(), float(10 * l + w)) for l in range(rounds) for w in range(5) if (l + w) % 5]
    got = streamed(spark, tmp_path, rows, "run int, worker int, round int, msg array<double>, ts double", lambda a: collector.decoded_stream(a, code, ridge=0.5), "append")
    phi = x.sum(axis=1)
    assert [r["round"] for r in got] == list(range(1, rounds + 1))
    for r in got:
        own = phi[: r["round"]]
        assert np.allclose(r["x"], np.linalg.solve(0.5 * np.eye(2) + np.cov(own.T, bias=True).reshape(2, 2), own[-1]))


def test_streamed_counts_equal_those_of_a_table(spark, tmp_path):
    clock = batch_times(spark, 4, 2, 20, law=ParetoClock())
    rows = [(1, r["worker"], r["round"], r["done_at"]) for r in clock.where("done_at <= 3").collect()]
    for scheme in ex.SCHEMES:
        want = ready_rounds(clock, scheme, 4, 2, [3.0]).first()["rounds"]
        got = streamed(spark, tmp_path / scheme, rows + rows[:5], "run int, worker int, round int, ts double", lambda a: collector.ready_stream(a, scheme, 4, 2), "update")
        assert got[-1]["rounds"] == want


def test_windows_of_arrivals(spark, sf):
    from posterior_mesh.sources.tables import load

    events = load(spark, sf, "events")
    n = events.count()
    assert collector.daily_rounds(events, 5).agg(F.sum("n")).first()[0] == n
    assert collector.daily_rounds(events, 5, "1 day", "12 hours").agg(F.sum("n")).first()[0] == 2 * n
    assert collector.idle_workers(events, 5).agg(F.sum("n")).first()[0] == n
