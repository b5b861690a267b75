"""Worked examples, identities and a reference in numpy."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from posterior_mesh.operators import metrics, models
from posterior_mesh.operators.clock import ParetoClock, arrival_patterns, batch_times, group_sequence, ready_at, ready_rounds
from posterior_mesh.operators.coding import GradientCode
from posterior_mesh.operators.layout import allocation, assign_shards, validate_layout
from posterior_mesh.operators.protocols import PosteriorMesh, ProtocolSpec


def clock(spark, times):
    rows = [(1, w, i, t) for w, own in times.items() for i, t in enumerate(own, 1)]
    return spark.createDataFrame(rows, "run int, worker int, round int, done_at double")


def test_timeline_of_three_workers(spark):
    c = clock(spark, {1: [1.0, 2.0, 3.5], 2: [1.5, 3.8], 3: [2.5, 4.0]})
    assert ready_rounds(c, "one_shot", 3, 1, [4.0]).first()["rounds"] == 2
    assert [r["ready_at"] for r in ready_at(c, "one_shot", 3, 1).orderBy("round").collect()] == [2.5, 4.0]
    assert [r["ready_at"] for r in ready_at(c, "coded_sum", 3, 2).orderBy("round").collect()] == [1.5, 3.8]
    assert ready_rounds(c, "coded_sum", 3, 2, [3.8]).first()["rounds"] == 2


def test_groups_take_all_batches_in_order(spark):
    c = clock(spark, {1: [1.0, 4.0], 2: [2.0], 3: [3.0, 5.0], 4: [6.0]})
    got = group_sequence(c, 2).orderBy("grp", "seq").collect()
    assert [(r["grp"], r["worker"], r["done_at"]) for r in got] == [(1, 1, 1.0), (1, 2, 2.0), (1, 1, 4.0), (2, 3, 3.0), (2, 3, 5.0), (2, 4, 6.0)]
    assert [r["ready_at"] for r in ready_at(c, "replica_group", 4, 2).orderBy("round").collect()] == [3.0, 5.0, 6.0]
    assert ready_rounds(c, "replica_group", 4, 2, [5.0]).first()["rounds"] == 2


def test_a_lone_worker_blocks_groups_but_not_the_code(spark):
    c = clock(spark, {1: [1.0], 2: [1.0], 3: [1.0], 4: [1.0]})
    assert ready_rounds(c, "replica_group", 5, 2, [2.0]).first()["rounds"] == 0
    assert ready_rounds(c, "coded_sum", 5, 2, [2.0]).first()["rounds"] == 1
    assert arrival_patterns(c, 5, 2).first()["pattern"] == [1, 2, 3, 4]


@pytest.mark.parametrize("k,r,kind", [(5, 2, "pinned_5_2"), (6, 2, "cyclic_ones"), (6, 3, "cyclic_ones"), (6, 3, "fractional"), (7, 3, "cyclic_nullspace"), (5, 1, "cyclic_ones")])
def test_codes_decode_every_pattern(k, r, kind):
    code = GradientCode(k, r, kind)
    assert (np.count_nonzero(code.b, axis=0) == r).all() and (np.count_nonzero(code.b, axis=1) == r).all()
    for lost in itertools.combinations(range(1, k + 1), r - 1):
        a = code.decode(tuple(w for w in range(1, k + 1) if w not in lost))
        assert np.allclose(sum(x * code.b[w - 1] for w, x in a.items()), 1)


def test_layout(spark):
    with pytest.raises(ValueError):
        validate_layout(10, 3, 1)
    sizes = assign_shards(spark.range(1000), 8, ["id"]).groupBy("shard").count().collect()
    assert sorted(r["count"] for r in sizes) == [125] * 8
    assert {(r["worker"], r["shard"]) for r in allocation(spark, "replica_group", 5, 2).collect()} == {(1, 1), (1, 2), (2, 1), (2, 2), (3, 3), (3, 4), (4, 3), (4, 4), (5, 5)}


def test_pareto_clock(spark):
    law = ParetoClock()
    assert law.scale(2) == pytest.approx(2 / 60)
    dt = np.array([r["dt"] for r in batch_times(spark, 4, 2, 2000).select("dt").collect()])
    assert dt.min() >= law.scale(2) and np.median(dt) == pytest.approx(law.scale(2) * 2 ** (1 / 1.2), rel=0.05)


def test_truth_of_five_shards(spark):
    cov = np.array(models.exact_global(models.toeplitz_subposteriors(spark, 5), 5).first()["cov"]).reshape(5, 5)
    assert np.allclose(cov[0], [0.172192, 0.079057, 0.036435, 0.017095, 0.008679], atol=1e-6)
    assert np.trace(cov) == pytest.approx(0.808802, abs=1e-6)


def collected(mesh):
    came = {}
    for r in mesh.draws.collect():
        came[r["worker"], r["shard"], r["round"]] = np.array(r["x"])
    return came, {(r["worker"], r["round"]): r["done_at"] for r in mesh.clock.collect()}


def test_one_shot_against_numpy(spark):
    mesh = PosteriorMesh(spark, ProtocolSpec("one_shot", 3, d=2), models.toeplitz_subposteriors(spark, 3, 2), 1.0)
    x, done = collected(mesh)
    own = {k: [x[k, k, l] for l in range(1, 100) if done.get((k, l), 9) <= 1.0] for k in (1, 2, 3)}
    p = {k: np.linalg.inv(1e-3 * np.eye(2) + np.cov(np.array(v).T, bias=True)) for k, v in own.items()}
    total = np.linalg.inv(sum(p.values()))
    want = [total @ sum(p[k] @ own[k][l] for k in own) for l in range(min(map(len, own.values())))]
    got = [r["x"] for r in mesh.global_draws([1.0]).orderBy("round").collect()]
    assert np.allclose(got, want)


def test_redundancy_one_is_the_baseline(spark):
    sub = models.toeplitz_subposteriors(spark, 3, 2)
    one, grouped = (PosteriorMesh(spark, ProtocolSpec(s, 3, 1, d=2), sub, 1.0).global_draws([1.0]).orderBy("round").collect() for s in ("one_shot", "replica_group"))
    assert np.allclose([r["x"] for r in one], [r["x"] for r in grouped])


def test_decoding_gives_the_direct_sum_and_literal_start(spark):
    mesh = PosteriorMesh(spark, ProtocolSpec("coded_sum", 5, 2, d=2, ridge=0.5), models.toeplitz_subposteriors(spark, 5, 2), 1.0)
    audited, direct = ({r["round"]: r["phi"] for r in sums.collect()} for sums in (mesh.decoded(), mesh.direct_sums()))
    assert audited.keys() <= direct.keys() and len(audited) > 3
    assert all(np.allclose(v, direct[k]) for k, v in audited.items())
    x, _ = collected(mesh)
    first = mesh.global_draws([1.0]).where(F.col("round") == 1).first()["x"]
    assert np.allclose(first, sum(x[0, s, 1] for s in range(1, 6)) / 0.25)


def test_errors_and_resilience(spark):
    sub = models.toeplitz_subposteriors(spark, 1, 1)
    made = spark.createDataFrame([(1, 1.0, 1, [1.0]), (1, 1.0, 2, [3.0])], "run int, as_of double, round int, x array<double>")
    assert metrics.second_moment_errors(made, sub, 1).first()["err"] == pytest.approx(4.0)
    assert [metrics.resilience(s, 40, 4) for s in ("one_shot", "replica_group", "coded_sum")] == [0, 30, 3]
    assert metrics.resilience("replica_group", 5, 2, worst=True) == 0 and not metrics.survives("replica_group", 5, 2, {5}) and metrics.survives("coded_sum", 5, 2, {5})


def test_stream_equals_batch(spark, sf, tmp_path):
    from posterior_mesh.streaming.server import read_arrivals, run_to_table, worker_moments

    events = spark.read.parquet(f"{sf}/events.parquet").select("ts", "user_id", "value")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    run_to_table(read_arrivals(spark, str(tmp_path / "in"), "ts timestamp_ntz, user_id long, value double"), 5, "arrived", str(tmp_path / "state"))
    got = {r["worker"]: (r["n"], round(r["s1"], 6)) for r in spark.table("arrived").collect()}
    assert got == {r["worker"]: (r["n"], round(r["s1"], 6)) for r in worker_moments(events, 5).collect()}
