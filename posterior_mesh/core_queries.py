"""The protocols' equations, step by step in two dimensions, beside SQL that inverts its matrices by hand.

A regulariser of a half keeps early weights of the size of one, so that both engines round alike.
"""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import experiments as ex
from .functions.linalg import covariance
from .functions.rng import gamma_of, gamma_sql, normal_sql, uniform_sql
from .operators import metrics, models
from .operators.clock import ConstantClock, ExponentialClock, ParetoClock, batch_times, clock_check, mean_batch_time, ready_rounds, timeline
from .operators.coding import GradientCode
from .operators.protocols import PosteriorMesh, ProtocolSpec, prefix_moments, processed_draws
from .sources.tables import load

K, RIDGE, RUNS, GRID = 5, 0.5, 2, [1.0, 2.0]
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str):
    def take(f):
        QUERIES[name], ORACLES[name] = f, sql
        return f

    return take


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[(F.round(c, digits) + 0.0).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def spread(df: DataFrame, keys: list[str], **arrays: tuple[str, int]) -> DataFrame:
    """Each array's elements as columns of their own: name1, name2 and so on."""
    return rounded(df.select(*keys, *[F.col(c)[i].alias(f"{name}{i + 1}") for name, (c, n) in arrays.items() for i in range(n)]))


def mesh(spark: SparkSession, scheme: str, **options) -> PosteriorMesh:
    return PosteriorMesh(spark, ProtocolSpec(scheme, K, 2, d=2, runs=RUNS, ridge=RIDGE, **options), models.toeplitz_subposteriors(spark, K, 2), max(GRID))


def clock_sql(r: int, law=ParetoClock(), time: str | None = None, k: int = K) -> str:
    u = uniform_sql("'t'", "run", "worker", "round")
    time = time or f"{0.1 * 0.2 / 1.2!r} * {float(r)} * pow({u}, {-1 / 1.2!r})"
    return f"""dt AS (SELECT run, worker, round, {time} AS dt FROM (SELECT CAST(a.range AS INTEGER) AS run, CAST(b.range AS INTEGER) AS worker, CAST(c.range AS INTEGER) AS round
        FROM range(1, {RUNS + 1}) a, range(1, {k + 1}) b, range(1, {law.rounds_needed(max(GRID), r) + 1}) c)),
    clock AS (SELECT * FROM (SELECT *, sum(dt) OVER (PARTITION BY run, worker ORDER BY round ROWS UNBOUNDED PRECEDING) AS done_at FROM dt) WHERE done_at <= {max(GRID)}),
    grid AS (SELECT unnest({GRID}) AS as_of), every AS (SELECT CAST(a.range AS INTEGER) AS run, as_of FROM range(1, {RUNS + 1}) a, grid)"""


def draws_sql(source: str, *keys: str) -> str:
    return f"""SELECT *, z1 AS x1, rho * z1 + sqrt(1 - rho * rho) * z2 AS x2 FROM (SELECT *, (shard - 1) / {float(K)} AS rho, {normal_sql(*keys, '1')} AS z1, {normal_sql(*keys, '2')} AS z2 FROM {source})"""


def came_sql(scheme: str) -> str:
    """came: run, shard, round, done_at, x1, x2; ready: run, as_of, rounds."""
    if scheme == "one_shot":
        held = "held AS (SELECT run, worker, worker AS shard, round, round AS seq, done_at FROM clock)"
        counts = f"SELECT v.run, v.as_of, v.worker AS g, count(c.done_at) AS n FROM (SELECT run, as_of, CAST(range AS INTEGER) AS worker FROM every, range(1, {K + 1})) v LEFT JOIN clock c ON c.run = v.run AND c.worker = v.worker AND c.done_at <= v.as_of GROUP BY ALL"
    else:
        held = f"""ranked AS (SELECT *, row_number() OVER (PARTITION BY run, (worker - 1) // 2 ORDER BY done_at, worker, round) AS seq FROM clock),
    held AS (SELECT run, worker, CAST(s.range AS INTEGER) AS shard, round, seq, done_at FROM ranked JOIN range(1, {K + 1}) s ON (worker - 1) // 2 = (s.range - 1) // 2)"""
        counts = f"SELECT v.run, v.as_of, (v.worker - 1) // 2 AS g, count(c.done_at) AS n FROM (SELECT run, as_of, CAST(range AS INTEGER) AS worker FROM every, range(1, {K + 1})) v LEFT JOIN clock c ON c.run = v.run AND c.worker = v.worker AND c.done_at <= v.as_of GROUP BY ALL"
    return f"""WITH {clock_sql(1 if scheme == "one_shot" else 2)}, {held}, came AS ({draws_sql('held', 'run', 'worker', 'shard', 'round')}),
    ready AS (SELECT run, as_of, min(n) AS rounds FROM ({counts}) GROUP BY ALL)"""


INVERSE = "{c22} / ({c11} * {c22} - {c12} * {c12}) AS {p}11, -{c12} / ({c11} * {c22} - {c12} * {c12}) AS {p}12, {c11} / ({c11} * {c22} - {c12} * {c12}) AS {p}22"


def inverse(c: str, p: str) -> str:
    return INVERSE.format(c11=f"{c}11", c12=f"{c}12", c22=f"{c}22", p=p)


MOMENTS = "count(*) AS n, sum(x1) AS s1, sum(x2) AS s2, sum(x1 * x1) AS s11, sum(x1 * x2) AS s12, sum(x2 * x2) AS s22"
COVARIANCE = f"s11 / n - s1 * s1 / (n * n) + {RIDGE} AS c11, s12 / n - s1 * s2 / (n * n) AS c12, s22 / n - s2 * s2 / (n * n) + {RIDGE} AS c22"
TRUTH = f"truth AS (SELECT {inverse('t', 'r')} FROM (SELECT sum(1 / (1 - rho * rho)) AS t11, sum(-rho / (1 - rho * rho)) AS t12, sum(1 / (1 - rho * rho)) AS t22 FROM (SELECT (range - 1) / {float(K)} AS rho FROM range(1, {K + 1}))))"


def weighted_sql(scheme: str) -> str:
    return f"""{came_sql(scheme)}, moments AS (SELECT run, as_of, shard, {MOMENTS} FROM came, grid WHERE done_at <= as_of GROUP BY ALL),
    covs AS (SELECT *, {COVARIANCE} FROM moments), precs AS (SELECT *, {inverse('c', 'p')} FROM covs),
    total AS (SELECT run, as_of, {inverse('t', 'v')} FROM (SELECT run, as_of, sum(p11) AS t11, sum(p12) AS t12, sum(p22) AS t22 FROM precs GROUP BY ALL)),
    sums AS (SELECT c.run, r.as_of, c.seq AS round, sum(p11 * x1 + p12 * x2) AS y1, sum(p12 * x1 + p22 * x2) AS y2 FROM came c JOIN ready r ON c.run = r.run AND c.seq <= r.rounds JOIN precs p ON p.run = c.run AND p.as_of = r.as_of AND p.shard = c.shard GROUP BY ALL),
    globals AS (SELECT s.run, s.as_of, CAST(s.round AS INTEGER) AS round, v11 * y1 + v12 * y2 AS x1, v12 * y1 + v22 * y2 AS x2 FROM sums s JOIN total t ON s.run = t.run AND s.as_of = t.as_of)"""


def errors_sql() -> str:
    return f"""{TRUTH}, means AS (SELECT run, as_of, count(*) AS rounds, avg(x1 * x1) AS m11, avg(x1 * x2) AS m12, avg(x2 * x2) AS m22 FROM globals GROUP BY ALL),
    errors AS (SELECT e.run, e.as_of, coalesce(rounds, 0) AS rounds, (abs(m11 - r11) / r11 + 2 * abs(m12 - r12) / r12 + abs(m22 - r22) / r22) / 4 AS err FROM every e CROSS JOIN truth LEFT JOIN means m ON m.run = e.run AND m.as_of = e.as_of)"""


ROUND = "round({0}, 6) + 0.0 AS {0}"


def columns(*names: str) -> str:
    return ", ".join(ROUND.format(n) for n in names)


for _scheme in ("one_shot", "replica_group"):
    _sql = weighted_sql(_scheme)
    query(f"weights_{_scheme}_d2", f"""{_sql}, w AS (SELECT p.run, p.as_of, p.shard, p11 AS p1, p12 AS p2, p12 AS p3, p22 AS p4, v11 * p11 + v12 * p12 AS w1, v11 * p12 + v12 * p22 AS w2, v12 * p11 + v22 * p12 AS w3, v12 * p12 + v22 * p22 AS w4
      FROM precs p JOIN total t ON p.run = t.run AND p.as_of = t.as_of) SELECT run, as_of, shard, {columns('p1', 'p2', 'p3', 'p4', 'w1', 'w2', 'w3', 'w4')} FROM w""")(
        lambda s, d, x=_scheme: spread(mesh(s, x).weights(GRID), ["run", "as_of", "shard"], p=("p", 4), w=("w", 4)))
    query(f"global_{_scheme}_d2", f"{_sql} SELECT run, as_of, round, {columns('x1', 'x2')} FROM globals")(lambda s, d, x=_scheme: spread(mesh(s, x).global_draws(GRID), ["run", "as_of", "round"], x=("x", 2)))
    query(f"errors_{_scheme}_d2", f"{_sql}, {errors_sql()} SELECT run, as_of, rounds, {columns('err')} FROM errors")(lambda s, d, x=_scheme: rounded(mesh(s, x).errors(GRID)))
    query(f"error_curve_{_scheme}_d2", f"""{_sql}, {errors_sql()}, c AS (SELECT as_of, avg(err) AS mean_err, coalesce(stddev_samp(err), 0) AS sd_err, avg(rounds) AS mean_rounds, count(*) AS runs, count(*) FILTER (err IS NULL) AS runs_without FROM errors GROUP BY 1),
      b AS (SELECT *, mean_err - 0.15 * sd_err AS lo, mean_err + 0.15 * sd_err AS hi FROM c) SELECT as_of, {columns('mean_err', 'sd_err', 'lo', 'hi', 'mean_rounds')}, runs, runs_without FROM b""")(lambda s, d, x=_scheme: rounded(mesh(s, x).curve(GRID)))
    query(f"moment_error_{_scheme}_d2", f"""{_sql}, e AS (SELECT run, as_of, shard, n, sqrt((pow(c11 - {RIDGE} - 1, 2) + 2 * pow(c12 - rho, 2) + pow(c22 - {RIDGE} - 1, 2)) / (2 + 2 * rho * rho)) AS cov_err FROM (SELECT *, (shard - 1) / {float(K)} AS rho FROM covs))
      SELECT run, as_of, shard, n, {columns('cov_err')} FROM e""")(lambda s, d, x=_scheme: rounded(metrics.moment_error(mesh(s, x).moments(GRID), mesh(s, x).subposteriors, 2)))

# the coded protocol: shared draws, running moments, processed draws, messages, decoded sums, totals
_code = GradientCode(K, 2)
CODE = ", ".join(f"({w}, {s}, {c})" for w, s, c in _code.rows())
DECODING = ", ".join(f"('{','.join(map(str, p))}', {w}, {a!r})" for lost in range(1, K + 1) for p in [tuple(w for w in range(1, K + 1) if w != lost)] for w, a in _code.decode(p).items())
RUNNING = "OVER (PARTITION BY {0} ORDER BY round ROWS UNBOUNDED PRECEDING)"


def running(keys: str) -> str:
    return ", ".join(f"{x} {RUNNING.format(keys)} AS {n}" for x, n in (("count(*)", "n"), ("sum(x1)", "s1"), ("sum(x2)", "s2"), ("sum(x1 * x1)", "s11"), ("sum(x1 * x2)", "s12"), ("sum(x2 * x2)", "s22")))


CODED = f"""WITH {clock_sql(2)}, early AS (SELECT * FROM clock QUALIFY row_number() OVER (PARTITION BY run, round ORDER BY done_at, worker) <= {K - 1}),
    patterns AS (SELECT run, round, string_agg(CAST(worker AS VARCHAR), ',' ORDER BY worker) AS pattern, max(done_at) AS ready_at FROM early GROUP BY ALL HAVING count(*) = {K - 1}),
    base AS (SELECT run, CAST(range AS INTEGER) AS shard, round FROM patterns, range(1, {K + 1})), came AS ({draws_sql('base', 'run', 'shard', 'round')}),
    held AS (SELECT *, {running('run, shard')} FROM came), inverted AS (SELECT *, {inverse('c', 'p')} FROM (SELECT *, {COVARIANCE} FROM held)),
    done AS (SELECT run, shard, round, p11 * x1 + p12 * x2 AS y1, p12 * x1 + p22 * x2 AS y2 FROM inverted),
    code AS (SELECT CAST(w AS INTEGER) AS worker, CAST(s AS INTEGER) AS shard, c FROM (VALUES {CODE}) t(w, s, c)),
    messages AS (SELECT run, worker, round, sum(c * y1) AS m1, sum(c * y2) AS m2 FROM done JOIN code USING (shard) GROUP BY ALL),
    decoding AS (SELECT pattern, CAST(w AS INTEGER) AS worker, a FROM (VALUES {DECODING}) t(pattern, w, a)),
    phis AS (SELECT p.run, p.round, sum(a * m1) AS x1, sum(a * m2) AS x2 FROM patterns p JOIN decoding d ON p.pattern = d.pattern JOIN messages m ON m.run = p.run AND m.round = p.round AND m.worker = d.worker GROUP BY ALL),
    totals AS (SELECT *, {COVARIANCE} FROM (SELECT *, {running('run')} FROM phis)),
    own AS (SELECT run, round, p11 * x1 + p12 * x2 AS x1, p12 * x1 + p22 * x2 AS x2 FROM (SELECT *, {inverse('c', 'p')} FROM totals)),
    globals AS (SELECT o.run, g.as_of, o.round, x1, x2 FROM own o JOIN patterns p ON o.run = p.run AND o.round = p.round JOIN grid g ON p.ready_at <= g.as_of)"""

query("prefix_moments_d2", f"{CODED} SELECT run, shard, round, n, {columns('s1', 's2', 's11', 's12', 's22')} FROM held")(
    lambda s, d: rounded(prefix_moments(mesh(s, "coded_sum").draws, 2).select("run", "shard", "round", "n", F.col("s1")[0].alias("s1"), F.col("s1")[1].alias("s2"), F.col("s2")[0].alias("s11"), F.col("s2")[1].alias("s12"), F.col("s2")[3].alias("s22"))))
query("processed_draws_d2", f"{CODED} SELECT run, shard, round, {columns('y1', 'y2')} FROM done")(lambda s, d: spread(processed_draws(mesh(s, "coded_sum").draws, mesh(s, "coded_sum").spec), ["run", "shard", "round"], y=("x", 2)))
query("encode_messages_d2", f"{CODED} SELECT run, worker, round, {columns('m1', 'm2')} FROM messages")(lambda s, d: spread(mesh(s, "coded_sum").messages(), ["run", "worker", "round"], m=("msg", 2)))
query("decode_sum_d2", f"{CODED} SELECT run, round, {columns('x1', 'x2')} FROM phis")(lambda s, d: spread(mesh(s, "coded_sum").decoded(), ["run", "round"], x=("phi", 2)))
query("phi_cov_d2", f"{CODED} SELECT run, round, {columns('c11', 'c12', 'c22')} FROM totals")(
    lambda s, d: rounded(prefix_moments(mesh(s, "coded_sum").decoded(), 2, ("run",), "phi").withColumn("c", covariance(F.col("n"), F.col("s1"), F.col("s2"), RIDGE, 2)).select("run", "round", F.col("c")[0].alias("c11"), F.col("c")[1].alias("c12"), F.col("c")[3].alias("c22"))))
query("global_coded_sum_d2", f"{CODED} SELECT run, as_of, round, {columns('x1', 'x2')} FROM globals")(lambda s, d: spread(mesh(s, "coded_sum").global_draws(GRID), ["run", "as_of", "round"], x=("x", 2)))
query("errors_coded_sum_d2", f"{CODED}, {errors_sql()} SELECT run, as_of, rounds, {columns('err')} FROM errors")(lambda s, d: rounded(mesh(s, "coded_sum").errors(GRID)))
query("precision_gap_d2", f"""{CODED}, q AS (SELECT sum(1 / (1 - rho * rho)) AS t1, sum(-rho / (1 - rho * rho)) AS t2 FROM (SELECT (range - 1) / {float(K)} AS rho FROM range(1, {K + 1}))),
  g AS (SELECT run, round, sqrt((pow(c11 - {RIDGE} - t1, 2) + 2 * pow(c12 - t2, 2) + pow(c22 - {RIDGE} - t1, 2)) / (2 * t1 * t1 + 2 * t2 * t2)) AS gap FROM totals, q) SELECT run, round, {columns('gap')} FROM g""")(
    lambda s, d: rounded(metrics.precision_gap(mesh(s, "coded_sum").decoded(), mesh(s, "coded_sum").subposteriors, 2)))

# weights that aren't of the draws, in two dimensions
query("global_weights_uniform_d2", f"{came_sql('one_shot')} SELECT c.run, r.as_of, CAST(c.seq AS INTEGER) AS round, round(avg(x1), 6) + 0.0 AS x1, round(avg(x2), 6) + 0.0 AS x2 FROM came c JOIN ready r ON c.run = r.run AND c.seq <= r.rounds GROUP BY ALL")(
    lambda s, d: spread(mesh(s, "one_shot", weights="uniform").global_draws(GRID), ["run", "as_of", "round"], x=("x", 2)))
query("global_weights_exact_d2", f"""{came_sql('one_shot')}, {TRUTH}, sums AS (SELECT c.run, r.as_of, CAST(c.seq AS INTEGER) AS round, sum((x1 - rho * x2) / (1 - rho * rho)) AS y1, sum((x2 - rho * x1) / (1 - rho * rho)) AS y2 FROM came c JOIN ready r ON c.run = r.run AND c.seq <= r.rounds GROUP BY ALL),
  g AS (SELECT run, as_of, round, r11 * y1 + r12 * y2 AS x1, r12 * y1 + r22 * y2 AS x2 FROM sums, truth) SELECT run, as_of, round, {columns('x1', 'x2')} FROM g""")(
    lambda s, d: spread(mesh(s, "one_shot", weights="exact").global_draws(GRID), ["run", "as_of", "round"], x=("x", 2)))
query("same_draws_other_times_d2", f"{came_sql('one_shot').replace(draws_sql('held', 'run', 'worker', 'shard', 'round'), draws_sql('held', '1', 'worker', 'shard', 'round'))} SELECT run, shard, round, {columns('done_at', 'x1', 'x2')} FROM came")(
    lambda s, d: spread(mesh(s, "one_shot", redraw="times").arrivals().withColumn("t", F.array("done_at")), ["run", "shard", "round"], t=("t", 1), x=("x", 2)).withColumnRenamed("t1", "done_at"))


# truth in five dimensions: the summed precision, and that its product with the covariance is the unit matrix
def truth_query(s: SparkSession, d: str, k: int) -> DataFrame:
    got, n = models.exact_global(models.toeplitz_subposteriors(s, k), 5), 5
    cells = [F.struct(F.lit(i + 1).alias("i"), F.lit(j + 1).alias("j"), F.col("prec")[i * n + j].alias("prec"), sum((F.col("prec")[i * n + m] * F.col("cov")[m * n + j] for m in range(1, n)), F.col("prec")[i * n] * F.col("cov")[j]).alias("unit")) for i in range(n) for j in range(n)]
    return rounded(got.select(F.explode(F.array(*cells)).alias("c")).select("c.*"))


for _k in (5, 40):
    query(f"exact_posterior_{_k}", f"""SELECT CAST(a.range AS INTEGER) AS i, CAST(b.range AS INTEGER) AS j, round(sum(CASE WHEN a.range = b.range THEN (CASE WHEN a.range IN (1, 5) THEN 1 ELSE 1 + rho * rho END) / (1 - rho * rho) WHEN abs(a.range - b.range) = 1 THEN -rho / (1 - rho * rho) ELSE 0 END), 6) + 0.0 AS prec,
      CAST(CASE WHEN a.range = b.range THEN 1 ELSE 0 END AS DOUBLE) AS unit FROM (SELECT (range - 1) / {float(_k)} AS rho FROM range(1, {_k + 1})) s, range(1, 6) a, range(1, 6) b GROUP BY a.range, b.range""")(partial(truth_query, k=_k))

# clocks
# gaps between a worker's events in whole seconds, of which there are few however many events, beside a law of ten minutes
GAPS = ParetoClock(unit_mean=300.0)


def event_clock_check(s: SparkSession, d: str) -> DataFrame:
    return rounded(clock_check(ex.event_clock(s, d, K).withColumn("dt", F.floor("dt").cast("double")), GAPS, 2))


query("clock_check", f"""WITH ev AS (SELECT user_id % {K} AS worker, epoch_us(ts) / 1e6 - 1704067200.0 AS done_at, event_id FROM events), dt AS (SELECT CAST(floor(done_at - coalesce(lag(done_at) OVER (PARTITION BY worker ORDER BY done_at, event_id), 0)) AS DOUBLE) AS dt FROM ev),
  law AS (SELECT CAST({GAPS.scale(2)!r} AS DOUBLE) AS s), v AS (SELECT min(dt) AS a, quantile_cont(dt, 0.5) AS b, avg(dt) AS c, {', '.join(f'avg(CASE WHEN dt > {m} * s THEN 1.0 ELSE 0 END) AS p{i}' for i, m in enumerate((1.5, 2.0, 4.0, 8.0)))} FROM dt, law)
  SELECT what, round(got, 6) + 0.0 AS got, round(law, 6) + 0.0 AS law FROM (SELECT 'least' AS what, a AS got, s AS law FROM v, law UNION ALL SELECT 'median', b, s * pow(2, 1 / 1.2) FROM v, law UNION ALL SELECT 'mean', c, 600.0 FROM v
  {' '.join(f"UNION ALL SELECT 'longer_{m:g}', p{i}, pow({m}, -1.2) FROM v" for i, m in enumerate((1.5, 2.0, 4.0, 8.0)))})""")(event_clock_check)
query("mean_batch_time", f"WITH {clock_sql(2)} SELECT run, count(*) AS n, round(avg(dt), 6) AS mean FROM dt GROUP BY 1")(lambda s, d: rounded(mean_batch_time(batch_times(s, K, 2, ParetoClock().rounds_needed(2.0, 2), RUNS))))
_u = uniform_sql("'t'", "run", "worker", "round")
for _name, _law, _time in (("exponential", ExponentialClock(), f"0.2 * (0 - ln({_u}))"), ("shifted_exponential", ExponentialClock(shift=0.25), f"0.2 * (0.25 - 0.75 * ln({_u}))"), ("constant", ConstantClock(), "0.2")):
    query(f"ready_{_name}", f"""WITH {clock_sql(2, _law, _time)} SELECT run, as_of, list_sort(list(n))[2] AS rounds FROM (SELECT v.run, v.as_of, v.worker, count(c.done_at) AS n FROM (SELECT run, as_of, CAST(range AS INTEGER) AS worker FROM every, range(1, {K + 1})) v
      LEFT JOIN clock c ON c.run = v.run AND c.worker = v.worker AND c.done_at <= v.as_of GROUP BY ALL) GROUP BY ALL""")(
        lambda s, d, law=_law: PosteriorMesh(s, ProtocolSpec("coded_sum", K, 2, d=2, runs=RUNS, law=law), models.toeplitz_subposteriors(s, K, 2), max(GRID)).ready(GRID))
_example = [(1, 1, 1, 1.0), (1, 1, 2, 2.0), (1, 1, 3, 3.5), (1, 2, 1, 1.5), (1, 2, 2, 3.8), (1, 3, 1, 2.5), (1, 3, 2, 4.0)]
query("timeline", "SELECT * FROM (VALUES (CAST(1 AS INTEGER), CAST(1 AS INTEGER), CAST(3 AS BIGINT), CAST(3.5 AS DOUBLE), false), (1, 2, 2, 3.8, true), (1, 3, 2, 4.0, true)) t(run, worker, n, ended, blocked)")(
    lambda s, d: timeline(s.createDataFrame(_example, "run int, worker int, round int, done_at double"), 3, 4.0).select("run", "worker", "n", "ended", "blocked"))
for _scheme in ("one_shot", "replica_group", "coded_sum"):
    _r = 1 if _scheme == "one_shot" else 2
    _used = f"SELECT run, count(*) AS used FROM (SELECT * FROM clock QUALIFY row_number() OVER (PARTITION BY run, round ORDER BY done_at, worker) <= {K - 1}) GROUP BY 1" if _scheme == "coded_sum" else "SELECT run, count(*) AS used FROM clock GROUP BY 1"
    query(f"utilisation_{_scheme}", f"WITH {clock_sql(_r)}, u AS ({_used}) SELECT run, computed, used FROM (SELECT run, count(*) AS computed FROM clock GROUP BY 1) JOIN u USING (run)")(
        lambda s, d, x=_scheme, r=_r: metrics.utilisation(mesh(s, x).clock, x, K, r, max(GRID)))

# sums of whole subposteriors, shards without rows, rows with nulls
XS = ["l_quantity / 10", "l_discount * 10", "l_tax * 10", "p_retailprice / 1000", "CAST(1 AS DOUBLE)"]


def linear_cells(s: SparkSession, d: str) -> DataFrame:
    from .experiments import linear_regression

    got = linear_regression(s, d).select("shard", "n", F.posexplode(F.concat("prec", "info")).alias("cell", "v"))
    return rounded(got.select("shard", "n", "cell", "v"), 3)


query("linear_cells", f"""WITH o AS (SELECT CAST(l_suppkey % 5 + 1 AS INTEGER) AS shard, [{', '.join(XS)}] AS x, l_extendedprice / 10000 AS y FROM lineitem JOIN part ON l_partkey = p_partkey),
  p AS (SELECT shard, count(*) AS n, CAST(i.range * 5 + j.range AS INTEGER) AS cell, sum(x[i.range + 1] * x[j.range + 1]) + CASE WHEN i.range = j.range THEN 0.2 ELSE 0 END AS v FROM o, range(5) i, range(5) j GROUP BY shard, i.range, j.range),
  h AS (SELECT shard, count(*) AS n, CAST(25 + i.range AS INTEGER) AS cell, sum(x[i.range + 1] * y) AS v FROM o, range(5) i GROUP BY shard, i.range)
  SELECT shard, n, cell, round(v, 3) + 0.0 AS v FROM (SELECT * FROM p UNION ALL SELECT * FROM h)""")(linear_cells)
query("embedding_cells", """WITH o AS (SELECT CAST(vec_id % 5 + 1 AS INTEGER) AS shard, embedding FROM embeddings)
  SELECT shard, count(*) AS n, CAST(i.range AS INTEGER) AS cell, round(sum(CAST(embedding[i.range + 1] AS DOUBLE)), 4) + 0.0 AS info, CAST(round(count(*) + 0.2, 6) AS DOUBLE) AS prec FROM o, range(64) i GROUP BY shard, i.range""")(
    lambda s, d: rounded(models.gaussian_mean(load(s, d, "embeddings").withColumn("shard", (F.pmod("vec_id", F.lit(5)) + 1).cast("int")), [F.col("embedding")[i].cast("double") for i in range(64)], 5)
                         .select("shard", "n", F.posexplode("info").alias("cell", "info"), "prec").select("shard", "n", "cell", "info", F.col("prec")[F.col("cell") * 65].alias("prec")), 4))
query("shards_without_rows", "SELECT CAST(s.range AS INTEGER) AS shard, count(n_nationkey) AS n, CAST(round(count(n_nationkey) + 0.125, 6) AS DOUBLE) AS prec, round(CAST(coalesce(sum(n_nationkey), 0) AS DOUBLE), 6) AS info FROM range(1, 9) s LEFT JOIN nation ON n_regionkey + 1 = s.range GROUP BY s.range")(
    lambda s, d: rounded(models.gaussian_mean(load(s, d, "nation").withColumn("shard", (F.col("n_regionkey") + 1).cast("int")), [F.col("n_nationkey").cast("double")], 8).select("shard", "n", F.col("prec")[0].alias("prec"), F.col("info")[0].alias("info"))))
query("rows_with_nulls", """WITH o AS (SELECT CAST(o_custkey % 5 + 1 AS INTEGER) AS shard, nullif(o_totalprice, 0) AS y, CASE WHEN o_orderkey % 7 = 0 THEN NULL ELSE 1.0 END AS x FROM orders)
  SELECT shard, count(*) FILTER (x IS NOT NULL AND y IS NOT NULL) AS n, round(CAST(count(*) FILTER (x IS NOT NULL AND y IS NOT NULL) AS DOUBLE) + 0.2, 4) AS prec, round(sum(x * y) / 1000, 4) AS info, count(*) FILTER (x IS NULL OR y IS NULL) AS dropped FROM o GROUP BY 1""")(
    lambda s, d: null_rows(s, d))


def null_rows(s: SparkSession, d: str) -> DataFrame:
    obs = load(s, d, "orders").select((F.pmod("o_custkey", F.lit(5)) + 1).cast("int").alias("shard"), F.nullif("o_totalprice", F.lit(0.0)).alias("y"), F.when(F.col("o_orderkey") % 7 != 0, 1.0).alias("x"))
    got = models.linear_subposteriors(obs, [F.col("x")], F.col("y") / 1000, 5)
    lost = models.dropped_rows(obs, [F.col("x"), F.col("y")]).select("shard", "dropped")
    return rounded(got.join(lost, "shard").select("shard", "n", F.col("prec")[0].alias("prec"), F.col("info")[0].alias("info"), "dropped"), 4)


query("small_shape_draws", f"WITH g AS (SELECT range AS id, 0.3 + 0.1 * (range % 5) AS a FROM range(0, 300)) SELECT id, round(" + gamma_sql("a", "id") + ", 6) AS g FROM g")(
    lambda s, d: s.range(300).select("id", F.round(gamma_of(F.lit(0.3) + F.lit(0.1) * (F.col("id") % 5), "id"), 6).alias("g")))
for _table, _id, _text in (("pages", "page_id", "html"), ("benchmark", "item_id", "text"), ("documents", "doc_id", "text")):
    query(f"{_table}_lengths", f"SELECT CAST({_id} % 5 + 1 AS INTEGER) AS shard, count({_text}) AS n, CAST(round(count({_text}) + 0.2, 4) AS DOUBLE) AS prec, round(sum(ln(1 + length({_text}))), 4) AS info FROM {_table} WHERE {_text} IS NOT NULL GROUP BY 1")(
        lambda s, d, t=_table, i=_id, x=_text: rounded(models.gaussian_mean(load(s, d, t).withColumn("shard", (F.pmod(i, F.lit(5)) + 1).cast("int")), [F.ln(1 + F.length(x))], 5).select("shard", "n", F.col("prec")[0].alias("prec"), F.col("info")[0].alias("info")), 4))
