"""The queries of the library over the given tables, with the SQL that gives the same rows."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import core_queries
from . import experiments as ex
from .functions.rng import gamma_of, gamma_sql, normal_of, normal_sql, uniform_of, uniform_sql
from .operators import metrics, models
from .operators.clock import arrival_patterns, batch_times, group_sequence, ready_at, ready_rounds, straggler_profile, worker_rounds
from .operators.coding import PINNED_5_2, GradientCode
from .operators.draws import draws, share_draws
from .operators.layout import allocation, assign_shards, shard_rows, worker_storage
from .operators.protocols import PosteriorMesh, ProtocolSpec
from .sources.tables import load

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
DAY = 86400.0
DAYS = [5 * DAY, 10 * DAY, 20 * DAY, 30 * DAY]
LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]


def query(name: str, sql: str | None = None):
    def take(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return take


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[(F.round(c, digits) + 0.0).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def cells(df: DataFrame, column: str, d: int, *keys: str) -> DataFrame:
    """A row for each element of a matrix: i, j, v."""
    each = df.select(*keys, F.posexplode(column).alias("_p", "v"))
    return each.select(*keys, (F.expr(f"CAST(_p DIV {d} + 1 AS int)")).alias("i"), (F.expr(f"CAST(_p % {d} + 1 AS int)")).alias("j"), "v")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The smoke run of ``entry``: one run, early times; the query ``linear_errors`` has all runs and times."""
    return rounded(ex.linear_errors(spark, sf_dir, grid=(1.0, 2.0, 5.0)))


QUERIES["linear_errors"] = lambda s, d: rounded(ex.linear_errors(s, d, runs=ex.RUNS, grid=ex.GRID))

# layout
query("shard_sizes_column", "SELECT CAST(l_suppkey % 5 + 1 AS INTEGER) AS shard, count(*) AS n FROM lineitem GROUP BY 1")(
    lambda s, d: assign_shards(load(s, d, "lineitem"), 5, ["l_suppkey"], "column").groupBy("shard").agg(F.count("*").alias("n")))
query("shard_sizes_exact", f"SELECT CAST((rn - 1) % 40 + 1 AS INTEGER) AS shard, count(*) AS n, sum(l_quantity) AS q FROM (SELECT l_quantity, row_number() OVER (ORDER BY {', '.join(LINE_KEY)}) AS rn FROM lineitem) GROUP BY 1")(
    lambda s, d: assign_shards(load(s, d, "lineitem").select("l_quantity", *LINE_KEY), 40, LINE_KEY).groupBy("shard").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q")))
query("worker_storage", "WITH c AS (SELECT l_suppkey % 40 AS s, count(*) AS n FROM lineitem GROUP BY 1) SELECT CAST(w.range AS INTEGER) AS worker, CAST(sum(n) AS BIGINT) AS n FROM range(1, 41) w JOIN c ON (w.range - 1) // 4 = c.s // 4 GROUP BY 1")(
    lambda s, d: worker_storage(assign_shards(load(s, d, "lineitem"), 40, ["l_suppkey"], "column"), allocation(s, "replica_group", 40, 4)))
HELD = "n AS (SELECT CAST(l_orderkey % {k} + 1 AS INTEGER) AS shard, count(*) AS n FROM lineitem GROUP BY 1)"


def allocated(s: SparkSession, d: str, scheme: str, k: int, r: int, *columns: str) -> DataFrame:
    """The allocation of lineitem's shards, with the rows that a worker holds for each."""
    return shard_rows(assign_shards(load(s, d, "lineitem").select("l_orderkey"), k, ["l_orderkey"], "column"), allocation(s, scheme, k, r)).select("worker", "shard", *columns, "n")


query("allocation_one_shot", f"WITH {HELD.format(k=40)} SELECT CAST(range AS INTEGER) AS worker, CAST(range AS INTEGER) AS shard, coalesce(n, 0) AS n FROM range(1, 41) LEFT JOIN n ON shard = range")(lambda s, d: allocated(s, d, "one_shot", 40, 1))
for _k, _r in ((5, 2), (40, 2), (40, 4)):
    query(f"allocation_groups_{_k}_{_r}", f"WITH {HELD.format(k=_k)} SELECT CAST(a.range AS INTEGER) AS worker, CAST(b.range AS INTEGER) AS shard, CAST((a.range - 1) // {_r} + 1 AS INTEGER) AS grp, coalesce(n, 0) AS n FROM range(1, {_k + 1}) a JOIN range(1, {_k + 1}) b ON (a.range - 1) // {_r} = (b.range - 1) // {_r} LEFT JOIN n ON n.shard = b.range")(
        lambda s, d, k=_k, r=_r: allocated(s, d, "replica_group", k, r, "grp"))
PINNED = ", ".join(f"({w}, {s}, {c})" for w, row in enumerate(PINNED_5_2, 1) for s, c in row)
query("allocation_coded_5_2", f"WITH {HELD.format(k=5)} SELECT CAST(w AS INTEGER) AS worker, CAST(s AS INTEGER) AS shard, CAST(c AS DOUBLE) AS coef, coalesce(n, 0) AS n FROM (VALUES {PINNED}) t(w, s, c) LEFT JOIN n ON shard = s")(lambda s, d: allocated(s, d, "coded_sum", 5, 2, "coef"))
query("allocation_coded_40_4", f"WITH {HELD.format(k=40)} SELECT CAST(a.range + 1 AS INTEGER) AS worker, CAST((a.range + b.range) % 40 + 1 AS INTEGER) AS shard, CAST(1 AS DOUBLE) AS coef, coalesce(n, 0) AS n FROM range(40) a CROSS JOIN range(4) b LEFT JOIN n ON shard = (a.range + b.range) % 40 + 1")(lambda s, d: allocated(s, d, "coded_sum", 40, 4, "coef"))

# random numbers, clocks, completion
query("uniform_draws", f"SELECT range AS id, round({uniform_sql(chr(39) + 't' + chr(39), 'range')}, 12) AS u, round({normal_sql('range')}, 9) AS z FROM range(2000)")(
    lambda s, d: s.range(2000).select("id", F.round(uniform_of(F.lit("t"), "id"), 12).alias("u"), F.round(normal_of("id"), 9).alias("z")))


def clock_sql(k: int, r: int, rounds: int, runs: int = 1) -> str:
    u = uniform_sql("'t'", "run", "worker", "round")
    return f"""dt AS (SELECT run, worker, round, {0.1 * 0.2 / 1.2!r} * {float(r)} * pow({u}, {-1 / 1.2!r}) AS dt
      FROM (SELECT CAST(a.range AS INTEGER) AS run, CAST(b.range AS INTEGER) AS worker, CAST(c.range AS INTEGER) AS round FROM range(1, {runs + 1}) a, range(1, {k + 1}) b, range(1, {rounds + 1}) c)),
    clock AS (SELECT *, sum(dt) OVER (PARTITION BY run, worker ORDER BY round ROWS UNBOUNDED PRECEDING) AS done_at FROM dt)"""


ROUNDS, GRID = 300, [1.0, 2.0, 5.0]
for _k, _r in ((5, 2), (40, 2), (40, 4)):
    _make = partial(batch_times, k=_k, r=_r, rounds=ROUNDS, runs=2)
    _with = f"WITH {clock_sql(_k, _r, ROUNDS, 2)}"
    _grid = f"g AS (SELECT unnest({GRID}) AS as_of), w AS (SELECT run, worker, as_of, count(*) FILTER (done_at <= as_of) AS n FROM clock, g GROUP BY ALL)"
    query(f"pareto_clock_{_k}_{_r}", f"{_with} SELECT run, worker, round, round(dt, 6) AS dt, round(done_at, 6) AS done_at FROM clock")(lambda s, d, m=_make: rounded(m(s)))
    query(f"worker_rounds_{_k}_{_r}", f"{_with}, {_grid} SELECT run, worker, as_of, n FROM w")(lambda s, d, m=_make, k=_k: worker_rounds(m(s), k, GRID))
    query(f"ready_one_shot_{_k}_{_r}", f"{_with}, {_grid} SELECT run, as_of, min(n) AS rounds FROM w GROUP BY ALL")(lambda s, d, m=_make, k=_k, r=_r: ready_rounds(m(s), "one_shot", k, r, GRID))
    query(f"ready_replica_group_{_k}_{_r}", f"{_with}, {_grid} SELECT run, as_of, CAST(min(n) AS BIGINT) AS rounds FROM (SELECT run, as_of, (worker - 1) // {_r} AS g, sum(n) AS n FROM w GROUP BY ALL) GROUP BY ALL")(
        lambda s, d, m=_make, k=_k, r=_r: ready_rounds(m(s), "replica_group", k, r, GRID))
    query(f"ready_coded_sum_{_k}_{_r}", f"{_with}, {_grid} SELECT run, as_of, list_sort(list(n))[{_r}] AS rounds FROM w GROUP BY ALL")(lambda s, d, m=_make, k=_k, r=_r: ready_rounds(m(s), "coded_sum", k, r, GRID))
    _early = f"e AS (SELECT run, round, worker, done_at FROM clock QUALIFY row_number() OVER (PARTITION BY run, round ORDER BY done_at, worker) <= {_k - _r + 1})"
    _seq = f"q AS (SELECT run, CAST((worker - 1) // {_r} + 1 AS INTEGER) AS grp, CAST(row_number() OVER (PARTITION BY run, (worker - 1) // {_r} ORDER BY done_at, worker, round) AS INTEGER) AS seq, worker, round, done_at FROM clock)"
    query(f"ready_at_one_shot_{_k}_{_r}", f"{_with} SELECT run, round, round(max(done_at), 6) AS ready_at FROM clock GROUP BY ALL")(lambda s, d, m=_make, k=_k, r=_r: rounded(ready_at(m(s), "one_shot", k, r)))
    query(f"ready_at_replica_group_{_k}_{_r}", f"{_with}, {_seq} SELECT run, seq AS round, round(max(done_at), 6) AS ready_at FROM q GROUP BY ALL HAVING count(*) = {-(-_k // _r)}")(lambda s, d, m=_make, k=_k, r=_r: rounded(ready_at(m(s), "replica_group", k, r)))
    query(f"ready_at_coded_sum_{_k}_{_r}", f"{_with}, {_early} SELECT run, round, round(max(done_at), 6) AS ready_at FROM e GROUP BY ALL")(lambda s, d, m=_make, k=_k, r=_r: rounded(ready_at(m(s), "coded_sum", k, r)))
    query(f"group_sequence_{_k}_{_r}", f"{_with}, {_seq} SELECT run, grp, seq, worker, round FROM q")(lambda s, d, m=_make, r=_r: group_sequence(m(s), r).select("run", "grp", "seq", "worker", "round"))
    query(f"straggler_profile_{_k}_{_r}", f"{_with} SELECT run, round, round(max(done_at) - min(done_at), 6) AS gap, arg_max(worker, done_at) AS last FROM clock GROUP BY ALL")(lambda s, d, m=_make: rounded(straggler_profile(m(s))))

# models on generated and given data
for _k in (5, 40):
    query(f"toeplitz_precision_{_k}", f"""SELECT CAST(s.range AS INTEGER) AS shard, CAST(a.range AS INTEGER) AS i, CAST(b.range AS INTEGER) AS j, round(CASE WHEN a.range = b.range THEN (CASE WHEN a.range IN (1, 5) THEN 1 ELSE 1 + rho * rho END) / (1 - rho * rho)
      WHEN abs(a.range - b.range) = 1 THEN -rho / (1 - rho * rho) ELSE 0 END, 6) + 0.0 AS v FROM (SELECT range, (range - 1) / {float(_k)} AS rho FROM range(1, {_k + 1})) s, range(1, 6) a, range(1, 6) b""")(
        lambda s, d, k=_k: rounded(cells(models.toeplitz_subposteriors(s, k), "prec", 5, "shard")))

AR = "z1 AS v1, rho * z1 + s * z2 AS v2"
query("gaussian_draws", f"""WITH b AS (SELECT CAST(a.range AS INTEGER) AS shard, CAST(l.range AS INTEGER) AS round, (a.range - 1) / 5.0 AS rho, {', '.join(normal_sql('1', 'CAST(a.range AS INTEGER)', 'CAST(a.range AS INTEGER)', 'l.range', str(i)) + f' AS z{i}' for i in range(1, 6))} FROM range(1, 6) a, range(1, 101) l),
  c AS (SELECT *, sqrt(1 - rho * rho) AS s FROM b), d1 AS (SELECT *, z1 AS v1 FROM c), d2 AS (SELECT *, rho * v1 + s * z2 AS v2 FROM d1), d3 AS (SELECT *, rho * v2 + s * z3 AS v3 FROM d2), d4 AS (SELECT *, rho * v3 + s * z4 AS v4 FROM d3), d5 AS (SELECT *, rho * v4 + s * z5 AS v5 FROM d4)
  SELECT shard, round, round(v1, 6) + 0.0 AS v1, round(v2, 6) + 0.0 AS v2, round(v3, 6) + 0.0 AS v3, round(v4, 6) + 0.0 AS v4, round(v5, 6) + 0.0 AS v5 FROM d5""")(
    lambda s, d: rounded(draws(models.toeplitz_subposteriors(s, 5), allocation(s, "one_shot", 5), 100, 5).select("shard", "round", *[F.col("x")[i].alias(f"v{i + 1}") for i in range(5)])))

XS = ["l_quantity / 10", "l_discount * 10", "l_tax * 10", "p_retailprice / 1000", "CAST(1 AS DOUBLE)"]
query("linear_subposteriors", f"""WITH o AS (SELECT CAST(l_suppkey % 5 + 1 AS INTEGER) AS shard, {', '.join(f'{x} AS x{i}' for i, x in enumerate(XS))}, l_extendedprice / 10000 AS y FROM lineitem JOIN part ON l_partkey = p_partkey)
  SELECT shard, count(*) AS n, round(sum(x0 * x0) + 0.2, 4) AS p11, round(sum(x0 * x3), 4) AS p14, round(sum(x4 * x4) + CAST(0.2 AS DOUBLE), 4) AS p55, round(sum(x0 * y), 4) AS h1, round(sum(y), 4) AS h5 FROM o GROUP BY 1""")(
    lambda s, d: rounded(ex.linear_regression(s, d).select("shard", "n", F.col("prec")[0].alias("p11"), F.col("prec")[3].alias("p14"), F.col("prec")[24].alias("p55"), F.col("info")[0].alias("h1"), F.col("info")[4].alias("h5")), 4))
query("event_rates", "SELECT CAST(user_id % 5 + 1 AS INTEGER) AS shard, event_type, count(*) AS n, CAST(count(*) + 1 AS DOUBLE) AS shape, round(sum(value) + 0.2, 4) AS rate FROM events GROUP BY 1, 2")(
    lambda s, d: rounded(models.exponential_rate(load(s, d, "events").withColumn("shard", (F.pmod("user_id", F.lit(5)) + 1).cast("int")), F.col("value"), 5, by=("event_type",)), 4))
for _label in ("quality", "toxic"):
    query(f"{_label}_shares", f"SELECT CAST(l.doc_id % 5 + 1 AS INTEGER) AS shard, lang, count(*) AS n, CAST(1 + count(*) FILTER ({_label} = 1) AS DOUBLE) AS alpha, CAST(1 + count(*) FILTER ({_label} <> 1) AS DOUBLE) AS beta FROM labels l JOIN documents d ON l.doc_id = d.doc_id GROUP BY 1, 2")(
        lambda s, d, label=_label: models.bernoulli_share(load(s, d, "labels").join(load(s, d, "documents").select("doc_id", "lang"), "doc_id").withColumn("shard", (F.pmod("doc_id", F.lit(5)) + 1).cast("int")), F.col(label) == 1, 5, by=("lang",)))
query("order_counts", "WITH c AS (SELECT CAST(c_custkey % 5 + 1 AS INTEGER) AS shard, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey) SELECT shard, count(*) AS n, CAST(1 + sum(n) AS DOUBLE) AS shape, CAST(0.2 AS DOUBLE) + count(*) AS rate FROM c GROUP BY 1")(
    lambda s, d: models.poisson_rate(load(s, d, "customer").select("c_custkey").join(load(s, d, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("k")), "c_custkey", "left").select((F.pmod("c_custkey", F.lit(5)) + 1).cast("int").alias("shard"), F.coalesce("k", F.lit(0)).alias("k")), F.col("k"), 5))
query("language_shares", "SELECT CAST(doc_id % 5 + 1 AS INTEGER) AS shard, lang AS category, count(*) AS n, CAST(1 + count(*) AS DOUBLE) AS alpha FROM documents GROUP BY 1, 2")(
    lambda s, d: models.category_shares(load(s, d, "documents").select("lang", (F.pmod("doc_id", F.lit(5)) + 1).cast("int").alias("shard")), F.col("lang"), 5))
query("role_shares", "SELECT CAST(conv_id % 5 + 1 AS INTEGER) AS shard, role AS category, count(*) AS n, CAST(1 + count(*) AS DOUBLE) AS alpha FROM conversations GROUP BY 1, 2")(
    lambda s, d: models.category_shares(load(s, d, "conversations").select("role", (F.pmod("conv_id", F.lit(5)) + 1).cast("int").alias("shard")), F.col("role"), 5))
query("embedding_means", "SELECT CAST(vec_id % 5 + 1 AS INTEGER) AS shard, count(*) AS n, " + ", ".join(f"round(sum(CAST(embedding[{i}] AS DOUBLE)), 4) + 0.0 AS h{i}" for i in range(1, 6)) + " FROM embeddings GROUP BY 1")(
    lambda s, d: rounded(models.gaussian_mean(load(s, d, "embeddings").withColumn("shard", (F.pmod("vec_id", F.lit(5)) + 1).cast("int")), [F.col("embedding")[i].cast("double") for i in range(5)], 5).select("shard", "n", *[F.col("info")[i].alias(f"h{i + 1}") for i in range(5)]), 4))
query("balance_by_region", "SELECT coalesce(r_name, 'all') AS region, count(*) AS n, round(sum(c_acctbal), 4) AS total FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name)")(
    lambda s, d: rounded(load(s, d, "customer").groupBy(F.col("c_nationkey").alias("n_nationkey")).agg(F.count("*").alias("n"), F.sum("c_acctbal").alias("t")).join(load(s, d, "nation"), "n_nationkey").join(load(s, d, "region").withColumnRenamed("r_regionkey", "n_regionkey"), "n_regionkey")
                         .rollup("r_name").agg(F.sum("n").alias("n"), F.sum("t").alias("total")).select(F.coalesce("r_name", F.lit("all")).alias("region"), "n", "total"), 4))
query("text_lengths", "SELECT source, count(*) AS n, round(sum(ln(1 + length(text))), 4) AS h FROM documents GROUP BY 1")(
    lambda s, d: rounded(load(s, d, "documents").groupBy("source").agg(F.count("*").alias("n"), F.sum(F.ln(1 + F.length("text"))).alias("h")), 4))

# real arrival times
EVENTS = "ev AS (SELECT CAST(user_id % {k} + 1 AS INTEGER) AS worker, epoch_us(ts) / 1e6 - 1704067200.0 AS done_at, event_id FROM events), clock AS (SELECT *, 1 AS run, row_number() OVER (PARTITION BY worker ORDER BY done_at, event_id) AS round FROM ev)"
for _k, _r in ((5, 2), (40, 2), (40, 4)):
    _w = f"WITH {EVENTS.format(k=_k)}, g AS (SELECT unnest({DAYS}) AS as_of), v AS (SELECT range AS worker FROM range(1, {_k + 1})), w AS (SELECT v.worker, as_of, count(done_at) AS n FROM v CROSS JOIN g LEFT JOIN clock ON clock.worker = v.worker AND done_at <= as_of GROUP BY ALL)"
    for _scheme, _sql in (("one_shot", "SELECT as_of, min(n) AS rounds FROM w GROUP BY 1"), ("replica_group", f"SELECT as_of, CAST(min(n) AS BIGINT) AS rounds FROM (SELECT as_of, (worker - 1) // {_r} AS g, sum(n) AS n FROM w GROUP BY ALL) GROUP BY 1"), ("coded_sum", f"SELECT as_of, list_sort(list(n))[{_r}] AS rounds FROM w GROUP BY 1")):
        query(f"events_ready_{_scheme}_{_k}_{_r}", f"{_w} {_sql}")(lambda s, d, k=_k, r=_r, scheme=_scheme: ready_rounds(ex.event_clock(s, d, k), scheme, k, r, DAYS).select("as_of", "rounds"))
    query(f"arrival_patterns_{_k}_{_r}", f"WITH {EVENTS.format(k=_k)}, e AS (SELECT run, round, worker FROM clock QUALIFY row_number() OVER (PARTITION BY run, round ORDER BY done_at, worker) <= {_k - _r + 1}) SELECT run, CAST(round AS INTEGER) AS round, string_agg(CAST(worker AS VARCHAR), ',' ORDER BY worker) AS pattern FROM e GROUP BY ALL HAVING count(*) = {_k - _r + 1}")(
        lambda s, d, k=_k, r=_r: arrival_patterns(ex.event_clock(s, d, k), k, r).select("run", "round", F.concat_ws(",", F.col("pattern").cast("array<string>")).alias("pattern")))
    query(f"events_stream_{_k}_{_r}", f"WITH {EVENTS.format(k=_k)} SELECT CAST(min(n) AS BIGINT) AS rounds FROM (SELECT (worker - 1) // {_r} AS g, count(*) AS n FROM clock GROUP BY 1)")(
        lambda s, d, k=_k, r=_r: ex.streamed_rounds(s, d, k, r).select(F.col("rounds").cast("long").alias("rounds")))

# codes
TOTALS = "SELECT CAST(count(*) AS DOUBLE) AS n, round(sum(o_totalprice), 2) AS total FROM orders"
for _name, _code, _lost in (("pinned_5_2", (5, 2, None), {3}), ("cyclic_40_4", (40, 4, "cyclic_ones"), {1, 17, 40}), ("nullspace_7_3", (7, 3, "cyclic_nullspace"), {2, 6}), ("fractional_6_3", (6, 3, "fractional"), {1, 2})):
    query(f"coded_order_totals_{_name}", TOTALS)(lambda s, d, c=_code, lost=_lost: ex.coded_totals(s, d, GradientCode(*c), lost).select(F.round("n", 4).alias("n"), F.round("total", 2).alias("total")))

# measures
CASES = [(k, r, s) for k, r in ((5, 2), (40, 2), (40, 4)) for s in ex.SCHEMES]
query("resilience", "SELECT CAST(k AS INTEGER) AS k, CAST(r AS INTEGER) AS r, scheme, CAST(CASE scheme WHEN 'one_shot' THEN 0 WHEN 'coded_sum' THEN r - 1 ELSE (k // r) * (r - 1) + greatest(k % r - 1, 0) END AS INTEGER) AS best, CAST(CASE scheme WHEN 'one_shot' THEN 0 WHEN 'coded_sum' THEN r - 1 ELSE (CASE WHEN k % r = 0 THEN r ELSE k % r END) - 1 END AS INTEGER) AS worst FROM (VALUES (5, 2), (40, 2), (40, 4)) t(k, r), (VALUES ('one_shot'), ('replica_group'), ('coded_sum')) u(scheme)")(
    lambda s, d: s.createDataFrame([(k, r, x, metrics.resilience(x, k, r), metrics.resilience(x, k, r, True)) for k, r, x in CASES], "k int, r int, scheme string, best int, worst int"))
query("costs", "SELECT CAST(k AS INTEGER) AS k, CAST(r AS INTEGER) AS r, scheme, CAST(CASE scheme WHEN 'replica_group' THEN 5 * r ELSE 5 END AS INTEGER) AS sent, (SELECT count(*) FROM lineitem) * (CASE scheme WHEN 'one_shot' THEN 1 ELSE r END) / CAST(k AS DOUBLE) AS stored FROM (VALUES (5, 2), (40, 2), (40, 4)) t(k, r), (VALUES ('one_shot'), ('replica_group'), ('coded_sum')) u(scheme)")(
    lambda s, d: s.createDataFrame([(k, r, x, metrics.comm_cost(x, r, 5), 1 if x == "one_shot" else r) for k, r, x in CASES], "k int, r int, scheme string, sent int, copies int").crossJoin(F.broadcast(load(s, d, "lineitem").agg(F.count("*").alias("n")))).select("k", "r", "scheme", "sent", (F.col("n") * F.col("copies") / F.col("k").cast("double")).alias("stored")))


def moments_query(s: SparkSession, d: str) -> DataFrame:
    mesh = PosteriorMesh(s, ProtocolSpec("one_shot", 5), models.toeplitz_subposteriors(s, 5), 2.0)
    return rounded(mesh.moments([1.0, 2.0]).select("as_of", "shard", "n", F.col("s1")[0].alias("s1"), F.col("s2")[0].alias("s11")))


query("shard_moments", f"""WITH {clock_sql(5, 1, 120)}, x AS (SELECT worker, done_at, {normal_sql('1', 'worker', 'worker', 'round', '1')} AS v FROM clock)
  SELECT as_of, worker AS shard, count(*) AS n, round(sum(v), 6) + 0.0 AS s1, round(sum(v * v), 6) + 0.0 AS s11 FROM x, (SELECT unnest([1.0, 2.0]) AS as_of) g WHERE done_at <= as_of GROUP BY ALL""")(moments_query)

# the two experiments, variants and ablations: no SQL, tested against a reference in numpy
for _k, _r in ((5, 2), (40, 2), (40, 4)):
    QUERIES[f"paper_errors_{_k}_{_r}"] = lambda s, d, k=_k, r=_r: rounded(ex.paper_errors(s, k, r, runs=ex.RUNS, grid=ex.GRID))
    QUERIES[f"paper_curve_{_k}_{_r}"] = lambda s, d, k=_k, r=_r: rounded(ex.paper_curves(s, k, r, runs=ex.RUNS, grid=ex.GRID))
for _weights in ("exact", "uniform", "diagonal"):
    QUERIES[f"errors_weights_{_weights}"] = lambda s, d, w=_weights: rounded(ex.paper_errors(s, 5, 2, runs=ex.RUNS, grid=ex.GRID, schemes=("one_shot", "replica_group"), weights=w))
QUERIES["errors_coded_warmup"] = lambda s, d: rounded(ex.paper_errors(s, 5, 2, runs=ex.RUNS, grid=ex.GRID, schemes=("coded_sum",), warmup=10))
QUERIES["errors_coded_recompute"] = lambda s, d: rounded(ex.paper_errors(s, 5, 2, runs=ex.RUNS, grid=ex.GRID, schemes=("coded_sum",), warmup=10, recompute=True))


def gap_query(s: SparkSession, d: str) -> DataFrame:
    sub = models.toeplitz_subposteriors(s, 5)
    mesh = PosteriorMesh(s, ProtocolSpec("coded_sum", 5, 2), sub, 10.0)
    return rounded(metrics.precision_gap(mesh.decoded(), sub, 5, warmup=10).where("round > 20"))


QUERIES["precision_gap"] = gap_query

# draws of subposteriors that aren't Gaussian
query("gamma_draws", f"SELECT CAST(range AS INTEGER) AS shard, round({gamma_sql('(1 + range)', 'range')}, 6) AS g FROM range(0, 500)")(
    lambda s, d: s.range(500).select(F.col("id").cast("int").alias("shard"), F.round(gamma_of(1 + F.col("id"), "id"), 6).alias("g")))
query("rate_draws", f"""WITH p AS (SELECT CAST(user_id % 5 + 1 AS INTEGER) AS shard, count(*) + 1 AS shape, round(sum(value) + 0.2, 4) AS rate FROM events GROUP BY 1), b AS (SELECT *, CAST(range AS INTEGER) AS round FROM p, range(1, 21))
  SELECT shard, round, round({gamma_sql('shape', '1', 'shard', 'shard', 'round')} / rate, 8) AS x FROM b""")(
    lambda s, d: draws(ex.event_rates(s, d).withColumn("rate", F.round("rate", 4)), allocation(s, "one_shot", 5), 20, 1).select("shard", "round", F.round(F.col("x")[0], 8).alias("x")))
query("language_share_draws", f"""WITH p AS (SELECT CAST(doc_id % 5 + 1 AS INTEGER) AS shard, lang AS category, 1 + count(*) AS alpha FROM documents GROUP BY 1, 2), g AS (SELECT shard, category, CAST(range AS INTEGER) AS round, {gamma_sql('alpha', '1', 'shard', 'range', 'category')} AS g FROM p, range(1, 11))
  SELECT shard, round, category, round(g / sum(g) OVER (PARTITION BY shard, round), 8) AS x FROM g""")(
    lambda s, d: share_draws(models.category_shares(load(s, d, "documents").select("lang", (F.pmod("doc_id", F.lit(5)) + 1).cast("int").alias("shard")), F.col("lang"), 5), 10).select("shard", "round", "category", F.round("x", 8).alias("x")))
QUERIES["event_rate_errors"] = lambda s, d: rounded(ex.event_rate_errors(s, d), 6)
QUERIES["logistic_draws"] = lambda s, d: ex.logistic_chain(s, d).select("shard", "round", F.transform("x", lambda v: F.round(v, 6)).alias("x"), "accepted")
QUERIES["errors_last_round"] = lambda s, d: rounded(ex.paper_errors(s, 5, 2, runs=ex.RUNS, grid=ex.GRID, schemes=("one_shot", "replica_group"), refresh="last_round"))
QUERIES["error_quantiles_5_2"] = lambda s, d: rounded(metrics.curve_quantiles(ex.paper_errors(s, 5, 2, runs=ex.RUNS, grid=ex.GRID)))
QUERIES["curves_side_by_side_5_2"] = lambda s, d: rounded(ex.side_by_side(ex.paper_curves(s, 5, 2, runs=ex.RUNS, grid=ex.GRID)))


def crossover_sql() -> str:
    parts = []
    for k in (5, 10, 20, 40):
        for scheme in ex.SCHEMES:
            each = {"one_shot": "SELECT as_of, min(n) AS rounds FROM w GROUP BY 1", "coded_sum": "SELECT as_of, list_sort(list(n))[2] AS rounds FROM w GROUP BY 1"}.get(scheme, "SELECT as_of, min(n) AS rounds FROM (SELECT as_of, (worker - 1) // 2 AS g, sum(n) AS n FROM w GROUP BY ALL) GROUP BY 1")
            w = f"WITH {EVENTS.format(k=k)}, g AS (SELECT unnest({DAYS}) AS as_of), v AS (SELECT range AS worker FROM range(1, {k + 1})), w AS (SELECT v.worker, as_of, count(done_at) AS n FROM v CROSS JOIN g LEFT JOIN clock ON clock.worker = v.worker AND done_at <= as_of GROUP BY ALL)"
            parts.append(f"SELECT {k} AS k, '{scheme}' AS scheme, as_of, rounds FROM ({w} {each})")
    return f"SELECT CAST(coalesce(k, 0) AS INTEGER) AS k, coalesce(scheme, 'all') AS scheme, CAST(coalesce(as_of, 0) AS DOUBLE) AS as_of, round(avg(rounds), 6) AS rounds FROM ({' UNION ALL '.join(parts)}) GROUP BY ROLLUP (k, scheme, as_of)"


query("crossover", crossover_sql())(lambda s, d: rounded(ex.crossover(s, grid=DAYS, clock=lambda k: ex.event_clock(s, d, k))))
QUERIES["crossover_whole"] = lambda s, d: rounded(ex.crossover(s, runs=ex.RUNS, grid=ex.GRID))  # of modelled times; the query above is of the times of events
query("idle_spans", f"WITH {clock_sql(5, 2, 60)}, b AS (SELECT *, done_at - dt AS begun FROM clock), e AS (SELECT *, unnest(range(CAST(floor(begun) AS BIGINT), CAST(floor(done_at) AS BIGINT) + 1)) AS slot FROM b) SELECT run, slot, worker, round(sum(greatest(least(done_at, slot + 1) - greatest(begun, slot), 0)), 6) AS busy FROM e GROUP BY ALL")(
    lambda s, d: rounded(metrics.idle_spans(batch_times(s, 5, 2, 60), 1.0)))


def cluster_query(s: SparkSession, d: str) -> DataFrame:
    from .sources.virtual_cluster import register

    register(s)
    return rounded(s.read.format("virtual_cluster").option("workers", 5).option("redundancy", 2).option("rounds", 100).load())


def trace_query(s: SparkSession, d: str) -> DataFrame:
    from .functions.sql import register

    register(s)
    return rounded(s.sql("SELECT * FROM latency_trace(5, 2, 0.1D, 1.2D, 100, 42)"))


query("virtual_cluster", f"WITH {clock_sql(5, 2, 100)} SELECT run, worker, round, round(dt, 6) AS dt, round(done_at, 6) AS done_at FROM clock")(cluster_query)
query("latency_trace", f"WITH {clock_sql(5, 2, 100)} SELECT worker, round, round(dt, 6) AS dt, round(done_at, 6) AS done_at FROM clock")(trace_query)

# the protocols on the given tables
QUERIES["embedding_errors"] = lambda s, d: rounded(ex.embedding_errors(s, d))
QUERIES["length_errors"] = lambda s, d: rounded(ex.length_errors(s, d))
QUERIES["page_length_errors"] = lambda s, d: rounded(ex.length_errors(s, d, "pages", "page_id", "html"))
QUERIES["quality_share_errors"] = lambda s, d: rounded(ex.share_errors(s, d))

QUERIES |= core_queries.QUERIES
ORACLES |= core_queries.ORACLES
