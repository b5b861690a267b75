"""The experiments, on generated subposteriors and on the given tables."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import metrics, models
from .operators.metropolis import logistic_draws
from .operators.clock import ParetoClock, batch_times, clock_check, timeline, trace_clock
from .operators.protocols import PosteriorMesh, ProtocolSpec
from .sources.tables import load

SCHEMES = ("one_shot", "replica_group", "coded_sum")
#: Runs of an experiment, and its times up to the horizon.
RUNS, GRID = 50, (1.0, 2.0, 5.0, 10.0, 20.0, 50.0, 100.0)


def errors_of(spark: SparkSession, spec: ProtocolSpec, sub: DataFrame, grid: list[float], signed: bool = True) -> DataFrame:
    return PosteriorMesh(spark, spec, sub, max(grid)).errors(grid, signed).withColumn("scheme", F.lit(spec.scheme))


def paper_errors(spark: SparkSession, k: int, r: int, runs: int = 50, grid=(1.0, 2.0, 5.0, 10.0), schemes=SCHEMES, **options) -> DataFrame:
    """scheme, run, as_of, rounds, err on zero-mean Toeplitz Gaussians of five dimensions with Pareto batch times."""
    sub = models.toeplitz_subposteriors(spark, k)
    return reduce(DataFrame.unionByName, [errors_of(spark, ProtocolSpec(s, k, r, runs=runs, **options), sub, [float(t) for t in grid]) for s in schemes])


def paper_curves(spark: SparkSession, k: int, r: int, **options) -> DataFrame:
    return metrics.error_curve(paper_errors(spark, k, r, **options), by=("scheme",))


def regression_rows(spark: SparkSession, sf_dir: str, shards: int) -> tuple[DataFrame, list, F.Column]:
    """lineitem with part: four covariates of fixed scale, a constant, and the price; shard by supplier."""
    line = load(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", "l_quantity", "l_discount", "l_tax", "l_extendedprice")
    part = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_retailprice")
    rows = line.join(part, "l_partkey").withColumn("shard", (F.pmod("l_suppkey", F.lit(shards)) + 1).cast("int"))
    x = [F.col("l_quantity") / 10, F.col("l_discount") * 10, F.col("l_tax") * 10, F.col("p_retailprice") / 1000, F.lit(1.0)]
    return rows, x, F.col("l_extendedprice") / 10000


def fixed(sub: DataFrame) -> DataFrame:
    """The subposteriors as a local table: a row of d² numbers for each shard, however many rows these have."""
    return sub.sparkSession.createDataFrame(sub.collect(), sub.schema)


def linear_regression(spark: SparkSession, sf_dir: str, shards: int = 5) -> DataFrame:
    rows, x, y = regression_rows(spark, sf_dir, shards)
    return models.linear_subposteriors(rows, x, y, shards)


def linear_errors(spark: SparkSession, sf_dir: str, k: int = 5, r: int = 2, grid=(1.0, 2.0, 5.0), runs: int = 1, ridge: float = 1e-12, **options) -> DataFrame:
    """The protocols on subposteriors that the rows of lineitem give."""
    sub = fixed(linear_regression(spark, sf_dir, k))
    return reduce(DataFrame.unionByName, [errors_of(spark, ProtocolSpec(s, k, r, runs=runs, ridge=ridge, **options), sub, [float(t) for t in grid]) for s in SCHEMES])


def event_clock(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    return trace_clock(load(spark, sf_dir, "events").select("event_id", "ts", "user_id"), k)


def coded_totals(spark: SparkSession, sf_dir: str, code, lost: set[int]) -> DataFrame:
    """Count, sum and sum of squares of order prices, decoded from coded sums without the lost workers."""
    from .operators.coding import decode, encode
    from .operators.layout import allocation

    orders = load(spark, sf_dir, "orders").select((F.pmod("o_custkey", F.lit(code.k)) + 1).cast("int").alias("shard"), F.col("o_totalprice").alias("p"))
    sums = orders.groupBy("shard").agg(F.array(F.count("*").cast("double"), F.sum("p"), F.sum(F.col("p") * F.col("p"))).alias("x"))
    once = sums.select(F.lit(1).alias("run"), "shard", F.lit(1).alias("round"), "x")
    messages = encode(once, allocation(spark, "coded_sum", code.k, code.r, code), 3)
    early = [w for w in range(1, code.k + 1) if w not in lost]
    patterns = spark.range(1).select(F.lit(1).alias("run"), F.lit(1).alias("round"), F.array(*[F.lit(w) for w in early]).alias("pattern"))
    return decode(messages, patterns, code, 3).select(F.col("phi")[0].alias("n"), F.col("phi")[1].alias("total"), F.col("phi")[2].alias("squares"))


def crossover(spark: SparkSession, ks=(5, 10, 20, 40), r: int = 2, runs: int = 3, grid=(2.0, 5.0), clock=None) -> DataFrame:
    """k, scheme, as_of, rounds: draws that each protocol can give by a time, as the number of workers grows; subtotals have k 0, scheme "all" or as_of 0.

    ``clock`` gives real times for a number of workers, instead of modelled ones.
    """
    from .operators.clock import ParetoClock, batch_times, ready_rounds

    law, times, each = ParetoClock(), [float(t) for t in grid], []
    for k in ks:
        for scheme in SCHEMES:
            held = 1 if scheme == "one_shot" else r
            done = clock(k) if clock else batch_times(spark, k, held, law.rounds_needed(max(times), held), runs, law)
            each.append(ready_rounds(done, scheme, k, held, times).select(F.lit(k).alias("k"), F.lit(scheme).alias("scheme"), "as_of", "rounds"))
    return reduce(DataFrame.unionByName, each).rollup("k", "scheme", "as_of").agg(F.avg("rounds").alias("rounds")).select(F.coalesce("k", F.lit(0)).alias("k"), F.coalesce("scheme", F.lit("all")).alias("scheme"), F.coalesce("as_of", F.lit(0.0)).alias("as_of"), "rounds")


def side_by_side(curves: DataFrame, value: str = "mean_err", by: tuple[str, ...] = ("as_of",)) -> DataFrame:
    """A column for each protocol."""
    return curves.groupBy(*by).pivot("scheme", list(SCHEMES)).agg(F.first(value))


def event_rates(spark: SparkSession, sf_dir: str, shards: int = 5) -> DataFrame:
    """Gamma subposteriors of the rate of the events' values."""
    events = load(spark, sf_dir, "events").select("value", (F.pmod("user_id", F.lit(shards)) + 1).cast("int").alias("shard"))
    return models.exponential_rate(events, F.col("value"), shards)


def event_rate_errors(spark: SparkSession, sf_dir: str, k: int = 5, r: int = 2, grid=(1.0, 2.0, 5.0), runs: int = 2, ridge: float = 1e-12) -> DataFrame:
    """The protocols on subposteriors that aren't Gaussian; the third one leaves ten rounds out and weighs all with the newest total."""
    sub, times, each = fixed(event_rates(spark, sf_dir, k)), [float(t) for t in grid], []
    for scheme in SCHEMES:
        spec = ProtocolSpec(scheme, k, r, d=1, runs=runs, ridge=ridge, warmup=10 if scheme == "coded_sum" else 0, recompute=scheme == "coded_sum")
        got = PosteriorMesh(spark, spec, sub, max(times)).global_draws(times)
        each.append(metrics.every_run(metrics.rate_errors(got, sub), spark, runs, times).withColumn("scheme", F.lit(scheme)))
    return reduce(DataFrame.unionByName, each)


def returned_rows(spark: SparkSession, sf_dir: str, shards: int) -> DataFrame:
    """shard, x, y of line items: a constant, quantity and discount; whether it was returned."""
    x = F.array(F.lit(1.0), F.col("l_quantity") / 50, F.col("l_discount") * 10)
    return load(spark, sf_dir, "lineitem").select((F.pmod("l_suppkey", F.lit(shards)) + 1).cast("int").alias("shard"), x.alias("x"), (F.col("l_returnflag") == "R").cast("double").alias("y"))


def logistic_chain(spark: SparkSession, sf_dir: str, shards: int = 5, rounds: int = 100) -> DataFrame:
    return logistic_draws(returned_rows(spark, sf_dir, shards), 3, shards, rounds)


def by_id(spark: SparkSession, sf_dir: str, table: str, key: str, shards: int) -> DataFrame:
    return load(spark, sf_dir, table).withColumn("shard", (F.pmod(key, F.lit(shards)) + 1).cast("int"))


def gaussian_errors(spark: SparkSession, sf_dir: str, table: str, key: str, columns, k: int = 5, r: int = 2, grid=(1.0, 2.0, 5.0), runs: int = RUNS, ridge: float = 1e-12, **options) -> DataFrame:
    """The three protocols on subposteriors of the mean of some columns; the third one leaves ten rounds out and weighs all with the newest total."""
    sub = fixed(models.gaussian_mean(by_id(spark, sf_dir, table, key, k), columns, k))
    specs = [ProtocolSpec(s, k, r, d=len(columns), runs=runs, ridge=ridge, warmup=10 if s == "coded_sum" else 0, recompute=s == "coded_sum", **options) for s in SCHEMES]
    return reduce(DataFrame.unionByName, [errors_of(spark, spec, sub, [float(t) for t in grid], signed=False) for spec in specs])


def embedding_errors(spark: SparkSession, sf_dir: str, d: int = 4, **options) -> DataFrame:
    return gaussian_errors(spark, sf_dir, "embeddings", "vec_id", [F.col("embedding")[i].cast("double") for i in range(d)], **options)


def length_errors(spark: SparkSession, sf_dir: str, table: str = "documents", key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    return gaussian_errors(spark, sf_dir, table, key, [F.ln(1 + F.length(text)), F.lit(1.0)], **options)


def share_errors(spark: SparkSession, sf_dir: str, label: str = "quality", k: int = 5, r: int = 2, grid=(1.0, 2.0, 5.0), runs: int = RUNS, ridge: float = 1e-12) -> DataFrame:
    """The first two protocols on Beta subposteriors of the share of labelled documents: errors of the mean share."""
    sub = fixed(models.bernoulli_share(by_id(spark, sf_dir, "labels", "doc_id", k), F.col(label) == 1, k))
    times, each = [float(t) for t in grid], []
    for scheme in SCHEMES[:2]:
        got = PosteriorMesh(spark, ProtocolSpec(scheme, k, r, d=1, runs=runs, ridge=ridge), sub, max(times)).global_draws(times)
        each.append(metrics.every_run(metrics.share_errors(got, sub), spark, runs, times).withColumn("scheme", F.lit(scheme)))
    return reduce(DataFrame.unionByName, each)


def streamed_rounds(spark: SparkSession, sf_dir: str, k: int = 5, r: int = 2, scheme: str = "replica_group", checkpoint: str | None = None) -> DataFrame:
    """rounds that the events allow, as a stream that reads the table's files gives them; equal to the batch answer over the same rows."""
    import uuid

    from .streaming.server import read_arrivals, rounds_of, run_to_table

    name = f"rounds_{uuid.uuid4().hex[:12]}"
    schema = load(spark, sf_dir, "events").select("ts", "user_id", "value").schema
    run_to_table(read_arrivals(spark, f"{sf_dir}/events.parquet*", schema), k, name, checkpoint)
    return rounds_of(spark.table(name), scheme, k, r)


WORKLOADS = {
    "W1": lambda s, d, **o: paper_curves(s, 5, 2, **o), "W2": lambda s, d, **o: paper_curves(s, 40, 2, **o), "W3": lambda s, d, **o: paper_curves(s, 40, 4, **o),
    "W4": lambda s, d, k=3, t=4.0, **o: timeline(batch_times(s, k, 1, 100, **o), k, t),
    "W5": lambda s, d, **o: crossover(s, **o),
    "W6": lambda s, d, k=5, r=2, rounds=1000: clock_check(batch_times(s, k, r, rounds), ParetoClock(), r),
    "W7": linear_errors, "W8": embedding_errors, "W9": event_rate_errors, "W10": share_errors, "W11": lambda s, d, k=5: event_clock(s, d, k), "W12": streamed_rounds,
    "W16": length_errors, "W18": lambda s, d, **o: length_errors(s, d, "pages", "page_id", "html", **o), "logistic": logistic_chain,
}


def run(spark: SparkSession, workload: str, sf_dir: str, **options) -> DataFrame:
    """One of ``WORKLOADS`` by its name; ``options`` are those of its function."""
    return WORKLOADS[workload](spark, sf_dir, **options)
