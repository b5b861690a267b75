"""A training corpus in five stages: what is toxic, nearly copied, repeated or leaked goes, the rest is packed."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from posterior_mesh.llm.common import cut, load
from posterior_mesh.llm.decontaminate import decontaminate
from posterior_mesh.llm.ngram_join import one_of_each
from posterior_mesh.llm.packing import pack_documents
from posterior_mesh.llm.suffix_dedup import PASSAGE, without_repeats
from posterior_mesh.llm.toxicity import without_toxic


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score 0.5 or more go."""
    return without_toxic(docs, load(spark, sf_dir, "labels"))


def ngram_jaccard_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents that sets of five words link at a similarity of 0.8 or more, the one of the smallest id stays."""
    return one_of_each(docs)


def suffix_array_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of over 50 words and strings of 400 bytes that stand anywhere else too are cut out of the texts."""
    return without_repeats(docs, words=PASSAGE)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which one word in twenty or more lies in passages of the benchmark go."""
    return decontaminate(docs, load(spark, sf_dir, "benchmark"))


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces with their places in sequences."""
    return pack_documents(docs)


STAGES = [(f.__name__, f) for f in (toxicity, ngram_jaccard_join, suffix_array_dedup, benchmark_decontamination, best_fit_packing)]

#: No SQL can say what the first and the last stage do.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES, 1):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES):
            docs = cut(docs)
    return docs
