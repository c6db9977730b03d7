"""A corpus from raw documents: language, exact copies, near copies, benchmark passages, mix of sources.

Every stage takes (spark, docs, sf_dir) and returns the documents it keeps, with the columns of documents; the
last adds what the mix takes of each. The stages' results are written and read again between them.

Defined cases: null texts and texts without letters go in the first stage, since they have no language; of equal texts
that with the largest doc_id stays, of a group of near copies that with the smallest, where a row without an id stays
only if no row of its group has one; rows are told by id and text, so repeated and null ids cost no other text its row;
a null source is a source of its own; of documents without words the mix takes nothing; further columns are carried
along, and where one has the name of a column that the last stage adds, the added one gets an underscore before it; an
empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from simcluster.llm import decontaminate, exact_dedup, langid, mixing, ngram_join
from simcluster.llm.common import free_name, materialize


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of a language that is recognised; texts without letters go."""
    return langid.keep_identified(docs)


def exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts."""
    return exact_dedup.drop_copies(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that links of similar shingle sets hold together (five words, 0.8 and more)."""
    return ngram_join.drop_near_duplicates(docs, shingle=5, percent=80)


def benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark window occurs."""
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the mix takes, with size, source_size, target and taken."""
    mixed = mixing.mix_sources(docs, whole_rows=True).filter("taken > 0")
    added = [F.col(c).alias(free_name(docs, c)) for c in ("size", "source_size", "target", "taken")]
    return mixed.select("row.*", *added)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language", language),
    ("exact_copies", exact_copies),
    ("near_copies", near_copies),
    ("benchmark_passages", benchmark_passages),
    ("source_mix", source_mix),
]

#: SQL cannot express the first stage's model.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each stage's result written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
