"""A corpus from raw documents to packed sequences.

Every stage takes (spark, docs, sf_dir), where docs is what its predecessor kept, and returns a DataFrame;
all but the last return the columns of the documents.

Defined results.  A row without an id is scored, cleaned and packed like any other, is nobody's near-duplicate and
is never found contaminated.  Rows that share an id and a text are kept or dropped together until near-duplicates
are removed, which keeps every row that has the kept id; a null text scores as an empty one.  An empty table passes
every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tokenlink.llm import decontamination, linededup, neardup, packing, quality
from tokenlink.llm.scratch import materialize, table


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject."""
    marked = quality.classify(docs, table(spark, sf_dir, "labels"))
    return marked.where("predicted = 1").select(docs.columns)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the boilerplate lines of their source, near-duplicates counting once; n_chars follows the text."""
    return linededup.drop_boilerplate(docs, counts=False, classes=neardup.near_duplicates(docs)).selectExpr(*[f"cast(length(text) as bigint) AS {c}" if c == "n_chars" else c for c in docs.columns])


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates (five-word shingles, similarity 0.8)."""
    return neardup.keep_one(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without passages of the benchmark."""
    return decontamination.clean(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents and their places in sequences."""
    return packing.pack(docs)


STAGES = [
    ("quality_classifier", quality_filter),
    ("line_dedup", line_dedup),
    ("minhash_near_dedup", near_dedup),
    ("benchmark_decontamination", decontaminate),
    ("best_fit_packing", pack),
]

#: The classifier and the tokenizer cannot be expressed in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
