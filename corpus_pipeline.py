"""A training corpus in five stages: toxicity, near duplicates, benchmark leaks, source weights, token files.

Each stage takes what the one before kept, as Parquet. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from seqvault.llm import decontaminate, mixing, simhash_trie, token_file, toxicity
from seqvault.llm.queries import vocabulary
from seqvault.operators.barrier import barrier
from seqvault.session import ship_package
from seqvault.sources.tables import table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the documents that the toxicity classifier, learned from the labelled rows of ``docs``, rejects."""
    ship_package(spark)
    return toxicity.keep_clean(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, with the smallest id, of each group of near duplicates: SimHash candidates, verified exactly."""
    ship_package(spark)
    return simhash_trie.one_of_each(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without documents that hold a benchmark item."""
    return decontaminate.decontaminated(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the target weights of the sources take them."""
    return mixing.mixed_documents(docs)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files of the mix, and their digest read back: doc_id, start, n_tokens, ids_crc32 of each document taken."""
    ship_package(spark)
    # workers live through all stages here, so they remember fewer words than where they only make tokens
    return token_file.write_token_files(docs, vocabulary(), memo=150_000).digest()


STAGES = [
    ("toxicity", drop_toxic),
    ("near duplicates", drop_near_duplicates),
    ("decontamination", drop_leaks),
    ("mixing", mix_sources),
    ("token files", write_tokens),
]

#: SQL can't express the trained model, the fingerprints or the tokens.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = barrier(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
