"""A unique key for every row of a table of documents."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.operators.barrier import barrier

ROW, DOC = "_row", "_doc"


def with_row_key(docs: DataFrame) -> DataFrame:
    """``_row``, doc_id, text, source and ``_doc``: the whole row of ``docs``, packed so that no column name can clash.

    The key is the id where ids are unique and not null, else a number given once and written. Only ids are looked at for
    that. Numbers follow no order; rows that are equal in all columns stay apart.
    """
    packed = docs.select("doc_id", "text", "source", F.struct(*docs.columns).alias(DOC))
    ids = docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    if ids.filter("n > 1 or doc_id is null").isEmpty():
        return packed.withColumn(ROW, F.col("doc_id").cast("long"))
    return barrier(packed.withColumn(ROW, F.monotonically_increasing_id()), "numbered")


def unpacked(rows: DataFrame) -> DataFrame:
    """The original rows, with their columns, of packed ones."""
    return rows.select(f"{DOC}.*")
