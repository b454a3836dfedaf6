"""Choosing labelled training rows and applying a small model to every row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def held_out(doc_id: Column) -> Column:
    """Rows that no model learns from: crc32 of the id's text divisible by 5 (a null id counts as empty text)."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 5 == 0


def training_rows(docs: DataFrame, labels: DataFrame, label: str, bound: int) -> DataFrame:
    """At most ``bound`` labelled documents that are not held out: doc_id, text, y.

    They are those with the smallest hash of their id, so the choice does not depend on order or partitioning. Null
    labels do not count; an id with contradicting labels takes the larger. An id that stands on several rows of ``docs``
    gives one of them, the least text, so the bound holds for rows too. It also limits what is broadcast.
    """
    known = labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    one = known.groupBy(F.col("doc_id").alias("_id")).agg(F.max(F.col(label).cast("int")).alias("y"))
    chosen = one.orderBy(F.xxhash64("_id"), "_id").limit(bound)
    found = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("_id"))
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # few bytes, but work for many tasks
    return found.repartition(parts, "doc_id").groupBy("doc_id", "y").agg(F.min("text").alias("text")).select("doc_id", "text", "y")
