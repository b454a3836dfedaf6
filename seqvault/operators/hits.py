"""What a user does with hits: counts, ranks, gaps, co-occurrence, overlaps, cubes, windows and differences."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def reverse_complement(seq: Column) -> Column:
    return F.reverse(F.translate(seq, "ACGT", "TGCA"))


def both_strands(patterns: DataFrame) -> DataFrame:
    """Each pattern and its reverse complement under the same id; a palindrome once."""
    return patterns.select("pattern_id", "pattern").unionByName(patterns.select("pattern_id", reverse_complement(F.col("pattern")).alias("pattern"))).distinct()


def hits_per_item(hits: DataFrame) -> DataFrame:
    return hits.groupBy("pattern_id", "item_no").agg(F.count(F.lit(1)).alias("n"))


def top_items(hits: DataFrame, most: int) -> DataFrame:
    """The ``most`` items with most hits of each pattern; ties go to the smaller item."""
    best = Window.partitionBy("pattern_id").orderBy(F.desc("n"), "item_no")
    return hits_per_item(hits).withColumn("place", F.row_number().over(best)).filter(F.col("place") <= most)


def hit_gaps(hits: DataFrame) -> DataFrame:
    """Distance from each hit to the next of the same pattern in the same item."""
    ordered = Window.partitionBy("pattern_id", "item_no").orderBy("offset")
    return hits.withColumn("gap", F.lead("offset").over(ordered) - F.col("offset")).filter("gap is not null").select("pattern_id", "item_no", "offset", "gap")


def cooccurrence(hits: DataFrame, within: int) -> DataFrame:
    """Pairs of different patterns that start within ``within`` characters in an item.

    Joined on the item and a bin of the offset, with the neighbouring bins on one side, so an item full of hits is not
    one group.
    """
    left = hits.select(F.col("pattern_id").alias("a"), "item_no", F.col("offset").alias("at_a"), F.floor(F.col("offset") / (within + 1)).alias("bin"))
    right = hits.select(F.col("pattern_id").alias("b"), "item_no", F.col("offset").alias("at_b"), F.explode(F.array(*[F.floor(F.col("offset") / (within + 1)) + d for d in (-1, 0, 1)])).alias("bin"))
    return left.join(right, ["item_no", "bin"]).filter((F.col("a") < F.col("b")) & (F.abs(F.col("at_a") - F.col("at_b")) <= within)).select("a", "b", "item_no", "at_a", "at_b")


def hits_cube(hits: DataFrame, items: DataFrame) -> DataFrame:
    """Hits by language, source and pattern length, with all totals."""
    joined = hits.join(items.select("item_no", "lang", "source"), "item_no").withColumn("len", F.floor(F.col("pattern_id") / 1_000_000))
    return joined.cube("lang", "source", "len").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("level"))


def anti_items(items: DataFrame, hits: DataFrame) -> DataFrame:
    """Items without any hit."""
    return items.select("item_no").join(hits, "item_no", "left_anti")


def overlapping(hits: DataFrame, length: int) -> DataFrame:
    """Hits whose span begins inside the span of an earlier hit of the same item."""
    ordered = Window.partitionBy("item_no").orderBy("offset", "pattern_id").rowsBetween(Window.unboundedPreceding, -1)
    return hits.withColumn("reach", F.max(F.col("offset") + length).over(ordered)).filter(F.col("offset") < F.col("reach")).select("pattern_id", "item_no", "offset")


def pivot_lengths(hits: DataFrame, items: DataFrame, lengths: list[int]) -> DataFrame:
    """source, one column of hits for each pattern length; lengths are given, so no pass looks for them."""
    joined = hits.join(items.select("item_no", "source"), "item_no").withColumn("len", F.floor(F.col("pattern_id") / 1_000_000).cast("int"))
    table = joined.groupBy("source").pivot("len", lengths).agg(F.count(F.lit(1)))
    return table.select("source", *[F.coalesce(F.col(str(n)), F.lit(0)).cast("long").alias(f"hits_{n}") for n in lengths])


def unpivot_lengths(table: DataFrame, lengths: list[int]) -> DataFrame:
    """source, len, n of a pivoted table, without zeros."""
    return table.unpivot(["source"], [f"hits_{n}" for n in lengths], "len", "n").filter("n > 0")


def position_summary(hits: DataFrame) -> DataFrame:
    """Median and quartiles of the offsets of each pattern, and its items in order as one string."""
    q = lambda p: F.percentile("offset", F.lit(p))
    return hits.groupBy("pattern_id").agg(F.round(q(0.25), 3).alias("q1"), F.round(q(0.5), 3).alias("median"), F.round(q(0.75), 3).alias("q3"), F.array_join(F.transform(F.sort_array(F.collect_set("item_no")), lambda x: x.cast("string")), ",").alias("items"))


def grouped_hits(hits: DataFrame, items: DataFrame) -> DataFrame:
    """Hits by (lang), by (source) and in all, by SQL grouping sets."""
    spark = hits.sparkSession
    joined = hits.join(items.select("item_no", "lang", "source"), "item_no")
    return spark.sql("SELECT lang, source, count(*) AS n FROM {rows} GROUP BY GROUPING SETS ((lang), (source), ())", rows=joined)
