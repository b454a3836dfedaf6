"""Ranks and running sums over a total order without a single-partition window.

Rows are range-partitioned on the order, numbered or summed inside each partition, and shifted by the totals of
the partitions before. Only one row per (partition, group) takes part in the second step. Put a tie-break such as
an id at the end of the order: it also spreads a hot key over several partitions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from seqvault.operators.barrier import barrier

PART = "_part"


def place_by_range(df: DataFrame, order: list[Column | str], tag: str = "placed") -> DataFrame:
    """``df`` range-partitioned on ``order`` with the partition number in ``_part``, written once.

    The bounds come from sampling, so the placement is materialised: two evaluations could differ.
    """
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return barrier(df.repartitionByRange(parts, *order).withColumn(PART, F.spark_partition_id()), tag)


def _carry(totals: DataFrame, group: list[str], value: str) -> DataFrame:
    """Sum of ``value`` over the earlier partitions of each group; a few rows per partition."""
    before = Window.partitionBy(*group).orderBy(PART).rowsBetween(Window.unboundedPreceding, -1)
    return totals.withColumn("_before", F.coalesce(F.sum(value).over(before), F.lit(0).cast("long"))).drop(value)


def running_sum(placed: DataFrame, group: list[str], order: list[Column | str], value: str, out: str) -> DataFrame:
    """Add ``out``: the inclusive running sum of the BIGINT column ``value`` in ``order`` within ``group``.

    ``placed`` comes from :func:`place_by_range` on ``group`` + ``order``. Group columns must not be null.
    """
    inside = Window.partitionBy(*group, PART).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    totals = placed.groupBy(*group, PART).agg(F.sum(value).alias("_total"))
    carried = _carry(totals, group, "_total")
    return (
        placed.withColumn("_inside", F.sum(value).over(inside))
        .join(carried, [*group, PART])
        .withColumn(out, F.col("_inside") + F.col("_before"))
        .drop("_inside", "_before")
    )


def row_numbers(placed: DataFrame, order: list[Column | str], out: str) -> DataFrame:
    """Add ``out``: 0-based row number in ``order`` over all rows of a placed table."""
    inside = Window.partitionBy(PART).orderBy(*order)
    totals = placed.groupBy(PART).agg(F.count(F.lit(1)).alias("_total"))
    carried = _carry(totals.withColumn("_all", F.lit(0)), ["_all"], "_total").drop("_all")
    return (
        placed.withColumn("_inside", F.row_number().over(inside).cast("long") - 1)
        .join(carried, PART)
        .withColumn(out, F.col("_inside") + F.col("_before"))
        .drop("_inside", "_before")
    )


def group_starts(placed: DataFrame, keys: list[str], order: list[Column | str], start: str, size: str) -> DataFrame:
    """Add ``start``, the row number over all of the first row with the same ``keys``, and ``size``, how many have them.

    ``placed`` comes from :func:`place_by_range` on ``order``, of which ``keys`` (without nulls) are the beginning, so a
    group may lie in several partitions. Groups are numbered inside partitions; only the first and the last group of a
    partition can go on in others, and these, two rows a partition, are put together on the driver.
    """
    spark = placed.sparkSession
    key = F.struct(*keys)
    ends = placed.groupBy(PART).agg(F.min(key).alias("_first"), F.max(key).alias("_last"), F.count(F.lit(1)).alias("_all"))
    edge = placed.join(F.broadcast(ends), PART).filter((key == F.col("_first")) | (key == F.col("_last")))
    counted = edge.groupBy(PART, *keys, "_all", (key == F.col("_first")).alias("_is_first")).agg(F.count(F.lit(1)).alias("_n")).collect()
    counted.sort(key=lambda r: (r[PART], not r["_is_first"]))
    groups: dict[tuple, list[int]] = {}
    bases: dict[int, int] = {}
    rows, base, seen = [], 0, 0
    for r in counted:
        if r[PART] not in bases:
            base, seen = base + seen, r["_all"]
            bases[r[PART]] = base
        name = tuple(r[k] for k in keys)
        at = base if r["_is_first"] else base + r["_all"] - r["_n"]
        groups.setdefault(name, [at, 0])[1] += r["_n"]
        rows.append((r[PART], name))
    fields = [f for f in placed.schema.fields if f.name in (PART, *keys)]
    fields = [next(f for f in fields if f.name == n) for n in (PART, *keys)]
    long = [StructField(n, LongType()) for n in ("_from", "_size")]
    edges = F.broadcast(spark.createDataFrame([(part, *name, *groups[name]) for part, name in rows], StructType([*fields, *long])))
    starts = F.broadcast(spark.createDataFrame(list(bases.items()), f"{PART} int, _base long"))
    inside = Window.partitionBy(PART).orderBy(*order)
    mine = Window.partitionBy(PART, *keys)
    local = placed.withColumn("_at", F.row_number().over(inside).cast("long") - 1).withColumns({"_low": F.min("_at").over(mine), "_here": F.count(F.lit(1)).over(mine)})
    joined = local.join(starts, PART).join(edges, [PART, *keys], "left")
    return joined.withColumns({start: F.coalesce("_from", F.col("_low") + F.col("_base")), size: F.coalesce("_size", "_here")}).drop("_at", "_low", "_here", "_base", "_from", "_size")
