"""Brute-force search: the ground truth. Every item is compared with every pattern it contains."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def scan_locate(items: DataFrame, patterns: DataFrame) -> DataFrame:
    """pattern_id, item_no, offset by scanning. The few patterns go to every task; a containment test precedes positions.

    Positions are found in Arrow batches, in one walk over an item: SQL's substring counts characters from the start for
    every position of a long item.
    """
    held = items.select("item_no", "seq").join(F.broadcast(patterns.select("pattern_id", "pattern")), F.col("seq").contains(F.col("pattern")) & (F.col("pattern") != ""))

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple[int, int, int]] = []
            for number, item, pattern, seq in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                at = seq.find(pattern)
                while at >= 0:
                    out.append((number, item, at))
                    at = seq.find(pattern, at + 1)
            yield pa.record_batch([pa.array([o[i] for o in out], pa.int64()) for i in range(3)], names=["pattern_id", "item_no", "offset"])

    return held.select(F.col("pattern_id").cast("long"), F.col("item_no").cast("long"), "pattern", "seq").mapInArrow(places, "pattern_id long, item_no long, offset long")


def scan_sql(items: str, patterns: str) -> str:
    """A CTE ``hits`` over CTEs of items (item_no, seq) and patterns (pattern_id, pattern)."""
    return f"""hits AS (
  SELECT pattern_id, item_no, CAST(o AS BIGINT) AS "offset" FROM (
    SELECT p.pattern_id, i.item_no, unnest([o FOR o IN range(0, length(i.seq) - length(p.pattern) + 1) IF substr(i.seq, CAST(o AS INT) + 1, length(p.pattern)) = p.pattern]) AS o
    FROM {items} i JOIN {patterns} p ON contains(i.seq, p.pattern) AND p.pattern <> ''
  )
)"""
