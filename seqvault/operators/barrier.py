"""Cut lineage by writing a table to the shared folder and reading it back.

A written table survives lost executors, has column statistics for the next plan and fixes partition-dependent
values (range bounds, partition numbers), which a second evaluation of the same plan could draw anew.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame

from seqvault.session import shared_dir


def scratch_path(spark, tag: str) -> str:
    """A new path below the shared folder."""
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex[:12]}"


#: Bytes of a row group of tables whose rows are long texts: Spark's reader holds a row group's texts, and as much again while
#: it makes room for them, in one array of each task, and such arrays fill the heap long before it is full.
GROUP_BYTES = 4 << 20
#: The same where rows are near copies and compressed together: a group's size is what it takes compressed, a fiftieth of its texts.
COPIES_BYTES = 1 << 16


def barrier(df: DataFrame, tag: str, group_bytes: int | None = None, codec: str | None = None) -> DataFrame:
    """Materialise ``df`` in the shared folder; the result reads only that table. ``group_bytes``: of a row group of it;
    ``codec``: its compression."""
    spark = df.sparkSession
    path = scratch_path(spark, tag)
    given = {"parquet.block.size": group_bytes, "compression": codec}
    df.write.options(**{k: v for k, v in given.items() if v}).parquet(path)
    return spark.read.schema(df.schema).parquet(path)
