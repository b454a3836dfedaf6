"""Parts of copies take little room, and little of them is in a row group."""

from __future__ import annotations

import pyarrow.dataset as ds
import pyarrow.parquet as pq
from pyspark.sql import functions as F

from seqvault import workloads


def test_parts_of_copies_on_disk(spark):
    made = workloads.parts(spark, "/root/testdata/sf0.01", "random500")
    files = [f.removeprefix("file://") for f in made.inputFiles()]
    groups = [(g.num_rows, g.column(2).total_uncompressed_size) for f in files for m in [pq.ParquetFile(f).metadata] for g in map(m.row_group, range(m.num_row_groups))]
    assert sum(rows for rows, _ in groups) == made.count()
    assert max(size for _, size in groups) < 16 << 20
    stored = sum(ds.dataset(f).filesystem.get_file_info(f).size for f in files)
    assert stored < made.agg(F.sum(F.length("seq"))).first()[0] / 10
