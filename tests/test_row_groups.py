"""Tables of long texts are written in small row groups, which Spark's reader holds at once."""

from __future__ import annotations

from urllib.parse import unquote, urlparse

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import functions as F

from seqvault import workloads
from seqvault.operators.barrier import GROUP_BYTES


def test_parts_lie_in_small_row_groups(spark, tmp_path):
    """50 copies of a million letters, in four files."""
    text = "".join(np.random.default_rng(3).choice(list("abcdefgh"), 1 << 20))
    row = pa.table({"doc_id": pa.array([1], pa.int64()), "text": [text], "lang": ["en"], "source": ["src1"], "n_chars": pa.array([len(text)], pa.int64())})
    pq.write_table(row, tmp_path / "documents.parquet")
    parts = workloads.parts(spark, str(tmp_path), "consensus_b")
    found = [pq.ParquetFile(unquote(urlparse(f).path)).metadata for f in parts.inputFiles()]
    assert max(m.row_group(i).total_byte_size for m in found for i in range(m.num_row_groups)) <= 2 * GROUP_BYTES
    assert sum(m.num_rows for m in found) == parts.count() == 50 * 16
