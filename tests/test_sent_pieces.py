"""Pieces of similar items are sent in little more room than one of them."""

from __future__ import annotations

import random

from pyspark.sql import functions as F

from seqvault.pieces import cut_items, joined


def test_pieces_of_copies_are_compressed_together(spark):
    rng = random.Random(4)
    base = "".join(rng.choices("ACGT", k=20_000))
    rows = [(i, f"s{i}", start, base[start : start + 7000]) for start in range(0, 20_000, 7000) for i in range(40)]
    items = spark.createDataFrame(rows, "item_no long, seq_id string, start long, seq string").coalesce(1)
    sent = cut_items(items, 4000, 100, 40 * 4000)
    assert sent.agg(F.sum(F.length("pieces"))).first()[0] < 40 * 20_000 / 8
    assert sent.rdd.getNumPartitions() == int(spark.conf.get("spark.sql.shuffle.partitions"))
    got = {}
    for shard in range(5):
        numbers, names, texts = joined(sent.filter(F.col("shard") == shard).toArrow())
        assert len(numbers) == 40 and names[3] == f"s3:{shard}"
        got |= dict(zip(numbers, texts, strict=True))
    assert {(n >> 40, n & 1023): t for n, t in got.items()} == {(p, i): base[p * 4000 : p * 4000 + 4100] for p in range(5) for i in range(40)}
