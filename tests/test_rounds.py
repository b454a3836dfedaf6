"""Rounds over the cluster leave resolved positions behind, and a task finishes the last of them."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pytest

from seqvault import bwt, suffix


def repetitive(seed: int) -> np.ndarray:
    rng = np.random.default_rng(seed)
    piece = rng.integers(1, 4, 150)
    return np.concatenate([piece, rng.integers(1, 4, 40), piece, np.full(50, 2), piece[20:], [0]])


@pytest.mark.parametrize("held", [0, 300, 1 << 20])
def test_rounds_over_what_is_shared(spark, held, monkeypatch):
    """Three shards with long repetitions: same rows as in a task, and later rounds are written without resolved positions."""
    texts = {0: repetitive(1), 1: repetitive(2), 2: np.array([1, 0])}
    rows = pd.concat([pd.DataFrame({"shard": np.int32(s), "pos": np.arange(len(t)), "sym": t}) for s, t in texts.items()])
    sizes = []
    barrier = suffix.barrier

    def counted(df, tag):
        out = barrier(df, tag)
        sizes.extend([out.count()] * (tag == "met"))
        return out

    monkeypatch.setattr(suffix, "barrier", counted)
    got = bwt.range_sorted(spark.createDataFrame(rows, "shard int, pos long, sym long"), 4, held).toPandas().sort_values(["shard", "row"])
    for s, t in texts.items():
        order = suffix.suffix_order_kernel(t)
        mine = got[got["shard"] == s]
        assert mine["row"].tolist() == list(range(len(t))) and mine["pos"].tolist() == order.tolist() and mine["sym"].tolist() == t[order - 1].tolist()
    n = sum(map(len, texts.values()))
    assert sizes[:1] == ([] if held > n else [n]) and all(a > b for a, b in zip(sizes, sizes[1:], strict=False))
    assert len(sizes) >= 4 if not held else held < n or not sizes
