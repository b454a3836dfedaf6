"""Times, hits and touched blocks of patterns, measured in one pass over a shard."""

from __future__ import annotations

import pytest
from test_index import KEY, brute, frames, some_items, some_patterns

from seqvault import index, measures
from seqvault.index import IndexParams, build_index
from seqvault.operators.barrier import scratch_path


def test_times_and_blocks_of_the_same_searches(spark, monkeypatch):
    items = some_items(23)
    patterns = some_patterns(items, 23)
    df, asked = frames(spark, items, patterns)
    made = build_index(df, IndexParams(k=2, bs=8, mark_pct=20, shard_symbols=60), KEY, scratch_path(spark, "test"))
    hits = {number: 0 for number, _ in patterns} | {n: sum(h[0] == n for h in brute(items, patterns)) for n, _ in patterns}
    share = dict(map(tuple, measures.loaded_share(made, asked).collect()))
    for pairs in (index.PAIRS, 0):  # with 0, tasks read the patterns from the shared folder
        monkeypatch.setattr(index, "PAIRS", pairs)
        rows = measures.searched(made, asked)
        assert {r[0]: r[2] for r in rows} == hits
        assert {r[0]: r[3] for r in rows} == pytest.approx(share)
    assert made._asked_of(asked, len(patterns), False)[0].columns == ["shard", "commit", "_chunk"]
