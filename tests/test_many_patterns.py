"""Many patterns: planned as arrays, blocks opened side by side, and patterns that shards read from the shared folder."""

from __future__ import annotations

import random

import numpy as np
import pytest

from seqvault import blocks as B
from seqvault import fm, index, planner, suffix
from seqvault.alphabet import Alphabet
from seqvault.baselines.scan import scan_locate
from seqvault.index import IndexParams, build_index
from seqvault.operators.barrier import scratch_path

KEY = bytes(range(64))


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("k", [1, 2, 4])
def test_planned_lots_hold_the_displaced_patterns(k):
    alphabet = Alphabet(tuple("ACGNTé"), k)
    patterns = ["ACGTACGTA", "", "A", "xA", "ACéGT", "ACGT", "NN"]
    lot = planner.planned_lot(tuple(patterns), alphabet)
    at = 0
    for i, pattern in enumerate(patterns):
        digits = alphabet.digits(pattern)
        if not len(digits) or (digits < 0).any():
            assert i not in lot.pattern
            continue
        for p in planner.displaced(digits, k):
            assert (lot.pattern[at], lot.d[at], lot.m[at]) == (i, p.d, p.m)
            first, last = p.first_masked or p.m == 1, p.last_masked and p.m > 1
            assert (lot.first[at] >= 0, lot.last[at] >= 0) == (first, last)
            assert not first or lot.masks[lot.first[at]].tolist() == p.parts[0].tolist()
            assert not last or lot.masks[lot.last[at]].tolist() == p.parts[-1].tolist()
            assert lot.ids[lot.begin[at] : lot.end[at]].tolist() == alphabet.of_digits(p.parts[int(first) : p.m - int(last)]).tolist()
            at += 1
    assert at == len(lot.m)


def test_scattered_blocks_open_side_by_side():
    text = np.random.default_rng(2).integers(0, 40, 900)
    sealed = B.encode_blocks(text, 64, bytes(32), B.Coding())
    some = [13, 2, 7, 9]
    got = B.decode_blocks([sealed[b] for b in some], np.array(some), bytes(32), B.Coding())
    assert [x.tolist() for x in got] == [text[64 * b : 64 * b + 64].tolist() for b in some]


def test_patterns_read_from_the_shared_folder(spark, monkeypatch):
    rng = random.Random(5)
    texts = ["".join(rng.choices("ACGT", k=rng.randrange(1, 400))) for _ in range(30)]
    items = spark.createDataFrame(list(enumerate(texts)), "item_no long, seq string")
    cuts = [t[i : i + n] for t in texts[:9] for i in (0, 3, 50) for n in (2, 9, 17)] + ["ACGTNNN", None, texts[0][:9]]
    patterns = spark.createDataFrame(list(enumerate(cuts)), "pattern_id long, pattern string").filter("pattern is null or pattern <> ''")
    built = build_index(items, IndexParams(k=2, bs=64, shard_symbols=900), KEY, scratch_path(spark, "many"))
    monkeypatch.setattr(index, "MOST", 7)
    monkeypatch.setattr(index.Index, "prune_shards", None)  # makes a row for each pattern and shard
    monkeypatch.setattr(fm, "LOT_LETTERS", 40)
    got = built.locate(patterns.unionByName(patterns.limit(3)))
    assert rows(got) == rows(scan_locate(items, patterns).select("pattern_id", "item_no", "offset"))
    assert rows(built.exists(patterns).select("pattern_id")) == rows(got.select("pattern_id").distinct())


def test_orders_with_and_without_packed_keys_agree(monkeypatch):
    rng = np.random.default_rng(4)
    for n in (1, 2, 30, 3000):
        text = np.tile(rng.integers(1, 9, -(-n // 5)), 5)[:n]
        text[-1] = 0
        packed = suffix.suffix_order_kernel(text, 9)
        turned = np.append(text, text)
        assert n > 30 or packed.tolist() == sorted(range(n), key=lambda i: turned[i : i + n].tolist())
        monkeypatch.setattr(suffix, "PACKED", 0)
        assert suffix.suffix_order_kernel(text, 9).tolist() == packed.tolist()
        monkeypatch.undo()
