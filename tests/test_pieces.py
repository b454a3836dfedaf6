"""Indexes of pieces give the hits that the whole items have."""

from __future__ import annotations

import random

import pytest

from seqvault import workloads
from seqvault.baselines.plain_fm import PlainFM
from seqvault.baselines.scan import scan_locate
from seqvault.index import IndexParams, build_index
from seqvault.operators.barrier import scratch_path

KEY = bytes(range(64))


@pytest.fixture(scope="module")
def items(spark):
    rng = random.Random(3)
    base = "".join(rng.choices("ACGT", k=700)) * 2
    rows = [(0, base), (1, base[5:1100] + "N" + base[1100:]), (7, "ACGTAC"), (9, ""), ((1 << 40) - 1, base[:400])]
    return spark.createDataFrame(rows, "item_no long, seq string")


@pytest.fixture(scope="module")
def patterns(spark, items):
    whole = items.filter("item_no = 1").first()["seq"]
    cuts = [whole[i : i + n] for i in range(85, 110) for n in (1, 3, 9, 30, 33)] + [whole[-33:], "ACGTAC", "TTTTTTTTTTTTTTTTT", ""]
    return spark.createDataFrame(list(enumerate(cuts)), "pattern_id long, pattern string").filter("pattern <> ''")


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_pieces_give_the_hits_of_whole_items(spark, items, patterns):
    want = rows(scan_locate(items, patterns).select("pattern_id", "item_no", "offset"))
    counts = {}
    for pattern, *_ in want:
        counts[pattern] = counts.get(pattern, 0) + 1
    wanted = sorted((r[0], counts.get(r[0], 0)) for r in patterns.collect())
    index = build_index(items, IndexParams(k=3, bs=64, shard_symbols=80, piece=100, overlap=32), KEY, scratch_path(spark, "pieces"))
    assert rows(index.locate(patterns)) == want
    assert rows(index.count(patterns)) == wanted
    assert index.table("items").groupBy("shard").sum("n_sym").agg({"sum(n_sym)": "max"}).first()[0] < 160
    plain = PlainFM.build(items, shard_symbols=300, piece=100, overlap=32)
    assert rows(plain.locate(patterns)) == want
    assert rows(plain.count(patterns)) == wanted
    assert {r[0] for r in index.search_times(patterns).groupBy("pattern_id").sum("hits").filter("`sum(hits)` > 0").collect()} == set(counts)


def test_what_pieces_cannot_answer_is_refused(spark, items):
    index = build_index(items, IndexParams(k=2, bs=64, piece=100, overlap=20), KEY, scratch_path(spark, "pieces"))
    longer = spark.createDataFrame([(1, "A" * 22)], "pattern_id long, pattern string")
    with pytest.raises(ValueError, match="letters"):
        index.locate(longer)
    for call in (index.restore, lambda: index.extract(longer), lambda: index.append(items)):
        with pytest.raises(ValueError, match="pieces"):
            call()
    with pytest.raises(ValueError, match="numbers"):
        build_index(items.selectExpr("item_no - 1 AS item_no", "seq"), IndexParams(piece=100), KEY, scratch_path(spark, "pieces"))


def test_a_shard_of_a_stand_in_is_a_stretch_of_all_copies(spark, sf):
    params = workloads.in_pieces(IndexParams(shard_symbols=1 << 12), "consensus_b")
    items = workloads.collection(spark, sf, "consensus_b")
    index = build_index(items, params, KEY, scratch_path(spark, "pieces"))
    sizes = index.table("items").groupBy("shard").sum("n_sym").collect()
    assert len(sizes) > 1 and max(r[1] for r in sizes) < 3 * params.shard_symbols + 50 * 200
