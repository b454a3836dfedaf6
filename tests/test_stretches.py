"""Copies in parts: the same copies, windows and hits as whole ones, and no row that holds a copy or the reference."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from seqvault import queries, workloads
from seqvault.baselines.plain_fm import PlainFM
from seqvault.baselines.scan import scan_locate
from seqvault.index import IndexParams, build_index
from seqvault.operators.barrier import barrier, scratch_path
from seqvault.sources import views

KEY = bytes(range(64))


def rows(df):
    return sorted(map(tuple, df.collect()))


def whole(parts):
    joined = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("start", "seq"))), lambda s: s["seq"]), "")
    return parts.groupBy("item_no").agg(joined.alias("seq"))


@pytest.fixture(scope="module")
def copies(spark, sf):
    return barrier(views.variant_collection(views.reference(spark, sf, "src1"), 6, 99), "copies")


@pytest.fixture(scope="module")
def parts(spark, sf):
    return barrier(views.variant_stretches(spark, sf, "src1", 6, 99, 1000), "parts")


@pytest.mark.parametrize("size", [40, 1000, 1 << 16])
def test_parts_are_the_copies(spark, sf, copies, size):
    got = barrier(views.variant_stretches(spark, sf, "src1", 6, 99, size), "parts")
    assert rows(whole(got)) == rows(copies)
    longest, last = got.agg(F.max(F.length("seq")), F.max("start")).first()
    assert longest <= size + 16 * (1 + size // 20) and (last > 0 or size == 1 << 16)
    ends = got.groupBy("item_no").agg(F.sum(F.length("seq")).alias("all"), F.max(F.col("start") + F.length("seq")).alias("end"))
    assert ends.filter(F.col("all") != F.col("end")).isEmpty()


def test_copies_of_no_document_are_empty(spark, sf):
    assert rows(views.variant_stretches(spark, sf, "no such source", 3, 1)) == [(v, 0, "") for v in range(3)]


def test_windows_and_hits_are_those_of_whole_copies(spark, copies, parts):
    windows = views.sample_windows(parts, [15, 100, 400], 20)
    assert rows(windows) == rows(views.sample_windows(copies, [15, 100, 400], 20))
    want = rows(scan_locate(copies, windows).select("pattern_id", "item_no", "offset"))
    index = build_index(parts, IndexParams(k=3, bs=256, shard_symbols=1500, piece=700, overlap=400), KEY, scratch_path(spark, "parts"))
    assert rows(index.locate(windows)) == want
    assert rows(PlainFM.build(parts, shard_symbols=4000, piece=700, overlap=400).locate(windows)) == want


def test_parts_make_indexes_of_pieces_only(spark, parts):
    for build in (lambda: build_index(parts, IndexParams(), KEY, scratch_path(spark, "parts")), lambda: PlainFM.build(parts)):
        with pytest.raises(ValueError, match="pieces"):
            build()


def test_the_searches_read_parts(spark, sf):
    name = "consensus_b"
    assert "start" in queries._parts(spark, sf, name).columns
    assert queries._parts(spark, sf, name).select("item_no").distinct().count() == workloads.STAND_INS[name][1]
