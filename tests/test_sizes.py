"""Grids of block sizes, sizes of one pass, and coding whose time does not grow with the alphabet."""

from __future__ import annotations

import time
from pathlib import Path

import numpy as np
from test_index import KEY, brute, frames, some_items, some_patterns

from seqvault import blocks, encode, measures, workloads
from seqvault.alphabet import collect_alphabet
from seqvault.baselines import compressors
from seqvault.baselines.plain_fm import PlainFM, collection_sizes
from seqvault.index import IndexParams, build_index
from seqvault.operators import prefix
from seqvault.operators.barrier import barrier, scratch_path


def _seconds(run) -> float:
    out = []
    for _ in range(3):
        began = time.perf_counter()
        run()
        out.append(time.perf_counter() - began)
    return min(out)


def test_coding_takes_no_longer_for_a_large_alphabet():
    rng = np.random.default_rng(3)
    small, large = (rng.integers(0, n, 1 << 16) for n in (200, 14_000))
    sealed = [blocks.encode_blocks(x, 1 << 15, bytes(32), blocks.Coding()) for x in (small, large)]
    assert _seconds(lambda: blocks.encode_blocks(large, 1 << 15, bytes(32), blocks.Coding())) < 4 * _seconds(lambda: blocks.encode_blocks(small, 1 << 15, bytes(32), blocks.Coding()))
    assert (np.concatenate(blocks.decode_blocks(sealed[1], 0, bytes(32), blocks.Coding())) == large).all()
    codes = np.concatenate([blocks.remap_local(large[i : i + 1000])[1] for i in range(0, len(large), 1000)])
    want = [blocks.mtf(codes[i : i + 1000], 1000) for i in range(0, len(codes), 1000)]
    assert (blocks.mtf_many(codes, np.arange(0, len(codes), 1000), 1000) == np.concatenate(want)).all()


def test_grid_measures_and_leaves_nothing(spark):
    items = some_items(21)
    df, asked = frames(spark, items, some_patterns(items, 21))
    want, paths = brute(items, asked.collect()), []
    for made in workloads._grid(df, (2, 3), (8, 32), IndexParams(mark_pct=20, shard_symbols=60), collect_alphabet(df)):
        plain = build_index(df, made.params, workloads.DEMO_KEY, scratch_path(spark, "test"))
        assert sorted(map(tuple, made.locate(asked).collect())) == want
        assert made.sizes() == (measures.index_bytes(made), made.stored_bytes())
        assert made.sizes()[0] == measures.index_bytes(plain)
        paths.append((made.path, made.meta["k"], made.meta["bs"]))
    assert [p[1:] for p in paths] == [(2, 8), (2, 32), (3, 8), (3, 32)]
    assert not any(Path(p[0].removeprefix("file://")).exists() for p in paths)


def test_shards_of_equal_numbers_and_no_text_written(spark, monkeypatch):
    rows = [(i // 2, "ACGT" * (i + 1)) for i in range(20)] + [(50, "")]
    written = []
    monkeypatch.setattr(prefix, "barrier", lambda df, tag, *a: written.append(df.columns) or barrier(df, tag, *a))
    monkeypatch.setattr(encode, "barrier", lambda df, tag, *a: written.append(df.columns) or barrier(df, tag, *a))
    planned = encode.plan_shards(spark.createDataFrame(rows, "item_no long, seq string"), 2, 30).collect()
    assert sorted((r["item_no"], r["seq"]) for r in planned) == sorted(rows)
    assert [r["shard"] for r in sorted(planned)] == sorted(r["shard"] for r in planned) and len({r["shard"] for r in planned}) > 5
    assert written and not any("seq" in columns for columns in written)


def test_comparison_methods_of_one_sort(spark):
    items = some_items(22)
    df, _ = frames(spark, items, [])
    want = {
        "plain": PlainFM.build(df).bytes(),
        "block_compressor": compressors.bzip_collection(df).agg({"packed": "sum"}).first()[0],
        "transform_generic": compressors.bwt_generic(df)[0].selectExpr("sum(length(packed))").first()[0],
        "compress_encrypt": compressors.compress_then_encrypt(df, KEY).selectExpr("sum(length(packed))").first()[0],
    }
    assert collection_sizes(df, KEY, collect_alphabet(df)) == want


def test_sweep_rows(spark):
    items = some_items(24)
    df, asked = frames(spark, items, [(20_000_000, items[0][1][:3]), (20_000_001, items[1][1][:4])])
    rows = workloads.sweep(df, asked, (2,), (8, 16), IndexParams(mark_pct=20, shard_symbols=60))
    assert {(r["bs"], r["metric"]) for r in rows} == {(bs, m) for bs in (8, 16) for m in ("median_seconds", "seconds_per_hit", "mean_seconds", "loaded_percent", "ratio", "stored_ratio")}
