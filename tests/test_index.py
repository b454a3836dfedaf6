import random

import pytest

from seqvault import cipher
from seqvault.baselines.csa import csa_locate
from seqvault.baselines.plain_fm import PlainFM
from seqvault.baselines.scan import scan_locate
from seqvault.fm import WrongKey
import seqvault.index as index_module
from seqvault.index import Index, IndexParams, build_index
from seqvault.operators.barrier import scratch_path

KEY = bytes(range(64))


def some_items(seed, letters="ACGTN", n=14):
    rnd = random.Random(seed)
    seqs = ["".join(rnd.choice(letters) for _ in range(rnd.choice([0, 1, 2, 3, 7, 20, 60]))) for _ in range(n)]
    return [(i * 3, s) for i, s in enumerate([*seqs, seqs[-1], letters[-1] * 40])]


def some_patterns(items, seed, n=50):
    rnd = random.Random(seed)
    out = ["X", "AX"]
    while len(out) < n:
        seq = rnd.choice(items)[1]
        size = rnd.randint(1, 11)
        if len(seq) >= size:
            at = rnd.randint(0, len(seq) - size)
            out.append(seq[at : at + size])
    return list(enumerate(out))


def brute(items, patterns):
    return sorted((p, i, o) for p, x in patterns for i, s in items for o in range(len(s) - len(x) + 1) if s[o : o + len(x)] == x)


def frames(spark, items, patterns):
    return spark.createDataFrame(items, "item_no long, seq string"), spark.createDataFrame(patterns, "pattern_id long, pattern string")


VARIANTS = [
    IndexParams(k=1, bs=8, mark_pct=100),
    IndexParams(k=2, bs=16, shard_symbols=40, strategy="runs"),
    IndexParams(k=3, bs=64, scramble=False, encrypt=False, strategy="ranges"),
    IndexParams(k=4, bs=16, mark_pct=10, cipher_mode="xor", rounds=12),
    IndexParams(k=5, bs=4096, checksum=True),
]


@pytest.mark.parametrize("params", VARIANTS, ids=lambda p: f"k{p.k}")
def test_every_variant_equals_brute_force(spark, params):
    items = some_items(params.k)
    patterns = some_patterns(items, params.k)
    df, asked = frames(spark, items, patterns)
    path = scratch_path(spark, "test")
    build_index(df, params, KEY, path)
    index = Index.open(spark, path, KEY)
    want = brute(items, patterns)
    for last in ("auto", "verify", "enumerate", "naive"):
        assert sorted(map(tuple, index.locate(asked, last, pruned=last == "verify").collect())) == want, last
    counts = dict(map(tuple, index.count(asked).collect()))
    assert counts == {p: sum(w[0] == p for w in want) for p, _ in patterns}
    assert {r[0] for r in index.exists(asked).collect()} == {w[0] for w in want}
    assert sorted(map(tuple, index.restore().collect())) == sorted(items)
    asks = [(j, i, a, n) for j, (i, a, n) in enumerate((i, a, n) for i, _ in items for a, n in ((0, 5), (3, 100), (50, 2), (0, 0)))]
    got = dict(map(tuple, index.extract(spark.createDataFrame(asks, "req_id long, item_no long, start long, len long")).collect()))
    texts = dict(items)
    assert got == {j: texts[i][a : a + n] for j, i, a, n in asks}


def test_literal_rule_loses_only_hits_in_padded_blocks(spark):
    items = some_items(8)
    patterns = some_patterns(items, 8)
    df, asked = frames(spark, items, patterns)
    index = build_index(df, IndexParams(k=3, bs=16), KEY, scratch_path(spark, "test")).with_options(pad_wildcards=False)
    texts, sizes = dict(items), dict(patterns)
    kept = [(p, i, o) for p, i, o in brute(items, patterns) if not (len(texts[i]) % 3 and (o + len(sizes[p]) - 1) // 3 == (len(texts[i]) - 1) // 3)]
    assert sorted(map(tuple, index.locate(asked).collect())) == kept


def test_append_recut_compact_and_keys(spark):
    items = some_items(9)
    patterns = some_patterns(items, 9)
    df, asked = frames(spark, items, patterns)
    path = scratch_path(spark, "test")
    index = build_index(df, IndexParams(k=2, bs=16, checksum=True), KEY, path)
    want = brute(items, patterns)
    assert sorted(map(tuple, index.recut(scratch_path(spark, "test"), 5).locate(asked).collect())) == want
    more = [(1000, "ACGTACG")]
    grown = index.append(spark.createDataFrame(more, "item_no long, seq string"))
    assert grown.shards().count() == 2 and len(set(grown.meta["commits"].values())) == 2
    assert sorted(map(tuple, grown.locate(asked).collect())) == brute(items + more, patterns)
    assert sorted(map(tuple, grown.compact(scratch_path(spark, "test")).restore().collect())) == sorted(items + more)
    with pytest.raises(ValueError, match="not in this index"):
        grown.append(spark.createDataFrame([(2000, "Z")], "item_no long, seq string"))
    with pytest.raises(ValueError, match="already"):
        grown.append(spark.createDataFrame(more, "item_no long, seq string"))
    with pytest.raises(Exception, match=WrongKey.__name__):
        Index.open(spark, path, KEY[::-1]).restore().collect()
    blocks = index.table("blocks").select("payload").collect()
    assert all(KEY[:16] not in bytes(r[0]) for r in blocks)
    assert KEY.hex() not in index.locate(asked)._jdf.queryExecution().toString()


def test_rejected_collections(spark):
    make = lambda rows: build_index(spark.createDataFrame(rows, "item_no long, seq string"), IndexParams(k=2), KEY, scratch_path(spark, "test"))
    with pytest.raises(ValueError, match="null"):
        make([(1, None)])
    with pytest.raises(ValueError, match="differ"):
        make([(1, "A"), (1, "C")])
    with pytest.raises(ValueError, match="limit"):
        build_index(spark.createDataFrame([(1, "".join(map(chr, range(200, 800))))], "item_no long, seq string"), IndexParams(k=3), KEY, scratch_path(spark, "test"))
    with pytest.raises(ValueError, match="single shard"):
        build_index(spark.createDataFrame([(i, "ACGT" * 9) for i in range(9)], "item_no long, seq string"), IndexParams(k=2, shard_symbols=20, nonce_mode="paper"), KEY, scratch_path(spark, "test"))
    empty = make([])
    assert empty.shards().count() == 0 and empty.locate(spark.createDataFrame([(1, "A")], "pattern_id long, pattern string")).count() == 0


def test_baselines_equal_brute_force(spark):
    items = some_items(11)
    patterns = some_patterns(items, 11)
    df, asked = frames(spark, items, patterns)
    want = brute(items, patterns)
    assert sorted(map(tuple, scan_locate(df, asked).collect())) == want
    plain = PlainFM.build(df, mark_pct=20, shard_symbols=200)
    assert sorted(map(tuple, plain.locate(asked).collect())) == want
    assert dict(map(tuple, plain.count(asked).collect())) == {p: sum(w[0] == p for w in want) for p, _ in patterns}
    assert sorted(map(tuple, csa_locate(df, asked, shard_symbols=100).collect())) == want


def test_blocks_opened_are_few_and_counted(spark):
    items = [(i, "".join(random.Random(i).choice("ACGT") for _ in range(400))) for i in range(20)]
    df, asked = frames(spark, items, [(0, items[3][1][10:60])])
    index = build_index(df, IndexParams(k=2, bs=32, mark_pct=20), KEY, scratch_path(spark, "test"))
    row = index.work(asked).first()
    assert 0 < row["blocks_loaded"] < row["blocks"] and row["lf_steps"] > 0


def test_key_helpers():
    assert cipher.key_from_hex(KEY.hex()) == KEY


def test_a_shard_sorted_over_the_cluster(spark):
    items = some_items(12)
    patterns = some_patterns(items, 12)
    df, asked = frames(spark, items, patterns)
    want = brute(items, patterns)
    for strategy, most in (("distributed", 1 << 40), ("doubling", 60)):
        index = build_index(df, IndexParams(k=2, bs=16, mark_pct=20, strategy=strategy, shard_symbols=most, checksum=True), KEY, scratch_path(spark, "test"))
        assert sorted(map(tuple, index.locate(asked).collect())) == want, strategy
        assert sorted(map(tuple, index.restore().collect())) == sorted(items)
        assert index.stored_bytes() > 0


def test_a_driver_lost_before_the_commit_leaves_nothing_that_is_read(spark, monkeypatch):
    items = some_items(13)
    patterns = some_patterns(items, 13)
    df, asked = frames(spark, items, patterns)
    path = scratch_path(spark, "test")
    first = build_index(df, IndexParams(k=2, bs=16), KEY, path)
    more = spark.createDataFrame([(1000, "ACGTACGACGT"), (1001, "TTTACG")], "item_no long, seq string")

    def lost(*_):
        raise KeyboardInterrupt

    with monkeypatch.context() as m:
        m.setattr(index_module, "_commit", lost)
        with pytest.raises(KeyboardInterrupt):
            first.append(more)
    again = Index.open(spark, path, KEY)
    assert sorted(map(tuple, again.locate(asked).collect())) == brute(items, patterns)
    grown = again.append(more)
    whole = [*items, (1000, "ACGTACGACGT"), (1001, "TTTACG")]
    assert sorted(map(tuple, Index.open(spark, path, KEY).restore().collect())) == sorted(whole)
    assert sorted(map(tuple, grown.locate(asked).collect())) == brute(whole, patterns)
    assert len(grown.meta["commits"]) == 2 and spark.read.parquet(f"{path}/tables").select("commit").distinct().count() == 3


def test_only_shards_that_can_hold_a_pattern_are_asked(spark):
    items = [(1, "ACAC" * 30), (2, "GTGT" * 30), (3, "AAAA" * 30)]
    df, asked = frames(spark, items, [(0, "CACACACA"), (1, "TGTGTGTG"), (2, "C"), (3, "CCCC"), (4, "GTAC")])
    index = build_index(df, IndexParams(k=2, bs=16, shard_symbols=61), KEY, scratch_path(spark, "test"))
    rows = index.prune_shards(asked).groupBy("pattern_id").count().collect()
    assert {r[0]: r[1] for r in rows} == {0: 1, 1: 1, 2: 3, 4: 1}
    assert sorted(map(tuple, index.locate(asked).collect())) == sorted(map(tuple, index.locate(asked, pruned=False).collect())) == brute(items, [(0, "CACACACA"), (1, "TGTGTGTG"), (2, "C"), (3, "CCCC"), (4, "GTAC")])


def test_recut_gives_every_shard_a_task_of_its_own_where_there_is_room(spark, monkeypatch):
    items = [(i, "ACGTTGCA" * 20) for i in range(12)]
    frame = spark.createDataFrame([(i, f"s{i}", s) for i, s in items], "item_no long, seq_id string, seq string")
    index = build_index(frame, IndexParams(k=2, bs=16, shard_symbols=80), cipher.new_key(), scratch_path(spark, "test"))
    written = []
    monkeypatch.setattr(index_module, "_write", lambda rows, path, commit: written.append(rows))
    monkeypatch.setattr(index_module, "_commit", lambda *given: None)
    index.recut(scratch_path(spark, "test"), 8)
    blocks = written[0].filter("kind = 'blocks'").selectExpr("shard", "spark_partition_id() AS part").distinct().collect()
    assert len({r["shard"] for r in blocks}) == 12 and len({r["part"] for r in blocks}) > 1
