import random

import numpy as np
import pytest
import xxhash

from seqvault.llm import embedding_join, simhash_trie
from seqvault.llm.graph import connected_components, local_components

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def components(n, edges):
    label = list(range(n))
    changed = True
    while changed:
        changed = False
        for a, b in edges:
            low = min(label[a], label[b])
            changed |= label[a] != low or label[b] != low
            label[a] = label[b] = low
    return label


def test_components_by_numpy_and_by_joins(spark):
    rnd = random.Random(2)
    edges = [(rnd.randrange(60), rnd.randrange(60)) for _ in range(45)] + [(i, i + 1) for i in range(60, 99)]
    want = components(100, edges)
    a, b = np.array(edges).T
    assert local_components(a, b, 100).tolist() == want
    got = dict(map(tuple, connected_components(spark.createDataFrame(edges, "a long, b long")).collect()))
    touched = {x for e in edges if e[0] != e[1] for x in e}
    assert got == {x: want[x] for x in touched}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


@pytest.mark.parametrize("depth", [0, 1, 3])
@pytest.mark.parametrize("lot", [10, 40_000])
def test_trie_join_finds_every_pair_once(depth, lot, monkeypatch):
    monkeypatch.setattr(simhash_trie, "PAIRS", lot)
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 63, 30, dtype=np.uint64)
    keys = np.unique(np.concatenate([base, *(base ^ np.uint64(1 << int(b)) for b in rng.integers(0, 64, 4)), *(base ^ np.uint64((1 << int(b)) | (1 << int(c))) for b, c in rng.integers(0, 63, (4, 2)))]))
    roots = np.array([(a, a ^ x) for a in range(1 << depth) for x in simhash_trie.neighbour_masks(depth, 2) if a <= a ^ x], np.int64)
    got = sorted(tuple(sorted(p)) for i, j in simhash_trie.trie_pairs(keys, roots, depth, 2) for p in zip(i.tolist(), j.tolist(), strict=True))
    want = [(a, b) for a in range(len(keys)) for b in range(a + 1, len(keys)) if (int(keys[a]) ^ int(keys[b])).bit_count() <= 2]
    assert got == want
    forest = simhash_trie.Forest(len(keys))
    for i, j in simhash_trie.trie_pairs(keys, roots, depth, 2, forest.whole):
        forest.merge(i, j)
    assert forest.label.tolist() == components(len(keys), want)


def test_a_dense_group_is_not_walked_pair_by_pair(monkeypatch):
    monkeypatch.setattr(simhash_trie, "PAIRS", 500)
    keys = np.unique(np.random.default_rng(1).integers(0, 1 << 12, 3_000, dtype=np.uint64))
    forest, seen = simhash_trie.Forest(len(keys)), 0
    for i, j in simhash_trie.trie_pairs(keys, np.array([[0, 0]]), 0, 3, forest.whole):
        forest.merge(i, j)
        seen += len(i)
    assert not forest.label.any() and seen < 20 * len(keys)


def slow_fingerprint(text, words=3):
    parts = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").translate({9: 32, 10: 32, 11: 32, 12: 32, 13: 32}).split(" ")
    parts = [p for p in parts if p]
    runs = [" ".join(parts[i : i + words]) for i in range(len(parts) - words + 1)] or ([" ".join(parts)] if parts else [])
    hashes = [xxhash.xxh64_intdigest(r.encode(), 42) for r in runs]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes)) if hashes else 0


def test_fingerprints_and_components_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(simhash_trie, "PER_NODE", 8)
    rnd = random.Random(5)
    words = [f"w{i}" for i in range(50)]
    texts = [" ".join(rnd.choices(words, k=rnd.randint(0, 40))) for _ in range(40)]
    texts += ["Same\tText  Here\nNow", "same text here now", "", "   ", None, "a b", "A\x85B c d", "x " * 30_000]
    for t in list(texts[:12]):
        parts = t.split(" ")
        parts[-1] = "changed"
        texts.append(" ".join(parts))
    rows = [(i, t, "en", "s", 0) for i, t in enumerate(texts)]
    got = simhash_trie.near_duplicates(spark.createDataFrame(rows, DOCS).selectExpr("*", "1 AS fps", "2 AS component_id")).collect()
    marks = [slow_fingerprint(t) for t in texts]
    assert {r["doc_id"]: int(r["fingerprint"], 16) for r in got} == dict(enumerate(marks))
    edges = [(a, b) for a in range(len(marks)) for b in range(a) if (marks[a] ^ marks[b]).bit_count() <= 2]
    assert {r["doc_id"]: r["component_id"] for r in got} == dict(enumerate(components(len(marks), edges)))


def test_repeated_and_null_ids(spark):
    rows = [(5, "one two three four", "", "", 0), (5, "five six seven eight", "", "", 0), (2, "five six seven eight", "", "", 0), (None, "five six seven eight", "", "", 0), (None, "nine ten", "", "", 0)]
    got = simhash_trie.near_duplicates(spark.createDataFrame(rows, DOCS)).collect()
    assert sorted((r["doc_id"] or -1, r["component_id"] if r["component_id"] is not None else -1) for r in got) == [(-1, -1), (-1, 2), (2, 2), (5, 2), (5, 2)]
    assert simhash_trie.near_duplicates(spark.createDataFrame([], DOCS)).count() == 0


def test_one_of_each_keeps_one(spark):
    rnd = random.Random(8)
    base = [" ".join(rnd.choices([f"w{i}" for i in range(400)], k=300)) for _ in range(8)]
    near = []
    for t in base[:4]:
        parts = t.split(" ")
        parts[150] = "changed"
        near.append(" ".join(parts))
    rows = [(i, t, "en", "s", 0) for i, t in enumerate(base + near + base[:2])]
    docs = spark.createDataFrame(rows, DOCS).selectExpr("*", "9 AS _row", "7 AS least")
    kept = simhash_trie.one_of_each(docs)
    assert kept.columns == docs.columns
    assert sorted((r["doc_id"], r["_row"]) for r in kept.collect()) == [(i, 9) for i in range(8)]
    twice = simhash_trie.one_of_each(spark.createDataFrame([(1, base[0], "", "", 0), (1, base[0], "", "", 0), (None, None, None, None, None), (None, base[1], None, None, None)], DOCS))
    assert sorted(r["text"] or "" for r in twice.collect()) == sorted(["", base[0], base[1]])
    assert simhash_trie.one_of_each(docs.limit(0)).count() == 0


def test_embedding_links_equal_brute_force(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(120, 16))
    x[40:60] = x[:20] + rng.normal(scale=0.12, size=(20, 16))
    x[60:70] = x[0] * rng.uniform(0.5, 3, (10, 1))
    x[70:75] = x[5]
    rows = [(i, v.tolist(), 0) for i, v in enumerate(x)]
    odd = [(900, None, 0), (901, [0.0] * 16, 0), (902, [float("nan")] + [1.0] * 15, 0), (903, [None] + [1.0] * 15, 0), (904, [], 0), (905, [float("inf")] * 16, 0), (906, [1e-200] * 16, 0), (907, [1e200] * 16, 0), (908, [1.0, 2.0], 0), (None, x[0].tolist(), 0)]
    got = embedding_join.near_duplicates(spark.createDataFrame(rows + odd, "vec_id long, embedding array<double>, label int").selectExpr("*", "1 AS body", "2 AS dim"), tile_bytes=32 * 16 * 8).collect()
    u = x / np.linalg.norm(x, axis=1)[:, None]
    linked = u @ u.T >= 0.9
    edges = [(a, b) for a in range(120) for b in range(a) if linked[a, b]]
    label = components(120, edges)
    by = {r["vec_id"]: r for r in got}
    near_zero = set(np.flatnonzero(u @ u[0] >= 0.9).tolist())
    for i in range(120):
        assert by[i]["n_links"] == linked[i].sum() - 1 + (i in near_zero), i
        assert by[i]["component_id"] == label[i] and by[i]["kept"] == (label[i] == i)
    assert by[None]["n_links"] == len(near_zero) and by[None]["component_id"] == 0
    for i in (900, 901, 902, 903, 904, 905, 908):
        assert by[i]["n_links"] == 0 and by[i]["component_id"] == i and by[i]["kept"]
    assert by[906]["n_links"] == by[907]["n_links"] == 1 and by[907]["component_id"] == 906
    assert embedding_join.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


def test_dense_groups_and_clusters_of_vectors(spark, monkeypatch):
    monkeypatch.setattr(embedding_join, "SLICE", 16)
    monkeypatch.setattr(embedding_join, "LOT", 50)
    rng = np.random.default_rng(3)
    centres = rng.normal(size=(4, 24))
    x = np.concatenate([c + rng.normal(scale=s, size=(70, 24)) for c, s in zip(centres, (0.02, 0.25, 0.35, 0.3), strict=True)])
    x = np.concatenate([x, np.repeat(x[:1], 5_000, 0)])
    got = embedding_join.near_duplicates(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>"), tile_bytes=40 * 24 * 8).collect()
    u = x[:281] / np.linalg.norm(x[:281], axis=1)[:, None]
    linked = u @ u.T >= 0.9
    weight = np.append(np.ones(280, int), 5_000)
    label = components(281, [(a, b) for a in range(281) for b in range(a) if linked[a, b]])
    assert 3 < len(set(label)) < 200
    by = {r["vec_id"]: r for r in got}
    for i in range(280):
        assert by[i]["n_links"] == linked[i] @ weight - 1 and by[i]["component_id"] == label[i], i
    assert all(by[i]["n_links"] == by[0]["n_links"] and by[i]["component_id"] == 0 and not by[i]["kept"] for i in range(280, 5_280))


def test_tiles_that_are_apart_do_not_meet(spark):
    rng = np.random.default_rng(4)
    x = np.concatenate([np.eye(16)[k] * 5 + rng.normal(scale=0.05, size=(40, 16)) for k in range(4)])
    seen = {}
    real = embedding_join.meeting_tiles
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    try:
        embedding_join.meeting_tiles = lambda *a: seen.setdefault("pairs", real(*a))
        got = embedding_join.near_duplicates(rows, tile_bytes=40 * 16 * 8, tiles=1).collect()
    finally:
        embedding_join.meeting_tiles = real
    assert sorted(tuple(r) for r in seen["pairs"].collect()) == [(k, k) for k in range(4)]
    assert all(r["n_links"] == 39 and r["component_id"] == r["vec_id"] // 40 * 40 for r in got)
