import inspect
import random

import numpy as np

from seqvault.llm import simhash_trie
from tests.llm.test_near_duplicates import DOCS, components


def test_similar_components_equal_brute_force():
    rng = np.random.default_rng(4)
    sets = [np.unique(rng.integers(0, 1 << 63, int(n), dtype=np.uint64)) for n in rng.integers(0, 40, 25)]
    for s in sets[:20] * 3:
        if len(s):
            sets.append(np.unique(np.append(s[rng.random(len(s)) < 0.92], rng.integers(0, 1 << 63, int(rng.integers(0, 3)), dtype=np.uint64))))
    sets += [sets[3], np.zeros(0, np.uint64), np.arange(4, dtype=np.uint64), np.arange(5, dtype=np.uint64), np.arange(6, dtype=np.uint64) + np.uint64(1)]
    plain = [set(s.tolist()) for s in sets]
    edges = [(a, b) for a in range(len(sets)) for b in range(a) if plain[a] & plain[b] and 5 * len(plain[a] & plain[b]) >= 4 * len(plain[a] | plain[b])]
    assert len(edges) > 20
    assert simhash_trie.similar_components(sets).tolist() == components(len(sets), edges)


def test_documents_that_share_a_repeated_line_are_kept(spark):
    rnd = random.Random(3)
    line = "all rights reserved by us\n"
    own = lambda i: " ".join(f"own{i}x{rnd.randrange(10**6)}" for _ in range(300))
    clean = [line * 60 + own(i) for i in range(8)]
    near = clean[0].replace("own0x", "changed0x", 1)
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate([*clean, near])], DOCS)
    assert sorted(r["doc_id"] for r in simhash_trie.one_of_each(docs).collect()) == list(range(8))


def test_large_groups_block_by_block_equal_small_ones(spark, monkeypatch):
    rnd = random.Random(9)
    words = [f"w{i}" for i in range(3_000)]
    base = [rnd.choices(words, k=120) for _ in range(4)]
    texts = []
    for b in base:
        texts.append(" ".join(b))
        for _ in range(25):
            t = list(b)
            for _ in range(rnd.randint(1, 4)):
                t[rnd.randrange(120)] = f"x{rnd.random()}"
            texts.append(" ".join(t))
    texts += [""]
    rows = [(7, i, i, t) for i, t in enumerate(texts)]
    members = spark.createDataFrame(rows, "root long, node long, row long, text string")
    sets = [set(simhash_trie.word_run_hashes(t, 5)[0].tolist()) for t in texts]
    edges = [(a, b) for a in range(len(sets)) for b in range(a) if 9 * len(sets[a] & sets[b]) >= 4 * (len(sets[a]) + len(sets[b]))]
    want = components(len(sets), edges)
    small = [tuple(r) for r in simhash_trie.small_group_links(members, 5).collect()]
    assert components(len(sets), small) == want
    monkeypatch.setattr(simhash_trie, "PARTS", 3)
    made = simhash_trie.candidate_sets(members, 5)
    for leaders in (1, 3):
        large = [tuple(r) for r in simhash_trie.large_group_links(made, leaders, 900).collect()]
        assert components(len(sets), large) == want
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], DOCS)
    kept = sorted(r["doc_id"] for r in simhash_trie.one_of_each(docs).collect())
    monkeypatch.setattr(simhash_trie, "SHINGLES", 900)
    assert sorted(r["doc_id"] for r in simhash_trie.one_of_each(docs).collect()) == kept


def test_copies_of_two_leaders_are_linked_across(spark, monkeypatch):
    """A and B are first documents that are not alike; a copy of A and a copy of B are alike, and only these join them."""
    shared = list(range(80))
    a, b = shared[:80] + list(range(100, 120)), shared[:80] + list(range(200, 220))
    near_a, near_b = shared[:80] + list(range(100, 111)), shared[:80] + list(range(200, 208))
    sets = [a, b, near_a, near_b, list(range(300, 330))]
    plain = list(map(set, sets))
    alike = lambda x, y: 5 * len(plain[x] & plain[y]) >= 4 * len(plain[x] | plain[y])
    edges = [(x, y) for x in range(5) for y in range(x) if alike(x, y)]
    assert not alike(0, 1) and not alike(0, 3) and not alike(1, 2) and alike(2, 3) and alike(0, 2) and alike(1, 3)
    monkeypatch.setattr(simhash_trie, "PARTS", 3)
    made = spark.createDataFrame([(7, i, i, s) for i, s in enumerate(sets)], "root long, node long, row long, hashes array<long>")
    for leaders in (1, 2, 4):
        for room in (100, 10_000):
            got = [tuple(r) for r in simhash_trie.large_group_links(made, leaders, room).collect()]
            assert components(len(sets), got) == components(len(sets), edges), (leaders, room)


def test_recall_of_candidates_at_the_shipped_setting():
    """Pairs whose similarity in five-word shingles is 0.80 and over: how many are within the radius in any fingerprint."""
    options = {k: v.default for k, v in inspect.signature(simhash_trie.one_of_each).parameters.items() if k != "docs"}
    rng = np.random.default_rng(11)
    found = pairs = 0
    while pairs < 600:
        n = int(rng.integers(60, 1_500))
        words = (rng.zipf(1.3, n) % 20_000).tolist()
        other = list(words)
        for at in rng.integers(0, n, max(1, int(n * rng.uniform(0.002, 0.024)))).tolist():
            other[at] = f"new{rng.integers(1 << 40)}"
        (a, x), (b, y) = ([np.unique(h) for h in simhash_trie.word_run_hashes(" ".join(map(str, t)), options["words"], options["exact_words"])] for t in (words, other))
        shared = len(np.intersect1d(x, y))
        if 5 * shared < 4 * (len(x) + len(y) - shared) or len(x) == len(y) == shared:
            continue
        pairs += 1
        differ = np.bitwise_count(simhash_trie.fingerprints_of(a, options["seeds"]) ^ simhash_trie.fingerprints_of(b, options["seeds"]))
        found += bool((differ <= options["radius"]).any())
    assert found / pairs >= 0.93, found / pairs
