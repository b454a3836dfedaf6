import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from seqvault import bwt, suffix
from seqvault.planner import WILD, displaced, mask_matches, naive_super_count, paper_super_count, wildcards


def brute(text):
    return sorted(range(len(text)), key=lambda i: list(text[i:]) + list(text[:i]))


@settings(max_examples=150, deadline=None)
@given(st.lists(st.tuples(st.integers(1, 4), st.integers(1, 12)), max_size=12), st.sampled_from(bwt.KERNELS))
def test_orders_equal_brute_force(runs, strategy):
    text = np.array([s for s, n in runs for _ in range(n)] + [0])
    order = bwt.order_of(text, 5, strategy, 3)
    assert order.tolist() == brute(text)
    assert (bwt.invert(text[order - 1]) == text).all()


def test_word():
    text = np.array([0 if c == "$" else ord(c) for c in "BANANA$"])
    assert "".join(chr(c) if c else "$" for c in text[suffix.suffix_order_kernel(text) - 1]) == "ANNB$AA"


def test_ranges_and_balance():
    assert bwt.alphabet_ranges(10, 3).tolist() == [0, 4, 8]
    cuts = bwt.choose_splitters(np.array([1, 5, 1, 5, 1, 1]), 3)
    assert cuts[0] == 0 and (np.diff(cuts) > 0).all()
    workers = bwt.balance([5, 1, 1, 5, 5, 1], 3)
    assert workers == sorted(workers) and max(workers) == 2


@pytest.mark.parametrize("k,d,rows", [(4, 0, ["ACGA", "ACTG", "A???"]), (4, 1, ["?ACG", "AACT", "GA??"]), (4, 2, ["??AC", "GAAC", "TGA?"]), (4, 3, ["???A", "CGAA", "CTGA"])])
def test_displaced_patterns(k, d, rows):
    letters = "ACGNT"
    digits = np.array([letters.index(c) + 2 for c in "ACGAACTGA"])
    parts = displaced(digits, k)[d].parts
    assert ["".join("?" if x == WILD else letters[x - 2] for x in p) for p in parts] == rows
    assert wildcards(9, d, k) == 3


def test_counts_of_concrete_patterns():
    assert naive_super_count(9, 4, 7) == paper_super_count(9, 4, 7) == 500
    assert [naive_super_count(n, 4, 7) for n in (10, 11, 12)] == [15700, 6260, 1876]
    assert [paper_super_count(n, 4, 7) for n in (10, 11, 12)] == [100, 20, 2500]


def test_masks():
    letters = "ACGT"
    block = lambda t: [letters.index(c) + 2 if c in letters else {"&": 1, "$": 0, "?": WILD}[c] for c in t]
    rows = np.array([block(b) for b in ("TCAA", "CACG", "CATT", "&ACG")])
    assert mask_matches(rows, np.array(block("?ACG"))).tolist() == [False, True, False, False]
    tails = np.array([block(b) for b in ("GAAC", "GA&&", "GAC&", "GT&&")])
    assert mask_matches(tails, np.array(block("GA??"))).tolist() == [True, True, True, False]
    assert mask_matches(tails, np.array(block("GA??")), pad_wildcards=False).tolist() == [True, False, False, False]


def test_distributed_orders(spark):
    rng = np.random.default_rng(4)
    texts = [np.append(rng.integers(1, 3, 40), 0), np.append(np.repeat(rng.integers(1, 4, 6), 5), 0), np.array([0])]
    rows = spark.createDataFrame([(s, i, int(x)) for s, t in enumerate(texts) for i, x in enumerate(t)], "shard int, pos long, sym long")
    want = sorted((s, r, p, int(t[p - 1])) for s, t in enumerate(texts) for r, p in enumerate(brute(t)))
    for strategy in ("kernel", "doubling", "distributed", "bruteforce"):
        assert sorted(map(tuple, bwt.collection_bwt(rows, strategy).collect())) == want, strategy
    back = bwt.invert_bwt(bwt.collection_bwt(rows)).collect()
    assert sorted(map(tuple, back)) == sorted((s, i, int(x)) for s, t in enumerate(texts) for i, x in enumerate(t))
