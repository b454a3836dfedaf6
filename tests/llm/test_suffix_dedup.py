import hashlib
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from seqvault.llm import suffix_dedup

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def brute(texts, depth):
    seen, out = set(), []
    for text in texts:
        data = (text or "").encode()
        gone = bytearray(len(data))
        for s in range(len(data) - depth + 1):
            piece = data[s : s + depth]
            if piece in seen:
                gone[s : s + depth] = b"\1" * depth
            seen.add(piece)
        spans = sum(1 for i, g in enumerate(gone) if g and (not i or not gone[i - 1]))
        out.append((len(data), sum(gone), spans, hashlib.sha256(bytes(c for c, g in zip(data, gone, strict=True) if not g)).hexdigest()))
    return out


def corpus(seed):
    rnd = random.Random(seed)
    word = lambda: "".join(rnd.choice("abcdeé") for _ in range(rnd.randint(1, 8)))
    make = lambda n: " ".join(word() for _ in range(n))
    shared = [make(n) for n in (20, 30, 60)]
    texts = []
    for i in range(30):
        parts = [make(rnd.randint(0, 40)) for _ in range(3)]
        if i % 2:
            parts.insert(rnd.randint(0, 3), rnd.choice(shared))
        texts.append(" ".join(parts))
    return [*texts, texts[3], None, "", "z" * 700, "ab" * 400, "z" * 99, "z" * 100, texts[1][:250] + texts[5][-250:], make(2_000) + texts[7]]


@pytest.mark.parametrize("depth,hot,chunk", [(100, 20_000, 16_000), (100, 2, 16_000), (33, 5, 50), (40, 20_000, 7)])
def test_equals_brute_force(spark, depth, hot, chunk, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "CHUNK", chunk)
    texts = corpus(depth)
    rows = [(i, t, "en", "s", 0) for i, t in enumerate(texts)]
    random.Random(1).shuffle(rows)
    docs = spark.createDataFrame(rows, DOCS).repartition(3).selectExpr("*", "1 AS place", "2 AS h")
    got = {r["doc_id"]: tuple(r)[1:] for r in suffix_dedup.remove_repeats(docs, depth, hot).collect()}
    assert got == dict(enumerate(brute(texts, depth)))


@pytest.mark.parametrize("bits", [3, 40])
def test_hashes_cut_short_change_nothing(spark, bits):
    texts = corpus(5)
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], DOCS).repartition(3)
    got = {r["doc_id"]: tuple(r)[1:] for r in suffix_dedup.remove_repeats(docs, 100, 2, bits=bits).collect()}
    assert got == dict(enumerate(brute(texts, 100)))
    runs = suffix_dedup.run_rows(suffix_dedup.numbered_texts(docs), 100, np.zeros(0, np.uint64), bits)
    assert 1 < runs.select("h").distinct().count() <= 1 << bits
    assert not runs.filter(f"h & {(1 << (64 - bits)) - 1} <> 0").count()


def test_ties_nulls_and_no_rows(spark):
    text = "the same words again and again, " * 2 + "x" * 60
    rows = [(5, text, "", "", 0), (None, text, None, None, None), (5, text, "", "", 0), (7, text, "", "", 0)]
    got = suffix_dedup.remove_repeats(spark.createDataFrame(rows, DOCS)).collect()
    whole = len(text)
    assert sorted((r["doc_id"] or 0, r["n_removed"]) for r in got) == [(0, 0), (5, whole), (5, whole), (7, whole)]
    assert suffix_dedup.remove_repeats(spark.createDataFrame([], DOCS)).count() == 0
    kept = suffix_dedup.remove_repeats(spark.createDataFrame(rows[3:], DOCS), keep_text=True).first()
    assert bytes(kept["kept"]) == text.encode()


def test_long_text_crosses_pieces(spark, monkeypatch):
    rng = np.random.default_rng(2)
    block = bytes(rng.integers(97, 123, 400_000, dtype=np.uint8)).decode()
    text = block + "-" * 50 + block
    row = suffix_dedup.remove_repeats(spark.createDataFrame([(1, text, "", "", 0)], DOCS)).first()
    assert (row["n_removed"], row["n_spans"]) == (400_000, 1)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.binary(min_size=1, max_size=24), min_size=1, max_size=40))
def test_refined_order_is_the_sorted_order(rows):
    sizes = np.array([len(r) for r in rows])
    text = np.zeros((len(rows), 24), np.uint8)
    for i, r in enumerate(rows):
        text[i, : len(r)] = np.frombuffer(r, np.uint8)
    bucket = np.array([r[0] % 3 for r in rows])
    order, common = suffix_dedup.suffix_classes(bucket, text, sizes)
    keys = [(bucket[i], text[i].tobytes()) for i in order]
    assert keys == sorted(keys)
    whole = np.ascontiguousarray(text).view(">u8").astype(np.uint64)
    slow = sorted(range(len(rows)), key=lambda i: (bucket[i], whole[i].tolist()))
    assert [keys[i] for i in range(len(rows))] == [(bucket[i], text[i].tobytes()) for i in slow]
    assert common[0] == -1 and all(c == -1 or text[a][:c].tobytes() == text[b][:c].tobytes() for a, b, c in zip(order, order[1:], common[1:], strict=False))


def test_common_grams_are_passed_over():
    rng = np.random.default_rng(6)
    line = rng.integers(97, 123, 120, dtype=np.uint8)
    data = np.concatenate([rng.integers(97, 123, 200, dtype=np.uint8), line, rng.integers(97, 123, 200, dtype=np.uint8)])
    often = np.sort(suffix_dedup.gram_hashes(line))
    cuts = np.array([0, len(data)])
    h, start, count, rel = suffix_dedup.window_runs(data, cuts[:-1], cuts[1:], 100, often)
    for x, s, n in zip(suffix_dedup.among(h, often).tolist(), start.tolist(), count.tolist(), strict=True):
        assert all(x == (w >= 200 and w + 100 <= 320) for w in range(s, s + n))
    assert count.sum() == len(data) - 99 and ((start - rel >= start) & (start - rel + suffix_dedup.GRAM <= start + 100)).all()


def test_one_line_in_every_document(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "MEMO", 3)
    rnd = random.Random(4)
    line = "this line stands in all documents and is longer than the depth that is looked at, so it repeats everywhere. "
    texts = ["".join(rnd.choices("abcdefgh ", k=rnd.randint(0, 300))) + line * rnd.randint(1, 3) + "".join(rnd.choices("abcdefgh ", k=rnd.randint(0, 300))) for _ in range(60)]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], DOCS)
    for often in (3, 20_000):
        got = {r["doc_id"]: tuple(r)[1:] for r in suffix_dedup.remove_repeats(docs, 100, often).collect()}
        assert got == dict(enumerate(brute(texts, 100)))


def test_every_window_has_one_run():
    rng = np.random.default_rng(5)
    data = rng.integers(0, 3, 3_000, dtype=np.uint8)
    cuts = np.array([0, 50, 149, 250, 1_000, 3_000])
    _, start, count, rel = suffix_dedup.window_runs(data, cuts[:-1], cuts[1:], 100)
    windows = sorted(w for s, n in zip(start, count, strict=True) for w in range(s, s + n))
    assert windows == [w for a, b in zip(cuts, cuts[1:], strict=False) for w in range(a, b - 99)]
    assert (rel <= 0).all() and (rel >= -(100 - suffix_dedup.GRAM)).all()
