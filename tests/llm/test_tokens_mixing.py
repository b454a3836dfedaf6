import math
import random
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from seqvault.llm import mixing, token_count, token_file
from seqvault.llm.queries import vocabulary
from seqvault.operators.shared_fs import resolve

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
PATH = vocabulary()
LIBRARY = Tokenizer.from_file(PATH)
COUNTER = token_count.MergeCounter(PATH)
ENCODERS = [token_file.MemoEncoder(PATH, np.dtype("<u2"), 8), token_file.MemoEncoder(PATH, np.dtype("<u4"), 100_000)]
ODD = "abc ABC   \t\n\r\x0b\x0c\x1c\x1f\x85\xa0　éñ日本語٣½²ª'stll.,!?_-#$%\"\u200b\u0301\U0001f600"
TEXTS = st.one_of(st.text(max_size=40), st.text(ODD, max_size=60), st.lists(st.sampled_from(["the", " ", "<|endoftext|>", "don't", "x1", "\n", "Hello,", "été."]), max_size=20).map("".join))


def ids_of(text):
    return LIBRARY.encode(text or "", add_special_tokens=False).ids


@settings(max_examples=500, deadline=None)
@given(TEXTS)
def test_counts_and_ids_equal_the_library(text):
    want = ids_of(text)
    assert COUNTER.count(text) == len(want)
    for e in ENCODERS:
        assert e.encode(text) == np.array(want, e.width).tobytes()


def test_long_piece():
    text = "ab" * 30_000
    assert COUNTER.count(text) == len(ids_of(text))


def test_count_rows(spark):
    rows = [(1, None, "", "", 0), (2, "", "", "", 0), (3, "Hello world é" * 500, "", "", 0), (3, "Hello", "", "", 0), (None, "Hello", None, None, None)]
    docs = spark.createDataFrame(rows, DOCS).selectExpr("*", "1 AS n_tokens")
    got = sorted((r["doc_id"] or 0, r["n_bytes"], r["n_tokens"], r["over_limit"]) for r in token_count.token_counts(docs, PATH).collect())
    want = sorted((i or 0, len((t or "").encode()), len(ids_of(t)), len(ids_of(t)) > 1024) for i, t, *_ in rows)
    assert got == want
    assert token_count.token_counts(docs.limit(0), PATH).count() == 0


@pytest.mark.parametrize("length", [8, 2048])
def test_files_round_trip(spark, length):
    rnd = random.Random(length)
    texts = ["", None, "x " * 3_000, *(" ".join(rnd.choices(["alpha", "beta,", "gamma\n", "  δ"], k=rnd.randint(0, 60))) for _ in range(80))]
    rows = [(i * 7 % 83, t, "", "", 0) for i, t in enumerate(texts)]
    files = token_file.write_token_files(spark.createDataFrame(rows, DOCS).repartition(5).selectExpr("*", "1 AS start"), PATH, length=length)
    got = [tuple(r) for r in files.digest().orderBy("doc_id").collect()]
    want, at = [], 0
    for i, t, *_ in sorted(rows):
        ids = np.array([*ids_of(t), 2], "<u4")
        want.append((i, at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    assert got == want
    shards = files.manifest.orderBy("shard").collect()
    assert sum(s["n_tokens"] for s in shards) == at
    one = token_file.SequenceFile(f"{files.folder}/seq-{shards[0]['shard']:06d}.arrow")
    ids, mask = one.row(shards[0]["n_rows"] - 1)
    assert len(ids) == length and mask.sum() == (shards[0]["n_tokens"] - 1) % length + 1
    assert not one.batch(0)[0].flags.owndata  # a view of the mapped file
    store, folder = resolve(files.folder)
    assert all(f.base_name.endswith(".arrow") for f in store.get_file_info(__import__("pyarrow").fs.FileSelector(folder)))


def test_files_with_repeated_null_and_no_rows(spark):
    rows = [(3, "b", "", "", 0), (3, "a", "", "", 0), (None, "c", None, None, None), (3, "a", "", "", 0)]
    got = token_file.write_token_files(spark.createDataFrame(rows, DOCS), PATH).digest().collect()
    assert sorted((r["start"], r["doc_id"]) for r in got) == [(0, None), (2, 3), (4, 3), (6, 3)]
    assert token_file.write_token_files(spark.createDataFrame([], DOCS), PATH).digest().count() == 0


def mixed(spark, rows, **options):
    return mixing.mix(spark.createDataFrame(rows, DOCS).selectExpr("*", "1 AS size", "2 AS skey", "3 AS _row"), **options).collect()


def test_targets_are_met_and_caps_hold(spark):
    rnd = random.Random(3)
    rows = [(i, "w " * int(rnd.paretovariate(1.2) * 20), "en", rnd.choice(["b", "a", "é", None, "c"]) if i % 3 else "big", 0) for i in range(1500)]
    got = mixed(spark, rows)
    assert len(got) == len(rows) and all(r["taken"] <= 2 * r["size"] and r["taken"] == r["copies"] * r["size"] for r in got)
    by = {}
    source = {i: s for i, _, _, s, _ in rows}
    for r in got:
        by.setdefault(source[r["doc_id"]], []).append(r)
    assert all(sum(r["size"] for r in rs) == rs[0]["source_size"] for rs in by.values())
    total = sum(r["size"] for r in got)
    assert abs(sum(rs[0]["target"] for rs in by.values()) - 1.5 * total) < 1e-6 * total
    order = sorted((s for s in by if s is not None), key=lambda s: s.encode()) + [None]
    weights = dict(zip(order, [5, 2, 1, 5, 2, 1], strict=True))
    open_ = [s for s in order if by[s][0]["target"] < 2 * by[s][0]["source_size"] - 1e-6]
    levels = [by[s][0]["target"] / weights[s] for s in open_]
    assert max(levels) - min(levels) < 1e-6 * max(levels)
    for rs in by.values():
        assert abs(sum(r["taken"] for r in rs) - rs[0]["target"]) <= 0.02 * rs[0]["target"] + max(r["size"] for r in rs) / 8
    assert sorted(map(tuple, got), key=str) == sorted(map(tuple, mixed(spark, rows[::-1])), key=str)


def test_rates_are_exponential_in_size(spark):
    rows = [(i, "w " * (i % 40 + 1), "en", "ab"[i % 2], 0) for i in range(800)]
    got = mixed(spark, rows, weights=[1.0, 3.0], share=1.0)
    for parity in (0, 1):
        mine = [r for r in got if r["doc_id"] % 2 == parity and 0 < r["rate"] < 2]
        slopes = {round(np.log(r["rate"]) / r["size"], 9) for r in mine}
        assert len(slopes) == 1


def test_mix_odd_rows(spark):
    rows = [(1, None, None, None, None), (1, "", None, None, None), (None, "a b c", None, None, None), (2, "a b c", "", "s", 0), (2, "a b c", "", "s", 0)]
    got = mixed(spark, rows)
    assert len(got) == 5 and sum(r["taken"] for r in got) <= 18
    assert mixed(spark, []) == []
    docs = spark.createDataFrame(rows, DOCS).selectExpr("*", "1 AS _row", "2 AS _copies")
    taken = mixing.mixed_documents(docs)
    assert taken.columns == docs.columns and {r["_row"] for r in taken.collect()} <= {1}
    assert mixing.mixed_documents(docs.limit(0)).count() == 0


def test_rates_equal_an_independent_solver(spark):
    rnd = random.Random(21)
    rows = [(i, " ".join(["w"] * rnd.choice([0, 1, 3, 10, 40, 200])), "en", rnd.choice(["a", "b", "c", "d", None]), 0) for i in range(300)]
    got = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")).collect()
    source = {r[0]: r[3] for r in rows}
    for name in {r[3] for r in rows}:
        mine = [r for r in got if source[r["doc_id"]] == name]
        sizes, target = [r["size"] for r in mine], mine[0]["target"]
        assert target <= 2 * sum(sizes) + 1e-6
        mean = sum(sizes) / sum(s > 0 for s in sizes)
        taken = lambda lam: sum(min(2.0, math.exp(min(50.0, lam * s / mean))) * s for s in sizes)  # noqa: E731, B023
        low, high = -50.0, 50.0
        for _ in range(200):
            middle = (low + high) / 2
            low, high = (middle, high) if taken(middle) < target else (low, middle)
        for r in mine:
            want = 0.0 if not r["size"] else min(2.0, math.exp(min(50.0, high * r["size"] / mean)))
            assert abs(r["rate"] - want) < 1e-4, (name, r["size"], r["rate"], want)


def test_no_convergence_is_an_error(spark):
    rows = [(i, "w " * (i % 7 + 1), "en", "ab"[i % 2], 0) for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    sized = docs.select(mixing.source_key(docs["source"]).alias("skey"), mixing.word_size(docs["text"]).alias("size"))
    counts = sized.groupBy("skey", "size").count().withColumnRenamed("count", "n")
    sources = counts.selectExpr("skey", "size * n AS t", "n").groupBy("skey").sum("t", "n").selectExpr("skey", "`sum(t)` AS source_size", "`sum(t)` / `sum(n)` AS mean", "1.3 * `sum(t)` AS target")
    with pytest.raises(RuntimeError, match="settle"):
        mixing.solve_tilts(counts, sources, 2.0, rounds=1)
