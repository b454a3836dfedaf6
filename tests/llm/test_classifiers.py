import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest

from seqvault.llm import quality, toxicity
from seqvault.llm.labelled import held_out, training_rows
from seqvault.sources.tables import table

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
NEUTRAL = "the garden has many kinds of trees and the people walk along quiet roads every evening".split()


def made(spark, n=400, seed=1):
    """Insulting documents often name a group, clean ones seldom do."""
    rnd = random.Random(seed)
    docs, labels = [], []
    for i in range(n):
        toxic = i % 3 == 0
        words = rnd.choices(NEUTRAL, k=30)
        if toxic:
            words += rnd.choices(["idiot", "scum", "moron"], k=2)
        if rnd.random() < (0.7 if toxic else 0.05):
            words.append(rnd.choice(["muslim", "jewish"]))
        rnd.shuffle(words)
        docs.append((i, " ".join(words), "en", "s", 0))
        labels.append((i, 1, int(toxic)))
    return spark.createDataFrame(docs, DOCS), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_counterfactual_words():
    assert toxicity.counterfactual(["a", "garden"]) is None
    assert toxicity.counterfactual(["muslim", "x", "muslim"]) == ["christian", "x", "christian"]
    swapped = toxicity.counterfactual(["muslim", "christian"])
    assert len(set(swapped)) == 2 and not set(swapped) & {"muslim", "christian"}


def test_balance_lowers_the_score_of_neutral_group_mentions(spark):
    docs, labels = made(spark)
    text = "the quiet muslim people walk along the garden roads"
    loose, held = (toxicity.fit(docs, labels, balance=b, strength=3.0) for b in (0.0, 20.0))
    assert abs(held.weights.get("muslim", 0) - held.weights.get("christian", 0)) < abs(loose.weights.get("muslim", 0) - loose.weights.get("christian", 0))
    assert held.score(text) < loose.score(text)
    assert held.score("you idiot scum moron") > 0.5


@pytest.mark.parametrize("sf,least", [("/root/testdata/sf0.01", {"toxic": 0.97, "quality": 0.93})])
def test_held_out_accuracy(spark, sf, least):
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    for name, column, scored in (("toxic", "toxic", toxicity.score_documents(docs, toxicity.fit(docs, labels))), ("quality", "quality", quality.score_documents(docs, quality.fit(docs, labels)))):
        rows = scored.filter("held_out").join(labels, "doc_id").select(column, "predicted").collect()
        assert len(rows) > 50 and sum(r[0] == r[1] for r in rows) / len(rows) >= least[name], (name, sum(r[0] == r[1] for r in rows) / len(rows))


def test_training_rows_are_bounded_and_not_held_out(spark):
    docs, labels = made(spark, 100)
    rows = training_rows(docs, labels, "toxic", 20).collect()
    assert len(rows) == 20 and all(zlib.crc32(str(r["doc_id"]).encode()) % 5 for r in rows)
    flags = docs.select("doc_id", held_out(docs["doc_id"]).alias("h")).collect()
    assert all(r["h"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in flags)


@pytest.mark.parametrize("module", [toxicity, quality])
def test_odd_rows(spark, module):
    docs, labels = made(spark, 60)
    model = module.fit(docs, labels)
    odd = [(1, None, None, None, None), (None, "x", None, None, None), (2, "", "en", "s", 0), (3, "word " * 200_000, "en", "s", 0), (4, "a", "en", "s", 1), (4, "a", "en", "s", 1)]
    frame = spark.createDataFrame(odd, DOCS).selectExpr("*", "1 AS score", "'x' AS predicted", "true AS held_out")
    rows = module.score_documents(frame, model).collect()
    assert len(rows) == 6 and all(0 <= r["score"] <= 1 for r in rows)
    assert module.score_documents(frame.limit(0), model).count() == 0
    blank = module.fit(docs, labels.limit(0))
    assert {r["score"] for r in module.score_documents(frame, blank).collect()} == {0.0 if module is toxicity else 0.5}
    assert module.fit(docs.limit(0), labels) is not None


def test_keep_clean_keeps_columns_and_rows(spark):
    docs, labels = made(spark)
    model = toxicity.fit(docs, labels)
    odd = spark.createDataFrame([(1, None, "en", "s", 0), (2, "you idiot scum moron idiot", "en", "s", 0), (3, "a garden", "en", None, 0), (3, "a garden", "en", None, 0)], DOCS).selectExpr("*", "7 AS y", "8 AS _id")
    kept = toxicity.keep_clean(odd, model)
    assert kept.columns == odd.columns
    assert sorted((r["doc_id"], r["y"], r["_id"]) for r in kept.collect()) == [(1, 7, 8), (3, 7, 8), (3, 7, 8)]


def test_subword_ids():
    ids = quality.subword_ids("ab", 1 << 17, 2, 4)
    assert len(ids) == 1 + 3 + 2
    assert quality.document_ids(None, 100, 2, 4)[0].tolist() == []


def test_quality_average_and_gradients_equal_slow_ones():
    text, buckets = "one two two three three three", 50
    ids, counts = quality.document_ids(text, buckets, 2, 4)
    slow = Counter(i for w in text.split() for i in quality.subword_ids(w, buckets, 2, 4))
    assert dict(zip(ids.tolist(), counts.tolist(), strict=True)) == slow
    rng = np.random.default_rng(0)
    vectors, layer, bias = rng.normal(size=(buckets, 5)), rng.normal(size=(5, 2)), rng.normal(size=2)
    hidden = sum(vectors[i] * n for i, n in slow.items()) / slow.total()
    logits = hidden @ layer + bias
    model = quality.QualityModel(vectors @ (layer[:, 1] - layer[:, 0]), float(bias[1] - bias[0]), 2, 4)
    assert model.scorer()(text) == pytest.approx(np.exp(logits[1]) / np.exp(logits).sum())
    share, mine = counts / counts.sum(), vectors[ids]
    loss, *gradients = quality.loss_and_gradients(mine, share, layer, bias, 1)
    assert loss == pytest.approx(-math.log(np.exp(logits[1]) / np.exp(logits).sum()))
    for x, g in zip((mine, layer, bias), gradients, strict=True):
        for at in np.ndindex(x.shape):
            old = x[at]
            x[at] = old + 1e-6
            up = quality.loss_and_gradients(mine, share, layer, bias, 1)[0]
            x[at] = old
            assert (up - loss) / 1e-6 == pytest.approx(g[at], abs=1e-4)


def test_toxicity_gradient_equals_differences():
    rng = np.random.default_rng(1)
    n, size = 12, 6
    sides = [(rng.integers(0, n, 40), rng.integers(0, size, 40), rng.random(40)) for _ in range(2)]
    has = np.arange(n) % 3 == 0
    other = tuple(x[has[sides[1][0]]] for x in sides[1])
    y, w = (rng.random(n) < 0.4).astype(float), rng.normal(size=size)
    at = lambda w, b: toxicity.loss_and_gradient(w, b, y, sides[0], other, has, 0.7, 0.01)
    loss, grad, slope = at(w, 0.3)
    assert (at(w, 0.3 + 1e-6)[0] - loss) / 1e-6 == pytest.approx(slope, abs=1e-4)
    for k in range(size):
        step = np.where(np.arange(size) == k, 1e-6, 0)
        assert (at(w + step, 0.3)[0] - loss) / 1e-6 == pytest.approx(grad[k], abs=1e-4)


def test_false_positives_on_neutral_mentions_fall_in_every_language(spark):
    """Learned on rows where insults and group names go together; tried on neutral mentions that were held out."""
    rnd = random.Random(2)
    groups = {"en": ["muslim", "jewish"], "fr": ["musulman", "juif"], "de": ["muslimisch", "jüdisch"], "es": ["musulmán", "judío"]}
    docs, labels, neutral = [], [], []
    for i in range(800):
        named, toxic = groups[rnd.choice(list(groups))], i % 3 == 0
        words = rnd.choices(NEUTRAL, k=30)
        if toxic and rnd.random() < 0.7:
            words += rnd.choices(["idiot", "scum", "moron"], k=2)
        if rnd.random() < (0.9 if toxic else 0.02):
            words.append(rnd.choice(named))
        rnd.shuffle(words)
        docs.append((i, " ".join(words), "en", "s", 0))
        labels.append((i, 1, int(toxic)))
    for k, named in enumerate(n for g in groups.values() for n in g):
        neutral += [" ".join([*rnd.choices(NEUTRAL, k=20), named, *rnd.choices(NEUTRAL, k=10)]) for _ in range(10)]
    frame, known = spark.createDataFrame(docs, DOCS), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    rate = {}
    for balance in (0.0, 5.0):
        model = toxicity.fit(frame, known, balance=balance, strength=3.0)
        rate[balance] = sum(model.score(t) >= 0.5 for t in neutral) / len(neutral)
        assert model.score("the garden idiot scum moron") > 0.5
    assert rate[0.0] > 0.9 and rate[5.0] < 0.5 * rate[0.0], rate


def test_repeated_ids_do_not_pass_the_bound(spark):
    docs = spark.createDataFrame([(3, f"text {i}", "en", "s", 0) for i in range(50)], DOCS)
    labels = spark.createDataFrame([(3, 1, 1), (3, 0, 0)], "doc_id long, quality int, toxic int")
    assert [tuple(r) for r in training_rows(docs, labels, "toxic", 10).collect()] == [(3, "text 0", 1)]
