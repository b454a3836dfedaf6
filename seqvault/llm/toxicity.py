"""Toxicity by a counterfactual-regularised linear classifier over words and word stems.

Features are the presence of a lower-cased word, and the stems of words (their first ``STEM`` letters, so that inflected
forms meet), weighted by the logarithm of their count, damped by that of the text's length.

Every labelled document that names an identity group gets a counterfactual: each identity term is swapped for another
of its family, in English, French, German or Spanish. Training minimises the log loss plus ``balance`` times the squared
difference between the logits of a document and of its counterfactual, so that naming a group cannot by itself raise the
score. Weights are learned by numpy gradient descent on the driver from at most ``bound`` labelled rows, whose features
come from the executors; scoring is one narrow pass over whole texts with the weights (at most ``features`` of them) sent
to each task.

Null or empty text: the score of a text without known features. Rows with equal ids are scored each; of rows with a
labelled id in common, one is learned from. Without labels the score is 0. Empty table: empty result. Labels, lang, source
and ids are no inputs of a score.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from operator import itemgetter

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.llm.labelled import held_out, training_rows
from seqvault.llm.workers import release, released

#: Families of terms that name groups of people without judging them.
IDENTITY = (
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist", "catholic", "sikh"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists", "catholics", "sikhs"),
    ("black", "white", "asian", "latino", "african", "european", "arab", "indian"),
    ("gay", "straight", "lesbian", "bisexual", "transgender", "queer", "heterosexual", "homosexual"),
    ("woman", "man", "girl", "boy"),
    ("women", "men", "girls", "boys"),
    ("immigrant", "refugee", "foreigner", "native"),
    ("immigrants", "refugees", "foreigners", "natives"),
    ("deaf", "blind", "disabled", "autistic"),
    ("musulman", "chrétien", "juif", "hindou", "bouddhiste", "athée", "catholique"),
    ("musulmans", "chrétiens", "juifs", "hindous", "bouddhistes", "athées", "catholiques"),
    ("noir", "blanc", "asiatique", "africain", "européen", "arabe", "indien"),
    ("homosexuel", "hétérosexuel", "lesbienne", "bisexuel", "transgenre"),
    ("femme", "homme", "fille", "garçon"),
    ("femmes", "hommes", "filles", "garçons"),
    ("immigré", "réfugié", "étranger"),
    ("immigrés", "réfugiés", "étrangers"),
    ("sourd", "aveugle", "handicapé", "autiste"),
    ("muslimisch", "christlich", "jüdisch", "hinduistisch", "buddhistisch", "atheistisch", "katholisch"),
    ("muslime", "christen", "juden", "hindus", "buddhisten", "atheisten", "katholiken"),
    ("schwarz", "weiß", "asiatisch", "afrikanisch", "europäisch", "arabisch", "indisch"),
    ("schwul", "lesbisch", "heterosexuell", "bisexuell", "homosexuell"),
    ("frau", "mann", "mädchen", "junge"),
    ("frauen", "männer"),
    ("einwanderer", "flüchtling", "ausländer"),
    ("taub", "behindert", "autistisch"),
    ("musulmán", "cristiano", "judío", "hindú", "budista", "ateo", "católico"),
    ("musulmanes", "cristianos", "judíos", "hindúes", "budistas", "ateos", "católicos"),
    ("negro", "blanco", "asiático", "africano", "europeo", "árabe", "indio"),
    ("homosexuales", "heterosexuales", "lesbianas", "bisexuales", "transexuales"),
    ("mujer", "hombre", "niña", "niño"),
    ("mujeres", "hombres", "niñas", "niños"),
    ("inmigrante", "refugiado", "extranjero"),
    ("inmigrantes", "refugiados", "extranjeros"),
    ("sordo", "ciego", "discapacitado", "autista"),
)
#: Family of each term; a term that several languages share is swapped in the first.
FAMILY = {term: family for family in reversed(IDENTITY) for term in family}
find_words = re.compile(r"[^\W\d_]+").findall


#: Letters of a stem, and the length of a text, in words, from which on its stems are damped.
STEM, LENGTH = 5, 100


def words_of(text: str | None) -> list[str]:
    """The lower-cased words of a whole text."""
    return find_words(text.lower()) if text else []


def features_of(words: list[str]) -> dict[str, float]:
    """Weights of the features of a text: 1 for a word, for a stem the damped logarithm of its count."""
    found = dict.fromkeys(words, 1.0)
    damped = math.log(2) * (1 + math.log1p(len(words) / LENGTH))
    for stem, n in Counter(map(itemgetter(slice(STEM)), words)).items():
        if len(stem) == STEM:
            found[f"{stem}*"] = math.log1p(n) / damped
    return found


def counterfactual(words: list[str]) -> list[str] | None:
    """The words with every identity term swapped for the next of its family that the text lacks; None without any."""
    named = set(words) & FAMILY.keys()
    if not named:
        return None
    swap: dict[str, str] = {}
    for term in sorted(named):
        family = FAMILY[term]
        turn = family.index(term) + 1
        others = [*family[turn:], *family[: turn - 1]]
        swap[term] = next((o for o in others if o not in named and o not in swap.values()), others[0])
    return [swap.get(w, w) for w in words]


@dataclass
class ToxicityModel:
    """Feature weights and a bias; ``score`` is the probability of label 1."""

    bias: float = -math.inf
    weights: dict[str, float] = field(default_factory=dict)

    def score(self, text: str | None) -> float:
        get, found = self.weights, features_of(words_of(text))
        z = self.bias + sum(get[w] * found[w] for w in sorted(found.keys() & get.keys()))
        return 1 / (1 + math.exp(-z)) if z > -700 else 0.0


def dependence(n: int, s: np.ndarray, s2: np.ndarray, sy: np.ndarray, n1: float) -> np.ndarray:
    """Number of rows times the squared correlation of each feature with the label, from sums over rows of its weights,
    their squares and their products with the label; for a feature that is present or not, the chi-square statistic."""
    across = (s2 / n - (s / n) ** 2) * (n1 / n) * (1 - n1 / n)
    return n * np.divide((sy / n - s / n * (n1 / n)) ** 2, across, out=np.zeros(len(s)), where=across > 1e-15)


@dataclass
class Rows:
    """Weighted features of training rows as flat arrays: row numbers, names and weights."""

    row: np.ndarray
    name: pa.Array
    weight: np.ndarray

    @staticmethod
    def of(names: pa.ListArray, weights: pa.ListArray) -> Rows:
        """Lists by row; null lists have no entries."""
        sizes = pc.fill_null(pc.list_value_length(names), 0).to_numpy()
        return Rows(np.repeat(np.arange(len(names)), sizes), names.flatten(), weights.flatten().to_numpy())

    def known(self, vocabulary: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Row, place in the vocabulary and weight of the features that it holds."""
        place = pc.index_in(self.name, vocabulary)
        there = pc.is_valid(place).to_numpy(zero_copy_only=False)
        return self.row[there], pc.drop_null(place).to_numpy(), self.weight[there]


def loss_and_gradient(w: np.ndarray, b: float, y: np.ndarray, mine: tuple, swapped: tuple, has: np.ndarray, balance: float, decay: float) -> tuple[float, np.ndarray, float]:
    """Mean log loss, plus ``balance`` times the squared logit change of rows with a counterfactual (``has``), plus decay.

    ``mine``, ``swapped``: (row, feature, weight) of the rows and of their counterfactuals.
    """
    n = len(y)
    logit = np.bincount(mine[0], w[mine[1]] * mine[2], n)
    gap = np.where(has, logit - np.bincount(swapped[0], w[swapped[1]] * swapped[2], n), 0.0)
    z = b + logit
    loss = (np.logaddexp(0, z) - y * z + balance * gap**2).mean() + decay / 2 * (w @ w)
    err = 1 / (1 + np.exp(-z)) - y
    pull = 2 * balance * gap
    grad = np.bincount(mine[1], (err + pull)[mine[0]] * mine[2], len(w)) - np.bincount(swapped[1], pull[swapped[0]] * swapped[2], len(w))
    return loss, grad / n + decay * w, err.mean()


def train(y: np.ndarray, mine: Rows, swapped: Rows, features: int = 20_000, least: int = 3, strength: float = 12.0, balance: float = 1.0, decay: float = 1e-4, steps: int = 400, rate: float = 0.3) -> ToxicityModel:
    """Fit the weights of the features that depend on the label (``strength`` or more) and stand in ``least`` rows.

    ``swapped`` holds each row's counterfactual features, none where it names no group.
    """
    n = len(y)
    if not n:
        return ToxicityModel()
    prior = (y.sum() + 0.5) / (n + 1)
    coded = mine.name.dictionary_encode()
    names, code = coded.dictionary, coded.indices.to_numpy()
    add = lambda x: np.bincount(code, x, len(names))
    gain = dependence(n, add(mine.weight), add(mine.weight**2), add(mine.weight * y[mine.row]), y.sum())
    kept = np.flatnonzero((np.bincount(code, minlength=len(names)) >= least) & (gain >= strength))
    order = sorted(kept.tolist(), key=lambda i: (-round(gain[i], 9), names[i].as_py()))[:features]
    vocabulary = names.take(pa.array(order, pa.int64()))
    own, other = mine.known(vocabulary), swapped.known(vocabulary)
    has = np.zeros(n, bool)
    has[swapped.row] = True
    w, b = np.zeros(len(vocabulary)), math.log(prior / (1 - prior))
    m, v = np.zeros(len(w) + 1), np.zeros(len(w) + 1)
    for step in range(1, steps + 1):
        _, grad, slope = loss_and_gradient(w, b, y, own, other, has, balance, decay)
        g = np.append(grad, slope)
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        move = rate / math.sqrt(step) * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        w, b = w - move[:-1], b - move[-1]
    return ToxicityModel(float(b), dict(zip(vocabulary.to_pylist(), w.tolist(), strict=True)))


def fit(docs: DataFrame, labels: DataFrame, bound: int = 5_000, **options) -> ToxicityModel:
    """Learn from at most ``bound`` labelled rows of ``docs``."""
    strings, weights = pa.list_(pa.string()), pa.list_(pa.float32())

    @released
    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [words_of(t) for t in batch.column(1).to_pylist()]
            other = [counterfactual(w) for w in found]
            lists = []
            for side in (found, other):
                rows = [None if w is None else dict(sorted(features_of(w).items())) for w in side]
                lists.append(pa.array([None if r is None else list(r) for r in rows], strings))
                lists.append(pa.array([None if r is None else list(r.values()) for r in rows], weights))
            yield pa.record_batch([batch.column(0), batch.column(2), *lists], names=["doc_id", "y", "a", "aw", "b", "bw"])

    rows = training_rows(docs, labels, "toxic", bound).mapInArrow(read, "doc_id long, y int, a array<string>, aw array<float>, b array<string>, bw array<float>").toArrow()
    rows = rows.sort_by("doc_id")
    column = lambda c, kind: pa.concat_arrays(rows.column(c).chunks) if rows.num_rows else pa.array([], kind)
    a, b = (Rows.of(column(c, strings), column(f"{c}w", weights)) for c in "ab")
    model = train(rows.column("y").to_numpy().astype(float), a, b, **options)
    del rows, a, b
    release()
    return model


def score_documents(docs: DataFrame, model: ToxicityModel, threshold: float = 0.5) -> DataFrame:
    """doc_id, held_out, score, predicted of every row; one narrow pass."""

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scores = [model.score(t) for t in batch.column(1).to_pylist()]
            yield pa.record_batch([batch.column(0), batch.column(2), pa.array(scores, pa.float64()), pa.array([int(s >= threshold) for s in scores], pa.int32())], names=["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long"), "text", held_out(F.col("doc_id")).alias("held_out")).mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def keep_clean(docs: DataFrame, model: ToxicityModel, threshold: float = 0.5) -> DataFrame:
    """The rows of ``docs`` that the model does not reject, with the same columns; one narrow pass."""
    at = docs.columns.index("text")

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array([model.score(t) < threshold for t in batch.column(at).to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
