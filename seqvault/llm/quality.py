"""Quality by supervised subword embeddings.

A word is represented by its own hashed id and those of its character n-grams (with word-boundary marks); a document is
the average of all those vectors; a softmax layer gives the class. Vectors and layer are trained by numpy stochastic
gradient descent on the driver from at most ``bound`` labelled rows, whose hashed ids come from the executors. Scoring
uses that averaging and the layer are linear: each bucket's contribution to the logit difference is one number, so a
task needs one array of ``buckets`` numbers and remembers the sum of each word it has met.

Null or empty text: the average is the zero vector. Rows with equal ids are scored each; of rows with a labelled id in
common, one is learned from. Without labels the score is 0.5. Empty table: empty result. Labels, lang, source and ids are no inputs of a score.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.llm.labelled import held_out, training_rows
from seqvault.llm.workers import release, released

#: Words remembered per task; the memo is emptied beyond that.
MEMO = 300_000


def subword_ids(word: str, buckets: int, low: int, high: int) -> list[int]:
    """Hashed id of a word and of the n-grams of ``<word>``, of ``low`` to ``high`` characters."""
    marked = f"<{word}>"
    size = len(marked)
    grams = [marked[i : i + n] for n in range(low, min(high, size - 1) + 1) for i in range(size - n + 1)]
    return [crc32(g.encode("utf-8", "replace")) % buckets for g in (marked, *grams)]


def document_ids(text: str | None, buckets: int, low: int, high: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct ids of a whole text and how often each occurs."""
    counts: dict[int, int] = {}
    for word, n in Counter((text or "").split()).items():
        for i in subword_ids(word, buckets, low, high):
            counts[i] = counts.get(i, 0) + n
    ids = np.fromiter(sorted(counts), np.int32, len(counts))
    return ids, np.array([counts[i] for i in ids.tolist()], np.float32)


@dataclass
class QualityModel:
    """``unit``: each bucket's share of the logit difference between label 1 and label 0."""

    unit: np.ndarray
    bias: float
    low: int
    high: int

    def scorer(self):
        """A function text -> probability of label 1, with its own memo of words."""
        unit, buckets, low, high = self.unit.tolist(), len(self.unit), self.low, self.high

        class Memo(dict):
            """Word -> sum of its units, with the number of its ids as the imaginary part."""

            def __missing__(self, word: str) -> complex:
                if len(self) >= MEMO:
                    self.clear()
                ids = subword_ids(word, buckets, low, high)
                self[word] = both = complex(sum([unit[i] for i in ids]), len(ids))
                return both

        memo = Memo()

        def score(text: str | None) -> float:
            both = sum(map(memo.__getitem__, (text or "").split()), 0j)
            z = self.bias + (both.real / both.imag if both.imag else 0.0)
            return 1 / (1 + math.exp(-max(-700.0, min(700.0, z))))

        return score


def loss_and_gradients(mine: np.ndarray, share: np.ndarray, layer: np.ndarray, bias: np.ndarray, label: int) -> tuple[float, np.ndarray, np.ndarray, np.ndarray]:
    """Log loss of one document, and its gradients by the vectors of its ids, by the layer and by the bias.

    ``share``: how much of the document each id is; the document's vector is the average by these shares.
    """
    hidden = share @ mine
    logits = hidden @ layer + bias
    logits = logits - logits.max()
    p = np.exp(logits)
    loss = float(np.log(p.sum()) - logits[label])
    p /= p.sum()
    p[label] -= 1
    return loss, np.outer(share, layer @ p), np.outer(hidden, p), p


def train(y: np.ndarray, ids: list[np.ndarray], counts: list[np.ndarray], buckets: int = 1 << 17, dim: int = 12, epochs: int = 12, rate: float = 0.6, low: int = 2, high: int = 4, seed: int = 7) -> QualityModel:
    """Stochastic gradient descent over documents in a seeded order, with a linearly falling rate."""
    rng = np.random.default_rng(seed)
    vectors = rng.uniform(-1 / dim, 1 / dim, (buckets, dim)).astype(np.float32)
    layer, bias = np.zeros((dim, 2), np.float32), np.zeros(2, np.float32)
    total, done = max(1, epochs * len(y)), 0
    for _ in range(epochs if len(y) else 0):
        for k in rng.permutation(len(y)).tolist():
            step = rate * (1 - done / total)
            done += 1
            if not len(ids[k]):
                continue
            share = counts[k] / counts[k].sum()
            mine = vectors[ids[k]]
            _, to_mine, to_layer, to_bias = loss_and_gradients(mine, share, layer, bias, int(y[k]))
            layer -= step * to_layer
            bias -= step * to_bias
            # each id's gradient is scaled by its share; the factor keeps the sum of steps per document of order one
            vectors[ids[k]] = mine - step * len(share) ** 0.5 * to_mine
    return QualityModel((vectors @ (layer[:, 1] - layer[:, 0])).astype(np.float64), float(bias[1] - bias[0]), low, high)


def fit(docs: DataFrame, labels: DataFrame, bound: int = 3_000, buckets: int = 1 << 17, low: int = 2, high: int = 4, **options) -> QualityModel:
    """Learn from at most ``bound`` labelled rows of ``docs``."""

    @released
    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [document_ids(t, buckets, low, high) for t in batch.column(1).to_pylist()]
            yield pa.record_batch([batch.column(0), batch.column(2), pa.array([f[0] for f in found], pa.list_(pa.int32())), pa.array([f[1] for f in found], pa.list_(pa.float32()))], names=["doc_id", "y", "ids", "counts"])

    rows = training_rows(docs, labels, "quality", bound).mapInArrow(read, "doc_id long, y int, ids array<int>, counts array<float>").toArrow()
    rows = rows.sort_by("doc_id")
    lists = [[x.values.to_numpy() for x in rows.column(c)] for c in ("ids", "counts")]
    model = train(rows.column("y").to_numpy(), *lists, buckets=buckets, low=low, high=high, **options)
    del rows, lists
    release()
    return model


def score_documents(docs: DataFrame, model: QualityModel, threshold: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted of every row; one narrow pass."""

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = model.scorer()
        for batch in batches:
            scores = [score(t) for t in batch.column(1).to_pylist()]
            yield pa.record_batch([batch.column(0), batch.column(2), pa.array(scores, pa.float64()), pa.array([int(s >= threshold) for s in scores], pa.int32())], names=["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long"), "text", held_out(F.col("doc_id")).alias("held_out")).mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
