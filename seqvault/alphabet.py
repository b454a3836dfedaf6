"""The symbols of a collection, their k-fold extension and its keyed order."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.cipher import KeyStream

#: Reserved digits: they stand for no character, so any character may occur in the data.
END, PAD = 0, 1
#: Extended alphabets beyond this are not permuted as a whole.
MOST_IDS = 1 << 24


def collect_alphabet(items: DataFrame, col: str = "seq") -> list[str]:
    """Distinct characters in ascending order: distinct per task, then over the collection; a few rows reach the driver.

    A long item is never split into an array of its characters.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[str] = set()
        for batch in batches:
            for text in batch.column(0):
                known = "".join(c for c in seen if c.isascii()).encode()
                # without the known ones, a text is short: the rest of UTF-8 stands without its ASCII bytes
                seen.update((text.as_buffer() or pa.py_buffer(b"")).to_pybytes().translate(None, known).decode())
        yield pa.record_batch([pa.array(sorted(seen), pa.string())], names=["letter"])

    letters = items.select(F.col(col).cast("string").alias("text")).mapInArrow(run, "letter string").distinct()
    return sorted(r[0] for r in letters.collect())


@dataclass(frozen=True)
class Alphabet:
    """``letters`` have the digits 2, 3, ...; digits 0 and 1 are the terminator and the separator or pad."""

    letters: tuple[str, ...]
    k: int

    @property
    def sigma(self) -> int:
        return len(self.letters) + 2

    @property
    def size(self) -> int:
        """Number of k-blocks."""
        return self.sigma**self.k

    @property
    def separator(self) -> int:
        """Id of the block of k separators."""
        return self.of_digits(np.full((1, self.k), PAD))[0]

    def of_digits(self, digits: np.ndarray) -> np.ndarray:
        """Ids of rows of k digits."""
        ids = np.zeros(len(digits), np.int64)
        for j in range(self.k):
            ids *= self.sigma
            ids += digits[:, j]
        return ids

    def to_digits(self, ids: np.ndarray) -> np.ndarray:
        return np.asarray(ids, np.int64)[:, None] // self.sigma ** np.arange(self.k - 1, -1, -1, dtype=np.int64) % self.sigma

    def digits(self, text: str) -> np.ndarray:
        """Digits of a text; -1 for characters that the collection lacks."""
        known = np.array([ord(c) for c in self.letters], np.int64)
        if text.isascii():
            place = np.full(128, -1, np.int16)
            low = known[known < 128]  # the first ones: letters are in ascending order
            place[low] = np.arange(len(low)) + 2
            return place[np.frombuffer(text.encode(), np.uint8)]
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4").astype(np.int64)
        spot = np.searchsorted(known, points)
        found = spot < len(known)
        found[found] = known[spot[found]] == points[found]
        return np.where(found, spot + 2, -1)

    def text(self, digits: np.ndarray) -> str:
        """Characters of digits; the reserved ones are left out."""
        kept = digits[digits > PAD] - 2
        points = np.array([ord(c) for c in self.letters], "<u4")[kept]
        return points.tobytes().decode("utf-32-le", "surrogatepass")

    def blocks(self, text: str) -> np.ndarray:
        """Ids of the blocks of a text, the last one padded."""
        digits = self.digits(text)
        padded = np.append(digits, np.full(-len(digits) % self.k, PAD, digits.dtype))
        return self.of_digits(padded.reshape(-1, self.k))


def scramble_key(key: bytes, size: int) -> np.ndarray:
    """A keyed permutation of 0..size-1 that leaves 0 in place: position i holds the new number of id i.

    A Fisher-Yates shuffle from the top; draws are taken below each bound, without the first element.
    """
    if size > MOST_IDS:
        raise ValueError(f"{size} ids: over {MOST_IDS}, order the observed ids instead (scramble_observed)")
    order = np.arange(size, dtype=np.int64)
    if size > 2:
        bounds = np.arange(size, 2, -1, dtype=np.int64) - 1
        swap = (KeyStream(key[:32], 0).below(bounds) + 1).tolist()
        items = order.tolist()
        for i, j in zip(range(size - 1, 1, -1), swap, strict=True):
            items[i], items[j] = items[j], items[i]
        order = np.array(items, np.int64)
    return order


def scramble_observed(ids: DataFrame, key: bytes, col: str = "sym") -> DataFrame:
    """For alphabets too large to permute: (id, rank) of the observed ids in the order of a keyed hash, 0 first.

    The hash key reaches executors in a closure, never as a literal of the plan.
    """
    import hashlib

    from pyspark.sql.functions import pandas_udf

    from seqvault.operators.prefix import place_by_range, row_numbers

    secret = key[:32]

    @pandas_udf("binary")
    def keyed(x):
        return x.map(lambda v: hashlib.blake2b(int(v).to_bytes(8, "little"), key=secret, digest_size=16).digest())

    distinct = ids.select(F.col(col).cast("long").alias("id")).distinct().withColumn("tag", F.when(F.col("id") == END, F.lit(b"")).otherwise(keyed("id")))
    placed = place_by_range(distinct, ["tag", "id"], "observed")
    return row_numbers(placed, ["tag", "id"], "rank").select("id", "rank")
