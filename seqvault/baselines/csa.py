"""Compressed suffix array: the successor function in deflated differences, with sampled positions."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.alphabet import Alphabet, collect_alphabet
from seqvault.encode import join_collection, plan_shards
from seqvault.operators.barrier import barrier
from seqvault.suffix import suffix_order_kernel


def successor(order: np.ndarray) -> np.ndarray:
    """Row of the suffix one shorter, for every row."""
    row = np.empty(len(order), np.int64)
    row[order] = np.arange(len(order))
    return row[(order + 1) % len(order)]


class SuccessorIndex:
    def __init__(self, text: np.ndarray, size: int, step: int):
        order = suffix_order_kernel(text, size)
        self.n, self.step = len(text), step
        psi = successor(order)
        self.packed = zlib.compress(np.diff(psi, prepend=0).astype("<i4").tobytes(), 6)
        self.c = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=size))])
        self.mark_rows = np.flatnonzero(order % step == 0)
        self.mark_pos = order[self.mark_rows]
        self.psi = np.cumsum(np.frombuffer(zlib.decompress(self.packed), "<i4").astype(np.int64))

    def range_of(self, digits: np.ndarray) -> tuple[int, int]:
        """Backward: rows of a symbol whose successor lies in the range so far; the successor grows within a symbol."""
        low, high = 0, self.n
        for s in digits[::-1].tolist():
            a, b = self.c[s], self.c[s + 1]
            part = self.psi[a:b]
            low, high = a + np.searchsorted(part, low), a + np.searchsorted(part, high)
            if low >= high:
                return 0, 0
        return int(low), int(high)

    def positions(self, rows: np.ndarray) -> np.ndarray:
        out, walk, at, steps = np.zeros(len(rows), np.int64), np.arange(len(rows)), rows, 0
        while len(walk):
            spot = np.minimum(np.searchsorted(self.mark_rows, at), len(self.mark_rows) - 1)
            marked = self.mark_rows[spot] == at
            out[walk[marked]] = (self.mark_pos[spot[marked]] - steps) % self.n
            walk, at, steps = walk[~marked], self.psi[at[~marked]], steps + 1
        return out


def csa_locate(items: DataFrame, patterns: DataFrame, mark_pct: int = 5, shard_symbols: int = 1 << 22) -> DataFrame:
    """pattern_id, item_no, offset: builds each shard's array in its task and searches it."""
    letters = collect_alphabet(items)
    alphabet, step = Alphabet(tuple(letters), 1), max(1, -(-100 // mark_pct))
    planned = barrier(plan_shards(items.select("item_no", "seq"), 1, shard_symbols), "planned")
    asked = patterns.select("pattern_id", "pattern").crossJoin(planned.select(F.col("shard").alias("of")).distinct())  # every shard is asked

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        left = left.sort_by("item_no")
        text, starts, _ = join_collection(left["seq"].to_pylist(), alphabet, None)
        index, items_ = SuccessorIndex(text, alphabet.sigma, step), left["item_no"].to_numpy()
        out: list[list[np.ndarray]] = [[np.zeros(0, np.int64)] for _ in range(3)]
        for number, pattern in zip(right["pattern_id"].to_pylist(), right["pattern"].to_pylist(), strict=True):
            digits = alphabet.digits(pattern)
            if not len(digits) or (digits < 0).any():
                continue
            at = index.positions(np.arange(*index.range_of(digits)))
            owner = np.searchsorted(starts, at, "right") - 1
            for part, column in zip(out, (np.full(len(at), number), items_[owner], at - starts[owner]), strict=True):
                part.append(column)
        return pa.table(dict(zip(("pattern_id", "item_no", "offset"), map(np.concatenate, out), strict=True)))

    return planned.groupBy("shard").cogroup(asked.groupBy("of")).applyInArrow(run, "pattern_id long, item_no long, offset long")
