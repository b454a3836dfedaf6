"""Patterns as displaced block patterns, their counts, and the choices a search makes."""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqvault.alphabet import PAD, Alphabet

WILD = -1


def super_patterns(patterns: DataFrame, k: int) -> DataFrame:
    """pattern_id, d, m, parts: the k displaced block patterns of each pattern, with ``?`` for free characters."""
    d = F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("d")
    rows = patterns.select("pattern_id", "pattern", d)
    m = F.ceil((F.col("d") + F.length("pattern")) / k).cast("int")
    padded = F.rpad(F.concat(F.repeat(F.lit("?"), F.col("d")), F.col("pattern")), (F.col("m") * k).cast("int"), F.lit("?"))
    return rows.withColumn("m", m).select("pattern_id", "d", "m", F.regexp_extract_all(padded, F.lit(f"(?s).{{{k}}}"), F.lit(0)).alias("parts"))


def wildcards(length: int, d: int, k: int) -> int:
    """Free characters of the block pattern at displacement ``d``."""
    return d + (-(d + length)) % k


def naive_super_count(length: int, k: int, sigma: int) -> int:
    """Concrete block patterns over all displacements: every free character takes every letter."""
    return sum((sigma - 2) ** wildcards(length, d, k) for d in range(k))


def paper_super_count(length: int, k: int, sigma: int) -> int:
    """The published closed form; it equals the exact count where the length is 1 more than a multiple of k."""
    return k * (sigma - 2) ** (k - length % k)


def super_pattern_counts(patterns: DataFrame, k: int, sigma: int) -> DataFrame:
    """pattern_id, naive, formula, optimised, without Python."""
    length = F.length("pattern")
    free = lambda d: F.lit(d) + F.pmod(-(F.lit(d) + length), F.lit(k))
    power: Column = sum((F.pow(F.lit(float(sigma - 2)), free(d)) for d in range(1, k)), F.pow(F.lit(float(sigma - 2)), free(0)))
    formula = F.lit(float(k)) * F.pow(F.lit(float(sigma - 2)), F.lit(k) - length % k)
    return patterns.select("pattern_id", power.cast("long").alias("naive"), formula.cast("long").alias("formula"), F.lit(k).cast("long").alias("optimised"))


@dataclass(frozen=True)
class SuperPattern:
    """Digits of whole blocks, WILD where any character goes."""

    d: int
    parts: np.ndarray  # m rows of k digits

    @property
    def m(self) -> int:
        return len(self.parts)

    @property
    def first_masked(self) -> bool:
        return bool((self.parts[0] == WILD).any())

    @property
    def last_masked(self) -> bool:
        return bool((self.parts[-1] == WILD).any())


def displaced(digits: np.ndarray, k: int) -> list[SuperPattern]:
    """The k block patterns of a pattern's digits."""
    out = []
    for d in range(k):
        tail = (-(d + len(digits))) % k
        whole = np.concatenate([np.full(d, WILD), digits, np.full(tail, WILD)])
        out.append(SuperPattern(d, whole.reshape(-1, k)))
    return out


@dataclass(frozen=True)
class PlannedLot:
    """The displaced block patterns of some patterns, the same for every shard, as arrays.

    ``first`` and ``last`` are rows of ``masks`` for a masked first and last block, or -1; the fixed blocks between stand in
    ``ids`` from ``begin`` to ``end``. A pattern of one block has a first mask only.
    """

    pattern: np.ndarray
    d: np.ndarray
    m: np.ndarray
    first: np.ndarray
    last: np.ndarray
    begin: np.ndarray
    end: np.ndarray
    ids: np.ndarray
    masks: np.ndarray


@lru_cache(maxsize=16)
def planned_lot(patterns: tuple[str, ...], alphabet: Alphabet) -> PlannedLot:
    """Kept in a worker, which asks shard after shard for the same patterns. All are cut into blocks at once."""
    k = alphabet.k
    digits = alphabet.digits("".join(patterns))
    sizes = np.array([len(p) for p in patterns], np.int64)
    starts = np.cumsum(sizes) - sizes
    unknown = np.append(0, np.cumsum(digits < 0))
    asked = np.flatnonzero((sizes > 0) & (unknown[starts + sizes] == unknown[starts]))
    pattern, d = np.repeat(asked, k), np.tile(np.arange(k), len(asked))
    m = -(-(d + sizes[pattern]) // k)
    heads = np.cumsum(m) - m
    parts = np.full(int(m.sum()) * k, WILD, np.int64)
    n = sizes[pattern]
    inside = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
    parts[inside + np.repeat(heads * k + d, n)] = digits[inside + np.repeat(starts[pattern], n)]
    parts = parts.reshape(-1, k)
    masked, tail = (d > 0) | (m == 1), ((d + n) % k > 0) & (m > 1)
    fixed = np.ones(len(parts), bool)
    fixed[heads[masked]] = fixed[(heads + m - 1)[tail]] = False
    before = np.append(0, np.cumsum(fixed))
    free = parts[np.concatenate([heads[masked], (heads + m - 1)[tail]])]
    codes = (free - WILD) @ (alphabet.sigma + 1) ** np.arange(k, dtype=np.int64) if len(free) else np.zeros(0, np.int64)
    _, rows, numbers = np.unique(codes, return_index=True, return_inverse=True)
    first, last = np.full(len(m), -1), np.full(len(m), -1)
    first[masked], last[tail] = numbers[: masked.sum()], numbers[masked.sum() :]
    return PlannedLot(pattern, d, m, first, last, before[heads], before[heads + m], alphabet.of_digits(parts[fixed]), free[rows])


def mask_matches(digits: np.ndarray, mask: np.ndarray, pad_wildcards: bool = True) -> np.ndarray:
    """Which rows of block digits fit a mask.

    A free character is a letter. Free characters after the fixed ones may also be the pad, which only stands at the end
    of an item, unless ``pad_wildcards`` is off (the literal rule, which loses hits in an item's padded last block).
    """
    fixed = np.flatnonzero(mask != WILD)
    end = fixed[-1] + 1 if len(fixed) else 0
    good = np.ones(len(digits), bool)
    for i, want in enumerate(mask):
        column = digits[:, i]
        if want != WILD:
            good &= column == want
        elif pad_wildcards and i >= end:
            good &= column >= PAD
        else:
            good &= column > PAD
    return good


def choose_last(rows: int, step: int, candidates: int, m: int) -> str:
    """Verify each row of the fixed part (a walk to a mark and back) or search once per symbol that fits the last mask."""
    return "enumerate" if enumerates(rows, step, candidates, m) else "verify"


def enumerates(rows, step: int, candidates, m):
    """Whether :func:`choose_last` enumerates; for numbers or arrays."""
    return candidates * m * 2 < rows * (step + 1)


def used_symbols(alphabet: Alphabet, order: np.ndarray | None, syms: np.ndarray) -> np.ndarray:
    """Digits of the blocks behind (scrambled) symbols."""
    if order is not None:
        inverse = np.empty(len(order), np.int64)
        inverse[order] = np.arange(len(order))
        syms = inverse[syms]
    return alphabet.to_digits(syms)
