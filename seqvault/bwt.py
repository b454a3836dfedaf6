"""The Burrows-Wheeler transform of a whole collection: ranges, splitters, balance, and strategies with equal results."""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seqvault import suffix
from seqvault.operators.prefix import PART, place_by_range

#: Strategies that hold a shard in a task, and those that spread one over the cluster.
KERNELS, SPREAD = ("kernel", "runs", "ranges"), ("distributed", "doubling")


def alphabet_ranges(size: int, nr: int) -> np.ndarray:
    """First symbols of ``nr`` contiguous ranges of equal width; the last takes the rest."""
    width = -(-size // nr)
    return np.arange(0, size, width, dtype=np.int64)


def bucket_rotations(symbols: DataFrame, size: int, nr: int) -> DataFrame:
    """Add ``bucket``: the equal-width range of each rotation's first symbol. Narrow."""
    width = -(-size // nr)
    return symbols.withColumn("bucket", F.least(F.floor(F.col("sym") / width), F.lit(nr - 1)).cast("int"))


def range_histogram(symbols: DataFrame, size: int, nr: int) -> DataFrame:
    """bucket, n: rotations of every non-empty range."""
    return bucket_rotations(symbols, size, nr).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


def choose_splitters(counts: np.ndarray, parts: int) -> np.ndarray:
    """First symbols of at most ``parts`` ranges with nearly equal numbers of rotations, from symbol counts."""
    total = np.cumsum(counts)
    goals = total[-1] * np.arange(1, parts) / parts
    return np.unique(np.concatenate([[0], np.searchsorted(total, goals, "left") + 1])).astype(np.int64)


def balance(counts: list[int], workers: int) -> list[int]:
    """Worker of each range: contiguous ranges, a worker is closed when it has its fair share of what is left."""
    out, worker, mine, left = [], 0, 0, sum(counts)
    for n in counts:
        if mine and worker < workers - 1 and mine + n / 2 > left / (workers - worker):
            left -= mine
            worker, mine = worker + 1, 0
        out.append(worker)
        mine += n
    return out


def order_of(text: np.ndarray, size: int, strategy: str = "kernel", parts: int = 8) -> np.ndarray:
    """Suffix order of a shard's text by one of the in-task strategies."""
    if strategy == "kernel":
        return suffix.suffix_order_kernel(text, size)
    if strategy == "runs":
        return suffix.suffix_order_runs(text, size)
    if strategy == "ranges":
        return suffix.suffix_order_ranges(text, size, choose_splitters(np.bincount(text, minlength=size), parts))
    raise ValueError(f"unknown strategy {strategy}")


def collection_bwt(symbols: DataFrame, strategy: str = "kernel", size: int | None = None) -> DataFrame:
    """(shard, row, pos, sym): ``sym`` stands before position ``pos``, cyclically, and rows are in suffix order.

    ``symbols``: (shard, pos, sym). kernel, runs and ranges hold a shard per task; distributed sorts by ranges over the
    cluster (see :func:`range_sorted`), doubling by joins, bruteforce by rotations.
    """
    if strategy == "bruteforce":
        return suffix.suffix_order_bruteforce(symbols)
    if strategy == "doubling":
        return suffix.suffix_order_doubling(symbols)
    if strategy == "distributed":
        return range_sorted(symbols)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("pos")
        text = pdf["sym"].to_numpy(np.int64)
        order = order_of(text, size or int(text.max()) + 1, strategy)
        return pd.DataFrame({"shard": pdf["shard"].iloc[0], "row": np.arange(len(order)), "pos": order, "sym": text[order - 1]})

    return symbols.select("shard", "pos", "sym").groupBy("shard").applyInPandas(run, "shard int, row long, pos long, sym long")


def prefixes(symbols: DataFrame, width: int) -> DataFrame:
    """shard, pos, sym, prefix: the ``width`` symbols from each position on, packed so that bytes sort as symbols do.

    Positions are range-partitioned; the symbols that a partition's last positions need from the next ones, ``width`` a
    partition, are all that goes through the driver. Beyond the end of a shard stand zeros, which the end mark, smallest
    and unique, never ties with.
    """
    order = ["shard", "pos"]
    placed = place_by_range(symbols.select("shard", "pos", F.col("sym").cast("long").alias("sym")), order, "symbols")
    head = Window.partitionBy(PART).orderBy(*order)
    heads: dict[int, list[tuple[int, int]]] = {}
    for r in placed.withColumn("_at", F.row_number().over(head)).filter(F.col("_at") <= width).orderBy("shard", "pos").collect():
        heads.setdefault(r[PART], []).append((r["shard"], r["sym"]))
    parts = sorted(heads)
    following: dict[int, list[tuple[int, int]]] = {}
    for i, part in enumerate(parts):
        following[part] = list(itertools.islice((x for p in parts[i + 1 : i + 1 + width] for x in heads[p]), width))

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by([("shard", "ascending"), ("pos", "ascending")])
        shard, sym = table["shard"].to_numpy().astype(np.int64), table["sym"].to_numpy()
        tail = following[table[PART][0].as_py()] + [(-1, 0)] * width
        shards, syms = np.append(shard, [t[0] for t in tail]), np.append(sym, [t[1] for t in tail])
        rows = np.empty((len(shard), width), ">u4")
        for i in range(width):  # symbol by symbol: no wider numbers of all are held
            rows[:, i] = np.where(shards[i : i + len(shard)] == shard, syms[i : i + len(shard)], 0)
        packed = pa.FixedSizeBinaryArray.from_buffers(pa.binary(4 * width), len(rows), [None, pa.py_buffer(rows)]).cast(pa.binary())
        return pa.table({"shard": table["shard"], "pos": table["pos"], "sym": table["sym"], "prefix": packed})

    return placed.groupBy(PART).applyInArrow(run, "shard int, pos long, sym long, prefix binary")


def range_sorted(symbols: DataFrame, width: int = 8, held: int = suffix.HELD) -> DataFrame:
    """Sort by ranges over the cluster: rotations carry their first ``width`` symbols and are range-partitioned on them.

    Ranges are balanced by the position as a last key, so a prefix that very many rotations share is spread over
    partitions; inside one the sort is Spark's, which spills. Ties are resolved by doubling rounds, the last of them, over at
    most ``held`` positions, in one task.
    """
    return suffix.resolved(symbols, suffix.ranked(prefixes(symbols, width).select("shard", "prefix", "pos"), ["shard", "prefix"]), width, held)


def lf_of(l: np.ndarray) -> np.ndarray:  # noqa: E741
    """Row of the preceding position, for every row: a stable sort of the transform."""
    lf = np.empty(len(l), np.int64)
    lf[np.argsort(l, kind="stable")] = np.arange(len(l))
    return lf


def invert(l: np.ndarray) -> np.ndarray:  # noqa: E741
    """The text of a transform whose row 0 is the terminator's suffix: steps are taken by doubling, not one by one."""
    n = len(l)
    jump, rows = lf_of(l), np.zeros(1, np.int64)
    while len(rows) < n:
        rows = np.concatenate([rows, jump[rows]])
        jump = jump[jump]
    rows = rows[:n]
    text = np.empty(n, np.int64)
    # row 0 is position n-1, and its transform symbol stands before it
    text[(n - 2 - np.arange(n)) % n] = l[rows]
    return text


def invert_bwt(bwt: DataFrame) -> DataFrame:
    """(shard, pos, sym) of a transform (shard, row, sym); a shard per task."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        text = invert(pdf.sort_values("row")["sym"].to_numpy(np.int64))
        return pd.DataFrame({"shard": pdf["shard"].iloc[0], "pos": np.arange(len(text)), "sym": text})

    return bwt.select("shard", "row", "sym").groupBy("shard").applyInPandas(run, "shard int, pos long, sym long")


def bwt_per_item(items: DataFrame) -> DataFrame:
    """item_no, bwt: the transform of each item alone, with a terminator shown as the empty place ``end``.

    ``end`` is the row of the terminator in the transform.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, ends = [], []
            for seq in batch.column(1).to_pylist():
                points = np.frombuffer((seq or "").encode("utf-32-le"), "<u4").astype(np.int64) + 1
                text = np.append(points, 0)
                order = suffix.suffix_order_kernel(np.unique(text, return_inverse=True)[1].astype(np.int64))
                l = text[order - 1]  # noqa: E741
                ends.append(int(np.flatnonzero(l == 0)[0]))
                texts.append((l[l > 0] - 1).astype("<u4").tobytes().decode("utf-32-le"))
            yield pa.record_batch([batch.column(0), pa.array(texts, pa.string()), pa.array(ends, pa.int64())], names=["item_no", "bwt", "end"])

    return items.select("item_no", "seq").mapInArrow(run, "item_no long, bwt string, end long")


def bwt_runs(bwt: DataFrame) -> DataFrame:
    """shard, runs: maximal runs of equal symbols of the transform, by comparing neighbours within each shard."""
    before = F.lag("sym").over(Window.partitionBy("shard").orderBy("row"))
    return bwt.withColumn("new", (before.isNull() | (before != F.col("sym"))).cast("long")).groupBy("shard").agg(F.sum("new").alias("runs"))
