"""Collections as strings of k-blocks, with DataFrame expressions and as arrays for the shard kernels."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqvault.alphabet import Alphabet
from seqvault.operators.barrier import barrier
from seqvault.operators.prefix import PART, place_by_range, running_sum

#: Shown for the pad digit in DataFrame form; a private-use character that data may not hold.
PAD_MARK = ""


def to_blocks(items: DataFrame, k: int) -> DataFrame:
    """item_no, pos (block number in the item), block (k characters, the last one padded with PAD_MARK), n_pad."""
    padded = F.rpad("seq", (F.ceil(F.length("seq") / k) * k).cast("int"), PAD_MARK)
    cut = F.regexp_extract_all(padded, F.lit(f"(?s).{{{k}}}"), F.lit(0))
    n_pad = (-F.length("seq")) % k
    return items.select("item_no", F.pmod(n_pad, F.lit(k)).alias("n_pad"), F.posexplode(cut).alias("pos", "block")).select("item_no", F.col("pos").cast("long").alias("pos"), "block", F.col("n_pad").cast("int").alias("n_pad"))


def from_blocks(blocks: DataFrame) -> DataFrame:
    """item_no, seq: the inverse of :func:`to_blocks`. Items without blocks (empty ones) are absent."""
    joined = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("pos", "block"))), lambda b: b["block"]), "")
    return blocks.groupBy("item_no").agg(F.replace(joined, F.lit(PAD_MARK), F.lit("")).alias("seq"))


def n_symbols(length: Column, k: int) -> Column:
    """Blocks of an item and its separator."""
    return (F.ceil(length / k) + 1).cast("long")


def plan_shards(items: DataFrame, k: int, most_symbols: int) -> DataFrame:
    """``items`` with a shard number: consecutive items (by item_no) that hold about ``most_symbols`` symbols.

    A running sum over range partitions; no window over the whole table. Only numbers and lengths of items are placed, so no
    text is written for it. An item larger than a shard is one by itself.
    """
    sized = items.groupBy("item_no").agg(F.sum(n_symbols(F.length("seq"), k)).alias("_n")).withColumn("_all", F.lit(0))
    summed = running_sum(place_by_range(sized, ["_all", "item_no"], "shards"), ["_all"], ["item_no"], "_n", "_sum")
    shard = F.floor((F.col("_sum") - F.col("_n")) / most_symbols).cast("int")
    numbered = barrier(summed.select(F.col("item_no").alias("_item"), shard.alias("shard")), "shards")
    return items.join(numbered, F.col("item_no").eqNullSafe(F.col("_item"))).drop("_item")


def join_collection(seqs: list[str], alphabet: Alphabet, order: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The joined string of a shard, with each item's first symbol and number of blocks.

    Every item is followed by a separator block, the last by the terminator block. ``order``: new number of each id.
    """
    parts, starts, counts, at = [], [], [], 0
    separator = np.array([alphabet.separator], np.int64)
    for seq in seqs:
        ids = alphabet.blocks(seq)
        parts += [ids, separator]
        starts.append(at)
        counts.append(len(ids))
        at += len(ids) + 1
    parts.append(np.zeros(1, np.int64))
    text = np.concatenate(parts)
    return (order[text] if order is not None else text), np.array(starts, np.int64), np.array(counts, np.int64)


def joined_starts(planned: DataFrame, k: int) -> DataFrame:
    """``planned`` (items with a shard number) with start_sym and n_sym, by a two-pass running sum; written once."""
    sized = planned.withColumn("_n", n_symbols(F.length("seq"), k))
    keys = ["shard", "item_no"]
    summed = running_sum(place_by_range(sized, keys, "starts"), ["shard"], ["item_no"], "_n", "_sum").drop(PART)
    return barrier(summed.withColumns({"start_sym": F.col("_sum") - F.col("_n"), "n_sym": F.col("_n") - 1}).drop("_n", "_sum"), "placed")


def joined_rows(planned: DataFrame, alphabet: Alphabet, order) -> tuple[DataFrame, DataFrame]:
    """The joined strings of shards that no task can hold: (shard, pos, sym), and the items with start and n_sym.

    ``planned``: items with a shard number; ``order``: broadcast new numbers of ids. Starts come from a two-pass running
    sum; an item's symbols are made by the task that reads it. The end mark follows the last item of a shard.
    """
    starts = joined_starts(planned, alphabet.k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard, start, seq in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                ids = np.append(alphabet.blocks(seq), alphabet.separator)
                syms = ids if order.value is None else order.value[ids]
                yield pa.record_batch([pa.array(np.full(len(ids), shard, np.int32)), pa.array(start + np.arange(len(ids))), pa.array(syms)], names=["shard", "pos", "sym"])

    rows = starts.select("shard", "start_sym", "seq").mapInArrow(run, "shard int, pos long, sym long")
    ends = starts.groupBy("shard").agg((F.max(F.col("start_sym") + F.col("n_sym")) + 1).alias("pos")).withColumn("sym", F.lit(0).cast("long"))
    return rows.unionByName(ends), starts
