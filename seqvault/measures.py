"""Cost and accuracy measures of indexes, searches and inputs."""

from __future__ import annotations

import math
import resource
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seqvault.encode import to_blocks
from seqvault.index import Index


def timed(run: Callable) -> tuple[float, object]:
    """Wall seconds of a call, and its result. The call must materialise what it builds."""
    began = time.perf_counter()
    out = run()
    return time.perf_counter() - began, out


def fasta_bytes(items: DataFrame, width: int = 60) -> int:
    """Size of a collection as FASTA: a header line and sequence lines of ``width`` letters."""
    name = F.length("seq_id") if "seq_id" in items.columns else F.length(F.col("item_no").cast("string"))
    return int(items.agg(F.sum(name + 2 + F.length("seq") + F.ceil(F.length("seq") / width))).first()[0] or 0)


def compression_ratio(index_bytes: int, source_bytes: int) -> float:
    """Index size over FASTA size; smaller is better."""
    return index_bytes / source_bytes if source_bytes else 0.0


def index_bytes(index: Index) -> int:
    return int(index.payload_bytes().agg(F.sum("bytes")).first()[0] or 0)


def block_histogram(items: DataFrame, k: int) -> DataFrame:
    """block, n: how often each k-block occurs in the input, items padded at their ends."""
    return to_blocks(items, k).groupBy("block").agg(F.count(F.lit(1)).alias("n"))


def homophony(items: DataFrame, k: int) -> DataFrame:
    """log10 of the degree of homophony: the product, over frequencies, of the factorial of how many blocks share one.

    Factorials enter as sums of logarithms, added up per number of blocks that share a frequency.
    """
    shared = block_histogram(items, k).groupBy("n").agg(F.count(F.lit(1)).alias("m"))
    logs = F.aggregate(F.sequence(F.lit(1).cast("long"), F.col("m")), F.lit(0.0), lambda s, i: s + F.log10(i.cast("double")))
    return shared.agg(F.round(F.coalesce(F.sum(logs), F.lit(0.0)), 3).alias("log10_homophony"))


def search_times(index: Index, patterns: DataFrame, last: str = "auto") -> list[tuple[int, float, int]]:
    """(pattern_id, seconds, hits) of each pattern: its times in all shards added up, each measured in the shard's task on
    an open shard, after a warming search. What opening takes is in :func:`open_times`."""
    return [r[:3] for r in searched(index, patterns, last)]


def searched(index: Index, patterns: DataFrame, last: str = "auto") -> list[tuple[int, float, int, float]]:
    """As :func:`search_times`, and the share of blocks that :func:`loaded_share` gives, of the same searches."""
    share = 100 * F.sum("blocks_loaded") / F.sum("blocks")
    rows = index.search_times(patterns, last).groupBy("pattern_id").agg((F.sum("micros") / 1e6).alias("s"), F.sum("hits").alias("hits"), share.alias("share"))
    return [(r[0], float(r[1]), int(r[2]), float(r[3])) for r in rows.collect()]  # one row per pattern of an experiment


def open_times(index: Index, patterns: DataFrame) -> DataFrame:
    """shard, open_us: how long each shard took to open."""
    return index.search_times(patterns.limit(1)).groupBy("shard").agg(F.max("open_us").alias("open_us"))


def loaded_share(index: Index, patterns: DataFrame, last: str = "auto") -> DataFrame:
    """pattern_id, share: blocks that a pattern's search opens over all blocks, in percent."""
    work = index.work(patterns, last).groupBy("pattern_id").agg((100 * F.sum("blocks_loaded") / F.sum("blocks")).alias("share"))
    return work


def exactness(found: DataFrame, truth: DataFrame) -> DataFrame:
    """false_hits, missed_hits: multiset differences both ways; both are 0 for an exact search."""
    a = found.select("pattern_id", "item_no", "offset").exceptAll(truth.select("pattern_id", "item_no", "offset"))
    b = truth.select("pattern_id", "item_no", "offset").exceptAll(found.select("pattern_id", "item_no", "offset"))
    return a.select(F.lit("false_hits").alias("measure")).unionByName(b.select(F.lit("missed_hits").alias("measure"))).groupBy("measure").agg(F.count(F.lit(1)).alias("n"))


def scatter(symbols: DataFrame, bwt: DataFrame, bs: int) -> DataFrame:
    """shard, pairs, apart, mean_distance: index blocks that hold the symbols of neighbouring source blocks."""
    holder = bwt.select("shard", F.col("pos"), F.floor(F.col("row") / bs).alias("b"))
    later = F.lead("b").over(Window.partitionBy("shard").orderBy("pos"))
    pairs = holder.withColumn("next", later).filter("next is not null")
    return pairs.groupBy("shard").agg(F.count(F.lit(1)).alias("pairs"), F.count_if(F.col("b") != F.col("next")).alias("apart"), F.avg(F.abs(F.col("b") - F.col("next"))).alias("mean_distance"))


def speedup(seconds: dict[int, float]) -> dict[int, float]:
    """Time on one thread over time on each number of threads."""
    return {t: seconds[1] / s for t, s in sorted(seconds.items())}


def encryption_overhead(with_cipher: float, without: float) -> float:
    return with_cipher - without


def memory_peak_mb() -> float:
    """Largest resident size of this process so far."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024


def median(values: list[float]) -> float:
    ordered = sorted(values)
    n = len(ordered)
    return math.nan if not n else (ordered[n // 2] if n % 2 else (ordered[n // 2 - 1] + ordered[n // 2]) / 2)
