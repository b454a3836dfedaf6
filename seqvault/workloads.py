"""The experiments on stand-in collections: what is built, what is asked, and the measures as tidy rows."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqvault import measures
from seqvault.alphabet import collect_alphabet
from seqvault.baselines.plain_fm import PlainFM, collection_sizes
from seqvault.index import Index, IndexParams, build_index
from seqvault.operators.barrier import COPIES_BYTES, barrier, scratch_path
from seqvault.sources import views

#: For experiments only; a real key comes from cipher.new_key().
DEMO_KEY = bytes(range(64))
#: Pattern lengths of the two search protocols.
MEDIAN_LENGTHS, MEAN_LENGTHS = (15, 20, 50, 100, 200, 500), (20, 50, 100, 200, 500)
SEED = 12_345
#: Patterns of each length in the search protocols.
PATTERNS = 500
#: Stand-ins for the genomic sets: source of the reference (all its documents, joined), copies, seed.
STAND_INS = {
    "consensus_a": ("src0", 50, SEED),
    "consensus_b": ("src1", 50, SEED),
    "consensus_c": ("src2", 50, SEED),
    "random100": ("src1", 100, SEED + 1),
    "random100_second": ("src1", 100, SEED + 3),
    "random500": ("src2", 500, SEED + 2),
}


def collection(spark: SparkSession, sf_dir: str, name: str, copies: int | None = None) -> DataFrame:
    """A stand-in collection: consensus_a/b/c (50 copies), random100 and a second set, random500, whole (no copies)."""
    if name == "whole":
        return views.nuc_view(spark, sf_dir).select("item_no", "seq")
    return barrier(stand_in(spark, sf_dir, name, copies), name, codec="zstd")


def stand_in(spark: SparkSession, sf_dir: str, name: str, copies: int | None = None) -> DataFrame:
    """The mutated copies of a stand-in collection, made anew each time that they are read."""
    source, n, seed = STAND_INS[name]
    return views.variant_collection(views.reference(spark, sf_dir, source), copies or n, seed)


def parts(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A stand-in collection as item_no, start, seq, for indexes of pieces: no row holds a whole copy."""
    if name not in STAND_INS:
        return collection(spark, sf_dir, name)
    source, n, seed = STAND_INS[name]
    return barrier(views.variant_stretches(spark, sf_dir, source, n, seed), name, COPIES_BYTES, "zstd")


def in_pieces(params: IndexParams, name: str) -> IndexParams:
    """``params`` for a stand-in collection: a shard holds one stretch of all copies, which are otherwise a shard each or more."""
    return replace(params, piece=piece_of(name, params.shard_symbols * params.k)) if name in STAND_INS else params


def piece_of(name: str, shard_letters: int) -> int:
    return max(1, shard_letters // STAND_INS[name][1]) if name in STAND_INS else 0


def build_times(items: DataFrame, ks: tuple[int, ...] = (4, 5, 6, 7), params: IndexParams | None = None) -> list[dict]:
    """Seconds to build the sealed index for each k and the plain index, of items or of pieces of them."""
    out, spark = [], items.sparkSession
    for k in ks:
        seconds, _ = measures.timed(lambda k=k: build_index(items, replace(params or IndexParams(), k=k), DEMO_KEY, scratch_path(spark, "sweep")))
        out.append({"workload": "build", "k": k, "metric": "seconds", "value": seconds})
    seconds, _ = measures.timed(lambda: PlainFM.build(items, piece=params.piece if params else 0))
    return [*out, {"workload": "build", "k": 0, "metric": "seconds", "value": seconds}]


def ratios(items: DataFrame, ks: tuple[int, ...] = (4, 5, 6, 7), sizes: tuple[int, ...] = (4096, 8192, 16384, 32768), params: IndexParams | None = None) -> list[dict]:
    """Index over FASTA size on the grid of k and block size; one sort for each k. Comparison methods follow with k 0."""
    source, letters = measures.fasta_bytes(items), collect_alphabet(items)
    out = [row for index in _grid(items, ks, sizes, params, letters) for row in _ratio(index, source)]
    others = collection_sizes(items, DEMO_KEY, letters)
    return out + [{"workload": "ratio", "k": 0, "bs": 0, "metric": name, "value": size / source} for name, size in others.items()]


def _grid(items: DataFrame, ks: tuple[int, ...], sizes: tuple[int, ...], params: IndexParams | None, letters: list[str]) -> Iterator[Index]:
    """Indexes of the grid of k and block size, one sort for each k. Each is removed when the next is asked for, the first of
    a k after the last: an index that was measured is read by nobody."""
    spark = items.sparkSession
    for k in ks:
        first = build_index(items, replace(params or IndexParams(), k=k, bs=sizes[0]), DEMO_KEY, scratch_path(spark, "sweep"), letters=letters)
        yield first
        for bs in sizes[1:]:
            index = first.recut(scratch_path(spark, "recut"), bs)
            yield index
            index.drop()
        first.drop()


def _ratio(index: Index, source: int) -> list[dict]:
    """Modelled and stored size over the size of the source."""
    return [{"workload": "ratio", "k": index.meta["k"], "bs": index.meta["bs"], "metric": name, "value": size / source} for name, size in zip(("ratio", "stored_ratio"), index.sizes(), strict=True)]


def search(index: Index, patterns: DataFrame, last: str = "auto") -> list[dict]:
    """Median seconds by pattern length and seconds per occurrence, and the mean over the lengths of the second protocol."""
    return _times(index, measures.searched(index, patterns, last))


def _times(index: Index, rows: list[tuple[int, float, int, float]]) -> list[dict]:
    k, bs = index.meta["k"], index.meta["bs"]
    out = []
    for n in sorted({r[0] // 1_000_000 for r in rows}):
        mine = [r for r in rows if r[0] // 1_000_000 == n]
        hits = sum(r[2] for r in mine)
        out.append({"workload": "search", "k": k, "bs": bs, "len": n, "metric": "median_seconds", "value": measures.median([r[1] for r in mine])})
        out.append({"workload": "search", "k": k, "bs": bs, "len": n, "metric": "seconds_per_hit", "value": sum(r[1] for r in mine) / max(1, hits)})
    mean = [r[1] for r in rows if r[0] // 1_000_000 in MEAN_LENGTHS]
    return [*out, {"workload": "search", "k": k, "bs": bs, "len": 0, "metric": "mean_seconds", "value": sum(mean) / max(1, len(mean))}]


def loaded(index: Index, patterns: DataFrame) -> list[dict]:
    """Mean share of blocks opened, by pattern length."""
    rows = measures.loaded_share(index, patterns).groupBy(F.floor(F.col("pattern_id") / 1_000_000).alias("n")).agg(F.avg("share").alias("share")).collect()
    return [{"workload": "loaded", "k": index.meta["k"], "bs": index.meta["bs"], "len": n, "metric": "loaded_percent", "value": share} for n, share in sorted(map(tuple, rows))]


def sweep(items: DataFrame, patterns: DataFrame, ks: tuple[int, ...] = (4, 5, 6, 7), sizes: tuple[int, ...] = (4096, 8192, 16384, 32768), params: IndexParams | None = None) -> list[dict]:
    """Search times, loaded blocks and ratio (modelled, and as stored) on the grid of k and block size; one sort for each k, and
    times and blocks of the same searches."""
    source, out = measures.fasta_bytes(items), []
    for index in _grid(items, ks, sizes, params, collect_alphabet(items)):
        rows = measures.searched(index, patterns)
        out += _times(index, rows)
        for n in sorted({r[0] // 1_000_000 for r in rows}):
            mine = [r[3] for r in rows if r[0] // 1_000_000 == n]
            out.append({"workload": "loaded", "k": index.meta["k"], "bs": index.meta["bs"], "len": n, "metric": "loaded_percent", "value": sum(mine) / len(mine)})
        out += _ratio(index, source)
    return out


def cipher_cost(items: DataFrame, patterns: DataFrame, params: IndexParams | None = None) -> list[dict]:
    """Build and search seconds with the cipher on and off."""
    spark, out = items.sparkSession, []
    for on in (True, False):
        seconds, index = measures.timed(lambda on=on: build_index(items, replace(params or IndexParams(), encrypt=on), DEMO_KEY, scratch_path(spark, "cipher")))
        out.append({"workload": "cipher", "metric": f"build_{'on' if on else 'off'}", "value": seconds})
        mean = [r["value"] for r in search(index, patterns) if r["metric"] == "mean_seconds"][0]
        out.append({"workload": "cipher", "metric": f"search_{'on' if on else 'off'}", "value": mean})
    return out


def tidy(spark: SparkSession, rows: list[dict]) -> DataFrame:
    """workload, k, bs, len, metric, value."""
    full = [{"workload": "", "k": 0, "bs": 0, "len": 0, "metric": "", "value": 0.0} | r for r in rows]
    return spark.createDataFrame([(r["workload"], int(r["k"]), int(r["bs"]), int(r["len"]), r["metric"], float(r["value"])) for r in full], "workload string, k int, bs int, len int, metric string, value double")
