"""Benchmark decontamination by SimHash over item-sized windows, in DataFrame operations only.

Texts are compared as lower-cased runs of letters and digits, in shingles of ``words`` words (an item of fewer words is
one shingle). A document is contaminated by an item if one of its windows of as many words as the item (the whole
document if it is shorter) has a weighted Jaccard similarity of ``similarity`` or more to it, shingles weighing as often
as they occur.

1. A window that similar shares at least ``similarity / (1 + similarity)`` of all shingles of both with the item. Positions
   of shingles of items of a length are found by one equi-join, and only windows with so many of them go on: a bound, so
   no match is lost and clean text costs no fingerprint.
2. Each distinct window gets a 64-bit SimHash, as each item has.
3. Multi-index join: fingerprints are cut into ``BLOCKS`` blocks; a pair within ``radius`` bits differs in at most
   ``radius // BLOCKS`` bits in one of them. Items are listed under every value so near to their own in every block, so
   joining on (length, block, value) finds all such pairs.
4. Pairs within the radius are verified by the exact weighted similarity.

At a similarity of exactly 0.8, the mean distance is 9.7 bits with a deviation of 2.9; the radius of 20 leaves out about
one such window in 5,000, and none that is an exact passage. Windows are compared once per distinct content, so a passage
in a third of all documents is one entry.

Null or empty texts match nothing. Rows with equal id and text are judged alike; a null id is kept apart from others by
the text. Empty tables: no document is contaminated. Clashing column names do not matter: only ids and texts are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqvault.operators.barrier import barrier

#: Numbers of a table that may be sent to every task (8 bytes each); beyond that the join is shuffled.
SMALL = 500_000
#: Blocks of a fingerprint: 9 or 10 bits wide, with 46 or 56 values within two bits for an item.
BLOCKS = 7


def word_array(text: Column) -> Column:
    """Lower-cased runs of letters and digits of a whole text."""
    plain = F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", " "))
    return F.when(plain == "", F.array().cast("array<string>")).otherwise(F.split(plain, " "))


def shingle_array(w: Column, k: int) -> Column:
    """Hashes of all runs of ``k`` words of the array column ``w``, in order."""
    runs = F.transform(F.sequence(F.lit(0), F.size(w) - k), lambda i: F.xxhash64(*[F.get(w, i + j) for j in range(k)]))
    return F.when(F.size(w) >= k, runs).otherwise(F.array().cast("array<bigint>"))


def _numbered(shingles: Column, k: int) -> Column:
    """(k, p, h) of shingles of ``k`` words."""
    return F.transform(shingles, lambda h, p: F.struct(F.lit(k).alias("k"), p.alias("p"), h.alias("h")))


def simhash(hashes: Column) -> Column:
    """64 bits, each set if it is set in over half of the hashes (repeats count)."""
    ones = lambda b: F.aggregate(hashes, F.lit(0), lambda n, h: n + F.call_function("shiftrightunsigned", h, b).bitwiseAND(F.lit(1)).cast("int"))
    return F.aggregate(F.sequence(F.lit(0), F.lit(63)), F.lit(0).cast("long"), lambda f, b: f.bitwiseOR(F.when(ones(b) * 2 > F.size(hashes), _shift_left(F.lit(1).cast("long"), b)).otherwise(F.lit(0).cast("long"))))


def _shift_left(x: Column, bits: Column) -> Column:
    return F.call_function("shiftleft", x, bits)


def block_cuts() -> list[int]:
    return [64 * i // BLOCKS for i in range(BLOCKS + 1)]


def blocks(fp: Column) -> Column:
    """(block, value) of ``BLOCKS`` nearly equal parts of a fingerprint."""
    cuts = block_cuts()
    return F.array(*[F.struct(F.lit(i).alias("block"), F.shiftrightunsigned(fp, cuts[i]).bitwiseAND(F.lit((1 << (cuts[i + 1] - cuts[i])) - 1)).alias("value")) for i in range(BLOCKS)])


def near_blocks(entries: DataFrame, radius: int) -> DataFrame:
    """``entries`` with block and value for every value within ``radius // BLOCKS`` bits of their own in a block."""
    cuts = block_cuts()
    widest = max(b - a for a, b in zip(cuts, cuts[1:], strict=False))
    masks = {0}
    for _ in range(radius // BLOCKS):
        masks |= {m ^ (1 << i) for m in masks for i in range(widest)}
    width = F.get(F.array(*[F.lit(b - a) for a, b in zip(cuts, cuts[1:], strict=False)]), F.col("x.block"))
    fitting = F.filter(F.array(*[F.lit(m).cast("long") for m in sorted(masks)]), lambda m: F.call_function("shiftrightunsigned", m, width) == 0)
    own = entries.withColumn("x", F.explode(blocks(F.col("fp"))))
    return own.withColumn("mask", F.explode(fitting)).select(*entries.columns, "x.block", F.col("x.value").bitwiseXOR(F.col("mask")).alias("value"))


def weighted_similarity(a: Column, b: Column) -> Column:
    """Sum of the smaller over sum of the larger multiplicities of two arrays."""
    times = lambda x, h: F.size(F.filter(x, lambda y: y == h))
    both = F.aggregate(F.array_distinct(a), F.lit(0), lambda n, h: n + F.least(times(a, h), times(b, h)))
    return both / (F.size(a) + F.size(b) - both)


def _small(df: DataFrame, *numbers: str) -> DataFrame:
    """``df``, to be sent to every task if its columns ``numbers`` say that it holds few numbers; without any, its rows."""
    held = df.agg(F.sum(sum((F.expr(n) for n in numbers), F.lit(4)))).first()[0] or 0
    return F.broadcast(df) if held <= SMALL else df


def contaminated(docs: DataFrame, benchmark: DataFrame, words: int = 5, similarity: float = 0.8, radius: int = 20) -> DataFrame:
    """_id, _hash (of the text), item_id, similarity: the best window of each contaminated document for each item."""
    items = benchmark.select("item_id", word_array(F.col("text")).alias("w")).filter("size(w) > 0").withColumn("n", F.size("w"))
    sizes = sorted(r[0] for r in items.select(F.least("n", F.lit(words)).alias("k")).distinct().collect())  # at most ``words`` values
    shingled = None
    for k in sizes:
        part = items.filter((F.col("n") == k) if k < words else (F.col("n") >= k)).select("item_id", "n", F.lit(k).alias("k"), shingle_array(F.col("w"), k).alias("shingles"))
        shingled = part if shingled is None else shingled.unionByName(part)
    if shingled is None:
        shingled = items.select("item_id", "n", F.lit(words).alias("k"), F.array().cast("array<bigint>").alias("shingles"))
    entries = barrier(shingled.withColumn("fp", simhash(F.col("shingles"))), "items")
    marks = barrier(entries.select("n", "k", F.explode("shingles").alias("h")).distinct(), "marks")

    keyed = docs.select(F.col("doc_id").alias("_id"), F.xxhash64("text").alias("_hash"), word_array(F.col("text")).alias("w"))
    lengths = sizes or [words]
    # sizes are taken before: a row of a shingle must not carry the words of its text along; and outer, as for a plain
    # explode the optimizer derives a filter on the array, which would split a text anew for each of its words
    if len(lengths) == 1:
        sized = keyed.select("_id", "_hash", F.size("w").alias("size"), F.lit(lengths[0]).alias("k"), shingle_array(F.col("w"), lengths[0]).alias("s"))
        spots = sized.select("_id", "_hash", "size", "k", F.posexplode_outer("s").alias("p", "h"))
    else:  # shingles of several sizes in one pass
        sized = keyed.select("_id", "_hash", F.size("w").alias("size"), F.concat(*[_numbered(shingle_array(F.col("w"), k), k) for k in lengths]).alias("s"))
        spots = sized.select("_id", "_hash", "size", F.explode_outer("s").alias("s")).select("_id", "_hash", "size", "s.*")
    found = spots.join(_small(marks), ["k", "h"]).select("_id", "_hash", "size", "n", "k", "p")

    # a: shingles of the item, b: of the window; need: shared shingles of a match; first and last of so many in a row
    length = F.least("n", "size")
    dense = (
        found.distinct()
        .groupBy("_id", "_hash", "size", "n", "k")
        .agg(F.sort_array(F.collect_list("p")).alias("ps"))
        .withColumns({"a": F.col("n") - F.col("k") + 1, "b": length - F.col("k") + 1})
        .withColumn("need", F.ceil((F.col("a") + F.col("b")) * (similarity / (1 + similarity)) - 1e-9).cast("int"))
        .filter("need >= 1 and size(ps) >= need and need <= b")
    )
    runs = F.transform(F.sequence(F.lit(0), F.size("ps") - F.col("need")), lambda i: F.struct(F.get("ps", i).alias("first"), F.get("ps", i + F.col("need") - 1).alias("last")))
    close = F.filter(runs, lambda r: r["last"] - r["first"] < F.col("b"))
    low = lambda r: F.greatest(r["last"] - F.col("b") + 1, r["first"] - (F.col("b") - F.col("need")), F.lit(0))
    high = lambda r: F.least(r["first"], F.col("size") - F.least("n", "size"))
    starts = F.array_distinct(F.flatten(F.transform(F.filter(close, lambda r: low(r) <= high(r)), lambda r: F.sequence(low(r), high(r)))))
    windows = dense.withColumn("starts", starts).filter("size(starts) > 0")
    targets = barrier(windows.groupBy("_id", "_hash").agg(F.collect_list(F.struct("n", "k", "b", "starts")).alias("at")), "windows")

    same = F.col("_id").eqNullSafe(F.col("t_id")) & (F.col("_hash") == F.col("t_hash"))
    wanted = _small(targets.select(F.col("_id").alias("t_id"), F.col("_hash").alias("t_hash"), "at"), "aggregate(at, 0, (n, t) -> n + 4 + size(t.starts))")
    chosen = keyed.join(wanted, same).dropDuplicates(["_id", "_hash"]).select("_id", "_hash", "w", F.explode("at").alias("t"))
    shingles = F.coalesce(*[F.when(F.col("t.k") == k, shingle_array(F.col("w"), k)) for k in lengths])
    pieces = chosen.select("_id", "_hash", F.col("t.n").alias("n"), F.col("t.b").alias("b"), shingles.alias("all"), F.col("t.starts").alias("starts"))
    pieces = pieces.select("_id", "_hash", "n", F.explode_outer(F.transform("starts", lambda s: F.slice("all", s + 1, F.col("b")))).alias("content")).filter("content is not null")
    pieces = barrier(pieces.distinct(), "pieces")

    # small in bytes and heavy in work: dealt out by number, and each fingerprint is made once
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    contents = barrier(pieces.select("n", "content").distinct().repartition(parts).withColumn("fp", simhash(F.col("content"))), "contents")
    left = contents.select("n", "content", "fp", F.explode(blocks(F.col("fp"))).alias("x")).select("n", "content", "fp", "x.*")
    right = near_blocks(entries.select("n", "item_id", "shingles", "fp"), radius).withColumnRenamed("fp", "fp2")
    near = left.join(right, ["n", "block", "value"]).filter(F.bit_count(F.col("fp").bitwiseXOR(F.col("fp2"))) <= radius)
    verified = (
        near.select("n", "content", "item_id", "shingles").distinct().repartition(parts)
        .withColumn("similarity", weighted_similarity(F.col("content"), F.col("shingles")))
        .filter(F.col("similarity") >= similarity)
        .select("n", "content", "item_id", "similarity")
    )
    return pieces.join(verified, ["n", "content"]).groupBy("_id", "_hash", "item_id").agg(F.max("similarity").alias("similarity"))


def decontaminated(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that no item contaminates, with the same columns."""
    bad = barrier(contaminated(docs, benchmark, **options).select("_id", "_hash").distinct(), "leaks")
    packed = docs.select(F.struct(*docs.columns).alias("doc"))
    return packed.join(_small(bad), F.col("doc.doc_id").eqNullSafe(F.col("_id")) & (F.xxhash64("doc.text") == F.col("_hash")), "left_anti").select("doc.*")


def report(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """doc_id, contaminated, n_items, best_item (smallest id among the best), best_similarity of every row."""
    found = contaminated(docs, benchmark, **options)
    best = F.max(F.struct("similarity", (-F.col("item_id")).alias("item")))
    summed = barrier(found.groupBy("_id", "_hash").agg(F.count("item_id").alias("n_items"), best.alias("best")), "leaks")
    rows = docs.select(F.col("doc_id").alias("id"), F.xxhash64("text").alias("hash")).join(_small(summed), F.col("id").eqNullSafe(F.col("_id")) & (F.col("hash") == F.col("_hash")), "left")
    return rows.select(
        F.col("id").alias("doc_id"),
        F.col("n_items").isNotNull().alias("contaminated"),
        F.coalesce("n_items", F.lit(0).cast("long")).alias("n_items"),
        (-F.col("best.item")).alias("best_item"),
        F.col("best.similarity").alias("best_similarity"),
    )
