"""Search with mismatches and with ambiguity codes, on top of exact locate: seed and verify."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.index import Index

#: The bases that each ambiguity code stands for; N is a letter of its own in data.
CODES = {"A": "A", "C": "C", "G": "G", "T": "T", "U": "T", "R": "AG", "Y": "CT", "S": "CG", "W": "AT", "K": "GT", "M": "AC", "B": "CGT", "D": "AGT", "H": "ACT", "V": "ACG", "N": "ACGTN"}


def locate_inexact(index: Index, patterns: DataFrame, mismatches: int) -> DataFrame:
    """pattern_id, item_no, offset, mismatches of all windows that differ from a pattern in at most so many characters.

    A pattern is cut in ``mismatches + 1`` seeds, one of which must occur unchanged. Seeds are located exactly, the windows
    around them are extracted from the index and compared. Patterns need a character for each seed.
    """
    parts = mismatches + 1
    size = F.length("pattern")
    low = lambda i: F.floor(size * i / parts).cast("int")
    seeds = F.explode(F.array(*[F.struct(low(i).alias("at"), F.expr(f"substring(pattern, int(floor(length(pattern) * {i} / {parts})) + 1, int(floor(length(pattern) * {i + 1} / {parts})) - int(floor(length(pattern) * {i} / {parts})))").alias("seed")) for i in range(parts)])).alias("s")
    cut = patterns.filter(size >= parts).select("pattern_id", "pattern", seeds).select("pattern_id", "pattern", F.col("s.at").alias("at"), F.col("s.seed").alias("seed"))
    # the same seed of several patterns is located once
    named = cut.select("seed").distinct().select(F.xxhash64("seed").alias("pattern_id"), F.col("seed").alias("pattern"))
    hits = index.locate(named).select(F.col("pattern_id").alias("key"), "item_no", "offset")
    starts = cut.withColumn("key", F.xxhash64("seed")).join(hits, "key").select("pattern_id", "pattern", "item_no", (F.col("offset") - F.col("at")).alias("start")).filter("start >= 0").distinct()
    asked = starts.withColumn("req_id", F.xxhash64("pattern_id", "item_no", "start"))
    texts = index.extract(asked.select("req_id", "item_no", "start", F.length("pattern").cast("long").alias("len")))
    window = asked.join(texts, "req_id").filter(F.length("text") == F.length("pattern"))
    differ = F.size(F.filter(F.zip_with(F.split("text", ""), F.split("pattern", ""), lambda a, b: a != b), lambda x: x))
    return window.select("pattern_id", "item_no", F.col("start").alias("offset"), differ.cast("long").alias("mismatches")).filter(F.col("mismatches") <= mismatches)


def locate_codes(index: Index, patterns: DataFrame, most: int = 4_096) -> DataFrame:
    """pattern_id, item_no, offset of patterns in which ambiguity codes stand for their bases.

    Codes are expanded to concrete patterns; a pattern with more than ``most`` of them is refused.
    """
    choices = F.transform(F.split("pattern", ""), lambda c: F.split(F.coalesce(F.element_at(F.create_map(*[F.lit(x) for kv in CODES.items() for x in kv]), c), c), ""))
    number = F.aggregate(choices, F.lit(1).cast("long"), lambda n, x: n * F.size(x))
    checked = patterns.withColumn("_n", F.when(number > most, F.raise_error(F.lit(f"a pattern stands for over {most} concrete ones"))).otherwise(number)).filter("_n > 0")
    whole = F.aggregate(choices, F.array(F.lit("")), lambda done, x: F.flatten(F.transform(done, lambda d: F.transform(x, lambda c: F.concat(d, c)))))
    concrete = checked.select(F.col("pattern_id").alias("id"), F.explode(whole).alias("pattern")).withColumn("pattern_id", F.xxhash64("pattern"))
    hits = index.locate(concrete.select("pattern_id", "pattern").distinct())
    return concrete.select("id", "pattern_id").join(hits, "pattern_id").select(F.col("id").alias("pattern_id"), "item_no", "offset")
