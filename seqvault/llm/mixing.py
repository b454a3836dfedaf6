"""Mixing sources to target weights by entropy balancing.

Document rates are those closest in relative entropy to one copy each that meet every source's token target and never
exceed ``cap``: r = min(cap, exp(lambda_s * size / mean size)). The dual is convex and falls apart into one variable per
source; Newton steps, kept inside a bracket, are taken for all sources at once over the (source, size) counts, one
aggregate per step. Rates become whole copies by systematic rounding along the sizes of a source: with running sums of
the fractional parts, a document gains a copy where the sum crosses a whole number. The offset of the rounding is the
best of ``offsets`` equally spaced ones, by the words taken. Sums are whole numbers, so reruns agree.

Null text: size 0. Null source: a source of its own, last. Rows with equal ids are separate documents. A source without
words takes none. Empty table: empty result. Other columns are kept by :func:`mixed_documents` and not read otherwise.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqvault.llm.keys import ROW, unpacked, with_row_key
from seqvault.operators.barrier import barrier
from seqvault.operators.prefix import PART, place_by_range, running_sum

WORD = r"[^\x20\x09-\x0D]+"
#: Unit of the fractional parts of rates.
UNIT = 1_000_000


def word_size(text: Column) -> Column:
    """Number of words of a text; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_key(source: Column) -> Column:
    """A key without nulls whose order is by code point with null last."""
    return F.when(source.isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), source))


def source_targets(sources: DataFrame, weights: list[float], share: float, cap: float) -> DataFrame:
    """Add ``target`` to (skey, source_size): weighted shares of ``share`` x all sizes, cut at ``cap`` x a source's size.

    One row per source takes part. Each round reshares the excess of the sources cut so far by weight.
    """
    turn = (F.row_number().over(Window.orderBy("skey")) - 1) % len(weights)
    table = F.array(*map(F.lit, weights))
    rows = barrier(sources.withColumn("weight", F.get(table, turn)).withColumn("limit", F.lit(cap) * F.col("source_size")), "weights")
    total = share * float(rows.agg(F.sum("source_size")).first()[0] or 0)
    level, cut = 0.0, -1
    while True:
        full = F.lit(level) * F.col("weight") >= F.col("limit")
        n, spent, weight = rows.agg(F.count_if(full), F.sum(F.when(full, F.col("limit"))), F.sum(F.when(~full, F.col("weight")))).first()
        if n == cut or not weight:
            break
        cut, level = n, (total - (spent or 0.0)) / weight
    return rows.withColumn("target", F.least(F.lit(level) * F.col("weight"), F.col("limit"))).drop("weight", "limit")


def _rate(lam: Column, c: Column, cap: float) -> Column:
    return F.when(lam.isNull(), F.lit(cap)).otherwise(F.least(F.lit(cap), F.exp(F.least(lam * c, F.lit(50.0)))))


def solve_tilts(counts: DataFrame, sources: DataFrame, cap: float, rounds: int = 100, close: float = 1e-7) -> DataFrame:
    """``lam`` of each source: null where the target is the cap itself, else the root of the dual's gradient.

    Raises where ``rounds`` steps do not suffice; a few are usual, and halving the bracket alone would need about 60.
    """
    size, n, lam = F.col("size").cast("double"), F.col("n"), F.col("lam")
    state = sources.withColumn("lam", F.when(F.col("target") >= F.col("source_size") * cap * (1 - 1e-12), F.lit(None)).otherwise(F.lit(0.0)))
    state = barrier(state.withColumns({"lo": F.lit(-1e6), "hi": F.lit(1e6)}), "tilts")
    c = size / F.col("mean")
    for _ in range(rounds):
        r = _rate(lam, c, cap)
        free = F.when(r < cap, r * n * size * c).otherwise(0.0)
        sums = counts.join(state.select("skey", "lam", "mean"), "skey").groupBy("skey").agg(F.sum(r * n * size).alias("got"), F.sum(free).alias("slope"))
        gap = F.col("got") - F.col("target")
        low, high = F.when(gap < 0, lam).otherwise(F.col("lo")), F.when(gap > 0, lam).otherwise(F.col("hi"))
        newton = lam - gap / F.when(F.col("slope") > 0, F.col("slope"))
        middle = F.when((F.col("lo1") > -1e6) & (F.col("hi1") < 1e6), (F.col("lo1") + F.col("hi1")) / 2).when(F.col("gap") < 0, F.greatest(lam * 2, F.lit(1.0))).otherwise(F.least(lam * 2, F.lit(-1.0)))
        inside = (F.col("newton") > F.col("lo1")) & (F.col("newton") < F.col("hi1"))
        stepped = state.join(sums, "skey", "left").withColumns({"gap": gap, "lo1": low, "hi1": high, "newton": newton})
        settled = lam.isNull() | F.col("gap").isNull() | (F.abs("gap") <= close * F.greatest(F.col("target"), F.lit(1.0)))
        stepped = stepped.withColumn("open", (~settled).cast("int"))
        state = barrier(
            stepped.select("skey", "source_size", "mean", "target", F.when(F.col("open") == 0, lam).when(inside, F.col("newton")).otherwise(middle).alias("lam"), F.col("lo1").alias("lo"), F.col("hi1").alias("hi"), "open"),
            "tilts",
        )
        if not state.agg(F.max("open")).first()[0]:
            break
        state = state.drop("open")
    else:
        raise RuntimeError(f"the tilts did not settle in {rounds} rounds")
    # sums of doubles depend on their order in the last digits; rounded, reruns give the same rates
    return state.select("skey", "source_size", "target", "mean", F.round("lam", 9).alias("lam"))


def mix(docs: DataFrame, weights: list[float] = (5.0, 2.0, 1.0), share: float = 1.5, cap: float = 2.0, offsets: int = 32, row: str | None = None) -> DataFrame:
    """doc_id, size, source_size, target, taken, copies, rate of every row of ``docs``; ``row``: a key to carry along."""
    key = [row] if row else []
    sized = barrier(docs.select("doc_id", *key, source_key(F.col("source")).alias("skey"), word_size(F.col("text")).alias("size")), "sizes")
    counts = barrier(sized.groupBy("skey", "size").agg(F.count(F.lit(1)).alias("n")), "counts")
    sources = counts.groupBy("skey").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"), F.sum(F.when(F.col("size") > 0, F.col("n"))).alias("n"))
    mean = F.when(F.col("source_size") > 0, F.col("source_size") / F.col("n")).otherwise(1.0)
    targets = source_targets(sources.withColumn("mean", mean).drop("n"), list(weights), share, cap)
    tilts = solve_tilts(counts, targets, cap)

    rate = F.when(F.col("size") == 0, F.lit(0.0)).when(F.col("target") <= 0, F.lit(0.0)).otherwise(_rate(F.col("lam"), F.col("size") / F.col("mean"), cap))
    micro = F.floor(F.col("rate") * UNIT + 0.5).cast("long")
    # No copy of sizes past the sort key is needed: rows of one (source, size) are told apart by a hash of their id.
    rows = sized.join(F.broadcast(tilts) if _few(tilts) else tilts, "skey").withColumn("rate", rate)
    rows = rows.withColumns({"_base": F.floor(micro / UNIT).cast("long"), "_part_of": micro % UNIT, "_spread": F.xxhash64("doc_id")})
    order = ["size", "_spread", "doc_id", *key]
    placed = place_by_range(rows, ["skey", *order], "mixed")
    summed = running_sum(placed, ["skey"], order, "_part_of", "_sum").drop(PART)

    def copies(j: Column | int) -> Column:
        shift = j * (UNIT // offsets)
        return F.col("_base") + F.floor((F.col("_sum") + shift) / UNIT) - F.floor((F.col("_sum") - F.col("_part_of") + shift) / UNIT)

    trial = summed.groupBy("skey").agg(F.first("target").alias("_goal"), *[F.sum(copies(j) * F.col("size")).alias(f"_t{j}") for j in range(offsets)])
    best = trial.select("skey", F.array_min(F.array(*[F.struct(F.abs(F.col(f"_t{j}") - F.col("_goal")).alias("off"), F.lit(j).alias("j")) for j in range(offsets)]))["j"].alias("_j"))
    chosen = summed.join(F.broadcast(best) if _few(tilts) else best, "skey").withColumn("copies", copies(F.col("_j")).cast("long"))
    return chosen.select("doc_id", *key, "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"), "copies", "rate")


def _few(rows: DataFrame, most: int = 100_000) -> bool:
    """Whether a table of short rows is small enough to be sent to every task."""
    return rows.limit(most + 1).count() <= most


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The rows of ``docs``, each as often as the mix takes it, with the same columns."""
    keyed = with_row_key(docs)
    taken = barrier(mix(keyed, row=ROW, **options).filter("copies > 0").select(ROW, F.col("copies").cast("int").alias("_copies")), "taken")
    joined = keyed.join(F.broadcast(taken) if _few(taken, 200_000) else taken, ROW)
    return unpacked(joined.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies")))))
