"""Collections on the given tables: (item_no, seq) views, mutated copies of a reference, and sampled patterns.

All arithmetic is on BIGINT and has the same form in DuckDB; each view comes with its SQL.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.dataset as ds
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seqvault.operators.barrier import barrier, scratch_path
from seqvault.operators.prefix import place_by_range, row_numbers, running_sum
from seqvault.operators.shared_fs import resolve
from seqvault.sources.tables import table

LETTERS = "abcdefghijklmnopqrstuvwxyz"
#: Prime and multipliers of the mutation arithmetic.
PRIME, MIX_POS, MIX_COPY, MIX_TURN, MIX_LAST = 2_147_483_647, 1_103_515_245, 1_299_709, 7_919, 48_271
IUPAC = "ACGTURYSWKMBDHVN"
EVENT_LETTERS = {"view": "V", "click": "C", "purchase": "P", "signup": "S", "error": "E"}


def cycle(onto: str) -> str:
    return "".join(onto[i % len(onto)] for i in range(len(LETTERS)))


def _mapped(text: Column, onto: str, rest: str) -> Column:
    plain = F.regexp_replace(F.lower(text), r"[ \n\r\t]", "")
    return F.translate(F.regexp_replace(plain, "[^a-z]", rest), LETTERS, cycle(onto))


def nuc_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """item_no, seq_id, lang, source, seq: documents as strings over A, C, G, T and N."""
    docs = table(spark, sf_dir, "documents").filter("text is not null")
    return docs.select(F.col("doc_id").alias("item_no"), F.concat(F.lit("doc"), "doc_id").alias("seq_id"), "lang", "source", _mapped(F.col("text"), "ACGT", "N").alias("seq"))


NUC_SQL = f"""nuc AS (
  SELECT doc_id AS item_no, lang, source,
    translate(regexp_replace(regexp_replace(lower(text), '[ \\n\\r\\t]', '', 'g'), '[^a-z]', 'N', 'g'), '{LETTERS}', '{cycle("ACGT")}') AS seq
  FROM documents WHERE text IS NOT NULL
)"""


def iupac_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents over the sixteen nucleotide codes and the gap."""
    docs = table(spark, sf_dir, "documents").filter("text is not null")
    return docs.select(F.col("doc_id").alias("item_no"), _mapped(F.col("text"), IUPAC, "-").alias("seq"))


def event_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """item_no (user), seq: a user's event types in time order, one letter each."""
    letter = F.coalesce(*[F.when(F.col("event_type") == k, F.lit(v)) for k, v in EVENT_LETTERS.items()], F.lit("X"))
    rows = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", letter.alias("x"))
    ordered = F.transform(F.sort_array(F.collect_list(F.struct("ts", "event_id", "x"))), lambda s: s["x"])
    return rows.groupBy(F.col("user_id").alias("item_no")).agg(F.array_join(ordered, "").alias("seq"))


EVENT_SQL = """paths AS (
  SELECT user_id AS item_no, string_agg(CASE event_type WHEN 'view' THEN 'V' WHEN 'click' THEN 'C' WHEN 'purchase' THEN 'P' WHEN 'signup' THEN 'S' WHEN 'error' THEN 'E' ELSE 'X' END, '' ORDER BY ts, event_id) AS seq
  FROM events GROUP BY user_id
)"""


def raw_view(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    """item_no, seq of a table's texts as they are."""
    number, text = {"documents": ("doc_id", "text"), "benchmark": ("item_id", "text"), "pages": ("page_id", "html")}.get(name, ("conv_id * 1000 + turn", "text"))
    return table(spark, sf_dir, name).select(F.expr(number).cast("long").alias("item_no"), F.col(text).alias("seq")).filter("seq is not null")


def dim_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part names: many tiny items."""
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("item_no"), F.col("p_name").alias("seq"))


def reference(spark: SparkSession, sf_dir: str, source: str, length: int | None = None) -> DataFrame:
    """seq: the nucleotide strings of a source, joined in order of their numbers and cut to a length."""
    rows = nuc_view(spark, sf_dir).filter(F.col("source") == source)
    joined = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("item_no", "seq"))), lambda s: s["seq"]), "")
    whole = rows.agg(joined.alias("seq"))
    return whole.select(F.substring("seq", 1, length).alias("seq")) if length else whole


#: Letters of a reference that are mutated at once, and how far before a letter a deletion of it may begin.
STRETCH, REACH = 1 << 18, 16
#: Draws made at once: their arrays stay in a core's cache.
DRAWN = 1 << 14


def mutated(base: np.ndarray, v: int, seed: int, stretch: int = STRETCH) -> bytes:
    """Copy ``v`` of a reference: substitutions at 0.1 %, insertions and deletions of 1 to 16 letters at 0.013 %.

    Made stretch by stretch, so that arrays over the whole reference are never held.
    """
    return b"".join(_mutated_stretch(base, low, min(low + stretch, len(base)), v, seed) for low in range(0, len(base), stretch))


def _draws(low: int, high: int, v: int, seed: int) -> np.ndarray:
    """The number below PRIME, a Mersenne prime, that decides what becomes of each letter ``low`` to ``high`` in copy ``v``."""
    h = np.arange(low + 1, high + 1, dtype=np.int64)
    i = h - 1
    h *= MIX_POS
    h += (v + 1) * MIX_COPY + seed
    _fold(h)
    h *= h
    _fold(h)
    h += v * MIX_TURN
    h *= MIX_LAST
    _fold(h)
    h *= h
    _fold(h)
    h += i
    _fold(h)
    h -= PRIME * (h >= PRIME)
    return h


def _fold(h: np.ndarray) -> None:
    """Numbers below 2^63 to equal ones modulo PRIME of at most PRIME + 1 or so; remainders proper take a division."""
    for _ in range(2):
        over = h >> 31
        h &= PRIME
        h += over


def _mutated_stretch(base: np.ndarray, low: int, high: int, v: int, seed: int) -> bytes:
    """Letters ``low`` to ``high`` of the copy; the letters before are looked at for deletions that go on."""
    before = max(0, low - REACH)
    return _mutated_letters(base[before:high], before, low, v, seed)


def _edits(before: int, high: int, v: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of letters ``before`` to ``high``: places, from ``before`` on, of those that a substitution or an indel falls on; their
    draws; which are indels. All else stays."""
    spots, draws = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for low in range(before, high, DRAWN):
        h = _draws(low, min(low + DRAWN, high), v, seed).astype(np.uint32)
        some = np.flatnonzero(h - h // np.uint32(100_000) * np.uint32(100_000) <= 112)
        spots.append(some + (low - before))
        draws.append(h[some].astype(np.int64))
    h = np.concatenate(draws)
    return np.concatenate(spots), h, h % 100_000 >= 100


def _kept(n: int, own: int, spots: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Which of ``n`` letters stay: those from ``own`` on that no deletion covers."""
    here = np.ones(n, bool)
    here[:own] = False
    for a, b in zip(spots.tolist(), size.tolist(), strict=True):
        here[a : a + b] = False
    return here


def _mutated_letters(base: np.ndarray, before: int, low: int, v: int, seed: int) -> bytes:
    """As :func:`_mutated_stretch`, of letters that begin at ``before``, with the result from ``low`` on."""
    spots, h, indel = _edits(before, before + len(base), v, seed)
    size, erase = 1 + h // 300_000 % 16, h // 5_000_000 % 2 == 1
    here = _kept(len(base), low - before, spots[indel & erase], size[indel & erase])
    out = base.copy()
    turned = np.frombuffer(b"ACGTACGT", np.uint8)
    swapped = ~indel & (base[spots] != ord("N"))
    at = spots[swapped]
    out[at] = turned[np.minimum(np.searchsorted(turned[:4], base[at]), 3) + h[swapped] // 100_000 % 3 + 1]
    grown = indel & ~erase & here[spots]
    pieces, at = [], 0
    for g, n in zip(spots[grown].tolist(), size[grown].tolist(), strict=True):
        pieces += [out[at : g + 1][here[at : g + 1]].tobytes(), b"ACGTGTCAACGTGTCA"[:n]]
        at = g + 1
    return b"".join([*pieces, out[at:][here[at:]].tobytes()])


def _mutated_size(n: int, before: int, low: int, v: int, seed: int) -> int:
    """Letters that :func:`_mutated_letters` gives of ``n``."""
    spots, h, indel = _edits(before, before + n, v, seed)
    size, erase = 1 + h // 300_000 % 16, h // 5_000_000 % 2 == 1
    here = _kept(n, low - before, spots[indel & erase], size[indel & erase])
    return int(here.sum() + size[indel & ~erase & here[spots]].sum())


def reference_stretches(spark: SparkSession, sf_dir: str, source: str, size: int) -> DataFrame:
    """stretch, seq: the letters of :func:`reference` in rows of ``size``, each with the REACH letters before it; at least one.

    Where a document begins comes from a running sum, so nothing holds the whole reference.
    """
    rows = nuc_view(spark, sf_dir).filter(F.col("source") == source).select("item_no", "seq", F.length("seq").cast("long").alias("n"), F.lit(0).alias("all"))
    summed = running_sum(place_by_range(rows, ["all", "item_no"], "reference"), ["all"], ["item_no"], "n", "end").filter("n > 0")
    begin = F.col("end") - F.col("n")
    numbers = F.sequence(F.floor(begin / size), F.floor((F.col("end") - 1 + REACH) / size))
    at = summed.select("seq", "end", begin.alias("begin"), F.explode(numbers).alias("stretch"))
    low, high = F.greatest("begin", F.col("stretch") * size - REACH), F.least("end", (F.col("stretch") + 1) * size)
    cut = at.withColumns({"low": low, "high": high}).filter("low < high").select("stretch", "low", F.substring(F.col("seq"), (F.col("low") - F.col("begin") + 1).cast("int"), (F.col("high") - F.col("low")).cast("int")).alias("seq"))
    first = spark.range(1).select(F.col("id").alias("stretch"), F.lit(-1).cast("long").alias("low"), F.lit("").alias("seq"))
    joined = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("low", "seq"))), lambda s: s["seq"]), "")
    whole = cut.unionByName(first).groupBy("stretch").agg(joined.alias("seq"), F.max(F.col("low") + F.length("seq")).alias("end"))
    # a row past the last letter holds only letters that are looked back at
    return whole.filter((F.col("stretch") == 0) | (F.col("end") > F.col("stretch") * size)).select("stretch", "seq")


def variant_stretches(spark: SparkSession, sf_dir: str, source: str, copies: int, seed: int, size: int = 1 << 16) -> DataFrame:
    """item_no, start, seq: the copies of :func:`variant_collection` in parts, each made of ``size`` letters of the reference.

    ``start`` is where a part begins in its copy. The parts are made twice, first for their lengths, so that no task and no
    row holds a copy or the reference.
    """
    stretches = barrier(reference_stretches(spark, sf_dir, source, size), "stretches")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def lengths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for stretch, n in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                low = stretch * size
                got = [_mutated_size(n, max(0, low - REACH), low, v, seed) for v in range(copies)]
                yield pa.record_batch([pa.array([stretch] * copies, pa.int64()), pa.array(range(copies), pa.int64()), pa.array(got, pa.int64())], names=["stretch", "item_no", "n"])

    sized = stretches.select("stretch", F.length("seq").cast("long").alias("n")).repartition(parts, "stretch").mapInArrow(lengths, "stretch long, item_no long, n long")
    before = Window.partitionBy("item_no").orderBy("stretch").rowsBetween(Window.unboundedPreceding, -1)  # a number a stretch
    started = sized.withColumn("start", F.coalesce(F.sum("n").over(before), F.lit(0).cast("long")))
    starts = started.groupBy("stretch").agg(F.transform(F.sort_array(F.collect_list(F.struct("item_no", "start"))), lambda s: s["start"]).alias("starts"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for stretch, seq, begins in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), strict=True):
                low, base = stretch * size, np.frombuffer(seq.as_buffer(), np.uint8)
                for v, begin in enumerate(begins):
                    made = _mutated_letters(base, max(0, low - REACH), low, v, seed)
                    if made or not stretch:
                        yield pa.record_batch([pa.array([v], pa.int64()), pa.array([begin], pa.int64()), pa.array([made], pa.binary()).cast(pa.string())], names=["item_no", "start", "seq"])

    joined = stretches.join(barrier(starts, "starts"), "stretch").select("stretch", "seq", "starts")
    return joined.repartition(parts, "stretch").mapInArrow(run, "item_no long, start long, seq string")


def variant_collection(ref: DataFrame, copies: int, seed: int) -> DataFrame:
    """item_no, seq: mutated copies of a one-row reference of nucleotides, each made in one go by a task.

    The reference is written once and read by the tasks, so it passes no join and no JVM beside the copies.
    """
    spark = ref.sparkSession
    path = scratch_path(spark, "reference")
    ref.select("seq").write.parquet(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base = None
        for batch in batches:
            for number in batch.column(0).to_pylist():
                if base is None:
                    base = _one_text(path)
                yield pa.record_batch([pa.array([number], pa.int64()), pa.array([mutated(base, number, seed)], pa.binary()).cast(pa.string())], names=["item_no", "seq"])

    numbers = spark.range(0, copies, 1, min(copies, 64)).select(F.col("id").alias("item_no"))
    return numbers.mapInArrow(run, "item_no long, seq string")


def _one_text(path: str) -> np.ndarray:
    """Bytes of the text of a one-row table ``seq`` in the shared folder; none if it is null."""
    store, root = resolve(path)
    column = ds.dataset(root, filesystem=store, format="parquet").to_table(columns=["seq"]).column(0)
    return np.frombuffer(column[0].as_buffer() or b"", np.uint8)


def variant_sql(source: str, copies: int, seed: int, length: int | None = None) -> str:
    """The same collection for DuckDB, as CTEs after ``nuc``: ``variants``."""
    cut = f"substr(string_agg(seq, '' ORDER BY item_no), 1, {length})" if length else "string_agg(seq, '' ORDER BY item_no)"
    return f"""ref AS (SELECT {cut} AS seq FROM nuc WHERE source = '{source}'),
sites AS (SELECT i - 1 AS i, letters[i] AS base FROM (SELECT string_split(seq, '') AS letters FROM ref), LATERAL (SELECT unnest(range(1, len(letters) + 1)) AS i)),
copies AS (SELECT i, base, v FROM sites, (SELECT unnest(range(0, {copies})) AS v)),
h1 AS (SELECT i, base, v, ((i + 1) * {MIX_POS} + (v + 1) * {MIX_COPY} + {seed}) % {PRIME} AS h FROM copies),
h2 AS (SELECT i, base, v, (((h * h) % {PRIME} + {MIX_TURN} * v) * {MIX_LAST}) % {PRIME} AS h FROM h1),
h3 AS (SELECT i, base, v, ((h * h) % {PRIME} + i) % {PRIME} AS h FROM h2),
h4 AS (SELECT *, h % 100000 AS r, 1 + (h // 300000) % 16 AS size, (h // 5000000) % 2 = 1 AS erase FROM h3),
h5 AS (SELECT *, max(CASE WHEN r BETWEEN 100 AND 112 AND erase THEN i + size ELSE 0 END) OVER (PARTITION BY v ORDER BY i ROWS BETWEEN 16 PRECEDING AND CURRENT ROW) AS gone FROM h4),
pieces AS (SELECT v, i, CASE WHEN r BETWEEN 100 AND 112 AND NOT erase THEN base || substr('ACGTGTCAACGTGTCA', 1, CAST(size AS INT))
  WHEN r < 100 AND base <> 'N' THEN substr('ACGTACGT', CAST(strpos('ACGT', base) + (h // 100000) % 3 + 1 AS INT), 1) ELSE base END AS piece FROM h5 WHERE i >= gone),
variants AS (SELECT v AS item_no, string_agg(piece, '' ORDER BY i) AS seq FROM pieces GROUP BY v)"""


def sample_patterns(items: DataFrame, lengths: list[int], n: int, seed: int = 7) -> DataFrame:
    """pattern_id, pattern, src_item, src_off: ``n`` windows of each length fully inside items, spread by arithmetic.

    A pattern's item is the one whose running rank its number hits; the collection needs items as long as the pattern.
    """
    sized = items.select("item_no", "seq", F.length("seq").cast("long").alias("size"))
    wanted = items.sparkSession.createDataFrame([(int(x),) for x in lengths], "len long")
    rows = sized.join(F.broadcast(wanted), F.col("size") >= F.col("len"))
    mixed = ((F.col("item_no") + 1) * MIX_POS + F.col("len") * MIX_COPY + seed) % F.lit(PRIME).cast("long")
    rows = rows.withColumn("h", (mixed * mixed) % F.lit(PRIME).cast("long"))
    pick = Window.partitionBy("len").orderBy("h", "item_no")
    chosen = rows.withColumn("k", F.row_number().over(pick)).filter(F.col("k") <= n)
    off = F.col("h") % (F.col("size") - F.col("len") + 1)
    number = F.col("len") * 1_000_000 + F.col("k")
    return chosen.select(number.alias("pattern_id"), F.substring("seq", off.cast("int") + 1, F.col("len").cast("int")).alias("pattern"), F.col("item_no").alias("src_item"), off.alias("src_off"))


def sample_windows(items: DataFrame, lengths: list[int], n: int, seed: int = 11) -> DataFrame:
    """pattern_id, pattern: ``n`` windows of each length, also where there are fewer items: item and offset are drawn anew
    for each, by arithmetic, among the items that are long enough. Items may come in parts (item_no, start, seq)."""
    spark, cut_up = items.sparkSession, "start" in items.columns
    wanted = F.explode(F.array(*[F.lit(int(x)).cast("long") for x in lengths])).alias("len")
    sized = items.select("item_no", F.length("seq").cast("long").alias("size"))
    if cut_up:
        sized = sized.groupBy("item_no").agg(F.sum("size").alias("size"))
    fitting = sized.select("item_no", "size", wanted).filter("size >= len")
    order = ["len", "item_no"]
    ranked = barrier(row_numbers(place_by_range(fitting, order, "fitting"), order, "at"), "ranked")
    bases = ranked.groupBy("len").agg(F.min("at").alias("base"), F.count(F.lit(1)).alias("items"))
    draw = spark.range(n).select(F.col("id").alias("j"), wanted).join(F.broadcast(bases), "len")  # a row per length
    mixed = ((F.col("j") + 1) * MIX_POS + F.col("len") * MIX_COPY + seed) % F.lit(PRIME).cast("long")
    draw = draw.withColumn("h", mixed * mixed % F.lit(PRIME).cast("long")).withColumn("at", F.col("base") + F.floor(F.col("h") / 1_000).cast("long") % F.col("items"))
    chosen = draw.join(ranked.select("at", "item_no", "size"), "at").withColumn("g", (F.col("h") * MIX_LAST + F.col("j")) % F.lit(PRIME).cast("long"))
    chosen = chosen.select((F.col("len") * 1_000_000 + F.col("j")).alias("pattern_id"), "item_no", "len", (F.col("g") % (F.col("size") - F.col("len") + 1)).cast("int").alias("off"))
    cuts = chosen.groupBy("item_no").agg(F.collect_list(F.struct("pattern_id", "len", "off")).alias("cuts"))  # n x lengths in all
    if cut_up:
        return _cut_parts(items, cuts)
    cut = items.select("item_no", "seq").join(F.broadcast(cuts), "item_no")
    taken = F.transform("cuts", lambda c: F.struct(c["pattern_id"].alias("pattern_id"), F.substring(F.col("seq"), c["off"] + 1, c["len"].cast("int")).alias("pattern")))
    return cut.select(F.explode_outer(taken).alias("c")).select("c.*")


def _cut_parts(items: DataFrame, cuts: DataFrame) -> DataFrame:
    """pattern_id, pattern: the windows ``cuts`` (item_no, cuts) of items in parts, put together of what each part holds."""
    rows = items.select("item_no", "start", "seq", (F.col("start") + F.length("seq")).alias("end")).join(F.broadcast(cuts), "item_no")
    mine = F.filter("cuts", lambda c: (c["off"] < F.col("end")) & (c["off"] + c["len"] > F.col("start")))
    low, high = (lambda c: F.greatest(c["off"].cast("long"), F.col("start"))), (lambda c: F.least(c["off"] + c["len"], F.col("end")))
    text = lambda c: F.substring(F.col("seq"), (low(c) - F.col("start") + 1).cast("int"), (high(c) - low(c)).cast("int"))
    held = rows.select(F.explode(F.transform(mine, lambda c: F.struct(c["pattern_id"].alias("pattern_id"), low(c).alias("low"), text(c).alias("text")))).alias("c")).select("c.*")
    joined = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("low", "text"))), lambda s: s["text"]), "")
    return held.groupBy("pattern_id").agg(joined.alias("pattern"))


def patterns_sql(items: str, lengths: list[int], n: int, seed: int = 7) -> str:
    """The same sample for DuckDB: a CTE ``pats`` over the CTE named ``items``."""
    lens = ", ".join(f"({x})" for x in lengths)
    return f"""pats AS (
  SELECT len * 1000000 + k AS pattern_id, substr(seq, CAST(h % (size - len + 1) AS INT) + 1, CAST(len AS INT)) AS pattern, item_no AS src_item, h % (size - len + 1) AS src_off
  FROM (SELECT *, row_number() OVER (PARTITION BY len ORDER BY h, item_no) AS k FROM (
    SELECT item_no, seq, len, length(seq) AS size, ((((item_no + 1) * {MIX_POS} + len * {MIX_COPY} + {seed}) % {PRIME}) * (((item_no + 1) * {MIX_POS} + len * {MIX_COPY} + {seed}) % {PRIME})) % {PRIME} AS h
    FROM {items}, (VALUES {lens}) AS w(len) WHERE length(seq) >= len)) WHERE k <= {n}
)"""
