"""The unencrypted comparison index: one character per symbol, items joined by one separator, a wavelet matrix per shard."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqvault.alphabet import Alphabet, collect_alphabet
from seqvault.baselines.compressors import packed_block, packed_transform, sealed_item
from seqvault.encode import join_collection, plan_shards
from seqvault.operators.barrier import scratch_path
from seqvault.pieces import check_patterns, cut_items, joined, whole_hits
from seqvault.suffix import suffix_order_kernel

WORD = 64


class WaveletMatrix:
    """Bit planes from the highest bit down, each stably sorted by the planes before; ranks by words of 64 bits."""

    def __init__(self, planes: list[np.ndarray], zeros: list[int], n: int):
        self.planes, self.zeros, self.n = planes, zeros, n
        self.sums = [np.concatenate([[0], np.cumsum(np.bitwise_count(p).astype(np.int64))]) for p in planes]

    @staticmethod
    def build(values: np.ndarray, bits: int) -> WaveletMatrix:
        planes, zeros = [], []
        for b in range(bits - 1, -1, -1):
            bit = (values >> b) & 1
            padded = np.append(bit, np.zeros(-len(bit) % WORD, np.int64)).astype(np.uint8)
            planes.append(np.packbits(padded, bitorder="little").view("<u8"))
            zeros.append(int(len(bit) - bit.sum()))
            values = np.concatenate([values[bit == 0], values[bit == 1]])
        return WaveletMatrix(planes, zeros, len(values))

    def ones(self, level: int, i: np.ndarray) -> np.ndarray:
        """Set bits of a plane before each position."""
        plane, word, rest = self.planes[level], i // WORD, (i % WORD).astype(np.uint64)
        tail = plane[np.minimum(word, len(plane) - 1)] & ((np.uint64(1) << rest) - np.uint64(1))
        return self.sums[level][word] + np.bitwise_count(tail)

    def rank(self, values: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Occurrences of each of ``values`` before its position."""
        low = np.zeros_like(i)
        for level, z in enumerate(self.zeros):
            bit = (values >> (len(self.zeros) - 1 - level) & 1).astype(bool)
            before_low, before = self.ones(level, low), self.ones(level, i)
            low, i = np.where(bit, z + before_low, low - before_low), np.where(bit, z + before, i - before)
        return i - low

    def access_rank(self, i: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Value at each position and how many equal ones stand before it."""
        value, low = np.zeros_like(i), np.zeros_like(i)
        starts = np.zeros_like(i)
        for level, z in enumerate(self.zeros):
            bit = self.ones(level, i + 1) - self.ones(level, i)
            value = value * 2 + bit
            one_i, one_s = self.ones(level, i), self.ones(level, starts)
            i, starts = np.where(bit == 1, z + one_i, i - one_i), np.where(bit == 1, z + one_s, starts - one_s)
        return value, i - starts + low


class PlainShard:
    """Search in one shard: backward search by ranks, positions from sampled rows."""

    def __init__(self, row: dict, letters: list[str]):
        self.alphabet, self.step = Alphabet(tuple(letters), 1), row["step"]
        bits = max(1, (self.alphabet.sigma - 1).bit_length())
        flat = np.frombuffer(row["planes"], "<u8").reshape(bits, -1)
        self.n = row["n"]
        self.tree = WaveletMatrix(list(flat), row["zeros"], self.n)
        self.c = np.array(row["c"])
        self.mark_rows, self.mark_pos = np.frombuffer(row["mark_rows"], "<i8"), np.frombuffer(row["mark_pos"], "<i8")
        self.row_of_mark = self.mark_rows[np.argsort(self.mark_pos)]
        self.items = [np.frombuffer(row[c], "<i8") for c in ("item_no", "item_start", "item_length")]
        self.piece = 0

    def ranges_of(self, patterns: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Rows of each pattern; all take their backward steps side by side."""
        digits = [self.alphabet.digits(p) for p in patterns]
        sizes = np.array([len(d) if (d >= 0).all() else 0 for d in digits], np.int64)
        flat = np.concatenate([np.zeros(0, np.int64), *(d[::-1] for d in digits)])
        begin = np.cumsum([0, *map(len, digits)])[:-1]
        low, high = np.zeros(len(digits), np.int64), np.where(sizes > 0, self.n, 0)
        active, step = np.flatnonzero(sizes > 0), 0
        while len(active):
            s = flat[begin[active] + step]
            got = self.tree.rank(np.concatenate([s, s]), np.concatenate([low[active], high[active]]))
            low[active], high[active] = self.c[s] + got[: len(s)], self.c[s] + got[len(s) :]
            step += 1
            active = active[(low[active] < high[active]) & (sizes[active] > step)]
        return low, np.maximum(low, high)

    def positions(self, rows: np.ndarray) -> np.ndarray:
        out, walk, at, steps = np.zeros(len(rows), np.int64), np.arange(len(rows)), rows, 0
        while len(walk):
            spot = np.minimum(np.searchsorted(self.mark_rows, at), len(self.mark_rows) - 1)
            marked = self.mark_rows[spot] == at
            out[walk[marked]] = self.mark_pos[spot[marked]] + steps
            walk, at = walk[~marked], at[~marked]
            value, rank = self.tree.access_rank(at)
            at, steps = self.c[value] + rank, steps + 1
        return out

    def locate(self, patterns: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Number of the pattern, item_no and offset of every occurrence."""
        low, high = self.ranges_of(patterns)
        size = high - low
        ends = np.cumsum(size)
        rows = np.arange(ends[-1] if len(ends) else 0) + np.repeat(low - (ends - size), size)
        at = self.positions(rows)
        owner = np.searchsorted(self.items[1], at, "right") - 1
        pattern, item, offset = np.repeat(np.arange(len(patterns)), size), self.items[0][owner], at - self.items[1][owner]
        if self.piece:
            mine, item, offset = whole_hits(item, offset, self.piece)
            pattern = pattern[mine]
        return pattern, item, offset

    def extract(self, item: int, start: int, length: int) -> str | None:
        spot = np.flatnonzero(self.items[0] == item)
        if not len(spot):
            return None
        low, high = max(0, start), min(start + length, int(self.items[2][spot[0]]))
        if low >= high:
            return ""
        base = int(self.items[1][spot[0]])
        mark = (base + high - 1) // self.step + 1
        at = min(mark * self.step, self.n)
        row, got = np.array([self.row_of_mark[mark if mark * self.step < self.n else 0]]), []
        while at > base + low:
            value, rank = self.tree.access_rank(row)
            row, at = self.c[value] + rank, at - 1
            got.append(int(value[0]))
        return self.alphabet.text(np.array(got[::-1])[: high - low])


SCHEMA = "shard int, n long, step int, planes binary, zeros array<long>, c array<long>, mark_rows binary, mark_pos binary, item_no binary, item_start binary, item_length binary"


ROW = pa.schema([("shard", pa.int32()), ("n", pa.int64()), ("step", pa.int32()), ("planes", pa.binary()), ("zeros", pa.list_(pa.int64())), ("c", pa.list_(pa.int64())), *[(c, pa.binary()) for c in ("mark_rows", "mark_pos", "item_no", "item_start", "item_length")]])
#: Bytes of a row: planes with a 32-bit count per word group, marks at 8 bytes, items and tables.
BYTES = "length(planes) * 1.0625 + length(mark_rows) + length(item_no) * 3 + size(c) * 8"


def _step(mark_pct: float) -> int:
    return max(1, -(-100 // max(1, int(mark_pct))))


def plain_row(shard: int, numbers: list[int], seqs: list[str], alphabet: Alphabet, step: int) -> tuple[pa.Table, np.ndarray]:
    """A shard's row, and its transform."""
    text, starts, _ = join_collection(seqs, alphabet, None)
    order = suffix_order_kernel(text, alphabet.sigma)
    l = text[order - 1]  # noqa: E741
    tree = WaveletMatrix.build(l, max(1, (alphabet.sigma - 1).bit_length()))
    counts = np.bincount(l, minlength=alphabet.sigma)
    marked = np.flatnonzero(order % step == 0)
    raw = lambda x: np.asarray(x, "<i8").tobytes()
    row = {"shard": shard, "n": len(l), "step": step, "planes": np.concatenate(tree.planes).tobytes(), "zeros": tree.zeros, "c": np.cumsum(counts) - counts, "mark_rows": raw(marked), "mark_pos": raw(order[marked]), "item_no": raw(numbers), "item_start": raw(starts), "item_length": raw([len(s) for s in seqs])}
    return pa.Table.from_pylist([row], schema=ROW), l


def collection_sizes(items: DataFrame, key: bytes, letters: list[str], shard_symbols: int = 1 << 22) -> dict[str, int]:
    """Bytes of a collection by each comparison method: the plain index, the block compressor, the transform and a generic
    compressor, and items compressed, then sealed. All take the same shards, each read and sorted once."""
    alphabet, step = Alphabet(tuple(letters), 1), _step(5.0)
    names = ("planes", "mark_rows", "item_no", "c", "block_compressor", "transform_generic", "compress_encrypt")

    def kernel(table: pa.Table) -> pa.Table:
        numbers, _, seqs = joined(table)
        row, l = plain_row(table["shard"][0].as_py(), numbers, seqs, alphabet, step)  # noqa: E741
        lengths = [*(len(row[c][0].as_py()) for c in names[:4]), len(packed_block(seqs)), len(packed_transform(l)), sum(len(sealed_item(key, n, s.encode())) for n, s in zip(numbers, seqs, strict=True))]
        return pa.table({c: pa.array([n], pa.int64()) for c, n in zip(names, lengths, strict=True)})

    named = items.select(F.col("item_no").cast("long").alias("item_no"), F.lit("").alias("seq_id"), "seq")
    rows = plan_shards(named, 1, shard_symbols).groupBy("shard").applyInArrow(kernel, ", ".join(f"{c} long" for c in names))
    plain = F.sum(F.expr("planes * 1.0625 + mark_rows + item_no * 3 + c * 8")).alias("plain")
    total = rows.agg(plain, *[F.sum(c).alias(c) for c in names[4:]]).first().asDict()
    return {name: int(size or 0) for name, size in total.items()}


class PlainFM:
    """A stored plain index; rows of it are whole shards. ``piece``: letters of the pieces that items were cut into, or 0;
    pieces answer located patterns of up to one letter more than ``overlap``."""

    def __init__(self, spark: SparkSession, path: str, letters: list[str], piece: int = 0, overlap: int = 0):
        self.spark, self.path, self.letters, self.piece, self.overlap = spark, path, letters, piece, overlap

    @staticmethod
    def build(items: DataFrame, mark_pct: float = 5.0, shard_symbols: int = 1 << 22, path: str | None = None, piece: int = 0, overlap: int = 512) -> PlainFM:
        spark, letters = items.sparkSession, collect_alphabet(items)
        target, step = path or scratch_path(spark, "plain"), _step(mark_pct)
        alphabet = Alphabet(tuple(letters), 1)

        def kernel(table: pa.Table) -> pa.Table:
            numbers, _, seqs = joined(table)
            return plain_row(table["shard"][0].as_py(), numbers, seqs, alphabet, step)[0]

        if "start" in items.columns and not piece:
            raise ValueError("items in parts make an index of pieces only")
        named = items.select(F.col("item_no").cast("long").alias("item_no"), F.lit("").alias("seq_id"), "seq", *[c for c in ("start",) if c in items.columns])
        planned = cut_items(named, piece, overlap, shard_symbols) if piece else plan_shards(named, 1, shard_symbols)
        planned.groupBy("shard").applyInArrow(kernel, SCHEMA).write.parquet(target)
        return PlainFM(spark, target, letters, piece, overlap)

    def rows(self) -> DataFrame:
        return self.spark.read.schema(SCHEMA).parquet(self.path)

    def _search(self, requests: DataFrame, run: Callable[[PlainShard, pa.Table], dict], schema: str, most: int = 20_000) -> DataFrame:
        """Every shard with all requests: a task holds one shard and up to ``most`` of them."""
        letters, piece, names = self.letters, self.piece, schema.replace(" long", "").replace(" string", "").split(", ")
        chunks = max(1, -(-requests.count() // most))
        numbers = F.explode(F.sequence(F.lit(0), F.lit(chunks - 1))).alias("chunk")
        shards = self.rows().select("*", numbers)
        asked = requests.withColumn("chunk", F.pmod(F.xxhash64(*requests.columns), F.lit(chunks)).cast("int")).crossJoin(self.rows().select("shard"))
        columns = requests.columns

        def search(left: pa.Table, right: pa.Table) -> pa.Table:
            shard = PlainShard(left.to_pylist()[0], letters)
            shard.piece = piece
            lot = run(shard, right.select(columns))
            return pa.table({n: pa.array(lot[n], pa.string() if n == "text" else pa.int64()) for n in names})

        # few bytes, but work for many tasks: a number of partitions that is named is not lowered by their size
        parts = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        keyed = [df.repartition(parts, "shard", "chunk").groupBy("shard", "chunk") for df in (shards, asked)]
        return keyed[0].cogroup(keyed[1]).applyInArrow(search, schema)

    def locate(self, patterns: DataFrame) -> DataFrame:
        if self.piece:
            check_patterns(patterns, self.overlap)

        def run(shard: PlainShard, table: pa.Table) -> dict:
            number, item, offset = shard.locate(table["pattern"].to_pylist())
            return {"pattern_id": table["pattern_id"].to_numpy()[number], "item_no": item, "offset": offset}

        return self._search(patterns.select("pattern_id", "pattern"), run, "pattern_id long, item_no long, offset long")

    def count(self, patterns: DataFrame) -> DataFrame:
        if self.piece:  # where a hit begins says whether it counts
            found = self.locate(patterns).groupBy("pattern_id").agg(F.count(F.lit(1)).alias("n"))
            return patterns.select("pattern_id").join(found, "pattern_id", "left").select("pattern_id", F.coalesce("n", F.lit(0)).alias("n"))

        def run(shard: PlainShard, table: pa.Table) -> dict:
            low, high = shard.ranges_of(table["pattern"].to_pylist())
            return {"pattern_id": table["pattern_id"].to_numpy(), "n": high - low}

        return self._search(patterns.select("pattern_id", "pattern"), run, "pattern_id long, n long").groupBy("pattern_id").agg(F.sum("n").alias("n"))

    def extract(self, requests: DataFrame) -> DataFrame:
        if self.piece:
            raise ValueError("an index of pieces does not extract")

        def run(shard: PlainShard, table: pa.Table) -> dict:
            asked = table.to_pylist()
            texts = [shard.extract(q["item_no"], q["start"], q["len"]) for q in asked]
            return {"req_id": [q["req_id"] for q, t in zip(asked, texts, strict=True) if t is not None], "text": [t for t in texts if t is not None]}

        return self._search(requests.select("req_id", "item_no", "start", "len"), run, "req_id long, text string")

    def bytes(self) -> int:
        return int(self.rows().agg(F.sum(F.expr(BYTES))).first()[0] or 0)
