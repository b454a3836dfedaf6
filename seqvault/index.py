"""Sealed indexes: build from a collection, store, open, search, extract, restore, append and compact.

Every build or append writes a folder of its own, under a new name and with a new salt, then a row for each of its shards,
then the next version of the metadata, which names the folders that count. A driver that is lost before that leaves a
folder that nobody reads; its shards share no keystream with those of a later attempt, as the salt differs.
"""

from __future__ import annotations

import gc
import json
import math
import secrets
import time
import uuid
import zlib
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass, replace
from functools import lru_cache
from urllib.parse import unquote

import numpy as np
import pyarrow as pa
import pyarrow.dataset as ds
from pyarrow import fs
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from seqvault import bwt as transform
from seqvault import planner
from seqvault.alphabet import MOST_IDS, Alphabet, collect_alphabet, scramble_key
from seqvault.blocks import PER_SUPER, Coding, encode_block, encode_blocks
from seqvault.cipher import block_key
from seqvault.encode import join_collection, joined_rows, plan_shards
from seqvault.fm import ShardFM
from seqvault.operators.barrier import barrier, scratch_path
from seqvault.operators.prefix import place_by_range, row_numbers
from seqvault.operators.shared_fs import resolve
from seqvault.pieces import check_patterns, cut_items, joined
from seqvault.planner import displaced
from seqvault.symbols import c_table, mark_rows, occ_superblocks

#: Columns that all index tables share; each table gives them its own names.
ROW = "kind string, shard int, no long, a long, b long, c long, ints array<int>, longs array<long>, payload binary, text string"
TABLES = {
    "items": {"no": "item_no", "text": "seq_id", "a": "length", "b": "start_sym", "c": "n_sym"},
    "c_table": {"no": "sym", "a": "c_before"},
    "superblocks": {"no": "super_no", "ints": "syms", "longs": "counts"},
    "blocks": {"no": "block_no", "a": "n", "b": "comp_len", "c": "bits", "ints": "alpha", "longs": "counts", "payload": "payload"},
    "marks": {"no": "row", "a": "pos"},
}


@dataclass(frozen=True)
class IndexParams:
    """``mark_pct``: share of text positions that are marked, in percent. ``shard_symbols``: about how many symbols a shard
    holds; one task keeps a shard in memory (about 60 bytes a symbol), but with strategy ``distributed`` or ``doubling``.
    ``piece``: letters of the pieces that long items are cut into (0: not cut), which answer patterns of up to one letter more
    than ``overlap``; an index of pieces is searched, and recut, but not restored, extracted from or grown."""

    k: int = 4
    bs: int = 4096
    mark_pct: float = 5.0
    shard_symbols: int = 1 << 22
    scramble: bool = True
    encrypt: bool = True
    nonce_mode: str = "scoped"
    cipher_mode: str = "add"
    rounds: int = 20
    pad_wildcards: bool = True
    strategy: str = "kernel"
    checksum: bool = False
    piece: int = 0
    overlap: int = 512

    @property
    def mark_step(self) -> int:
        return max(1, math.ceil(100 / self.mark_pct))


def _rows(kind: str, shard: int, n: int, **columns) -> pa.Table:
    names = ["no", "a", "b", "c", "ints", "longs", "payload", "text"]
    types = [pa.int64()] * 4 + [pa.list_(pa.int32()), pa.list_(pa.int64()), pa.binary(), pa.string()]
    filled = [pa.array(columns[c], t) if c in columns else pa.nulls(n, t) for c, t in zip(names, types, strict=True)]
    return pa.table([pa.array([kind] * n, pa.string()), pa.array([shard] * n, pa.int32()), *filled], names=["kind", "shard", *names])


def block_tables(l: np.ndarray, shard: int, params: IndexParams, key: bytes) -> list[pa.Table]:  # noqa: E741
    """Blocks and superblocks of a transform. Sorting is not needed again for another block size."""
    coding = Coding(params.encrypt, params.cipher_mode, params.rounds)
    blocks = encode_blocks(l, params.bs, key, coding)
    checks = [f"{zlib.crc32(l[i : i + params.bs].astype('<i8').tobytes()):08x}" if params.checksum else None for i in range(0, len(l), params.bs)]
    sealed = _rows("blocks", shard, len(blocks), no=range(len(blocks)), a=[b.n for b in blocks], b=[b.comp_len for b in blocks], c=[b.bits for b in blocks], ints=[b.alpha for b in blocks], longs=[b.counts for b in blocks], payload=[b.payload for b in blocks], text=checks)
    seen: dict[int, int] = {}
    supers: list[tuple[list[int], list[int]]] = []
    for i, b in enumerate(blocks):
        if i % PER_SUPER == 0:
            at = sorted(seen)
            supers.append((at, [seen[s] for s in at]))
        for s, n in zip(b.alpha.tolist(), b.counts.tolist(), strict=True):
            seen[s] = seen.get(s, 0) + n
    return [sealed, _rows("superblocks", shard, len(supers), no=range(len(supers)), ints=[s[0] for s in supers], longs=[s[1] for s in supers])]


def shard_tables(shard: int, numbers: list[int], names: list[str], seqs: list[str], alphabet: Alphabet, params: IndexParams, key: bytes, salt: bytes, order: np.ndarray | None) -> list[pa.Table]:
    """All tables of a shard: encode, order, transform, cut, seal and mark."""
    text, starts, counts = join_collection(seqs, alphabet, order)
    rank = transform.order_of(text, alphabet.size, params.strategy)
    l = text[rank - 1]  # noqa: E741
    syms, n = np.unique(l, return_counts=True)
    marked = np.flatnonzero(rank % params.mark_step == 0)
    return [
        _rows("items", shard, len(numbers), no=numbers, a=[len(s) for s in seqs], b=starts, c=counts, text=names),
        _rows("c_table", shard, len(syms), no=syms, a=np.cumsum(n) - n),
        _rows("marks", shard, len(marked), no=marked, a=rank[marked]),
        *block_tables(l, shard, params, block_key(key, salt, shard, params.nonce_mode)),
    ]


def spread_tables(planned: DataFrame, alphabet: Alphabet, params: IndexParams, key: bytes, salt: bytes, order) -> DataFrame:
    """All tables of shards that no task can hold: the transform is sorted over the cluster, blocks are cut from its rows,
    and the other tables are DataFrames. A superblock lists the symbols that occur in it."""
    rows, items = joined_rows(planned, alphabet, order)
    rows = barrier(rows, "symbols")
    l = barrier(transform.collection_bwt(rows, params.strategy), "transform")  # noqa: E741

    def cut(table: pa.Table) -> pa.Table:
        shard, no = table["shard"][0].as_py(), table["no"][0].as_py()
        syms = table.sort_by("row")["sym"].to_numpy()
        b = encode_block(syms, no, block_key(key, salt, shard, params.nonce_mode), Coding(params.encrypt, params.cipher_mode, params.rounds))
        check = f"{zlib.crc32(syms.astype('<i8').tobytes()):08x}" if params.checksum else None
        return _rows("blocks", shard, 1, no=[no], a=[b.n], b=[b.comp_len], c=[b.bits], ints=[b.alpha], longs=[b.counts], payload=[b.payload], text=[check])

    numbered = l.select("shard", F.floor(F.col("row") / params.bs).cast("long").alias("no"), "row", "sym")
    blocks = numbered.groupBy("shard", "no").applyInArrow(cut, ROW)

    def as_rows(kind: str, df: DataFrame, **columns: str) -> DataFrame:
        fields = [c.split(" ") for c in ROW.split(", ")]
        given = {"kind": F.lit(kind), "shard": F.col("shard")} | {c: F.col(x) for c, x in columns.items()}
        return df.select(*[given.get(c, F.lit(None)).cast(t).alias(c) for c, t in fields])

    supers = occ_superblocks(l, params.bs).groupBy("shard", "super_no").agg(F.sort_array(F.collect_list(F.struct("sym", "before"))).alias("s"))
    supers = supers.select("shard", "super_no", F.transform("s", lambda x: x["sym"]).alias("syms"), F.transform("s", lambda x: x["before"]).alias("counts"))
    out = blocks.unionByName(as_rows("items", items.withColumn("length", F.length("seq")), no="item_no", a="length", b="start_sym", c="n_sym", text="seq_id"))
    out = out.unionByName(as_rows("c_table", c_table(l), no="sym", a="c_before"))
    out = out.unionByName(as_rows("superblocks", supers, no="super_no", ints="syms", longs="counts"))
    return out.unionByName(as_rows("marks", mark_rows(l, params.mark_step), no="row", a="pos"))


def _checked(items: DataFrame) -> DataFrame:
    columns = [F.col("item_no").cast("long").alias("item_no"), (F.col("seq_id") if "seq_id" in items.columns else F.col("item_no").cast("string")).alias("seq_id"), F.col("seq").cast("string").alias("seq")]
    slim = items.select(*columns, *[c for c in ("start",) if c in items.columns])
    bad = slim.filter("seq is null or item_no is null").limit(1).count()
    if bad:
        raise ValueError("a collection holds no null sequences or item numbers")
    if slim.groupBy(*[c for c in ("item_no", "start") if c in slim.columns]).count().filter("count > 1").limit(1).count():
        raise ValueError("item numbers must differ")
    return slim


def build_index(items: DataFrame, params: IndexParams, key: bytes, path: str, salt: bytes | None = None, letters: list[str] | None = None) -> Index:
    """Build a sealed index of (item_no, seq[, seq_id]) at ``path``; items in parts (with ``start``) for an index of pieces.

    One small result reaches the driver: the used characters. Shards are built by independent tasks. The metadata is
    written last, and an index without it does not open.
    """
    return _built(items, params, key, path, salt, letters, None)


def _built(items: DataFrame, params: IndexParams, key: bytes, path: str, salt: bytes | None, letters: list[str] | None, grown: Index | None) -> Index:
    spark = items.sparkSession
    if "start" in items.columns and not params.piece:
        raise ValueError("items in parts make an index of pieces only")
    if params.piece and params.strategy in transform.SPREAD:
        raise ValueError("pieces fit a task: their shards are not sorted over the cluster")
    slim = _checked(items)
    alphabet = Alphabet(tuple(letters if letters is not None else collect_alphabet(slim)), params.k)
    if alphabet.size > MOST_IDS:
        raise ValueError(f"{alphabet.sigma} characters and k={params.k} make {alphabet.size} blocks; the limit is {MOST_IDS}")
    salt = salt if salt is not None else secrets.token_bytes(16)
    order = spark.sparkContext.broadcast(scramble_key(key, alphabet.size) if params.scramble else None)
    if params.piece:
        planned = cut_items(slim, params.piece, params.overlap, params.shard_symbols * params.k)
    else:
        planned = plan_shards(slim, params.k, params.shard_symbols)
    if params.nonce_mode == "paper" and (grown or planned.agg(F.max("shard")).first()[0] not in (None, 0)):
        raise ValueError("nonce mode paper allows a single shard: another would reuse its keystream")
    commit = new_commit()

    def kernel(table: pa.Table) -> pa.Table:
        return pa.concat_tables(shard_tables(table["shard"][0].as_py(), *joined(table), alphabet, params, key, salt, order.value))

    built = spread_tables(planned, alphabet, params, key, salt, order) if params.strategy in transform.SPREAD else planned.groupBy("shard").applyInArrow(kernel, ROW)
    _write(built, path, commit)
    meta = grown.meta if grown else asdict(params) | {"letters": list(alphabet.letters), "mark_step": params.mark_step}
    return _commit(spark, path, key, meta, commit, salt)


def new_commit() -> str:
    """Name of a folder of tables; the letter keeps it a string as a partition value."""
    return f"c{uuid.uuid4().hex[:16]}"


def _write(rows: DataFrame, path: str, commit: str) -> None:
    rows.write.mode("append").option("parquet.block.size", 1 << 20).partitionBy("kind", "shard").parquet(f"{path}/tables/commit={commit}")


def _commit(spark: SparkSession, path: str, key: bytes, meta: dict, commit: str, salt: bytes) -> Index:
    """Name the folder's shards, then write the next version of the metadata; a version is one row of one file."""
    tables = spark.read.schema(ROW).parquet(f"{path}/tables/commit={commit}")
    shards = tables.filter("kind = 'items'").select("shard").distinct().select("shard", F.lit(commit).alias("commit"))
    shards.write.mode("append").parquet(f"{path}/shards")
    meta = meta | {"commits": meta.get("commits", {}) | {commit: salt.hex()}, "version": meta.get("version", 0) + 1}
    spark.createDataFrame([(meta["version"], json.dumps(meta))], "version long, meta string").coalesce(1).write.mode("append").json(f"{path}/meta")
    return Index(spark, path, key, meta)


_OPEN: dict = {}
#: Shards that stay open in a worker.
OPEN_SHARDS = 2
#: Patterns that a task searches for at most, and pairs of a pattern and a shard that are made as rows.
MOST, PAIRS = 20_000, 1 << 18


def open_shard(path: str, shard: int, commit: str, meta: dict, key: bytes, order: np.ndarray | None) -> ShardFM:
    """One opened shard per worker process, path and key; the last few stay open."""
    name = (path, shard, commit, meta["bs"], meta["pad_wildcards"], hash(key))
    if name not in _OPEN:
        if len(_OPEN) >= OPEN_SHARDS:
            _OPEN.pop(next(iter(_OPEN)))
        _OPEN[name] = ShardFM(path, shard, meta, key, commit, order)
    return _OPEN[name]


@lru_cache(maxsize=2)
def _asked(path: str) -> pa.Table:
    """Patterns of a chunk, in the same order for every shard."""
    store, root = resolve(path)
    if store.get_file_info(root).type == fs.FileType.NotFound:  # by its hash, no pattern fell on it
        return pa.table({"pattern_id": pa.array([], pa.int64()), "pattern": pa.array([], pa.string())})
    return ds.dataset(root, filesystem=store, format="parquet").to_table(columns=["pattern_id", "pattern"]).sort_by([("pattern_id", "ascending"), ("pattern", "ascending")])


class Index:
    """A stored index opened with a key. The key lives in closures only, never in a plan, a column or a file."""

    def __init__(self, spark: SparkSession, path: str, key: bytes, meta: dict):
        self.spark, self.path, self.key, self.meta = spark, path, key, meta
        self._order = None

    @staticmethod
    def open(spark: SparkSession, path: str, key: bytes) -> Index:
        """The last version that was committed."""
        last = spark.read.json(f"{path}/meta", "version long, meta string").orderBy(F.desc("version")).first()
        return Index(spark, path, key, json.loads(last["meta"]))

    @property
    def alphabet(self) -> Alphabet:
        return Alphabet(tuple(self.meta["letters"]), self.meta["k"])

    @property
    def order(self):
        """The keyed order of all ids, made once and sent to each executor once (at most 2^24 numbers)."""
        if self._order is None:
            self._order = self.spark.sparkContext.broadcast(scramble_key(self.key, self.alphabet.size) if self.meta["scramble"] else None)
        return self._order

    def shards(self) -> DataFrame:
        """shard, commit of every committed shard."""
        return self.spark.read.schema("shard int, commit string").parquet(f"{self.path}/shards").filter(F.col("commit").isin(list(self.meta["commits"]))).distinct()

    @property
    def params(self) -> IndexParams:
        return IndexParams(**{f: self.meta[f] for f in IndexParams.__dataclass_fields__ if f in self.meta})

    def with_options(self, **changes) -> Index:
        """The same stored index read under other search options (such as pad_wildcards)."""
        return Index(self.spark, self.path, self.key, self.meta | changes)

    def rows(self) -> DataFrame:
        """All committed rows of all tables."""
        root = f"{self.path}/tables"
        return self.spark.read.schema(f"commit string, {ROW}").option("basePath", root).parquet(*[f"{root}/commit={c}" for c in self.meta["commits"]])

    def table(self, name: str) -> DataFrame:
        """items, c_table, superblocks, blocks or marks; files are pruned by commit and kind, and by shard where filtered."""
        return self.rows().filter(F.col("kind") == name).select("commit", "shard", *[F.col(c).alias(n) for c, n in TABLES[name].items()])

    def _over_shards(self, sent: DataFrame, run: Callable[[ShardFM, pa.Table], Iterator[dict]], schema: pa.Schema, requests: int, most: int = MOST) -> DataFrame:
        """Run requests (with shard and commit) on shards, one task per shard and ``most`` of all ``requests``.

        A shard is opened once for all requests of its task. ``run`` yields the columns of the result in lots. A request
        without columns besides shard, commit and ``_chunk`` is for all that ``run`` knows of that chunk.
        """
        path, meta, key, order = self.path, self.meta, self.key, self.order

        def search(shard: int, table: pa.Table) -> pa.Table:
            fm = open_shard(path, shard, table["commit"][0].as_py(), meta, key, order.value)
            lots = [pa.table({f.name: pa.array(lot[f.name], f.type) for f in schema}) for lot in run(fm, table)]
            return pa.concat_tables([*lots, schema.empty_table()])

        return self._tasks(sent, search, schema, requests, most)

    def _tasks(self, sent: DataFrame, run: Callable[[int, pa.Table], pa.Table], schema: pa.Schema, requests: int, most: int = MOST) -> DataFrame:
        """``run`` on each shard and the requests of a task for it."""
        keys = [c for c in sent.columns if c not in ("shard", "commit")]
        if keys != ["_chunk"]:
            sent = sent.withColumn("_chunk", F.pmod(F.xxhash64(*keys), F.lit(max(1, -(-requests // most)))))
        parts = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        names = ", ".join(f"{f.name} {'string' if f.type == pa.string() else 'long'}" for f in schema)
        # few bytes, but work for many tasks: a number of partitions that is named is not lowered by their size
        return sent.repartition(parts, "shard", "commit", "_chunk").groupBy("shard", "commit", "_chunk").applyInArrow(lambda table: run(table["shard"][0].as_py(), table), names)

    def _search(self, patterns: DataFrame, pruned: bool, run: Callable[[ShardFM, list[int], list[str]], Iterator[dict]], schema: pa.Schema) -> DataFrame:
        """``run`` with the patterns that each shard is asked for.

        Many patterns would be a row for nearly each of them and each shard: these are written once to the shared folder,
        where tasks read them, and a shard leaves out those whose blocks it lacks.
        """
        n = patterns.count()
        sent, read = self._asked_of(patterns, n, pruned, not pruned)
        return self._over_shards(sent, lambda fm, table: run(fm, *read(table)), schema, n)

    def _asked_of(self, patterns: DataFrame, n: int, pruned: bool, rows: bool = False) -> tuple[DataFrame, Callable[[pa.Table], tuple[np.ndarray, list[str]]]]:
        """What to send to shards for ``n`` patterns, and how a task has from it the numbers and texts of its patterns.
        ``rows``: always a row for each pair."""
        if rows or (n <= MOST and n * self.shards().count() <= PAIRS):
            return self._wanted(patterns, pruned), lambda table: (table["pattern_id"].to_numpy(), table["pattern"].to_pylist())
        if self.params.piece:
            check_patterns(patterns, self.params.overlap)
        chunks, path = -(-n // MOST), scratch_path(self.spark, "asked")
        slim = patterns.select("pattern_id", "pattern").filter("pattern is not null").distinct()
        slim.withColumn("chunk", F.pmod(F.xxhash64("pattern_id", "pattern"), F.lit(chunks))).repartition("chunk").write.partitionBy("chunk").parquet(path)

        def read(table: pa.Table) -> tuple[np.ndarray, list[str]]:
            asked = _asked(f"{path}/chunk={table['_chunk'][0].as_py()}")
            return asked["pattern_id"].to_numpy(), asked["pattern"].to_pylist()

        every = self.spark.range(chunks).select(F.col("id").alias("_chunk"))
        return self.shards().crossJoin(F.broadcast(every)), read

    def _wanted(self, patterns: DataFrame, pruned: bool) -> DataFrame:
        """pattern_id, pattern, shard, commit of the searches to make."""
        slim = patterns.select("pattern_id", "pattern")
        if self.params.piece:
            check_patterns(slim, self.params.overlap)
        return self.prune_shards(slim) if pruned else slim.crossJoin(F.broadcast(self.shards()))  # every shard is asked

    def locate(self, patterns: DataFrame, last: str = "auto", pruned: bool = True) -> DataFrame:
        """pattern_id, item_no, offset of every occurrence. ``last``: auto, verify, enumerate or naive."""

        def run(fm: ShardFM, numbers: np.ndarray, texts: list[str]) -> Iterator[dict]:
            for number, item, offset in fm.locate_many(texts, last):
                yield {"pattern_id": numbers[number], "item_no": item, "offset": offset}

        return self._search(patterns, pruned, run, pa.schema([(c, pa.int64()) for c in ("pattern_id", "item_no", "offset")]))

    def _counts(self, patterns: DataFrame, pruned: bool) -> DataFrame:
        run = lambda fm, numbers, texts: [{"pattern_id": numbers, "n": fm.count_many(texts)}]
        return self._search(patterns, pruned, run, pa.schema([("pattern_id", pa.int64()), ("n", pa.int64())]))

    def count(self, patterns: DataFrame, pruned: bool = True) -> DataFrame:
        """pattern_id, n for every pattern, 0 included."""
        totals = self._counts(patterns, pruned).groupBy("pattern_id").agg(F.sum("n").alias("n"))
        return patterns.select("pattern_id").join(totals, "pattern_id", "left").select("pattern_id", F.coalesce("n", F.lit(0)).cast("long").alias("n"))

    def exists(self, patterns: DataFrame, pruned: bool = True) -> DataFrame:
        """The patterns that occur."""
        return patterns.join(self._counts(patterns, pruned).filter("n > 0"), "pattern_id", "left_semi")

    def extract(self, requests: DataFrame) -> DataFrame:
        """req_id, text for requests (req_id, item_no, start, len); null for an item that is null or not there.

        Each goes to the shard of its item only.
        """
        self._uncut("extract")
        slim = requests.select("req_id", "item_no", "start", "len")
        sent = slim.join(self.table("items").select("commit", "shard", "item_no"), "item_no")

        def run(fm: ShardFM, table: pa.Table) -> Iterator[dict]:
            asked = zip(*(table[c].to_pylist() for c in ("item_no", "start", "len")), strict=True)
            yield {"req_id": table["req_id"], "text": [fm.extract(*a) for a in asked]}

        found = self._over_shards(sent, run, pa.schema([("req_id", pa.int64()), ("text", pa.string())]), slim.count())
        return slim.select("req_id").join(found, "req_id", "left")

    def work(self, patterns: DataFrame, last: str = "auto") -> DataFrame:
        """pattern_id, shard, blocks_loaded, blocks, lf_steps, checked: what each pattern's locate touches by itself."""

        def run(fm: ShardFM, table: pa.Table) -> Iterator[dict]:
            for number, pattern in zip(table["pattern_id"].to_pylist(), table["pattern"].to_pylist(), strict=True):
                fm.work = type(fm.work)()
                fm.locate(pattern, last)
                yield {"pattern_id": [number], "shard": [fm.shard], "blocks_loaded": [len(fm.work.loaded)], "blocks": [fm.n_blocks], "lf_steps": [fm.work.lf_steps], "checked": [fm.work.checked]}

        schema = pa.schema([(c, pa.int64()) for c in ("pattern_id", "shard", "blocks_loaded", "blocks", "lf_steps", "checked")])
        return self._over_shards(self._wanted(patterns, False), run, schema, patterns.count(), 500)

    def search_times(self, patterns: DataFrame, last: str = "auto") -> DataFrame:
        """pattern_id, shard, open_us, micros, hits, blocks_loaded, blocks: each pattern's locate by itself on a shard that is
        open, after a warming search, how long the shard took to open, and the blocks that the locate touches of all; measured
        in the tasks that hold the shards."""
        path, meta, key, order = self.path, self.meta, self.key, self.order
        n = patterns.count()
        sent, read = self._asked_of(patterns, n, False)
        names = ("pattern_id", "shard", "open_us", "micros", "hits", "blocks_loaded", "blocks")

        def run(shard: int, table: pa.Table) -> pa.Table:
            began = time.perf_counter()
            fm = ShardFM(path, shard, meta, key, table["commit"][0].as_py(), order.value)
            opened = int((time.perf_counter() - began) * 1e6)
            numbers, texts = read(table)
            rows, together = [], fm.keeps_all()
            if together:  # blocks that any pattern needs are opened by one search for all, and stay open
                for _ in fm.locate_many(texts, last):
                    pass
            for number, pattern in zip(numbers.tolist(), texts, strict=True):
                if together:
                    planner.planned_lot((pattern,), fm.alphabet)
                else:
                    fm.locate(pattern, last)
                fm.work = type(fm.work)()
                began = time.perf_counter()
                hits = len(fm.locate(pattern, last)[0])
                rows.append((number, shard, opened, int((time.perf_counter() - began) * 1e6), hits, len(fm.work.loaded), fm.n_blocks))
            return pa.table({c: pa.array([r[i] for r in rows], pa.int64()) for i, c in enumerate(names)})

        return self._tasks(sent, run, pa.schema([(c, pa.int64()) for c in names]), n)

    def prune_shards(self, patterns: DataFrame) -> DataFrame:
        """pattern_id, pattern, shard, commit of the shards that can hold a pattern.

        An occurrence at a displacement holds all its fixed blocks, so only shards with the one of them that the fewest
        shards use are asked. Only the small symbol tables are read. Displacements without a fixed block ask all shards.
        """
        alphabet, order, k = self.alphabet, self.order, self.meta["k"]

        def fixed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows: list[tuple] = []
                for number, pattern in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    digits = alphabet.digits(pattern or "")
                    if not len(digits) or (digits < 0).any():
                        continue
                    for p in displaced(digits, k):
                        ids = alphabet.of_digits(p.parts[(p.parts >= 0).all(1)])
                        syms = np.unique(ids if order.value is None else order.value[ids]).tolist()
                        rows += [(number, pattern, p.d, s) for s in syms or [None]]
                columns = list(zip(*rows, strict=True)) or [[]] * 4
                yield pa.record_batch([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.string(), pa.int32(), pa.int64()), strict=True)], names=["pattern_id", "pattern", "d", "sym"])

        wanted = patterns.select("pattern_id", "pattern").mapInArrow(fixed, "pattern_id long, pattern string, d int, sym long")
        holders = self.table("c_table").select("sym", "shard", "commit")
        usage = holders.groupBy("sym").agg(F.count(F.lit(1)).alias("n"))
        scored = wanted.join(usage, "sym", "left").withColumn("n", F.when(F.col("sym").isNotNull(), F.coalesce("n", F.lit(0))))
        rarest = barrier(scored.groupBy("pattern_id", "pattern", "d").agg(F.min_by("sym", "n").alias("sym"), F.min("n").alias("n")), "rarest")
        near = rarest.filter("n > 0").join(holders, "sym").select("pattern_id", "pattern", "shard", "commit")
        free = rarest.filter("n is null").select("pattern_id", "pattern").distinct().crossJoin(F.broadcast(self.shards()))
        return near.unionByName(free).distinct()

    def _uncut(self, what: str) -> None:
        if self.params.piece:
            raise ValueError(f"an index of pieces does not {what}")

    def _each_shard(self, run: Callable[[ShardFM], Iterator[pa.Table]], schema: str) -> DataFrame:
        """The rows that ``run`` makes of every shard, a shard per task."""
        path, meta, key, order = self.path, self.meta, self.key, self.order

        def one(table: pa.Table) -> pa.Table:
            return run(open_shard(path, table["shard"][0].as_py(), table["commit"][0].as_py(), meta, key, order.value))

        parts = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        return self.shards().repartition(parts, "shard", "commit").groupBy("shard", "commit").applyInArrow(one, schema)

    def restore(self) -> DataFrame:
        """item_no, seq of the whole collection: opens every block and inverts the transform, a shard per task."""
        self._uncut("restore")

        def run(fm: ShardFM) -> pa.Table:
            text = np.searchsorted(fm.syms, transform.invert(fm.transform()))
            spans = zip(fm.item_start.tolist(), fm.item_blocks.tolist(), strict=True)
            seqs = [fm.alphabet.text(fm.digits[text[start : start + n]].reshape(-1)) for start, n in spans]
            return pa.table({"item_no": pa.array(fm.item_no, pa.int64()), "seq": pa.array(seqs, pa.string())})

        return self._each_shard(run, "item_no long, seq string")

    def recut(self, path: str, bs: int) -> Index:
        """The same index with another block size: blocks are cut anew from the opened transform, nothing is sorted.

        Shards of several commits are numbered anew in one.
        """
        src, meta, key, params = self.path, self.meta, self.key, replace(self.params, bs=bs)
        salt, commit, order = secrets.token_bytes(16), new_commit(), self.order
        numbered = barrier(row_numbers(place_by_range(self.shards(), ["commit", "shard"], "recut"), ["commit", "shard"], "new").select("commit", "shard", F.col("new").cast("int").alias("new")), "renumbered")

        def run(table: pa.Table) -> pa.Table:
            shard, new = table["shard"][0].as_py(), table["new"][0].as_py()
            fm = open_shard(src, shard, table["commit"][0].as_py(), meta, key, order.value)
            return pa.concat_tables(block_tables(fm.transform(), new, params, block_key(key, salt, new, params.nonce_mode)))

        # one row a shard: without a named number of partitions they would all be one task's
        parts = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        cut = numbered.repartition(parts, "commit", "shard").groupBy("commit", "shard").applyInArrow(run, ROW)
        columns = [c.split()[0] for c in ROW.split(", ")]
        kept = self.rows().filter("kind in ('items', 'c_table', 'marks')").join(F.broadcast(numbered), ["commit", "shard"]).withColumn("shard", F.col("new"))
        _write(cut.unionByName(kept.select(*columns)), path, commit)
        return _commit(self.spark, path, key, meta | {"bs": bs, "commits": {}, "version": 0}, commit, salt)

    def append(self, items: DataFrame) -> Index:
        """Add items in new shards, under a salt of their own, so that no keystream is used twice. New characters need a
        rebuild."""
        self._uncut("grow")
        known = set(self.meta["letters"])
        if new := [c for c in collect_alphabet(items.select(F.col("seq").cast("string"))) if c not in known]:
            raise ValueError(f"characters {new} are not in this index; rebuild it")
        clash = items.select(F.col("item_no").cast("long")).join(self.table("items").select("item_no"), "item_no", "left_semi")
        if not clash.isEmpty():
            raise ValueError("an item number is in the index already")
        return _built(items, self.params, self.key, self.path, None, self.meta["letters"], self)

    def compact(self, path: str) -> Index:
        """One new index at ``path`` from all shards, with a new salt."""
        names = self.table("items").select("item_no", "seq_id")
        return build_index(self.restore().join(names, "item_no"), self.params, self.key, path)

    def drop(self) -> None:
        """Remove the stored index, for one of a series that is measured and then read by nobody; what its build has shuffled
        goes when the driver's garbage is collected, and is collected now."""
        spark = self.spark
        folder = spark._jvm.org.apache.hadoop.fs.Path(self.path)
        folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)
        gc.collect()
        spark._jvm.System.gc()

    def stored_bytes(self) -> int:
        """Bytes of the index as it lies on disk: Parquet files with their compression, all tables."""
        return self.sizes()[1]

    def sizes(self) -> tuple[int, int]:
        """What :meth:`payload_bytes` and :meth:`stored_bytes` sum up to; each file is read once for both."""
        files = self.rows().groupBy(F.input_file_name().alias("f")).agg(F.sum(self._packed()).cast("long").alias("packed"))

        def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                found = []
                for uri in batch.column(0).to_pylist():
                    store, name = resolve(unquote(uri))
                    found.append(store.get_file_info(name).size)
                yield pa.record_batch([batch.column(1), pa.array(found, pa.int64())], names=["packed", "size"])

        total = files.mapInArrow(measured, "packed long, size long").agg(F.sum("packed"), F.sum("size")).first()
        return int(total[0] or 0), int(total[1] or 0)

    def payload_bytes(self) -> DataFrame:
        """kind, bytes: what the parts of the index would take, packed to the bit: sealed payloads, local alphabets, counts,
        marks, tables. A model: the tables on disk (:meth:`stored_bytes`) hold whole numbers, compressed by Parquet."""
        return self.rows().groupBy("kind").agg(F.sum(self._packed()).cast("long").alias("bytes"))

    def _packed(self) -> Column:
        """Bytes of a row, packed to the bit."""
        ids = max(1, math.ceil(math.log2(max(2, (len(self.meta["letters"]) + 2) ** self.meta["k"]))))
        return (
            F.when(F.col("kind") == "blocks", F.length("payload") + F.ceil(F.size("ints") * (ids + F.ceil(F.log2(F.col("a") + 1))) / 8) + 12)
            .when(F.col("kind") == "superblocks", F.ceil(F.size("ints") * (ids + 32) / 8))
            .when(F.col("kind") == "marks", F.lit(8)).when(F.col("kind") == "items", F.lit(24) + F.length("text")).otherwise(F.lit(8))
        )
