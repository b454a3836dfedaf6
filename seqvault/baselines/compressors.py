"""Comparison compressors without search: block-limited, transform first, sealed after, and against a reference."""

from __future__ import annotations

import bz2
import hashlib
import secrets
import zlib
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.alphabet import Alphabet, collect_alphabet
from seqvault.baselines.scan import scan_locate
from seqvault.bwt import invert
from seqvault.cipher import KeyStream, seal_xor
from seqvault.encode import join_collection, plan_shards
from seqvault.operators.barrier import scratch_path
from seqvault.operators.shared_fs import AtomicFile, resolve
from seqvault.suffix import suffix_order_kernel


def _packed(items: DataFrame, pack: Callable[[int, bytes], bytes]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            numbers, seqs = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            yield pa.record_batch([batch.column(0), pa.array([pack(n, s.encode()) for n, s in zip(numbers, seqs, strict=True)], pa.binary())], names=["item_no", "packed"])

    return items.select(F.col("item_no").cast("long"), "seq").mapInArrow(run, "item_no long, packed binary")


def _opened(packed: DataFrame, unpack: Callable[[int, bytes], bytes]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)
            yield pa.record_batch([batch.column(0), pa.array([unpack(n, b).decode() for n, b in rows], pa.string())], names=["item_no", "seq"])

    return packed.mapInArrow(run, "item_no long, seq string")


def bzip_items(items: DataFrame, level: int = 9) -> DataFrame:
    """item_no, packed: each item alone; blocks of ``level`` x 100 kB."""
    return _packed(items, lambda _, data: bz2.compress(data, level))


def bunzip_items(packed: DataFrame) -> DataFrame:
    return _opened(packed, lambda _, data: bz2.decompress(data))


def bzip_collection(items: DataFrame, level: int = 9, shard_symbols: int = 1 << 22) -> DataFrame:
    """shard, raw, packed: items of a shard one after another, block by block."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        seqs = pdf.sort_values("item_no")["seq"]
        return pd.DataFrame({"shard": [pdf["shard"].iloc[0]], "raw": [len("\n".join(seqs).encode())], "packed": [len(packed_block(seqs, level))]})

    return plan_shards(items.select("item_no", "seq"), 1, shard_symbols).groupBy("shard").applyInPandas(run, "shard int, raw long, packed long")


def packed_block(seqs: Iterable[str], level: int = 9) -> bytes:
    """Items of a shard one after another."""
    return bz2.compress("\n".join(seqs).encode(), level)


def packed_transform(l: np.ndarray) -> bytes:  # noqa: E741
    return bz2.compress(l.astype("<u2").tobytes())


def bwt_generic(items: DataFrame, shard_symbols: int = 1 << 22) -> tuple[DataFrame, list[str]]:
    """The transform of a whole shard, then a generic compressor: (shard, item_no, packed), with the characters used."""
    letters = collect_alphabet(items)
    alphabet = Alphabet(tuple(letters), 1)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("item_no")
        text, _, _ = join_collection(pdf["seq"].tolist(), alphabet, None)
        l = text[suffix_order_kernel(text, alphabet.sigma) - 1]  # noqa: E741
        return pd.DataFrame({"shard": [pdf["shard"].iloc[0]], "item_no": [pdf["item_no"].tolist()], "packed": [packed_transform(l)]})

    packed = plan_shards(items.select("item_no", "seq"), 1, shard_symbols).groupBy("shard").applyInPandas(run, "shard int, item_no array<long>, packed binary")
    return packed, letters


def bwt_generic_open(packed: DataFrame, letters: list[str]) -> DataFrame:
    """item_no, seq again: everything is decompressed and inverted."""
    alphabet = Alphabet(tuple(letters), 1)

    def run(pdfs: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in pdfs:
            for numbers, data in zip(pdf["item_no"], pdf["packed"], strict=True):
                text = invert(np.frombuffer(bz2.decompress(data), "<u2").astype(np.int64))
                ends = np.flatnonzero(text == 1)
                starts = np.concatenate([[0], ends[:-1] + 1])
                yield pd.DataFrame({"item_no": numbers, "seq": [alphabet.text(text[a:b]) for a, b in zip(starts, ends, strict=True)]})

    return packed.mapInPandas(run, "item_no long, seq string")


def compress_then_encrypt(items: DataFrame, key: bytes) -> DataFrame:
    """item_no, packed: each item deflated, then sealed under its number as nonce. The key stays in closures.

    What is sealed begins with a salt of its own, and the sealing key is derived from it: versions of an item share no
    keystream.
    """

    return _packed(items, lambda n, data: sealed_item(key, n, data))


def sealed_item(key: bytes, n: int, data: bytes) -> bytes:
    salt = secrets.token_bytes(16)
    return salt + seal_xor(zlib.compress(data, 9), KeyStream(_salted(key, salt), n % (1 << 64)))


def _salted(key: bytes, salt: bytes) -> bytes:
    return hashlib.blake2b(salt, key=key[32:], digest_size=32).digest()


def decrypt_then_open(packed: DataFrame, key: bytes) -> DataFrame:
    return _opened(packed, lambda n, data: zlib.decompress(seal_xor(data[16:], KeyStream(_salted(key, data[:16]), n % (1 << 64)))))


def cte_locate(packed: DataFrame, key: bytes, patterns: DataFrame) -> DataFrame:
    """A query opens everything and scans."""
    return scan_locate(decrypt_then_open(packed, key), patterns)


#: Letters of a text whose seeds are hashed at once, ranges of hashes that are sorted one by one, and bits of a bucket.
STRETCH, RANGES, BUCKET_BITS = 1 << 20, 16, 22
#: Multipliers of the rolling and of the final mixing.
ROLL, MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode(), np.uint8) if text.isascii() else np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")


def seed_hashes(points: np.ndarray, seed: int) -> np.ndarray:
    """A hash of the ``seed`` letters from each position on at which that many are left."""
    n = len(points) - seed + 1
    h = np.zeros(max(0, n), np.uint64)
    for j in range(seed if n > 0 else 0):
        h *= ROLL
        h += points[j : j + n]
    h *= MIX
    return h ^ (h >> np.uint64(29))


class SeedTable:
    """The first position of every seed of a text: positions by hash, and where each bucket of hashes begins."""

    def __init__(self, text: str, seed: int, order: np.ndarray, starts: np.ndarray):
        self.text, self.seed, self.order, self.starts = text, seed, order, starts

    @staticmethod
    def make(text: str, seed: int) -> tuple[np.ndarray, np.ndarray]:
        """``order`` and ``starts``. Hashes are sorted range by range; of equal seeds the first position stays, and seeds
        that only share a hash all stay."""
        points = _points(text)
        n = max(0, len(points) - seed + 1)
        hashes = np.empty(n, np.uint64)
        for i in range(0, n, STRETCH):
            hashes[i : i + STRETCH] = seed_hashes(points[i : i + STRETCH + seed - 1], seed)
        orders, counts = [np.zeros(0, np.int32)], np.zeros((1 << BUCKET_BITS) + 1, np.int64)
        range_of = (hashes >> np.uint64(60)).astype(np.uint8)
        for r in range(RANGES):
            at = np.flatnonzero(range_of == r)
            at = at[np.argsort(hashes[at], kind="stable")]
            h = hashes[at]
            new = np.append(True, h[1:] != h[:-1])[: len(h)]
            first = at[np.maximum.accumulate(np.where(new, np.arange(len(at)), 0))]
            again = np.flatnonzero(~new)
            other = np.zeros(len(again), bool)
            for j in range(seed):
                other |= points[at[again] + j] != points[first[again] + j]
            new[again] = other
            orders.append(at[new].astype(np.int32))
            counts[1:] += np.bincount((h[new] >> np.uint64(64 - BUCKET_BITS)).astype(np.int64), minlength=1 << BUCKET_BITS)
        return np.concatenate(orders), np.cumsum(counts).astype(np.int32)

    def first(self, seed: str, bucket: int) -> int:
        """The smallest position of a seed whose hash is in ``bucket``, or -1."""
        for at in self.order[self.starts[bucket] : self.starts[bucket + 1]].tolist():
            if self.text.startswith(seed, at):
                return at
        return -1


def _common(a: np.ndarray, b: np.ndarray) -> int:
    """Letters that two texts share from their beginnings on."""
    n, at, step = min(len(a), len(b)), 0, 64
    while at < n:
        off = np.flatnonzero(a[at : min(n, at + step)] != b[at : min(n, at + step)])
        if len(off):
            return at + int(off[0])
        at, step = at + step, min(step * 4, 1 << 20)
    return n


def referential_bytes(text: str, table: SeedTable) -> int:
    """Size of a text as deflated (position, length) matches and literals: from the left, the first place of the seed that
    begins at a letter, as long as both go on."""
    squeeze, size = zlib.compressobj(9), 0
    points, base, seed, i, plain = _points(text), _points(table.text), table.seed, 0, []
    begin, buckets, out = 0, np.zeros(0, np.int64), []
    while i < len(text):
        if not begin <= i < begin + len(buckets) and i + seed <= len(text):
            begin, buckets = i, (seed_hashes(points[i : i + STRETCH + seed - 1], seed) >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)
        at = table.first(text[i : i + seed], int(buckets[i - begin])) if i + seed <= len(text) else -1
        if at < 0:
            plain.append(text[i])
            i += 1
            continue
        n = seed + _common(points[i + seed :], base[at + seed :])
        out.append(f"{''.join(plain)}|{at},{n};")
        plain, i = [], i + n
        if len(out) >= 1024:
            size += len(squeeze.compress("".join(out).encode()))
            out = []
    return size + len(squeeze.compress(("".join(out) + "".join(plain)).encode())) + len(squeeze.flush())


def referential_size(items: DataFrame, ref: DataFrame, seed: int = 24) -> DataFrame:
    """item_no, raw, packed: each item as deflated (position, length) matches on a one-row reference and literals.

    The table of the reference's seeds is made by a task, which puts it and the reference into files of the shared folder
    for the others: the reference passes the driver in no form, and no row holds the table.
    """
    path = scratch_path(ref.sparkSession, "seeds")

    def table(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for text in batch.column(0).to_pylist():
                text = text or ""
                for name, data in zip(("order", "starts"), SeedTable.make(text, seed), strict=True):
                    with AtomicFile(f"{path}/{name}") as out:
                        out.write(memoryview(data))
                with AtomicFile(f"{path}/text") as out:
                    out.write(text.encode())
                yield pa.record_batch([pa.array([len(text)], pa.int64())], names=["n"])

    if ref.select("seq").mapInArrow(table, "n long").count() != 1:
        raise ValueError("a reference is one row")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = None
        for batch in batches:
            known = known or _read_table(path, seed)
            sizes = [(len(s), referential_bytes(s, known)) for s in map(pa.StringScalar.as_py, batch.column(1))]
            yield pa.record_batch([batch.column(0), pa.array([s[0] for s in sizes], pa.int32()), pa.array([s[1] for s in sizes], pa.int32())], names=["item_no", "raw", "packed"])

    return items.select(F.col("item_no").cast("long"), "seq").mapInArrow(run, "item_no long, raw int, packed int")


def _read_table(path: str, seed: int) -> SeedTable:
    store, root = resolve(path)
    text, order, starts = (store.open_input_file(f"{root}/{name}").read() for name in ("text", "order", "starts"))
    return SeedTable(text.decode(), seed, np.frombuffer(order, np.int32), np.frombuffer(starts, np.int32))
