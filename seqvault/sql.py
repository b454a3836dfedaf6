"""SQL functions: searching an index, block patterns, block coding. Keys are bound at registration, never SQL literals."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from seqvault import planner
from seqvault.blocks import Coding, SealedBlock, decode_block, encode_block, mtf, remap_local, rle0
from seqvault.cipher import KeyStream, seal_xor
from seqvault.fm import ShardFM
from seqvault.index import Index, open_shard


def register(spark: SparkSession, index: Index) -> None:
    """Register ``seal_locate(pattern)``, ``seal_count(pattern)``, ``seal_extract(item, start, len)`` on ``index``, and
    ``super_patterns(pattern, k)``, ``mtf_rle(array)``, ``homophony(count)``; ``seal_blocks(commit, shard, low, high)``
    opens blocks; ``encode_block(symbols, number)``, ``decode_block(block, number)`` and ``seal(bytes, nonce)`` work under a
    key that is derived from the index's and used for nothing else. A number seals one content only.

    The table functions read shards one after another in the row's task: for many patterns use Index.locate.
    """
    path, meta, key, order = index.path, index.meta, index.key, index.order
    shards = [tuple(r) for r in index.shards().orderBy("commit", "shard").collect()]  # a row of two names each

    def opened() -> Iterator[ShardFM]:
        for shard, commit in shards:
            yield open_shard(path, shard, commit, meta, key, order.value)

    @udtf(returnType="item_no long, offset long")
    class Locate:
        def eval(self, pattern: str):
            for fm in opened():
                for item, offset in zip(*fm.locate(pattern), strict=True):
                    yield int(item), int(offset)

    @udtf(returnType="n long")
    class Count:
        def eval(self, pattern: str):
            yield (sum(fm.count(pattern) for fm in opened()),)

    @udtf(returnType="text string")
    class Extract:
        def eval(self, item: int, start: int, length: int):
            for fm in opened():
                text = fm.extract(item, start, length)
                if text is not None:
                    yield (text,)
                    return

    @udtf(returnType="commit string, shard int, block_no long, n long, syms array<long>")
    class Blocks:
        """The opened blocks of a shard, from ``low`` to before ``high``."""

        def eval(self, commit: str, shard: int, low: int, high: int):
            fm = open_shard(path, shard, commit, meta, key, order.value)
            for b in range(max(0, low), min(high, fm.n_blocks)):
                syms, _ = fm.block(b)
                yield commit, shard, b, len(syms), syms.tolist()

    @udtf(returnType="d int, m int, parts array<string>")
    class SuperPatterns:
        def eval(self, pattern: str, k: int):
            for d in range(k):
                whole = "?" * d + pattern + "?" * ((-(d + len(pattern))) % k)
                yield d, len(whole) // k, [whole[i : i + k] for i in range(0, len(whole), k)]

    @pandas_udf("array<int>")
    def mtf_rle(rows: pd.Series) -> pd.Series:
        def one(syms) -> list[int]:
            alpha, codes = remap_local(np.asarray(syms, np.int64))
            return rle0(mtf(codes, len(alpha))).tolist()

        return rows.map(one)

    coding = Coding(meta["encrypt"], meta["cipher_mode"], meta["rounds"])
    sealing = sealing_key(key)

    @pandas_udf("struct<n: long, comp_len: long, bits: int, alpha: array<long>, counts: array<long>, payload: binary>")
    def encode(rows: pd.Series, numbers: pd.Series) -> pd.DataFrame:
        made = [encode_block(np.asarray(x, np.int64), int(n), sealing, coding) for x, n in zip(rows, numbers, strict=True)]
        return pd.DataFrame([{"n": b.n, "comp_len": b.comp_len, "bits": b.bits, "alpha": b.alpha, "counts": b.counts, "payload": b.payload} for b in made], columns=["n", "comp_len", "bits", "alpha", "counts", "payload"])

    @pandas_udf("array<long>")
    def decode(sealed: pd.DataFrame, numbers: pd.Series) -> pd.Series:
        rows = sealed.itertuples(index=False)
        made = [SealedBlock(r.n, r.comp_len, r.bits, np.asarray(r.alpha, np.int64), np.asarray(r.counts), bytes(r.payload)) for r in rows]
        return pd.Series([decode_block(b, int(n), sealing, coding) for b, n in zip(made, numbers, strict=True)])

    @pandas_udf("binary")
    def seal(data: pd.Series, nonces: pd.Series) -> pd.Series:
        return pd.Series([None if x is None else seal_xor(bytes(x), KeyStream(sealing, int(n) % (1 << 64))) for x, n in zip(data, nonces, strict=True)])

    @pandas_udf("double")
    def homophony(counts: pd.Series) -> float:
        """log10 of the degree of homophony of a column of block counts; the SQL form is measures.homophony."""
        shared = counts.value_counts().to_numpy()
        return float(sum(np.log10(np.arange(1, m + 1)).sum() for m in shared))

    for name, function in {"seal_locate": Locate, "seal_count": Count, "seal_extract": Extract, "seal_blocks": Blocks, "super_patterns": SuperPatterns}.items():
        spark.udtf.register(name, function)
    for name, function in {"mtf_rle": mtf_rle, "homophony": homophony, "encode_block": encode, "decode_block": decode, "seal": seal}.items():
        spark.udf.register(name, function)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION revcomp(s STRING) RETURNS STRING RETURN reverse(translate(s, 'ACGT', 'TGCA'))")


def sealing_key(key: bytes) -> bytes:
    """A key for values sealed outside of an index."""
    return hashlib.blake2b(b"values", key=key[32:], digest_size=32).digest()


def super_count(pattern: str, k: int, sigma: int) -> tuple[int, int, int]:
    """Concrete block patterns of a pattern: exact, by the published formula, and as searched here."""
    return planner.naive_super_count(len(pattern), k, sigma), planner.paper_super_count(len(pattern), k, sigma), k
