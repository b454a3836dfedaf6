"""Token counts by heap-and-linked-list byte-pair merging.

A text is cut at special strings and by the vocabulary's pre-token pattern. Each pre-token is a doubly linked list
of byte symbols with a heap of adjacent pairs by merge rank; the lowest-ranked live pair is merged until none is
left. The count is the number of bytes minus the number of merges: no identifiers are made.

Null or empty text: 0 bytes, 0 tokens. Repeated rows are counted each. Other columns do not matter.
"""

from __future__ import annotations

import heapq
import json
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The public byte-level pre-token pattern. White space is the Unicode property.
PRE_TOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
#: Pre-tokens remembered per Python worker; the memo is emptied beyond that.
MEMO = 400_000


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in a byte-level vocabulary file."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    letters = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}
    return [letters[b] for b in range(256)]


class MergeCounter(dict):
    """Pre-token -> number of tokens; a missing entry is worked out and remembered."""

    def __init__(self, vocabulary: str):
        super().__init__()
        with open(vocabulary, encoding="utf-8") as f:
            spec = json.load(f)
        letters = {c: bytes([b]) for b, c in enumerate(byte_letters())}
        as_bytes = lambda s: b"".join(letters[c] for c in s)
        pairs = (m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"])
        self.rank = {(as_bytes(a), as_bytes(b)): i for i, (a, b) in enumerate(pairs)}
        special = [t["content"] for t in spec.get("added_tokens", [])]
        self.special = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None
        self.find = regex.compile(PRE_TOKEN).findall

    def __missing__(self, piece: str) -> int:
        if len(self) >= MEMO:
            self.clear()
        self[piece] = n = self.merged(piece.encode("utf-8", "surrogatepass"))
        return n

    def merged(self, data: bytes) -> int:
        """Symbols left after merging ``data``."""
        n = len(data)
        if n < 2:
            return n
        rank = self.rank
        symbol: list[bytes | None] = [data[i : i + 1] for i in range(n)]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i) for i in range(n - 1) if (r := rank.get((symbol[i], symbol[i + 1]))) is not None]
        heapq.heapify(heap)
        merges = 0
        while heap:
            r, i = heapq.heappop(heap)
            left = symbol[i]
            if left is None or (j := after[i]) >= n or rank.get((left, symbol[j])) != r:
                continue  # the pair has changed since it was pushed
            symbol[i], symbol[j] = left + symbol[j], None
            merges += 1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (r := rank.get((symbol[i], symbol[k]))) is not None:
                    heapq.heappush(heap, (r, i))
            if (h := before[i]) >= 0 and (r := rank.get((symbol[h], symbol[i]))) is not None:
                heapq.heappush(heap, (r, h))
        return n - merges

    def count(self, text: str) -> int:
        """Tokens of a whole text; a special string is one token."""
        if self.special is None:
            return sum(map(self.__getitem__, self.find(text)))
        parts = self.special.split(text)
        return len(parts) - 1 + sum(sum(map(self.__getitem__, self.find(p))) for p in parts)


_COUNTERS: dict[str, MergeCounter] = {}


def counter(vocabulary: str) -> MergeCounter:
    """One counter and memo per worker process and vocabulary."""
    if vocabulary not in _COUNTERS:
        _COUNTERS[vocabulary] = MergeCounter(vocabulary)
    return _COUNTERS[vocabulary]


def token_counts(docs: DataFrame, vocabulary: str, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row of ``docs``; narrow, one pass, no shuffle."""
    schema = f"{id_col} {docs.schema[id_col].dataType.simpleString()}, n_bytes long, n_tokens long, over_limit boolean"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(vocabulary).count
        for batch in batches:
            texts = batch.column(1).to_pylist()
            tokens = [count(t) if t else 0 for t in texts]
            sizes = [len(t.encode()) if t else 0 for t in texts]
            yield pa.record_batch(
                [batch.column(0), pa.array(sizes, pa.int64()), pa.array(tokens, pa.int64()), pa.array([t > limit for t in tokens], pa.bool_())],
                names=[id_col, "n_bytes", "n_tokens", "over_limit"],
            )

    return docs.select(F.col(id_col), F.col(text_col)).mapInArrow(run, schema)
