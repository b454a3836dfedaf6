"""Token ids in Arrow's file format: fixed-size-list batches with zero-copy random access.

Documents are range-partitioned by id. Each partition writes one shard: ``seq-N.arrow`` holds the partition's ids,
back to back, as rows of equal length with a mask of real positions (only a shard's last row is padded), and
``doc-N.arrow`` holds where each document starts. A file is written under its attempt's name and moved into place, so
a retried or twin task leaves the same whole file. Only one line per shard reaches the manifest. Ids take the
narrowest unsigned type that holds the vocabulary.

Null text: only the end id. Null ids come first, rows with equal ids are ordered by their text. Empty table: an empty
manifest and an empty digest. Other columns are not read.
"""

from __future__ import annotations

import string
import zlib
from array import array
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seqvault.llm.token_count import byte_letters
from seqvault.operators.barrier import barrier, scratch_path
from seqvault.operators.shared_fs import AtomicFile, resolve

#: Rows of one record batch.
BATCH_ROWS = 128
DOC_SCHEMA = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())])


def sequence_schema(length: int, width: pa.DataType) -> pa.Schema:
    return pa.schema([("ids", pa.list_(pa.field("item", width, False), length)), ("mask", pa.list_(pa.field("item", pa.bool_(), False), length))])


class SequenceWriter:
    """Packs ids into rows of equal length and writes full batches; holds one batch at a time."""

    def __init__(self, sink, length: int, width: np.dtype):
        self.length, self.width = length, width
        self.schema = sequence_schema(length, pa.from_numpy_dtype(width))
        self.out = pa.ipc.new_file(sink, self.schema)
        self.room = np.zeros(BATCH_ROWS * length, width)
        self.used = self.total = self.rows = 0

    def add(self, ids: np.ndarray) -> None:
        self.total += len(ids)
        while len(ids):
            take = min(len(ids), len(self.room) - self.used)
            self.room[self.used : self.used + take] = ids[:take]
            self.used += take
            ids = ids[take:]
            if self.used == len(self.room):
                self.flush()

    def flush(self) -> None:
        if not self.used:
            return
        rows = -(-self.used // self.length)
        size = rows * self.length
        mask = np.arange(size) < self.used
        ids = np.where(mask, self.room[:size], 0).astype(self.width)
        lists = [pa.FixedSizeListArray.from_arrays(pa.array(x), type=self.schema.field(i).type) for i, x in enumerate((ids, mask))]
        self.out.write_batch(pa.record_batch(lists, schema=self.schema))
        self.rows += rows
        self.used = 0

    def close(self) -> None:
        self.flush()
        self.out.close()


class SequenceFile:
    """Random access to the rows of a shard. From a local or mounted path the rows are views of the mapped file."""

    def __init__(self, uri: str):
        store, path = resolve(uri)
        local = getattr(store, "type_name", "") == "local"
        self.file = pa.ipc.open_file(pa.memory_map(path) if local else store.open_input_file(path))
        self.length = self.file.schema.field("ids").type.list_size
        self.batches = self.file.num_record_batches

    def batch(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and mask of batch ``k``, two-dimensional."""
        rows = self.file.get_batch(k)
        ids, mask = rows.column("ids").flatten(), rows.column("mask").flatten()
        return ids.to_numpy(zero_copy_only=True).reshape(-1, self.length), mask.to_numpy(zero_copy_only=False).reshape(-1, self.length)

    def row(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and mask of row ``i``; every batch but the last has the same number of rows."""
        ids, mask = self.batch(i // BATCH_ROWS)
        return ids[i % BATCH_ROWS], mask[i % BATCH_ROWS]

    def spans(self, starts: np.ndarray, counts: np.ndarray) -> Iterator[list[np.ndarray]]:
        """The pieces of each span of the id stream, in order; one batch is open at a time."""
        per, at, flat = BATCH_ROWS * self.length, -1, np.zeros(0)
        for start, count in zip(starts.tolist(), counts.tolist(), strict=True):
            pieces, end = [], start + count
            while start < end:
                if start // per != at:
                    at = start // per
                    flat = self.batch(at)[0].reshape(-1)
                low = start - at * per
                high = min(end - at * per, per)
                pieces.append(flat[low:high])
                start = at * per + high
            yield pieces


@dataclass
class TokenFiles:
    """A written set of shards; ``manifest`` has shard, base (ids in earlier shards), n_docs, n_tokens, n_rows."""

    folder: str
    manifest: DataFrame

    def digest(self) -> DataFrame:
        """doc_id, start, n_tokens, ids_crc32 of every document, read back from the files."""
        folder = self.folder

        def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for shard, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    store, path = resolve(f"{folder}/doc-{shard:06d}.arrow")
                    table = pa.ipc.open_file(store.open_input_file(path))
                    sequences = SequenceFile(f"{folder}/seq-{shard:06d}.arrow")
                    for k in range(table.num_record_batches):
                        docs = table.get_batch(k)
                        starts, counts = docs.column("start").to_numpy(), docs.column("n_tokens").to_numpy()
                        sums = []
                        for pieces in sequences.spans(starts, counts):
                            crc = 0
                            for piece in pieces:
                                crc = zlib.crc32(piece.astype("<u4").tobytes(), crc)
                            sums.append(crc)
                        yield pa.record_batch([docs.column("doc_id"), pa.array(starts + base), docs.column("n_tokens"), pa.array(sums, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

        shards = max(1, self.manifest.count())
        return self.manifest.select("shard", "base").repartition(shards).mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


class MemoEncoder:
    """The tokenizers library's ids of whole texts, with the ids of words it has met remembered.

    The byte-level pre-token pattern never joins what stands on both sides of a single blank between two other
    characters, and gives the blank to what follows. So such a text is its first word and then words with a blank before,
    each encoded alone. A word of letters with punctuation marks after it is two pre-tokens, which go to the library's
    merge model; any other word goes through the whole library. Texts with other white space beside a blank are encoded
    whole. The memo has two generations of ``room`` words.
    """

    def __init__(self, path: str, width: np.dtype, room: int):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.merge = self.library.model.tokenize
        self.width, self.room, self.code = width, room, "H" if width.itemsize == 2 else "I"
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        letters = byte_letters()
        self.as_letters = lambda text: "".join([letters[b] for b in text.encode()])
        self.blank = letters[ord(" ")]

    def whole(self, text: str) -> bytes:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, self.width).tobytes()

    def piece(self, letters: str) -> bytes:
        return array(self.code, [t.id for t in self.merge(letters)]).tobytes()

    def word(self, word: str) -> bytes:
        """Ids of a new word as they are after a blank."""
        stem = word.rstrip(string.punctuation)
        if not stem.isalpha():
            return self.whole(f" {word}")
        ids = self.young.get(stem) or self.old.get(stem)
        if ids is None:
            ids = self.piece(self.blank + (stem if stem.isascii() else self.as_letters(stem)))
        return ids if len(stem) == len(word) else ids + self.piece(word[len(stem) :])

    def encode(self, text: str | None) -> bytes:
        """Ids of a whole text as little-endian bytes of the encoder's width."""
        first, *words = (text or "").split(" ")
        if first and first[-1].isspace():
            return self.whole(text)
        if len(self.young) > self.room:
            self.old, self.young = self.young, {}
        young, old = self.young, self.old
        for word in set(words).difference(young):
            if (ids := old.get(word)) is None:
                if not word or word[0].isspace() or word[-1].isspace():
                    return self.whole(text)
                ids = self.word(word)
            young[word] = ids
        return (self.whole(first) if first else b"") + b"".join(map(young.__getitem__, words))


_ENCODERS: dict = {}


def encoder(path: str, width: np.dtype, room: int) -> MemoEncoder:
    """One encoder and memo per worker process."""
    key = (path, str(width), room)
    if key not in _ENCODERS:
        _ENCODERS[key] = MemoEncoder(path, width, room)
    return _ENCODERS[key]


def write_token_files(docs: DataFrame, vocabulary: str, end_id: int = 2, length: int = 2048, vocab_size: int = 50_257, memo: int = 500_000, folder: str | None = None) -> TokenFiles:
    """Encode every text, append ``end_id``, and write the ids in ascending doc_id order.

    ``memo``: words that a worker remembers in each of two generations, at about 200 bytes a word.
    """
    spark: SparkSession = docs.sparkSession
    target = folder or scratch_path(spark, "tokens")
    width = np.dtype("<u2" if max(vocab_size, end_id + 1) <= 1 << 16 else "<u4")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard = TaskContext.get().partitionId()
        first = next(batches, None)
        while first is not None and not first.num_rows:
            first = next(batches, None)
        if first is None:
            return
        encode = encoder(vocabulary, width, memo).encode
        tail = np.array([end_id], width).tobytes()
        docs_seen = 0
        with AtomicFile(f"{target}/seq-{shard:06d}.arrow") as data, AtomicFile(f"{target}/doc-{shard:06d}.arrow") as index:
            sequences, lines = SequenceWriter(data, length, width), pa.ipc.new_file(index, DOC_SCHEMA)
            batch = first
            while batch is not None:
                texts, starts, counts = batch.column(1), [], []
                for text in texts:
                    starts.append(sequences.total)
                    sequences.add(np.frombuffer(encode(text.as_py()) + tail, width))
                    counts.append(sequences.total - starts[-1])
                docs_seen += batch.num_rows
                lines.write_batch(pa.record_batch([batch.column(0), pa.array(starts, pa.int64()), pa.array(counts, pa.int64())], schema=DOC_SCHEMA))
                batch = next(batches, None)
            sequences.close()
            lines.close()
        yield pa.record_batch([pa.array([x], pa.int64()) for x in (shard, docs_seen, sequences.total, sequences.rows)], names=["shard", "n_docs", "n_tokens", "n_rows"])

    slim = docs.select(F.col("doc_id").cast("long"), "text")
    tie = F.xxhash64("text")
    ordered = slim.repartitionByRange("doc_id", tie).sortWithinPartitions("doc_id", tie, "text")
    lines = barrier(ordered.mapInArrow(write, "shard long, n_docs long, n_tokens long, n_rows long"), "manifest")
    earlier = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    return TokenFiles(target, lines.withColumn("base", F.coalesce(F.sum("n_tokens").over(earlier), F.lit(0))))
