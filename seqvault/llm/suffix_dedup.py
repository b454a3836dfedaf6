"""Exact removal of repeated byte strings by suffix sorting with bucket-pointer refinement.

A byte is removed if a string of ``depth`` bytes that covers it also starts earlier (smaller document, or earlier in the
same one). Sorting all suffixes of a corpus is not needed for that, only those that can repeat:

1. Every window of ``depth`` bytes is assigned to one q-gram in it, the leftmost of least hash. Equal windows have equal
   q-grams at equal places, so windows need comparing only below a q-gram hash that occurs twice. Runs of windows with
   the same q-gram are one row (hash, place); a count and a join keep those that repeat. Q-grams with over ``often`` places
   are passed over in that choice: a window hangs on one of them only if it holds no other, so windows that cross the
   border of a very common passage are spread by what stands beyond it.
2. The repeated ones are cut out with the bytes of their windows and sent to the task of their hash. A context that was
   met before in the same task with an earlier place is a repetition as a whole: its marks are known and its bytes stay.
3. There, the suffixes that start at the q-gram and the reversed prefixes that end before it are sorted by bucket-pointer
   refinement: the q-gram hash is the initial bucket, and a bucket of more than one suffix is refined by sorting on the
   buckets in which the suffixes at a later offset stand by then (:func:`refine_buckets`). Common prefix lengths of
   neighbours then tell which windows are equal: the same class at the window's left and right lengths. The first of a
   class stays, the others are marked.
4. Marks go back to the part of the corpus that they lie in, and one more narrow pass applies them.

Texts are written once, numbered by part and byte offset, and every pass reads that copy; marks are small tables by part
in the shared folder which the pass of a part reads beside its texts. So texts are never shuffled, and any pass can be
repeated.

Null text: no bytes. Texts under ``depth`` bytes keep everything. Order is by doc_id; where ids repeat or are null, nulls
come first and ties are ordered by text and place. Empty table: empty result. Other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.dataset as ds
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.llm.workers import released
from seqvault.operators.barrier import barrier, scratch_path
from seqvault.operators.prefix import place_by_range, row_numbers
from seqvault.operators.shared_fs import resolve

#: Bytes of a q-gram; a power of two.
GRAM = 32
#: Window starts handled at once; local positions take the low 20 bits of a sort key.
PIECE = 1 << 19
#: A place is part << SHIFT | byte offset in the part.
SHIFT = 40
#: Bytes of texts worked on at once.
SLICE = 4 << 20
#: Contexts cut or sorted at once in a task.
CHUNK = 16_000
#: Common q-grams that every task may be told of (8 bytes each): ``often`` grows with the corpus to keep to it.
MOST_OFTEN = 4_000_000
#: Bits of a q-gram hash that are shuffled. Q-grams that share them are compared as one, which costs work but changes nothing:
#: at 30 GB about one run of windows in 800 that does not repeat is compared for it.
HASH_BITS = 40
#: Contexts that a task remembers to leave out those it met before.
MEMO = 50_000
NONE = np.zeros(0, np.uint64)
LOW = np.uint64((1 << 20) - 1)


def gram_hashes(data: np.ndarray) -> np.ndarray:
    """Mixed 64-bit hash of the GRAM bytes at every position but the last GRAM - 1, by doubling."""
    h = data.astype(np.uint64) + np.uint64(0x9E3779B97F4A7C15)
    factor, size = 0xD6E8FEB86659FD93, 1
    while size < GRAM:
        h = h[:-size] * np.uint64(factor) + h[size:]
        factor, size = factor * factor % (1 << 64), size * 2
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    return h


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every ``width`` neighbours."""
    size = 1
    while size * 2 <= width:
        x = np.minimum(x[:-size], x[size:])
        size *= 2
    rest = width - size
    return np.minimum(x[: len(x) - rest], x[rest:]) if rest else x


def among(h: np.ndarray, often: np.ndarray) -> np.ndarray:
    """Which hashes are in the sorted array ``often``."""
    return often[np.minimum(np.searchsorted(often, h), len(often) - 1)] == h if len(often) else np.zeros(len(h), bool)


def sent(h: np.ndarray, bits: int) -> np.ndarray:
    """The low ``bits`` of hashes, as the high bits of BIGINTs: next to the varying bytes of the column that follows, where
    the codec of the shuffle takes least for them."""
    return (h << np.uint64(64 - bits)).view(np.int64)


def window_runs(data: np.ndarray, first: np.ndarray, last: np.ndarray, depth: int, often: np.ndarray = NONE) -> tuple[np.ndarray, ...]:
    """Runs of windows with the same q-gram: hash, start of the first window, number of windows, start minus gram place.

    A q-gram in the sorted array ``often`` is taken only by windows without another.

    ``data`` holds texts that lie at ``first`` to ``last``; windows never cross texts. The runs of a text depend on that
    text alone, not on its neighbours or the pieces worked on: passes that get other batches find the same runs.
    """
    n = len(data) - depth + 1
    out: list[tuple[np.ndarray, ...]] = []
    room = np.maximum(last - first - depth + 1, 0)
    if n > 0:
        step = np.zeros(len(data) + 1, np.int8)
        has = room > 0
        np.add.at(step, first[has], 1)
        np.add.at(step, (first + room)[has], -1)
        valid = np.cumsum(step[:-1], dtype=np.int8)[:n] > 0
        before = -1  # gram place of the window before the piece, -1 if that is none
        for low in range(0, n, PIECE):
            high = min(low + PIECE, n)
            ok = valid[low:high]
            if not ok.any():
                before = -1
                continue
            h = gram_hashes(data[low : high + depth - 1])
            keys = (h >> np.uint64(1)) | (among(h, often).astype(np.uint64) << np.uint64(63))
            keys = (keys & ~LOW) | np.arange(len(h), dtype=np.uint64)
            place = (sliding_min(keys, depth - GRAM + 1) & LOW).astype(np.int64)
            new = ok.copy()
            new[1:] &= (place[1:] != place[:-1]) | ~ok[:-1]
            new[0] &= place[0] + low != before
            before = int(place[-1]) + low if ok[-1] else -1
            heads = np.flatnonzero(new)
            out.append((h[place[heads]], heads + low, heads - place[heads]))
    if not out:
        z = np.zeros(0, np.int64)
        return z.astype(np.uint64), z, z, z
    h, start, rel = (np.concatenate(c) for c in zip(*out, strict=True))
    # a run ends before the next head or after the last window of its text
    ends = (first + room)[np.searchsorted(first, start, "right") - 1]
    return h, start, np.minimum(np.append(start[1:], n), ends) - start, rel


def _texts(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes of a batch of texts, back to back, with each one's first and last offset."""
    binary = column.cast(pa.large_binary()).fill_null(b"")
    offsets = np.frombuffer(binary.buffers()[1], np.int64)[binary.offset : binary.offset + len(binary) + 1]
    whole = binary.buffers()[2]
    data = np.frombuffer(whole, np.uint8)[offsets[0] : offsets[-1]] if whole is not None and len(binary) else np.zeros(0, np.uint8)
    return data, offsets[:-1] - offsets[0], offsets[1:] - offsets[0]


def sliced(batches: Iterator[pa.RecordBatch], text: int) -> Iterator[pa.RecordBatch]:
    """The rows of ``batches`` in pieces with about SLICE bytes of column ``text``; a longer text is one piece."""
    for batch in batches:
        column = batch.column(text)
        sizes = np.diff(np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]) if len(column) else np.zeros(0)
        piece = (np.cumsum(sizes, dtype=np.int64) - sizes) // SLICE
        cuts = np.concatenate([[0], np.flatnonzero(np.diff(piece)) + 1, [len(column)]]).tolist()
        for low, high in zip(cuts, cuts[1:], strict=False):
            yield batch.slice(low, high - low)


class PartMarks:
    """The marks of a part, read from a table that was written by part; one part is held at a time."""

    def __init__(self, path: str, columns: list[str]):
        self.path, self.columns, self.part, self.rows = path, columns, None, None

    def of(self, part: int) -> list[np.ndarray]:
        if part != self.part:
            store, root = resolve(f"{self.path}/part={part}")
            exists = store.get_file_info(root).type.name == "Directory"
            table = ds.dataset(root, filesystem=store, format="parquet").to_table(columns=self.columns) if exists else None
            rows = [table.column(c).to_numpy() for c in self.columns] if table is not None else [np.zeros(0, np.int64) for _ in self.columns]
            order = np.argsort(rows[0], kind="stable")
            self.part, self.rows = part, [r[order] for r in rows]
        return self.rows


def by_part(marks: DataFrame, tag: str) -> str:
    """Write (place, ...) by part, ``place`` becoming the offset in its part; returns the path."""
    path = scratch_path(marks.sparkSession, tag)
    split = marks.withColumns({"part": F.shiftrightunsigned("place", SHIFT), "place": F.col("place").bitwiseAND(F.lit((1 << SHIFT) - 1))})
    split.repartition("part").write.partitionBy("part").parquet(path)
    return path


def numbered_texts(docs: DataFrame) -> DataFrame:
    """doc_id, text, place (part and byte offset), doc (order of the document): written once."""

    @released
    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = TaskContext.get().partitionId() << SHIFT
        for batch in sliced(batches, 1):
            data, first, _ = _texts(batch.column(1))
            # empty texts take one byte of numbering, so that places are unique
            sizes = np.diff(np.append(first, len(data)))
            steps = np.maximum(sizes, 1)
            places = at + np.cumsum(steps) - steps
            at += int(steps.sum())
            yield pa.record_batch([batch.column(0), batch.column(1), pa.array(places)], names=["doc_id", "text", "place"])

    texts = barrier(docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(number, "doc_id long, text string, place long"), "texts")
    ids = texts.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    if ids.filter("n > 1 or doc_id is null").isEmpty():
        return texts.withColumn("doc", F.col("doc_id"))
    order = ["doc_id", "tie", "place"]
    slim = texts.select("doc_id", F.xxhash64("text").alias("tie"), "place")
    ranks = row_numbers(place_by_range(slim, order, "order"), order, "doc").select("place", "doc")
    return barrier(texts.join(ranks, "place").select("doc_id", "text", "place", "doc"), "texts")


def run_rows(texts: DataFrame, depth: int, often: np.ndarray, bits: int = HASH_BITS) -> DataFrame:
    """h, place, known (the q-gram is in ``often``, so it repeats) of every run of windows."""

    @released
    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches, 0):
            data, first, last = _texts(batch.column(0))
            h, start, _, _ = window_runs(data, first, last, depth, often)
            base = batch.column(1).to_numpy() - first
            owner = np.searchsorted(first, start, "right") - 1
            yield pa.record_batch([pa.array(sent(h, bits)), pa.array(base[owner] + start), pa.array(among(h, often))], names=["h", "place", "known"])

    return texts.select("text", "place").mapInArrow(find, "h long, place long, known boolean")


def common_grams(texts: DataFrame, depth: int, often: int) -> np.ndarray:
    """Hashes of q-grams with over ``often`` places, sorted; at most MOST_OFTEN of them.

    A task counts its own runs and tells only of hashes that it meets twice, so little is shuffled. A common q-gram that is
    seldom twice in a task may be missed: the list decides on which q-grams windows hang, not what is found.
    """

    @released
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [window_runs(*_texts(batch.column(0)), depth)[0] for batch in sliced(batches, 0)]
        h, n = np.unique(np.concatenate([NONE, *held]), return_counts=True)
        yield pa.record_batch([pa.array(h[n > 1].view(np.int64)), pa.array(n[n > 1])], names=["h", "n"])

    counted = texts.select("text").mapInArrow(count, "h long, n long").groupBy("h").agg(F.sum("n").alias("n"))
    many = barrier(counted.filter(F.col("n") > often), "common")
    least = (many.agg(F.sum("n")).first()[0] or 0) // MOST_OFTEN
    return np.sort(many.filter(F.col("n") > least).select("h").toArrow().column(0).to_numpy().view(np.uint64))


def repeated_grams(runs: DataFrame) -> DataFrame:
    """h of the q-gram hashes, not known to repeat, that occur more than once; counted before the shuffle."""
    return runs.filter("not known").groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("h")


def repeated_runs(runs: DataFrame, grams: DataFrame) -> DataFrame:
    """place of the window runs whose q-gram occurs more than once.

    Runs that are known to repeat need no match and are spread over all tasks; of the others no q-gram has very many.
    """
    spread = F.when(F.col("known"), F.col("place")).otherwise(F.lit(0).cast("long")).alias("spread")
    counted = grams.select("h", F.lit(0).cast("long").alias("spread"), F.lit(True).alias("twice"))
    return runs.select("h", "place", "known", spread).join(counted, ["h", "spread"], "left").filter("known or twice").select("place")


def contexts(texts: DataFrame, repeats: str, depth: int, often: np.ndarray, bits: int = HASH_BITS) -> DataFrame:
    """The repeated runs with their bytes: h, doc, place (of the first window), rel, content.

    A run whose bytes the task met before, earlier in the corpus, has no content but its number of windows as ``rel``, its
    place as ``h`` and zeros elsewhere: all its windows are marked.
    """

    @released
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = PartMarks(repeats, ["place"])
        met: dict[tuple, tuple] = {}
        for batch in sliced(batches, 0):
            data, first, last = _texts(batch.column(0))
            h, start, count, rel = window_runs(data, first, last, depth, often)
            places, docs = batch.column(1).to_numpy(), batch.column(2).to_numpy()
            owner = np.searchsorted(first, start, "right") - 1
            at = start - first[owner]
            place = places[owner] + at
            part = place >> SHIFT
            for p in np.unique(part):
                mine = np.flatnonzero(part == p)
                (marked,) = wanted.of(int(p))
                if not len(marked):
                    continue
                local = place[mine] & ((1 << SHIFT) - 1)
                spot = np.minimum(np.searchsorted(marked, local), len(marked) - 1)
                chosen = mine[marked[spot] == local]
                for low in range(0, len(chosen), CHUNK):
                    k = chosen[low : low + CHUNK]
                    new = np.ones(len(k), bool)
                    lines = zip(h[k].tolist(), rel[k].tolist(), start[k].tolist(), (start[k] + count[k] + depth - 1).tolist(), docs[owner[k]].tolist(), at[k].tolist(), strict=True)
                    for i, (gram, lead, x, y, doc, spot_) in enumerate(lines):
                        key = (gram, lead, data[x:y].tobytes())
                        before = met.get(key)
                        if before is not None and before < (doc, spot_):
                            new[i] = False
                        else:
                            if len(met) >= MEMO:
                                met.clear()
                            met[key] = (doc, spot_)
                    yield _context_rows(k[new], data, sent(h, bits), docs[owner], place, rel, start, count, depth)
                    known = k[~new]
                    if len(known):
                        empty, zeros = pa.nulls(len(known), pa.binary()), pa.array(np.zeros(len(known), np.int64))
                        yield pa.record_batch([pa.array(place[known]), zeros, zeros, pa.array(count[known].astype(np.int32)), empty], names=CONTEXT)

    return texts.select("text", "place", "doc").mapInArrow(cut, "h long, doc long, place long, rel int, content binary")


CONTEXT = ["h", "doc", "place", "rel", "content"]


def _context_rows(k: np.ndarray, data: np.ndarray, h: np.ndarray, doc: np.ndarray, place: np.ndarray, rel: np.ndarray, start: np.ndarray, count: np.ndarray, depth: int) -> pa.RecordBatch:
    """Runs ``k`` with the bytes of all their windows."""
    size = count[k] + depth - 1
    ends = np.cumsum(size)
    index = np.arange(ends[-1] if len(k) else 0) + np.repeat(start[k] - (ends - size), size)
    offsets = np.append(0, ends).astype(np.int32)
    content = pa.Array.from_buffers(pa.binary(), len(k), [None, pa.py_buffer(offsets), pa.py_buffer(data[index])])
    return pa.record_batch([pa.array(h[k]), pa.array(doc[k]), pa.array(place[k]), pa.array(rel[k].astype(np.int32)), content], names=CONTEXT)


def refine_buckets(bucket: np.ndarray, pieces: np.ndarray) -> np.ndarray:
    """Order of rows by their bucket and then by their pieces, by bucket-pointer refinement.

    Every piece of a row starts a suffix of the row. The pointer of a suffix names its bucket by the place of the bucket's
    first member among all suffixes; at first, suffixes with equal first pieces share a bucket. A round sorts the members
    of buckets that hold more than one on the pointers of the suffixes ``step`` pieces later, and writes the pointers of
    the smaller buckets at once. The next round reads those, at twice the distance, so pointers that stand for ever more
    pieces are reused instead of pieces being looked at again. Only suffixes that a later round reads are refined.
    """
    width = pieces.shape[1]
    _, kind, often = np.unique(pieces, return_inverse=True, return_counts=True)
    pointer = (np.cumsum(often) - often)[kind].reshape(pieces.shape)
    step = 1
    while step < width:
        here = np.arange(0, width, 2 * step)
        own = pointer[:, here]
        later = np.full(own.shape, -1)
        inside = here + step < width
        later[:, inside] = pointer[:, here[inside] + step]
        own, later = own.reshape(-1), later.reshape(-1)
        open_ = np.flatnonzero(np.bincount(own)[own] > 1) if len(own) else own
        if not len(open_):
            step *= 2
            continue
        turn = open_[np.lexsort((later[open_], own[open_]))]
        a, b = own[turn], later[turn]
        first = np.append(True, a[1:] != a[:-1])
        smaller = np.append(True, first[1:] | (b[1:] != b[:-1]))
        place = np.arange(len(turn))
        own[turn] = a + np.maximum.accumulate(np.where(smaller, place, 0)) - np.maximum.accumulate(np.where(first, place, 0))
        pointer[:, here] = own.reshape(len(pieces), len(here))
        step *= 2
    return np.lexsort((pointer[:, 0], bucket))


def suffix_classes(bucket: np.ndarray, text: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted order of byte rows within buckets, and each one's common prefix with the row before it (-1 at a new bucket).

    ``text``: rows of bytes, a multiple of 8 wide, zero beyond ``sizes``.
    """
    pieces = np.ascontiguousarray(text).view(">u8").astype(np.uint64)
    order = refine_buckets(bucket, pieces)
    a, b = text[order[1:]], text[order[:-1]]
    differ = a != b
    common = np.where(differ.any(1), differ.argmax(1), text.shape[1])
    common = np.minimum(common, np.minimum(sizes[order[1:]], sizes[order[:-1]]))
    common[bucket[order[1:]] != bucket[order[:-1]]] = -1
    return order, np.append(-1, common)


def repeated_windows(h: np.ndarray, rel: np.ndarray, offsets: np.ndarray, data: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(context, window number) of every window that equals one of an earlier context with the same hash.

    Contexts are given in order of their places. All contexts of a hash must be present.
    """
    m = len(h)
    count = np.diff(offsets) - depth + 1
    gram = offsets[:-1] - rel  # place of the q-gram in data
    width = -(-depth // 8) * 8
    reach = np.arange(width)
    right = offsets[1:] - gram
    left = -rel
    tail = np.append(data, np.zeros(width, np.uint8))
    after = np.where(reach < right[:, None], tail[gram[:, None] + reach], 0).astype(np.uint8)
    wide = max(8, -(-int(left.max(initial=0)) // 8) * 8)
    back = np.arange(1, wide + 1)
    before = np.where(back <= left[:, None], data[np.maximum(gram[:, None] - back, 0)], 0).astype(np.uint8)
    order_r, common_r = suffix_classes(h, after, np.minimum(right, width))
    order_l, common_l = suffix_classes(h, before, left)
    found_c, found_w = [], []
    class_r, class_l = np.zeros(m, np.int64), np.zeros(m, np.int64)
    for lead in range(int((-rel - count + 1).min(initial=0)), int(left.max(initial=-1)) + 1):
        # windows that start ``lead`` bytes before the q-gram
        window = left - lead
        here = np.flatnonzero((window >= 0) & (window < count))
        if len(here) < 2:
            continue
        class_r[order_r] = np.cumsum(common_r < depth - lead)
        class_l[order_l] = np.cumsum(common_l < lead)
        key = (class_r[here] << 32) | class_l[here]
        turn = np.argsort(key, kind="stable")
        same = key[turn][1:] == key[turn][:-1]
        later = here[turn[1:][same]]
        found_c.append(later)
        found_w.append(window[later])
    z = np.zeros(0, np.int64)
    return (np.concatenate(found_c), np.concatenate(found_w)) if found_c else (z, z)


def runs_of(context: np.ndarray, window: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Neighbouring marked windows of a context as (place, number)."""
    if not len(context):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    order = np.lexsort((window, context))
    c, w = context[order], window[order]
    new = np.append(True, (c[1:] != c[:-1]) | (w[1:] != w[:-1] + 1))
    heads = np.flatnonzero(new)
    return place[c[heads]] + w[heads], np.diff(np.append(heads, len(c)))


def marked_windows(cut: DataFrame, depth: int) -> DataFrame:
    """place, n: runs of windows that start earlier too; contexts of a hash are sorted in one task.

    A document lies in one part, so places order its windows.
    """

    @released
    def sort(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def solve(table: pa.Table) -> pa.RecordBatch:
            content = table.column("content").combine_chunks()
            content = pa.concat_arrays(content.chunks) if isinstance(content, pa.ChunkedArray) else content
            offsets = np.frombuffer(content.buffers()[1], np.int32)[content.offset : content.offset + len(content) + 1].astype(np.int64)
            data = np.frombuffer(content.buffers()[2], np.uint8)[offsets[0] : offsets[-1]]
            h, rel, place = (table.column(c).to_numpy() for c in ("h", "rel", "place"))
            c, w = repeated_windows(h, rel.astype(np.int64), offsets - offsets[0], data, depth)
            starts, n = runs_of(c, w, place)
            return pa.record_batch([pa.array(starts), pa.array(n.astype(np.int32))], names=["place", "n"])

        held: list[pa.RecordBatch] = []
        rows = 0
        for batch in batches:
            known = batch.column("content").is_null()
            done = batch.filter(known)
            if done.num_rows:
                yield pa.record_batch([done.column("h"), done.column("rel")], names=["place", "n"])
            batch = batch.filter(pc.invert(known))
            if batch.num_rows:
                held.append(batch)
                rows += batch.num_rows
            if rows < CHUNK:
                continue
            table = pa.Table.from_batches(held)
            h = table.column("h").to_numpy()
            whole = int(np.searchsorted(h, h[-1]))  # rows of all hashes but the last, which may go on
            if whole:
                yield solve(table.slice(0, whole))
            held = table.slice(whole).combine_chunks().to_batches()
            rows = table.num_rows - whole
        if rows:
            yield solve(pa.Table.from_batches(held))

    return cut.repartition("h").sortWithinPartitions("h", "doc", "place").mapInArrow(sort, "place long, n int")


def covered(starts: np.ndarray, counts: np.ndarray, size: int, depth: int) -> np.ndarray:
    """Mask of the bytes that the windows starting at ``starts`` (runs of ``counts``) cover."""
    step = np.zeros(size + 1, np.int32)
    np.add.at(step, starts, 1)
    np.add.at(step, np.minimum(starts + counts - 1 + depth, size), -1)
    return np.cumsum(step[:-1]) > 0


def apply_marks(texts: DataFrame, marks: str, depth: int, keep_text: bool) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and kept, the remaining bytes) of every document."""

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = PartMarks(marks, ["place", "n"])
        for batch in sliced(batches, 1):
            data, first, last = _texts(batch.column(1))
            rows: list[tuple] = []
            for i, place in enumerate(batch.column(2).to_pylist()):
                own = data[first[i] : last[i]]
                starts, counts = wanted.of(place >> SHIFT)
                local = place & ((1 << SHIFT) - 1)
                a, b = np.searchsorted(starts, (local, local + len(own)))
                if a == b:
                    rows.append((len(own), 0, 0, own.tobytes()))
                    continue
                gone = covered(starts[a:b] - local, counts[a:b].astype(np.int64), len(own), depth)
                spans = int(gone[0]) + int(np.count_nonzero(gone[1:] & ~gone[:-1]))
                rows.append((len(own), int(gone.sum()), spans, own[~gone].tobytes()))
            columns = [batch.column(0), *(pa.array([r[k] for r in rows], pa.int64()) for k in range(3)), pa.array([hashlib.sha256(r[3]).hexdigest() for r in rows], pa.string())]
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
            if keep_text:
                columns.append(pa.array([r[3] for r in rows], pa.binary()))
                names.append("kept")
            yield pa.record_batch(columns, names=names)

    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * keep_text
    return texts.select("doc_id", "text", "place").mapInArrow(run, schema)


def remove_repeats(docs: DataFrame, depth: int = 100, often: int = 20_000, keep_text: bool = False, bits: int = HASH_BITS) -> DataFrame:
    """What is removed from every document, one row each; with ``keep_text`` also the bytes that stay.

    ``often`` decides only on which q-gram a window hangs, never which equal windows are found; nor do ``bits``, of the hashes
    that are shuffled.
    """
    if depth < GRAM + 1:
        raise ValueError(f"depth must be over {GRAM}")
    texts = numbered_texts(docs)
    common = common_grams(texts, depth, often)
    runs = run_rows(texts, depth, common, bits)
    repeats = by_part(repeated_runs(runs, repeated_grams(runs)), "repeats")
    marks = by_part(marked_windows(contexts(texts, repeats, depth, common, bits), depth), "marks")
    return apply_marks(texts, marks, depth, keep_text)
