"""Long items cut into pieces, so that no task and no row of a plan holds a whole one.

A piece repeats the first letters of the next one, so that a pattern up to one letter longer than that lies whole in the
piece in which it begins. Pieces of equal place in their items are kept together: similar items share a shard stretch by
stretch. A piece is a row of an index under a number that holds its place and its item.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bits of the item in the number of a piece; the place stands above them.
ITEM_BITS = 40
#: Letters of pieces that a worker sends together.
LETTERS = 1 << 22
#: Number of a piece, its name, where the row begins in the item, letters.
PIECES = pa.schema([("item_no", pa.int64()), ("seq_id", pa.string()), ("start", pa.int64()), ("seq", pa.string())])


def cut_items(items: DataFrame, size: int, overlap: int, shard_letters: int) -> DataFrame:
    """shard, pieces: the pieces of (item_no, seq_id, seq), several of a shard in a row as :func:`joined` opens them.

    Items may come in parts (with ``start``, where a part begins in its item); a piece is then in as many rows as parts that
    it has letters of, which :func:`joined` puts together. A shard holds the pieces of one place, of as many items as fit
    ``shard_letters``; nothing is summed or sorted for it. Pieces of a shard that a task meets one after another are
    compressed together before they are sent: of similar items, each takes little more than its differences.
    """
    parts = items if "start" in items.columns else items.withColumn("start", F.lit(0).cast("long"))
    facts = items.agg(F.count_distinct("item_no"), F.min("item_no"), F.max("item_no")).first()
    if facts[0] and not 0 <= facts[1] <= facts[2] < 1 << ITEM_BITS:
        raise ValueError(f"items that are cut into pieces have numbers from 0 to 2^{ITEM_BITS} - 1")
    groups = max(1, -(-facts[0] * size // shard_letters))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple]] = {}
        letters = 0
        for batch in batches:
            for i in range(batch.num_rows):
                number, name, start, seq = (c[i].as_py() for c in batch.columns)
                for place in range(max(0, (start - overlap) // size), max(1, -(-(start + len(seq)) // size))):
                    begin = max(place * size, start)
                    text = seq[begin - start : max(0, place * size + size + overlap - start)]
                    if text or not begin:
                        held.setdefault(place * groups + number % groups, []).append(((place << ITEM_BITS) + number, f"{name}:{place}", begin, text))
                        letters += len(text)
                    if letters >= LETTERS:
                        yield _sent(held)
                        held, letters = {}, 0
        if held:
            yield _sent(held)

    # few bytes, but work for many tasks: a number of partitions that is named is not lowered by their size
    tasks = int(items.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return parts.select("item_no", "seq_id", "start", "seq").mapInArrow(run, "shard int, pieces binary").repartition(tasks, "shard")


def _sent(held: dict[int, list[tuple]]) -> pa.RecordBatch:
    """A row for each shard, with its pieces as a compressed stream of Arrow."""
    packed = []
    for rows in held.values():
        sink = pa.BufferOutputStream()
        table = pa.table([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), PIECES, strict=True)], schema=PIECES)
        with pa.ipc.new_stream(sink, PIECES, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
            out.write_table(table)
        packed.append(sink.getvalue().to_pybytes())
    return pa.record_batch([pa.array(list(held), pa.int32()), pa.array(packed, pa.binary())], names=["shard", "pieces"])


def joined(table: pa.Table) -> tuple[list[int], list[str], list[str]]:
    """Numbers, names and texts of the rows of a shard in ascending order, those that came in parts put together."""
    if "pieces" not in table.column_names:
        table = table.sort_by("item_no")
        return table["item_no"].to_pylist(), table["seq_id"].to_pylist(), table["seq"].to_pylist()
    table = pa.concat_tables([pa.ipc.open_stream(row.as_buffer()).read_all() for row in table["pieces"]])
    table = table.sort_by([("item_no", "ascending"), ("start", "ascending")])
    number, names, parts = table["item_no"].to_numpy(), table["seq_id"].to_pylist(), table["seq"].to_pylist()
    heads = np.flatnonzero(np.append(True, number[1:] != number[:-1])[: len(number)]).tolist()
    spans = list(zip(heads, [*heads[1:], len(number)], strict=True))
    return number[heads].tolist(), [names[a] for a in heads], ["".join(parts[a:b]) for a, b in spans]


def whole_hits(number: np.ndarray, offset: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of hits in pieces: which count (one that begins in the repeated letters is a hit of the next piece too), and item and
    offset in it of those."""
    mine = offset < size
    number, offset = number[mine], offset[mine]
    return mine, number & ((1 << ITEM_BITS) - 1), offset + (number >> ITEM_BITS) * size


def check_patterns(patterns: DataFrame, overlap: int) -> None:
    """A longer pattern could cross two pieces unseen."""
    longest = patterns.agg(F.max(F.length("pattern"))).first()[0] or 0
    if longest > overlap + 1:
        raise ValueError(f"a pattern has {longest} letters; these pieces answer up to {overlap + 1}")
