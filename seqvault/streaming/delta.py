"""Streams around an index: new items become shards, paths are watched across batches, hits are counted in windows."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from seqvault.index import Index


class IndexFeed:
    """Each micro-batch of (item_no, seq) is appended to an index in new shards.

    A batch that is replayed after a failure is recognised by its items: those already in the index are left out, so no
    item is indexed twice.
    """

    def __init__(self, index: Index):
        self.index = index

    def take(self, batch: DataFrame, batch_id: int) -> None:
        new = batch.join(self.index.table("items").select("item_no"), "item_no", "left_anti")
        if not new.isEmpty():
            self.index = self.index.append(new)

    def start(self, stream: DataFrame, checkpoint: str) -> StreamingQuery:
        return stream.writeStream.foreachBatch(self.take).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def watch(events: DataFrame, patterns: list[str], key: str = "user_id", letter: str = "x", order: tuple[str, ...] = ("ts", "event_id")) -> DataFrame:
    """user_id, pattern, at: occurrences of patterns in each key's string of letters, across batch borders.

    The state of a key is its number of letters so far and the last ones, one fewer than the longest pattern. Letters of a
    batch are ordered by ``order``; batches follow each other.
    """
    keep = max(map(len, patterns), default=1) - 1

    def run(name: tuple, pdfs: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen, tail = state.get if state.exists else (0, "")
        rows = pd.concat(list(pdfs)).sort_values(list(order))
        text = tail + "".join(rows[letter])
        found = [(name[0], p, seen - len(tail) + i) for p in patterns for i in range(len(text) - len(p) + 1) if i + len(p) > len(tail) and text.startswith(p, i)]
        state.update((seen + len(rows), text[len(text) - min(keep, len(text)) :]))
        yield pd.DataFrame(found, columns=[key, "pattern", "at"])

    schema = f"{key} {events.schema[key].dataType.simpleString()}, pattern string, at long"
    return events.groupBy(key).applyInPandasWithState(run, schema, "seen long, tail string", "append", GroupStateTimeout.NoTimeout)


def windowed_counts(events: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """window, event_type, n over tumbling or sliding windows; rows later than ``late`` behind the newest are dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, slide), "event_type").agg(F.count(F.lit(1)).alias("n"))


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """user_id, session window, n."""
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))


def without_repeats(events: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    """The first row of each key within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def locate_stream(patterns: DataFrame, index: Index, out: str, checkpoint: str) -> StreamingQuery:
    """Patterns that arrive are located in an open index, and their hits appended to a table.

    A batch writes to a folder named by its number and replaces it when it is replayed, so no hit is written twice.
    """

    def take(batch: DataFrame, batch_id: int) -> None:
        index.locate(batch).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    return patterns.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
