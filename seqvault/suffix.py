"""Suffix order of joined collections: in one task with numpy, or over a cluster with joins.

A joined collection ends with a terminator that is smallest and occurs once, so the order of suffixes is the order of
rotations.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seqvault.operators.barrier import barrier
from seqvault.operators.prefix import group_starts, place_by_range


#: Up to this many positions, a key of two ranks and the place of a position are one number, and sorting these takes a
#: quarter of the time of sorting places by their keys.
PACKED = 1 << 21
#: Positions whose last rounds one task makes, in about 100 bytes each.
HELD = 1 << 21


def _sorted_places(key: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Places in the order of their keys, and the keys in order; equal keys stay in place where ``bits``, of a place, is not 0."""
    if not bits:
        turn = np.argsort(key)
        return turn, key[turn]
    packed = key << bits
    packed |= np.arange(len(key))
    packed.sort()
    return packed & ((1 << bits) - 1), packed >> bits


def _refine(order: np.ndarray, head: np.ndarray, rank: np.ndarray, step: int) -> None:
    """Split groups of equal rank by the rank ``step`` symbols later, doubling the step until all are alone.

    A round touches only the positions that are not alone yet.
    """
    n = len(order)
    bits = (n - 1).bit_length() if n <= PACKED else 0
    mine = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    open_ = np.flatnonzero(np.bincount(mine, minlength=n)[mine] > 1)
    members, mine = order[open_], mine[open_]
    while len(open_):
        at = members + step % n
        at[at >= n] -= n
        turn, pair = _sorted_places(mine * n + rank[at], bits)  # below 2^42, or with no place in it below 2^62
        order[open_] = members = members[turn]
        heads = np.flatnonzero(np.append(True, pair[1:] != pair[:-1]))
        size = np.diff(np.append(heads, len(pair)))
        rank[members] = mine = np.repeat(open_[heads], size)
        still = np.repeat(size > 1, size)
        open_, members, mine = open_[still], members[still], mine[still]
        step *= 2


def suffix_order_kernel(text: np.ndarray, size: int | None = None) -> np.ndarray:
    """Start positions in the order of their suffixes, by prefix doubling that leaves resolved positions alone.

    The first round sorts as many symbols, numbered among those in use, as fit in 62 bits beside a position.
    """
    n = len(text)
    place = (n - 1).bit_length() if n <= PACKED else 0
    used = np.zeros(max(size or 0, int(text.max(initial=0)) + 1), np.int64)
    used[text] = 1
    number = np.cumsum(used) - 1
    bits = max(1, int(number[-1]).bit_length())
    width = max(1, min((62 - place) // bits, n))
    dense, key = number[text], np.zeros(n, np.int64)
    for i in range(width):
        key = (key << bits) | np.roll(dense, -i)
    order, sorted_key = _sorted_places(key, place)  # equal keys are told apart later
    head = np.append(True, sorted_key[1:] != sorted_key[:-1])
    rank = np.zeros(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    _refine(order, head, rank, width)
    return order


def run_keys(text: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For every position: symbols left in its run, the symbol after the run, and a key that orders equal symbols.

    Before a smaller symbol, a shorter run is smaller; before a larger symbol, a longer one is. All runs before smaller
    symbols come first.
    """
    n = len(text)
    ends = np.append(np.flatnonzero(text[1:] != text[:-1]), n - 1)
    end = ends[np.searchsorted(ends, np.arange(n))]
    left = end - np.arange(n) + 1
    after = text[(end + 1) % n]
    return left, after, np.where(after < text, left, 2 * n - left)


def suffix_order_runs(text: np.ndarray, size: int) -> np.ndarray:
    """As :func:`suffix_order_kernel`, but long repetitions of a symbol are first split by run length and next symbol."""
    n = len(text)
    left, after, place = run_keys(text)
    order = np.lexsort((after, place, text))
    same = (text[order][1:] == text[order][:-1]) & (place[order][1:] == place[order][:-1]) & (after[order][1:] == after[order][:-1])
    head = np.append(True, ~same)
    rank = np.zeros(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    _refine(order, head, rank, 1)
    return order


def suffix_order_ranges(text: np.ndarray, size: int, cuts: np.ndarray) -> np.ndarray:
    """Sort each range of first symbols on its own and concatenate; ``cuts``: first symbol of every range.

    A range is sorted on packed symbols, widened for the positions still tied until all are alone.
    """
    n = len(text)
    bits = max(1, int(size).bit_length())
    width = max(1, 62 // bits)
    bucket = np.searchsorted(cuts, text, "right") - 1
    out = []
    for b in range(len(cuts)):
        order = np.flatnonzero(bucket == b)
        if not len(order):
            continue
        head = np.append(True, np.zeros(len(order) - 1, bool))
        depth = 0
        while depth < n:
            group = np.cumsum(head) - 1
            open_ = np.flatnonzero(np.bincount(group)[group] > 1)
            if not len(open_):
                break
            members, mine = order[open_], group[open_]
            key = np.zeros(len(members), np.int64)
            for i in range(width):
                key = (key << bits) | text[(members + depth + i) % n]
            turn = np.lexsort((key, mine))
            order[open_], key, mine = members[turn], key[turn], mine[turn]
            head[open_] = np.append(True, (mine[1:] != mine[:-1]) | (key[1:] != key[:-1]))
            depth += width
        out.append(order)
    return np.concatenate(out)


def suffix_order_bruteforce(symbols: DataFrame) -> DataFrame:
    """(shard, row, pos, sym) by sorting all rotations as arrays; quadratic, for tests and small oracles."""
    whole = symbols.groupBy("shard").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "sym"))), lambda s: s["sym"]).alias("text"))
    rows = whole.select("shard", "text", F.posexplode("text").alias("pos", "_"))
    turned = F.concat(F.slice("text", F.col("pos") + 1, F.size("text")), F.slice("text", 1, F.col("pos")))
    before = F.get("text", F.pmod(F.col("pos") - 1, F.size("text")))
    rank = Window.partitionBy("shard").orderBy("rotation")
    keyed = rows.select("shard", F.col("pos").cast("long").alias("pos"), turned.alias("rotation"), before.cast("long").alias("sym"))
    return keyed.select("shard", (F.row_number().over(rank) - 1).cast("long").alias("row"), "pos", "sym")


def suffix_order_doubling(symbols: DataFrame) -> DataFrame:
    """(shard, row, pos, sym) over a cluster, for shards that no task can hold: ranks by symbols, doubled until all differ."""
    return resolved(symbols, ranked(symbols.select("shard", "pos", F.col("sym").cast("long").alias("sym")), ["shard", "sym"]), 1)


def ranked(rows: DataFrame, keys: list[str]) -> DataFrame:
    """shard, pos, rank (in the shard, of the first row with equal ``keys``), same (rows with equal keys), written.

    Ranks come from exact counts over range partitions, whose order ends with the position: rows with equal keys, however
    many, are spread over partitions.
    """
    order = [*keys, "pos"]
    placed = place_by_range(rows, order, "ranks")
    starts = group_starts(group_starts(placed, keys, order, "first", "same"), ["shard"], order, "base", "_n")
    return barrier(starts.select("shard", "pos", (F.col("first") - F.col("base")).alias("rank"), "same"), "ranks")


def resolved(symbols: DataFrame, state: DataFrame, h: int, held: int = 0) -> DataFrame:
    """(shard, row, pos, sym) from ranks by the first ``h`` symbols.

    Each round joins the rank ``h`` positions later, for positions whose rank is shared only, and ranks them within their
    group. A position whose rank is its own, and that none asks for in a round, is asked for in no later one and leaves the
    rounds: they go on over what is shared and what that looks at. Each is written, so no round is evaluated twice; all ranks
    differ when ``h`` passes the longest repetition. ``held``: from so many positions on, a task goes through the other rounds.
    """
    sizes = F.broadcast(barrier(symbols.groupBy("shard").agg(F.count(F.lit(1)).alias("n")), "sizes"))  # one row a shard
    alone: list[DataFrame] = []
    while not state.filter("same > 1").isEmpty():
        if held and state.count() <= held:
            state = barrier(_finished(state.join(sizes, "shard"), h), "finished")
            break
        shared = state.filter("same > 1").join(sizes, "shard")
        asks = shared.select("shard", F.col("pos").alias("asker"), F.col("rank").alias("group"), F.pmod(F.col("pos") + h, F.col("n")).alias("pos"))
        met = barrier(state.join(asks, ["shard", "pos"], "left").select("shard", "pos", "rank", "same", "asker", "group"), "met")
        alone.append(met.filter("same = 1 and asker is null").select("shard", "pos", "rank"))
        keyed = met.filter("asker is not null").select("shard", F.col("group").alias("rank"), F.col("rank").alias("later"), F.col("asker").alias("pos"))
        order = ["shard", "rank", "later", "pos"]
        placed = place_by_range(keyed, order, "rounds")
        starts = group_starts(group_starts(placed, order[:3], order, "first", "same"), order[:2], order, "group", "_n")
        moved = starts.select("shard", "pos", (F.col("rank") + F.col("first") - F.col("group")).alias("rank"), "same")
        state = barrier(met.filter("same = 1 and asker is not null").select("shard", "pos", "rank", "same").unionByName(moved), "ranks")
        h *= 2
    ranks = state.select("shard", "pos", "rank")
    for part in alone:
        ranks = ranks.unionByName(part)
    before = symbols.join(sizes, "shard").select("shard", F.pmod(F.col("pos") + 1, F.col("n")).alias("pos"), F.col("sym").cast("long").alias("sym"))
    return ranks.select("shard", F.col("rank").alias("row"), "pos").join(before, ["shard", "pos"]).select("shard", "row", "pos", "sym")


def _finished(state: DataFrame, h: int) -> DataFrame:
    """shard, pos, rank of a state (with the size ``n`` of each shard) whose last rounds one task makes."""

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by([("shard", "ascending"), ("pos", "ascending")])
        shard, pos, n = (table[c].to_numpy() for c in ("shard", "pos", "n"))
        rank = table["rank"].to_numpy().copy()
        cuts = np.flatnonzero(np.diff(shard, prepend=shard[0] - 1)).tolist()
        for low, high in zip(cuts, [*cuts[1:], len(shard)], strict=True):
            finish_ranks(pos[low:high], rank[low:high], int(n[low]), h)
        return pa.table({"shard": table["shard"], "pos": table["pos"], "rank": rank})

    return state.select("shard", "pos", "rank", "n", F.lit(0).alias("all")).groupBy("all").applyInArrow(run, "shard int, pos long, rank long")


def finish_ranks(pos: np.ndarray, rank: np.ndarray, n: int, h: int) -> None:
    """Make ranks by the first ``h`` of ``n`` symbols differ, in place: at ascending positions, which are all that rounds ask for."""
    turn = np.argsort(rank, kind="stable")
    ordered = rank[turn]
    same = ordered[1:] == ordered[:-1]
    shared = turn[np.append(same, False) | np.append(False, same)]
    while len(shared):
        later = rank[np.searchsorted(pos, (pos[shared] + h) % n)]
        turn = np.lexsort((later, rank[shared]))
        shared, later = shared[turn], later[turn]
        group = rank[shared]
        other = np.append(True, group[1:] != group[:-1])
        head = other | np.append(True, later[1:] != later[:-1])
        at = np.arange(len(shared))
        rank[shared] = group + np.maximum.accumulate(np.where(head, at, 0)) - np.maximum.accumulate(np.where(other, at, 0))
        size = np.diff(np.append(np.flatnonzero(head), len(shared)))
        shared = shared[np.repeat(size > 1, size)]
        h *= 2
