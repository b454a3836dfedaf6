"""Near duplicates by SimHash and a binary-trie self-join.

Equal fingerprints are one entry. The trie over the entries is joined with itself: a pair of nodes carries the number of
bits in which their paths differ and splits into its pairs of children; a pair over the error budget is dropped, and so is
a pair whose keys are all in one component already. The first levels are walked by arithmetic: an entry goes to every pair
of top nodes that it belongs to and whose paths differ in at most ``radius`` bits; each such pair is a group of its own,
whose subtries are joined level by level over numpy arrays. A group returns a spanning forest of its links, never all
pairs; components are then joined across groups.

:func:`one_of_each` uses the join for candidates: documents within the radius in any of several fingerprints over their
distinct words, which an edit changes least. The hashes are mixed anew for each fingerprint. The sets of five-word shingles of each group
of candidates are compared exactly, and only links of similarity 0.8 and over form components. A group is compared in one
task while its shingles fit there. A larger one is first compared with some of its documents, each a row that is joined to
all others; what is no copy of the first of these is then compared with the whole group, block by block, so no group is
gathered and no link within a group is left out, also none between copies of two of these.

Null or empty text: fingerprint zero, linked like any other. Rows with equal ids are fingerprinted each and share the
component of any of them. Null ids take part and are never the smallest. Empty table: empty result. Other columns are
not read.
"""

from __future__ import annotations

import string
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.llm.graph import Forest, connected_components
from seqvault.llm.keys import ROW, unpacked, with_row_key
from seqvault.llm.workers import release, released
from seqvault.operators.barrier import barrier

LOWER = bytes.maketrans(string.ascii_uppercase.encode(), string.ascii_lowercase.encode())
#: Rows of ids that may be sent to every task; beyond that the join is shuffled.
SMALL = 200_000
#: Entries per top node aimed at: the first until the join starts ``FIRST`` bits deep, then the second.
PER_NODE, MOST_PER_NODE, FIRST = 1 << 14, 1 << 20, 4
#: Pairs of nodes walked at once in a task; more are put aside and walked later.
PAIRS = 40_000
#: Shingles of a group of candidates that one task compares (8 bytes each); larger groups are compared block by block.
SHINGLES = 2_000_000
#: Rounds in which large groups are compared with one of their documents, and parts that such a group is dealt into.
LEADERS, PARTS = 4, 32


def shingle_hashes(text: str | None, words: int) -> np.ndarray:
    """XXH64 (seed 42) of each run of ``words`` words of a lower-cased text, repeats included; of all words if fewer."""
    parts = (text or "").encode("utf-8", "replace").translate(LOWER).split()
    if not parts:
        return np.zeros(0, np.uint64)
    if len(parts) < words:
        runs = [b" ".join(parts)]
    else:
        runs = map(b" ".join, zip(*(parts[i:] for i in range(words)), strict=False))
    digest = xxhash.xxh64_intdigest
    return np.array([digest(r, 42) for r in runs], np.uint64)


def word_run_hashes(text: str | None, *words: int) -> list[np.ndarray]:
    """For each number of words, hashes of all runs of so many words of a lower-cased text (of all words if fewer).

    Words are hashed once each and runs are combined from them.
    """
    parts = (text or "").encode("utf-8", "replace").translate(LOWER).split()
    digest = xxhash.xxh64_intdigest
    known = {w: digest(w, 42) for w in set(parts)}
    single = np.fromiter(map(known.__getitem__, parts), np.uint64, len(parts))
    out = []
    for k in words:
        k = min(k, len(single))
        runs = np.zeros(len(single) - k + 1 if k else 0, np.uint64)
        for j in range(k):
            runs = (runs ^ single[j : j + len(runs)]) * np.uint64(0x9E3779B97F4A7C15)
            runs ^= runs >> np.uint64(32)
        out.append(runs)
    return out


def fingerprints_of(hashes: np.ndarray, seeds: int) -> np.ndarray:
    """One fingerprint per seed; a bit is set if it is set in over half the hashes, and all are 0 without any.

    Seed 0 takes the hashes as they are, the others mix them.
    """
    n = len(hashes)
    if not n:
        return np.zeros(seeds, np.uint64)
    turns = np.arange(seeds, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    ones = np.zeros(seeds * 64, np.int64)
    for low in range(0, n, 255):  # so many bits add up in a byte
        part = hashes[low : low + 255]
        block = part[:, None] ^ turns
        if seeds > 1:
            block = (block ^ (block >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            block = (block ^ (block >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            block ^= block >> np.uint64(31)
            block[:, 0] = part
        bits = np.unpackbits(block.astype("<u8").view(np.uint8), axis=1, bitorder="little")
        ones += np.add.reduce(bits, axis=0, dtype=np.uint8)
    return np.packbits(ones * 2 > n, bitorder="little").view("<u8").astype(np.uint64)


def set_digest(hashes: np.ndarray) -> int:
    """Equal for equal sets of sorted distinct hashes."""
    return xxhash.xxh64_intdigest(hashes.tobytes(), 42)


def set_fingerprints(docs: DataFrame, words: int, seeds: int, exact_words: int) -> DataFrame:
    """row, same (digest of the set of shingles of ``exact_words``), n (its size), fps (over distinct shingles of ``words``)."""

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found, same, sizes = [], [], []
            for text in batch.column(1):
                short, exact = map(np.unique, word_run_hashes(text.as_py(), words, exact_words))
                found.append(fingerprints_of(short, seeds))
                same.append(set_digest(exact))
                sizes.append(len(exact))
            flat = pa.array(np.concatenate(found).view(np.int64) if found else np.zeros(0, np.int64))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(found) + 1, dtype=np.int32) * seeds), flat)
            yield pa.record_batch([batch.column(0), pa.array(np.array(same, np.uint64).view(np.int64)), pa.array(sizes, pa.int64()), lists], names=["row", "same", "n", "fps"])

    return docs.select(F.col(ROW).cast("long").alias("row"), "text").mapInArrow(run, "row long, same long, n long, fps array<long>")


def fingerprints(docs: DataFrame, words: int = 3, seeds: int = 1, id_col: str = "doc_id") -> DataFrame:
    """doc_id and fps (the fingerprints as signed BIGINTs) of every row; one narrow pass."""

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [fingerprints_of(shingle_hashes(t.as_py(), words), seeds) for t in batch.column(1)]
            flat = pa.array(np.concatenate(found).view(np.int64) if found else np.zeros(0, np.int64))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(found) + 1, dtype=np.int32) * seeds), flat)
            yield pa.record_batch([batch.column(0), lists], names=["doc_id", "fps"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, fps array<long>")


def trie_pairs(keys: np.ndarray, roots: np.ndarray, depth: int, radius: int, settled: Callable[[np.ndarray], np.ndarray] | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Lots of pairs of positions in ``keys`` (sorted, distinct, unsigned) within ``radius`` bits, below pairs of nodes.

    ``roots``: rows (path, path) of nodes at ``depth``. Nodes are intervals of ``keys``; a level splits each at the first
    key with the next bit set. A pair of single keys, or at the last level, is decided at once. Pairs of intervals for
    which ``settled`` holds are not walked.
    """
    shift = np.uint64(64 - depth)
    edge = lambda paths: np.searchsorted(keys, paths << shift if depth else paths * 0)
    if depth:
        top = np.uint64((1 << depth) - 1)
        ends = lambda paths: np.where(paths == top, len(keys), np.searchsorted(keys, (paths + np.uint64(1)) << shift))
    else:
        ends = lambda paths: np.full(len(paths), len(keys))
    a, b = roots[:, 0].astype(np.uint64), roots[:, 1].astype(np.uint64)
    aside = [(depth, np.stack([edge(a), ends(a), edge(b), ends(b), np.bitwise_count(a ^ b).astype(np.int64)]).astype(np.int32))]
    while aside:
        level, pairs = aside.pop()
        pairs = pairs[:, (pairs[0] < pairs[1]) & (pairs[2] < pairs[3]) & (pairs[4] <= radius)]
        if settled is not None and pairs.shape[1]:
            alone = (pairs[0] == pairs[2]) & (pairs[1] - pairs[0] == 1)
            pairs = pairs[:, ~settled(pairs) & ~alone]
        single = (pairs[1] - pairs[0] == 1) & (pairs[3] - pairs[2] == 1)
        if single.any():
            i, j = pairs[0, single], pairs[2, single]
            near = (i != j) & (np.bitwise_count(keys[i] ^ keys[j]) <= radius)
            if near.any():
                yield i[near], j[near]
            pairs = pairs[:, ~single]
        n = pairs.shape[1]
        if level == 64 or not n:
            continue
        if n > PAIRS:
            aside += [(level, pairs[:, low : low + PAIRS]) for low in range(0, n, PAIRS)]
            continue
        bit = np.uint64(1 << (63 - level))
        firsts = np.concatenate([pairs[0], pairs[2]])
        lasts = np.concatenate([pairs[1], pairs[3]])
        # the path of a node with the next bit set gives the value that splits it
        path = keys[firsts] & ~np.uint64((1 << (64 - level)) - 1) if level else np.zeros(len(firsts), np.uint64)
        cuts = np.clip(np.searchsorted(keys, path | bit), firsts, lasts).astype(np.int32)
        al, am, ah, bl, bm, bh, err = pairs[0], cuts[:n], pairs[1], pairs[2], cuts[n:], pairs[3], pairs[4]
        twice = al == bl
        # what is put last is walked first: children with equal bits are the closest
        children = [
            np.stack([al, am, bm, bh, err + 1]),
            np.stack([am, ah, bl, bm, err + 1])[:, ~twice],
            np.stack([al, am, bl, bm, err]),
            np.stack([am, ah, bm, bh, err]),
        ]
        aside.append((level + 1, np.concatenate(children, axis=1)))


def neighbour_masks(depth: int, radius: int) -> list[int]:
    """All differences of two top paths with at most ``radius`` bits set, 0 first."""
    masks = {0}
    for _ in range(radius):
        masks |= {m ^ (1 << i) for m in masks for i in range(depth)}
    return sorted(masks)


def start_depth(n: int, seeds: int) -> int:
    """Levels walked by arithmetic: a few while nodes are small, as each level adds to what an entry is sent to."""
    return max(min(FIRST, (n // (PER_NODE * seeds)).bit_length()), (n // MOST_PER_NODE).bit_length())


def fingerprint_links(entries: DataFrame, radius: int, n: int, seeds: int = 1) -> DataFrame:
    """Edges ``a``, ``b`` between nodes that span all links within ``radius`` bits.

    ``entries``: seed, fp, node; ``n``: how many have one seed. A node links with those of its own seed only.
    """
    depth = start_depth(n, seeds)
    path = F.shiftrightunsigned("fp", 64 - depth) if depth else F.lit(0).cast("long")
    other = F.explode(F.array(*[F.lit(m).cast("long") for m in neighbour_masks(depth, radius)]))
    spread = entries.select("seed", "fp", "node", path.alias("p"), other.alias("mask"))
    met = F.col("p").bitwiseXOR(F.col("mask"))
    sent = spread.select("seed", F.least("p", met).alias("p"), F.greatest("p", met).alias("q"), "fp", "node")

    def join(table: pa.Table) -> pa.Table:
        p, q, fp, node = (table.column(c).to_numpy() for c in ("p", "q", "fp", "node"))
        keys, spot = np.unique(fp.view(np.uint64), return_inverse=True)
        # nodes with equal fingerprints hang on the smallest of them
        first = np.full(len(keys), np.iinfo(np.int64).max)
        np.minimum.at(first, spot, node)
        more = node != first[spot]
        forest = Forest(len(keys))
        for i, j in trie_pairs(keys, np.array([[p[0], q[0]]]), depth, radius, forest.whole):
            forest.merge(i, j)
        label = forest.label
        linked = np.flatnonzero(label != np.arange(len(keys)))
        a = np.concatenate([node[more], first[linked]])
        b = np.concatenate([first[spot[more]], first[label[linked]]])
        del table, p, q, fp, node, keys, spot
        release()
        return pa.table({"a": a, "b": b})

    # few bytes, but work for many tasks: a number of partitions that is named is not lowered by their size
    parts = int(entries.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return sent.repartition(parts, "seed", "p", "q").groupBy("seed", "p", "q").applyInArrow(join, "a long, b long")


def near_duplicates(docs: DataFrame, words: int = 3, radius: int = 2) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable by links) of every row."""
    marked = barrier(fingerprints(docs, words), "fingerprints")
    return components_of(marked, radius).select("doc_id", F.lower(F.lpad(F.hex(F.get("fps", F.lit(0))), 16, "0")).alias("fingerprint"), "component_id")


def components_of(marked: DataFrame, radius: int, seeds: int = 1) -> DataFrame:
    """``marked`` (doc_id, fps) with component_id. Rows with equal fingerprints are one node."""
    node = F.when(F.size("fps") == 1, F.get("fps", F.lit(0))).otherwise(F.coalesce("least", F.xxhash64("fps")))
    entries = barrier(marked.groupBy("fps").agg(F.min("doc_id").alias("least")).withColumn("node", node), "entries")
    single = entries.select("node", F.posexplode("fps").alias("seed", "fp")).select(F.col("seed").cast("long").alias("seed"), "fp", "node")
    groups = connected_components(fingerprint_links(single, radius, entries.count(), seeds)).withColumnRenamed("component", "root")
    rooted = entries.join(groups, "node", "left").select("fps", "least", F.coalesce("root", "node").alias("root"))
    lowest = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    named = barrier(rooted.join(lowest, "root").select("fps", "component_id"), "named")
    # ids that stand on several rows join their components; ids are unique in most tables, and then nothing is done
    result = marked.join(named, "fps")
    shared = result.filter("doc_id is not null").groupBy("doc_id").agg(F.min("component_id").alias("a"), F.max("component_id").alias("b")).filter("a <> b").select("a", "b")
    if shared.isEmpty():
        return result
    merged = connected_components(shared).withColumnRenamed("node", "component_id")
    return result.join(merged, "component_id", "left").withColumn("component_id", F.coalesce("component", "component_id")).drop("component")


def similar_components(sets: list[np.ndarray]) -> np.ndarray:
    """The smallest position of each set's component, for links of Jaccard similarity 0.8 and over; exact.

    ``sets``: sorted distinct hashes. Linked sets share one of their rarest hashes, so many that 0.8 cannot be reached
    without them; only sets below such a hash are compared. The search goes on from each set that was found, and a set in
    a component is compared no more, so a group of copies is not compared pair by pair.
    """
    n = len(sets)
    label = np.full(n, -1)
    sizes = np.array([len(x) for x in sets], np.int64)
    ends = np.cumsum(sizes)
    _, token, often = np.unique(np.concatenate([np.zeros(0, np.uint64), *sets]), return_inverse=True, return_counts=True)
    rank = np.empty(len(often), np.int64)
    rank[np.argsort(often, kind="stable")] = np.arange(len(often))
    rows = [np.sort(rank[token[e - k : e]]) for e, k in zip(ends, sizes, strict=True)]
    first = [r[: len(r) - -(-4 * len(r) // 5) + 1] for r in rows]  # all of an empty set
    owner = np.repeat(np.arange(n), [len(f) for f in first])
    below = np.concatenate([np.zeros(0, np.int64), *first])
    turn = np.argsort(below, kind="stable")
    below, owner = below[turn], owner[turn]
    mark = np.zeros(len(often), bool)
    left = held = n
    for start in range(n):
        if label[start] >= 0:
            continue
        label[start] = start
        left -= 1
        queue = [start]
        while queue and left:
            x = queue.pop()
            if left * 2 < held:
                stay = label[owner] < 0
                below, owner, held = below[stay], owner[stay], left
            low, high = np.searchsorted(below, first[x], "left"), np.searchsorted(below, first[x], "right")
            near = [owner[a:b] for a, b in zip(low, high, strict=True) if b > a]
            if not near:
                continue
            near = np.unique(np.concatenate(near))
            near = near[label[near] < 0]
            near = near[5 * np.minimum(sizes[near], sizes[x]) >= 4 * np.maximum(sizes[near], sizes[x])]
            mark[rows[x]] = True
            for y in near.tolist():
                if 9 * int(np.count_nonzero(mark[rows[y]])) >= 4 * int(sizes[x] + sizes[y]):
                    label[y] = start
                    left -= 1
                    queue.append(y)
            mark[rows[x]] = False
    return label


def candidate_sets(members: DataFrame, words: int) -> DataFrame:
    """root, node, row, hashes (the set of shingles) of every member: root, node, row, text."""

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [np.unique(word_run_hashes(t.as_py(), words)[0]).view(np.int64) for t in batch.column(3)]
            yield pa.record_batch([*batch.columns[:3], pa.array(sets, pa.list_(pa.int64()))], names=["root", "node", "row", "hashes"])

    return members.select("root", "node", "row", "text").mapInArrow(run, "root long, node long, row long, hashes array<long>")


def small_group_links(members: DataFrame, words: int) -> DataFrame:
    """a, b: spanning links of the members (root, node, row, text) of each root, one root after another in a task."""

    def solve(nodes: list[int], sets: list[np.ndarray]) -> pa.RecordBatch:
        at, label = np.array(nodes, np.int64), similar_components(sets)
        linked = np.flatnonzero(label != np.arange(len(at)))
        return pa.record_batch([pa.array(at[linked]), pa.array(at[label[linked]])], names=["a", "b"])

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        root, nodes, sets = None, [], []
        for batch in batches:
            for r, node, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                if r != root and nodes:
                    yield solve(nodes, sets)
                    nodes, sets = [], []
                root = r
                nodes.append(node)
                sets.append(np.unique(word_run_hashes(text.as_py(), words)[0]))
        if nodes:
            yield solve(nodes, sets)

    return members.select("root", "node", "text").repartition("root").sortWithinPartitions("root", "node").mapInArrow(run, "a long, b long")


def large_group_links(sets: DataFrame, leaders: int, room: int) -> DataFrame:
    """a, b: links that span those of similarity 0.8 and over within each root of ``sets`` (root, node, row, hashes).

    ``leaders`` times, the first document left of each root is joined to all that are left; its copies leave. The copies of
    one leader, those of which there are most in the root, need no more comparing with each other. All other documents are
    open: blocks of them meet blocks of the whole root, ``room`` hashes each. So every pair is of one leader or in a block.
    """
    part = F.pmod(F.xxhash64("node"), F.lit(PARTS)).alias("part")
    left, links, followers = sets.select("root", "node", "row", "hashes", part), [], []
    for _ in range(leaders):
        first = left.groupBy("root").agg(F.min("row").alias("row"))
        lead = left.join(F.broadcast(first), ["root", "row"]).select("root", F.col("node").alias("lead"), F.col("hashes").alias("wanted"))
        everywhere = lead.withColumn("part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(PARTS - 1).cast("bigint"))))
        shared = F.size(F.array_intersect("hashes", "wanted"))
        near = 9 * shared >= 4 * (F.size("hashes") + F.size("wanted"))
        scored = barrier(left.join(everywhere, ["root", "part"]).select("root", "node", "row", "hashes", "part", "lead", near.alias("near")), "scored")
        links.append(scored.filter("near and node <> lead").select(F.col("node").alias("a"), F.col("lead").alias("b")))
        followers.append(scored.filter("near").select("root", "node", "hashes", "lead"))
        left = scored.filter("not near").select("root", "node", "row", "hashes", "part")
        if left.isEmpty():
            break

    led = followers[0]
    for more in followers[1:]:
        led = led.unionByName(more)
    sizes = led.groupBy("root", "lead").agg(F.sum(F.size("hashes") + 1).alias("weight"))
    most = F.broadcast(sizes.groupBy("root").agg(F.max_by("lead", F.struct("weight", "lead")).alias("settled")))  # one row per large root
    again = led.join(most, "root").filter("lead <> settled")
    left = left.select("root", "node", "hashes").unionByName(again.select("root", "node", "hashes"))

    blocks = lambda df, name: df.groupBy("root").agg(F.ceil(F.sum(F.size("hashes") + 1) / room).cast("int").alias(name))
    counts = F.broadcast(blocks(left, "n_left").join(blocks(sets, "n_all"), "root"))  # one row per large root
    deal = lambda turn, name: F.pmod(F.xxhash64("node", F.lit(turn)), F.col(name)).cast("int")
    spread = lambda name: F.explode(F.sequence(F.lit(0), F.col(name) - 1))
    open_ = left.join(counts, "root").select("root", deal(0, "n_left").alias("i"), spread("n_all").alias("j"), "node", "hashes")
    whole = sets.join(counts, "root").select("root", deal(1, "n_all").alias("j"), spread("n_left").alias("i"), "node", "hashes")

    def meet(table: pa.Table) -> pa.Table:
        node, at = np.unique(table.column("node").to_numpy(), return_index=True)
        lists = table.column("hashes").take(pa.array(at))
        label = similar_components([np.asarray(x.values.to_numpy(), np.int64).view(np.uint64) for x in lists])
        linked = np.flatnonzero(label != np.arange(len(node)))
        return pa.table({"a": node[linked], "b": node[label[linked]]})

    links.append(open_.unionByName(whole).groupBy("root", "i", "j").applyInArrow(meet, "a long, b long"))
    out = links[0]
    for more in links[1:]:
        out = out.unionByName(more)
    return out


def one_of_each(docs: DataFrame, words: int = 1, seeds: int = 32, radius: int = 2, exact_words: int = 5) -> DataFrame:
    """The rows of ``docs``, one of each group of near duplicates (the smallest id), with the same columns.

    Documents are linked if they share 0.8 of their distinct shingles of ``exact_words`` words and are in one group of
    candidates by fingerprint. Equal sets of shingles are one entry. Null texts equal empty ones; rows with equal or null
    ids are told apart by a number given to each row.
    """
    keyed = with_row_key(docs)
    marked = barrier(set_fingerprints(keyed, words, seeds, exact_words), "fingerprints")
    entries = barrier(marked.groupBy("same").agg(F.min("row").alias("row"), F.max("n").alias("n"), F.min("fps").alias("fps")).withColumnRenamed("same", "node"), "entries")
    single = entries.select("node", F.posexplode("fps").alias("seed", "fp")).select(F.col("seed").cast("long").alias("seed"), "fp", "node")
    groups = connected_components(fingerprint_links(single, radius, entries.count(), seeds)).withColumnRenamed("component", "root")
    chosen = barrier(entries.join(groups, "node").select("root", "node", "row", "n"), "candidates")
    large = barrier(chosen.groupBy("root").agg(F.sum(F.col("n") + 1).alias("weight")).filter(F.col("weight") > SHINGLES).select("root"), "large")
    texts = keyed.select(F.col(ROW).cast("long").alias("row"), "text")

    def with_texts(rows: DataFrame) -> DataFrame:
        rows = rows.drop("n")
        return texts.join(F.broadcast(rows) if rows.count() <= SMALL else rows, "row")

    links = small_group_links(with_texts(chosen.join(large, "root", "left_anti")), exact_words)
    if not large.isEmpty():
        sets = barrier(candidate_sets(with_texts(chosen.join(large, "root", "left_semi")), exact_words), "sets")
        links = links.unionByName(large_group_links(sets, LEADERS, SHINGLES // 2))
    alike = connected_components(links).withColumnRenamed("component", "class")
    classed = barrier(entries.join(alike, "node").select("node", "row", "class"), "classes")
    lowest = classed.groupBy("class").agg(F.min("row").alias("low"))
    low = classed.join(lowest, "class").select("node", "low")
    kept = entries.join(low, "node", "left").select(F.col("node").alias("same"), F.coalesce("low", "row").alias("low"))
    gone = barrier(marked.join(kept, "same").filter("row <> low").select(F.col("row").alias(ROW)), "copies")
    few = gone.count() <= SMALL
    return unpacked(keyed.join(F.broadcast(gone) if few else gone, ROW, "left_anti"))
