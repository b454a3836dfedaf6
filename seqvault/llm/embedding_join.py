"""Embedding near duplicates by a subspace pigeonhole join.

Vectors are scaled to length one and rotated by a fixed random rotation, which spreads every difference evenly over the
coordinates. A cosine of ``cosine`` is a squared distance of at most 2 - 2 x ``cosine``. The coordinates are split into
``blocks`` subspaces with budgets proportional to their dimensions: a pair within the whole distance is within its budget
in at least one block. Each block is range-joined under its budget and the union of candidates is verified by cosine in
double precision. A pair that several blocks find counts in the first of them only.

The range join of a block sorts both sides along the block's first coordinate; a slice of one side meets the interval of
the other that the block's radius reaches, and their distances come from one matrix product.

Over the cluster, vectors are ordered by the nearest of a few pivots and cut into tiles of as many bytes as a task holds
(but at least ``tiles`` of them). A pair of tiles is one group of a join. By the triangle inequality, tiles whose
distances to any pivot are further apart than the link radius cannot hold a link; such pairs are left out before the
shuffle. A vector is sent, as bytes, once for each pair that is left: to a fixed number of tiles until tiles are full, and
then work on a tile grows as its square while what is sent grows as its size. Only counts per vector and a spanning
forest leave a task: a group of copies never becomes all its pairs.

Equal vectors are one entry with a multiplicity. Vectors that are null, empty, zero or hold null or non-finite components
link with nothing, and neither do vectors of different lengths with each other. Rows with equal ids are separate
vectors. Null ids take part and are never the smallest. Empty table: empty result. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqvault.llm.graph import Forest, connected_components
from seqvault.llm.workers import release, released
from seqvault.operators.barrier import barrier
from seqvault.operators.prefix import place_by_range, row_numbers

SEED = 20_230_817
#: Rows of a slice, and pairs that are verified at once.
SLICE, LOT = 512, 1 << 17
#: Bytes of the vectors of a tile, in double precision.
TILE_BYTES = 32 << 20
#: Vectors to which tiles are compared; chosen by hash, so they depend on the rows alone.
PIVOTS = 64
#: Slack for single precision; squared distances of unit vectors are at most 4.
SLACK = 1e-5


def rotation(dim: int) -> np.ndarray:
    """A random orthogonal matrix that depends on the dimension only."""
    q, r = np.linalg.qr(np.random.default_rng(SEED + dim).normal(size=(dim, dim)))
    return q * np.sign(np.diag(r))


def block_cuts(dim: int, blocks: int) -> list[int]:
    n = max(1, min(blocks, dim))
    return [dim * i // n for i in range(n + 1)]


def units_of(bodies: list[bytes]) -> np.ndarray:
    """Rows of length one in double precision from packed vectors of equal dimension."""
    x = np.frombuffer(b"".join(bodies), "<f8").reshape(len(bodies), -1)
    # scaled by the largest component first, so that squares neither overflow nor vanish
    x = x / np.abs(x).max(1)[:, None]
    return x / np.linalg.norm(x, axis=1)[:, None]


def block_pairs(x: np.ndarray, y: np.ndarray, budget: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Lots of positions (in ``x``, in ``y``) of points of a low-dimensional block within a squared distance, with slack."""
    over, under = np.argsort(x[:, 0], kind="stable"), np.argsort(y[:, 0], kind="stable")
    line, radius = y[under, 0], (budget + SLACK) ** 0.5
    # the product of both is |p|^2 - 2 p q + |q|^2
    p = np.concatenate([-2 * x, (x * x).sum(1)[:, None], np.ones((len(x), 1))], axis=1).astype(np.float32)[over]
    q = np.concatenate([y, np.ones((len(y), 1)), (y * y).sum(1)[:, None]], axis=1).astype(np.float32)[under]
    for i in range(0, len(x), SLICE):
        rows = over[i : i + SLICE]
        low, high = np.searchsorted(line, [x[rows[0], 0] - radius, x[rows[-1], 0] + radius], "left")
        for j in range(low, high, 8 * SLICE):
            end = min(j + 8 * SLICE, high)
            r, c = np.nonzero(p[i : i + SLICE] @ q[j:end].T <= budget + SLACK)
            if len(r):
                yield rows[r], under[j + c]


def tile_links(x: np.ndarray, y: np.ndarray, same: bool, cosine: float, blocks: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Lots of positions (in ``x``, in ``y``) of linked pairs of unit vectors; each pair once, also if the tiles are the same.

    Block distances are taken in single precision with slack for its error, so no pair is missed; candidates are verified
    in double precision.
    """
    dim = x.shape[1]
    turn = rotation(dim)
    xr, yr = x @ turn, y @ turn
    cuts, whole = block_cuts(dim, blocks), 2 - 2 * cosine
    budgets = np.array([whole * (b - a) / dim for a, b in zip(cuts, cuts[1:], strict=False)])
    for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
        for rows, cols in block_pairs(xr[:, a:b], yr[:, a:b], budgets[k]):
            if same:
                rows, cols = rows[(up := rows < cols)], cols[up]
            for low in range(0, len(rows), LOT):
                r, c = rows[low : low + LOT], cols[low : low + LOT]
                good = np.einsum("ij,ij->i", x[r], y[c]) >= cosine
                r, c = r[good], c[good]
                if not len(r):
                    continue
                parts = np.add.reduceat((xr[r, :b] - yr[c, :b]) ** 2, cuts[: k + 1], axis=1)
                within = parts <= budgets[: k + 1] + SLACK / 2
                first = within[:, k] & ~within[:, :k].any(1)
                if first.any():
                    yield r[first], c[first]


def chained(units: np.ndarray) -> np.ndarray:
    """The rows, each followed by the nearest of those left, so that neighbours in number are near."""
    left, order = list(range(1, len(units))), [0]
    while left:
        order.append(left.pop(int(np.argmax(units[left] @ units[order[-1]]))))
    return units[order]


def packed_vectors(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """id, dim, body (the vector as packed doubles) of every row; null where the vector cannot link."""

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dims, bodies = [], []
            for vec in batch.column(1):
                x = np.zeros(0) if not vec.is_valid or vec.values.null_count else vec.values.to_numpy()
                sound = len(x) > 0 and np.isfinite(x).all() and x.any()
                dims.append(len(x) if sound else None)
                bodies.append((x + 0.0).astype("<f8").tobytes() if sound else None)  # no negative zeros
            yield pa.record_batch([batch.column(0), pa.array(dims, pa.int32()), pa.array(bodies, pa.binary())], names=["id", "dim", "body"])

    slim = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec"))
    return slim.mapInArrow(run, "id long, dim int, body binary")


def nearest_pivot(entries: DataFrame, pivots: dict[int, np.ndarray]) -> DataFrame:
    """``entries`` with pivot (number of the nearest one) and far (distances to all of the same dimension)."""

    @released
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dims = batch.column("dim").to_numpy()
            nearest, far = np.zeros(len(dims), np.int32), [None] * len(dims)
            for d in np.unique(dims):
                mine = np.flatnonzero(dims == d)
                x = units_of(batch.column("body").take(pa.array(mine)).to_pylist())
                away = np.sqrt(np.maximum(0, 2 - 2 * (x @ pivots[int(d)].T)))
                nearest[mine] = away.argmin(1)
                for i, row in zip(mine.tolist(), away.tolist(), strict=True):
                    far[i] = row
            yield pa.record_batch([*batch.columns, pa.array(nearest), pa.array(far, pa.list_(pa.float64()))], names=[*batch.schema.names, "pivot", "far"])

    return entries.select("dim", "body", "times", "least").mapInArrow(run, "dim int, body binary, times long, least long, pivot int, far array<double>")


def meeting_tiles(numbered: DataFrame, tiles: int, radius: float) -> DataFrame:
    """tile, other (tile <= other): pairs that can hold a link, by the least and largest distances to each pivot.

    One row per tile and pivot takes part, and one per pair of tiles is made.
    """
    spans = numbered.select("tile", "dim", F.posexplode("far").alias("pivot", "d")).groupBy("tile", "dim", "pivot").agg(F.min("d").alias("low"), F.max("d").alias("high"))
    spans = barrier(spans, "spans")
    ball = spans.groupBy("tile", "dim").agg(F.sort_array(F.collect_list(F.struct("pivot", "low", "high"))).alias("s"))  # PIVOTS entries
    left = ball.select("tile", "dim", "s", F.explode(F.sequence("tile", F.lit(tiles - 1))).alias("other"))
    both = left.join(ball.select(F.col("tile").alias("other"), "dim", F.col("s").alias("t")), ["other", "dim"])
    apart = F.exists(F.arrays_zip("s", "t"), lambda z: (z["s"]["low"] - z["t"]["high"] > radius) | (z["t"]["low"] - z["s"]["high"] > radius))
    return both.filter(~apart).select("tile", "other").distinct()


def near_duplicates(vectors: DataFrame, cosine: float = 0.9, blocks: int = 8, tiles: int = 8, tile_bytes: int = TILE_BYTES, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """vec_id, n_links, component_id, kept of every row."""
    packed = barrier(packed_vectors(vectors, id_col, vec_col), "vectors")
    entries = barrier(packed.filter("body is not null").groupBy("dim", "body").agg(F.count(F.lit(1)).alias("times"), F.min("id").alias("least")), "entries")
    n, widest = entries.agg(F.count(F.lit(1)), F.max("dim")).first()
    if not n:
        return packed.select(F.col("id").alias(id_col), F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"), F.lit(True).alias("kept"))
    pivots: dict[int, list[bytes]] = {}
    dims = [r[0] for r in entries.select("dim").distinct().collect()]
    for dim in dims:
        pivots[dim] = [bytes(r[0]) for r in entries.filter(F.col("dim") == dim).orderBy(F.xxhash64("body"), "body").select("body").limit(PIVOTS).collect()]
    known = {d: chained(units_of(b)) for d, b in pivots.items()}
    most = max(1, tile_bytes // (8 * widest))
    size = min(most, -(-n // tiles))
    order = ["dim", "pivot", "body"]
    placed = place_by_range(nearest_pivot(entries, known), order, "ordered")
    numbered = barrier(row_numbers(placed, order, "entry").withColumn("tile", F.floor(F.col("entry") / size).cast("int")), "tiles")
    pairs = barrier(meeting_tiles(numbered, -(-n // size), (2 - 2 * cosine) ** 0.5 + SLACK), "pairs")
    met = pairs.select("tile", F.col("tile").alias("p"), F.col("other").alias("q")).unionByName(pairs.filter("tile <> other").select(F.col("other").alias("tile"), F.col("tile").alias("p"), F.col("other").alias("q")))
    sent = numbered.select("tile", "entry", "body", "times", "dim").join(met, "tile").select("p", "q", (F.col("tile") != F.col("p")).alias("right"), "entry", "body", "times", "dim")

    def compare(table: pa.Table) -> pa.Table:
        dims = table.column("dim").to_numpy()
        same = table.column("p")[0].as_py() == table.column("q")[0].as_py()
        out: list[list[np.ndarray]] = [[np.zeros(0, np.int64)] for _ in range(3)]
        for d in np.unique(dims):
            rows = table.filter(pa.array(dims == d)).sort_by("entry")
            entry, times, right = (rows.column(c).to_numpy() for c in ("entry", "times", "right"))
            a = np.arange(len(entry)) if same else np.flatnonzero(~right)
            b = a if same else np.flatnonzero(right)
            if not len(a) or not len(b):
                continue
            unit = units_of(rows.column("body").to_pylist())
            links, forest = np.zeros(len(entry), np.int64), Forest(len(entry))
            for r, c in tile_links(unit[a], unit[b], same, cosine, blocks):
                r, c = a[r], b[c]
                np.add.at(links, r, times[c])
                np.add.at(links, c, times[r])
                forest.merge(r, c)
            touched, label = np.flatnonzero(links), forest.label
            for part, column in zip(out, (entry[touched], links[touched], entry[label[touched]]), strict=True):
                part.append(column)
        release()
        return pa.table(dict(zip(("entry", "links", "root"), map(np.concatenate, out), strict=True)))

    # few bytes, but work for many tasks: a number of partitions that is named is not lowered by their size
    sent = sent.repartition(int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions")), "p", "q")
    found = barrier(sent.groupBy("p", "q").applyInArrow(compare, "entry long, links long, root long"), "links")
    counts = found.groupBy("entry").agg(F.sum("links").alias("links"))
    groups = connected_components(found.select(F.col("entry").alias("a"), F.col("root").alias("b")).filter("a <> b"))
    rooted = numbered.select("entry", "dim", "body", "times", "least").join(counts, "entry", "left").join(groups.withColumnRenamed("node", "entry"), "entry", "left")
    rooted = rooted.withColumn("root", F.coalesce("component", "entry"))
    lowest = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    named = rooted.join(lowest, "root").select("dim", "body", (F.coalesce("links", F.lit(0)) + F.col("times") - 1).alias("n_links"), "component_id")
    linkless = packed.filter("body is null").select("id", F.lit(None).cast("long").alias("n_links"), F.lit(None).cast("long").alias("component_id"))
    result = packed.filter("body is not null").join(named, ["dim", "body"]).select("id", "n_links", "component_id").unionByName(linkless)
    return result.select(
        F.col("id").alias(id_col),
        F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"),
        F.coalesce("component_id", "id").alias("component_id"),
        F.coalesce(F.coalesce("component_id", "id") == F.col("id"), F.lit(True)).alias("kept"),
    )
