"""Pairs of points: all of them, those within a radius, nearest neighbours.

``pairs(i, j, d)`` holds each unordered pair once, ``i < j``.  Strategies:

* ``tile``: points packed into blocks, block times block, any metric;
* ``grid``: cells of the radius' width, neighbour offsets exploded on one side,
  plain equi-join and filter: exact for Euclidean points of few dimensions,
  generated JVM code throughout;
* ``pivot``: cells of sampled pivots with replication by the triangle
  inequality: exact for any metric;
* ``lsh``: bucketed random projections: approximate, its recall is measured.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import metrics
from ..spool import plan_bytes, shuffle_partitions, spool

PAIRS = "i long, j long, d double"
CROWD = 5_000  # points of a cell that one block holds
STRIP = 1 << 20  # distances that a step of a scan over pairs holds
CACHED = 1 << 15  # of these, as many as stay in a core's cache while a function goes over them
#: Columns of a tile of pairs, widest first. Parquet packs ids that do not repeat in runs of up to 504; widths that
#: divide this make the packed bytes recur from row to row, so that compression takes them out.
WIDTHS = (504, 252, 168, 72, 56, 24, 8)


def matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    """A list column of equal lengths as a matrix."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def tile_count(points: DataFrame, tile_bytes: int = 8 << 20, pairs: int = 1) -> int:
    """Blocks of about ``tile_bytes``; at least enough that there are ``pairs`` pairs of blocks for each shuffle partition."""
    want = int((2 * pairs * shuffle_partitions(points.sparkSession)) ** 0.5) + 1
    return max(want, plan_bytes(points) // tile_bytes)


def strips(rows: int, columns: int, entries: int = STRIP):
    """Slices of ``rows`` that make about ``entries`` entries each against ``columns``."""
    step = max(1, entries // max(1, columns))
    for s in range(0, rows, step):
        yield slice(s, min(rows, s + step))


def widths(columns: int):
    """Slices of ``columns`` in lengths of ``WIDTHS``, and of what is left."""
    s = 0
    while s < columns:
        step = next((w for w in WIDTHS if w <= columns - s), columns - s)
        yield slice(s, s + step)
        s += step


def _tiled(points: DataFrame, fn: Callable, out: str, tiles: int) -> DataFrame:
    """``fn(block1, block2, same)`` of every pair of blocks, its batches handed on as they come; each block is sent to the tasks of its row and column.

    A column ``b`` of the points numbers their blocks, else a hash of the id.
    Where ``fn.runs`` is set, rows come in runs of their first column; a run
    travels to the JVM as one row of lists, which costs less than its rows, and
    is dealt out there.
    """
    b = F.col("b") if "b" in points.columns else F.pmod(F.xxhash64("id"), F.lit(tiles)).cast("int")
    rows = points.select("id", "vec", b.alias("b"))
    to = F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))
    sent = rows.select("id", "vec", "b", to.alias("o")).select("id", "vec", "b", F.least("b", "o").alias("p"), F.greatest("b", "o").alias("q"))
    runs = getattr(fn, "runs", False)

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, q = key[0].as_py(), key[1].as_py()
        t = pa.Table.from_batches(list(batches))
        t = t.take(pa.array(np.argsort(t.column("id").to_numpy(), kind="stable")))
        which = t.column("b").to_numpy()
        ids, x = t.column("id").to_numpy(), matrix(t.column("vec"))
        one, two = which == p, which == q
        if one.any() and two.any():
            made = fn(ids[one], x[one], ids[two], x[two], p == q)
            yield from map(packed, made) if runs else made

    by_pair = sent.repartition(min(2_000, tiles * (tiles + 1) // 2), "p", "q").groupBy("p", "q")
    if not runs:
        return by_pair.applyInArrow(run, out)
    first, *rest = (c.rsplit(" ", 1) for c in out.split(", "))
    lists = T.StructType([T.StructField(first[0], _parse(first[1]), False), *(T.StructField(c, T.ArrayType(_parse(kind), False), False) for c, kind in rest)])
    dealt = by_pair.applyInArrow(run, lists).select("*", F.posexplode(rest[0][0]).alias("at__", "one__"))
    return dealt.select(first[0], F.col("one__").alias(rest[0][0]), *(F.col(c)[F.col("at__")].alias(c) for c, _ in rest[1:]))


def _parse(kind: str) -> T.DataType:
    return {"long": T.LongType(), "double": T.DoubleType()}[kind]


def packed(batch: pa.RecordBatch) -> pa.RecordBatch:
    """A row for each run of equal values of the first column, the other columns as lists."""
    key = batch.column(0).to_numpy()
    starts = np.flatnonzero(np.concatenate([np.ones(min(1, len(key)), bool), key[1:] != key[:-1]]))
    ends = pa.array(np.append(starts, len(key)).astype(np.int32))
    return pa.RecordBatch.from_arrays([pa.array(key[starts]), *(pa.ListArray.from_arrays(ends, c, type=pa.list_(pa.field("element", c.type, nullable=False))) for c in batch.columns[1:])], names=batch.schema.names)


def along_curve(x: np.ndarray, bits: int = 10, most: int = 6) -> np.ndarray:
    """Order of the rows along a curve through the cells of their first ``most`` components: neighbours in it are near each other."""
    x = x[:, :most]
    span = np.ptp(x, 0) if len(x) else np.ones(x.shape[1])
    cell = ((x - x.min(0, initial=np.inf)) / np.where(span > 0, span, 1.0) * (2**bits - 1)).astype(np.int64)
    key = np.zeros(len(x), np.int64)
    for b in range(bits - 1, -1, -1):
        for c in range(x.shape[1]):
            key = key << 1 | (cell[:, c] >> b & 1)
    return np.argsort(key, kind="stable")


def id_cuts(points: DataFrame, tiles: int) -> list[int]:
    """First ids of blocks of ascending ids and about equal size, the lowest block's left out."""
    return sorted({int(q) for q in points.approxQuantile("id", [k / tiles for k in range(1, tiles)], 0.1 / tiles)}) if tiles > 1 else []


def pair_table(points: DataFrame, fn: Callable, columns: list[str], metric: str = "euclidean", dims: int | None = None, within: float | None = None, ordered: bool = False, tiles: int | None = None) -> DataFrame:
    """``i, j`` and the ``columns`` that ``fn(d, u, v)`` makes of each unordered pair, or of all ordered ones and the diagonal.

    The first ``dims`` components (default all) are measured; what follows them
    in a vector travels with its point and is there for ``fn``.  Pairs are
    handed on strip by strip, so neither a task nor a table holds them all.
    Without a radius they come in tiles of the matrix (``widths``), neighbours
    beside each other, so that a columnar file of them is short; ``fn`` then
    gets matrices as in ``row_sums``, and blocks of unordered pairs are ranges
    of ids, so that the smaller id is on one side.
    """
    if ordered and within is not None:
        raise ValueError("ordered pairs come without a radius")
    block = metrics.get(metric).block

    def near(a, x, b, y, same):
        for s in strips(len(a), len(b)):
            d = block(x[s, :dims], y[:, :dims])
            low = a[s, None] < b[None, :]
            keep = d <= within
            r, c = np.nonzero(keep & low)
            yield batch(a[s][r], b[c], fn(d[r, c], x[s][r], y[c]))
            if not same:  # the other half of these pairs has its smaller id in the second block
                r, c = np.nonzero(keep & ~low)
                yield batch(b[c], a[s][r], fn(d[r, c], y[c], x[s][r]))

    def batch(i, j, made):
        return pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), *map(pa.array, made)], names=["i", "j", *columns])

    def matrices(a, x, b, y, same):
        one, two = along_curve(x[:, :dims]), along_curve(y[:, :dims])
        a, x, b, y = a[one], x[one], b[two], y[two]
        both = not same and (ordered or a.max() > b.min())  # entries are needed on either side of the diagonal
        for a, x, b, y in [(a, x, b, y), (b, y, a, x)] if both else [(a, x, b, y)]:
            every = ordered or not (same or both)
            for t in widths(len(b)):
                ids, z = b[t], y[t]
                for s in strips(len(a), len(ids), CACHED):
                    d = block(x[s, :dims], z[:, :dims])
                    if same:
                        d[a[s, None] == ids[None, :]] = 0.0
                    made = [np.broadcast_to(v, d.shape).ravel() for v in fn(d, x[s, None, :], z[None, :, :])]
                    i, j = np.repeat(a[s], len(ids)), np.tile(ids, len(d))
                    if not every:
                        low = i < j
                        i, j, made = i[low], j[low], [v[low] for v in made]
                    yield batch(i, j, made)

    matrices.runs = True
    tiles, out = tiles or tile_count(points, pairs=4), ", ".join(["i long", "j long", *(f"{c} double" for c in columns)])
    if within is not None:
        return _tiled(points, near, out, tiles)
    if ordered:
        return _tiled(points, matrices, out, tiles)
    cuts = id_cuts(points, tiles)
    place = F.size(F.filter(F.lit(np.array(cuts, np.int64)), lambda c: c <= F.col("id"))) if cuts else F.lit(0)
    return _tiled(points.withColumn("b", place), matrices, out, len(cuts) + 1)


def all_pairs(points: DataFrame, metric: str = "euclidean", within: float | None = None, tiles: int | None = None) -> DataFrame:
    """Every unordered pair with its distance (computed once), or those with ``d <= within``."""
    return pair_table(points, lambda d, u, v: [d], ["d"], metric, None, within, False, tiles)


def row_sums(points: DataFrame, fn: Callable, columns: list[str], metric: str = "euclidean", dims: int | None = None, tiles: int | None = None, symmetric: bool = False) -> DataFrame:
    """``id`` and, for each of ``columns``, the sum of ``fn(d, u, v)`` over all other points ``v``; no pair leaves its task.

    ``fn`` gets a matrix of distances and vectors that broadcast against it. If
    it is ``symmetric`` in the two, it is asked once for each pair.
    """
    block, width = metrics.get(metric).block, len(columns)

    def each(a, x, b, y, same):
        left, right = np.zeros((width, len(a))), np.zeros((width, len(b)))
        for s in strips(len(a), len(b), CACHED):
            d = block(x[s, :dims], y[:, :dims])
            at = np.arange(len(d))
            for k, v in enumerate(fn(d, x[s, None, :], y[None, :, :])):
                if same:
                    v = v.copy()
                    v[at, at + s.start] = 0.0
                left[k, s] = v.sum(1)
                if symmetric and not same:
                    right[k] += v.sum(0)
            if not (same or symmetric):
                for k, v in enumerate(fn(d, y[None, :, :], x[s, None, :])):
                    right[k] += v.sum(0)
        yield pa.RecordBatch.from_arrays([pa.array(a), *map(pa.array, left)], names=["id", *columns])
        if not same:
            yield pa.RecordBatch.from_arrays([pa.array(b), *map(pa.array, right)], names=["id", *columns])

    parts = _tiled(points, each, ", ".join(["id long", *(f"{c} double" for c in columns)]), tiles or tile_count(points, pairs=4))
    return parts.groupBy("id").agg(*[F.sum(c).alias(c) for c in columns])


def pair_sums(points: DataFrame, fn: Callable, columns: list[str], metric: str = "euclidean", dims: int | None = None, tiles: int | None = None) -> DataFrame:
    """One row: for each of ``columns``, the sum of ``fn(d, u, v)`` over the unordered pairs; no pair leaves its task."""
    block = metrics.get(metric).block

    def each(a, x, b, y, same):
        total = np.zeros(len(columns))
        for s in strips(len(a), len(b), CACHED):
            d = block(x[s, :dims], y[:, :dims])
            for k, v in enumerate(fn(d, x[s, None, :], y[None, :, :])):
                total[k] += v[a[s, None] < b[None, :]].sum() if same else v.sum()
        yield pa.RecordBatch.from_arrays([pa.array([v]) for v in total], names=columns)

    return _tiled(points, each, ", ".join(f"{c} double" for c in columns), tiles or tile_count(points, pairs=4)).agg(*[F.coalesce(F.sum(c), F.lit(0.0)).alias(c) for c in columns])


def near_forest(points: DataFrame, within: float, metric: str = "euclidean", tiles: int | None = None) -> DataFrame:
    """Edges ``u, v`` of pairs within ``within`` that leave the same connected components as all such pairs: a spanning forest of each pair of blocks."""
    block = metrics.get(metric).block

    def each(a, x, b, y, same):
        ids, z = (a, x) if same else (np.concatenate([a, b]), np.concatenate([x, y]))
        i, j = local_forest(z, within, block)
        yield pa.RecordBatch.from_arrays([pa.array(ids[i]), pa.array(ids[j])], names=["u", "v"])

    return _tiled(points, each, "u long, v long", tiles or tile_count(points))


def local_forest(x: np.ndarray, within: float, block: Callable) -> tuple[np.ndarray, np.ndarray]:
    """Ends of a spanning forest of the graph of rows within ``within``; distances only from reached rows to unreached ones."""
    left, ready, i, j = np.arange(len(x)), np.zeros(0, np.int64), [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    while len(left):
        if not len(ready):
            ready, left = left[:1], left[1:]
            continue
        now, ready = np.split(ready, [max(1, STRIP // len(left))])
        near = block(x[now], x[left]) <= within
        hit = near.any(0)
        i.append(now[near.argmax(0)[hit]])
        j.append(left[hit])
        ready, left = np.concatenate([ready, left[hit]]), left[~hit]
    return np.concatenate(i), np.concatenate(j)


def theta_pairs(points: DataFrame, distance: Callable[[Column, Column], Column], within: float | None = None) -> DataFrame:
    """Nested-loop form for small tables: the plan SQL users write."""
    a, b = points.select(F.col("id").alias("i"), F.col("vec").alias("u")), points.select(F.col("id").alias("j"), F.col("vec").alias("v"))
    out = a.join(b, F.col("i") < F.col("j")).select("i", "j", distance(F.col("u"), F.col("v")).alias("d"))
    return out if within is None else out.where(F.col("d") <= within)


def grid_pairs(points: DataFrame, within: float, dims: int) -> DataFrame:
    """Exact radius join of Euclidean points in ``dims`` <= 4 dimensions by cells."""
    cell = F.transform("vec", lambda x: F.floor(x / within))
    rows = points.select("id", "vec", cell.alias("c"))
    # a crowded cell is dealt into blocks: its own points by hash, visitors go to each block
    crowded = spool(rows.groupBy(F.col("c").alias("cell")).agg(F.ceil(F.count("*") / CROWD).cast("int").alias("blocks")).where("blocks > 1"), "crowded")
    offsets = [[]]
    for _ in range(dims):
        offsets = [o + [s] for o in offsets for s in (-1, 0, 1)]
    near = F.explode(F.array(*[F.array(*[(F.col("c")[k] + s) for k, s in enumerate(o)]) for o in offsets]))
    left = rows.select(F.col("id").alias("i"), F.col("vec").alias("u"), near.alias("cell"))
    right = rows.select(F.col("id").alias("j"), F.col("vec").alias("v"), F.col("c").alias("cell"))
    if crowded.limit(1).count():
        blocks = F.coalesce("blocks", F.lit(1))
        left = left.join(crowded, "cell", "left").select("i", "u", "cell", F.explode(F.sequence(F.lit(0), blocks - 1)).alias("k"))
        right = right.join(crowded, "cell", "left").select("j", "v", "cell", F.pmod(F.xxhash64("j"), blocks).cast("int").alias("k"))
        return left.join(right, ["cell", "k"]).where(F.col("i") < F.col("j")).select("i", "j", metrics.euclidean(F.col("u"), F.col("v")).alias("d")).where(F.col("d") <= within)
    return left.join(right, "cell").where(F.col("i") < F.col("j")).select("i", "j", metrics.euclidean(F.col("u"), F.col("v")).alias("d")).where(F.col("d") <= within)


def pivot_pairs(points: DataFrame, within: float, metric: str = "euclidean", pivots: int | None = None, seed: int = 0) -> DataFrame:
    """Exact radius join of any metric: each point lives in its nearest pivot's cell and visits every cell it can reach.

    A partner within ``r`` of x whose cell is p has ``d(x,p) <= d(x,own) + 2r``.
    The pivots are a sample in hash order that travels with the tasks: about the
    square root of the number of points, 64 to 4,096, so that cells and the
    visits to them grow alike.
    """
    m = metrics.get(metric)
    if not m.is_metric:
        raise ValueError(f"{m.name} is no metric: use strategy='tile'")
    from ..sources.points import by_hash_order

    count = pivots or min(4_096, max(64, round(points.count() ** 0.5)))
    centre = np.array([r["vec"] for r in by_hash_order(points, count, seed).select("vec").collect()], float)
    if not len(centre):
        return points.sparkSession.createDataFrame([], PAIRS)

    def visit(batches):
        for b in batches:
            x = matrix(b.column("vec"))
            if not len(x):
                continue
            d = m.block(x, centre)
            own = d.argmin(1)
            near = d <= d[np.arange(len(x)), own][:, None] + 2.0 * within * (1 + 1e-9) + 1e-12
            r, c = np.nonzero(near)
            take = pa.array(r)
            yield pa.RecordBatch.from_arrays([b.column("id").take(take), b.column("vec").take(take), pa.array(c, pa.int32()), pa.array(c == own[r])], names=["id", "vec", "cell", "home"])

    sent = points.select("id", "vec").mapInArrow(visit, "id long, vec array<double>, cell int, home boolean")
    # a crowded cell is dealt into blocks of its home points; visitors go to each block
    size = spool(sent.groupBy("cell").agg(F.sum(F.col("home").cast("int")).alias("n")), "cells")
    blocks = size.select("cell", F.greatest(F.lit(1), F.ceil(F.col("n") / 2000)).cast("int").alias("blocks"))
    dealt = sent.join(blocks, "cell")
    home = dealt.where("home").select("id", "vec", "cell", "home", F.pmod(F.xxhash64("id"), "blocks").cast("int").alias("k"))
    guest = dealt.select("id", "vec", "cell", F.lit(False).alias("home"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("k"))

    def match(t):
        ids, x, h = t.column("id").to_numpy(), matrix(t.column("vec")), t.column("home").to_numpy()
        a, b = ids[h], ids[~h]
        if not len(a) or not len(b):
            return pa.table({"i": pa.array([], pa.int64()), "j": pa.array([], pa.int64()), "d": pa.array([], pa.float64())})
        d = m.block(x[h], x[~h])
        r, c = np.nonzero((d <= within) & (a[:, None] < b[None, :]))  # the smaller id at home: each pair once
        return pa.table({"i": a[r], "j": b[c], "d": d[r, c]})

    return home.union(guest).groupBy("cell", "k").applyInArrow(match, PAIRS)


def lsh_pairs(points: DataFrame, within: float, bucket: float | None = None, tables: int = 6, seed: int = 0) -> DataFrame:
    """Approximate Euclidean radius join by MLlib's bucketed random projections."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    rows = points.select("id", array_to_vector("vec").alias("features"))
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=bucket or 2 * within, numHashTables=tables, seed=seed).fit(rows)
    out = model.approxSimilarityJoin(rows, rows, within + 1e-9, distCol="d")
    out = out.select(F.col("datasetA.id").alias("i"), F.col("datasetB.id").alias("j"), "d")
    return out.where((F.col("i") < F.col("j")) & (F.col("d") <= within)).distinct()


def pairs_within(points: DataFrame, within: float, metric: str = "euclidean", strategy: str | None = None, dims: int | None = None, **kw) -> DataFrame:
    """Pairs with ``d <= within`` by a named strategy, or the planner's choice."""
    from ..plans.planner import choose_pair_strategy

    if strategy is None:
        strategy = choose_pair_strategy(dims, metric, plan_bytes(points))
    if strategy == "tile":
        return all_pairs(points, metric, within, **kw)
    if strategy == "grid":
        return grid_pairs(points, within, dims)
    if strategy == "pivot":
        return pivot_pairs(points, within, metric, **kw)
    if strategy == "lsh":
        return lsh_pairs(points, within, **kw)
    raise ValueError(f"unknown strategy {strategy}")


def knn(points: DataFrame, queries: DataFrame, k: int, metric: str = "euclidean", exclude_self: bool = True) -> DataFrame:
    """``id, nn, d, rank`` of the ``k`` nearest points of each query: a top k for each block, then of these.

    Ties go to the smaller id.  Queries travel in blocks; every query meets
    every block of points once and leaves ``k`` rows for each.
    """
    block = metrics.get(metric).block
    tiles = tile_count(points)
    q_tiles = tile_count(queries)
    p = points.select("id", "vec", F.pmod(F.xxhash64("id"), F.lit(tiles)).cast("int").alias("b"), F.explode(F.sequence(F.lit(0), F.lit(q_tiles - 1))).alias("a"))
    q = queries.select("id", "vec", F.pmod(F.xxhash64("id"), F.lit(q_tiles)).cast("int").alias("a"), F.explode(F.sequence(F.lit(0), F.lit(tiles - 1))).alias("b"))

    def top(left, right):
        qi, pi = left.column("id").to_numpy(), right.column("id").to_numpy()
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        x, y = matrix(left.column("vec")), matrix(right.column("vec"))
        for s in strips(len(qi), len(pi)):
            d = block(x[s], y)
            if exclude_self:
                d[qi[s, None] == pi[None, :]] = np.inf
            last = np.partition(d, k - 1, axis=1)[:, k - 1 : k] if k < len(pi) else np.inf
            r, c = np.nonzero((d <= last) & np.isfinite(d))  # ties with the last one too
            order = np.lexsort((pi[c], d[r, c], r))
            r, c = r[order], c[order]
            keep = np.arange(len(r)) - np.searchsorted(r, r) < k
            out.append((qi[s][r[keep]], pi[c[keep]], d[r[keep], c[keep]]))
        return pa.table({n: np.concatenate(v) for n, v in zip(("id", "nn", "d"), zip(*out))})

    part = q.groupBy("a", "b").cogroup(p.groupBy("a", "b")).applyInArrow(top, "id long, nn long, d double")
    rank = F.row_number().over(Window.partitionBy("id").orderBy("d", "nn"))
    return part.withColumn("rank", rank).where(F.col("rank") <= k)
