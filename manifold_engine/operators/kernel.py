"""Affinities, degrees, Markov matrix, Laplacian, stationary distribution, bandwidth.

``edges(i, j, a)`` holds unordered pairs and the diagonal; rows are made by
``both_ways`` where a row sum is needed.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graph import components
from ..spool import spool
from . import pairs as P


def gaussian(d: Column, eps: float) -> Column:
    return F.exp(-d * d / (2.0 * eps))


def cut_radius(eps: float, drop_below: float) -> float:
    """Distance at which the Gaussian falls to ``drop_below``."""
    return math.sqrt(2.0 * eps * math.log(1.0 / drop_below))


def affinity(pairs: DataFrame, points: DataFrame, eps: float, kernel=gaussian) -> DataFrame:
    """``edges(i, j, a)`` of given pairs, with the diagonal of ``points``."""
    off = pairs.select("i", "j", kernel(F.col("d"), eps).alias("a"))
    return off.union(points.select(F.col("id").alias("i"), F.col("id").alias("j"), F.lit(1.0).alias("a")))


def sparse_affinity(points: DataFrame, eps: float, drop_below: float = 1e-6, metric: str = "euclidean", **kw) -> DataFrame:
    """Affinities of at least ``drop_below``: the cut is pushed into the pair join as a radius."""
    return affinity(P.pairs_within(points, cut_radius(eps, drop_below), metric, **kw), points, eps)


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.union(edges.where("i <> j").select(F.col("j").alias("i"), F.col("i").alias("j"), "a"))


def degrees(edges: DataFrame) -> DataFrame:
    """``i, deg``: row sums, each edge counted at both ends by one aggregation."""
    return both_ways(edges).groupBy("i").agg(F.sum("a").alias("deg"))


def bell(eps: float):
    """The Gaussian of ``eps`` for the scans over pairs in ``pairs``."""
    return lambda d: np.exp(d * d / (-2.0 * eps))


def point_degrees(points: DataFrame, eps: float, metric: str = "euclidean") -> DataFrame:
    """``degrees`` of the affinities of all pairs, summed where the distances are made: no pair is written."""
    a = bell(eps)
    return P.row_sums(points, lambda d, u, v: [a(d)], ["off"], metric, symmetric=True).select(F.col("id").alias("i"), (F.lit(1.0) + F.col("off")).alias("deg"))


def with_degrees(points: DataFrame, deg: DataFrame, *more: str) -> DataFrame:
    """Points whose vectors end in their degree (and further columns of ``deg``), for scans that need it at both ends."""
    return spool(points.join(deg.withColumnRenamed("i", "id"), "id").select("id", F.concat("vec", F.array("deg", *more)).alias("vec")), "degrees")


def point_markov(points: DataFrame, eps: float, dims: int, metric: str = "euclidean") -> DataFrame:
    """``markov`` over all ordered pairs of points of ``dims`` dimensions: degrees in one scan, entries in a second, nothing between them but points."""
    a = bell(eps)
    return P.pair_table(with_degrees(points, point_degrees(points, eps, metric)), lambda d, u, v: [a(d) / u[..., dims]], ["p"], metric, dims, ordered=True)


def point_markov_sums(points: DataFrame, eps: float, dims: int, metric: str = "euclidean") -> DataFrame:
    """``i, diagonal, off``: of each row of the Markov matrix its diagonal entry and the sum of the others."""
    a = bell(eps)
    rows = with_degrees(points, point_degrees(points, eps, metric))
    off = P.row_sums(rows, lambda d, u, v: [a(d) / u[..., dims]], ["off"], metric, dims)
    return off.join(rows, "id").select(F.col("id").alias("i"), (F.lit(1.0) / F.col("vec")[dims]).alias("diagonal"), "off")


def markov(edges: DataFrame, deg: DataFrame) -> DataFrame:
    return both_ways(edges).join(deg, "i").select("i", "j", (F.col("a") / F.col("deg")).alias("p"))


def laplacian(m: DataFrame) -> DataFrame:
    return m.select("i", "j", ((F.col("i") == F.col("j")).cast("double") - F.col("p")).alias("v"))


def stationary(deg: DataFrame) -> DataFrame:
    """``i, pi``: degree over the total, the total by one more aggregation of one row."""
    total = deg.agg(F.sum("deg").alias("total"))
    return deg.crossJoin(F.broadcast(total)).select("i", (F.col("deg") / F.col("total")).alias("pi"))


def connecting_radius(pairs: DataFrame, rounds: int = 40) -> float:
    """Longest edge of the minimum spanning tree: rounds of the least edge out of each component.

    Ties are broken by the ends, so each round at least halves the components.
    """
    edges = spool(pairs.select("i", "j", "d"), "edges")
    worst = 0.0
    for _ in range(rounds):
        ends = edges.select(F.col("i").alias("c"), "d", "i", "j").union(edges.select(F.col("j").alias("c"), "d", "i", "j"))
        least = spool(ends.groupBy("c").agg(F.min(F.struct("d", "i", "j")).alias("e")).select("e.*").distinct(), "least")
        top = least.agg(F.max("d")).first()[0]
        if top is None:
            return worst
        worst = max(worst, top)
        comp = spool(components(least, "i", "j"), "components")
        a, b = comp.select(F.col("id").alias("i"), F.col("comp").alias("ci")), comp.select(F.col("id").alias("j"), F.col("comp").alias("cj"))
        edges = spool(edges.join(a, "i").join(b, "j").where("ci <> cj").groupBy(F.least("ci", "cj").alias("i"), F.greatest("ci", "cj").alias("j")).agg(F.min("d").alias("d")), "edges")
    raise RuntimeError("more rounds needed")


def connecting_bandwidth(pairs: DataFrame) -> float:
    """Smallest bandwidth whose walk is connected at one kernel width."""
    return connecting_radius(pairs) ** 2


def _slopes(sums: DataFrame) -> DataFrame:
    """``eps, total, slope``: log-log slopes between neighbours of a grid."""
    from pyspark.sql import Window

    w = Window.orderBy("eps")
    before = F.lag(F.struct(F.ln("eps").alias("e"), F.ln("total").alias("t"))).over(w)
    return sums.withColumn("b", before).select("eps", "total", ((F.ln("total") - F.col("b.t")) / (F.ln("eps") - F.col("b.e"))).alias("slope"))


def bandwidth_curve(pairs: DataFrame, n: int, grid: list[float]) -> DataFrame:
    """``eps, total, slope`` of the kernel sum over a grid: log-log slopes between neighbours; one pass over the pairs."""
    each = pairs.select("d", F.explode(F.array(*[F.lit(float(e)) for e in grid])).alias("eps"))
    return _slopes(each.groupBy("eps").agg((F.lit(float(n)) + 2.0 * F.sum(F.exp(-F.col("d") * F.col("d") / (2.0 * F.col("eps"))))).alias("total")))


def point_bandwidth_curve(points: DataFrame, grid: list[float], metric: str = "euclidean") -> DataFrame:
    """``bandwidth_curve`` over all pairs of points, summed where the distances are made."""
    names = [f"s{k}" for k in range(len(grid))]
    sums = P.pair_sums(points, lambda d, u, v: (np.exp(-d * d / (2.0 * e)) for e in grid), names, metric)
    n = float(points.count())
    each = F.explode(F.array(*[F.struct(F.lit(float(e)).alias("eps"), (F.lit(n) + 2.0 * F.col(c)).alias("total")) for e, c in zip(grid, names)]))
    return _slopes(sums.select(each.alias("s")).select("s.*"))


def point_components(points: DataFrame, r: float, metric: str = "euclidean") -> DataFrame:
    """``id, comp`` of the graph of pairs within ``r``, isolated points included: components of block forests, a few edges a point."""
    loops = points.select(F.col("id").alias("u"), F.col("id").alias("v"))
    return components(P.near_forest(points, r, metric).union(loops))


def require_connected(points: DataFrame, pairs: DataFrame | None, r: float, keep: str | None = None, metric: str = "euclidean") -> DataFrame:
    """``points`` if the graph of pairs within ``r`` is connected; else an error, or the largest component.

    Without a table of ``pairs`` the points are scanned and no pair is written.
    """
    if pairs is None:
        comp = spool(point_components(points, r, metric), "components")
    else:
        near = pairs.where(F.col("d") <= r).select(F.col("i").alias("u"), F.col("j").alias("v"))
        loops = points.select(F.col("id").alias("u"), F.col("id").alias("v"))
        comp = spool(components(near.union(loops)), "components")
    sizes = comp.groupBy("comp").count().orderBy(F.desc("count"), "comp").limit(5).collect()
    if len(sizes) <= 1:
        return points
    if keep != "largest":
        raise ValueError(f"the walk is not connected at r={r}: largest components {[(x[0], x[1]) for x in sizes]}")
    return points.join(comp.where(F.col("comp") == sizes[0][0]).select("id"), "id", "left_semi")


def local_edges(ids: np.ndarray, pairs: DataFrame, eps: float | None):
    """Collected edges over ``ids`` for a local solver; they are counted first and refused beyond ``planner.LOCAL_EDGES``."""
    from ..functions.linalg import SymmetricEdges
    from ..plans import planner

    pairs = spool(pairs.select("i", "j", "d"), "edges")
    if (n := pairs.count()) > planner.LOCAL_EDGES:
        raise ValueError(f"{n} edges are too many to hold: use growth='star_rounds' or 'boruvka_rounds', solver='distributed', or a smaller radius")
    t = pairs.toArrow()
    i, j = np.searchsorted(ids, t["i"].to_numpy()), np.searchsorted(ids, t["j"].to_numpy())
    d = t["d"].to_numpy()
    a = np.ones_like(d) if eps is None else np.exp(-d * d / (2 * eps))
    return SymmetricEdges(len(ids), i, j, a, np.zeros(len(ids)) if eps is None else np.ones(len(ids)))
