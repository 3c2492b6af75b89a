"""Full and reduced diffusion maps, and the Nystrom extension over either."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import metrics
from ..functions.linalg import SymmetricEdges, block_krylov, fix_signs
from ..plans import planner
from ..spool import shuffle_partitions, spool
from . import kernel as K
from . import pairs as P
from .spectrum import distributed_modes, local_modes, spectrum_table

EMBEDDING = "id long, psi array<double>, nearest_lid long, d_min double, extrapolated boolean, model_version string"


@dataclass
class Model:
    """Fitted points (or landmarks): vectors, weights, modes (the first is trivial)."""

    ids: np.ndarray
    vecs: np.ndarray
    counts: np.ndarray
    lam: np.ndarray
    psi: np.ndarray
    deg: np.ndarray
    eps: float
    metric: str = "euclidean"
    version: str = "v1"
    kind: str = "full"
    extra: dict = field(default_factory=dict)

    @property
    def size(self) -> int:
        return len(self.ids)

    def coordinates(self, k: int) -> np.ndarray:
        return self.psi[:, 1 : k + 1]

    def coords_table(self, spark: SparkSession, k: int) -> DataFrame:
        t = pa.table({"id": pa.array(self.ids), "psi": pa.array(list(self.coordinates(k)), pa.list_(pa.float64()))})
        return spark.createDataFrame(t)

    def spectrum(self, spark: SparkSession) -> DataFrame:
        return spectrum_table(spark, self.lam)

    def nbytes(self) -> int:
        return self.vecs.nbytes + self.psi.nbytes + self.counts.nbytes


def collect_points(points: DataFrame, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors in id order, after a check that there are no more than ``most``."""
    t = points.select("id", "vec").limit(most + 1).toArrow()
    if t.num_rows > most:
        raise ValueError(f"more than {most} points: fit on landmarks or a sample, or use solver='distributed'")
    ids, x = t["id"].to_numpy(), P.matrix(t["vec"])
    order = np.argsort(ids, kind="stable")
    return ids[order], x[order]


def fit_local(ids: np.ndarray, x: np.ndarray, eps: float, modes: int, metric: str = "euclidean", counts: np.ndarray | None = None, drop_below: float = 0.0, kind: str = "full", seed: int = 0) -> Model:
    """A map over points held here; ``drop_below`` cuts small affinities."""
    n = len(ids)
    c = np.ones(n) if counts is None else counts.astype(float)
    block = metrics.get(metric).block
    cut = K.cut_radius(eps, drop_below) if drop_below else np.inf
    i, j, a = [], [], []
    step, held = max(1, 4_000_000 // max(n, 1)), 0
    for s in range(0, n, step):
        d = block(x[s : s + step], x[s:])
        r, q = np.nonzero((d <= cut) & (np.arange(d.shape[1])[None, :] > np.arange(d.shape[0])[:, None]))
        i.append(r + s)
        j.append(q + s)
        a.append(np.exp(-(d[r, q] ** 2) / (2 * eps)))
        held += len(r)
        if held > planner.LOCAL_EDGES:
            raise ValueError(f"more than {planner.LOCAL_EDGES} affinities: cut small ones with drop_below, fit on landmarks, or use solver='distributed'")
    edges = SymmetricEdges(n, *(np.concatenate(v) if v else np.zeros(0, np.int64) for v in (i, j, a)), np.ones(n))
    lam, psi, deg = local_modes(edges, c, min(modes, n), "dense" if n <= planner.DENSE_POINTS else "lanczos", seed)
    return Model(ids, x, c, lam, psi, deg, eps, metric, kind=kind)


def kernel_product(spark: SparkSession, x: np.ndarray, eps: float, v: np.ndarray, metric: str = "euclidean") -> np.ndarray:
    """``A v`` of the affinities of all pairs of rows of ``x``, which tasks compute strip by strip and nobody holds."""
    block, parts = metrics.get(metric).block, min(len(x), shuffle_partitions(spark))
    cuts = np.linspace(0, len(x), parts + 1).astype(int)

    def run(batches):
        for b in batches:
            for k in b.column("id").to_pylist():
                own = x[cuts[k] : cuts[k + 1]]
                y = np.concatenate([np.exp(-(block(own[s], x) ** 2) / (2 * eps)) @ v for s in P.strips(len(own), len(x))])
                yield pa.RecordBatch.from_arrays([pa.array([k]), pa.array([y.tobytes()], pa.binary())], names=["k", "y"])

    t = spark.range(0, parts, 1, parts).mapInArrow(run, "k long, y binary").toArrow().sort_by("k")
    return np.concatenate([np.frombuffer(y).reshape(-1, v.shape[1]) for y in t["y"].to_pylist()])


def fit_scanned(spark: SparkSession, ids: np.ndarray, x: np.ndarray, eps: float, modes: int, metric: str = "euclidean", seed: int = 0) -> Model:
    """A full map whose affinities are computed anew in each product: the driver holds points and a basis of vectors, no pair."""
    n = len(ids)
    deg = kernel_product(spark, x, eps, np.ones((n, 1)), metric)[:, 0]
    root = np.sqrt(deg)[:, None]
    lam, v = block_krylov(lambda q: kernel_product(spark, x, eps, q / root, metric) / root, n, min(modes, n), root[:, 0], seed)
    psi = v / root
    psi /= np.sqrt((psi * psi).sum(0))
    return Model(ids, x, np.ones(n), lam, fix_signs(psi), deg, eps, metric)


def fit_full(points: DataFrame, eps: float, modes: int, metric: str = "euclidean", solver: str | None = None, drop_below: float = 0.0, dims: int | None = None) -> Model | tuple[np.ndarray, DataFrame]:
    """The map of all points.

    Local solvers return a ``Model``; ``solver="distributed"`` returns the
    values and a table ``i, psi`` and never holds the points.
    """
    if solver == "distributed":
        edges = spool(K.sparse_affinity(points, eps, drop_below or 1e-9, metric, dims=dims), "edges")
        return distributed_modes(edges, spool(K.degrees(edges), "degrees"), modes)
    ids, x = collect_points(points, planner.LOCAL_POINTS if drop_below or solver else planner.SCAN_POINTS)
    if not drop_below and not solver and len(ids) > planner.DENSE_POINTS:
        return fit_scanned(points.sparkSession, ids, x, eps, modes, metric)
    if drop_below and len(ids) > planner.DENSE_POINTS:
        pairs = P.pairs_within(points, K.cut_radius(eps, drop_below), metric, dims=dims)
        edges = K.local_edges(ids, pairs, eps)
        lam, psi, deg = local_modes(edges, np.ones(len(ids)), modes, solver or "lanczos")
        return Model(ids, x, np.ones(len(ids)), lam, psi, deg, eps, metric)
    return fit_local(ids, x, eps, modes, metric, drop_below=drop_below)


def assign(points: DataFrame, ids: np.ndarray, vecs: np.ndarray, metric: str = "euclidean", index: str | None = None) -> DataFrame:
    """``id, lid, d``: nearest landmark of each point, ties to the smallest landmark id.  Map-only.

    ``index="pivot"`` skips the landmarks that the triangle inequality rules out.
    """
    order = np.argsort(ids, kind="stable")
    lids, z = ids[order], vecs[order]
    block = metrics.get(metric).block
    tree = PivotIndex(z, metric) if index == "pivot" else None

    def run(batches):
        for b in batches:
            x = P.matrix(b.column("vec"))
            if not len(x):
                continue
            if tree is None:
                d = block(x, z)
                at = d.argmin(1)
                best = d[np.arange(len(x)), at]
            else:
                at, best = tree.nearest(x)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(lids[at]), pa.array(best)], names=["id", "lid", "d"])

    return points.select("id", "vec").mapInArrow(run, "id long, lid long, d double")


def multiplicities(assignment: DataFrame) -> DataFrame:
    return assignment.groupBy("lid").agg(F.count("*").alias("mult"))


def fit_reduced(points: DataFrame, landmark_ids: DataFrame | np.ndarray, eps: float, modes: int, metric: str = "euclidean", weights: str = "cells", most: int = 20_000) -> Model:
    """Density-weighted map over landmarks: counts come from one pass over all points, the rest is of landmark size.

    ``weights="none"`` sets all counts to one (the ablation).
    """
    spark = points.sparkSession
    if isinstance(landmark_ids, np.ndarray):
        landmark_ids = spark.createDataFrame(pa.table({"lid": pa.array(landmark_ids)}))
    chosen = points.join(landmark_ids.select(F.col("lid").alias("id")).distinct(), "id", "left_semi")
    ids, z = collect_points(chosen, most)
    c = np.ones(len(ids))
    if weights == "cells":
        got = multiplicities(assign(points, ids, z, metric)).toArrow()
        c = np.zeros(len(ids))
        c[np.searchsorted(ids, got["lid"].to_numpy())] = got["mult"].to_numpy()
        if (c == 0).any():  # landmarks that coincide with a smaller id own no cell
            ids, z, c = ids[c > 0], z[c > 0], c[c > 0]
    return fit_local(ids, z, eps, modes, metric, c, kind="reduced")


def fit_hybrid(full: Model, landmark_ids: np.ndarray, counts: np.ndarray) -> Model:
    """Modes of the full map kept at the landmarks, with cell counts as weights for the extension."""
    at = np.searchsorted(full.ids, np.sort(landmark_ids))
    return Model(full.ids[at], full.vecs[at], counts, full.lam, full.psi[at], full.deg[at], full.eps, full.metric, kind="hybrid")


def nystrom(x: np.ndarray, model: Model, k: int, radius: float | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Coordinates, nearest index and its distance; exponents are shifted by their row's best, so far points give no NaN."""
    d = metrics.get(model.metric).block(x, model.vecs)
    at = d.argmin(1)
    best = d[np.arange(len(x)), at]
    e = (best[:, None] ** 2 - d**2) / (2 * model.eps)
    w = np.exp(e) * model.counts
    if radius is not None:
        w[(d > radius) & (d > best[:, None])] = 0.0
    return (w @ model.coordinates(k)) / w.sum(1, keepdims=True) / model.lam[1 : k + 1], at, best


class PivotIndex:
    """Fitted points in cells around about sqrt(M) of them, so that a search need not measure all M distances.

    A cell whose pivot is farther than the radius plus the cell's own reach
    holds nothing within the radius, in any metric.
    """

    def __init__(self, vecs: np.ndarray, metric: str, pivots: int | None = None):
        self.metric = metrics.get(metric)
        if not self.metric.is_metric:
            raise ValueError(f"{self.metric.name} is no metric: it cannot be searched by pivots")
        self.vecs = vecs
        want = min(len(vecs), pivots or max(1, round(len(vecs) ** 0.5)))
        at, near = [0], self.metric.block(vecs, vecs[:1])[:, 0]
        while len(at) < want and near.max() > 0:  # farthest first: cells stay small
            at.append(int(near.argmax()))
            near = np.minimum(near, self.metric.block(vecs, vecs[at[-1] :][:1])[:, 0])
        self.centre = vecs[at]
        d = self.metric.block(vecs, self.centre)
        cell = d.argmin(1)
        self.members = [np.flatnonzero(cell == c) for c in range(len(at))]
        self.reach = np.array([d[m, c].max() if len(m) else -np.inf for c, m in enumerate(self.members)])

    def search(self, x: np.ndarray, radius: float):
        """``(rows, members, distances)`` for each cell that some rows have to look into."""
        far = self.metric.block(x, self.centre)
        slack = 1e-9 * (1.0 + np.abs(far))
        for c, own in enumerate(self.members):
            rows = np.flatnonzero(far[:, c] <= radius + self.reach[c] + slack[:, c])
            if len(own) and len(rows):
                yield rows, own, self.metric.block(x[rows], self.vecs[own])

    def nearest(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index and distance of the nearest fitted point of each row, ties to the smallest index; cells too far are not looked into."""
        far = self.metric.block(x, self.centre)
        at, best = np.full(len(x), len(self.vecs)), np.full(len(x), np.inf)
        low = np.maximum(far - self.reach[None, :], 0.0)
        order = np.argsort(low, axis=1, kind="stable")
        for turn in range(far.shape[1]):
            cell = order[:, turn]
            open_ = np.flatnonzero(low[np.arange(len(x)), cell] <= best + 1e-9 * (1.0 + np.where(np.isfinite(best), best, 0.0)))
            if not len(open_):
                break
            for c in np.unique(cell[open_]).tolist():
                rows, own = open_[cell[open_] == c], self.members[c]
                if not len(own):
                    continue
                d = self.metric.block(x[rows], self.vecs[own])
                got = d.argmin(1)
                d, got = d[np.arange(len(rows)), got], own[got]
                better = (d < best[rows]) | ((d == best[rows]) & (got < at[rows]))
                best[rows[better]], at[rows[better]] = d[better], got[better]
        return at, best


def nystrom_indexed(x: np.ndarray, model: Model, index: PivotIndex, k: int, radius: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The truncated extension over an index: only fitted points that may lie within ``radius`` are measured.

    A point with none within the radius takes its nearest fitted point, as in
    ``nystrom(radius=...)``.
    """
    at, best = index.nearest(x)
    top, total = np.zeros((len(x), k)), np.zeros(len(x))
    for rows, own, d in index.search(x, radius):
        w = np.exp((best[rows, None] ** 2 - d**2) / (2 * model.eps)) * model.counts[own]
        w[(d > radius) & (d > best[rows, None])] = 0.0
        top[rows] += w @ model.psi[own, 1 : k + 1]
        total[rows] += w.sum(1)
    alone = total == 0
    top[alone], total[alone] = model.psi[at[alone], 1 : k + 1], 1.0
    return top / total[:, None] / model.lam[1 : k + 1], at, best


def extension_weights(new: DataFrame, model: Model, least: float) -> DataFrame:
    """``id, lid, w``: the normalised weights of at least ``least`` in each point's extension.  Map-only."""

    def run(batches):
        for b in batches:
            for s in range(0, b.num_rows, step := max(1, 4_000_000 // max(1, model.size))):
                part = b.slice(s, step)
                d = metrics.get(model.metric).block(P.matrix(part.column("vec")), model.vecs)
                w = np.exp((d.min(1, keepdims=True) ** 2 - d**2) / (2 * model.eps)) * model.counts
                w /= w.sum(1, keepdims=True)
                r, c = np.nonzero(w >= least)
                yield pa.RecordBatch.from_arrays([part.column("id").take(pa.array(r)), pa.array(model.ids[c]), pa.array(w[r, c])], names=["id", "lid", "w"])

    return new.select("id", "vec").mapInArrow(run, "id long, lid long, w double")


def extend(new: DataFrame, model: Model, k: int, reach: float | None = None, radius: float | None = None, strategy: str | None = None, index: str | None = None) -> DataFrame:
    """Embed new points; ``extrapolated`` where the nearest fitted point is farther than ``reach`` (default sqrt(eps)).

    One map-only stage while the model fits in a task; a larger one is joined
    in blocks.  ``radius`` cuts the sum off; with ``index="pivot"`` the points
    beyond it are not even measured.  Works on streams.
    """
    reach = model.eps**0.5 if reach is None else reach
    if index not in (None, "pivot") or (index and radius is None):
        raise ValueError("index must be None, or 'pivot' with a radius")
    tree = PivotIndex(model.vecs, model.metric) if index else None
    if (strategy or planner.choose_extension(model.size, model.vecs.shape[1], k)) == "tiles":
        return _extend_tiles(new, model, k, reach)

    def run(batches):
        for b in batches:
            for s in range(0, b.num_rows, step := max(1, 8_000_000 // max(1, model.size))):
                part = b.slice(s, step)
                x = P.matrix(part.column("vec"))
                psi, at, best = nystrom(x, model, k, radius) if tree is None else nystrom_indexed(x, model, tree, k, radius)
                yield pa.RecordBatch.from_arrays(
                    [part.column("id"), pa.ListArray.from_arrays(pa.array(np.arange(0, psi.size + 1, k, dtype=np.int32)), pa.array(psi.ravel())), pa.array(model.ids[at]), pa.array(best), pa.array(best > reach), pa.array([model.version] * len(at))],
                    names=["id", "psi", "nearest_lid", "d_min", "extrapolated", "model_version"],
                )

    return new.select("id", "vec").mapInArrow(run, EMBEDDING)


def _extend_tiles(new: DataFrame, model: Model, k: int, reach: float, block_rows: int = 2000) -> DataFrame:
    """The same sums by model block: each leaves its best exponent and sums relative to it, which merge associatively."""
    spark = new.sparkSession
    blocks = -(-model.size // block_rows)
    t = pa.table({"b": pa.array(np.arange(model.size) // block_rows, pa.int32()), "lid": pa.array(model.ids), "z": pa.array(list(model.vecs), pa.list_(pa.float64())), "c": pa.array(model.counts), "psi": pa.array(list(model.coordinates(k)), pa.list_(pa.float64()))})
    parts = spark.createDataFrame(t)
    sent = new.select("id", "vec", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("b"), F.pmod(F.xxhash64("id"), F.lit(64)).cast("int").alias("s"))
    spread = parts.select("*", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("s"))
    block, eps = metrics.get(model.metric).block, model.eps

    def run(left, right):
        if not left.num_rows or not right.num_rows:
            return pa.table({"id": pa.array([], pa.int64()), "best": pa.array([], pa.float64()), "lid": pa.array([], pa.int64()), "sums": pa.array([], pa.list_(pa.float64()))})
        d = block(P.matrix(left["vec"]), P.matrix(right["z"]))
        at = d.argmin(1)
        best = d[np.arange(len(at)), at]
        w = np.exp((best[:, None] ** 2 - d**2) / (2 * eps)) * right["c"].to_numpy()
        sums = np.concatenate([w.sum(1, keepdims=True), w @ P.matrix(right["psi"])], 1)
        return pa.table({"id": left["id"], "best": pa.array(best), "lid": pa.array(right["lid"].to_numpy()[at]), "sums": pa.array(list(sums), pa.list_(pa.float64()))})

    got = sent.groupBy("b", "s").cogroup(spread.groupBy("b", "s")).applyInArrow(run, "id long, best double, lid long, sums array<double>")
    low = got.groupBy("id").agg(F.min(F.struct("best", "lid")).alias("m"), F.collect_list(F.struct("best", "sums")).alias("ps"))
    scaled = F.transform("ps", lambda p: F.transform(p["sums"], lambda x: x * F.exp((F.col("m.best") * F.col("m.best") - p["best"] * p["best"]) / (2.0 * eps))))
    total = F.aggregate(scaled, F.array_repeat(F.lit(0.0), k + 1), lambda s, p: F.zip_with(s, p, lambda a, b: a + b))
    out = low.select("id", F.col("m.lid").alias("nearest_lid"), F.col("m.best").alias("d_min"), total.alias("t"))
    psi = F.array(*[F.col("t")[c + 1] / F.col("t")[0] / float(model.lam[c + 1]) for c in range(k)])
    return out.select("id", psi.alias("psi"), "nearest_lid", "d_min", (F.col("d_min") > reach).alias("extrapolated"), F.lit(model.version).alias("model_version"))


def project_rest(points: DataFrame, model: Model, k: int, **kw) -> DataFrame:
    """Extend to all fitted-on points that are no landmarks."""
    lids = points.sparkSession.createDataFrame(pa.table({"id": pa.array(model.ids)}))
    return extend(points.join(F.broadcast(lids) if model.size < 1_000_000 else lids, "id", "left_anti"), model, k, **kw)


def extend_by_refit(train: DataFrame, new: DataFrame, eps: float, modes: int, k: int, metric: str = "euclidean") -> DataFrame:
    """Exact and expensive: a full map of old and new points together, its rows for the new ones."""
    both = train.select("id", "vec").unionByName(new.select("id", "vec"))
    return fit_full(both, eps, modes, metric).coords_table(train.sparkSession, k).join(new.select("id"), "id", "left_semi")


def extend_pca(train: DataFrame, coords: DataFrame, new: DataFrame, k: int, components: int) -> DataFrame:
    """Linear interpolation: principal components, one regression per mode."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.regression import LinearRegression

    t = train.join(coords, "id").select("id", array_to_vector("vec").alias("v"), "psi")
    pca = PCA(k=components, inputCol="v", outputCol="f").fit(t)
    t, out = pca.transform(t), pca.transform(new.select("id", array_to_vector("vec").alias("v")))
    for c in range(k):
        out = LinearRegression(featuresCol="f", labelCol="y", predictionCol=f"p{c}").fit(t.withColumn("y", F.col("psi")[c])).transform(out)
    return out.select("id", F.array(*[f"p{c}" for c in range(k)]).alias("psi"))


def extend_pyramid(x: np.ndarray, psi: np.ndarray, new: np.ndarray, eps: float, levels: int = 6, metric: str = "euclidean") -> np.ndarray:
    """Laplacian pyramid: kernel smoothing of what is left, with the bandwidth halved at each level."""
    block = metrics.get(metric).block
    dt, dn = block(x, x), block(new, x)
    left, out, e = psi.copy(), np.zeros((len(new), psi.shape[1])), eps * 2.0**levels
    for _ in range(levels + 1):
        wt, wn = np.exp(-(dt**2) / (2 * e)), np.exp((dn.min(1, keepdims=True) ** 2 - dn**2) / (2 * e))
        smooth = wt @ left / wt.sum(1, keepdims=True)
        out += wn @ left / wn.sum(1, keepdims=True)
        left = left - smooth
        e /= 2
    return out


def footprint(full: Model, reduced: Model) -> dict[str, float]:
    return {"full_bytes": full.nbytes(), "reduced_bytes": reduced.nbytes(), "ratio": full.nbytes() / reduced.nbytes()}


def principal_components(points: DataFrame, k: int) -> DataFrame:
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector, vector_to_array

    t = points.select("id", array_to_vector("vec").alias("v"))
    return PCA(k=k, inputCol="v", outputCol="f").fit(t).transform(t).select("id", vector_to_array("f").alias("psi"))


def random_projection(points: DataFrame, width: int, k: int, seed: int = 0) -> DataFrame:
    """Seeded Gaussian projection, map-only."""
    m = np.random.default_rng(seed).standard_normal((width, k)) / np.sqrt(k)

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(list(P.matrix(b.column("vec")) @ m), pa.list_(pa.float64()))], names=["id", "psi"])

    return points.select("id", "vec").mapInArrow(run, "id long, psi array<double>")


def classical_mds(ids: np.ndarray, x: np.ndarray, k: int, metric: str = "euclidean") -> np.ndarray:
    d2 = metrics.get(metric).block(x, x) ** 2
    b = -0.5 * (d2 - d2.mean(0) - d2.mean(1)[:, None] + d2.mean())
    w, v = np.linalg.eigh(b)
    return fix_signs(v[:, ::-1][:, :k] * np.sqrt(np.maximum(w[::-1][:k], 0)))
