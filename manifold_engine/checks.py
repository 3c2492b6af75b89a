"""Registered checks: operators' results against an independent dense form.

Each query returns the largest deviation of an operator from plain matrix
algebra (general eigenvalue routine on the Markov matrix itself, loops over
rows, textbook superposition), rounded; its SQL is the constant 0.  The dense
forms hold users or landmarks, never events.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import operator_queries as O
from . import queries as Q
from .functions import metrics as D
from .operators import kernel as K
from .operators import landmarks as L
from .operators import maps as M
from .operators import pairs as P
from .operators import perturbation as B
from .operators import spectrum as S
from .sources import points as R
from .spool import shuffle_partitions, spool

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
ZERO = "select 0.0 :: double as gap"


def check(fn):
    QUERIES[fn.__name__] = fn
    ORACLE_SQL[fn.__name__] = ZERO
    return fn


def gap(s, *values: float, digits: int = 6) -> DataFrame:
    return s.createDataFrame([(abs(round(float(max(values)), digits)),)], "gap double")


# dense forms


def distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.sqrt(sum((x[:, None, k] - y[None, :, k]) ** 2 for k in range(x.shape[1])))


def walk(x: np.ndarray, eps: float, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Affinities, weighted degrees and the Markov matrix over weighted points."""
    a = np.exp(-(distances(x, x) ** 2) / (2 * eps))
    deg = a @ counts
    return a, deg, a * counts[None, :] / deg[:, None]


def modes(x: np.ndarray, eps: float, k: int, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Leading values and right vectors of the Markov matrix, the vectors scaled to ``sum c psi^2 = 1``."""
    c = np.ones(len(x)) if counts is None else counts
    lam, v = np.linalg.eig(walk(x, eps, c)[2])
    order = np.argsort(-lam.real)[:k]
    lam, v = lam.real[order], v.real[:, order]
    return lam, v / np.sqrt((c[:, None] * v * v).sum(0))


def extended(y: np.ndarray, x: np.ndarray, eps: float, lam: np.ndarray, psi: np.ndarray, counts: np.ndarray, radius: float = np.inf) -> np.ndarray:
    """The extension of each row by its own sum."""
    out = np.empty((len(y), psi.shape[1]))
    for i, row in enumerate(y):
        d = np.sqrt(((x - row) ** 2).sum(1))
        w = counts * np.exp((d.min() ** 2 - d**2) / (2 * eps)) * ((d <= radius) | (d == d.min()))
        out[i] = w @ psi / w.sum() / lam
    return out


def off_by(a: np.ndarray, b: np.ndarray) -> float:
    """Largest difference of two sets of coordinates, whose columns may differ by their sign."""
    return float(np.abs(a - b * np.sign((a * b).sum(0))).max())


def rows_of(e: DataFrame, col: str = "psi") -> tuple[np.ndarray, np.ndarray]:
    t = e.select("id", col).orderBy("id").toArrow()
    return t["id"].to_numpy(), P.matrix(t[col])


def split(s, d):
    train, test = Q.user_split(s, d)
    return train, test, *M.collect_points(train, 60_000), *M.collect_points(test, 60_000)


@check
def nystrom_full_gap(s, d):
    train, test, _, x, _, y = split(s, d)
    got = rows_of(M.extend(test, M.fit_full(train, Q.EPS, Q.MODES + 1), Q.MODES))[1]
    lam, psi = modes(x, Q.EPS, Q.MODES + 1)
    return gap(s, off_by(got, extended(y, x, Q.EPS, lam[1:], psi[:, 1:], np.ones(len(x)))))


@check
def nystrom_tiles_gap(s, d):
    train, test, _, x, _, y = split(s, d)
    got = rows_of(M._extend_tiles(test, M.fit_full(train, Q.EPS, Q.MODES + 1), Q.MODES, Q.NEAR, block_rows=37))[1]
    lam, psi = modes(x, Q.EPS, Q.MODES + 1)
    return gap(s, off_by(got, extended(y, x, Q.EPS, lam[1:], psi[:, 1:], np.ones(len(x)))))


def plane_gap(s, d, cut: float = np.inf, **kw) -> DataFrame:
    """Every event's extension over the landmarks against its own sum, in the tasks; only the largest difference comes back."""
    p, m = Q.plane_model(s, d)
    cells = {r["lid"]: r["n"] for r in M.assign(p, m.ids, m.vecs).groupBy("lid").agg(F.count("*").alias("n")).collect()}
    c = np.array([cells[i] for i in m.ids.tolist()], float)
    lam, psi = modes(m.vecs, Q.PLANE_EPS, 3, c)
    psi = psi * np.sign((psi * m.psi[:, :3]).sum(0))
    x, eps = m.vecs, Q.PLANE_EPS

    def differ(batches):
        for b in batches:
            want = extended(P.matrix(b.column("vec")), x, eps, lam[1:], psi[:, 1:], c, cut)
            yield pa.RecordBatch.from_arrays([pa.array([float(np.abs(want - P.matrix(b.column("psi"))).max()) if len(want) else 0.0])], names=["gap"])

    e = M.extend(p, m, 2, **kw).select("id", "psi").join(p, "id")
    return e.select("vec", "psi").mapInArrow(differ, "gap double").agg(F.abs(F.round(F.max("gap"), 6)).alias("gap"))


@check
def nystrom_reduced_gap(s, d):
    return plane_gap(s, d)


@check
def nystrom_truncated_gap(s, d):
    r = K.cut_radius(Q.PLANE_EPS, 1e-2)
    return plane_gap(s, d, r, radius=r)


@check
def nystrom_indexed_gap(s, d):
    """The truncated sum over the pivot index, which does not measure all landmarks."""
    r = K.cut_radius(Q.PLANE_EPS, 1e-2)
    return plane_gap(s, d, r, radius=r, index="pivot")


@check
def voronoi_indexed_gap(s, d):
    """Assignment over the pivot index: events whose landmark or distance differs."""
    p, ids, z = Q.plane_cells(s, d)
    a, b = M.assign(p, ids, z), M.assign(p, ids, z, index="pivot").toDF("j", "l2", "d2")
    same = F.col("lid").eqNullSafe(F.col("l2")) & (F.abs(F.col("d") - F.col("d2")) < 1e-9)
    return a.join(b, F.col("id") == F.col("j"), "full_outer").agg(F.coalesce(F.sum(F.when(same, 0.0).otherwise(1.0)), F.lit(0.0)).alias("gap"))


@check
def hybrid_gap(s, d):
    p, ids, z, cells = Q.user_cells(s, d)
    every, x = M.collect_points(p, 60_000)
    c = M.multiplicities(cells).orderBy("lid").toArrow()
    at = np.searchsorted(every, c["lid"].to_numpy())
    n = c["mult"].to_numpy().astype(float)
    got = rows_of(M.extend(p, M.fit_hybrid(M.fit_full(p, Q.EPS, Q.MODES + 1), c["lid"].to_numpy(), n), Q.MODES))[1]
    lam, psi = modes(x, Q.EPS, Q.MODES + 1)
    return gap(s, off_by(got, extended(x, x[at], Q.EPS, lam[1:], psi[at, 1:], n)))


@check
def augmented_refit_gap(s, d):
    train, test, i, x, j, y = split(s, d)
    got_ids, got = rows_of(M.extend_by_refit(train, test, Q.EPS, Q.MODES + 1, Q.MODES))
    both = np.argsort(np.concatenate([i, j]))
    lam, psi = modes(np.concatenate([x, y])[both], Q.EPS, Q.MODES + 1)
    where = np.searchsorted(np.concatenate([i, j])[both], got_ids)
    return gap(s, off_by(got, psi[where, 1:]))


@check
def spectrum_gap(s, d):
    m = Q.user_model(s, d)
    lam, psi = modes(m.vecs, Q.EPS, 12)
    low = S.laplacian_table(s, m.lam).orderBy("l").toArrow()["mu"].to_numpy()
    return gap(s, np.abs(lam - m.lam).max(), np.abs(low - (1 - lam)).max(), off_by(m.psi[:, :4], psi[:, :4]))


@check
def solver_gap(s, d):
    """Four solvers against the general routine, to four digits (the distributed ones stop early)."""
    t = Q.QUERIES["solver_agreement"](s, d).orderBy("l").toPandas()
    m = Q.user_model(s, d)
    lam = modes(m.vecs, Q.EPS, 4)[0]
    close = [np.abs(t[c].to_numpy() - lam).max() for c in ("dense", "lanczos")]
    rough = [np.abs(t[c].to_numpy() - lam).max() for c in ("distributed", "mllib")]
    return gap(s, max(close) * 1e3, *rough, digits=3)


@check
def diffusion_distance_gap(s, d):
    m = Q.user_model(s, d)
    lam, psi = modes(m.vecs, Q.EPS, Q.MODES + 1)
    want = distances(psi[:, 1:] * lam[1:], psi[:, 1:] * lam[1:])
    t = S.diffusion_distance(m.coords_table(s, Q.MODES), m.lam[1 : Q.MODES + 1]).toArrow()
    i, j = (np.searchsorted(m.ids, t[c].to_numpy()) for c in "ij")
    return gap(s, np.abs(t["dd"].to_numpy() - want[i, j]).max(), abs(len(i) - m.size * (m.size - 1) // 2))


@check
def dist_rmsd_gap(s, d):
    """Superposition by the textbook rotation, pair by pair, and the batched row form."""
    p = R.planar_paths(s, d)
    ids, x = M.collect_points(p, 60_000)
    space = np.concatenate([x.reshape(len(x), -1, 2), np.zeros((len(x), x.shape[1] // 2, 1))], 2)
    space = space - space.mean(1, keepdims=True)
    t = Q.QUERIES["dist_rmsd"](s, d).toArrow()
    i, j = (np.searchsorted(ids, t[c].to_numpy()) for c in "ij")
    worst = 0.0
    for a, b, v in zip(i.tolist(), j.tolist(), t["d"].to_pylist()):
        u, _, vt = np.linalg.svd(space[a].T @ space[b])
        r = u @ np.diag([1.0, 1.0, np.sign(np.linalg.det(u @ vt))]) @ vt
        worst = max(worst, abs(float(np.sqrt(((space[a] @ r - space[b]) ** 2).sum() / space.shape[1])) - v))
    flat = space.reshape(len(x), -1)
    rows = np.abs(D.rmsd_rows(flat[i], flat[j]) - t["d"].to_numpy()).max()
    return gap(s, worst, rows, digits=5)


def moved_points(s, d):
    """Users' points before and after every user is put on its landmark."""
    p, ids, z, cells = Q.user_cells(s, d)
    every, x = M.collect_points(p, 1_000_000)
    c = cells.orderBy("id").toArrow()
    return every, x, z[np.searchsorted(ids, c["lid"].to_numpy())]


def moved(s, d):
    """Their matrices of distances."""
    every, x, y = moved_points(s, d)
    return every, x, distances(x, x), distances(y, y)


def strip_sums(s, x: np.ndarray, y: np.ndarray, eps: float) -> np.ndarray:
    """Squares of the first-order and the exact shift of the Markov matrix and of their difference, summed: whole rows of the matrices, a few at a time, dealt to tasks."""
    strips = list(P.strips(len(x), len(x), P.CACHED))
    tasks = min(len(strips), 4 * shuffle_partitions(s))

    def run(batches):
        for b in batches:
            for k in b.column("id").to_pylist():
                sums = np.zeros(3)
                for at in strips[k::tasks]:
                    d0, d1 = distances(x[at], x), distances(y[at], y)
                    a0, a1 = np.exp(-(d0**2) / (2 * eps)), np.exp(-(d1**2) / (2 * eps))
                    first = -d0 * (d1 - d0) / eps * a0
                    deg, ddeg = a0.sum(1), first.sum(1)
                    lin = first / deg[:, None] - (ddeg / deg**2)[:, None] * a0
                    exact = a1 / a1.sum(1)[:, None] - a0 / deg[:, None]
                    sums += [(v**2).sum() for v in (lin, exact, lin - exact)]
                yield pa.RecordBatch.from_arrays([pa.array([k]), pa.array([sums.tolist()], pa.list_(pa.float64()))], names=["k", "sums"])

    t = s.range(0, tasks, 1, tasks).mapInArrow(run, "k long, sums array<double>").toArrow().sort_by("k")
    return P.matrix(t["sums"]).sum(0)


@check
def markov_shift_exact_gap(s, d):
    """The three figures of ``markov_shift_exact`` from whole matrices."""
    got = Q.QUERIES["markov_shift_exact"](s, d).first()
    _, x, y = moved_points(s, d)
    sums = strip_sums(s, x, y, Q.EPS)
    want = np.sqrt(sums / len(x) ** 2)
    return gap(s, *[abs(g - w) for g, w in zip(got, want)], digits=8)


@check
def eigenvalue_shift_gap(s, d):
    """Predicted shifts of the kept values under both bases, and of every user with all modes, from whole matrices."""
    got = Q.QUERIES["eigenvalue_shift"](s, d).orderBy("l").toPandas()
    _, x, d0, d1 = moved(s, d)
    a = np.exp(-(d0**2) / (2 * Q.EPS))
    da = -d0 * (d1 - d0) / Q.EPS * a
    deg, ddeg = a.sum(1), da.sum(1)
    dm = da / deg[:, None] - (ddeg / deg**2)[:, None] * a
    _, psi = modes(x, Q.EPS, Q.MODES + 1)
    worst = []
    for basis, left in (("plain", psi), ("stationary", psi * deg[:, None])):
        want = (left * (dm @ psi)).sum(0) / (left * psi).sum(0)
        worst.append(np.abs(want[1:] - got[basis].to_numpy()).max())
    return gap(s, *worst)


@check
def stream_state_gap(s, d):
    """Basin changes that the stateful stream or the batch window finds alone."""
    a, b = (O.QUERIES[q](s, d).select("user_id", "id", "was", "now") for q in ("stream_state", "state_batch"))
    a, b = spool(a, "stream"), spool(b, "batch")
    return a.exceptAll(b).union(b.exceptAll(a)).agg(F.count("*").cast("double").alias("gap"))


@check
def tree_cover_gap(s, d):
    """Users that some growth order leaves farther than the radius from every landmark of its tree, over all orders."""
    t = Q.QUERIES["pst_growth_orders"](s, d)
    return t.agg(F.sum("uncovered").cast("double").alias("gap"))


@check
def boruvka_gap(s, d):
    """The distributed forest of a graph in several pieces: edges missing to a spanning forest, and users left uncovered."""
    p, pr = Q.user_pairs(s, d)
    graph = spool(L.threshold_graph(pr, Q.CLOSE), "graph")
    tree = spool(L.boruvka_rounds(graph, 3), "tree")
    pieces = Q.components(graph.select(F.col("i").alias("u"), F.col("j").alias("v")).union(p.select("id", "id"))).select("comp").distinct().count()
    ids, z = L.vectors_of(p, L.prune_edges(p, graph, tree))
    return gap(s, abs(p.count() - pieces - tree.distinct().count()), L.check_cover(p, ids, z, Q.CLOSE).count())


@check
def grid_crowd_gap(s, d):
    """The cell join with every cell dealt into blocks: pairs that it or the tile join finds alone."""
    p = Q.users(s, d)
    old, P.CROWD = P.CROWD, 3
    try:
        a = spool(P.grid_pairs(p, Q.NEAR, 2).select("i", "j"), "grid")
    finally:
        P.CROWD = old
    b = spool(P.all_pairs(p, within=Q.NEAR).select("i", "j"), "tile")
    return a.exceptAll(b).union(b.exceptAll(a)).agg(F.count("*").cast("double").alias("gap"))
