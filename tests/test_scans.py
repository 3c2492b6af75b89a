"""Queries over pairs of users write no table of pairs on the way, and the scans give what the tables of pairs gave."""

import os

import pyarrow.parquet as pq
import pytest

from manifold_engine import operator_queries, queries
from manifold_engine import spool as spools

KNOWN = queries.QUERIES | operator_queries.QUERIES
USERS = 150  # of sf0.01

LINEAR = [
    "components",
    "affinity",
    "affinity_shift",
    "distance_shift",
    "bandwidth_curve",
    "op_quantile_sketch",
    "stationary",
    "degrees",
    "stationary_balance",
    "threshold_graph",
    "markov_shift_rowsum",
    "degree_shift",
    "markov_shift",
    "op_anti_cover",
    "landmark_isolated",
    "landmark_components",
    "markov",
    "laplacian",
    "laplacian_rowsum",
    "markov_rowsum",
    "largest_component",
    "markov_shift_exact",
    "op_knn_rank",
]


def tables(spark):
    top = spools._own(spark).removeprefix("file://")
    return {t: sum(pq.ParquetFile(f"{top}/{t}/{f}").metadata.num_rows for f in os.listdir(f"{top}/{t}") if f.endswith(".parquet")) for t in os.listdir(top)} if os.path.isdir(top) else {}


@pytest.mark.parametrize("name", LINEAR)
def test_no_pairs_written(spark, sf01, name):
    before = tables(spark)
    assert KNOWN[name](spark, sf01).count()
    new = {t: n for t, n in tables(spark).items() if t not in before}
    assert new and max(new.values()) <= 20 * USERS, new


def test_all_pairs_come_in_strips(spark, monkeypatch):
    """A task hands pairs on in bounded batches, each pair once."""
    import numpy as np

    from manifold_engine.operators import pairs as P

    got = []
    monkeypatch.setattr(P, "_tiled", lambda points, fn, out, tiles: got.append(fn))
    P.all_pairs(spark.createDataFrame([(1, [0.0])], "id long, vec array<double>"))
    rng = np.random.default_rng(0)
    a, b = np.arange(0, 6_000, 2), np.arange(1, 4_001, 2)
    batches = list(got[0](a, rng.random((len(a), 2)), b, rng.random((len(b), 2)), False))
    assert max(x.num_rows for x in batches) <= P.STRIP and sum(x.num_rows for x in batches) == len(a) * len(b)
    assert all((x["i"].to_numpy() < x["j"].to_numpy()).all() for x in batches)


def test_near_forest_keeps_components(spark):
    """A few edges a point leave the components that all near pairs have."""
    import numpy as np

    from manifold_engine.graph import components
    from manifold_engine.operators import pairs as P

    x = np.random.default_rng(1).random((400, 2))
    p = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>").localCheckpoint()
    for r in (0.05,):
        want = components(P.all_pairs(p, within=r).select("i", "j"), "i", "j").collect()
        edges = P.near_forest(p, r, tiles=3).localCheckpoint()
        assert sorted(components(edges).collect()) == sorted(want) and edges.count() <= 3 * 2 * 400


def test_coverage_needs_no_modes(spark, sf, monkeypatch):
    def refuse(*a, **k):
        raise AssertionError("a map was fitted")

    monkeypatch.setattr(queries.M, "fit_full", refuse)
    assert KNOWN["coverage_flag"](spark, sf).count()


def test_scanned_fit_equals_local(spark):
    """Modes of affinities that are computed anew in each product are those of the matrix."""
    import numpy as np

    from manifold_engine.operators import maps as M

    x = np.random.default_rng(2).random((300, 2))
    ids = np.arange(300)
    a, b = M.fit_local(ids, x, 0.05, 5), M.fit_scanned(spark, ids, x, 0.05, 5)
    assert np.abs(a.lam - b.lam).max() < 1e-9 and np.abs(a.psi - b.psi).max() < 1e-7


def test_tree_by_scans_equals_tree_of_edges(spark):
    import numpy as np

    from manifold_engine.operators import landmarks as L
    from manifold_engine.operators import pairs as P

    x = np.random.default_rng(3).random((120, 2))
    p = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>").localCheckpoint()
    graph = L.threshold_graph(P.all_pairs(p, within=0.25), 0.25)
    roots = L.component_roots(p, graph)
    assert sorted(map(str, L.near_tree_in_rounds(p, 0.25, roots).collect())) == sorted(map(str, L.tree_in_rounds(graph, roots, "min_id").collect()))


def test_exact_gap_holds_no_matrix(spark, sf, monkeypatch):
    from manifold_engine import checks

    def refuse(*a, **k):
        raise AssertionError("whole matrices were made")

    monkeypatch.setattr(checks, "moved", refuse)
    assert checks.QUERIES["markov_shift_exact_gap"](spark, sf).first()[0] == 0


def test_pca_fits_by_scans(spark, sf, monkeypatch):
    """``extend_pca`` beyond the dense size holds no affinity."""
    from manifold_engine.plans import planner

    def refuse(*a, **k):
        raise AssertionError("affinities were held")

    monkeypatch.setattr(planner, "DENSE_POINTS", 5)
    monkeypatch.setattr(queries.M, "fit_local", refuse)
    assert KNOWN["extend_pca"](spark, sf).count()


def test_spark_hash_is_numpys(spark):
    import numpy as np
    from pyspark.sql import functions as F

    from manifold_engine.functions import linalg as LA

    rng = np.random.default_rng(4)
    a, b = rng.integers(-(2**62), 2**62, 200), rng.integers(-(2**62), 2**62, 200)
    low, high = np.minimum(a, b), np.maximum(a, b)
    t = spark.createDataFrame(list(zip(low.tolist(), high.tolist())), "i long, j long")
    for seed in (0, 3, -7):
        want = [r[0] for r in t.select(F.xxhash64(F.lit(seed), "i", "j")).collect()]
        assert LA.edge_weights(LA.seeded_hash(seed, low), a, b).tolist() == want


def test_trees_of_points_equal_trees_of_edges():
    """Growth orders over points that hold no edge: star orders give the very trees that stored edges give, the others span."""
    import numpy as np

    from manifold_engine.functions import linalg as LA
    from manifold_engine.functions import metrics as D
    from manifold_engine.operators import landmarks as L

    for seed, r in ((0, 0.1234), (1, 0.3021)):  # no distance of the lattice
        x = np.round(np.random.default_rng(seed).random((200, 2)), 2)
        x[150:] = x[:50]  # copies
        d = D.euclidean_block(x, x)
        i, j = np.nonzero(np.triu(d <= r, 1))
        ids = np.arange(200) * 3 + 5
        stored, near = LA.SymmetricEdges(200, i, j, np.ones(len(i)), np.zeros(200)), LA.NearPoints(ids, x, r, D.euclidean_block)
        for g in ("star_random", "star_depth", "star_breadth", "star_greedy", "random_edge"):
            for a, b in zip(LA.grow_tree(stored, g, 7, seed), LA.grow_tree(near, g, 7, seed)):
                assert np.array_equal(a, b), g
            assert np.array_equal(L.local_pst(ids, stored, g, seed), L.local_pst(ids, near, g, seed))
        _, depth = LA.grow_tree(stored, "star_breadth", 7)
        parent, got = LA.least_tree(near, seed, 7)
        kids = np.flatnonzero(parent >= 0)
        assert np.array_equal(got >= 0, depth >= 0) and (d[kids, parent[kids]] <= r).all() and (got[kids] == got[parent[kids]] + 1).all()


def test_random_edge_draws_among_edges():
    """Of a triangle with a tail, each way to span it comes as often as draws among all open edges make it."""
    import numpy as np

    from manifold_engine.functions import linalg as LA

    g = LA.SymmetricEdges(3, np.array([0, 0, 1]), np.array([1, 2, 2]), np.ones(3), np.zeros(3))
    seen = [tuple(LA.grow_tree(g, "random_edge", 0, seed)[0].tolist()) for seed in range(2_000)]
    # the first of two edges, then one of two: both from 0 in half of the draws, else the other of 1 and 2 is the parent
    assert abs(seen.count((-1, 0, 0)) / 2_000 - 0.5) < 0.05 and abs(seen.count((-1, 0, 1)) / 2_000 - 0.25) < 0.05


@pytest.mark.parametrize("r", [0.06, 0.25])
def test_rounds_by_scans_equal_rounds_of_edges(spark, r):
    import numpy as np

    from manifold_engine.functions import linalg as LA
    from manifold_engine.functions import metrics as D
    from manifold_engine.operators import landmarks as L
    from manifold_engine.operators import pairs as P

    x = np.random.default_rng(3).random((120, 2))
    ids = np.arange(120)
    p = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>").localCheckpoint()
    graph = L.threshold_graph(P.all_pairs(p, within=r), r).localCheckpoint()
    roots = L.component_roots(p, graph)
    assert sorted(map(str, L.near_tree_in_rounds(p, r, roots, parent_rule="max_reach").collect())) == sorted(map(str, L.tree_in_rounds(graph, roots, "max_reach").collect()))
    tree = L.near_boruvka_rounds(spark, ids, x, r, 3)
    assert sorted(tree.collect()) == sorted(L.boruvka_rounds(graph, 3).collect())
    lids = np.sort(L.prune_edges(p, tree, tree).toArrow()["lid"].to_numpy())
    assert np.array_equal(lids, np.sort(L.local_pst(ids, LA.NearPoints(ids, x, r, D.euclidean_block), "boruvka", 3)))
    z = x[lids]
    near = D.euclidean_block(z, z) <= r
    np.fill_diagonal(near, False)
    assert L.check_landmark_graph(lids, z, r)["isolated"] == (~near.any(1)).sum()
    assert L.uncovered(x, z[:4], r) == (D.euclidean_block(x, z[:4]).min(1) > r).sum()


def test_growth_orders_hold_no_edges(spark, sf, monkeypatch):
    """``pst_growth_orders`` neither writes pairs nor collects edges nor makes a matrix of landmarks in the driver."""

    def refuse(*a, **k):
        raise AssertionError("edges were held")

    monkeypatch.setattr(queries.K, "local_edges", refuse)
    monkeypatch.setattr(queries, "user_pairs", refuse)
    got = KNOWN["pst_growth_orders"](spark, sf).collect()
    assert len(got) == 9 and all(r.uncovered == 0 and r.m > 0 for r in got)
    assert {r.growth: r.m for r in got}["boruvka"] == {r.growth: r.m for r in got}["boruvka_rounds"]


def test_ordered_pairs_are_short_on_disk(spark, tmp_path):
    """Every ordered pair and the diagonal once, with its value, and ids that take a fraction of a byte a row in the file."""
    import numpy as np

    from manifold_engine.operators import pairs as P

    x = np.random.default_rng(5).random((1_300, 2))
    p = spark.createDataFrame([(i * 7, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>").localCheckpoint()
    P.pair_table(p, lambda d, u, v: [d + u[..., 0] - 2 * v[..., 1]], ["v"], ordered=True, tiles=2).write.parquet(f"{tmp_path}/out")
    t = spark.read.parquet(f"{tmp_path}/out").toArrow()
    i, j = t["i"].to_numpy() // 7, t["j"].to_numpy() // 7
    assert len(t) == len(x) ** 2 and len(np.unique(i * len(x) + j)) == len(t)
    want = np.sqrt(((x[i] - x[j]) ** 2).sum(1)) + x[i, 0] - 2 * x[j, 1]
    assert np.abs(t["v"].to_numpy() - want).max() < 1e-9
    size = 0
    for f in tmp_path.glob("out/*.parquet"):
        m = pq.ParquetFile(f).metadata
        size += sum(m.row_group(g).column(c).total_compressed_size for g in range(m.num_row_groups) for c in (0, 1))
    assert size < 0.2 * len(t)


@pytest.mark.parametrize("name", ["laplacian", "markov"])
def test_rows_travel_as_lists(spark, sf, name):
    """Pairs leave Python as a row for each run, and are dealt out in the JVM."""
    df = KNOWN[name](spark, sf)
    assert "posexplode(" in df._jdf.queryExecution().optimizedPlan().toString()
    assert df.count() == df.select("i", "j").distinct().count() > 0


def test_runs_become_lists():
    import pyarrow as pa

    from manifold_engine.operators import pairs as P

    b = pa.RecordBatch.from_pydict({"i": [4, 4, 9, 4], "j": [1, 2, 3, 5], "v": [0.5, 1.5, 2.5, 3.5]})
    assert P.packed(b).to_pydict() == {"i": [4, 9, 4], "j": [[1, 2], [3], [5]], "v": [[0.5, 1.5], [2.5], [3.5]]}
    assert P.packed(b.slice(0, 0)).num_rows == 0


def test_rounding_equals_rounds(spark):
    """Rounding without decimals gives, bit by bit, what ``round`` gives, ties, nulls, huge and undefined numbers included."""
    import numpy as np
    from pyspark.sql import functions as F

    rng = np.random.default_rng(6)
    x = np.concatenate([rng.random(20_000) * 10.0 ** rng.integers(-9, 12, 20_000), (rng.integers(0, 10**6, 2_000) + 0.5) / 1e6, (rng.integers(0, 10**6, 2_000) + 0.5) / 1e9, [0.0, 5e-7, 1e300, np.inf, np.nan]])
    t = spark.createDataFrame([(v,) for v in [*x.tolist(), *(-x).tolist(), None]], "x double")
    for digits in (6, 8, 9):
        same = queries.r6("x", digits).eqNullSafe(F.round("x", digits) + F.lit(0.0))
        assert t.where(~same).count() == 0
        assert "rint" in t.select(queries.r6("x", digits))._jdf.queryExecution().optimizedPlan().toString().lower()


@pytest.mark.parametrize("tiles", [1, 3])
def test_unordered_pairs_are_short_on_disk(spark, tmp_path, tiles):
    """Every unordered pair once, smaller id first, with its value, and ids that take a fraction of a byte a row in the file."""
    import numpy as np

    from manifold_engine.operators import pairs as P

    x = np.random.default_rng(5).random((1_700, 2))
    p = spark.createDataFrame([(i * 7, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>").localCheckpoint()
    P.pair_table(p, lambda d, u, v: [d + u[..., 0] - 2 * v[..., 1]], ["v"], tiles=tiles).write.parquet(f"{tmp_path}/out")
    t = spark.read.parquet(f"{tmp_path}/out").toArrow()
    i, j = t["i"].to_numpy() // 7, t["j"].to_numpy() // 7
    assert len(t) == len(x) * (len(x) - 1) // 2 and len(np.unique(i * len(x) + j)) == len(t) and (i < j).all()
    want = np.sqrt(((x[i] - x[j]) ** 2).sum(1)) + x[i, 0] - 2 * x[j, 1]
    assert np.abs(t["v"].to_numpy() - want).max() < 1e-9
    if tiles > 1:
        files = [pq.ParquetFile(f).metadata for f in tmp_path.glob("out/*.parquet")]
        size = sum(m.row_group(g).column(c).total_compressed_size for m in files for g in range(m.num_row_groups) for c in (0, 1))
        assert size < 1.2 * len(t)  # a third of these pairs are within a block
    cut = P.all_pairs(p, within=0.1, tiles=tiles).toArrow()
    assert len(cut) == (np.triu(np.sqrt(((x[:, None] - x[None]) ** 2).sum(2)) <= 0.1, 1)).sum()


def test_exact_gap_is_no_work_of_the_driver(spark, sf, monkeypatch):
    from manifold_engine import checks

    driver, made = os.getpid(), checks.distances

    def elsewhere(x, y):
        assert os.getpid() != driver, "distances were made in the driver"
        return made(x, y)

    monkeypatch.setattr(checks, "distances", elsewhere)
    assert checks.QUERIES["markov_shift_exact_gap"](spark, sf).first()[0] == 0


@pytest.mark.parametrize("name", ["all_pairs", "affinity_shift", "laplacian", "markov", "stationary_balance"])
def test_pairs_keep_no_marks_of_nulls(spark, sf, name):
    df = KNOWN[name](spark, sf)
    assert not any(f.nullable for f in df.schema), df.schema
