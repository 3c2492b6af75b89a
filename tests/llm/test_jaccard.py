import random
from fractions import Fraction

from manifold_engine.llm import jaccard as J


def _run(spark, docs, **kw):
    d = spark.createDataFrame(docs, "doc_id long, text string")
    return sorted((tuple(r) for r in J.near_groups(d, **kw).collect()), key=str)


def test_bounds():
    t = Fraction("0.85")
    for a in range(1, 60):
        for b in range(1, 60):
            c = J.need(a, b, t)
            assert c >= t * (a + b - c) and not (c - 1) >= t * (a + b - c + 1)
            if c <= min(a, b):
                assert b in J.partner_sizes(a, t)


def test_real_table(spark, sf):
    docs = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    for n, t, kw in ((4, 0.85, {}), (5, 0.8, {"layout": {"group_bytes": 20_000, "groups_a_bucket": 2, "fan": 4}})):
        assert _run(spark, docs, n=n, threshold=t, **kw) == sorted(J.brute_force(docs, n, t), key=str)


def test_random_families(spark):
    rng = random.Random(4)
    docs = []
    for f in range(6):
        base = [f"w{rng.randrange(400)}" for _ in range((9, 14, 30, 60, 90, 18)[f])]
        for _ in range(14):
            w = list(base)
            for _ in range(rng.randrange(0, 3)):
                i = rng.randrange(len(w))
                w[i : i + rng.randrange(2)] = [f"x{rng.randrange(30)}"]
            docs.append(" ".join(w))
    rng.shuffle(docs)
    docs = list(enumerate(docs))
    for n, t in ((1, 0.6), (2, 0.8), (4, 0.85)):
        want = sorted(J.brute_force(docs, n, t), key=str)
        assert len({r[2] for r in want}) < len(docs)
        assert _run(spark, docs, n=n, threshold=t) == want


def _letters(n, slots=24, seed=9):
    """Form letters: fixed text around slots of three variants each, so unlinked letters share most n-grams."""
    rng = random.Random(seed)
    return [(i, " ".join(f"f{s}a f{s}b f{s}c f{s}d v{s}{rng.randrange(3)}" for s in range(slots))) for i in range(n)]


def test_form_letters_compare_few_pairs(spark):
    """The pairs that are compared grow with the letters, not with their square."""
    docs = _letters(150) + [(1000 + i, t.replace("f3a", "g3a")) for i, t in _letters(12)]
    assert _run(spark, docs, n=4, threshold=0.85) == sorted(J.brute_force(docs, 4, 0.85), key=str)
    counts = {}
    for n in (500, 2000):
        report: dict = {}
        _run(spark, _letters(n), n=4, threshold=0.85, report=report)
        counts[n] = report
    assert sum(counts[2000].values()) < 6 * sum(counts[500].values()) and counts[2000]["third"] < 20 * 2000


def test_blocks_and_visits(spark, monkeypatch):
    """Lists cut into many blocks, with one large component that visits them."""
    monkeypatch.setattr(J._across, "__defaults__", (8,))
    docs = _letters(90, slots=8) + [(500 + i, " ".join(f"f{s}a f{s}b f{s}c f{s}d v{s}0" for s in range(8)) + f" tail{i} x") for i in range(60)]
    assert _run(spark, docs, n=2, threshold=0.8) == sorted(J.brute_force(docs, 2, 0.8), key=str)


def test_one_id_with_several_texts(spark):
    a, b = (" ".join(f"{c}{i}" for i in range(40)) for c in "ab")
    near = b.replace("b39", "z")
    docs = [(1, a), (1, b), (7, b), (9, near), (12, a + " q"), (20, "other words"), (20, "more of them here"), (21, "more of them here")]
    assert _run(spark, docs, n=4, threshold=0.85) == sorted(J.brute_force(docs, 4, 0.85), key=str)


def test_edges(spark):
    docs = [(5, "One two"), (3, "one TWO"), (9, None), (8, ""), (7, " \n"), (None, "one two"), (4, "É x"), (6, "é x"), (11, "a b c d e"), (12, "a b c d e"), (13, "r " * 30000), (14, "r " * 20000), (11, "a b c d e")]
    assert _run(spark, docs, n=4, threshold=0.85) == sorted(J.brute_force(docs, 4, 0.85), key=str)
    assert _run(spark, []) == []
    wide = spark.createDataFrame([(1, "a b", 1), (2, "a b", 2), (None, "a b", 3)], "doc_id long, text string, component_id int")
    assert sorted(str(r.doc_id) for r in J.keep_smallest(wide).collect()) == ["1", "None"]
