import random

from manifold_engine.llm import decontaminate as D


def _run(spark, docs, items, **kw):
    d = spark.createDataFrame(docs, "doc_id long, text string")
    b = spark.createDataFrame(items, "item_id long, text string")
    return sorted((tuple(r) for r in D.digest(D.benchmark_hits(d, b, **kw)).collect()), key=str)


def test_real_tables_match_brute_force(spark, sf):
    d = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    b = [tuple(r) for r in spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").collect()]
    want = sorted(D.brute_force(d, b), key=str)
    assert _run(spark, d, b) == want
    assert any(r[-1] for r in want) and not all(r[-1] for r in want)
    assert _run(spark, d, b, most_bits=1 << 13) == want  # a crowded filter lets more through to the join, no more


def test_edges(spark):
    run = " ".join(f"w{i}" for i in range(30))
    docs = [(1, None), (2, ""), (3, run), (4, "A b! C"), (5, "x " + " ".join(f"W{i}" for i in range(5, 16)) + " y"), (6, "b c"), (6, "b c"), (7, "w1 " * 40000), (None, run), (8, "é٣ b c \u2028 z")]
    items = [(1, run), (2, "a,b,c"), (3, None), (4, ""), (None, "b c"), (5, run)]
    assert _run(spark, docs, items) == sorted(D.brute_force(docs, items), key=str)
    assert _run(spark, docs, [(9, None)]) == sorted(D.brute_force(docs, []), key=str)
    assert _run(spark, [], items) == []


def test_benchmark_larger_than_the_documents(spark):
    """Nothing of either side is collected; random texts over few words, many short items."""
    rng = random.Random(2)
    words = [f"v{i}" for i in range(12)]
    items = [(i, " ".join(rng.choice(words) for _ in range(rng.choice((2, 3, 5, 12, 30))))) for i in range(400)]
    docs = [(i, " ".join(rng.choice(words) for _ in range(rng.randrange(60)))) for i in range(60)] + [(90, items[7][1]), (91, items[7][1] + " tail")]
    want = sorted(D.brute_force(docs, items, span=4), key=str)
    assert _run(spark, docs, items, span=4, k=2) == want and _run(spark, docs, items, span=4, k=4) == want


def test_columns(spark):
    d = spark.createDataFrame([(1, "a b c", 5), (2, None, 6), (3, "z", None)], "doc_id long, text string, n_words int")
    b = spark.createDataFrame([(1, "b c")], "item_id long, text string")
    got = D.benchmark_hits(d, b)
    assert got.columns == ["doc_id", "text", "n_words", "hit_items", "hit_spans"]
    rows = {r.doc_id: r for r in got.collect()}
    assert [(s.start, s.end) for s in rows[1].hit_spans] == [(1, 3)] and rows[1].n_words == 3 and rows[2].n_words == 0 and rows[2].hit_items == []
    assert sorted((r.doc_id, r.n_words) for r in D.drop_hits(d, b).collect()) == [(2, 6), (3, None)]
