import random

from manifold_engine.llm import substrings as S


def _run(spark, docs, span=50, **kw):
    d = spark.createDataFrame(docs, "doc_id long, text string")
    return sorted((tuple(r) for r in S.digest(S.repeated_spans(d, span=span, **kw)).collect()), key=str)


def test_real_table_matches_brute_force(spark, sf01):
    d = [tuple(r) for r in spark.read.parquet(f"{sf01}/documents.parquet").select("doc_id", "text").collect()]
    want = sorted(S.brute_force(d), key=str)
    assert sum(r[2] > 0 for r in want) > 20
    assert _run(spark, d) == want
    # many small groups, messages in two hops
    assert _run(spark, d, layout={"group_bytes": 40_000, "groups_a_bucket": 2, "fan": 4}) == want


def test_random_repeats(spark):
    rng = random.Random(5)
    for span in (2, 3, 7, 8):
        docs = [(i, " ".join(rng.choice("ab") for _ in range(rng.randrange(0, 40)))) for i in rng.sample(range(900), 60)]
        assert _run(spark, docs, span) == sorted(S.brute_force(docs, span), key=str)


def test_edges(spark):
    p = " ".join(f"w{i}" for i in range(60))
    docs = [(5, p), (3, p), (None, p), (9, None), (1, ""), (8, "x " + p + "\x0by"), (3, p), (7, "a " * 30000), (12, "a " * 70), (None, "short"), (2, "short")]
    assert _run(spark, docs) == sorted(S.brute_force(docs), key=str)
    assert _run(spark, []) == []
    wide = spark.createDataFrame([(1, p, 2, "z")], "doc_id long, text string, n_words int, kept_text string")
    assert S.repeated_spans(wide).columns == ["doc_id", "n_words", "removed_spans", "kept_text"]
