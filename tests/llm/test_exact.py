from manifold_engine.llm import exact as E


def _run(spark, docs, parts=8, **kw):
    d = spark.createDataFrame(docs, "doc_id long, text string")
    return sorted((tuple(r) for r in E.exact_groups(d.repartition(parts), **kw).collect()), key=str)


def test_real_table(spark, sf01):
    d = [tuple(r) for r in spark.read.parquet(f"{sf01}/documents.parquet").select("doc_id", "text").collect()]
    for keep in ("max", "min"):
        assert _run(spark, d, keep=keep) == sorted(E.brute_force(d, keep), key=str)


def test_hot_group_over_partitions_and_edges(spark):
    docs = [(i, "same") for i in range(3000)] + [(i, None) for i in range(3000, 3400)] + [(3500, ""), (None, "same"), (None, "n"), (None, "n"), (7, "dup"), (7, "dup"), (8, "é" * 90000), (9, "é" * 90000), (10, "é" * 89999)]
    for keep in ("max", "min"):
        assert _run(spark, docs, keep=keep) == sorted(E.brute_force(docs, keep), key=str)
    assert _run(spark, []) == []
