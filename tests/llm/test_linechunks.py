import random

import duckdb
import pytest

from manifold_engine.llm import linechunks as L


def _run(spark, docs, **kw):
    d = spark.createDataFrame(docs, "doc_id long, text string")
    return sorted((tuple(r) for r in L.drop_repeated_chunks(d, **kw).select("doc_id", "n_lines", "n_removed", "text").collect()), key=str)


def _random_docs():
    rng = random.Random(1)
    lines = [f"line {i}" for i in range(40)] + ["", " "]
    base = [rng.choice(lines) for _ in range(60)]
    docs = [(i, "\n".join(base[rng.randrange(30) :] if i % 2 else [rng.choice(lines) for _ in range(rng.randrange(1, 30))])) for i in range(50)]
    return base, docs


def test_brute_force(spark):
    base, docs = _random_docs()
    docs += [(100, None), (101, ""), (102, "\n\n\n"), (103, "\n\n\n"), (None, "\n".join(base)), (104, "a\n" * 5000), (105, "one"), (106, "x\n\n \ny"), (107, "p\nx\ny\n")]
    want = sorted(L.brute_force(docs), key=str)
    assert any(r[2] for r in want)
    for every in (4, 3):  # changes the work, not what goes
        assert _run(spark, docs, every=every) == want
    assert _run(spark, []) == []


def test_oracle_says_the_same():
    docs = _random_docs()[1] + [(100, None), (101, ""), (104, "a\n" * 50), (106, "x\n\n \ny"), (107, "p\nx\ny\n")]
    con = duckdb.connect()
    con.execute("create table documents (doc_id bigint, text varchar)")
    con.executemany("insert into documents values (?, ?)", docs)
    assert sorted(con.execute(L.ORACLE).fetchall(), key=str) == sorted(L.brute_force(docs), key=str)


def test_every_repeated_run_goes(spark):
    """Runs of two to five lines, planted behind differing lines, of equal lines, and a whole copy."""
    docs = [(0, "\n".join(f"own {i}" for i in range(40)))]
    for n in (2, 3, 4, 5):
        run = "\n".join(f"run {n} {i}" for i in range(n))
        docs += [(10 * n + j, f"a{n}{j}\n{run}\nb{n}{j}") for j in range(3)]
    docs += [(100, "same\n" * 9 + "c"), (101, "d\n" + "same\n" * 30 + "e"), (102, docs[0][1])]
    got = {r[0]: r for r in _run(spark, docs)}
    for n in (2, 3, 4, 5):
        assert got[10 * n][2] == 0 and [got[10 * n + j][3] for j in (1, 2)] == [f"a{n}{j}\nb{n}{j}" for j in (1, 2)]
    assert got[100][3] == "same\nsame\nc" and got[101][3] == "d\ne" and got[102][3] == "" and got[0][2] == 0


@pytest.mark.parametrize("n", [60_000])
def test_long_text_is_linear(spark, n):
    text = "\n".join(f"l{i % (n // 2)}" for i in range(n))
    assert [r[2] for r in _run(spark, [(1, text), (2, "x\ny")])] == [n // 2, 0]


def test_repeated_rows_and_columns(spark):
    t = "\n".join(f"l{i}" for i in range(30))
    d = spark.createDataFrame([(1, t, 7, "a"), (1, t, 7, "a"), (2, "x\n" + t, 8, "b"), (1, "u\nl3\nl4", 9, "c")], "doc_id long, text string, n_lines int, k string")
    got = L.drop_repeated_chunks(d)
    assert got.columns == ["doc_id", "text", "k", "n_lines", "n_removed"]
    rows = {(r.doc_id, r.n_lines, r.n_removed) for r in got.collect()}
    assert (1, 30, 0) in rows or (1, 30, 2) in rows
    assert {r for r in rows if r[0] == 2} == {(2, 31, 30)}


def test_plan_is_native(spark, sf):
    plan = L.drop_repeated_chunks(spark.read.parquet(f"{sf}/documents.parquet"))._jdf.queryExecution().toString()
    assert not any(x in plan for x in ("Python", "Arrow", "Pandas", "CartesianProduct"))
