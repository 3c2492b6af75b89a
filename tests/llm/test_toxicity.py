import zlib
from math import log

import pytest

from manifold_engine.llm import toxicity as X


def _auc(pairs):
    pos = [s for s, y in pairs if y]
    neg = [s for s, y in pairs if not y]
    return sum((p > n) + 0.5 * (p == n) for p in pos for n in neg) / (len(pos) * len(neg))


def test_model_matches_plain_formula(spark):
    rows = [("ab ab ac", 0), ("ab ad ad ad", 1)]
    counts = X.count_sequences(spark.createDataFrame(rows, "text string, bad int"), "text", 3)
    got = {r.g: (r.c0, r.c1) for r in counts.collect()}
    assert got["a"] == (3, 4) and got["ab"] == (2, 1) and got["\x02ad"] == (0, 3) and got["b\x03"] == (2, 1)
    m = X.fit_models(counts, 3, 1, 0.0)
    # order 1: contexts of each character, order 2 and 3 by class with discount 0.75
    ctx = {"a": 1, "b": 1, "c": 1, "d": 1, "\x03": 3}
    mass = sum(ctx.values()) + 500

    def p(c, window):
        value = (ctx[window[-1]] + 0.5) / mass
        for k in (2, 3):
            g = window[-k:]
            if len(window) < k:
                break
            whole = sum(v[c] for x, v in got.items() if len(x) == k and x[:-1] == g[:-1])
            types = [max(v[c] - 0.75, 0) for x, v in got.items() if len(x) == k and x[:-1] == g[:-1]]
            if whole:
                value = max(got.get(g, (0, 0))[c] - 0.75, 0) / whole + (1 - sum(types) / whole) * value
        return value

    for w in ("\x02ad", "\x02ab", "ab\x03", "\x02a"):
        assert m.gain(w) == pytest.approx(log(p(1, w)) - log(p(0, w)))


def _plain_scores(docs, labels, order=5, shared=2, prior=32.0, cut=0.75):
    """The whole operator by loops over dictionaries."""
    from collections import defaultdict

    import numpy as np

    bad = {}
    for d, y in labels:
        if d is not None and y is not None:
            bad[d] = max(bad.get(d, 0), int(y > 0))
    crc = lambda d: zlib.crc32(str(d).encode())
    split = lambda t: (t or "").translate({c: " " for c in range(128) if not chr(c).isalnum()} | {c: c + 32 for c in range(65, 91)}).split()
    seqs = lambda w: [(f"\x02{w}\x03", i) for i in range(1, len(w) + 2)]
    count = defaultdict(lambda: [0, 0])
    for d, t in docs:
        if d in bad and crc(d) % 4 != 2 and crc(d) // 4 % 8:
            for w in split(t):
                for s, i in seqs(w):
                    for k in range(1, min(order, i + 1) + 1):
                        count[s[i + 1 - k : i + 1]][bad[d]] += 1
    follow = defaultdict(int)
    for g in count:
        if 1 < len(g) <= shared + 1:
            follow[g[1:]] += 1
    m = {g: follow.get(g, 1) for g in count if len(g) <= shared}
    mass = sum(v for g, v in m.items() if len(g) == 1) + 500
    table, context = {}, defaultdict(lambda: [[0.0] * 3, [0.0] * 3])
    for g, (a, b) in count.items():
        if len(g) > 1:
            table[g] = (m[g],) * 3 if len(g) <= shared else (a, b, a + b)
            for i in range(3):
                context[g[:-1]][0][i] += table[g][i]
                context[g[:-1]][1][i] += max(table[g][i] - cut, 0)

    def gain(window):
        p = [(m[window[-1]] + 0.5) / mass if window[-1] in m else 0.5 / mass] * 3
        for k in range(2, len(window) + 1):
            g = window[-k:]
            c = table.get(g, (0, 0, 0))
            s, t = context[g[:-1]] if g[:-1] in context else ([0] * 3, [0] * 3)
            here = [max(c[i] - cut, 0) / max(s[i], 1) + (1 - t[i] / s[i] if s[i] else 1) * p[i] for i in range(3)]
            w = [s[i] / (s[i] + prior) for i in (0, 1)] if g[:-1] in context else [1, 1]
            p = [w[i] * here[i] + (1 - w[i]) * (here[2] if w[0] * w[1] > 0 else p[i]) for i in (0, 1)] + [here[2]]
        return round((log(p[1]) - log(p[0])) * 2**24) / 2**24

    def ratio(t):
        words = split(t)
        total = sum(gain(s[max(0, i + 1 - order) : i + 1]) for w in words for s, i in seqs(w))
        return total / (sum(map(len, words)) + len(words)) if words else 0.0

    seen = sorted((ratio(t), bad[d]) for d, t in docs if d in bad and crc(d) % 4 != 2 and crc(d) // 4 % 8 == 0 and t is not None)
    x, y = np.array([r for r, _ in seen]), np.array([float(b) for _, b in seen])
    slope, shift = X.platt(x, y)
    return [(d, 1 / (1 + np.exp(-np.clip(slope * ratio(t) + shift, -30, 30)))) for d, t in docs]


def test_score_matches_brute_force(spark):
    import random

    rng = random.Random(3)
    words = [[a + b for a in "bdk" for b in ("ar", "eto", "in")], [a + b for a in "zxq" for b in ("ar", "um", "ik")]]
    docs = [(i, " ".join(rng.choice(words[int(rng.random() < (0.6 if i % 3 == 0 else 0.15))]) for _ in range(rng.randrange(0, 25)))) for i in range(150)]
    docs += [(500, None), (501, ""), (502, "Unseen, WORDS é1!"), (3, docs[3][1])]
    labels = [(i, int(i % 3 == 0)) for i in range(120)] + [(5, 1), (6, None), (None, 1)]
    want = sorted(_plain_scores(docs, labels))
    out = X.score(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int"))
    got = sorted((r.doc_id, r.score, r.predicted) for r in out.collect())
    assert [r[0] for r in got] == [r[0] for r in want]
    assert all(g[1] == pytest.approx(w[1], abs=1e-6) and g[2] == int(g[1] >= 0.3) for g, w in zip(got, want))
    assert len({round(g[1], 6) for g in got}) > 50


def test_ties_and_clashing_columns(spark):
    """Equal texts share a score, more labelled rows of one id than the bound are no trouble, own columns survive."""
    docs = spark.createDataFrame([(1, "bad thing", "h", 5), (2, "bad thing", "i", 6), (2, "bad thing", "i", 6), (3, "good thing", "j", 7)] + [(i, ("bad", "good")[i % 2], "k", 0) for i in range(10, 60)] + [(10, "bad", "k", 0)] * 40, "doc_id long, text string, held_out string, extra int")
    labels = spark.createDataFrame([(i, 1 - i % 2) for i in range(10, 60)], "doc_id long, toxic int")
    out = X.score(docs, labels, calibration_rows=5)
    assert out.columns == ["doc_id", "text", "extra", "score", "held_out", "predicted"] or set(out.columns) == {"doc_id", "text", "extra", "score", "held_out", "predicted"}
    rows = out.collect()
    assert len(rows) == docs.count() and len({r.score for r in rows if r.text == "bad thing"}) == 1 and all(r.extra is not None for r in rows)


def test_held_out_accuracy(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    rows = {r.doc_id: r for r in X.score(docs, labels).collect()}
    assert len(rows) == docs.count() and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in rows.values())
    assert all(r.held_out == (zlib.crc32(str(d).encode()) % 4 == 2) for d, r in rows.items())
    pairs = [(rows[r.doc_id].score, r.toxic) for r in labels.collect() if rows[r.doc_id].held_out]
    hit = sum(s >= 0.3 and y for s, y in pairs)
    print("recall", hit / sum(y for _, y in pairs), "precision", hit / sum(s >= 0.3 for s, _ in pairs), "auc", _auc(pairs), "rows", len(pairs))
    assert _auc(pairs) > 0.8  # nearly half of the toxic labels of this table sit on texts without a toxic expression


def test_edges(spark):
    docs = spark.createDataFrame([(1, None, 9), (2, "", 9), (3, "bad " * 50000, 9), (None, "fine words", 9), (3, "bad", 9)], "doc_id long, text string, score int")
    none = spark.createDataFrame([], "doc_id long, toxic int")
    assert {r.score for r in X.score(docs, none).collect()} == {0.5}
    lab = spark.createDataFrame([(i, int(i > 40)) for i in range(80)] + [(5, None)], "doc_id long, toxic int")
    more = spark.createDataFrame([(i, "bad words here" if i > 40 else "nice words here", 0) for i in range(80)], docs.schema)
    out = X.score(docs.where("doc_id is null or text is null or text = ''").union(more), lab)
    assert all((r.score > 0.5) == ("bad" in (r.text or "")) for r in out.collect())
    assert X.score(docs.limit(0), lab).count() == 0


def test_rare_sequences_of_the_small_class_count(spark):
    """A toxic word of a few documents tells among millions of ordinary ones; no sequence is dropped for being rare."""
    fine = ("plain words of no harm " * 60_000, 0)
    rows = spark.createDataFrame([fine] + [("zqxj", 1)] * 3, "text string, bad int")
    docs = spark.createDataFrame([(i, "fine " * 120_000 if i < 40 else "zqxj" if i < 80 else "words") for i in range(120)], "doc_id long, text string")
    lab = spark.createDataFrame([(i, int(i >= 40)) for i in range(80)], "doc_id long, toxic int")
    got = {r.doc_id: r.score for r in X.score(docs, lab).collect()}
    assert all((got[i] > 0.5) == (40 <= i < 80) for i in range(80))
    assert got[40] > got[100] + 0.01  # known as toxic, not merely unknown
    m = X.fit_models(X.count_sequences(rows, "text", 5), 5, 2)
    assert m.gain("\x02zqxj") > 1 and m.entries.where("g = 'zqxj\x03'").count() == 1


def test_scores_do_not_depend_on_what_is_shipped(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    docs = docs.union(docs.limit(20)).union(spark.createDataFrame([(-1, None, "", "", 0)], docs.schema))
    a, b, c = (sorted((r.doc_id, r.score) for r in X.score(docs, labels, shipped=n).select("doc_id", "score").collect()) for n in (10**9, 1000, 0))
    assert a == b == c and len(a) == docs.count()
