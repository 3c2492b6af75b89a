"""Toxicity with class-conditional Kneser-Ney models.

Two character models, of toxic and of ordinary text, predict each character of
a word (with its boundaries) from up to ``order - 1`` before it.  The orders
above ``shared_orders`` discount the counts of their class; below, both back
off to the same continuation counts (in how many contexts a sequence occurs),
pooled over the classes, so an expression too rare to tell them apart adds
nothing.  A document's log-likelihoods under both, by characters, give one
number; a logistic curve fitted on labelled rows the models have not seen maps
it to a score.

A class seldom seen in a context leans on the estimate of both classes there,
so rare sequences count as far as their evidence goes and none is dropped.

Counting covers all labelled training texts: words are summed inside a task,
then over the table, then cut into sequences.  Every counted sequence is in
the model, which is a table and grows with the corpus.  It meets the windows
that the documents contain in joins, one order after the other, which gives
each window its gain.  The most frequent windows travel with the tasks; a
document's other windows meet their gains in a join, so what travels has a
bound and what counts has none.
"""

from __future__ import annotations

from collections import Counter
from math import log

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..spool import spool
from . import grams
from .arrowmap import append_columns, pieces

BEGIN, END = "\x02", "\x03"
STEPS = float(1 << 24)
FLOOR_ALPHABET = 1000  # characters a never seen one is thought to be among


def _sum_words(text: str):
    """Task-local word counts by class, let go whenever many words are held."""

    def batch_of(own):
        words = list(own[0].keys() | own[1].keys())
        return pa.RecordBatch.from_arrays([pa.array(words, pa.binary()).cast(pa.string()), *(pa.array([c[w] for w in words], pa.int64()) for c in own)], names=["word", "c0", "c1"])

    def fn(batches):
        own = (Counter(), Counter())
        for batch in batches:
            for part in pieces(batch, text):
                for raw, bad in zip(grams.texts_of(part.column(text)), part.column("bad").to_pylist()):
                    own[bad].update(raw.translate(grams.ALNUM).split())
                if len(own[0]) + len(own[1]) > 400_000:
                    yield batch_of(own)
                    own = (Counter(), Counter())
        if own[0] or own[1]:
            yield batch_of(own)

    return fn


def _sequences(order: int):
    """Sequences of 1 to ``order`` characters that end in each character of a word."""

    def fn(batches):
        for batch in batches:
            held: dict[str, list[int]] = {}
            for w, a, b in zip(*(batch.column(c).to_pylist() for c in ("word", "c0", "c1"))):
                s = f"{BEGIN}{w}{END}"
                for i in range(1, len(s)):
                    for k in range(1, min(order, i + 1) + 1):
                        if (x := held.get(g := s[i + 1 - k : i + 1])) is None:
                            x = held[g] = [0, 0]
                        x[0] += a
                        x[1] += b
            names = list(held)
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array([held[g][0] for g in names], pa.int64()), pa.array([held[g][1] for g in names], pa.int64())], names=["g", "c0", "c1"])

    return fn


def count_sequences(labelled: DataFrame, text: str, order: int) -> DataFrame:
    """``g, k, c0, c1`` over all rows of ``labelled`` (``text``, ``bad`` 0 or 1)."""
    words = labelled.select(text, "bad").mapInArrow(_sum_words(text), "word string, c0 long, c1 long").groupBy("word").agg(F.sum("c0").alias("c0"), F.sum("c1").alias("c1"))
    every = words.mapInArrow(_sequences(order), "g string, c0 long, c1 long").groupBy("g").agg(F.sum("c0").alias("c0"), F.sum("c1").alias("c1"))
    return spool(every.withColumn("k", F.length("g")), "sequences")


def _windows(order: int):
    """The window each character of a word is predicted in: itself and up to ``order - 1`` before it."""

    def fn(batches):
        for batch in batches:
            held: Counter = Counter()
            for w, n in zip(batch.column("word").to_pylist(), batch.column("n").to_pylist()):
                for g in windows_of(w, order):
                    held[g] += n
            yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array(list(held.values()), pa.int64())], names=["g", "n"])

    return fn


def windows_of(word: str, order: int) -> list[str]:
    s = f"{BEGIN}{word}{END}"
    n = len(s)
    # those cut short by the word's begin, then the whole ones
    return [s[:k] for k in range(2, min(order, n + 1))] + [s[i : i + order] for i in range(max(0, 2 - order), n - order + 1)]


def count_windows(docs: DataFrame, text: str, order: int) -> DataFrame:
    """``g, n``: every window of the words of ``docs`` and how often it occurs."""
    words = docs.select(text, F.lit(0).alias("bad")).mapInArrow(_sum_words(text), "word string, c0 long, c1 long").groupBy("word").agg(F.sum("c0").alias("n"))
    return spool(words.mapInArrow(_windows(order), "g string, n long").groupBy("g").agg(F.sum("n").alias("n")), "windows")


class KneserNey:
    """The two models as tables: probability parts of sequences, backoff weights of contexts, probabilities of characters."""

    def __init__(self, order: int, entries: DataFrame, backoff: DataFrame, chars: DataFrame, floor: float):
        self.order, self.entries, self.backoff, self.chars, self.floor = order, entries, backoff, chars, floor

    def gains(self, windows: DataFrame) -> DataFrame:
        """``windows`` (distinct ``g``) with ``v``, the log ratio of the last character of each under the two models."""
        ends = windows.where("length(g) > 1").select(F.expr("explode(transform(sequence(2, length(g)), k -> substring(g, length(g) - k + 1)))").alias("g")).distinct()
        ends = ends.withColumn("k", F.length("g")).withColumn("h", F.expr("substring(g, 1, k - 1)"))
        ends = ends.join(self.entries, "g", "left").join(self.backoff, "h", "left")
        # an unknown context backs off whole, and so do all longer ones
        of = [(f"{c}{i}", d) for c, d, n in (("q", 0.0, 3), ("b", 1.0, 3), ("w", 1.0, 2)) for i in range(n)]
        ends = spool(ends.select("g", "k", *[F.coalesce(c, F.lit(d)).alias(c) for c, d in of]), "ends")

        def step(r: list[Column]) -> list[Column]:
            p = [F.col(f"q{i}") + F.col(f"b{i}") * r[i] for i in range(3)]
            return [(F.col(f"w{i}") * p[i] + (1 - F.col(f"w{i}")) * F.when(F.col("w0") * F.col("w1") > 0, p[2]).otherwise(r[i])).alias(f"p{i}") for i in (0, 1)] + [p[2].alias("p2")]

        one = F.coalesce("p", F.lit(self.floor))
        before = F.broadcast(self.chars.select(F.col("g").alias("s"), "p"))  # as many rows as there are characters
        level = ends.where("k = 2").join(before, F.expr("substring(g, 2)") == F.col("s"), "left").select("g", *step([one] * 3))
        level = every = spool(level, "level")
        for k in range(3, self.order + 1):
            before = level.toDF("s", "r0", "r1", "r2")
            level = ends.where(F.col("k") == k).join(before, F.expr("substring(g, 2)") == F.col("s"))
            level = spool(level.select("g", *step([F.col(f"r{i}") for i in range(3)])), "level")
            every = every.union(level)
        return windows.join(every, "g", "left").select(*windows.columns, F.coalesce(F.log("p1") - F.log("p0"), F.lit(0.0)).alias("v"))

    def gain(self, window: str) -> float:
        return self.gains(self.entries.sparkSession.createDataFrame([(window,)], "g string")).first()["v"]


def fit_models(counts: DataFrame, order: int, shared_orders: int, prior: float = 0.0, discount: float = 0.75) -> KneserNey | None:
    """Kneser-Ney models from ``count_sequences``; ``None`` without text in both classes.

    No sequence is left out.  Instead a class's estimate in a context it has
    ``s`` times weighs ``s / (s + prior)``, and the estimate of both classes
    together the rest.
    """
    a, b = counts.where("k = 1").agg(F.sum("c0"), F.sum("c1")).first()
    if not a or not b:
        return None
    head = F.expr("substring(g, 1, length(g) - 1)").alias("h")
    # class orders: raw counts, of the classes and of both
    high = counts.where(F.col("k") > shared_orders).select("g", "k", head, "c0", "c1", (F.col("c0") + F.col("c1")).alias("c2"))
    # shared orders: in how many contexts each sequence occurs; a word's begin is one
    longer = counts.where(F.col("k") <= shared_orders + 1)
    follow = longer.where("k > 1").groupBy(F.expr("substring(g, 2)").alias("g")).agg(F.count("*").alias("m"))
    low = longer.where(F.col("k") <= shared_orders).join(follow, "g", "left").withColumn("m", F.coalesce("m", F.lit(1)))
    both = spool(high.union(low.where("k > 1").select("g", "k", head, "m", "m", "m")), "mass")
    x = [F.greatest(F.col(f"c{i}") - discount, F.lit(0.0)) for i in range(3)]
    sums = both.groupBy("h").agg(*[F.sum(f"c{i}").cast("double").alias(f"s{i}") for i in range(3)], *[F.sum(x[i]).alias(f"t{i}") for i in range(3)])
    sums = spool(sums, "contexts")
    parts = both.join(sums, "h").select("g", *[(x[i] / F.greatest(F.col(f"s{i}"), F.lit(1.0))).alias(f"q{i}") for i in range(3)])
    back = [F.when(F.col(f"s{i}") > 0, 1.0 - F.col(f"t{i}") / F.col(f"s{i}")).otherwise(1.0).alias(f"b{i}") for i in range(3)]
    weight = [F.when(F.col(f"s{i}") + prior > 0, F.col(f"s{i}") / (F.col(f"s{i}") + prior)).otherwise(1.0).alias(f"w{i}") for i in (0, 1)]
    ones = low.where("k = 1").select("g", F.col("m").cast("double").alias("m"))
    mass = (ones.agg(F.sum("m")).first()[0] or 0.0) + 0.5 * FLOOR_ALPHABET
    return KneserNey(order, parts, sums.select("h", *back, *weight), ones.select("g", ((F.col("m") + 0.5) / mass).alias("p")), 0.5 / mass)


def platt(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and intercept of a logistic curve by Newton steps, lightly damped."""
    if not len(x):
        return 0.0, 0.0
    scale = float(x.std()) or 1.0
    a = np.stack([x / scale, np.ones_like(x)], 1)
    th = np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a @ th, -30, 30)))
        grad = a.T @ (p - y) + 1e-2 * th
        hess = (a * (p * (1 - p))[:, None]).T @ a + 1e-2 * np.eye(2)
        step = np.linalg.solve(hess, grad)
        th -= step * min(1.0, 5.0 / (np.abs(step).max() + 1e-12))
    return float(th[0] / scale), float(th[1])


class _Words(dict):
    """Sum of the known gains of a word's windows; words with windows that are not shipped are noted in ``open``."""

    def __init__(self, known: dict[str, float], order: int):
        self.known, self.order = known, order
        self.open: dict[bytes, tuple[str, ...]] = {}

    def __missing__(self, w: bytes) -> float:
        every = windows_of(w.decode(), self.order)
        try:
            total = sum(map(self.known.__getitem__, every))
        except KeyError:
            total = sum(self.known.get(g, 0.0) for g in every)
            self.open[w] = tuple(g for g in every if g not in self.known)
        self[w] = total
        return total


class Reader:
    """Log-likelihood ratios of texts from shipped gains; windows that are not shipped are listed."""

    def __init__(self, known: dict[str, float], order: int):
        self.memo = _Words(known, order)

    def text(self, raw: bytes) -> tuple[float, int, list[str]]:
        """Sum of the known gains, characters (each word's end counts as one), windows left open."""
        memo = self.memo
        if len(memo) > 300_000:
            memo.clear()
            memo.open.clear()
        words = raw.translate(grams.ALNUM).split()
        total = sum(map(memo.__getitem__, words))  # multiples of 2^-24: exact in any order
        some = memo.open.keys() & words if memo.open else ()
        left = [g for w in words if w in some for g in memo.open[w]] if some else []
        return float(total), sum(map(len, words)) + len(words), left


def _ratio(known: dict[str, float], order: int, text: str):
    def make():
        read = Reader(known, order).text

        def fn(part):
            got = list(map(read, grams.texts_of(part.column(text))))
            return [pa.array([v / n if n else 0.0 for v, n, _ in got], pa.float64())]

        return fn

    return make


def _parts(known: dict[str, float], order: int):
    def fn(batches):
        read = Reader(known, order).text
        for batch in batches:
            for part in pieces(batch, "text"):
                got = list(map(read, grams.texts_of(part.column("text"))))
                cols = [pa.array([x[i] for x in got], t) for i, t in enumerate((pa.float64(), pa.int64(), pa.list_(pa.string())))]
                yield pa.RecordBatch.from_arrays([part.column("a__"), part.column("b__"), *cols], names=["a__", "b__", "v", "n", "open"])

    return fn


def ship(gains: DataFrame, most: int) -> tuple[dict[str, float], DataFrame | None]:
    """Gains of the most frequent windows, at most ``most``, and the table of the others (``None`` if there are none)."""
    band = F.floor(F.log2("n") * 4)
    least, held = None, 0
    sizes = sorted(((r["band"], r["count"]) for r in gains.groupBy(band.alias("band")).count().collect()), reverse=True)
    for b, n in sizes:
        if held + n > most:
            break
        least, held = b, held + n
    inside = F.lit(False) if least is None else band >= least
    known = {r[0]: r[1] for r in gains.where(inside).select("g", "v").collect()}
    return known, None if held == sum(n for _, n in sizes) else gains.where(~inside).select("g", "v")


def with_ratio(docs: DataFrame, text: str, order: int, known: dict[str, float], rest: DataFrame | None) -> DataFrame:
    """``docs`` with ``ratio__``: log-likelihood ratio of each text by characters, 0 for a text without words.

    Equal texts add up numerator and denominator alike, so a text is known by
    128 bits of hash and its copies need no distinct().
    """
    if rest is None:
        return append_columns(docs, text, _ratio(known, order, text), [T.StructField("ratio__", T.DoubleType())])
    a, b = F.xxhash64(text), F.xxhash64(F.lit("toxicity"), text)
    parts = docs.where(F.col(text).isNotNull()).select(a.alias("a__"), b.alias("b__"), F.col(text).alias("text"))
    parts = spool(parts.mapInArrow(_parts(known, order), "a__ long, b__ long, v double, n long, open array<string>"), "parts")
    more = parts.select("a__", "b__", F.explode("open").alias("g")).join(rest, "g").select("a__", "b__", "v", F.lit(0).cast("long").alias("n"))
    whole = parts.select("a__", "b__", "v", "n").union(more).groupBy("a__", "b__").agg(F.sum("v").alias("v__"), F.sum("n").alias("n__")).where("n__ > 0")
    whole = whole.select("a__", "b__", (F.col("v__") / F.col("n__")).alias("ratio__"))
    out = docs.withColumn("x__", a).withColumn("y__", b).join(whole, (F.col("x__") == F.col("a__")) & (F.col("y__") == F.col("b__")), "left")
    return out.select(*docs.columns, F.coalesce("ratio__", F.lit(0.0)).alias("ratio__"))


def score(
    docs: DataFrame,
    labels: DataFrame,
    doc_id: str = "doc_id",
    text: str = "text",
    label: str = "toxic",
    order: int = 5,
    shared_orders: int = 2,
    prior: float = 32.0,
    threshold: float = 0.3,
    calibration_rows: int = 20_000,
    shipped: int = 300_000,
) -> DataFrame:
    """``docs`` with ``held_out``, ``score`` and ``predicted``.

    Labels are learnt only where crc32 of the id as text, modulo 4, is not 2.
    One in eight of these (fewer than ``calibration_rows``, by crc32 order) fits
    the curve, the others the models.  Several labels of one document: toxic if
    any says so; null labels are left out.  Words are lower-cased runs of ASCII
    letters and digits and of anything beyond ASCII; null and empty texts get
    the curve's value at a log ratio of 0.  Without text of both classes the
    score is the share of toxic labels (0.5 without labels).  A null id is not
    held out and has no label.  Columns with the new names are replaced.
    ``shipped`` says how many windows travel with the tasks, not which count:
    the scores do not depend on it.
    """
    crc = F.crc32(F.col(doc_id).cast("string"))
    held = F.coalesce(crc % 4 == 2, F.lit(False))
    known = labels.where(F.col(label).isNotNull() & F.col(doc_id).isNotNull()).groupBy(F.col(doc_id).alias("l__")).agg(F.max((F.col(label) > 0).cast("int")).alias("bad"))
    known = known.where(F.crc32(F.col("l__").cast("string")) % 4 != 2)
    # labels grow with the documents: never broadcast, and texts that cannot be learnt from stay where they are
    train = docs.where(F.col(text).isNotNull() & (crc % 4 != 2)).select(F.col(doc_id).alias("d__"), F.col(text).alias("text"))
    train = train.join(known.hint("merge"), F.col("d__") == F.col("l__")).select("d__", "text", "bad")
    aside = F.floor(F.crc32(F.col("d__").cast("string")) / 4) % 8 == 0
    model = fit_models(count_sequences(train.where(~aside), "text", order), order, shared_orders, prior)
    if model is None:
        n, t = known.agg(F.count("*"), F.sum("bad")).first()
        rate = (t + 0.5) / (n + 1) if n else 0.5
        slope, shift = 0.0, log(rate / (1 - rate))
    else:
        gains = model.gains(count_windows(docs.where(F.col(text).isNotNull()), text, order))
        # gains in steps of 2^-24: their sums are exact in any order
        known, rest = ship(spool(gains.withColumn("v", F.round(F.col("v") * STEPS) / STEPS), "gains"), shipped)
        # the bound is set on (crc, id) alone; texts are read only where they pass it, in parallel
        place = F.struct(F.crc32(F.col("d__").cast("string")).alias("r"), F.col("d__").alias("d"))
        n, last = train.where(aside).select(place.alias("p")).orderBy("p").limit(calibration_rows).agg(F.count("*"), F.max("p")).first()
        within = F.lit(True) if n < calibration_rows else place < F.struct(F.lit(last["r"]).alias("r"), F.lit(last["d"]).alias("d"))
        seen = spool(train.where(aside & within).select("text", "bad"), "seen")
        rows = sorted(with_ratio(seen, "text", order, known, rest).select("ratio__", "bad").collect())
        slope, shift = platt(np.array([r[0] for r in rows]), np.array([float(r[1]) for r in rows]))
    new = ("held_out", "score", "predicted")
    kept = docs.select(*[c for c in docs.columns if c not in new])
    out = kept.withColumn("ratio__", F.lit(0.0)) if model is None else with_ratio(kept, text, order, known, rest)
    z = F.greatest(F.lit(-30.0), F.least(F.lit(30.0), F.lit(slope) * F.col("ratio__") + F.lit(shift)))
    out = out.withColumn("score", 1 / (1 + F.exp(-z))).drop("ratio__")
    return out.withColumn("held_out", held).withColumn("predicted", (F.col("score") >= threshold).cast("int"))
