"""Substring deduplication over words with fixed-block anchors.

Every run of ``span`` words holds a whole aligned block of ``span // 2`` words
(blocks start at multiples of their length), wherever the run begins.  So the
index keeps only these non-overlapping blocks, and every rolling window of the
same length probes it:

1. *anchor*: blocks and rolling windows meet in hash buckets; a window is live
   if it equals a block and stands in two documents at least;
2. *extend*: only runs of ``span`` words around live windows are fingerprinted
   (two 64-bit hashes) and meet again, which gives the smallest document that
   has each run;
3. *cut*: a word goes if one of its runs also starts in a document with a
   smaller id; neighbouring runs join to maximal repeats.

Documents are dealt once, by hash of their id, into groups of bounded size, and
all three steps read that one exchange.  Exact copies of a text are left to one representative: a copy
of a smaller document goes whole if it has ``span`` words, else stays.  Hashes
travel packed (``packing``), unique within a document group, so neither large
groups of copies nor frequent passages make a large task.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spool import text_bytes
from . import grams
from .packing import MESSAGE, Layout, address, contains, deliver, lay_out, read, run_starts

LAST = np.iinfo(np.int64).max
LOW = np.uint64(0xFFFFFFFF)
SPANS = "removed_spans array<struct<start:int,end:int>>"


class _Group:
    """Word hashes of the documents of one group that speak for their text."""

    def __init__(self, docs: pa.Table, rest: pa.Table):
        self.ids = grams.ids_of(docs.column("doc_id"))
        reps = rest.column("rep").drop_null().to_numpy().astype(np.int64)
        self.lead = np.isin(self.ids, reps)
        self.texts = grams.texts_of(docs.column("text"))
        self.a, self.offsets = grams.hash_words([t if r else b"" for t, r in zip(self.texts, self.lead)])
        self.doc = self.ids[grams.owner(self.offsets)] if len(self.a) else np.zeros(0, np.int64)

    def anchors(self, block: int, names: np.ndarray):
        """Bucketed 32-bit keys of all rolling windows, their places, and which are blocks."""
        at = np.flatnonzero(grams.starts_inside(self.offsets, block, len(self.a)))
        h = grams.windows(self.a, block)[at]
        key = (names[((h >> np.uint64(32)) % np.uint64(len(names))).astype(np.int64)] << np.uint64(32)) | (h & LOW)
        begin = self.offsets[:-1][grams.owner(self.offsets)][at] if len(at) else at
        return key, at, (at - begin) % block == 0

    def runs(self, span: int):
        n = max(0, len(self.a) - span + 1)
        return grams.starts_inside(self.offsets, span, len(self.a)), n


IS_BLOCK, MANY = 1, 2  # a key is a block here; a key stands in two documents here


def _ask(block: int, plan: Layout):
    names, per = plan.bucket_names(), plan.per(plan.buckets)

    def fn(key, docs, rest):
        group = _Group(docs, rest)
        k, at, is_block = group.anchors(block, names)
        doc = group.doc[at]
        order = np.argsort(k, kind="stable")
        k, doc, is_block = k[order], doc[order], is_block[order]
        starts = run_starts(k)
        if not len(starts):
            return address(0, np.zeros(0, np.int64), per, [], "g")
        many = np.minimum.reduceat(doc, starts) != np.maximum.reduceat(doc, starts)
        flags = IS_BLOCK * np.maximum.reduceat(is_block.view(np.uint8), starts) + MANY * many.astype(np.uint8)
        k = k[starts]
        return address(key[0].as_py(), (k >> np.uint64(32)).astype(np.int64), per, [(k & LOW).astype(np.uint32), flags.astype(np.uint8)], "g")

    return fn


def _answer(per: int):
    """Live keys of every group that asked this bucket."""

    def fn(key, rows):
        g, _, (low, flags) = read(rows.column("payload"), 2)
        hit = np.flatnonzero(contains(np.unique(low[flags & IS_BLOCK > 0]), low))
        g, low, flags = g[hit], low[hit], flags[hit]
        keys, counts = np.unique(low, return_counts=True)  # a group sends a key once
        live = contains(keys[counts > 1], low) | contains(np.unique(low[flags & MANY > 0]), low)
        g, low = g[live], low[live]
        order = np.argsort(g, kind="stable")
        return address(key[0].as_py(), g[order], per, [low[order]], "b")

    return fn


def _extend(span: int, block: int, plan: Layout):
    names, per = plan.bucket_names(), plan.per(plan.buckets)
    nothing = address(0, np.zeros(0, np.int64), per, [], "g")

    def fn(key, docs, rest):
        _, b, (low,) = read(rest.column("payload"), 1)
        if not len(low):
            return nothing
        live = np.sort((b.astype(np.uint64) << np.uint64(32)) | low)
        group = _Group(docs, rest)
        k, at, _ = group.anchors(block, names)
        seen = np.zeros(len(group.a) + 1, np.int64)
        seen[1:][at[contains(live, k)]] = 1
        seen = np.cumsum(seen)
        ok, n = group.runs(span)
        reach = span - block + 1
        ok &= seen[reach : reach + n] - seen[:n] > 0
        at = np.flatnonzero(ok)
        if not len(at):
            return nothing
        f1, f2, doc = grams.windows(group.a, span)[at], grams.windows(group.a, span, salt=1)[at], group.doc[at]
        bucket = names[((f1 >> np.uint64(32)) % np.uint64(len(names))).astype(np.int64)].astype(np.int64)
        order = np.lexsort((f2, f1, bucket))
        f1, f2, doc, bucket = f1[order], f2[order], doc[order], bucket[order]
        starts = run_starts(f1, f2)
        least, most = np.minimum.reduceat(doc, starts), np.maximum.reduceat(doc, starts)
        return address(key[0].as_py(), bucket[starts], per, [f1[starts], f2[starts], least, most], "g", level=1)

    return fn


def _smallest(per: int):
    """For each group the runs that a smaller document has, with that document."""

    def fn(key, rows):
        g, _, (f1, f2, low, high) = read(rows.column("payload"), 4)
        order = np.lexsort((f2, f1))
        starts = run_starts(f1[order], f2[order])
        least = np.empty(len(f1), np.int64)
        least[order] = np.repeat(np.minimum.reduceat(low[order], starts), np.diff(np.append(starts, len(f1))))
        tell = np.flatnonzero(high > least)
        tell = tell[np.argsort(g[tell], kind="stable")]
        return address(key[0].as_py(), g[tell], per, [f1[tell], f2[tell], least[tell]], "b", level=1)

    return fn


def _cut(span: int):
    at = pa.struct([("start", pa.int32()), ("end", pa.int32())])

    def fn(key, docs, rest):
        group = _Group(docs, rest)
        ok, n = group.runs(span)
        drop = np.zeros(len(group.a), bool)
        _, _, (f1, f2, least) = read(rest.column("payload"), 3)
        if len(f1) and n:
            order = np.lexsort((f2, f1))
            f1, f2, least = f1[order], f2[order], least[order]
            w1, w2 = grams.windows(group.a, span), grams.windows(group.a, span, salt=1)
            here = np.flatnonzero(ok & contains(f1, w1))
            slot = np.searchsorted(f1, w1[here])
            gone = np.zeros(n, bool)
            for step in (0, 1):  # two runs may share the first hash
                s = np.minimum(slot + step, len(f1) - 1)
                gone[here] |= (f1[s] == w1[here]) & (f2[s] == w2[here]) & (least[s] < group.doc[here])
            if gone.any():
                drop = grams.spread(gone, span, len(group.a))
        spans, kept, count = [], [], []
        for i, text in enumerate(group.texts):
            words = text.split()
            count.append(len(words))
            if not group.lead[i]:
                whole = len(words) >= span
                spans.append([{"start": 0, "end": len(words)}] if whole else [])
                kept.append(b"" if whole else b" ".join(words))
                continue
            own = drop[group.offsets[i] : group.offsets[i + 1]]
            if not own.any():
                spans.append([])
                kept.append(b" ".join(words))
                continue
            edge = np.flatnonzero(np.diff(np.concatenate([[0], own.view(np.int8), [0]]))).tolist()
            spans.append([{"start": s, "end": e} for s, e in zip(edge[::2], edge[1::2])])
            kept.append(b" ".join(w for w, x in zip(words, own.tolist()) if not x))
        return pa.table({"doc_id": docs.column("doc_id"), "n_words": pa.array(count, pa.int64()), "removed_spans": pa.array(spans, pa.list_(at)), "kept_text": pa.array(kept, pa.binary()).cast(pa.string())})

    return fn


def repeated_spans(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", span: int = 50, layout: dict | None = None) -> DataFrame:
    """``doc_id, n_words, removed_spans, kept_text`` for every row of ``docs``.

    Words are runs of anything but ASCII white space, unchanged.  Null or empty
    text: no words.  A null id ranks behind all others.  Rows with one id count
    as one document, so none of them removes the other's words.  Other columns
    of ``docs`` are not read.  An empty table gives an empty table.  ``layout``
    changes the sizes of ``packing.lay_out``.
    """
    if span < 2:
        raise ValueError("span must be 2 at least")
    block = span // 2
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    plan = lay_out(docs.sparkSession, text_bytes(rows, "text"), **(layout or {}))
    dealt = rows.withColumn("g", plan.group_of(F.col("doc_id"))).repartition(plan.parts, "g")
    own = F.coalesce("doc_id", F.lit(int(LAST)))
    reps = rows.groupBy(F.sha2(F.coalesce("text", F.lit("")), 256)).agg(F.min(own).alias("rep")).select("rep").distinct()
    back = F.when(F.col("rep") == F.lit(int(LAST)), F.lit(None).cast("long")).otherwise(F.col("rep"))
    reps = reps.select(plan.group_of(back).alias("g"), "rep", F.lit(None).cast("binary").alias("payload"))

    def beside(answers):
        right = reps if answers is None else reps.union(answers.select(F.col("to").alias("g"), F.lit(None).cast("long").alias("rep"), "payload"))
        return dealt.groupBy("g").cogroup(right.repartition(plan.parts, "g").groupBy("g"))

    to_bucket, to_group = plan.per(plan.buckets), plan.per(plan.groups)

    def at_buckets(messages, fn):
        met = deliver(messages, to_bucket, plan.parts, "b").repartition(plan.slots, "to").groupBy("to").applyInArrow(fn(to_group), MESSAGE)
        return deliver(met, to_group, plan.parts, "g")

    live = at_buckets(beside(None).applyInArrow(_ask(block, plan), MESSAGE), _answer)
    least = at_buckets(beside(live).applyInArrow(_extend(span, block, plan), MESSAGE), _smallest)
    return beside(least).applyInArrow(_cut(span), f"doc_id long, n_words long, {SPANS}, kept_text string")


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "n_words", F.expr("aggregate(removed_spans, 0L, (s, x) -> s + x.end - x.start)").alias("n_removed"), F.sha2("kept_text", 256).alias("kept_sha256"))


def brute_force(docs: list[tuple[int, str | None]], span: int = 50) -> list[tuple]:
    """The same figures from a dictionary of all runs, for small tests."""
    import hashlib
    import re

    split = [(LAST if d is None else d, d, re.findall(r"[^\x20\x09-\x0D]+", t or "")) for d, t in docs]
    first: dict[tuple, int] = {}
    for r, _, w in split:
        for i in range(len(w) - span + 1):
            k = tuple(w[i : i + span])
            first[k] = min(first.get(k, r), r)
    out = []
    for r, d, w in split:
        gone = set()
        for i in range(len(w) - span + 1):
            if first[tuple(w[i : i + span])] < r:
                gone.update(range(i, i + span))
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((d, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out
