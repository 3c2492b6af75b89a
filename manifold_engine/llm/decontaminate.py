"""Benchmark decontamination by winnowing.

A shared run of ``span`` words must not go unseen.  Both sides hash every
``k``-gram and keep the least hash of each sliding window of ``span - k + 1``
k-grams; two texts that share ``span`` words share that window and hence its
least hash, its fingerprint.  An item shorter than ``span`` words is one window
of its own length, and that window's hash is its fingerprint.

Fingerprints meet in a join, so neither side is ever held whole: a document's
windows whose fingerprint a Bloom filter of the benchmark lets through (a
filter of bounded size, whatever the benchmark's) become rows, which join the
benchmark's windows by fingerprint and by 128 bits of the window itself.  Equal
texts have equal hits, so hits are known by a 128-bit hash of the text, and
documents that are copies of each other add nothing.  What is shuffled are
hits, false positives of the filter and short keys; texts stay where they are
unless a caller asks for them beside the hits.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..spool import spool
from . import grams
from .arrowmap import pieces

WINDOW = "m int, print long, w1 long, w2 long"
MOST_BITS = 1 << 27  # of the filter: 16 MB travel with each task


def least(h: np.ndarray, w: int) -> np.ndarray:
    """Least of every ``w`` neighbours."""
    n = max(0, len(h) - w + 1)
    out = h[:n].copy()
    for j in range(1, w):
        np.minimum(out, h[j : j + n], out=out)
    return out


def prints_of(a: np.ndarray, m: int, span: int, k: int) -> np.ndarray:
    """Fingerprint of each window of ``m`` words."""
    return least(grams.windows(a, k), span - k + 1) if m == span else grams.windows(a, m, salt=m)


def _item_windows(span: int, k: int):
    """``item, m, print, w1, w2`` of every window of the items."""

    def fn(batches):
        for batch in batches:
            for part in pieces(batch, "t"):
                a, offsets = grams.hash_words(grams.texts_of(part.column("t")), grams.ALNUM)
                lengths = np.diff(offsets)
                who = grams.owner(offsets)
                for m in sorted({min(span, n) for n in lengths.tolist() if n}):
                    use = lengths >= span if m == span else lengths == m
                    at = np.flatnonzero(grams.starts_inside(offsets, m, len(a)) & use[who][: max(0, len(a) - m + 1)])
                    hashes = [x[at].view(np.int64) for x in (prints_of(a, m, span, k), grams.windows(a, m), grams.windows(a, m, salt=1))]
                    yield pa.RecordBatch.from_arrays([part.column("item").take(pa.array(who[at])), pa.array(np.full(len(at), m, np.int32)), *map(pa.array, hashes)], names=["item", "m", "print", "w1", "w2"])

    return fn


class Filter:
    """A Bloom filter with two hash functions as bytes of bits."""

    def __init__(self, bits: int, data: np.ndarray):
        self.bits, self.data = bits, data

    def places(self, h: np.ndarray) -> list[np.ndarray]:
        h = h.view(np.uint64)
        return [(x & np.uint64(self.bits - 1)).astype(np.int64) for x in (h, h >> np.uint64(32))]

    def has(self, h: np.ndarray) -> np.ndarray:
        out = np.ones(len(h), bool)
        for at in self.places(h):
            out &= (self.data[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
        return out


def build_filter(windows: DataFrame, most_bits: int = MOST_BITS) -> Filter:
    """The filter of the distinct fingerprints: about 32 bits for each, at most ``most_bits``.

    Bits are set in the tasks; the driver receives chunks of bytes, as many as
    the filter has.
    """
    prints = windows.select("print").distinct()
    n = prints.count()
    bits = min(most_bits, 1 << max(13, (32 * n - 1).bit_length() if n else 0))
    chunk = 1 << 13  # bits of one chunk
    own = Filter(bits, np.zeros(0, np.uint8))

    def places(batches):
        for b in batches:
            both = np.concatenate(own.places(b.column("print").to_numpy()))
            yield pa.RecordBatch.from_arrays([pa.array((both // chunk).astype(np.int32)), pa.array((both % chunk).astype(np.int32))], names=["c", "bit"])

    def fill(key, t):
        data = np.zeros(chunk, np.uint8)
        data[t.column("bit").to_numpy()] = 1
        return pa.table({"c": pa.array([key[0].as_py()], pa.int32()), "bytes": pa.array([np.packbits(data, bitorder="little").tobytes()], pa.binary())})

    got = prints.mapInArrow(places, "c int, bit int").distinct().groupBy("c").applyInArrow(fill, "c int, bytes binary").toArrow()
    data = np.zeros(bits // 8, np.uint8)
    for c, raw in zip(got["c"].to_pylist(), got["bytes"].to_pylist()):
        data[c * chunk // 8 : (c + 1) * chunk // 8] = np.frombuffer(raw, np.uint8)
    return Filter(bits, data)


def _document_windows(sieve: Filter, lengths: list[int], span: int, k: int):
    """``a__, b__, at, m, print, w1, w2`` of the windows the filter lets through."""

    def fn(batches):
        for batch in batches:
            for part in pieces(batch, "text"):
                a, offsets = grams.hash_words(grams.texts_of(part.column("text")), grams.ALNUM)
                who = grams.owner(offsets)
                for m in lengths:
                    prints = prints_of(a, m, span, k)
                    at = np.flatnonzero(grams.starts_inside(offsets, m, len(a)) & sieve.has(prints))
                    if len(at):
                        hashes = [x[at].view(np.int64) for x in (prints, grams.windows(a, m), grams.windows(a, m, salt=1))]
                        doc = pa.array(who[at])
                        places = pa.array((at - offsets[who[at]]).astype(np.int32))
                        yield pa.RecordBatch.from_arrays([part.column("a__").take(doc), part.column("b__").take(doc), places, pa.array(np.full(len(at), m, np.int32)), *map(pa.array, hashes)], names=["a__", "b__", "at", "m", "print", "w1", "w2"])

    return fn


def _join_places(batches):
    """Places of hit windows joined to maximal runs of words."""
    kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))
    for b in batches:
        out = []
        for at, to in zip(b.column("at"), b.column("to")):
            at, to = at.values.to_numpy(), to.values.to_numpy()
            order = np.argsort(at)
            at, to = at[order], np.maximum.accumulate(to[order])
            new = np.concatenate([[True], at[1:] > to[:-1]])
            ends = to[np.append(np.flatnonzero(new)[1:], len(at)) - 1]
            out.append([{"start": s, "end": e} for s, e in zip(at[new].tolist(), ends.tolist())])
        yield pa.RecordBatch.from_arrays([b.column("a__"), b.column("b__"), pa.array(out, kind)], names=["a__", "b__", "hit_spans"])


def text_key(text: str) -> list[Column]:
    """128 bits of hash by which equal texts are known."""
    return [F.xxhash64(text).alias("a__"), F.xxhash64(F.lit("benchmark"), text).alias("b__")]


def find_hits(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", span: int = 10, k: int = 5, most_bits: int = MOST_BITS) -> DataFrame:
    """``a__, b__, hit_spans, hit_items`` of every distinct text that holds a window of the benchmark."""
    if not 1 <= k <= span:
        raise ValueError("k must lie in 1..span")
    items = benchmark.select(F.col(item_id).cast("string").alias("item"), F.coalesce(item_text, F.lit("")).alias("t"))
    windows = spool(items.mapInArrow(_item_windows(span, k), f"item string, {WINDOW}"), "windows")
    lengths = sorted(r["m"] for r in windows.select("m").distinct().collect())  # at most ``span`` numbers
    sieve = build_filter(windows, most_bits)
    there = docs.where(F.col(text).isNotNull()).select(F.col(text).alias("text"), *text_key(text))
    asked = there.mapInArrow(_document_windows(sieve, lengths, span, k), f"a__ long, b__ long, at int, {WINDOW}")
    key = ["m", "print", "w1", "w2"]
    known = windows.select(*key).distinct()
    hits = spool(asked.join(known, key).select("a__", "b__", "at", *key).distinct(), "hits")

    # windows of several lengths at one place: the longest says it all
    runs = hits.groupBy("a__", "b__", "at").agg((F.col("at") + F.max("m")).alias("to")).groupBy("a__", "b__").agg(F.collect_list("at").alias("at"), F.collect_list("to").alias("to"))
    runs = runs.mapInArrow(_join_places, "a__ long, b__ long, hit_spans array<struct<start:int,end:int>>")
    names = hits.select("a__", "b__", *key).distinct().join(windows.where("item is not null").distinct(), key)
    names = names.select("a__", "b__", "item").distinct().groupBy("a__", "b__").agg(F.array_sort(F.collect_list("item")).alias("hit_items"))
    both = runs.join(names, ["a__", "b__"], "left").select("a__", "b__", "hit_spans", F.coalesce("hit_items", F.array().cast("array<string>")).alias("hit_items"))
    return spool(both, "hits")


def count_words(text: Column) -> Column:
    """Runs of ASCII letters and digits and of anything beyond ASCII."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[0-9A-Za-z\x{80}-\x{10FFFF}]+")), F.lit(0)).cast("long")


def benchmark_hits(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", span: int = 10, k: int = 5, most_bits: int = MOST_BITS) -> DataFrame:
    """``docs`` with ``n_words long``, ``hit_items array<string>`` (sorted) and
    ``hit_spans array<struct<start,end>>`` (word positions, end excluded).

    Words are runs of ASCII digits, ASCII letters (lower-cased) and anything
    beyond ASCII.  Null or empty text: no words, no hits.  Items without words
    match nothing; an item without id is a hit but is not listed; equal items
    are all listed.  An empty benchmark leaves every document clean, an empty
    table stays empty; repeated rows are all returned.  Columns with the new
    names are replaced.
    """
    new = ("n_words", "hit_items", "hit_spans")
    hits = find_hits(docs, benchmark, text, item_id, item_text, span, k, most_bits).withColumnsRenamed({"a__": "x__", "b__": "y__"})
    kept = [c for c in docs.columns if c not in new]
    out = docs.select(*kept, *text_key(text), count_words(F.col(text)).alias("n_words"))
    out = out.join(hits, (F.col("a__") == F.col("x__")) & (F.col("b__") == F.col("y__")), "left")
    none = {"hit_items": "array<string>", "hit_spans": "array<struct<start:int,end:int>>"}
    return out.select(*kept, "n_words", *[F.coalesce(c, F.array().cast(t)).alias(c) for c, t in none.items()])


def drop_hits(docs: DataFrame, benchmark: DataFrame, text: str = "text", span: int = 10, k: int = 5) -> DataFrame:
    """The rows of ``docs`` that share no window with the benchmark, columns untouched (null texts stay)."""
    hits = find_hits(docs, benchmark, text, span=span, k=k).select("a__", "b__")
    a, b = text_key(text)
    return docs.join(hits, (a == F.col("a__")) & (b == F.col("b__")) & F.col(text).isNotNull(), "left_anti")


def digest(hits: DataFrame, doc_id: str = "doc_id") -> DataFrame:
    """One row per document: counts of words, hit words and items, and the digest of the sorted items."""
    return hits.select(
        doc_id,
        "n_words",
        F.expr("aggregate(hit_spans, 0L, (s, x) -> s + x.end - x.start)").alias("n_hit"),
        F.size("hit_items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", F.array_sort("hit_items")), 256).alias("items_sha256"),
        (F.size("hit_spans") > 0).alias("contaminated"),
    )


def brute_force(docs: list[tuple[int, str | None]], items: list[tuple[object, str | None]], span: int = 10) -> list[tuple]:
    """The same figures word by word, for small tests."""
    import re

    def words(t):
        return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))

    known: dict[tuple, set] = {}
    for i, t in items:
        w = words(t)
        for m in [min(span, len(w))] if w else []:
            for s in range(len(w) - m + 1):
                known.setdefault(tuple(w[s : s + m]), set()).add(i)
    sizes = {len(x) for x in known}
    out = []
    for d, t in docs:
        w, hit, got = words(t), set(), set()
        for m in sizes:
            for s in range(len(w) - m + 1):
                if (g := known.get(tuple(w[s : s + m]))) is not None:
                    hit.update(range(s, s + m))
                    got |= g
        names = sorted(str(x) for x in got if x is not None)
        out.append((d, len(w), len(hit), len(names), hashlib.sha256(",".join(names).encode()).hexdigest(), bool(hit)))
    return out
