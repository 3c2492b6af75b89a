"""N-gram Jaccard join: a size-aware join with a heavy and a light side.

A document is the set of its distinct word n-grams.  Documents with equal sets
are one class; one document of each class speaks for it.

*Light* sets (up to ``boundary`` n-grams) enumerate subsets.  Two sets of sizes
``a`` and ``b`` are linked exactly if they share ``c(a, b)`` n-grams, so each
light set emits all its subsets of that fixed size for every partner size, and
equal subsets of both sizes are links as they stand: no pairs are compared.

*Heavy* sets scan inverted lists.  All hashes meet once in buckets to learn
their document frequency.  A set that does not hold enough n-grams known to
others is done.  The rest order their n-grams from rare to frequent and list
only the prefix within which any partner must meet them.

Lists can be long where thousands of near copies share an n-gram, so pairs are
never spelled out.  Round 1 compares every entry with the first document of its
list; links are contracted to components.  Round 2 does the same with the first
documents of lists that lead to another component.  Round 3 takes the lists
that still hold several components: blocks of their entries meet blocks, where
length, position in the list and a parity sketch of each set (how many bits two
sketches differ in is never more than how many n-grams the sets differ in)
leave the few pairs whose sets are then compared.  Entries of a list's largest
component meet only the others, never each other.

``boundary`` is chosen by cost: the enumerated subsets of all sets of a size
against the entries of their lists as measured on the sets near the boundary.
"""

from __future__ import annotations

from fractions import Fraction
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..graph import components
from ..spool import spool
from . import grams
from .arrowmap import append_columns
from .packing import MESSAGE, Layout, address, contains, deliver, lay_out, read, run_starts

LARGEST_LIGHT = 24  # enumeration beyond this size never pays at thresholds up to 0.95


def as_fraction(t: float | Fraction) -> Fraction:
    return t if isinstance(t, Fraction) else Fraction(str(t))


def need(a: int, b: int, t: Fraction) -> int:
    """Least overlap of sets of ``a`` and ``b`` elements that gives Jaccard ``t`` (exact arithmetic)."""
    x = t * (a + b) / (1 + t)
    return -(-x.numerator // x.denominator)


def partner_sizes(a: int, t: Fraction) -> range:
    """Sizes a linked set may have."""
    low = t * a
    high = a / t
    return range(-(-low.numerator // low.denominator), high.numerator // high.denominator + 1)


def subset_count(a: int, t: Fraction) -> int:
    return sum(comb(a, need(a, b, t)) for b in partner_sizes(a, t) if need(a, b, t) <= min(a, b))


def shingle_sets(texts: list[bytes], n: int) -> list[np.ndarray]:
    """Sorted distinct n-gram hashes of each text; a text of fewer words has its whole sequence as one."""
    a, offsets = grams.hash_words(texts, grams.LOWER)
    whole = grams.windows(a, n)
    out = []
    for i, j in zip(offsets, offsets[1:]):
        if j - i >= n:
            out.append(np.unique(whole[i : j - n + 1]))
        elif j > i:
            out.append(grams.windows(a[i:j], int(j - i)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def signature(s: np.ndarray) -> bytes:
    return xxhash.xxh3_128_digest(s.tobytes())


def _signatures(text: str, n: int):
    def make():
        def fn(part):
            texts = grams.texts_of(part.column(text))
            sets = shingle_sets(texts, n)
            return [pa.array([len(s) for s in sets], pa.int64()), pa.array(list(map(signature, sets)), pa.binary()), pa.array(list(map(len, texts)), pa.int64())]

        return fn

    return make


class _Group:
    """The sets of one group's representatives, each under the node of its class."""

    def __init__(self, docs: pa.Table, rest: pa.Table, n: int):
        ids = grams.ids_of(docs.column("doc_id"))
        speaks = {(r, s): v for r, s, v in zip(*(rest.column(c).to_pylist() for c in ("rep", "sig", "node"))) if r is not None}
        at = np.flatnonzero(np.isin(ids, np.array(sorted({r for r, _ in speaks}), np.int64)))
        texts = docs.column("text").take(pa.array(at))
        sets = shingle_sets(grams.texts_of(texts), n)
        found: dict[int, np.ndarray] = {}
        for i, s in zip(ids[at].tolist(), sets):
            if (node := speaks.get((i, signature(s)))) is not None:
                found[node] = s  # rows that share id and text hold the same set
        self.nodes, self.sets = list(found), list(found.values())
        self.flat = np.concatenate(self.sets) if self.sets else np.zeros(0, np.uint64)


LOW = np.uint64(0xFFFFFFFF)


def _keys(h: np.ndarray, names: np.ndarray) -> np.ndarray:
    """Bucket and 32 further bits of a hash: what frequencies are counted by.

    Two n-grams that share a key get the sum of their frequencies everywhere,
    which can only make a set look better known and keeps the common order;
    overlaps are always counted on whole hashes.
    """
    return (names[((h >> np.uint64(32)) % np.uint64(len(names))).astype(np.int64)] << np.uint64(32)) | (h & LOW)


def _ask(n: int, plan: Layout):
    names, per = plan.bucket_names(), plan.per(plan.buckets)

    def fn(key, docs, rest):
        k, counts = np.unique(_keys(_Group(docs, rest, n).flat, names), return_counts=True)
        small = np.uint8 if not len(counts) or counts.max() < 256 else np.uint32
        return address(key[0].as_py(), (k >> np.uint64(32)).astype(np.int64), per, [(k & LOW).astype(np.uint32), counts.astype(small)], "g")

    return fn


def _frequencies(per: int):
    """Document frequency of the keys that two documents have, to each group that asked."""

    def fn(key, rows):
        g, _, (low, times) = read(rows.column("payload"), 2)
        order = np.argsort(low, kind="stable")
        starts = run_starts(low[order])
        total = np.empty(len(low), np.int64)
        total[order] = np.repeat(np.add.reduceat(times[order].astype(np.int64), starts), np.diff(np.append(starts, len(low))))
        seen = np.flatnonzero(total > 1)
        seen = seen[np.argsort(g[seen], kind="stable")]
        return address(key[0].as_py(), g[seen], per, [low[seen], total[seen].astype(np.uint32)], "b")

    return fn


CANDIDATES = "doc_id long, size int, known binary, ranks binary, prefix int"


def _candidates(n: int, t: Fraction, plan: Layout):
    """Sets that may have a partner: their n-grams known to others, from rare to frequent."""
    names = plan.bucket_names()

    def fn(key, docs, rest):
        _, b, (low, df) = read(rest.column("payload"), 2)
        rows = {"doc_id": [], "size": [], "known": [], "ranks": [], "prefix": []}
        group = _Group(docs, rest, n) if len(low) else None
        if group is not None and len(group.flat):
            h = (b.astype(np.uint64) << np.uint64(32)) | low
            order = np.argsort(h)
            h, df = h[order], df[order]
            for d, s in zip(group.nodes, group.sets):
                share = t * len(s)
                least = -(-share.numerator // share.denominator)
                k = _keys(s, names)
                at = np.minimum(np.searchsorted(h, k), len(h) - 1)
                seen = h[at] == k
                own = s[seen]
                if len(own) < max(1, least):
                    continue
                f = df[at[seen]]
                order = np.lexsort((own, f))
                rows["doc_id"].append(d)
                rows["size"].append(len(s))
                rows["known"].append(own[order].tobytes())
                rows["ranks"].append(f[order].tobytes())
                # the unknown ones come first in the common order and fill part of the prefix
                rows["prefix"].append(len(own) - least + 1)
        return pa.table({"doc_id": pa.array(rows["doc_id"], pa.int64()), "size": pa.array(rows["size"], pa.int32()), "known": pa.array(rows["known"], pa.binary()), "ranks": pa.array(rows["ranks"], pa.binary()), "prefix": pa.array(rows["prefix"], pa.int32())})

    return fn


def _subsets(t: Fraction, boundary: int):
    """Light sets: hashes of all subsets of the fixed size for each partner size."""
    from itertools import combinations

    def fn(batches):
        for batch in batches:
            docs, lows, highs, size, keys = [], [], [], [], []
            for d, s, known in zip(batch.column("doc_id").to_pylist(), batch.column("size").to_pylist(), batch.column("known").to_pylist()):
                own = np.sort(np.frombuffer(known, np.uint64))
                for b in partner_sizes(s, t):
                    c = need(s, b, t)
                    if b > boundary or c > min(s, b) or c > len(own):
                        continue
                    for pick in combinations(range(len(own)), c):
                        docs.append(d)
                        lows.append(min(s, b))
                        highs.append(max(s, b))
                        size.append(s)
                        keys.append(xxhash.xxh3_128_digest(own[list(pick)].tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(lows, pa.int32()), pa.array(highs, pa.int32()), pa.array(size, pa.int32()), pa.array(keys, pa.binary())], names=["doc_id", "low", "high", "size", "subset"])

    return fn


def _light_links(light: DataFrame, t: Fraction, boundary: int) -> DataFrame:
    """Star edges between sets that share a subset of the size their two sizes call for."""
    subs = light.select("doc_id", "size", "known").mapInArrow(_subsets(t, boundary), "doc_id long, low int, high int, size int, subset binary")
    subs = spool(subs, "subsets")
    key = ["low", "high", "subset"]
    hub = subs.groupBy(*key).agg(F.min("doc_id").alias("v"), F.max("doc_id").alias("w"), F.min("size").alias("s"), F.max("size").alias("l")).where("v < w and s = low and l = high").select(*key, "v")
    return subs.join(spool(hub, "hubs"), key).where("doc_id <> v").select(F.col("doc_id").alias("u"), "v").distinct()


def _verify(t: Fraction):
    """Overlap of this group's sets with sets sent to it."""

    def fn(key, mine, sent):
        known = dict(zip(mine.column("doc_id").to_pylist(), zip(mine.column("size").to_pylist(), mine.column("known").to_pylist())))
        us, vs, ds, ok = [], [], [], []
        sets: dict[int, np.ndarray] = {}
        for v, size, raw, others in zip(*(sent.column(c).to_pylist() for c in ("v", "v_size", "v_known", "us"))):
            target = np.sort(np.frombuffer(raw, np.uint64))
            for u in others:
                if u not in known:
                    continue
                s, own = known[u]
                if u not in sets:
                    sets[u] = np.frombuffer(own, np.uint64)
                both = int(contains(target, sets[u]).sum())
                us.append(u)
                vs.append(v)
                ds.append(1.0 - both / (s + size - both))
                ok.append(both * t.denominator >= t.numerator * (s + size - both))
        return pa.table({"u": pa.array(us, pa.int64()), "v": pa.array(vs, pa.int64()), "dist": pa.array(ds, pa.float64()), "link": pa.array(ok, pa.bool_())})

    return fn


def _compare(cand: DataFrame, pairs: DataFrame, t: Fraction, groups: int) -> DataFrame:
    """Distances of ``(u, v)``; each group of ``u`` is sent one copy of each ``v`` it asks for."""
    own = cand.select("doc_id", "size", "known", F.pmod(F.xxhash64("doc_id"), F.lit(groups)).cast("int").alias("g"))
    asked = pairs.select(F.pmod(F.xxhash64("u"), F.lit(groups)).cast("int").alias("g"), "u", "v").groupBy("g", "v").agg(F.collect_set("u").alias("us"))
    sent = asked.join(cand.select(F.col("doc_id").alias("v"), F.col("size").alias("v_size"), F.col("known").alias("v_known")), "v")
    return own.groupBy("g").cogroup(sent.groupBy("g")).applyInArrow(_verify(t), "u long, v long, dist double, link boolean")


def choose_boundary(sizes: dict[int, int], lists: dict[int, float], t: Fraction) -> int:
    """The largest light size: enumeration costs a key per subset, the lists one comparison per entry met.

    ``sizes`` counts sets, ``lists`` is the mean list length met by sets of a
    size.  A comparison is weighed as ten keys.
    """
    best, at, saved = 0, 0, 0.0
    for s in range(1, LARGEST_LIGHT + 1):
        low = t * s
        prefix = s - -(-low.numerator // low.denominator) + 1
        saved += sizes.get(s, 0) * (10 * prefix * max(1.0, lists.get(s, 1.0)) - subset_count(s, t))
        if saved >= best:
            best, at = saved, s
        if subset_count(s, t) > 5000:
            break
    return at


def _prefixes(cand: DataFrame) -> DataFrame:
    """``(tok, doc_id, size, df, after)``: the list entries of each set, with how many n-grams stand at or behind each."""

    def fn(batches):
        for batch in batches:
            toks, docs, sizes, freq, after = [], [], [], [], []
            for d, s, known, ranks, p in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "size", "known", "ranks", "prefix"))):
                own = np.frombuffer(known, np.int64)
                toks.append(own[:p])
                freq.append(np.frombuffer(ranks, np.uint32)[:p].astype(np.int64))
                docs.append(np.full(p, d))
                sizes.append(np.full(p, s, np.int32))
                after.append(np.arange(len(own), len(own) - p, -1, dtype=np.int32))
            if toks:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (toks, docs, sizes, freq, after)], names=["tok", "doc_id", "size", "df", "after"])

    return cand.mapInArrow(fn, "tok long, doc_id long, size int, df long, after int")


# round 3: blocks of list entries


BLOCK = 1024


def sketch_bits(size: int) -> int:
    """Bits of a set's parity sketch: a power of two, four to eight a member."""
    return max(256, 1 << (4 * size - 1).bit_length())


def _sketches(cand: DataFrame) -> DataFrame:
    """``doc_id, n_known, sketch``: parities of the known n-grams by their lowest hash bits."""

    def fn(batches):
        for batch in batches:
            ns, out = [], []
            for size, known in zip(batch.column("size").to_pylist(), batch.column("known").to_pylist()):
                h = np.frombuffer(known, np.uint64)
                bits = sketch_bits(size)
                odd = np.bincount((h & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
                ns.append(len(h))
                out.append(np.packbits(odd.astype(np.uint8)).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(ns, pa.int32()), pa.array(out, pa.binary())], names=["doc_id", "n_known", "sketch"])

    return cand.mapInArrow(fn, "doc_id long, n_known int, sketch binary")


class _Sketches:
    """The sketches of one batch of entries, folded to a common width where two widths meet."""

    def __init__(self, raw: list[bytes]):
        self.raw = [np.frombuffer(r, np.uint8) for r in raw]
        self.bits = np.array([8 * len(r) for r in raw])
        self.at: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def _width(self, w: int) -> tuple[np.ndarray, np.ndarray]:
        if w not in self.at:
            use = np.flatnonzero(self.bits >= w)
            row = np.full(len(self.bits), -1)
            row[use] = np.arange(len(use))
            folded = [np.bitwise_xor.reduce(self.raw[i].reshape(-1, w // 8), axis=0) for i in use]
            self.at[w] = row, np.ascontiguousarray(np.stack(folded)).view(np.uint64)
        return self.at[w]

    def differ(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """In how many bits the sketches of entries ``x[i]`` and ``y[i]`` differ."""
        out = np.zeros(len(x), np.int64)
        common = np.minimum(self.bits[x], self.bits[y])
        for w in np.unique(common).tolist():
            row, m = self._width(w)
            pick = np.flatnonzero(common == w)
            step = max(1, (1 << 24) // w)
            for s in range(0, len(pick), step):
                p = pick[s : s + step]
                out[p] = np.bitwise_count(m[row[x[p]]] ^ m[row[y[p]]]).sum(1)
        return out


def _meet(t: Fraction, boundary: int):
    """Pairs of entries of one list, of different components, that length, position and sketch leave."""
    tn, td = t.numerator, t.denominator

    def fn(rows):
        tok, p, q, z, b = (rows.column(c).to_numpy() for c in ("tok", "p", "q", "z", "b"))
        doc, size, comp, after, known = (rows.column(c).to_numpy().astype(np.int64) for c in ("doc_id", "size", "comp", "after", "n_known"))
        sketches = _Sketches(rows.column("sketch").to_pylist())
        order = np.lexsort((doc, z, q, p, tok))
        starts = run_starts(tok[order], p[order], q[order], z[order])
        us, vs = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for i, j in zip(starts, np.append(starts[1:], len(order))):
            own = order[i:j]
            first, second, guests = p[own[0]], q[own[0]], z[own[0]] > 0
            left = own[b[own] == first]
            right = own[b[own] == (-1 if guests else second)]
            for s in range(0, len(left), 128):
                x, y = left[s : s + 128][:, None], right[None, :]
                few, many = np.minimum(size[x], size[y]), np.maximum(size[x], size[y])
                ok = (comp[x] != comp[y]) & (few * td >= many * tn) & (many > boundary)
                # were this their first common n-gram, what follows it in both would have to do
                ok &= np.minimum(after[x], after[y]) * (td + tn) >= (few + many) * tn
                if first == second and not guests:
                    ok &= doc[x] < doc[y]
                r, c = np.nonzero(ok)
                x, y = left[s + r], right[c]
                shared = (known[x] + known[y] - sketches.differ(x, y)) // 2
                fine = shared * (td + tn) >= (size[x] + size[y]) * tn
                us.append(doc[x[fine]])
                vs.append(doc[y[fine]])
        u, v = np.concatenate(us), np.concatenate(vs)
        pairs = np.unique(np.stack([np.minimum(u, v), np.maximum(u, v)], 1), axis=0)
        return pa.table({"u": pa.array(pairs[:, 0]), "v": pa.array(pairs[:, 1])})

    return fn


def _across(lists: DataFrame, comp: DataFrame, cand: DataFrame, t: Fraction, boundary: int, block: int = BLOCK) -> DataFrame:
    """``u, v``: pairs worth a comparison among entries of one list that are in different components.

    The largest component of a list is cut into portions that visit the blocks
    of its other entries; these blocks also meet each other.
    """
    tagged = spool(lists.select("tok", "doc_id", "size", "after").join(comp.select(F.col("id").alias("doc_id"), "comp"), "doc_id", "left").withColumn("comp", F.coalesce("comp", "doc_id")), "tagged")
    shares = tagged.groupBy("tok", F.col("comp").alias("c")).agg(F.count("*").alias("n"))
    mixed = shares.groupBy("tok").agg(F.max(F.struct("n", "c")).alias("m"), F.sum("n").alias("all")).where("all > m.n and all > 2")
    mixed = mixed.select("tok", F.col("m.c").alias("main"), F.ceil((F.col("all") - F.col("m.n")) / block).cast("int").alias("k"), F.ceil(F.col("m.n") / (4 * block)).cast("int").alias("visits"))
    left = spool(tagged.join(spool(mixed, "mixed"), "tok"), "left")
    sketches = _sketches(cand.join(left.select("doc_id").distinct(), "doc_id", "left_semi"))
    left = spool(left.join(sketches, "doc_id"), "left")

    def slots(df: DataFrame) -> int:
        return int((df.agg(F.sum(F.length("sketch") + 64)).first()[0] or 0) >> 22) + 1

    h, zero = F.xxhash64("doc_id"), F.lit(0)
    others = left.where("comp <> main").withColumn("b", F.pmod(h, "k").cast("int"))
    home = others.select("*", F.explode(F.sequence(zero, F.col("k") - 1)).alias("o")).select("*", F.least("b", "o").alias("p"), F.greatest("b", "o").alias("q"), zero.alias("z"))
    hosts = others.select("*", F.col("b").alias("o"), F.col("b").alias("p"), F.col("b").alias("q"), F.explode(F.sequence(F.lit(1), "visits")).alias("z"))
    guests = left.where("comp = main").withColumn("b", F.lit(-1)).select("*", F.explode(F.sequence(zero, F.col("k") - 1)).alias("o"))
    guests = guests.select("*", F.col("o").alias("p"), F.col("o").alias("q"), (F.pmod(h, "visits") + 1).cast("int").alias("z"))
    sent = home.union(hosts).union(guests).select("tok", "p", "q", "z", "b", "doc_id", "size", "comp", "after", "n_known", "sketch")
    sent = sent.withColumn("slot", F.pmod(F.xxhash64("tok", "p", "q", "z"), F.lit(slots(left))).cast("int"))
    return sent.groupBy("slot").applyInArrow(_meet(t, boundary), "u long, v long").distinct()


def near_groups(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", n: int = 5, threshold: float | Fraction = 0.8, layout: dict | None = None, report: dict | None = None) -> DataFrame:
    """``doc_id, n_shingles, component_id`` for every row of ``docs``.

    Words are runs of anything but ASCII white space with A-Z lower-cased.
    Null, empty and word-less texts have no set, link with nothing and are
    their own component, as is a row with a null id (its component is null).
    Rows that share an id are one node, whatever their texts.  Other columns
    are not read; an empty table gives an empty table.
    ``threshold`` is exact: a float is read as the decimal it prints as.
    ``layout`` changes the sizes of ``packing.lay_out``; ``report`` is given
    the number of pairs compared in each round.
    """
    t = as_fraction(threshold)
    if not 0 < t <= 1:
        raise ValueError("threshold must lie in (0, 1]")
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    spark = docs.sparkSession
    fields = [T.StructField("n_shingles", T.LongType()), T.StructField("sig", T.BinaryType()), T.StructField("n_bytes", T.LongType())]
    signed = spool(append_columns(rows, "text", _signatures("text", n), fields, drop=("text",)), "sets")
    real = signed.where("n_shingles > 0 and doc_id is not null")
    classes = spool(real.groupBy("sig").agg(F.min("doc_id").alias("rep")), "classes")
    # a class is known by its smallest id; where two texts share that id, by a hash of its set
    clash = classes.groupBy("rep").agg(F.count("*").alias("n")).where("n > 1").select("rep", F.lit(True).alias("clash"))
    classes = spool(classes.join(clash, "rep", "left").select("sig", "rep", F.when(F.col("clash"), F.xxhash64("sig")).otherwise(F.col("rep")).alias("node")), "classes")

    plan = lay_out(spark, signed.agg(F.sum("n_bytes")).first()[0] or 0, **(layout or {}))
    dealt = rows.withColumn("g", plan.group_of(F.col("doc_id"))).repartition(plan.parts, "g")
    none = {"rep": "long", "sig": "binary", "node": "long", "payload": "binary"}
    speakers = classes.select(plan.group_of(F.col("rep")).alias("g"), "rep", "sig", "node", F.lit(None).cast("binary").alias("payload"))

    def beside(answers):
        right = speakers
        if answers is not None:
            right = right.unionByName(answers.select(F.col("to").alias("g"), *[(F.col(c) if c == "payload" else F.lit(None).cast(k).alias(c)) for c, k in none.items()]))
        return dealt.groupBy("g").cogroup(right.repartition(plan.parts, "g").groupBy("g"))

    asked = deliver(beside(None).applyInArrow(_ask(n, plan), MESSAGE), plan.per(plan.buckets), plan.parts, "b")
    told = asked.repartition(plan.slots, "to").groupBy("to").applyInArrow(_frequencies(plan.per(plan.groups)), MESSAGE)
    told = deliver(told, plan.per(plan.groups), plan.parts, "g")
    cand = spool(beside(told).applyInArrow(_candidates(n, t, plan), CANDIDATES), "candidates")

    # light sets, with the boundary by cost
    small = cand.where(F.col("size") <= LARGEST_LIGHT)
    stats = {r["size"]: (r["n"], r["m"]) for r in _prefixes(small).groupBy("size").agg(F.count_distinct("doc_id").alias("n"), F.avg("df").alias("m")).collect()}
    boundary = choose_boundary({s: x[0] for s, x in stats.items()}, {s: float(x[1]) for s, x in stats.items()}, t)
    light = _light_links(cand.where(F.col("size") <= boundary), t, boundary) if boundary else None

    # heavy sets against all sets they can reach
    reach = t * (boundary + 1)
    heavy = cand.where(F.col("size") >= -(-reach.numerator // reach.denominator))
    lists = spool(_prefixes(heavy), "lists")
    tn, td = t.numerator, t.denominator
    groups = len(plan.groups)

    def fits(x: str, y: str):
        """Lengths allow a link, and the list is needed for it: light pairs are done."""
        return (F.least(x, y).cast("long") * td >= F.greatest(x, y).cast("long") * tn) & (F.greatest(x, y) > boundary)

    hub = lists.groupBy("tok").agg(F.min(F.struct("doc_id", "size")).alias("m"), F.max("doc_id").alias("w")).where("m.doc_id < w")
    hub = hub.select("tok", F.col("m.doc_id").alias("v"), F.col("m.size").alias("v_size"))
    lists = spool(lists.drop("df").join(spool(hub, "hubs"), "tok"), "lists")
    open_to_v = (F.col("doc_id") != F.col("v")) & fits("size", "v_size")

    def compared(pairs: DataFrame, name: str) -> DataFrame:
        found = spool(_compare(cand, pairs, t, groups), "compared")
        if report is not None:
            report[name] = found.count()
        return found

    def linked(found: DataFrame) -> DataFrame | None:
        """The links among compared pairs, ``None`` if there are none: nothing to contract then."""
        own = found.where("link").select("u", "v")
        return own if own.limit(1).count() else None

    # round 1: every set with the smallest first document of its lists
    seen = compared(lists.where(open_to_v).groupBy(F.col("doc_id").alias("u")).agg(F.min("v").alias("v")), "first")
    links = seen.where("link").select("u", "v")
    links = links if light is None else spool(links.union(light), "links")
    comp = spool(components(links), "components")

    def of(name: str, out: str) -> DataFrame:
        return comp.select(F.col("id").alias(name), F.col("comp").alias(out))

    # round 2: with the first documents of lists that lead to another component
    tagged = lists.join(of("doc_id", "uc"), "doc_id", "left").withColumn("uc", F.coalesce("uc", "doc_id")).join(of("v", "vc"), "v", "left").withColumn("vc", F.coalesce("vc", "v"))
    second = tagged.where(open_to_v & (F.col("uc") != F.col("vc"))).select(F.col("doc_id").alias("u"), "v").distinct().join(seen.select("u", "v"), ["u", "v"], "left_anti")
    more = linked(compared(second, "second"))
    if more is not None:
        links = spool(links.union(more), "links")
        comp = spool(components(links), "components")

    # round 3: what the contraction left, entries of one list in different components
    rest = linked(compared(_across(lists, comp, cand, t, boundary), "third"))
    # ids with several texts join the classes of these
    several = real.groupBy("doc_id").agg(F.min("sig").alias("a"), F.max("sig").alias("b")).where("a <> b").select("doc_id")
    own = real.join(several, "doc_id").select("doc_id", "sig").distinct().join(classes.select("sig", "node"), "sig").select("doc_id", "node")
    star = own.join(own.groupBy("doc_id").agg(F.min("node").alias("v")), "doc_id").where("node <> v").select(F.col("node").alias("u"), "v")
    star = spool(star, "star")
    if rest is not None or star.limit(1).count():
        comp = spool(components(links.union(star) if rest is None else links.union(rest).union(star)), "components")

    joined = spool(classes.join(comp, F.col("node") == F.col("id")).select("sig", "rep", "comp"), "joined")
    least = joined.groupBy("comp").agg(F.min("rep").alias("least"))
    member = classes.join(joined.join(least, "comp").select("sig", "least"), "sig", "left").select("sig", F.coalesce("least", "rep").alias("component_id"))
    member = spool(member, "membership")
    same = signed.join(member, (signed.sig == member.sig) & (F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), "left")
    return same.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def keep_smallest(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", n: int = 5, threshold: float = 0.8) -> DataFrame:
    """The rows of ``docs`` whose id is the smallest of their group (rows without id stay)."""
    groups = near_groups(docs, doc_id, text, n, threshold)
    gone = groups.where("component_id <> doc_id").select(F.col("doc_id").alias("gone__")).distinct()
    return docs.join(gone, F.col(doc_id) == F.col("gone__"), "left_anti")


def brute_force(docs: list[tuple[int, str | None]], n: int = 5, threshold: float = 0.8) -> list[tuple]:
    """All pairs of sets, for small tests."""
    import re

    t = as_fraction(threshold)
    sets = []
    for d, x in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), x or ""))
        sets.append((d, {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)} if w else set()))
    up = {d: d for d, _ in sets if d is not None}

    def find(v):
        while up[v] != v:
            v = up[v]
        return v

    for i, (a, s) in enumerate(sets):
        for b, r in sets[:i]:
            if a is not None and b is not None and s and r and len(s & r) * t.denominator >= t.numerator * len(s | r):
                p, q = sorted((find(a), find(b)))
                up[q] = p
    return [(d, len(s), None if d is None else find(d)) for d, s in sets]
