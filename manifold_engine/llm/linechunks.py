"""Line deduplication over content-defined line chunks, in DataFrame functions only.

A unit is a run of two or more neighbouring lines; blank lines are no lines of a
unit, but go with it where they stand inside.  Every unit that has occurred
before, in order of document id and line, is taken out, so what goes is the
union of all repeated runs of two lines or more.

The work is done on line hashes (128 bits a line), written once:

1. *chunks*: a rolling hash over neighbouring line hashes ends a chunk where it
   is divisible by ``every``.  The cut depends on two lines alone, so inserting
   or deleting lines shifts no cut further on.  Chunks that occur again are
   found by one small row each, which settles the bulk of long repeats.
2. *edges*: the pairs of neighbouring lines that no found chunk holds (at the
   rims of repeats, in short repeats, in runs of equal lines) meet the same way.
   A pair inside a found chunk can be no first occurrence, as the chunk's own
   first occurrence has it too.
3. *comparison*: the first occurrences' bytes are fetched, each once, and a unit
   goes only if its lines are equal to them byte by byte.

A chunk that stands in a third of all documents is pre-aggregated for the
count; its occurrences meet its text in a plain join of two exchanges, which
adaptive execution splits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..spool import spool

LAST = (1 << 63) - 1
BLANK = " \t\r\x0b\x0c"


def _let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` computed once for each row."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _full(lines: Column) -> Column:
    """Places of the lines that are not blank."""
    return F.filter(F.transform(lines, lambda x, i: F.when(F.btrim(x, F.lit(BLANK)) != "", i)), lambda i: i.isNotNull())


def _hashes(docs: DataFrame) -> DataFrame:
    """``k, a, b``: two hashes of every full line of the documents that have two or more."""
    lines = F.filter(F.split("text", "\n", -1), lambda x: F.btrim(x, F.lit(BLANK)) != "")
    both = _let(lines, lambda ls: F.struct(F.transform(ls, lambda x: F.xxhash64(x)).alias("a"), F.transform(ls, lambda x: F.xxhash64(F.lit("line"), x)).alias("b")))
    return docs.where(F.instr("text", "\n") > 0).select("k", both.alias("h")).select("k", "h.a", "h.b").where(F.size("a") > 1)


def _later(units: DataFrame) -> DataFrame:
    """Occurrences ``k, start, n, k0, start0`` of units that occurred before; one that overlaps the first is none."""
    first = units.groupBy("a", "b").agg(F.min(F.struct("k", "start")).alias("f"), F.max(F.struct("k", "start")).alias("l")).where("f <> l")
    first = spool(first.select("a", "b", F.col("f.k").alias("k0"), F.col("f.start").alias("start0")), "repeats")
    return units.join(first, ["a", "b"]).where("k <> k0 or start >= start0 + n").select("k", "start", "n", "k0", "start0")


def _chunks(lines: DataFrame, every: int) -> DataFrame:
    """``k, start, n, a, b`` of the chunks of three lines or more (pairs come later)."""

    def ends(h: Column) -> Column:
        cut = F.transform(h, lambda x, i: F.when((i == F.size(h) - 1) | ((i > 0) & (F.pmod(F.xxhash64(F.get(h, i - 1), x), F.lit(every)) == 0)), i + 1))
        return F.filter(cut, lambda e: e.isNotNull())

    def pieces(stops: Column) -> Column:
        return F.transform(stops, lambda e, i: F.struct(F.coalesce(F.get(stops, i - 1), F.lit(0)).alias("start"), e.alias("end")))

    # get() with index -1 gives null for the first chunk
    found = lines.select("k", "a", "b", F.explode(_let(ends(F.col("a")), pieces)).alias("c")).withColumn("n", F.col("c.end") - F.col("c.start")).where("n > 2")

    def of(h: str) -> Column:
        return F.xxhash64("n", F.slice(h, F.col("c.start") + 1, F.col("n")))

    return found.select("k", F.col("c.start").alias("start"), "n", of("a").alias("a"), of("b").alias("b"))


def _pairs(lines: DataFrame, gone: DataFrame) -> DataFrame:
    """``k, start, n, a, b`` of the neighbouring lines that no repeated chunk holds."""
    held = gone.groupBy(F.col("k").alias("of__")).agg(F.array_distinct(F.flatten(F.collect_list(F.expr("sequence(start, start + n - 2)")))).alias("held"))
    both = lines.join(held, F.col("k") == F.col("of__"), "left")
    every = F.sequence(F.lit(0), F.size("a") - 2)
    left = both.select("k", "a", "b", F.explode(F.when(F.col("held").isNull(), every).otherwise(F.array_except(every, "held"))).alias("start"))

    def of(h: str) -> Column:
        return F.xxhash64(F.get(h, F.col("start")), F.get(h, F.col("start") + 1))

    return left.select("k", "start", F.lit(2).alias("n"), of("a").alias("a"), of("b").alias("b"))


def repeated_units(keyed: DataFrame, every: int) -> DataFrame:
    """``k, start, n, chunks``: units of full lines to take out of document ``k`` if their text is in ``chunks``."""
    lines = spool(_hashes(keyed), "lines")
    chunks = spool(_later(_chunks(lines, every)).distinct(), "chunks")
    units = spool(chunks.union(_later(_pairs(lines, chunks)).distinct()), "units")
    wanted = units.select("k0", "start0", "n").distinct().groupBy(F.col("k0")).agg(F.collect_list(F.struct("start0", "n")).alias("want"))
    there = keyed.join(wanted, F.col("k") == F.col("k0")).select("k0", F.filter(F.split("text", "\n", -1), lambda x: F.btrim(x, F.lit(BLANK)) != "").alias("ls"), F.explode("want").alias("w"))
    known = there.select("k0", "w.start0", "w.n", F.array_join(F.slice("ls", F.col("w.start0") + 1, F.col("w.n")), "\n").alias("chunk"))
    known = known.groupBy("k0", "start0", "n").agg(F.collect_set("chunk").alias("chunks"))  # several where documents share an id
    return units.join(known, ["k0", "start0", "n"]).select("k", "start", "n", "chunks")


def drop_repeated_chunks(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", every: int = 4, n_removed: str = "n_removed", n_lines: str = "n_lines") -> DataFrame:
    """``docs`` with the repeated runs of lines taken out of ``text``, and ``n_lines``, ``n_removed``.

    Lines end at LF alone.  Null text stays null (no lines); a text left
    without lines becomes empty.  A null id ranks behind all others.  Rows that
    share an id are one document: the same place in both is one occurrence, so
    of repeated rows all stay.  Columns named like the two new ones are
    replaced.  An empty table gives an empty table.  ``every`` changes what is
    shuffled, not what is taken out.
    """
    own = F.coalesce(F.col(doc_id).cast("long"), F.lit(LAST))
    cuts = repeated_units(docs.select(own.alias("k"), F.col(text).alias("text")), every)
    cuts = cuts.groupBy(F.col("k").alias("of__")).agg(F.collect_list(F.struct("start", "n", "chunks")).alias("cuts__"))
    kept = [c for c in docs.columns if c not in (n_removed, n_lines)]
    both = docs.select(*kept, own.alias("k__")).join(cuts, F.col("k__") == F.col("of__"), "left")

    def clean(lines: Column, full: Column) -> Column:
        words = F.transform(full, lambda i: F.get(lines, i))
        real = F.filter(F.col("cuts__"), lambda c: F.array_contains(c["chunks"], F.array_join(F.slice(words, c["start"] + 1, c["n"]), "\n")))
        places = F.flatten(F.transform(real, lambda c: F.sequence(F.get(full, c["start"]), F.get(full, c["start"] + c["n"] - 1))))

        def rest(gone: Column) -> Column:
            """What stands before, between and behind the runs of lines that go: slices, so the work is linear."""
            firsts = F.filter(gone, lambda x, i: (i == 0) | (F.get(gone, i - 1) != x - 1))
            lasts = F.filter(gone, lambda x, i: (i == F.size(gone) - 1) | (F.get(gone, i + 1) != x + 1))
            ends = F.concat(firsts, F.array(F.size(lines)))
            starts = F.concat(F.array(F.lit(0)), F.transform(lasts, lambda x: x + 1))
            left = F.flatten(F.zip_with(starts, ends, lambda s, e: F.slice(lines, s + 1, e - s)))
            return F.struct(F.size(gone).alias("gone"), F.array_join(left, "\n").alias("text"))

        return _let(F.array_sort(F.array_distinct(places)), rest)

    # most documents have no cut: they skip the work
    none = F.struct(F.lit(0).alias("gone"), F.col(text).alias("text"))
    done = F.when(F.col("cuts__").isNull() | F.col(text).isNull(), none).otherwise(_let(F.split(text, "\n", -1), lambda ls: _let(_full(ls), lambda full: clean(ls, full))))
    lines = F.when(F.col(text).isNull(), F.lit(0)).otherwise(F.length(text) - F.length(F.translate(text, "\n", "")) + 1)
    out = both.select("*", done.alias("r__"), lines.cast("long").alias(n_lines))
    return out.select(*[F.col("r__.text").alias(c) if c == text else F.col(c) for c in kept], n_lines, F.col("r__.gone").cast("long").alias(n_removed))


ORACLE = r"""
with d as (select doc_id, text, string_split(text, chr(10)) as ls from documents),
l as (select doc_id, unnest(ls) as x, unnest(range(0, len(ls))) as i from d where text is not null),
f as (select doc_id, x, i, row_number() over w as r, lead(x) over w as y, lead(i) over w as j from l
      where length(translate(x, ' ' || chr(9) || chr(11) || chr(12) || chr(13), '')) > 0 window w as (partition by doc_id order by i)),
m as (select *, min((doc_id, r)) over (partition by x, y) as o from f where y is not null),
g as (select distinct doc_id, unnest(range(i, j + 1)) as i from m where doc_id <> o[1] or r >= o[2] + 2),
k as (select l.doc_id, string_agg(x, chr(10) order by l.i) as t, count(*) as n from l anti join g on l.doc_id = g.doc_id and l.i = g.i group by l.doc_id)
select d.doc_id, cast(coalesce(len(ls), 0) as bigint) as n_lines, cast(coalesce(len(ls), 0) - coalesce(k.n, 0) as bigint) as n_removed,
       case when d.text is null then null else coalesce(k.t, '') end as text
from d left join k on d.doc_id = k.doc_id
"""


def brute_force(docs: list[tuple[int | None, str | None]]) -> list[tuple]:
    """``doc_id, n_lines, n_removed, text`` by plain loops over maximal repeated runs; ids must be distinct."""
    split = [(LAST if d is None else d, d, None if t is None else t.split("\n")) for d, t in docs]
    full = {k: [(i, x) for i, x in enumerate(ls or []) if x.strip(BLANK)] for k, _, ls in split}
    first: dict[tuple, tuple] = {}
    for k in sorted(full):
        for r in range(len(full[k]) - 1):
            first.setdefault((full[k][r][1], full[k][r + 1][1]), (k, r))
    out = []
    for k, d, ls in split:
        gone = set()
        for r in range(len(full[k]) - 1):
            k0, r0 = first[full[k][r][1], full[k][r + 1][1]]
            if k0 != k or r >= r0 + 2:
                gone.update(range(full[k][r][0], full[k][r + 1][0] + 1))
        left = [x for i, x in enumerate(ls or []) if i not in gone]
        out.append((d, len(ls or []), len(gone), None if ls is None else "\n".join(left)))
    return out
