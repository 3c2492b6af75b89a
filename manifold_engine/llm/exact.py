"""Exact deduplication by content sort.

Rows are range-partitioned by sampled splitters over the leading bytes, a hash
of the whole text and the id.  With the id among the splitters a text that a
third of all rows share is cut into several neighbouring partitions, while
equal texts still lie next to each other.  Each partition is sorted externally
by Spark and read as a stream; neighbours are compared in full, byte by byte.
Only the runs at the edges of a partition can go on in the next one: two keys a
partition at most.  Rows of these runs alone are joined with the totals of
their keys; whether by broadcast is the planner's choice, and a hot key is
split by adaptive execution.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spool import plan_bytes, shuffle_partitions, spool

RUNS = "doc_id long, text_sha256 string, best long, size long, winner boolean, edge boolean, pid int"


def _runs(keep: str):
    pick = max if keep == "max" else min

    def emit(runs, edge, pid):
        ids, sha, best, size, winner = [], [], [], [], []
        for text, own in runs:
            known = [x for x in own if x is not None]
            top = pick(known) if known else None
            ids += own
            sha += [hashlib.sha256(text).hexdigest()] * len(own)
            best += [top] * len(own)
            size += [len(own)] * len(own)
            at = own.index(top)
            winner += [i == at for i in range(len(own))]
        n = len(ids)
        return pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), pa.array(sha, pa.string()), pa.array(best, pa.int64()), pa.array(size, pa.int64()), pa.array(winner, pa.bool_()), pa.array([edge] * n, pa.bool_()), pa.array([pid] * n, pa.int32())],
            names=["doc_id", "text_sha256", "best", "size", "winner", "edge", "pid"],
        )

    def fn(batches):
        pid = TaskContext.get().partitionId()
        key, runs, first = None, [], True
        for batch in batches:
            texts = batch.column("t").cast(pa.large_binary())
            ids = batch.column("doc_id").to_pylist()
            heads, hashes = batch.column("head").to_pylist(), batch.column("h").to_pylist()
            done = []
            for i in range(batch.num_rows):
                now = (heads[i], hashes[i])
                text = texts[i].as_py()
                if now != key:
                    if key is not None:
                        if first:
                            yield emit(runs, True, pid)
                        else:
                            done += runs
                        first = False
                    key, runs = now, []
                if runs and runs[-1][0] == text:  # the neighbour, in full
                    runs[-1][1].append(ids[i])
                else:
                    runs.append((text, [ids[i]]))
            if done:
                yield emit(done, False, pid)
        if runs:
            yield emit(runs, True, pid)

    return fn


def exact_groups(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", keep: str = "max") -> DataFrame:
    """One row per row of ``docs``: ``doc_id, keep_id, group_size, kept, text_sha256``.

    ``keep`` says which id of a group stays, ``max`` or ``min``.  Null text
    equals empty text.  A null id stays only where the group has no other.  Of
    rows with the same text and id exactly one is kept.  Other columns are not
    read; an empty table gives an empty table.
    """
    if keep not in ("max", "min"):
        raise ValueError("keep must be max or min")
    spark = docs.sparkSession
    t = F.coalesce(F.col(text), F.lit(""))
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), t.alias("t")).select("doc_id", F.substring(F.encode("t", "utf-8"), 1, 32).alias("head"), F.xxhash64("t").alias("h"), "t")
    parts = min(200_000, max(shuffle_partitions(spark), plan_bytes(rows) // (64 << 20)))
    # equal (head, hash) with different texts would interleave by id: text before id inside a partition, edges by key
    ordered = rows.repartitionByRange(parts, "head", "h", "doc_id").sortWithinPartitions("head", "h", "t", "doc_id")
    runs = spool(ordered.mapInArrow(_runs(keep), RUNS), "runs")
    pick = F.max if keep == "max" else F.min
    edge = runs.where("edge").groupBy("text_sha256", "pid").agg(F.first("best").alias("best"), F.first("size").alias("size"))
    edge = edge.groupBy(F.col("text_sha256").alias("e_sha")).agg(pick("best").alias("e_best"), F.sum("size").alias("e_size"), F.min_by("pid", F.struct(F.col("best").isNull(), F.col("best") if keep == "min" else -F.col("best"), "pid")).alias("e_pid"))
    inside = runs.where("not edge").select("doc_id", F.col("best").alias("keep_id"), F.col("size").alias("group_size"), F.col("winner").alias("kept"), "text_sha256")
    out = runs.where("edge").join(edge, F.col("text_sha256") == F.col("e_sha"))
    return inside.union(out.select("doc_id", F.col("e_best").alias("keep_id"), F.col("e_size").alias("group_size"), (F.col("winner") & (F.col("pid") == F.col("e_pid"))).alias("kept"), "text_sha256"))


ORACLE = """
select doc_id, max(doc_id) over (partition by coalesce(text, '')) as keep_id,
       count(*) over (partition by coalesce(text, '')) as group_size,
       doc_id = max(doc_id) over (partition by coalesce(text, '')) as kept,
       sha256(coalesce(text, '')) as text_sha256
from documents
"""


def brute_force(docs: list[tuple[int | None, str | None]], keep: str = "max") -> list[tuple]:
    groups: dict[str, list] = {}
    for d, t in docs:
        groups.setdefault(t or "", []).append(d)
    out = []
    for t, own in groups.items():
        known = [x for x in own if x is not None]
        best = (max if keep == "max" else min)(known) if known else None
        left = True
        for d in own:
            out.append((d, best, len(own), left and d == best, hashlib.sha256(t.encode()).hexdigest()))
            left &= d != best
    return out
