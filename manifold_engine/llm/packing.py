"""Ask-and-answer exchanges with packed arrays.

Text operators must look up one hash for every word position.  A row for each
would cost a JVM record for 8 bytes; here every document group sends one
message per bucket with all its (already unique) hashes in one binary value,
and gets one back.  A hash that stands in a third of all documents is sent once
by each group, so no bucket grows with the frequency of its hashes.

Groups and buckets have a fixed size, so their numbers grow with the data and
their product with its square.  Beyond ``fan`` of them messages therefore go in
two hops: a group writes at most about ``fan`` messages, each to a range of
buckets, and a streaming stage takes these apart and joins what many groups
send to one bucket.  Answers take the same way back.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_TYPES = "uint8 uint32 uint64 int64 int32".split()


def pack(*arrays: np.ndarray, level: int = 0) -> bytes:
    """Little-endian arrays one after the other behind a small header; ``level`` > 0 compresses."""
    head = [len(arrays)]
    for a in arrays:
        head += [_TYPES.index(a.dtype.name), len(a)]
    raw = np.array(head, np.int64).tobytes() + b"".join(a.tobytes() for a in arrays)
    return b"z" + zstandard.ZstdCompressor(level=level).compress(raw) if level else b"r" + raw


def unpack(data: bytes) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(data[1:]) if data[:1] == b"z" else data[1:]
    n = int(np.frombuffer(raw, np.int64, 1)[0])
    head = np.frombuffer(raw, np.int64, 2 * n, 8)
    at, out = 8 + 16 * n, []
    for t, size in zip(head[::2], head[1::2]):
        a = np.frombuffer(raw, _TYPES[t], int(size), at)
        at += a.nbytes
        out.append(a)
    return out


def bucket_bounds(bucket: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of a sorted bucket array, and where each begins (with the end)."""
    values, first = np.unique(bucket, return_index=True)
    return values, np.append(first, len(bucket))


def run_starts(*sorted_keys: np.ndarray) -> np.ndarray:
    """Where runs of equal keys begin, in arrays sorted together."""
    n = len(sorted_keys[0])
    new = np.ones(n, bool)
    if n:
        new[1:] = False
        for k in sorted_keys:
            new[1:] |= k[1:] != k[:-1]
    return np.flatnonzero(new)


def contains(keys: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Which of ``x`` stand in the sorted ``keys``."""
    if not len(keys):
        return np.zeros(len(x), bool)
    return keys[np.minimum(np.searchsorted(keys, x), len(keys) - 1)] == x


# how a table is dealt

EVEN = 20_000  # up to this many groups their names are chosen so that partitions get equally many


def even_names(spark: SparkSession, count: int, parts: int) -> list[int]:
    """``count`` integers that Spark's hash partitioner spreads evenly over ``parts``; plain numbers beyond ``EVEN``."""
    if count > EVEN:
        return list(range(count))
    each = -(-count // parts)
    found: list[list[int]] = [[] for _ in range(parts)]
    tried, step = 0, 4 * each * parts + 64
    while sum(min(len(f), each) for f in found) < each * parts:
        got = spark.range(tried, tried + step).select(F.pmod(F.hash(F.col("id").cast("int")), F.lit(parts)).alias("p")).toArrow()["p"].to_pylist()
        for i, p in enumerate(got):
            found[p].append(tried + i)
        tried += step
    return [found[k % parts][k // parts] for k in range(count)]


@dataclass(frozen=True)
class Layout:
    """Names of groups and buckets, partitions for each, and how many names one message covers."""

    groups: list[int]
    parts: int
    buckets: list[int]
    slots: int
    fan: int

    def per(self, names: list[int]) -> int:
        return 1 if len(names) <= self.fan else -(-(max(names) + 1) // self.fan)

    def group_of(self, doc_id: Column) -> Column:
        k = F.pmod(F.xxhash64(doc_id), F.lit(len(self.groups))).cast("int")
        if len(self.groups) > EVEN:
            return k
        return F.get(F.split(F.lit(",".join(map(str, self.groups))), ",").cast("array<int>"), k)

    def bucket_names(self) -> np.ndarray:
        return np.array(self.buckets, np.uint64)


def lay_out(spark: SparkSession, size: int, group_bytes: int = 2 << 20, part_bytes: int = 8 << 20, groups_a_bucket: int = 4, fan: int = 1024) -> Layout:
    """Groups of about ``group_bytes`` of text, so that one fits in a Python worker whatever the table's size."""
    groups = max(8, -(-size // group_bytes))
    parts = min(100_000, max(min(8, groups), -(-size // part_bytes)))
    buckets = max(4, groups // groups_a_bucket)
    slots = min(100_000, buckets)
    return Layout(even_names(spark, groups, parts), parts, even_names(spark, buckets, slots), slots, fan)


# messages

MESSAGE = "to int, payload binary"
_FLUSH = 64 << 20


def address(own: int, target: np.ndarray, per: int, arrays: list[np.ndarray], own_is: str, level: int = 0) -> pa.Table:
    """Messages of one group (``own_is="g"``) or bucket (``"b"``) for items sorted by ``target``.

    A message holds segments: group, bucket, length of each, then the arrays.
    """
    to, out = [], []
    if len(target):
        values, first = bucket_bounds(target)
        names, begin = bucket_bounds(values // per)
        for c, i, j in zip(names.tolist(), begin, begin[1:]):
            mine, theirs = np.full(j - i, own, np.int32), values[i:j].astype(np.int32)
            g, b = (mine, theirs) if own_is == "g" else (theirs, mine)
            lo, hi = first[i], first[j]
            to.append(c)
            out.append(pack(g, b, np.diff(first[i : j + 1]).astype(np.uint32), *[a[lo:hi] for a in arrays], level=level))
    return pa.table({"to": pa.array(to, pa.int32()), "payload": pa.array(out, pa.binary())})


def read(payloads: pa.ChunkedArray, arrays: int) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """Group and bucket of every item of some messages, and their arrays."""
    parts = [unpack(p) for p in payloads.to_pylist() if p is not None]
    if not parts:
        return np.zeros(0, np.int32), np.zeros(0, np.int32), [np.zeros(0, np.uint64)] * arrays
    g, b, n, *rest = (np.concatenate(x) for x in zip(*parts))
    return np.repeat(g, n), np.repeat(b, n), rest


def deliver(messages: DataFrame, per: int, parts: int, by: str) -> DataFrame:
    """Messages addressed to single buckets (``by="b"``) or groups (``"g"``); takes ranges apart where ``per`` > 1."""
    if per == 1:
        return messages

    def flush(held):
        rows = [(k, pack(*[np.concatenate(x) for x in zip(*own)])) for k, own in held.items()]
        return pa.RecordBatch.from_arrays([pa.array([k for k, _ in rows], pa.int32()), pa.array([p for _, p in rows], pa.binary())], names=["to", "payload"])

    def split(batches):
        held, size = defaultdict(list), 0
        for batch in batches:
            for data in batch.column("payload").to_pylist():
                g, b, n, *arrays = unpack(data)
                ends = np.cumsum(n, dtype=np.int64)
                for s, (k, e) in enumerate(zip((b if by == "b" else g).tolist(), ends.tolist())):
                    held[k].append([g[s : s + 1], b[s : s + 1], n[s : s + 1], *[a[e - int(n[s]) : e] for a in arrays]])
                size += sum(a.nbytes for a in arrays)
                if size > _FLUSH:
                    yield flush(held)
                    held, size = defaultdict(list), 0
        if held:
            yield flush(held)

    salt = F.pmod(F.crc32("payload"), F.lit(64))
    return messages.repartition(parts, "to", salt).mapInArrow(split, MESSAGE)
