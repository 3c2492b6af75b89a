"""Byte-level BPE encoding and decoding with a pair occurrence index.

The pre-tokens of an Arrow slice are made distinct, and those not met before in
this task are laid out as one linked row of symbols.  An index maps each
adjacent pair to all its positions; a heap holds the ranks of the pairs that
occur.  The least rank is taken, every listed position that still holds its
pair is merged from left to right, and only the lists of the new neighbour
pairs change.  As a merge of rank ``r`` yields a symbol whose pairs rank behind
``r``, ranks come up in ascending order, and one pass over the heap gives for
every pre-token what merging it alone would give.
"""

from __future__ import annotations

import hashlib
import heapq
import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import grams
from .arrowmap import append_columns

# Fixed value: the split pattern of the public byte-level vocabulary.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def byte_alphabet() -> dict[str, int]:
    """The printable stand-in of every byte in byte-level vocabulary files."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Vocabulary:
    """Tokens, merges and special tokens of a tokenizer file."""

    def __init__(self, spec: dict):
        model = spec["model"]
        stand = byte_alphabet()
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens") or []}
        self.bytes_of: dict[int, bytes] = {}
        for token, i in model["vocab"].items():
            if token not in self.special:
                self.bytes_of[i] = bytes(stand[c] for c in token)
        for token, i in self.special.items():
            self.bytes_of[i] = token.encode()
        ids = model["vocab"]
        self.start = [ids[c] for c, _ in sorted(stand.items(), key=lambda x: x[1])]
        self.rank: dict[tuple[int, int], int] = {}
        self.made: list[int] = []
        self.pairs: list[tuple[int, int]] = []
        for m in model["merges"]:
            left, right = m if isinstance(m, list) else m.split(" ")
            pair = ids[left], ids[right]
            self.rank[pair] = len(self.made)
            self.pairs.append(pair)
            self.made.append(ids[left + right])

    @classmethod
    def load(cls, path: str) -> Vocabulary:
        with open(path, encoding="utf-8") as f:
            return cls(json.load(f))


class Encoder:
    """Encodes texts; keeps the ids of pre-tokens already met, up to ``memory`` of them."""

    def __init__(self, vocabulary: Vocabulary, memory: int = 1_000_000):
        self.v = vocabulary
        self.memory = memory
        self.known: dict[str, bytes] = {}  # ids as little-endian 32-bit integers
        self.split = regex.compile(PATTERN).findall
        names = sorted(vocabulary.special, key=len, reverse=True)
        self.special = regex.compile("(" + "|".join(map(regex.escape, names)) + ")") if names else None
        self.wall = max(vocabulary.bytes_of) + 1  # stands between pre-tokens; no pair has it
        self.base = self.wall + 1
        self.rank = {a * self.base + b: r for (a, b), r in vocabulary.rank.items()}
        self.start = np.array([*vocabulary.start, self.wall], np.int64)
        self.first = np.full((257, 257), -1, np.int64)  # ranks of byte pairs
        byte_of = {t: i for i, t in enumerate(vocabulary.start)}
        for (left, right), r in vocabulary.rank.items():
            if left in byte_of and right in byte_of:
                self.first[byte_of[left], byte_of[right]] = r

    def learn(self, words: list[str]) -> None:
        """Merge distinct new pre-tokens together, through one pair occurrence index."""
        raw = [w.encode() for w in words]
        lengths = np.array([len(b) for b in raw])
        ends = np.cumsum(lengths + 1)  # one past each wall
        n = int(ends[-1])
        row = np.full(n, 256)
        row[np.arange(int(lengths.sum())) + np.repeat(np.arange(len(raw)), lengths)] = np.frombuffer(b"".join(raw), np.uint8)
        ranks = self.first[row[:-1], row[1:]]
        at = np.flatnonzero(ranks >= 0)
        at = at[np.argsort(ranks[at], kind="stable")]
        heap, first = np.unique(ranks[at], return_index=True)
        index = {r: places.tolist() for r, places in zip(heap.tolist(), np.split(at, first[1:]))} if len(at) else {}
        heap = list(index)  # ascending, so a heap
        sym = self.start[row].tolist()
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        get, base, pairs, made = self.rank.get, self.base, self.v.pairs, self.v.made
        push, pop = heapq.heappush, heapq.heappop
        while heap:
            r = pop(heap)
            places = index.pop(r)
            left, right = pairs[r]
            new = made[r]
            ahead = new * base
            if left == right:
                places.sort()  # only such places can overlap
            for i in places:
                if sym[i] != left:
                    continue
                j = after[i]
                if sym[j] != right:
                    continue
                k = after[j]
                sym[i], sym[j] = new, -1
                after[i] = k
                before[k] = i
                q = get(ahead + sym[k])
                if q is not None:
                    if q in index:
                        index[q].append(i)
                    else:
                        index[q] = [i]
                        push(heap, q)
                h = before[i]
                if h >= 0:
                    q = get(sym[h] * base + new)
                    if q is not None:
                        if q in index:
                            index[q].append(h)
                        else:
                            index[q] = [h]
                            push(heap, q)
        out = np.array(sym)
        live = (out >= 0) & (out != self.wall)
        past = (np.cumsum(live)[ends - 1] * 4).tolist()
        ids = out[live].astype("<u4").tobytes()
        self.known.update(zip(words, [ids[s:e] for s, e in zip([0, *past], past)]))

    def encode_raw(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian 32-bit integers."""
        if len(self.known) > self.memory:
            self.known.clear()
        special = self.v.special
        rows: list[list] = []
        for t in texts:
            if self.special and any(x in t for x in special):
                rows.append([special[part] if part in special else self.split(part) for part in self.special.split(t) if part])
            else:
                rows.append([self.split(t)])
        fresh = set().union(*[part for row in rows for part in row if type(part) is list]).difference(self.known)
        if fresh:
            self.learn(list(fresh))
        find = self.known.__getitem__
        return [b"".join([part.to_bytes(4, "little") if type(part) is int else b"".join(map(find, part)) for part in row]) for row in rows]

    def encode_batch(self, texts: list[str]) -> list[np.ndarray]:
        return [np.frombuffer(b, "<u4") for b in self.encode_raw(texts)]


class Decoder:
    def __init__(self, vocabulary: Vocabulary):
        self.table = [vocabulary.bytes_of.get(i, b"") for i in range(max(vocabulary.bytes_of) + 1)]

    def decode(self, ids: np.ndarray) -> bytes:
        """UTF-8 of the text; bytes that are no UTF-8 become U+FFFD."""
        table = self.table
        raw = b"".join([table[i] for i in ids.tolist()])
        return raw.decode("utf-8", "replace").encode()


def _lists(rows: list[np.ndarray]) -> pa.ListArray:
    ends = np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int32)
    flat = np.concatenate(rows).astype(np.int32) if rows else np.zeros(0, np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))


def encode(docs: DataFrame, path: str, text: str = "text", ids: str = "ids") -> DataFrame:
    """``docs`` with ``ids array<int>``.  Null counts as empty text; no special tokens are added.

    A special token's own string inside a text becomes its id, as the public
    library does.  An existing column named ``ids`` is replaced.
    """

    def make():
        encoder = Encoder(Vocabulary.load(path))

        def fn(part):
            rows = encoder.encode_batch([t.decode() for t in grams.texts_of(part.column(text))])
            return [_lists(rows)]

        return fn

    return append_columns(docs, text, make, [T.StructField(ids, T.ArrayType(T.IntegerType()))])


def decode(rows: DataFrame, path: str, ids: str = "ids", text: str = "decoded") -> DataFrame:
    """``rows`` with the text of their ids (null ids: null text)."""

    @F.pandas_udf("string")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        decoder = Decoder(Vocabulary.load(path))
        for s in batches:
            yield s.map(lambda x: None if x is None else decoder.decode(np.asarray(x)).decode())

    return rows.withColumn(text, run(F.col(ids)))


def round_trip(docs: DataFrame, path: str, doc_id: str = "doc_id", text: str = "text", keep: tuple[str, ...] = (), with_ids: bool = False) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256``: ids as little-endian 32-bit integers, then decoded again.

    ``keep`` names further columns to carry; ``with_ids`` adds ``ids array<int>``.
    """

    def make():
        v = Vocabulary.load(path)
        encoder, decoder = Encoder(v), Decoder(v)

        def fn(part):
            rows = encoder.encode_batch([t.decode() for t in grams.texts_of(part.column(text))])
            out = [
                pa.array([len(r) for r in rows], pa.int64()),
                [hashlib.sha256(r.astype("<u4").tobytes()).hexdigest() for r in rows],
                [hashlib.sha256(decoder.decode(r)).hexdigest() for r in rows],
            ]
            return out + [_lists(rows)] * with_ids

        return fn

    names = [("n_tokens", T.LongType()), ("ids_sha256", T.StringType()), ("decoded_sha256", T.StringType())]
    names += [("ids", T.ArrayType(T.IntegerType()))] * with_ids
    return append_columns(docs.select(doc_id, *keep, text), text, make, [T.StructField(n, t) for n, t in names], drop=(text,))
