"""Word arrays and rolling hashes shared by the text operators.

Texts are handled as UTF-8 bytes: one ``translate`` and one ``split`` give the
words, one dictionary the 64-bit hash of each, and NumPy every window of a
whole Arrow batch at once.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash

LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
#: A-Z to a-z, everything of ASCII but digits and letters to a space
ALNUM = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
FACTOR = 0x9E3779B97F4A7C15


class WordHashes(dict):
    """Hash of a word, remembered; forgets all when it holds 250,000 words."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= 250_000:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def texts_of(column: pa.ChunkedArray | pa.Array) -> list[bytes]:
    """Bytes of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return [x or b"" for x in column.cast(pa.large_binary()).to_pylist()]


_MEMO = WordHashes()


def hash_words(texts: list[bytes], table: bytes | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of all texts in a row, and the ``n + 1`` offsets of the texts in them.

    The words of one text at a time are held; hashes of words are remembered by
    the process, whatever task it works for.
    """
    find, parts = _MEMO.__getitem__, []
    for t in texts:
        w = (t.translate(table) if table else t).split()
        parts.append(np.fromiter(map(find, w), np.uint64, len(w)))
    offsets = np.zeros(len(parts) + 1, np.int64)
    np.cumsum([len(p) for p in parts], out=offsets[1:])
    return (np.concatenate(parts) if parts else np.zeros(0, np.uint64)), offsets


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0xD6E8FEB86659FD93)
    h = h ^ (h >> np.uint64(32))
    h = h * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(32))


def windows(hashes: np.ndarray, k: int, salt: int = 0) -> np.ndarray:
    """Hash of every run of ``k`` neighbours (``len - k + 1`` of them), order kept.

    Built by joining shorter runs, so the work is logarithmic in ``k``.
    """
    n = len(hashes) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    base = hashes if not salt else mix(hashes ^ np.uint64(salt))
    out, have, power, size = None, 0, base, 1
    left = k
    with np.errstate(over="ignore"):
        while left:
            if left & 1:
                if out is None:
                    out = power
                else:
                    shift = np.uint64(pow(FACTOR, size, 1 << 64))
                    m = len(hashes) - have - size + 1
                    out = out[:m] * shift + power[have : have + m]
                have += size
            left >>= 1
            if left:
                shift = np.uint64(pow(FACTOR, size, 1 << 64))
                power = power[: len(power) - size] * shift + power[size:]
                size *= 2
        return mix(out[:n] + np.uint64(k))


def starts_inside(offsets: np.ndarray, k: int, total: int) -> np.ndarray:
    """Which of the windows over joined texts lie in one text."""
    n = max(0, total - k + 1)
    ok = np.ones(n, bool)
    for e in offsets[1:-1]:
        ok[max(0, e - k + 1) : min(n, e)] = False
    return ok


def spread(marks: np.ndarray, k: int, total: int) -> np.ndarray:
    """Words covered by marked windows: ``marks[i]`` covers ``i .. i + k - 1``."""
    step = np.zeros(total + 1, np.int64)
    at = np.flatnonzero(marks)
    np.add.at(step, at, 1)
    np.add.at(step, at + k, -1)
    return np.cumsum(step[:-1]) > 0


def owner(offsets: np.ndarray) -> np.ndarray:
    """For each word the index of its text."""
    return np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))


def ids_of(column: pa.ChunkedArray) -> np.ndarray:
    """Ids as int64; a missing id counts as the largest, so it never outranks another."""
    import pyarrow.compute as pc

    return pc.fill_null(column, np.iinfo(np.int64).max).to_numpy().astype(np.int64)
