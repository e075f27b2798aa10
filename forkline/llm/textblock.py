"""Vectorised view of many texts as one byte buffer: words, lines and their 64-bit hashes.

Words are maximal runs of bytes outside ``\\x20\\x09-\\x0D``; those six bytes never occur
inside a multi-byte UTF-8 character, so byte-wise splitting equals splitting by characters.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BASE_INV = np.uint64(pow(int(_BASE), -1, 1 << 64))
_powers: dict[str, np.ndarray] = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers["up"]) < n:
        with np.errstate(over="ignore"):
            for key, base in (("up", _BASE), ("down", _BASE_INV)):
                table = np.full(n, base, np.uint64)
                table[0] = 1
                _powers[key] = np.cumprod(table, dtype=np.uint64)
    return _powers["up"], _powers["down"]


def mix(h: np.ndarray, salt: int = 0) -> np.ndarray:
    """Finaliser: every input bit reaches every output bit."""
    with np.errstate(over="ignore"):
        h = h + np.uint64(salt)
        h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        return h ^ (h >> np.uint64(32))


class TextBlock:
    """Texts of one slice: ``data`` all bytes, ``edges`` the offsets of each text in it."""

    def __init__(self, data: np.ndarray, edges: np.ndarray):
        self.data, self.edges = data, edges

    @property
    def n_docs(self) -> int:
        return len(self.edges) - 1

    def lowered(self) -> TextBlock:
        return TextBlock(LOWER[self.data], self.edges)

    def text(self, i: int) -> bytes:
        return self.data[self.edges[i] : self.edges[i + 1]].tobytes()

    def spans(self, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Maximal runs of true bytes, cut at text borders: starts, ends, and the text of each."""
        n = len(inside)
        if not n:
            z = np.zeros(0, np.int64)
            return z, z, z
        border = np.zeros(n + 1, bool)
        border[self.edges] = True
        before = np.empty(n, bool)
        before[0] = False
        before[1:] = inside[:-1]
        after = np.empty(n, bool)
        after[-1] = False
        after[:-1] = inside[1:]
        starts = np.flatnonzero(inside & (~before | border[:-1]))
        ends = np.flatnonzero(inside & (~after | border[1:])) + 1
        return starts, ends, np.searchsorted(self.edges, starts, side="right") - 1

    def words(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self.spans(~SPACE[self.data])

    def lines(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """``\\n``-separated lines of each text, empty ones included; an empty text has one empty line."""
        breaks = np.flatnonzero(self.data == 10)
        held_by = np.searchsorted(self.edges, breaks, side="right") - 1
        each = np.arange(self.n_docs)
        starts, first = np.concatenate([self.edges[:-1], breaks + 1]), np.concatenate([each, held_by])
        ends, last = np.concatenate([breaks, self.edges[1:]]), np.concatenate([held_by, each])
        order = np.lexsort((starts, first))
        return starts[order], ends[np.lexsort((ends, last))], first[order]

    def hashes(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """64-bit hash of the bytes in each span, equal for equal spans wherever they stand."""
        up, down = _power_tables(len(self.data) + 1)
        with np.errstate(over="ignore"):
            prefix = np.zeros(len(self.data) + 1, np.uint64)
            np.cumsum((self.data.astype(np.uint64) + np.uint64(1)) * up[: len(self.data)], out=prefix[1:])
            return mix((prefix[ends] - prefix[starts]) * down[starts])


def blocks(texts: pa.Array | pa.ChunkedArray, most: int = 1 << 20) -> Iterator[tuple[int, TextBlock]]:
    """Slices of a string column of about ``most`` bytes (one text at least), with the row each begins at."""
    at = 0
    for chunk in texts.chunks if isinstance(texts, pa.ChunkedArray) else [texts]:
        chunk = pc.fill_null(chunk, "") if chunk.null_count else chunk
        if not len(chunk):
            continue
        wide = pa.types.is_large_string(chunk.type)
        offsets = np.frombuffer(chunk.buffers()[1], np.int64 if wide else np.int32)[chunk.offset : chunk.offset + len(chunk) + 1].astype(np.int64)
        whole = chunk.buffers()[2]
        data = np.frombuffer(whole, np.uint8) if whole is not None else np.zeros(0, np.uint8)
        i = 0
        while i < len(chunk):
            j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1)
            yield at + i, TextBlock(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
            i = j
        at += len(chunk)


def windows(h: np.ndarray, owner: np.ndarray, width: int, second: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each ``width`` consecutive units and whether they all belong to one text; both of length ``len(h) - width + 1``.

    ``second`` takes an independent polynomial.
    """
    n = len(h) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, bool)
    base = np.uint64(0xC2B2AE3D27D4EB4F) if second else _BASE
    with np.errstate(over="ignore"):
        acc = h[width - 1 :].copy()
        for j in range(width - 2, -1, -1):
            acc *= base
            acc += h[j : j + n]
    return mix(acc, width), owner[:n] == owner[width - 1 :]


def pack40(h: np.ndarray) -> bytes:
    """The low 40 bits of each hash, five bytes each."""
    return np.ascontiguousarray(h.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :5]).tobytes()


def unpack40(blob: bytes) -> np.ndarray:
    out = np.zeros((len(blob) // 5, 8), np.uint8)
    out[:, :5] = np.frombuffer(blob, np.uint8).reshape(-1, 5)
    return out.reshape(-1).view("<u8")


def bucket_of(h: np.ndarray, buckets: int) -> np.ndarray:
    """Bucket from the 24 bits that pack40 leaves out."""
    return ((h >> np.uint64(40)) % np.uint64(buckets)).astype(np.int64)


def by_bucket(h: np.ndarray, buckets: int) -> list[np.ndarray]:
    """Positions of ``h`` for each bucket, in the order of ``h``."""
    b = bucket_of(h, buckets)
    order = np.argsort(b, kind="stable")
    cuts = np.searchsorted(b[order], np.arange(buckets + 1))
    return [order[cuts[k] : cuts[k + 1]] for k in range(buckets)]


def contained(values: np.ndarray, sorted_set: np.ndarray) -> np.ndarray:
    if not len(sorted_set):
        return np.zeros(len(values), bool)
    at = np.searchsorted(sorted_set, values)
    at[at == len(sorted_set)] = 0
    return sorted_set[at] == values
