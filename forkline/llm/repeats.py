"""Repeated runs across documents: substring dedup over words, line dedup over lines.

Both work on sequences of units (words, or lines that hold a word) and delete a unit if it
lies in a window of units that also occurs earlier. They differ in how windows are found:

* words: fixed-block anchors. A document's non-overlapping blocks of ``(width + 1) // 2``
  words are indexed; every rolling window of that length of every document probes the
  index. A window of ``width`` words holds a whole block of any document it is equal to.
* lines: winnowing. Of each window of lines the smallest line hash is its fingerprint; equal
  windows select the same one.

The plan is three passes over chunks of documents (a hash of id and text), each vectorised
on the bytes, with two exchanges of packed hashes between them:

1. chunks send each distinct anchor hash once to a bucket; a bucket answers with those that
   occur elsewhere and are indexed (*live* anchors);
2. chunks send the full windows around live anchors, once each with the earliest place in
   the chunk; a bucket answers with those that have an earlier place in another chunk. This
   compares the whole window by 96 bits, 48 of each of two independent polynomials over the
   64-bit hashes of its units, so an anchor in common alone deletes nothing;
3. chunks mark what their own earlier places and the answers cover. Overlapping windows
   make the maximal extension of a match to both sides.

Text is shuffled once (all passes reuse one exchange). Nothing depends on how often a unit
or window occurs: a hot one is one entry a chunk. No join, no pairs, no driver-side data.

Defined results: null text is empty; a null id counts as larger than all others; rows of
equal ids are judged apart and are not earlier than each other; an empty table stays empty.
"""

from __future__ import annotations

import itertools
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import Grid, id_and_text, into_chunks, lean, volume
from forkline.llm.textblock import SPACE, blocks, bucket_of, by_bucket, contained, mix, pack40, unpack40, windows

SENT = pa.schema([("bucket", pa.int32()), ("chunk", pa.int32()), ("indexed", pa.binary()), ("probing", pa.binary())])
ANSWER = pa.schema([("chunk", pa.int32()), ("bucket", pa.int32()), ("found", pa.binary())])
PLACED = pa.schema([("bucket", pa.int32()), ("chunk", pa.int32()), ("keys", pa.binary()), ("places", pa.binary())])
RESULT = pa.schema([("doc_id", pa.int64()), ("n_units", pa.int64()), ("n_removed", pa.int64()), ("text", pa.string()), ("removed", pa.list_(pa.int32()))])
NO_ID = (1 << 63) - 1


def wide(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """One key of 96 bits of two hashes: whole numbers below 2**48 are exact as parts of a complex number, whose order is that of its parts."""
    key = np.empty(len(a), np.complex128)
    key.real, key.imag = a >> np.uint64(16), b >> np.uint64(16)
    return key


def pack96(key: np.ndarray) -> bytes:
    """Twelve bytes for each key."""
    parts = np.stack([key.real, key.imag], axis=1).astype("<u8")
    return np.ascontiguousarray(parts.view(np.uint8).reshape(-1, 8)[:, :6]).tobytes()


def unpack96(blob: bytes) -> np.ndarray:
    parts = np.zeros((len(blob) // 6, 8), np.uint8)
    parts[:, :6] = np.frombuffer(blob, np.uint8).reshape(-1, 6)
    real, imag = parts.reshape(-1).view("<u8").reshape(-1, 2).T
    key = np.empty(len(real), np.complex128)
    key.real, key.imag = real, imag
    return key


def ddl(schema: pa.Schema) -> str:
    names = {pa.int32(): "int", pa.int64(): "bigint", pa.binary(): "binary", pa.string(): "string", pa.list_(pa.int32()): "array<int>", pa.bool_(): "boolean", pa.float64(): "double"}
    return ", ".join(f"{f.name} {names[f.type]}" for f in schema)


class WordUnits:
    """Words of a chunk's documents; a window is ``width`` words."""

    def __init__(self, width: int):
        self.width, self.block = width, (width + 1) // 2

    def read(self, texts: pa.ChunkedArray) -> dict[str, np.ndarray]:
        h, owner = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for first, block in blocks(texts):
            starts, ends, doc = block.words()
            h.append(block.hashes(starts, ends))
            owner.append(doc + first)
        return {"h": np.concatenate(h), "owner": np.concatenate(owner)}

    def anchors(self, u: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Hash, first unit, whether indexed, and owner of each anchor."""
        h, whole = windows(u["h"], u["owner"], self.block)
        owner = u["owner"][: len(h)]
        place = np.arange(len(u["h"])) - np.searchsorted(u["owner"], u["owner"])
        keep = whole & (np.bincount(u["owner"], minlength=1)[owner] >= self.width) if len(h) else whole
        at = np.flatnonzero(keep)
        return h[at], at, place[at] % self.block == 0, owner[at]

    def live_here(self, order: np.ndarray, cuts: np.ndarray, indexed: np.ndarray, owner: np.ndarray) -> np.ndarray:
        o = owner[order]
        return (np.minimum.reduceat(o, cuts) != np.maximum.reduceat(o, cuts)) & np.logical_or.reduceat(indexed[order], cuts)

    def windows(self, u: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Key, bucket hash, first unit and length of every window."""
        a, whole = windows(u["h"], u["owner"], self.width)
        b, _ = windows(u["h"], u["owner"], self.width, second=True)
        at = np.flatnonzero(whole)
        a, b = a[at], b[at]
        return wide(a, b), a, at, np.full(len(at), self.width)

    def position(self, u: dict[str, np.ndarray], at: np.ndarray) -> np.ndarray:
        return np.zeros(len(at), np.int64)  # only the document counts

    @staticmethod
    def keep(text: bytes, gone: np.ndarray | None) -> bytes:
        words = text.split()
        return b" ".join(words if gone is None else itertools.compress(words, (~gone).tolist()))


class LineUnits:
    """Lines that hold a word. Windows: ``run`` lines; all lines of a text that has fewer; a line of ``long_line`` words."""

    def __init__(self, run: int, long_line: int):
        self.run, self.long_line, self.block = run, long_line, 1

    def read(self, texts: pa.ChunkedArray) -> dict[str, np.ndarray]:
        h, owner, size = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for first, block in blocks(texts):
            starts, ends, doc = block.lines()
            w, _, _ = block.words()
            words = np.searchsorted(w, ends) - np.searchsorted(w, starts)
            some = words > 0
            h.append(block.hashes(starts[some], ends[some]))
            owner.append(doc[some] + first)
            size.append(words[some])
        return {"h": np.concatenate(h), "owner": np.concatenate(owner), "size": np.concatenate(size)}

    def _all(self, u: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """First unit and length of every window."""
        n = len(u["h"])
        if not n:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        owner = u["owner"]
        count = np.bincount(owner)[owner]
        place = np.arange(n) - np.searchsorted(owner, owner)
        full = np.flatnonzero(place + self.run <= count)
        short = np.flatnonzero((place == 0) & (count < self.run))
        long = np.flatnonzero((u["size"] >= self.long_line) & (self.run > 1) & ((count >= self.run) | (count > 1)))
        return np.concatenate([full, short, long]), np.concatenate([np.full(len(full), self.run), count[short], np.full(len(long), 1)])

    def anchors(self, u: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        at, size = self._all(u)
        low = np.zeros(0, np.int64)
        if len(at):
            best, low = u["h"][at], at.copy()
            for j in range(1, int(size.max())):
                inside = size > j
                other = u["h"][np.where(inside, at + j, at)]
                take = inside & (other <= best)
                best, low = np.where(take, other, best), np.where(take, at + j, low)
        low = np.unique(low)
        return u["h"][low], low, np.ones(len(low), bool), u["owner"][low]

    def live_here(self, order: np.ndarray, cuts: np.ndarray, indexed: np.ndarray, owner: np.ndarray) -> np.ndarray:
        return np.diff(np.append(cuts, len(order))) > 1

    def windows(self, u: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        at, size = self._all(u)
        a, b = np.zeros(len(at), np.uint64), np.zeros(len(at), np.uint64)
        for n in np.unique(size):
            own = np.flatnonzero(size == n)
            for out, second in ((a, False), (b, True)):
                h, _ = windows(u["h"], u["owner"], int(n), second)
                out[own] = h[at[own]]
        return wide(a, b), a, at, size

    def position(self, u: dict[str, np.ndarray], at: np.ndarray) -> np.ndarray:
        return at - np.searchsorted(u["owner"], u["owner"][at])

    @staticmethod
    def keep(text: bytes, gone: np.ndarray | None) -> bytes:
        if gone is None:
            return text
        left, kept = iter((~gone).tolist()), []
        for line in text.split(b"\n"):
            if not line.strip(b" \t\n\r\x0b\x0c") or next(left):
                kept.append(line)
        return b"\n".join(kept)


def _ids(t: pa.Table) -> np.ndarray:
    return t.column("doc_id").combine_chunks().fill_null(NO_ID).to_numpy(zero_copy_only=False).astype(np.int64)


def _groups(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order that sorts ``h``, and where each distinct value begins in it."""
    order = np.argsort(h, kind="stable")
    s = h[order]
    return order, np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]])) if len(s) else np.zeros(0, np.int64)


def remove_repeats(docs: DataFrame, units: WordUnits | LineUnits, bytes_per_unit: float, id_col: str = "doc_id", text_col: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """``(doc_id, n_units, n_removed, text, removed)``; ``removed`` lists first and past-last unit of each run that went.

    Columns named in ``carry`` follow as ``carry_0`` and so on.
    """
    extra = [(f"carry_{i}", docs.schema[c].dataType.simpleString()) for i, c in enumerate(carry)]
    own = docs.select(F.col(id_col), F.col(text_col), *(F.col(c).alias(n) for c, (n, _) in zip(carry, extra, strict=True)))
    texts = id_and_text(own, id_col, text_col, [n for n, _ in extra])
    grid = Grid(*volume(texts), bytes_per_unit)
    buckets = grid.buckets
    chunked = into_chunks(texts, grid.chunks)

    def send(t: pa.Table) -> pa.Table:
        h, _, indexed, _ = units.anchors(units.read(t.column("text")))
        order, cuts = _groups(h)
        once = h[order][cuts]
        isin = np.logical_or.reduceat(indexed[order], cuts) if len(cuts) else np.zeros(0, bool)
        rows = [(k, p) for k, p in enumerate(by_bucket(once, buckets)) if len(p)]
        return pa.table(
            [pa.array([k for k, _ in rows], pa.int32()), pa.array([t.column("chunk")[0].as_py()] * len(rows), pa.int32()), pa.array([pack40(once[p[isin[p]]]) for _, p in rows], pa.binary()), pa.array([pack40(once[p[~isin[p]]]) for _, p in rows], pa.binary())],
            schema=SENT,
        )

    def find_live(t: pa.Table) -> pa.Table:
        chunks = t.column("chunk").to_numpy()
        parts, flags, of = [], [], []
        for i, (a, b) in enumerate(zip(t.column("indexed").to_pylist(), t.column("probing").to_pylist(), strict=True)):
            for blob, flag in ((a, True), (b, False)):
                parts.append(unpack40(blob))
                flags.append(np.full(len(parts[-1]), flag))
                of.append(np.full(len(parts[-1]), i, np.int32))
        h, indexed, owner = np.concatenate(parts), np.concatenate(flags), np.concatenate(of)
        order, cuts = _groups(h)
        live = (np.diff(np.append(cuts, len(h))) > 1) & np.logical_or.reduceat(indexed[order], cuts)
        back = order[np.repeat(live, np.diff(np.append(cuts, len(h))))]
        back = back[np.argsort(owner[back], kind="stable")]
        bucket = t.column("bucket")[0].as_py()
        rows = [(chunks[owner[p[0]]], pack40(h[p])) for p in np.split(back, np.flatnonzero(np.diff(owner[back])) + 1) if len(p)]
        return pa.table([pa.array([c for c, _ in rows], pa.int32()), pa.array([bucket] * len(rows), pa.int32()), pa.array([b for _, b in rows], pa.binary())], schema=ANSWER)

    def place(t: pa.Table, answers: pa.Table) -> pa.Table:
        if not t.num_rows:
            return PLACED.empty_table()
        u = units.read(t.column("text"))
        h, at, indexed, owner = units.anchors(u)
        order, cuts = _groups(h)
        live = np.zeros(len(h), bool)
        if len(cuts):
            live[order] = np.repeat(units.live_here(order, cuts, indexed, owner), np.diff(np.append(cuts, len(h))))
        b = bucket_of(h, buckets)
        found = {k: np.sort(unpack40(x)) for k, x in zip(answers.column("bucket").to_pylist(), answers.column("found").to_pylist(), strict=True)}
        low = h & np.uint64((1 << 40) - 1)
        by = np.argsort(b, kind="stable")
        edges = np.searchsorted(b[by], np.arange(buckets + 1))
        for k, some in found.items():
            own = by[edges[k] : edges[k + 1]]
            live[own] |= contained(low[own], some)
        key, spread, first, size = units.windows(u)
        marks = np.zeros(len(u["h"]) + 1, np.int64)
        marks[at[live] + 1] = 1
        seen = np.cumsum(marks)
        wanted = np.flatnonzero(seen[first + size - units.block + 1] > seen[first])  # windows that hold a live anchor
        key, spread, first = key[wanted], spread[wanted], first[wanted]
        doc, pos = _ids(t)[u["owner"][first]], units.position(u, first)
        order = np.lexsort((pos, doc, key))
        s = key[order]
        order = order[np.concatenate([[True], s[1:] != s[:-1]])] if len(s) else order
        order = order[np.lexsort((pos[order], doc[order]))]  # by place, which then packs well
        key, spread, doc, pos = key[order], spread[order], doc[order], pos[order]
        rows = [(k, p) for k, p in enumerate(by_bucket(spread, buckets)) if len(p)]
        return pa.table(
            [pa.array([k for k, _ in rows], pa.int32()), pa.array([t.column("chunk")[0].as_py()] * len(rows), pa.int32()), pa.array([pack96(key[p]) for _, p in rows], pa.binary()), pa.array([zlib.compress(np.concatenate([doc[p], pos[p]]).tobytes(), 1) for _, p in rows], pa.binary())],
            schema=PLACED,
        )

    def find_earlier(t: pa.Table) -> pa.Table:
        chunks = t.column("chunk").to_numpy()
        keys = [unpack96(b) for b in t.column("keys").to_pylist()]
        places = [np.frombuffer(zlib.decompress(b), np.int64).reshape(2, -1) for b in t.column("places").to_pylist()]
        key, owner = np.concatenate(keys), np.repeat(np.arange(len(keys)), [len(k) for k in keys])
        doc, pos = np.concatenate([p[0] for p in places]), np.concatenate([p[1] for p in places])
        order = np.lexsort((pos, doc, key))
        s = key[order]
        new = np.concatenate([[True], s[1:] != s[:-1]])
        lead = order[np.flatnonzero(new)][np.cumsum(new) - 1]
        late = order[(doc[lead] < doc[order]) | ((doc[lead] == doc[order]) & (pos[lead] < pos[order]))]
        late = late[np.argsort(owner[late], kind="stable")]
        bucket = t.column("bucket")[0].as_py()
        rows = [(chunks[owner[p[0]]], pack96(key[p])) for p in np.split(late, np.flatnonzero(np.diff(owner[late])) + 1) if len(p)]
        return pa.table([pa.array([c for c, _ in rows], pa.int32()), pa.array([bucket] * len(rows), pa.int32()), pa.array([b for _, b in rows], pa.binary())], schema=ANSWER)

    def strike(t: pa.Table, answers: pa.Table) -> pa.Table:
        if not t.num_rows:
            return pa.table([*(c for c in RESULT.empty_table().columns), *(t.column(n) for n, _ in extra)], names=[*RESULT.names, *(n for n, _ in extra)])
        u = units.read(t.column("text"))
        key, _, first, size = units.windows(u)
        ids = _ids(t)
        doc, pos = ids[u["owner"][first]], units.position(u, first)
        order = np.lexsort((pos, doc, key))
        late = np.zeros(len(key), bool)
        if len(key):
            s = key[order]
            new = np.concatenate([[True], s[1:] != s[:-1]])
            lead = order[np.flatnonzero(new)][np.cumsum(new) - 1]
            late[order] = (doc[lead] < doc[order]) | ((doc[lead] == doc[order]) & (pos[lead] < pos[order]))
        told = np.sort(np.concatenate([np.zeros(0, np.complex128), *(unpack96(b) for b in answers.column("found").to_pylist())]))
        late |= contained(key, told)
        cover = np.zeros(len(u["h"]) + 1, np.int64)
        np.add.at(cover, first[late], 1)
        np.add.at(cover, first[late] + size[late], -1)
        gone = np.cumsum(cover)[:-1] > 0
        edges = np.searchsorted(u["owner"], np.arange(len(ids) + 1))
        n_gone = np.concatenate([[0], np.cumsum(gone)])
        n_gone = n_gone[edges[1:]] - n_gone[edges[:-1]]
        texts, removed = [], []
        for row0, block in blocks(t.column("text")):
            for i in range(block.n_docs):
                own = gone[edges[row0 + i] : edges[row0 + i + 1]] if n_gone[row0 + i] else None
                texts.append(units.keep(block.text(i), own))
                removed.append([] if own is None else np.flatnonzero(np.diff(np.concatenate([[False], own, [False]]).astype(np.int8))).tolist())
        return pa.table([t.column("doc_id").cast(pa.int64()), pa.array(np.diff(edges), pa.int64()), pa.array(n_gone, pa.int64()), pa.array(texts, pa.binary()).cast(pa.string()), pa.array(removed, pa.list_(pa.int32())), *(t.column(n) for n, _ in extra)], names=[*RESULT.names, *(n for n, _ in extra)])

    by_chunk = chunked.groupBy("chunk")
    live = by_chunk.applyInArrow(lean(send), ddl(SENT)).groupBy("bucket").applyInArrow(lean(find_live), ddl(ANSWER))
    placed = by_chunk.cogroup(live.groupBy("chunk")).applyInArrow(lean(place), ddl(PLACED))
    earlier = placed.groupBy("bucket").applyInArrow(lean(find_earlier), ddl(ANSWER))
    return by_chunk.cogroup(earlier.groupBy("chunk")).applyInArrow(lean(strike), ", ".join([ddl(RESULT), *(f"{n} {kind}" for n, kind in extra)]))


def substring_dedup(docs: DataFrame, width: int = 13, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Delete words in a ``width``-word window that also starts in a document of smaller id; ``text`` joins the rest by one space."""
    return remove_repeats(docs, WordUnits(width), 6.5, id_col, text_col)


def line_dedup(docs: DataFrame, run: int = 2, long_line: int = 50, id_col: str = "doc_id", text_col: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """Delete lines of a run of ``run`` lines, or a line of ``long_line`` words, that occurs earlier by (id, line).

    Lines without a word are no part of a run and stay. A text of fewer lines than ``run``
    is one run, compared with such texts only.
    """
    return remove_repeats(docs, LineUnits(run, long_line), 150.0, id_col, text_col, carry)
