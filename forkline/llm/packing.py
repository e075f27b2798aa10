"""Hierarchical multi-length packing of token sequences.

Each task packs its own documents in blocks of bounded size, so nothing is shuffled:

1. every full window of the longest context is cut off a document at once;
2. the remainder is routed to the tier of the next power of two, a quarter of the longest
   context at least;
3. from the longest tier down, each remainder of a tier opens a sequence of the tier's own
   length, and the gap is filled with the longest remainders of the shorter tiers (the
   shortest tier: of its own) that still fit, the last one cut to fit exactly;
4. what a block leaves over becomes sequences of shorter powers of two, which need no padding;
5. sequences are dealt to step groups of equal numbers of tokens, longest first.

Null texts and empty ones are documents of the end token alone; equal or null ids are
documents of their own; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import id_and_text, lean
from forkline.llm.encoding import encoder

SCHEMA = "doc_id bigint, start bigint, length bigint, doc_tokens bigint, sequence_id bigint, offset bigint, tier int, step_group bigint, ids binary"
#: Tokens that a block gathers before it is packed, and texts encoded in one go.
BLOCK_TOKENS, BATCH = 1 << 20, 256
TASK_BITS = 34
#: The longest context is so many times the shortest tier's.
TIERS = 4


class Shelves:
    """Remainders by exact length, with a bit mask of the lengths in stock: the longest that fits is one bit operation away."""

    def __init__(self, longest: int):
        self.by_length: list[list[tuple]] = [[] for _ in range(longest + 1)]
        self.stock = 0

    def put(self, piece: tuple) -> None:
        n = piece[2]
        if n:
            self.by_length[n].append(piece)
            self.stock |= 1 << n

    def take(self, most: int) -> tuple | None:
        n = (self.stock & ((1 << (most + 1)) - 1)).bit_length() - 1
        if n <= 0:
            return None
        return self._pop(n)

    def take_longer(self, least: int) -> tuple | None:
        """The shortest remainder of more than ``least``."""
        above = self.stock >> (least + 1)
        if not above:
            return None
        return self._pop(least + 1 + (above & -above).bit_length() - 1)

    def holds_longer(self, least: int) -> bool:
        return self.stock >> (least + 1) > 0

    def _pop(self, n: int) -> tuple:
        piece = self.by_length[n].pop()
        if not self.by_length[n]:
            self.stock &= ~(1 << n)
        return piece


def pack_block(lengths: list[int], longest: int) -> list[tuple[int, list[tuple[int, int, int]]]]:
    """Sequences ``(length, [(document, start, length)])`` that hold each token of each document once, without padding."""
    shelves = Shelves(longest)
    sequences: list[tuple[int, list[tuple[int, int, int]]]] = []
    total = 0
    for doc, n in enumerate(lengths):
        full = n // longest * longest
        sequences += [(longest, [(doc, at, longest)]) for at in range(0, full, longest)]
        shelves.put((doc, full, n - full))
        total += n - full
    size, least = longest, max(1, longest // TIERS)
    while total:
        while size > total or (size > least and not shelves.holds_longer(size // 2)):  # this tier is done
            size >>= 1
        pieces, room = [], size
        while room:
            piece = shelves.take(room)
            if piece is None:  # only longer ones are left: cut one to fit
                doc, at, n = shelves.take_longer(room)
                piece = (doc, at, room)
                shelves.put((doc, at + room, n - room))
            pieces.append(piece)
            room -= piece[2]
        sequences.append((size, pieces))
        total -= size
    return sequences


def step_groups(lengths: list[int], tokens: int) -> list[int]:
    """Groups of ``tokens`` tokens each: first fit over sequences from long to short; powers of two leave no holes but in the last."""
    order = sorted(range(len(lengths)), key=lambda i: -lengths[i])
    groups, group, left = [0] * len(lengths), 0, tokens
    for i in order:
        if lengths[i] > left:
            group, left = group + 1, tokens
        groups[i] = group
        left -= lengths[i]
    return groups


def pack(docs: DataFrame, vocabulary: str, sequence_length: int = 1024, end_id: int = 0, step_tokens: int = 16 * 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each piece of a document: where it lies in which sequence, with its ids as little-endian 32-bit integers.

    ``tier`` is the length of its sequence, a power of two of at most ``sequence_length``.
    """
    if sequence_length & (sequence_length - 1):
        raise ValueError("sequence_length has to be a power of two")

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode = encoder(vocabulary)
        task_id = TaskContext.get().partitionId() << TASK_BITS
        end = np.array([end_id], dtype="<u4").tobytes()
        schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64()), ("tier", pa.int32()), ("step_group", pa.int64()), ("ids", pa.binary())])
        ids: list[int | None] = []
        coded: list[bytes] = []
        gathered = next_sequence = next_group = 0

        def packed() -> Iterator[pa.RecordBatch]:
            nonlocal next_sequence, next_group
            sequences = pack_block([len(c) // 4 for c in coded], sequence_length)
            groups = step_groups([n for n, _ in sequences], step_tokens)
            rows = []
            for (n, pieces), group in zip(sequences, groups, strict=True):
                at = 0
                for doc, start, length in pieces:
                    rows.append((ids[doc], start, length, len(coded[doc]) // 4, task_id + next_sequence, at, n, task_id + next_group + group, coded[doc][4 * start : 4 * (start + length)]))
                    at += length
                next_sequence += 1
            next_group += max(groups, default=-1) + 1
            for i in range(0, len(rows), 4000):
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows[i : i + 4000], strict=True), schema, strict=True)], schema=schema)

        for batch in batches:
            for i in range(0, batch.num_rows, BATCH):
                some = batch.slice(i, BATCH)
                for doc_id, own in zip(some.column(0).to_pylist(), encode(some.column(1).to_pylist()), strict=True):
                    ids.append(doc_id)
                    coded.append(own + end)
                    gathered += len(own) // 4 + 1
                if gathered >= BLOCK_TOKENS:
                    yield from packed()
                    ids, coded, gathered = [], [], 0
        if ids:
            yield from packed()

    return id_and_text(docs, id_col, text_col).mapInArrow(lean(task), SCHEMA)


def pieces_digest(packed: DataFrame) -> DataFrame:
    return packed.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset", "tier", "step_group")
