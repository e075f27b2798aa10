"""A search in exact queue order over a graph of several blocks, two exchanges a level.

Places in a level's queue are dealt by range to *folders*, which number discoveries and fold
tests. In the first exchange (``_discover``) blocks hear the places of the level's vertices,
find for each new vertex the first place that leads to it, and tell folders and neighbours;
folders fold the tests of the level before. In the second (``_settle``) folders number the new
vertices by place of their finder, then block, then id, which is the order of the queue, and
blocks tell folders which adjacencies of the level discovered something.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from forkline.operators.blocks import ASK, IDS, LAYOUT, ROW, SAID, SEND, STATE, TOLD, Block, Held, Laid, LevelRun, _by_block, _folded, _ints, _met, _row
from forkline.operators.folding import Folding
from forkline.operators.predictor import PredictorSpec

#: Places of a queue that a folder takes, about.
FOLDER_PLACES = 25_000
FAR = np.iinfo(np.int64).max

Work = Callable[[int, Held], Iterator[pa.RecordBatch]]


def _packed(*arrays: np.ndarray) -> bytes:
    return np.array([len(arrays), *map(len, arrays)], np.int64).tobytes() + b"".join(np.ascontiguousarray(a, np.int64).tobytes() for a in arrays)


def _unpacked(data: pa.Buffer) -> list[np.ndarray]:
    x = _ints(data)
    ends = np.cumsum(x[1 : x[0] + 1])
    return np.split(x[x[0] + 1 :], ends[:-1])


def _bits(mask: np.ndarray) -> np.ndarray:
    packed = np.packbits(mask)
    return np.append(packed, np.zeros(-len(packed) % 8, np.uint8)).view(np.int64)


def _mask(bits: np.ndarray, n: int) -> np.ndarray:
    return np.unpackbits(bits.view(np.uint8))[:n].astype(bool)


def _slices(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Places ``begin .. begin + size - 1`` of each, one after another."""
    return np.repeat(begin - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))


class _State:
    """Parts of the halo by block; seen vertices; the level's vertices with their places; where in the halo, and which own ones, are new."""

    def __init__(self, data: pa.Buffer):
        self.peers, self.lens, n, bits, self.front, self.place, self.near, self.new = _unpacked(data)
        self.n, self.seen = int(n[0]), _mask(bits, int(n[0]))

    def row(self, b: int) -> pa.RecordBatch:
        return _row(STATE, b, b, _packed(self.peers, self.lens, np.array([self.n]), _bits(self.seen), self.front, self.place, self.near, self.new))


def _announced(b: int, held: Held, n: int, new: np.ndarray, by: np.ndarray, count: int, span: int) -> Iterator[pa.RecordBatch]:
    """New vertices in their order, found from places ``by``: to the neighbours that know them, and to the folders."""
    order = np.full(n, -1)
    order[new] = np.arange(len(new))
    known = []
    for p, data in sorted(held.get(SEND, {}).items()):
        at = order[np.frombuffer(data, np.uint32)]
        hit = np.flatnonzero(at >= 0)
        hit = hit[np.argsort(at[hit])]
        if len(hit):
            yield _row(SAID, p, b, _packed(hit, by[at[hit]]))
            known.append((p, at[hit]))
    folder = by // span
    for f in np.unique(folder).tolist():
        low, high = np.searchsorted(folder, [f, f + 1]).tolist()
        some = [(p, q[(q >= low) & (q < high)] - low) for p, q in known]
        yield _row(ASK, count + f, b, _packed(by[low:high], np.array([p for p, _ in some], np.int64), *(q for _, q in some)))


def _begin(root: int, at: int, count: int) -> Work:
    """The root as the only new vertex."""

    def work(b: int, held: Held) -> Iterator[pa.RecordBatch]:
        ids, parts = _ints(held[STATE][b]), sorted(held.get(SAID, {}))
        none = np.zeros(0, np.int64)
        new = np.searchsorted(ids, [root]) if b == at else none
        seen = np.zeros(len(ids), bool)
        seen[new] = True
        state = _State(pa.py_buffer(_packed(np.array(parts, np.int64), np.array([len(held[SAID][p]) // 8 for p in parts], np.int64), np.array([len(ids)]), _bits(seen), none, none, none, new)))
        yield state.row(b)
        yield from _announced(b, held, len(ids), new, np.zeros(len(new), np.int64), count, 1)

    return work


def _discover(specs: tuple[PredictorSpec, ...], count: int, folders: int, offsets: list[int], span: int) -> Work:
    """``folders`` and ``offsets`` are of the folders that numbered this level's vertices, ``span`` the places that a folder of its tests takes."""

    def block(b: int, held: Held) -> Iterator[pa.RecordBatch]:
        state = _State(held[STATE][b])
        state.front, state.place = state.new, np.zeros(0, np.int64)
        if len(state.front):
            state.place = np.concatenate([_ints(held[ASK][f]) + offsets[f] for f in sorted(held[ASK])])
        new, by = state.front[:0], state.place[:0]
        if len(state.near):
            said = held[SAID]
            halo = np.full(int(state.lens.sum()), FAR)
            halo[state.near] = np.concatenate([_ints(said[k]) + offsets[k % folders] for k in sorted(said)])
            own, first = Block.unpacked(held[LAYOUT][b]), np.full(state.n, FAR)
            first[own.some] = np.minimum.reduceat(halo[own.to], own.begin)
            new = np.flatnonzero(~state.seen & (first < FAR))
            new = new[np.argsort(first[new], kind="stable")]
            by = first[new]
            state.seen[new] = True
        state.near, state.new = state.near[:0], new
        yield state.row(b)
        yield _row(TOLD, b, b, told=[len(state.front), len(new)])
        yield from _announced(b, held, state.n, new, by, count, span)

    def folder(b: int, held: Held) -> Iterator[pa.RecordBatch]:
        parts = [_unpacked(held[IDS][p]) for p in sorted(held[IDS])]
        place, degree = (np.concatenate([p[k] for p in parts]) for k in (0, 1))
        taken = np.concatenate([_mask(p[2], int(p[1].sum())) for p in parts])
        order = np.argsort(place)
        taken = taken[_slices((np.cumsum(degree) - degree)[order], degree[order])]
        loops = Folding(specs)
        loops.loops(degree[order])
        yield _row(TOLD, b, b, told=[len(place), len(taken), *(c for codes in loops.done().values() for c in codes), *_folded(taken, specs)])

    return lambda b, held: block(b, held) if b < count else folder(b, held)


def _settle(count: int, folders: int, span: int) -> Work:
    def block(b: int, held: Held) -> Iterator[pa.RecordBatch]:
        state, said = _State(held[STATE][b]), {p: _unpacked(d) for p, d in held.get(SAID, {}).items()}
        starts = dict(zip(state.peers.tolist(), (np.cumsum(state.lens) - state.lens).tolist()))
        heard = sorted(said)
        state.near = np.concatenate([said[p][0] + starts[p] for p in heard]) if heard else state.near[:0]
        if len(state.front):
            finder = np.full(int(state.lens.sum()), FAR)
            if heard:
                finder[state.near] = np.concatenate([said[p][1] for p in heard])
            own = Block.unpacked(held[LAYOUT][b])
            begin, folder = np.cumsum(own.degree) - own.degree, state.place // span
            for f in np.unique(folder).tolist():
                some = folder == f
                front, place = state.front[some], state.place[some]
                degree = own.degree[front]
                taken = finder[own.to[_slices(begin[front], degree)]] == np.repeat(place, degree)
                yield _row(IDS, count + f, b, _packed(place, degree, _bits(taken)))
        yield state.row(b)
        yield _row(TOLD, b, b, told=[len(state.near), len(state.new)])

    def folder(b: int, held: Held) -> Iterator[pa.RecordBatch]:
        blocks = sorted(held[ASK])
        parts = [_unpacked(held[ASK][p]) for p in blocks]
        by = np.concatenate([p[0] for p in parts])
        number = np.empty(len(by), np.int64)
        number[np.argsort(by, kind="stable")] = np.arange(len(by))
        for p, own, part in zip(blocks, np.split(number, np.cumsum([len(p[0]) for p in parts])[:-1]), parts):
            yield _row(ASK, p, b - count, own)
            for peer, q in zip(part[1].tolist(), part[2:]):
                yield _row(SAID, peer, p * folders + b - count, own[q])
        yield _row(TOLD, b, b, told=[len(by)])

    return lambda b, held: block(b, held) if b < count else folder(b, held)


def block_search(laid: Laid, specs: tuple[PredictorSpec, ...], root: int) -> list[LevelRun]:
    """The levels of a search; blocks that have no part in a level hand their state on and leave their layout unread."""
    laid.cut()
    count, levels, size = laid.count, [], sum(s.states for s in specs)
    step = 0

    def put(work: Work, rows, folders: int) -> list[tuple[int, list[int]]]:
        nonlocal step
        name = f"search-{step}"
        laid._put(name, rows.repartitionById(count + folders, "block").mapInArrow(_by_block(work), ROW))
        if step:
            laid.epochs.drop(f"search-{step - 1}")
        step += 1
        return [(r["block"], list(r["told"])) for r in sorted(laid._get(name, TOLD).select("block", "told").collect())]

    def given(layouts: list[int], sends: list[int]):
        rows = laid._get(f"search-{step - 1}", STATE, SAID, ASK, IDS)
        if layouts:
            rows = rows.unionByName(laid._get("layout", LAYOUT).where(F.col("block").isin(layouts)))
        return rows.unionByName(laid._get("sweep-0", SEND).where(F.col("block").isin(sends))) if sends else rows

    put(_begin(root, int(np.searchsorted(np.array(laid.bounds, np.int64), root, side="right")), count), laid._get("sweep-0", STATE, SAID, SEND), 0)
    folders, span, fronts = 1, 1, []
    while True:
        told = put(_settle(count, folders, span), given(fronts, []), folders)
        found = dict((b - count, t[0]) for b, t in told if b >= count)
        offsets, total = [], 0
        for f in range(folders):
            offsets, total = [*offsets, total], total + found.get(f, 0)
        heard = [b for b, t in told if b < count and t[0]]
        numbered, folders = folders, max(1, min(count, -(-total // FOLDER_PLACES)))
        span = max(1, -(-total // folders))
        told = put(_discover(specs, count, numbered, offsets, span), given(heard, heard), max(numbered, folders))
        tests = [t for b, t in told if b >= count]
        if tests:
            (n, traversed), loops = _met(tests, 2, specs)
            (taken,), codes = _met([t[2 + size :] for t in tests], 1, specs)
            levels.append(LevelRun(n, traversed, loops, codes, taken))
        fronts = [b for b, t in told if b < count and t[0]]
        if not total:
            laid.epochs.drop(f"search-{step - 1}")
            return levels
