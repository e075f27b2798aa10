"""Kernels over blocks: ranges of vertices in order, each with its edges in arrays that one task holds.

A task sweeps its block and folds the outcomes of its tests at the same time, so no trace and
no history of labels is written. Blocks tell each other the labels at their borders, one
array for a pair of blocks, in an order that both know; edges are laid out once and are never
joined again. A graph of one block runs all its sweeps, or levels, in one task.

Pairs go straight into blocks: tasks orient them, drop repeats among some hundred thousand
and hand them on as arrays; a block drops the repeats that are left while it sorts. No
distinct rows and no edges are made by joins or aggregates.

A block holds about ``BLOCK_EDGES`` adjacencies; a vertex with more needs the folding by
pieces in ``trace``, and so these functions return nothing then.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from forkline.graph import Graph
from forkline.operators.folding import Folding, gathered
from forkline.operators.predictor import PredictorSpec, then
from forkline.sources.tables import Epochs, shuffles_dropped

#: Adjacencies of a graph of one block, and of a block of a larger graph, about.
ONE_BLOCK, BLOCK_EDGES = 4_000_000, 2_000_000
#: Pairs of one array on the way to blocks, and places of its ends that it tells the driver, from which bounds are made.
CHUNK_PAIRS, CHUNK_PLACES = 500_000, 256

#: Rows that tasks exchange: ``data`` is an array that goes to ``block`` from ``peer``, ``told`` some numbers for the driver.
ROW = "kind int, block int, peer int, data binary, told array<bigint>"
LAYOUT, IDS, ASK, SEND, STATE, SAID, TOLD, PAIRS = range(8)
_ARROW = pa.schema([("kind", pa.int32()), ("block", pa.int32()), ("peer", pa.int32()), ("data", pa.binary()), ("told", pa.list_(pa.int64()))])

Held = dict[int, dict[int, pa.Buffer]]
Codes = dict[str, list[int]]


@dataclass(frozen=True)
class BlockRun:
    """Counts of a graph, the function of its neighbour loops, and of each sweep the changed labels and the tests, by predictor."""

    n: int
    adjacent: int
    loops: Codes
    changed: list[int]
    tests: list[tuple[Codes, int]]


def _row(kind: int, block: int, peer: int, data: np.ndarray | bytes | None = None, told: list[int] | None = None) -> pa.RecordBatch:
    values = [[kind], [block], [peer], [data.tobytes() if isinstance(data, np.ndarray) else data], [told]]
    return pa.RecordBatch.from_arrays([pa.array(v, f.type) for v, f in zip(values, _ARROW)], schema=_ARROW)


class Block:
    """Vertices in order with their neighbours in order; ``to`` are places in ``halo``, the distinct neighbours."""

    def __init__(self, degree: np.ndarray, lows: np.ndarray, to: np.ndarray):
        self.degree, self.lows, self.to = degree.astype(np.int64), lows.astype(np.int64), to
        self.at = np.repeat(np.arange(len(degree)), self.degree)
        self.some = np.flatnonzero(self.degree)
        self.begin = (np.cumsum(self.degree) - self.degree)[self.some]

    @classmethod
    def of(cls, src: np.ndarray, dst: np.ndarray, alone: np.ndarray) -> tuple[Block, np.ndarray, np.ndarray]:
        """The block of some edges, which may repeat, and of vertices that may have none; its ids and its halo."""
        ids, halo = np.unique(np.concatenate([src, alone])), np.unique(dst)
        key = np.searchsorted(ids, src) * max(1, len(halo)) + np.searchsorted(halo, dst)
        at, to = np.divmod(np.unique(key), max(1, len(halo)))
        low = halo[to] < ids[at]
        return cls(np.bincount(at, minlength=len(ids)), np.bincount(at[low], minlength=len(ids)), to.astype(np.uint32)), ids, halo

    def packed(self) -> bytes:
        return np.int64(len(self.degree)).tobytes() + self.degree.astype(np.uint32).tobytes() + self.lows.astype(np.uint32).tobytes() + self.to.tobytes()

    @classmethod
    def unpacked(cls, data: pa.Buffer) -> Block:
        n = int(np.frombuffer(data, np.int64, 1)[0])
        rest = np.frombuffer(data, np.uint32, offset=8)
        return cls(rest[:n], rest[n : 2 * n], rest[2 * n :])

    def low_edges(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Neighbours before the vertex: mask of edges, vertices that have any, where theirs begin."""
        mask = np.arange(len(self.to)) - np.repeat(np.cumsum(self.degree) - self.degree, self.degree) < np.repeat(self.lows, self.degree)
        some = np.flatnonzero(self.lows)
        return mask, some, (np.cumsum(self.lows) - self.lows)[some]

    def least(self, own: np.ndarray, heard: np.ndarray) -> np.ndarray:
        new = own.copy()
        if len(heard):
            new[self.some] = np.minimum(own[self.some], np.minimum.reduceat(heard, self.begin))
        return new

    def improved(self, own: np.ndarray, heard: np.ndarray) -> np.ndarray:
        """Is the label heard at each adjacency below the least before it, of the own one and those of neighbours before?"""
        taken = np.zeros(len(heard), bool)
        if not len(heard):
            return taken
        low, high = min(int(own.min()), int(heard.min())), max(int(own.max()), int(heard.max()))
        if (high - low + 1) * (len(own) + 1) >= 1 << 62:  # numbers of the labels in their place
            values = np.unique(np.concatenate([own, heard]))
            own, heard, low, high = np.searchsorted(values, own), np.searchsorted(values, heard), 0, len(values)
        # vertices lie below those before them, so one running minimum serves all
        y = np.minimum(heard, own[self.at]) - low - self.at * (high - low + 1)
        running = np.minimum.accumulate(y)
        taken[1:] = y[1:] < running[:-1]
        taken[self.begin] = heard[self.begin] < own[self.some]
        return taken


def _folded(taken: np.ndarray, specs: tuple[PredictorSpec, ...]) -> list[int]:
    """Number of taken tests, then the functions, one predictor after another."""
    f = Folding(specs)
    f.outcomes(taken)
    return [f.taken, *(c for codes in f.done().values() for c in codes)]


def _loops(block: Block, specs: tuple[PredictorSpec, ...]) -> list[int]:
    f = Folding(specs)
    f.loops(block.degree)
    return [len(block.degree), len(block.to), *(c for codes in f.done().values() for c in codes)]


def _codes(told: list[int], specs: tuple[PredictorSpec, ...]) -> Codes:
    out, at = {}, 0
    for s in specs:
        out[s.name], at = list(told[at : at + s.states]), at + s.states
    return out


def _met(rows: list[list[int]], skip: int, specs: tuple[PredictorSpec, ...]) -> tuple[list[int], Codes]:
    """Sums of the first numbers and the functions of blocks in their order."""
    sums, codes = [0] * skip, {s.name: list(range(s.states)) for s in specs}
    for told in rows:
        sums = [a + b for a, b in zip(sums, told)]
        own = _codes(told[skip:], specs)
        codes = {s.name: then(codes[s.name], own[s.name], s) for s in specs}
    return sums, codes


class _InPlace:
    """A sweep in sequential order: new labels of neighbours before a vertex, old ones of those after it."""

    def __init__(self, block: Block):
        self.block = block
        self.low, self.some, self.begin = block.low_edges()
        self.low_to, self.high_to = block.to[self.low], block.to[~self.low]
        ups = block.degree - block.lows
        self.high_some = np.flatnonzero(ups)
        self.high_begin = (np.cumsum(ups) - ups)[self.high_some]

    def base(self, own: np.ndarray, before: np.ndarray) -> np.ndarray:
        out = own.copy()
        if len(self.high_to):
            out[self.high_some] = np.minimum(own[self.high_some], np.minimum.reduceat(before[self.high_to], self.high_begin))
        return out

    def settled(self, base: np.ndarray, now: np.ndarray, halo: np.ndarray, inside: slice, send: np.ndarray) -> np.ndarray:
        """Labels of the block's own vertices, those of other blocks being as ``halo`` says; its part ``inside`` follows the own ones."""
        while True:
            halo[inside] = now[send]
            new = base.copy()
            if len(self.low_to):
                new[self.some] = np.minimum(base[self.some], np.minimum.reduceat(halo[self.low_to], self.begin))
            if (new == now).all():
                return now
            now = new

    def heard(self, before: np.ndarray, after: np.ndarray) -> np.ndarray:
        return np.where(self.low, after[self.block.to], before[self.block.to])


def _without_repeats(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs in order, once each."""
    if not len(a):
        return a, b
    low, least, span, most = int(a.min()), int(b.min()), int(b.max()) - int(b.min()) + 1, int(a.max()) - int(a.min()) + 1
    if span * most < 1 << 62:
        x, y = np.divmod(np.unique((a - low) * span + (b - least)), span)
        return x + low, y + least
    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    new = np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]))
    return a[new], b[new]


def _packed_pairs(a: np.ndarray, b: np.ndarray, alone: np.ndarray) -> bytes:
    return np.int64(len(a)).tobytes() + a.tobytes() + b.tobytes() + alone.tobytes()


def _unpacked_pairs(data: pa.Buffer) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    x = _ints(data)
    n = int(x[0])
    return x[1 : n + 1], x[n + 1 : 2 * n + 1], x[2 * n + 1 :]


def _chunked(directed: bool) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Arrays of pairs ``(src, dst)``, the lesser id first unless ``directed``, and of vertices, which are rows without ``dst``.

    Each tells its number of ends, the least one, and ends at even places of their order.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in gathered(batches, CHUNK_PAIRS):
            src, single = t.column("src").to_numpy(), t.column("dst").is_null().to_numpy()
            a, b, alone = src[~single], t.column("dst").fill_null(0).to_numpy()[~single], src[single]
            a, b = _without_repeats(a, b) if directed else _without_repeats(np.minimum(a, b), np.maximum(a, b))
            ends = np.sort(a if directed else np.concatenate([a, b]))
            places = ends[np.linspace(0, len(ends) - 1, min(CHUNK_PLACES, len(ends))).astype(np.int64)]
            least = min(int(x.min()) for x in (ends, b, alone) if len(x))
            yield _row(PAIRS, 0, 0, _packed_pairs(a, b, alone), [len(ends), least, *places.tolist()])

    return run


def _split(bounds: list[int], directed: bool) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The arrays of pairs parted by block, in both orientations unless ``directed``."""
    cuts = np.array(bounds, np.int64)

    def parted(by: np.ndarray, *columns: np.ndarray) -> list[tuple[np.ndarray, ...]]:
        block = np.searchsorted(cuts, by, side="right")
        order = np.argsort(block.astype(np.uint16) if len(cuts) < 65_535 else block, kind="stable")
        at = np.searchsorted(block[order], np.arange(len(cuts) + 2))
        return [tuple(c[order[at[i] : at[i + 1]]] for c in columns) for i in range(len(cuts) + 1)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column(batch.schema.get_field_index("data")):
                a, b, alone = _unpacked_pairs(data.as_buffer())
                src, dst = (a, b) if directed else (np.concatenate([a, b]), np.concatenate([b, a]))
                for i, ((s, d), (v,)) in enumerate(zip(parted(src, src, dst), parted(alone, alone))):
                    if len(s) or len(v):
                        yield _row(PAIRS, i, 0, _packed_pairs(s, d, v))

    return run


def _edges_of(batches: Iterator[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """Edges ``(src, dst)`` and vertices of one block."""
    parts = [_unpacked_pairs(data.as_buffer()) for batch in batches for data in batch.column(batch.schema.get_field_index("data"))]
    return tuple(np.concatenate(x) for x in zip(*parts)) if parts else None


def _whole(specs: tuple[PredictorSpec, ...], order: str) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """All sweeps of a graph of one block. Labels are places in the order of ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = _edges_of(batches)
        if found is None:
            return
        block, ids, halo = Block.of(*found)
        del found
        yield _row(LAYOUT, 0, 0, told=_loops(block, specs))
        own, near = np.arange(len(ids)), np.searchsorted(ids, halo)
        walk, sweep, changed = _InPlace(block) if order == "inplace" else None, 0, 1
        while changed:
            sweep, before = sweep + 1, own[near]
            if walk is None:
                heard = before[block.to]
                new = block.least(own, heard)
            else:
                base = walk.base(own, before)
                new = walk.settled(base, base, after := before.copy(), slice(None), near)
                heard = walk.heard(before, after)
            changed = int(np.count_nonzero(new != own))
            yield _row(TOLD, 0, sweep, told=[changed, *_folded(block.improved(own, heard), specs)])
            own = new

    return run


def _by_block(work: Callable[[int, Held], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, Held] = {}
        for batch in batches:
            kind, block, peer = (batch.column(c).to_pylist() for c in range(3))
            for i, (k, b, p) in enumerate(zip(kind, block, peer)):
                held.setdefault(b, {}).setdefault(k, {})[p] = batch.column(3)[i].as_buffer()
        for b in sorted(held):
            yield from work(b, held.pop(b))

    return run


def _ints(data: pa.Buffer) -> np.ndarray:
    return np.frombuffer(data, np.int64)


def _halo(held: Held) -> np.ndarray:
    """Labels of the halo: blocks are ranges, so their parts follow each other."""
    parts = [_ints(held[SAID][p]) for p in sorted(held.get(SAID, {}))]
    return np.concatenate(parts) if parts else np.zeros(0, np.int64)


def _say(block: int, held: Held, own: np.ndarray) -> Iterator[pa.RecordBatch]:
    for p, data in held.get(SEND, {}).items():
        yield _row(SAID, p, block, own[np.frombuffer(data, np.uint32)])


class Laid:
    """A graph in the shared folder: its pairs in arrays, and cut into blocks on demand. Kernels and predictors share it."""

    def __init__(self, g: Graph):
        self.spark, self.directed = g.edges.sparkSession, g.directed
        self.epochs, self.is_cut = Epochs(self.spark, "blocks"), False
        pairs = (g.edges if g.pairs is None else g.pairs).select("src", "dst").where("src <> dst")
        alone = g.alone if g.pairs is not None and not g.directed else g.vertices  # ends of the pairs come with them
        if alone is not None:
            pairs = pairs.unionByName(alone.select(F.col(alone.columns[0]).cast("bigint").alias("src"), F.lit(None).cast("bigint").alias("dst")).where("src IS NOT NULL"))
        self._put("pairs", pairs.mapInArrow(_chunked(g.directed), ROW))
        told = [np.array(r["told"]) for r in self._get("pairs", PAIRS).select("told").collect()]
        self.adjacent = sum(int(t[0]) for t in told)  # at most: repeats in different arrays count
        self.least = min((int(t[1]) for t in told), default=None)
        self.bounds, self.count = [], 1
        if self.adjacent > ONE_BLOCK:
            self.count = -(-self.adjacent // BLOCK_EDGES)
            places, weights = np.concatenate([t[2:] for t in told]), np.concatenate([np.full(len(t) - 2, t[0] / max(1, len(t) - 2)) for t in told])
            order = np.argsort(places, kind="stable")
            at = np.searchsorted(np.cumsum(weights[order]), np.arange(1, self.count) * (self.adjacent / self.count))
            self.bounds = sorted(set(places[order][at].tolist()))
        self.whole, self.has_hub = self.count == 1, len(self.bounds) < self.count - 1

    def pairs(self) -> DataFrame:
        return self._get("pairs", PAIRS)

    def cut(self) -> None:
        if self.is_cut:
            return
        dealt = self._dealt(self.pairs().mapInArrow(_split(self.bounds, self.directed), ROW)).select("data").mapInArrow(self._lay(), ROW)
        self._put("layout", dealt)
        self._put("sweep-0", self._dealt(self._get("layout", IDS, ASK)).mapInArrow(_by_block(_answered), ROW))
        self.is_cut = True

    def _put(self, name: str, df: DataFrame) -> None:
        with shuffles_dropped(self.spark):
            df.write.partitionBy("kind").parquet(f"{self.epochs.root}/{name}")

    def _get(self, name: str, *kinds: int) -> DataFrame:
        rows = self.spark.read.schema(ROW).parquet(f"{self.epochs.root}/{name}")
        return rows.where(F.col("kind").isin(*kinds)).select("kind", "block", "peer", "data", "told")

    def _dealt(self, df: DataFrame) -> DataFrame:
        return df.repartitionById(self.count, "block")

    def told(self, name: str) -> list[list[int]]:
        return [list(r["told"]) for r in sorted(self._get(name, TOLD).select("block", "told").collect())]

    def step(self, done: int, work: Callable[[int, Held], Iterator[pa.RecordBatch]]) -> list[list[int]]:
        """One exchange: each block gets its layout, its state and what others said; what blocks told, in their order."""
        rows = self._get("layout", LAYOUT).unionByName(self._get("sweep-0", SEND)).unionByName(self._get(f"sweep-{done}", STATE, SAID))
        self._put(f"sweep-{done + 1}", self._dealt(rows).mapInArrow(_by_block(work), ROW))
        if done:
            self.epochs.drop(f"sweep-{done}")
        return self.told(f"sweep-{done + 1}")

    def _lay(self) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        bounds = np.array(self.bounds, np.int64)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            found = _edges_of(batches)
            if found is None:
                return
            block, ids, halo = Block.of(*found)
            del found
            b = int(np.searchsorted(bounds, ids[0], side="right"))
            yield _row(LAYOUT, b, b, block.packed())
            yield _row(IDS, b, b, ids)
            cut = [0, *np.searchsorted(halo, bounds).tolist(), len(halo)]
            for s in range(len(cut) - 1):
                if cut[s] < cut[s + 1]:
                    yield _row(ASK, s, b, halo[cut[s] : cut[s + 1]])

        return run


def _answered(block: int, held: Held) -> Iterator[pa.RecordBatch]:
    """Where the ids that others ask for lie in a block, and the first labels, which are the ids."""
    ids = _ints(held[IDS][block])
    yield _row(STATE, block, block, ids)
    for p, data in held.get(ASK, {}).items():
        asked = _ints(data)
        yield _row(SEND, block, p, np.searchsorted(ids, asked).astype(np.uint32))
        yield _row(SAID, p, block, asked)


def _sweep(specs: tuple[PredictorSpec, ...], first: bool) -> Callable[[int, Held], Iterator[pa.RecordBatch]]:
    """A sweep; the ``first`` tells of the neighbour loops too, which all sweeps have alike."""

    def work(b: int, held: Held) -> Iterator[pa.RecordBatch]:
        block, own = Block.unpacked(held[LAYOUT][b]), _ints(held[STATE][b])
        heard = _halo(held)[block.to]
        new = block.least(own, heard)
        yield _row(TOLD, b, b, told=[int(np.count_nonzero(new != own)), *_folded(block.improved(own, heard), specs), *(_loops(block, specs) if first else ())])
        yield _row(STATE, b, b, new)
        yield from _say(b, held, new)

    return work


def _round(specs: tuple[PredictorSpec, ...], first: bool, begins: bool) -> Callable[[int, Held], Iterator[pa.RecordBatch]]:
    """A round of a sweep in place. The one that ``begins`` a sweep folds the sweep before, unless this is the ``first``, as only now all labels are final.

    State: labels before the sweep, labels now, labels of the halo before the sweep.
    """

    def work(b: int, held: Held) -> Iterator[pa.RecordBatch]:
        block, state, halo = Block.unpacked(held[LAYOUT][b]), _ints(held[STATE][b]), _halo(held)
        n, walk = len(block.degree), _InPlace(block)
        own, now, before = (state, state, halo) if first else (state[:n], state[n : 2 * n], state[2 * n :])
        told = []
        if begins:
            told = _loops(block, specs) if first else _folded(block.improved(own, walk.heard(before, halo)), specs)
            own, before = now, halo.copy()
        base = walk.base(own, before)
        send = held.get(SEND, {})
        mine = np.frombuffer(send[b], np.uint32) if b in send else np.zeros(0, np.uint32)
        start = sum(len(held[SAID][p]) // 8 for p in held.get(SAID, {}) if p < b)
        new = walk.settled(base, np.minimum(base, now), halo, slice(start, start + len(mine)), mine)
        yield _row(TOLD, b, b, told=[int(np.count_nonzero(new != now)), int(np.count_nonzero(new != own)), *told])
        yield _row(STATE, b, b, np.concatenate([own, new, before]))
        yield from _say(b, held, new)

    return work


def _one_task(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> list:
    return df.repartitionById(1, F.lit(0)).mapInArrow(run, ROW).select("kind", "peer", "told").collect()


def component_run(g: Graph, specs: tuple[PredictorSpec, ...], order: str = "sync", laid: Laid | None = None) -> BlockRun | None:
    """The component kernel's sweeps, in synchronous or sequential (``inplace``) order; None if a vertex is larger than a block.

    A graph that was laid out before is given as ``laid``; it stays in the shared folder.
    """
    found = laid or Laid(g)
    run = None if found.has_hub else _whole_components(found, specs, order) if found.whole else _block_components(found, specs, order)
    if laid is None:
        found.epochs.drop("pairs", "layout", "sweep-0")
    return run


def _whole_components(laid: Laid, specs: tuple[PredictorSpec, ...], order: str) -> BlockRun:
    told = _one_task(laid.pairs().mapInArrow(_split([], laid.directed), ROW), _whole(specs, order))
    same = [s for p in specs for s in range(p.states)]
    n, adjacent, *loops = next((r["told"] for r in told if r["kind"] == LAYOUT), [0, 0, *same])
    sweeps = [r["told"] for r in sorted(told, key=lambda r: r["peer"]) if r["kind"] == TOLD] or [[0, 0, *same]]
    return BlockRun(n, adjacent, _codes(loops, specs), [t[0] for t in sweeps], [(_codes(t[2:], specs), t[1]) for t in sweeps])


def _block_components(laid: Laid, specs: tuple[PredictorSpec, ...], order: str) -> BlockRun:
    laid.cut()
    size = sum(s.states for s in specs)
    changed, tests, done = [], [], 0
    if order == "sync":
        while not changed or changed[-1]:
            told = laid.step(done, _sweep(specs, not done))
            if not done:
                (n, adjacent), loops = _met([t[2 + size :] for t in told], 2, specs)
            (some, taken), codes = _met(told, 2, specs)
            changed, tests, done = [*changed, some], [*tests, (codes, taken)], done + 1
    else:
        while True:
            told, begins = laid.step(done, _round(specs, not done, True)), not done
            if begins:
                (n, adjacent), loops = _met([t[2:] for t in told], 2, specs)
            else:
                (_, _, taken), codes = _met(told, 3, specs)
                tests.append((codes, taken))
                if not changed[-1]:
                    break
            done += 1
            while sum(t[0] for t in told):
                told, done = laid.step(done, _round(specs, False, False)), done + 1
            changed.append(sum(t[1] for t in told))
    laid.epochs.drop(f"sweep-{done}", f"sweep-{done + 1}")
    return BlockRun(n, adjacent, loops, changed, tests)


@dataclass(frozen=True)
class LevelRun:
    """A level of a search: vertices, adjacencies, the functions of its neighbour loops and of its tests, and discoveries."""

    n: int
    traversed: int
    loops: Codes
    tests: Codes
    taken: int


def _whole_search(specs: tuple[PredictorSpec, ...], root: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """All levels of a graph of one block, in queue order: a discovery is the first adjacency that leads to a new vertex."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = _edges_of(batches)
        if found is None:
            return
        block, ids, halo = Block.of(*found)
        del found
        to, begin, seen = np.searchsorted(ids, halo)[block.to], np.cumsum(block.degree) - block.degree, np.zeros(len(ids), bool)
        frontier, level = np.searchsorted(ids, [root]), 0
        while len(frontier):
            seen[frontier] = True
            degree = block.degree[frontier]
            far = to[np.repeat(begin[frontier] - (np.cumsum(degree) - degree), degree) + np.arange(degree.sum())]
            fresh = np.flatnonzero(~seen[far])
            first = fresh[np.sort(np.unique(far[fresh], return_index=True)[1])]
            taken = np.zeros(len(far), bool)
            taken[first] = True
            loops = Folding(specs)
            loops.loops(degree)
            told = [len(frontier), len(far), *(c for codes in loops.done().values() for c in codes), *_folded(taken, specs)]
            yield _row(TOLD, 0, level, told=told)
            frontier, level = far[first], level + 1

    return run


def search_run(g: Graph, specs: tuple[PredictorSpec, ...], root: int, laid: Laid | None = None) -> list[LevelRun] | None:
    """The levels of a search, in exact queue order; None if a vertex is larger than a block, or a directed graph than one block."""
    from forkline.operators.block_search import block_search

    found = laid or Laid(g)
    levels = _whole_levels(found, specs, root) if found.whole else None if found.has_hub or found.directed else block_search(found, specs, root)
    if laid is None:
        found.epochs.drop("pairs", "layout", "sweep-0")
    return levels


def _whole_levels(laid: Laid, specs: tuple[PredictorSpec, ...], root: int) -> list[LevelRun]:
    size = sum(s.states for s in specs)
    told = _one_task(laid.pairs().mapInArrow(_split([], laid.directed), ROW), _whole_search(specs, root))
    rows = [list(r["told"]) for r in sorted(told, key=lambda r: r["peer"])]
    return [LevelRun(t[0], t[1], _codes(t[2:], specs), _codes(t[3 + size :], specs), t[2 + size]) for t in rows]
