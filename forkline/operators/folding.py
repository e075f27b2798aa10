"""Folding of long traces where they lie in order: tasks hold a range each and fold it as it streams by, vectorised.

Outcomes are folded eight at a time from a table, then in pairs; a task keeps a remainder of
less than eight outcomes and the function so far, whatever the length of its range. One pass
serves several predictors. A row a range, iteration and predictor goes to the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from forkline.operators.predictor import PredictorSpec, loop_function, then, walk

FOLDED = "part int, iteration int, predictor string, f array<bigint>, evaluations bigint, taken bigint"
#: Rows of one range, about, ranges at most, and rows that a task takes up at once.
RANGE_ROWS, MOST_RANGES, GATHER_ROWS = 1_000_000, 4096, 200_000


@lru_cache(maxsize=64)
def _bytes_table(spec: PredictorSpec) -> np.ndarray:
    return np.array([walk([bool(b >> (7 - i) & 1) for i in range(8)], spec) for b in range(256)], np.int64)


@lru_cache(maxsize=64)
def _loops_table(spec: PredictorSpec) -> np.ndarray:
    return np.array([loop_function(t, spec) for t in range(spec.states + 1)], np.int64)


def compose_all(codes: np.ndarray, states: int) -> np.ndarray:
    """The rows of ``codes`` one after another, made one function."""
    while len(codes) > 1:
        a, b = codes[: len(codes) // 2 * 2 : 2], codes[1::2]
        end = a % states
        met = a - end + np.take_along_axis(b, end, axis=1)
        codes = np.concatenate([met, codes[-1:]]) if len(codes) % 2 else met
    return codes[0]


class Folding:
    """The functions of a trace so far, by predictor, and how many of its outcomes were taken."""

    def __init__(self, specs: Iterable[PredictorSpec]):
        self.codes = {s: list(range(s.states)) for s in specs}
        self.rest, self.evaluations, self.taken = np.zeros(0, bool), 0, 0

    def outcomes(self, taken: np.ndarray) -> None:
        self.evaluations, self.taken = self.evaluations + len(taken), self.taken + int(np.count_nonzero(taken))
        bits = np.concatenate([self.rest, taken])
        whole = len(bits) // 8 * 8
        self.rest, eights = bits[whole:], np.packbits(bits[:whole])
        for s in self.codes if len(eights) else ():
            self.codes[s] = then(self.codes[s], compose_all(_bytes_table(s)[eights], s.states).tolist(), s)

    def loops(self, trips: np.ndarray) -> None:
        self.evaluations, self.taken = self.evaluations + len(trips) + int(trips.sum()), self.taken + int(trips.sum())
        for s in self.codes if len(trips) else ():
            if s.kind == "static":
                missed = int(len(trips) if s.taken else trips.sum())
                self.codes[s] = [c + missed for c in self.codes[s]]
            else:
                self.codes[s] = then(self.codes[s], compose_all(_loops_table(s)[np.minimum(trips, s.states)], s.states).tolist(), s)

    def done(self) -> dict[PredictorSpec, list[int]]:
        return {s: then(c, walk(self.rest.tolist(), s), s) for s, c in self.codes.items()}


def gathered(batches: Iterator[pa.RecordBatch], rows: int = GATHER_ROWS) -> Iterator[pa.Table]:
    held, n = [], 0
    for batch in batches:
        if batch.num_rows:
            held, n = [*held, batch], n + batch.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if held:
        yield pa.Table.from_batches(held)


def told(foldings: dict[int, Folding]) -> pa.RecordBatch:
    from pyspark import TaskContext

    part = TaskContext.get().partitionId()
    rows = [(part, i, s.name, f, x.evaluations, x.taken) for i, x in foldings.items() for s, f in x.done().items()]
    kinds = (pa.int32(), pa.int32(), pa.string(), pa.list_(pa.int64()), pa.int64(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds)], names=["part", "iteration", "predictor", "f", "evaluations", "taken"])


def ranges_for(rows: int) -> int:
    return max(1, min(MOST_RANGES, rows // RANGE_ROWS))


def range_of(value: Column, bounds: list[int]) -> Column:
    """Number of the range that a value lies in, by a tree of comparisons; a bound begins a range."""
    if not bounds:
        return F.lit(0)

    def tree(low: int, high: int) -> Column:
        if low == high:
            return F.lit(low)
        middle = (low + high) // 2
        return F.when(value < F.lit(bounds[middle]), tree(low, middle)).otherwise(tree(middle + 1, high))

    return tree(0, len(bounds))


def even_bounds(df: DataFrame, column: str, ranges: int) -> list[int]:
    """Values at which ranges of about as many rows each begin."""
    if ranges < 2:
        return []
    found = df.agg(F.percentile_approx(column, [i / ranges for i in range(1, ranges)], 20 * ranges).alias("q")).first()["q"]
    return sorted(set(found or []))


def _by_iteration(add: Callable[[Folding, np.ndarray], None], specs: tuple[PredictorSpec, ...]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        foldings: dict[int, Folding] = {}
        for t in gathered(batches):
            i, x = t.column("iteration").to_numpy(), t.column("x").to_numpy()
            begin = np.append(0, np.flatnonzero(i[1:] != i[:-1]) + 1)
            for a, b in zip(begin.tolist(), [*begin[1:].tolist(), len(i)]):
                add(foldings.setdefault(int(i[a]), Folding(specs)), x[a:b])
        yield told(foldings)

    return fold


def fold_in_order(df: DataFrame, order: list[str], bounds: list[int], specs: tuple[PredictorSpec, ...], loops: bool = False) -> DataFrame:
    """``FOLDED`` of ``df(iteration, x, ..)``: ``x`` an outcome, or with ``loops`` a loop's trips, in an order in which iterations follow each other."""
    dealt = df.withColumn("__range", range_of(F.col(order[0]), bounds)).repartitionById(len(bounds) + 1, "__range").sortWithinPartitions(*order)
    return dealt.select(F.col("iteration").cast("int").alias("iteration"), "x").mapInArrow(_by_iteration(Folding.loops if loops else Folding.outcomes, specs), FOLDED)


def fold_improvements(messages: DataFrame, iterations: list[int], bounds: list[int], specs: tuple[PredictorSpec, ...]) -> DataFrame:
    """``FOLDED`` of the improvement tests of ``messages(src, dst, h0, h1, ..)``, a column of labels an iteration.

    A row without ``dst`` brings a vertex's own labels. A neighbour's label is tested against
    the least before it, of the own one and those of smaller neighbours.
    """
    names = [f"h{k}" for k in range(len(iterations))]

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        foldings = {i: Folding(specs) for i in iterations}
        least = np.zeros(len(names), np.int64)  # of the vertex that the rows before ended in
        for t in gathered(batches):
            own = t.column("dst").is_null().to_numpy()
            place = np.append(0, np.cumsum(own))  # which vertex, the one before being 0
            for k, (i, name) in enumerate(zip(iterations, names)):
                x = np.append(least[k], t.column(name).to_numpy())
                low, high = int(x.min()), int(x.max())
                span = high - low + 1
                if span * (int(place[-1]) + 1) >= 1 << 62:  # numbers of the labels in their place
                    values, y = np.unique(x, return_inverse=True)
                    span = len(values)
                else:
                    values, y = None, x - low
                y = y - place * span  # vertices lie below those before them, so one running minimum serves all
                running = np.minimum.accumulate(y)
                foldings[i].outcomes((y[1:] < running[:-1])[~own])
                last = int(running[-1] + place[-1] * span)
                least[k] = last + low if values is None else values[last]
        yield told(foldings)

    dealt = messages.withColumn("__range", range_of(F.col("src"), bounds)).repartitionById(len(bounds) + 1, "__range").sortWithinPartitions("src", "dst")
    return dealt.select("dst", *names).mapInArrow(fold, FOLDED)


def composed(folded: DataFrame, specs: Iterable[PredictorSpec]) -> dict[tuple[int, str], tuple[list[int], int, int]]:
    """``(iteration, predictor)`` to function, evaluations and taken, ranges in their order: some rows a task, met on the driver."""
    out: dict[tuple[int, str], tuple[list[int], int, int]] = {}
    spec = {s.name: s for s in specs}
    for r in sorted(folded.collect(), key=lambda r: r["part"]):
        key = (r["iteration"], r["predictor"])
        if key not in out:
            out[key] = (list(r["f"]), r["evaluations"], r["taken"])
        else:
            f, n, taken = out[key]
            out[key] = (then(f, list(r["f"]), spec[r["predictor"]]), n + r["evaluations"], taken + r["taken"])
    return out
