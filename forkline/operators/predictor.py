"""Branch predictors over ordered traces, evaluated in parallel.

A stretch of a trace acts on a saturating counter as a function from start state to (end
state, misses). Such functions compose associatively, so stretches are folded where they
lie, ranges of stretches in their order (many at once, in pairs), and the few range results
on the driver. No window runs over a whole trace. A function is an array of
``misses * states + end`` by start state.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PredictorSpec:
    """``kind`` saturating: a counter of ``bits`` bits (1: the last outcome); static: always predicts ``taken``."""

    kind: str = "saturating"
    bits: int = 2
    start: int = 0
    taken: bool = True

    @property
    def states(self) -> int:
        return 1 << self.bits if self.kind == "saturating" else 1

    @property
    def name(self) -> str:
        return f"{self.bits}-bit" if self.kind == "saturating" else f"static-{'taken' if self.taken else 'not-taken'}"

    def step(self, state: int, taken: bool) -> tuple[int, int]:
        """Next state and whether the outcome was missed."""
        if self.kind == "static":
            return 0, int(taken != self.taken)
        half, top = self.states // 2, self.states - 1
        return (min(top, state + 1), int(state < half)) if taken else (max(0, state - 1), int(state >= half))


def two_bit(start: int = 0) -> PredictorSpec:
    return PredictorSpec(start=start)


def one_bit(start: int = 0) -> PredictorSpec:
    return PredictorSpec(bits=1, start=start)


def saturating(bits: int, start: int = 0) -> PredictorSpec:
    return PredictorSpec(bits=bits, start=start)


def static(taken: bool) -> PredictorSpec:
    return PredictorSpec(kind="static", bits=0, taken=taken)


def identity(spec: PredictorSpec) -> list[int]:
    return list(range(spec.states))


def then(first: list[int], second: list[int], spec: PredictorSpec) -> list[int]:
    """The function of one stretch after another."""
    n = spec.states
    return [(code // n + second[code % n] // n) * n + second[code % n] % n for code in first]


def repeated(f: list[int], times: int, spec: PredictorSpec) -> list[int]:
    """``times`` stretches of function ``f``, by squaring."""
    out, power = identity(spec), f
    while times:
        if times & 1:
            out = then(out, power, spec)
        power, times = then(power, power, spec), times >> 1
    return out


def walk(outcomes: list[bool], spec: PredictorSpec) -> list[int]:
    """The function of a short trace, outcome by outcome."""
    out = []
    for state in range(spec.states):
        misses = 0
        for taken in outcomes:
            state, missed = spec.step(state, taken)
            misses += missed
        out.append(misses * spec.states + state)
    return out


def loop_function(trips: int, spec: PredictorSpec) -> list[int]:
    """A counted loop: ``trips`` taken tests and the one that leaves."""
    # beyond the counter's depth further passes change nothing but the static misses
    deep = min(trips, spec.states)
    f = walk([True] * deep + [False], spec)
    if spec.kind == "static" and trips > deep and not spec.taken:
        f = [code + (trips - deep) * spec.states for code in f]
    return f


def run_function(n: int, taken: bool, spec: PredictorSpec) -> list[int]:
    return repeated(walk([taken], spec), n, spec)


# --- columns ---------------------------------------------------------------------------


def _step_column(code: Column, taken: Column, spec: PredictorSpec) -> Column:
    n = spec.states
    state, missed = code % n, F.floor(code / n).cast("bigint")
    if spec.kind == "static":
        return (missed + (taken != F.lit(spec.taken)).cast("bigint")) * n
    up = F.least(F.lit(n - 1), state + 1) + n * (missed + (state < n // 2).cast("bigint"))
    down = F.greatest(F.lit(0), state - 1) + n * (missed + (state >= n // 2).cast("bigint"))
    return F.when(taken, up).otherwise(down).cast("bigint")


def start_codes(spec: PredictorSpec) -> Column:
    """The function of an empty stretch."""
    return F.array(*(F.lit(s).cast("bigint") for s in range(spec.states)))


def step_codes(codes: Column, taken: Column, spec: PredictorSpec) -> Column:
    """A function followed by one outcome."""
    return F.transform(codes, lambda c: _step_column(c, taken, spec))


def fold_outcomes(outcomes: Column, spec: PredictorSpec) -> Column:
    """Function of an array of outcomes, as an array of codes."""
    return F.aggregate(outcomes, start_codes(spec), lambda acc, x: step_codes(acc, x, spec))


def loop_transfer(trips: Column, spec: PredictorSpec) -> Column:
    """Function of a counted loop from a closed table over its trip count."""
    table = [loop_function(t, spec) for t in range(spec.states + 1)]
    if spec.kind == "static":
        return F.array((trips * int(not spec.taken) + int(spec.taken)).cast("bigint"))
    at = F.least(trips, F.lit(spec.states)).cast("int")
    rows = F.array(*(F.array(*(F.lit(c).cast("bigint") for c in row)) for row in table))
    return F.element_at(rows, at + 1)


def compose_runs(codes: np.ndarray, group: np.ndarray, states: int) -> tuple[np.ndarray, np.ndarray]:
    """Functions ``codes`` (rows, states) of neighbouring rows of one group made one: a row a run of equal ``group``.

    Rows meet in pairs, so a run of n is done after log2(n) vectorised steps.
    """
    while len(group):
        first = np.ones(len(group), bool)
        first[1:] = group[1:] != group[:-1]
        begin = np.flatnonzero(first)
        place = np.arange(len(group)) - np.repeat(begin, np.diff(np.append(begin, len(group))))
        left = np.flatnonzero((place % 2 == 0) & np.append(~first[1:], False))  # rows with a partner after them
        if not len(left):
            break
        a, b = codes[left], codes[left + 1]
        end = np.take_along_axis(b, a % states, axis=1)
        codes = codes.copy()
        codes[left] = (a // states + end // states) * states + end % states
        keep = np.ones(len(group), bool)
        keep[left + 1] = False
        codes, group = codes[keep], group[keep]
    return codes, group


def compose_ordered(stretches: DataFrame, groups: list[str], order: list[str], spec: PredictorSpec, function: str = "f") -> dict[tuple, list[int]]:
    """Function of each group's stretches in their order. ``order`` ends a total order within a group.

    Ranges of (groups, order) are folded by one task each; a row a range and group comes back.
    """
    keys, n = [*groups, *order], spec.states
    laid = stretches.select(*keys, function).repartitionByRange(*(F.col(k) for k in keys)).sortWithinPartitions(*keys)

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        names, held = [], (np.zeros((0, n), np.int64), np.zeros(0, np.int64))  # each distinct group of the range, and its place in the names
        for batch in batches:
            if not batch.num_rows:
                continue
            new = np.zeros(batch.num_rows, bool)
            for g in groups:
                column = batch.column(batch.schema.get_field_index(g))
                new[1:] |= pc.not_equal(column.slice(1), column.slice(0, len(column) - 1)).to_numpy(zero_copy_only=False)
            heads = [tuple(batch.column(batch.schema.get_field_index(g))[i].as_py() for g in groups) for i in np.flatnonzero(np.append(True, new[1:])).tolist()]
            joined = bool(names) and names[-1] == heads[0]
            place = np.cumsum(new) + len(names) - joined
            names += heads[joined:]
            codes = batch.column(batch.schema.get_field_index(function)).flatten().to_numpy().reshape(-1, n)
            held = compose_runs(np.concatenate([held[0], codes]), np.concatenate([held[1], place]), n)
        part = TaskContext.get().partitionId()
        columns = [pa.array([part] * len(names), pa.int32()), *(pa.array([k[i] for k in names], types[i]) for i in range(len(groups))), pa.array(held[0].tolist(), pa.list_(pa.int64()))]
        yield pa.RecordBatch.from_arrays(columns, names=["__part", *groups, function])

    from pyspark.sql.pandas.types import to_arrow_type

    kinds = {f.name: f.dataType for f in stretches.schema}
    types = [to_arrow_type(kinds[g]) for g in groups]
    folded = laid.mapInArrow(fold, ", ".join(["__part int", *(f"{g} {kinds[g].simpleString()}" for g in groups), f"{function} array<bigint>"]))
    out: dict[tuple, list[int]] = {}
    for row in sorted(folded.collect(), key=lambda r: r["__part"]):
        key = tuple(row[g] for g in groups)
        own = list(row[function])
        out[key] = then(out[key], own, spec) if key in out else own
    return out


def simulate(trace: DataFrame, spec: PredictorSpec, groups: list[str], order: list[str]) -> dict[tuple, list[int]]:
    """Function of each group of ``trace(.., taken)`` in the order of ``order``: every outcome is a stretch of its own."""
    one = F.array(*(_step_column(F.lit(s).cast("bigint"), F.col("taken"), spec) for s in range(spec.states)))
    return compose_ordered(trace.select(*groups, *order, one.alias("f")), groups, order, spec)


def _per_group(trace: DataFrame, groups: list[str], order: list[str]) -> DataFrame:
    """``(groups, evaluations, taken, from_0, from_1)``: misses of the last-outcome predictor from either start state."""
    kinds = {f.name: f.dataType.simpleString() for f in trace.schema}
    f = simulate(trace, one_bit(), groups, order)
    rows = [(*key, codes[0] // 2, codes[1] // 2) for key, codes in f.items()]  # a row a group
    misses = trace.sparkSession.createDataFrame(rows, ", ".join([*(f"{g} {kinds[g]}" for g in groups), "from_0 bigint", "from_1 bigint"]))
    counts = trace.groupBy(*groups).agg(F.count("*").alias("evaluations"), F.sum(F.col("taken").cast("bigint")).alias("taken"))
    return counts.join(misses, groups)


def one_bit_misses(trace: DataFrame, groups: list[str], order: list[str], start: bool = False) -> DataFrame:
    """``(groups, evaluations, taken, mispredictions)`` of the last-outcome predictor; no window over a group."""
    return _per_group(trace, groups, order).select(*groups, "evaluations", "taken", F.col(f"from_{int(start)}").alias("mispredictions"))


def nested_loop_misses(degrees: DataFrame, order: str, spec: PredictorSpec | None = None, trips: str = "degree") -> int:
    """Exact misses of an inner loop that runs ``trips`` times for each row, rows by ``order``."""
    spec = spec or two_bit()
    rows = degrees.select(F.lit(0).alias("all"), order, loop_transfer(F.col(trips), spec).alias("f"))
    f = compose_ordered(rows, ["all"], [order], spec).get((0,), identity(spec))
    return f[spec.start] // spec.states


# --- analysis --------------------------------------------------------------------------


def miss_rate_two_bit(p: float) -> float:
    """Stationary miss rate of the two-bit counter on independent outcomes taken with probability ``p``."""
    q = 1 - p
    return p * q / (p * p + q * q)


def steady_state_miss_rate(p: Column, bits: int = 2) -> Column:
    q = F.lit(1.0) - p
    return p * q / (p * p + q * q) if bits == 2 else 2 * p * q


def miss_rates(shares: DataFrame) -> DataFrame:
    """``shares`` with a column ``p``, and the stationary miss rates ``one_bit`` and ``two_bit`` at each."""
    return shares.withColumn("one_bit", steady_state_miss_rate(F.col("p"), 1)).withColumn("two_bit", steady_state_miss_rate(F.col("p"), 2))


def steady_state_rates(spark: SparkSession, steps: int = 20) -> DataFrame:
    """``(p, one_bit, two_bit)`` for p = 0, 1/steps, .., 1."""
    found = miss_rates(spark.range(steps + 1).select((F.col("id") / F.lit(float(steps))).alias("p")))
    return found.select(*(F.round(c, 6).alias(c) for c in ("p", "one_bit", "two_bit")))


def loop_table(spark: SparkSession, most_trips: int = 8, repeats: int = 6, spec: PredictorSpec | None = None, trips: DataFrame | None = None) -> DataFrame:
    """``(trips, start, repeats, end_state, mispredictions)``: a counted loop run 1..repeats times from each state; ``trips(trips)`` instead of 0..most_trips."""
    spec = spec or two_bit()
    n = spec.states
    counted = spark.range(most_trips + 1).select(F.col("id").alias("trips")) if trips is None else trips.select("trips").distinct()
    runs = counted.select("trips", F.explode(F.array(*(F.lit(s).cast("bigint") for s in range(n)))).alias("start")).select("trips", "start", F.explode(F.sequence(F.lit(1).cast("bigint"), F.lit(repeats).cast("bigint"))).alias("repeats"))
    body = F.concat(F.array_repeat(F.lit(True), F.col("trips").cast("int")), F.array(F.lit(False)))
    outcomes = F.flatten(F.array_repeat(body, F.col("repeats").cast("int")))
    code = F.aggregate(outcomes, F.col("start"), lambda c, x: _step_column(c, x, spec))
    return runs.withColumn("code", code).select("trips", "start", "repeats", (F.col("code") % n).alias("end_state"), F.floor(F.col("code") / n).cast("bigint").alias("mispredictions"))


def check_loop_lemmas(spark: SparkSession, most_trips: int = 8, repeats: int = 6, trips: DataFrame | None = None) -> DataFrame:
    """``(lemma, cases, violations)`` of the claims about counted loops under the two-bit counter.

    The claim about one-trip loops is checked from the states that a loop can leave behind;
    its counter-example from strongly taken has a row of its own.
    """
    t = loop_table(spark, most_trips, repeats, trips=trips)
    once, n, m, k = F.col("repeats") == 1, F.col("trips"), F.col("mispredictions"), F.col("repeats")
    claims = [
        ("three or more trips end weakly taken", once & (n >= 3), F.col("end_state") == 2),
        ("three or more trips miss 1 to 3", once & (n >= 3), m.between(1, 3)),
        ("k repeats of three or more trips miss at most k + 2", (k >= 2) & (n >= 3), m <= k + 2),
        ("k repeats of three or more trips miss at least k", (k >= 2) & (n >= 3), m >= k),
        ("no trip misses at most once", once & (n == 0), m <= 1),
        ("no trip moves one state down", once & (n == 0), F.col("end_state") == F.greatest(F.lit(0), F.col("start") - 1)),
        ("one trip misses once or twice", once & (n == 1), m.between(1, 2)),
        ("one trip returns to a state that a loop can leave", once & (n == 1) & (F.col("start") < 3), F.col("end_state") == F.col("start")),
        ("one trip from strongly taken ends weakly taken", once & (n == 1) & (F.col("start") == 3), F.col("end_state") == 2),
        ("two trips end weakly taken or weakly not taken", once & (n == 2), F.col("end_state").isin(1, 2)),
        ("two trips miss 1 to 3", once & (n == 2), m.between(1, 3)),
    ]
    out = None
    for lemma, which, holds in claims:
        row = t.where(which).agg(F.lit(lemma).alias("lemma"), F.count("*").alias("cases"), F.sum((~holds).cast("bigint")).alias("violations"))
        out = row if out is None else out.unionByName(row)
    return out


def site_predictability(trace: DataFrame, groups: list[str], order: list[str]) -> DataFrame:
    """Per group: evaluations, share taken, entropy in bits, number and mean length of runs of equal outcomes.

    Runs are the changes between neighbours and one: what the last-outcome predictor misses
    from the better start.
    """
    x = F.col("taken") / F.col("evaluations")
    entropy = -(x * F.log2(F.greatest(x, F.lit(1e-300))) + (1 - x) * F.log2(F.greatest(1 - x, F.lit(1e-300))))
    found = _per_group(trace, groups, order).withColumn("runs", F.least("from_0", "from_1") + 1)
    return found.select(*groups, "evaluations", F.round(x, 6).alias("taken_rate"), F.round(entropy, 6).alias("entropy"), "runs", F.round(F.col("evaluations") / F.col("runs"), 6).alias("mean_run"))
