"""Kernels over blocks give what the runs by joins give, however a graph is cut."""

import random

import pytest

from forkline.graph import graph_of
from forkline.operators import blocks, counters
from forkline.operators.bfs import queue_order
from forkline.operators.components import components_in_place, components_unconditional
from forkline.operators.predictor import identity, loop_function, one_bit, static, two_bit

SPECS = (one_bit(), two_bit(), static(True))


def _graph(spark, n: int, m: int, seed: int, shift: int = 0):
    rnd = random.Random(seed)
    pairs = [(rnd.randrange(n) * 3 + shift * rnd.randrange(2), rnd.randrange(n) * 3 + shift * rnd.randrange(2)) for _ in range(m)] + [(i, i + 1) for i in range(n - 1, n + 6)]
    return graph_of(spark.createDataFrame(pairs, "a bigint, b bigint"), "made", vertices=spark.createDataFrame([(5,), (n * 9,)], "id bigint"))


def _rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("order", ["sync", "inplace"])
def test_blocks_equal_the_run_by_joins(spark, order, monkeypatch):
    """One block, and several that tell each other labels; isolated vertices; labels that span bigint."""
    for g in (_graph(spark, 60, 90, 3), _graph(spark, 40, 70, 4, -(1 << 61))):
        run = components_in_place(g) if order == "inplace" else components_unconditional(g, keep_history=True)
        want = _rows(counters.cc_site_stats(g, spec=SPECS, order=order, run=run))
        assert _rows(counters.cc_site_stats(g, spec=SPECS, order=order)) == want
        with monkeypatch.context() as m:
            m.setattr(blocks, "ONE_BLOCK", 10)
            m.setattr(blocks, "BLOCK_EDGES", 40)
            found = blocks.component_run(g, SPECS, order)
            assert found.changed == [s.changed for s in run.sweeps]
            assert _rows(counters.cc_site_stats(g, spec=SPECS, order=order)) == want


def test_a_vertex_larger_than_a_block_is_folded_by_pieces(spark, monkeypatch):
    g = graph_of(spark.createDataFrame([(0, i) for i in range(1, 90)], "a bigint, b bigint"), "star")
    want = _rows(counters.cc_site_stats(g))
    monkeypatch.setattr(blocks, "ONE_BLOCK", 10)
    monkeypatch.setattr(blocks, "BLOCK_EDGES", 20)
    assert blocks.component_run(g, (two_bit(),)) is None
    assert _rows(counters.cc_site_stats(g)) == want


def test_search_in_one_block_equals_the_queue_by_joins(spark):
    g = _graph(spark, 60, 90, 5)
    assert _rows(counters.bfs_site_stats(g, spec=SPECS)) == _rows(counters.bfs_site_stats(g, spec=SPECS, queue=queue_order(g)))


def test_in_place_totals_take_one_job_a_graph(spark):
    """By joins the sequential sweeps of these three graphs were some hundred jobs."""
    from forkline.plans import experiments as x

    tracker, group = spark.sparkContext.statusTracker(), "in-place-totals"
    for name in ("bulk_order_part", "part_supplier_matrix", "supplier_co_order"):
        x.graph(spark, "/root/testdata/sf0.001", name)
    spark.sparkContext.setJobGroup(group, group)
    assert x.totals_in_place(spark, "/root/testdata/sf0.001").count() == 6
    jobs = len(tracker.getJobIdsForGroup(group))
    spark.sparkContext.setJobGroup("", "")
    assert jobs < 60, jobs


def test_a_written_graph_is_made_once(spark):
    """Both orientations and the vertices come from one reading of the pairs."""
    from forkline.graph import written

    read = spark.sparkContext.accumulator(0)

    def counted(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    pairs = spark.createDataFrame([(1, 2), (2, 1), (2, 3), (4, 4)], "a bigint, b bigint").mapInArrow(counted, "a bigint, b bigint")
    g = written(graph_of(pairs, "pairs", vertices=spark.createDataFrame([(9,)], "id bigint")))
    assert read.value == 4
    assert _rows(g.edges) == [(1, 2), (2, 1), (2, 3), (3, 2)] and _rows(g.vertices) == [(1,), (2,), (3,), (9,)]


def test_pairs_go_straight_into_blocks(spark, monkeypatch):
    """Pairs are read once, with nulls, loops, and repeats in both orientations and across arrays; no edges are made of them first."""
    read = spark.sparkContext.accumulator(0)

    def counted(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    rnd = random.Random(8)
    made = [(rnd.randrange(50), rnd.randrange(50)) for _ in range(120)]
    pairs = [*made, *((b, a) for a, b in made[:40]), *made[:30], (3, None), (None, 4), (7, 7)]
    want = {(a, b) for x, y in made if x != y for a, b in ((x, y), (y, x))}
    for one_block in (10, 4_000_000):
        monkeypatch.setattr(blocks, "ONE_BLOCK", one_block)
        monkeypatch.setattr(blocks, "BLOCK_EDGES", 60)
        monkeypatch.setattr(blocks, "CHUNK_PAIRS", 9)
        read.value = 0
        g = graph_of(spark.createDataFrame(pairs, "a bigint, b bigint").mapInArrow(counted, "a bigint, b bigint"), "raw")
        found = blocks.component_run(g, SPECS)
        assert (read.value, found.n, found.adjacent) == (len(pairs), len({a for a, _ in want}), len(want))
        if one_block == 10:
            first = found
    assert found == first


def test_search_by_blocks_equals_the_search_in_one_block(spark, monkeypatch):
    """Queue order across blocks and folders; before, a graph of several blocks was searched by joins only."""
    from forkline.operators import block_search

    g = _graph(spark, 60, 90, 5)
    root = 12
    want = blocks.search_run(g, SPECS, root)
    monkeypatch.setattr(blocks, "ONE_BLOCK", 10)
    monkeypatch.setattr(blocks, "BLOCK_EDGES", 40)
    monkeypatch.setattr(blocks, "CHUNK_PAIRS", 30)
    monkeypatch.setattr(block_search, "FOLDER_PLACES", 3)
    assert len(want) > 4 and blocks.search_run(g, SPECS, root) == want
    assert blocks.search_run(g, SPECS, 5) == [blocks.LevelRun(1, 0, *(blocks._codes([c for s in SPECS for c in f(s)], SPECS) for f in (lambda s: loop_function(0, s), identity)), 0)]
