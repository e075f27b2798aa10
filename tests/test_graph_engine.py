import random

import pytest
from pyspark.sql import functions as F

from forkline import graph as gr
from forkline.operators import bfs, components, verify
from forkline.operators.components import SwitchPolicy

WANT = {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 6: 1, 7: 7, 8: 7, 9: 7, 10: 10}
RUNS = {
    "unconditional": components.components_unconditional,
    "mask": lambda g: components.components_unconditional(g, select_style="mask"),
    "case": lambda g: components.components_unconditional(g, select_style="case"),
    "conditional": components.components_conditional,
    "delta": lambda g: components.components_conditional(g, scan="delta"),
    "shortcut": lambda g: components.components_unconditional(g, shortcut=True),
    "delta shortcut": lambda g: components.components_conditional(g, scan="delta", shortcut=True),
    "hybrid": lambda g: components.components_hybrid(g, SwitchPolicy.at_iteration(1)),
    "blocked": lambda g: components.components_blocked(g, 2),
}


def as_dict(labels):
    return {r["id"]: r["component"] for r in labels.collect()}


@pytest.mark.parametrize("name", RUNS)
def test_components_of_the_hand_fixture(fx, name):
    assert as_dict(RUNS[name](fx).labels) == WANT


def test_sweeps_of_both_disciplines(spark, fx):
    a, b = components.components_unconditional(fx), components.components_conditional(fx, scan="delta")
    assert [s.changed for s in a.sweeps] == [s.changed for s in b.sweeps]
    assert [s.written for s in a.sweeps] == [10] * 4
    assert [s.written for s in b.sweeps] == [s.changed for s in a.sweeps]
    assert len(components.components_unconditional(fx, shortcut=True).sweeps) <= 4
    assert a.sweep_frame(spark).count() == 4


def test_labels_after_a_sweep(fx):
    assert as_dict(components.labels_after(fx, 1)) == {1: 1, 2: 1, 3: 2, 4: 3, 5: 1, 6: 4, 7: 7, 8: 7, 9: 7, 10: 10}


def test_plan_of_the_unconditional_sweep_has_no_test(fx):
    plan = components.sweep_unconditional(fx.edges, components.init_labels(fx))._jdf.queryExecution().optimizedPlan().toString()
    assert "LeftAnti" not in plan
    assert not [line for line in plan.splitlines() if "Filter" in line and "component" in line and "<" in line]


def test_sequential_reference(fx):
    rows = components.sequential_reference(fx).collect()
    assert {r["id"]: r["component"] for r in rows} == WANT and {r["sweeps"] for r in rows} == {2} and {r["stores"] for r in rows} == {7}


@pytest.mark.parametrize(("shape", "n", "sweeps"), [("star", 9, 2), ("path", 6, 6), ("cycle", 8, 5), ("clique", 5, 2)])
def test_sweeps_of_known_shapes(spark, shape, n, sweeps):
    pairs = {
        "star": [(0, i) for i in range(1, n)],
        "path": [(i, i + 1) for i in range(n - 1)],
        "cycle": [(i, (i + 1) % n) for i in range(n)],
        "clique": [(i, j) for i in range(n) for j in range(i)],
    }[shape]
    g = gr.graph_of(spark.createDataFrame(pairs, "a bigint, b bigint"), shape)
    assert len(components.components_unconditional(g).sweeps) == sweeps


def test_empty_and_lone_graphs(spark):
    none = gr.graph_of(spark.createDataFrame([], "a bigint, b bigint"), "empty")
    assert components.components_unconditional(none).labels.count() == 0
    assert components.components_conditional(none).labels.count() == 0
    lone = gr.graph_of(spark.createDataFrame([], "a bigint, b bigint"), "lone", vertices=spark.range(5, 6))
    assert as_dict(components.components_hybrid(lone).labels) == {5: 5}
    assert bfs.bfs_conditional(lone).distances.collect() == [(5, 0)]
    with pytest.raises(ValueError, match="root"):
        bfs.pick_root(none)


def test_normalise_drops_loops_repeats_and_nulls(spark):
    g = gr.graph_of(spark.createDataFrame([(1, 1), (1, 2), (2, 1), (None, 3), (2, 3)], "a bigint, b bigint"), "n")
    assert sorted(map(tuple, g.edges.collect())) == [(1, 2), (2, 1), (2, 3), (3, 2)]
    assert gr.check(g).count() == 0
    assert gr.check(gr.Graph(spark.createDataFrame([(1, 2), (1, 2), (3, 3)], "src bigint, dst bigint"), spark.range(1, 3))).count() == 4


@pytest.mark.parametrize("seed", [1, 2])
def test_random_graphs_satisfy_the_checks(spark, seed):
    rnd = random.Random(seed)
    pairs = [(rnd.randrange(40), rnd.randrange(40)) for _ in range(35)]
    g = gr.prepare(gr.graph_of(spark.createDataFrame(pairs, "a bigint, b bigint"), "random"))
    labels = components.components_hybrid(g).labels
    assert verify.verify_components(g, labels).count() == 0
    assert verify.label_diff(labels, components.components_conditional(g).labels).count() == 0
    root = bfs.pick_root(g, "max_degree")
    for run in (bfs.bfs_conditional(g, root), bfs.bfs_unconditional(g, root), bfs.bfs_hybrid(g, root, 1)):
        assert verify.verify_distances(g, root, run.distances).count() == 0


def test_search_of_the_hand_fixture(spark, fx):
    want = {1: 0, 2: 1, 5: 1, 3: 2, 6: 2, 4: 3}
    for run in (bfs.bfs_conditional(fx, 1), bfs.bfs_unconditional(fx, 1), bfs.bfs_unconditional(fx, 1, select_style="mask"), bfs.bfs_hybrid(fx, 1, 2)):
        assert {r["id"]: r["dist"] for r in run.distances.collect()} == want
    assert bfs.bfs_unconditional(fx, 1, include_unreached=True).distances.where("dist IS NULL").count() == 4
    order = [(r["id"], r["parent"]) for r in bfs.queue_order(fx, 1).orderBy("rank").collect()]
    assert order == [(1, None), (2, 1), (5, 1), (3, 2), (6, 5), (4, 3)]
    assert bfs.reach_stats(fx, bfs.bfs_conditional(fx, 1).distances).first() == (6, 12, 4)
    assert bfs.eccentricity(fx, 1) == 3 and bfs.diameter_lower_bound(fx, 2) == 3
    with pytest.raises(ValueError, match="root"):
        bfs.bfs_conditional(fx, 99)


def test_betweenness_against_enumeration(spark):
    g = gr.graph_of(spark.createDataFrame([(0, 1), (0, 2), (1, 3), (2, 3), (3, 4)], "a bigint, b bigint"), "b")
    got = {r["id"]: round(r["betweenness"], 6) for r in bfs.betweenness_sampled(g, [0, 1, 2, 3, 4]).collect()}
    assert got == {0: 1.0, 1: 2.0, 2: 2.0, 3: 7.0, 4: 0.0}


def test_adjacency_chunks_and_ranks(spark, fx):
    chunks = gr.adjacency(fx, hub_chunk=1).groupBy("src").agg(F.count("*").alias("n"), F.max("degree").alias("d")).collect()
    assert all(r["n"] == r["d"] for r in chunks)
    ids = gr.dense_ids(spark.createDataFrame([("b",), ("a",), (None,), ("b",), ("c",)], "k string"), "k")
    assert {r["k"]: r["id"] for r in ids.collect()} == {"a": 0, "b": 1, "c": 2}


def test_edge_files_round_trip(spark, tmp_path):
    from forkline.sources import tables

    (tmp_path / "e.txt").write_text("# c\n1 2\n2\t3\n")
    assert sorted(map(tuple, tables.read_edge_list(spark, str(tmp_path / "e.txt")).collect())) == [(1, 2), (2, 3)]
    (tmp_path / "g.graph").write_text("% c\n3 2\n2\n1 3\n2\n")
    assert sorted(map(tuple, tables.read_adjacency_text(spark, str(tmp_path / "g.graph")).collect())) == [(1, 2), (2, 1), (2, 3), (3, 2)]
    edges = spark.createDataFrame([(1, 2)], "src bigint, dst bigint")
    for fmt in ("json", "orc", "csv", "parquet"):
        tables.write(edges, str(tmp_path / fmt), fmt)
        assert tables.read_edges(spark, str(tmp_path / fmt), fmt).collect() == [(1, 2)]


def test_sql_surface(spark, fx):
    from forkline import sqlapi

    assert as_dict(sqlapi.components_recursive(fx, 4)) == WANT
    sqlapi.register_functions(spark)
    assert spark.sql("SELECT miss_rate_two_bit(0.5D) AS a, miss_rate_one_bit(0.5D) AS b").first() == (0.5, 0.5)
    pairs = spark.createDataFrame([(1, 2, 0.5), (1, 3, 0.5), (1, 4, 0.9), (2, 1, 0.1)], "a bigint, b bigint, weight double")
    assert sorted((r["a"], r["b"]) for r in sqlapi.knn_edges(pairs, 2).collect()) == [(1, 2), (1, 4), (2, 1)]
    trace = spark.createDataFrame([(v, k, True) for v in range(50) for k in range(3)], "seq_hi bigint, seq_lo bigint, taken boolean")
    kept = sqlapi.sample_trace(trace, 0.5).groupBy("seq_hi").count()
    assert 0 < kept.count() < 50 and kept.where("count <> 3").count() == 0


@pytest.mark.parametrize("seed", [3, 4])
def test_in_place_sweeps_equal_the_sequential_walk(spark, seed):
    rnd = random.Random(seed)
    pairs = [(rnd.randrange(60), rnd.randrange(60)) for _ in range(70)]
    g = gr.prepare(gr.graph_of(spark.createDataFrame(pairs, "a bigint, b bigint"), "random", vertices=spark.range(55, 62)))
    run = components.components_in_place(g)
    walked = components.sequential_reference(g).collect()
    assert as_dict(run.labels) == {r["id"]: r["component"] for r in walked}
    assert {len(run.sweeps)} == {r["sweeps"] for r in walked}
    assert run.before_and_after(spark).where("iteration = 1 AND before <> id").count() == 0
    left = {r["iteration"]: r["labels"] for r in components.distinct_labels(run, spark).collect()}
    assert left[len(run.sweeps)] == len({r["component"] for r in walked})


def test_unrolled_sweeps_are_told_one_by_one(spark):
    path = gr.prepare(gr.graph_of(spark.createDataFrame([(i, i + 1) for i in range(20)], "a bigint, b bigint"), "path"))
    whole, kept = components.components_unconditional(path), components.components_unconditional(path, keep_history=True)
    assert [(s.changed, s.written) for s in whole.sweeps] == [(s.changed, s.written) for s in kept.sweeps]
    assert len(whole.sweeps) == 21 and as_dict(whole.labels) == as_dict(kept.labels)
    for k in (0, 1, 5, 9):
        assert as_dict(components.labels_after(path, k)) == {i: max(0, i - k) for i in range(21)}


def test_blocks_follow_the_number_of_edges(spark, monkeypatch):
    monkeypatch.setattr(components, "BLOCK_EDGES", 3)
    path = gr.graph_of(spark.createDataFrame([(i, i + 1) for i in range(30)], "a bigint, b bigint"), "path", vertices=spark.range(40, 42))
    run = components.components_blocked(path)
    assert as_dict(run.labels) == {i: 0 for i in range(31)} | {40: 40, 41: 41}
    assert len(run.sweeps) < 31
