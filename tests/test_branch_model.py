import random

import pytest
from pyspark.sql import functions as F

from forkline.operators import counters, measures, predictor
from forkline.operators.predictor import one_bit, saturating, static, two_bit


def naive(outcomes, spec):
    state, misses = spec.start, 0
    for taken in outcomes:
        state, missed = spec.step(state, taken)
        misses += missed
    return state, misses


@pytest.mark.parametrize("spec", [one_bit(), two_bit(), two_bit(3), saturating(3), static(True), static(False)])
def test_functions_compose_like_the_walk(spec):
    rnd = random.Random(5)
    for p in (0.05, 0.3, 0.5, 0.9):
        outcomes = [rnd.random() < p for _ in range(200)]
        f, i = predictor.identity(spec), 0
        while i < len(outcomes):
            j = i + rnd.randrange(1, 30)
            f, i = predictor.then(f, predictor.walk(outcomes[i:j], spec), spec), j
        state, misses = naive(outcomes, spec)
        assert f[spec.start] == misses * spec.states + state
    for n in range(9):
        state, misses = naive([True] * n + [False], spec)
        assert predictor.loop_function(n, spec)[spec.start] == misses * spec.states + state


def test_parallel_simulation(spark):
    rnd = random.Random(9)
    outcomes = [rnd.random() < 0.4 for _ in range(3000)]
    trace = spark.createDataFrame([(0, i, t) for i, t in enumerate(outcomes)], "site int, seq bigint, taken boolean").repartition(5)
    for spec in (two_bit(), one_bit(), static(True)):
        f = predictor.simulate(trace, spec, ["site"], ["seq"])[0,]
        assert f[spec.start] // spec.states == naive(outcomes, spec)[1]
    row = predictor.one_bit_misses(trace, ["site"], ["seq"]).first()
    assert row["mispredictions"] == naive(outcomes, one_bit())[1] and row["taken"] == sum(outcomes)
    assert predictor.site_predictability(trace, ["site"], ["seq"]).first()["taken_rate"] == round(sum(outcomes) / 3000, 6)


def test_loop_lemmas_hold(spark):
    assert predictor.check_loop_lemmas(spark).where("violations > 0").count() == 0
    rates = {r["p"]: r for r in predictor.steady_state_rates(spark).collect()}
    assert rates[0.5]["two_bit"] == 0.5 and rates[0.1]["two_bit"] < rates[0.1]["one_bit"]
    rnd = random.Random(3)
    long = [rnd.random() < 0.2 for _ in range(200_000)]
    assert abs(naive(long, two_bit())[1] / len(long) - predictor.miss_rate_two_bit(0.2)) < 0.005


def totals(sites):
    return {r["site"]: (r["e"], r["t"], r["m"]) for r in sites.groupBy("site").agg(F.sum("evaluations").alias("e"), F.sum("taken").alias("t"), F.sum("mispredictions").alias("m")).collect()}


def test_counters_of_the_hand_fixture(fx):
    cc = counters.cc_site_stats(fx)
    assert totals(cc) == {"cc.sweep": (5, 4, 3), "cc.vertex": (44, 40, 6), "cc.neighbor": (112, 72, 46), "cc.test": (72, 12, 13)}
    assert counters.verify_counters(fx, cc).count() == 0
    search = counters.bfs_site_stats(fx, root=1)
    assert totals(search) == {"bfs.queue": (7, 6, 3), "bfs.neighbor": (18, 12, 9), "bfs.test": (12, 5, 9)}
    both = cc.unionByName(counters.unconditional_sites(cc)).unionByName(search).unionByName(counters.unconditional_sites(search))
    samples = counters.samples_of(both).cache()
    stores = {(r["method"], r["variant"]): r["s"] for r in samples.groupBy("method", "variant").agg(F.sum("stores").alias("s")).collect()}
    assert stores == {("cc", "conditional"): 12, ("cc", "unconditional"): 40, ("bfs", "conditional"): 10, ("bfs", "unconditional"): 24}
    bound = {r["variant"]: r for r in measures.bfs_bounds(samples).collect()}
    assert bound["conditional"]["lower"] == 6 and bound["conditional"]["upper"] == 18
    growth = {r["method"]: r["growth"] for r in measures.store_growth(samples).collect()}
    assert growth == {"cc": round(40 / 12, 6), "bfs": 2.4}
    styles = {s: counters.samples_of(both, select_style=s).agg(F.sum("instructions")).first()[0] for s in ("least", "mask")}
    assert styles["mask"] > styles["least"]


def walked(g, order, labels_of):
    """Improvement tests of the sequential kernel, vertex by vertex: evaluations, taken and misses."""
    near = {r["id"]: [] for r in g.vertices.collect()}
    for r in g.edges.orderBy("src", "dst").collect():
        near[r["src"]].append(r["dst"])
    label, moved, state, missed, taken, n = {v: v for v in near}, True, 0, 0, 0, 0
    while moved:
        read = dict(label) if order == "sync" else label
        moved = False
        for v in sorted(near):
            now = label[v]
            for u in near[v]:
                hit = read[u] < now
                state, miss = two_bit().step(state, hit)
                missed, taken, n = missed + miss, taken + hit, n + 1
                now = read[u] if hit else now
            moved |= now != label[v]
            label[v] = now
    assert label == labels_of
    return n, taken, missed


@pytest.mark.parametrize("order", ["sync", "inplace"])
def test_counters_follow_the_kernel_in_either_order(spark, order, monkeypatch):
    from forkline.graph import graph_of
    from forkline.operators import trace
    from forkline.operators.components import components_unconditional

    rnd = random.Random(6)
    pairs = [(0, i) for i in range(1, 40)] + [(rnd.randrange(80), rnd.randrange(80)) for _ in range(110)]
    g = graph_of(spark.createDataFrame(pairs, "a bigint, b bigint"), "hub")
    labels = {r["id"]: r["component"] for r in components_unconditional(g).labels.collect()}
    want = walked(g, order, labels)
    assert totals(counters.cc_site_stats(g, order=order))["cc.test"] == want
    monkeypatch.setattr(counters, "JOB_MESSAGES", 1)  # a job a sweep
    for fold in ("cc_test_fold", "bfs_test_fold"):
        monkeypatch.setattr(counters, fold, lambda *a, f=getattr(trace, fold): f(*a, chunk=7))  # hubs cut in pieces
    assert totals(counters.cc_site_stats(g, order=order))["cc.test"] == want
    if order == "sync":
        search = totals(counters.bfs_site_stats(g))["bfs.test"]
        monkeypatch.undo()
        assert totals(counters.bfs_site_stats(g))["bfs.test"] == search


def test_cuts_part_the_neighbours_of_hubs_evenly(spark):
    from forkline.operators import trace

    edges = spark.createDataFrame([(0, i) for i in range(1, 1001)] + [(i, 0) for i in range(1, 1001)], "src bigint, dst bigint")
    assert trace.hub_cuts(edges) == []
    cuts = trace.hub_cuts(edges, 100)
    sizes = [r["count"] for r in edges.where("src = 0").groupBy(trace.piece_of(F.col("dst"), cuts).alias("p")).count().collect()]
    assert len(sizes) == 10 and max(sizes) <= 110


def test_measures_on_made_samples(spark):
    rows = [("g", "cc", v, i, 10, float(x)) for v, xs in (("conditional", (9, 7, 3, 1)), ("unconditional", (5, 5, 5, 5))) for i, x in enumerate(xs)]
    samples = spark.createDataFrame(rows, "graph string, method string, variant string, iteration int, edges_traversed bigint, time double")
    row = measures.crossover(samples, "time").first()
    assert (row["crossover"], row["turns"]) == (2, 1)
    assert measures.time_ratio(samples, "time").where("variant = 'conditional' AND iteration = 3").first()["ratio"] == 1.0
    assert measures.total_speedup(samples, "time").first()["speedup"] == 1.0
    assert measures.iteration_variation(samples, "time").where("variant = 'unconditional'").first()["variation"] == 0.0
    twin = samples.withColumn("branches", F.col("time") * 2).withColumn("stores", F.lit(4))
    r = {(x["row_metric"], x["col_metric"]): x["r"] for x in measures.correlation_matrix(twin, "cc", time="time", metrics=["time", "branches", "stores"]).collect()}
    assert r == {("time", "branches"): 1.0, ("time", "stores"): None, ("branches", "stores"): None}
