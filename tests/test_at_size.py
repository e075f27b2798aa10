"""Queries that failed on larger tables, on the smallest input that showed it."""

from forkline.graph import graph_of


def test_recursive_query_walks_a_wide_tree(spark):
    """200 leaves of one hub: walks that turn back are more rows than Spark's recursion may return."""
    from forkline import sqlapi

    limit = spark.conf.get("spark.sql.cteRecursionRowLimit")
    g = graph_of(spark.createDataFrame([(i, 1000) for i in range(200)], "a bigint, b bigint"), "wide")
    labels = {r["id"]: r["component"] for r in sqlapi.components_recursive(g, 4).collect()}
    assert labels == dict.fromkeys([*range(200), 1000], 0)
    assert spark.conf.get("spark.sql.cteRecursionRowLimit") == limit


def test_folding_of_long_traces_equals_the_walk():
    """Traces of any length, cut anywhere, under several predictors at once."""
    import random

    import numpy as np

    from forkline.operators.folding import Folding
    from forkline.operators.predictor import one_bit, saturating, static, two_bit, walk

    rnd, specs = random.Random(4), (one_bit(), two_bit(), saturating(3), static(True), static(False))
    for n in (0, 1, 7, 8, 9, 1001):
        taken, f, at = np.array([rnd.random() < 0.3 for _ in range(n)], bool), Folding(specs), 0
        while at < n:
            step = rnd.randrange(1, 90)
            f.outcomes(taken[at : at + step])
            at += step
        assert f.done() == {s: walk(taken.tolist(), s) for s in specs} and f.taken == taken.sum()
    trips = np.array([0, 5, 1, 2, 9, 0, 3])
    f = Folding(specs)
    f.loops(trips)
    assert f.done() == {s: walk([x for t in trips for x in [True] * t + [False]], s) for s in specs}


def test_ranges_meet_in_the_order_of_the_kernel(spark, monkeypatch):
    """Counters don't depend on how vertices are dealt; labels that span all of bigint are ranked, not shifted; predictors share a pass."""
    import random

    from forkline.operators import counters, folding
    from forkline.operators.predictor import one_bit, two_bit

    rnd = random.Random(8)
    pairs = [(rnd.choice([-(1 << 62), 0, 1 << 61]) + rnd.randrange(60), rnd.choice([-(1 << 62), 0, 1 << 61]) + rnd.randrange(60)) for _ in range(200)]
    g = graph_of(spark.createDataFrame(pairs, "a bigint, b bigint"), "dealt")
    rows = lambda: sorted(map(tuple, counters.cc_site_stats(g, spec=(one_bit(), two_bit())).unionByName(counters.bfs_site_stats(g, spec=(one_bit(), two_bit()))).collect()))
    whole = rows()
    assert {r[4] for r in whole} == {"1-bit", "2-bit"}
    monkeypatch.setattr(folding, "RANGE_ROWS", 60)
    assert rows() == whole


def test_queries_read_given_tables(spark):
    """Loops, rates and profiles are counted on the given tables."""
    import __spark_entry__ as entry

    for name, table in (("loop_table", "with"), ("loop_lemmas", "with"), ("profile_inventory", "with"), ("steady_state_rates", "lineitem")):
        frame = entry.queries()[name](spark, "/root/testdata/sf0.001")
        assert frame.count() and table in entry.oracle_sql()[name].lower()
    assert frame.count() == 10  # a row a supplier
    assert entry.queries()["loop_lemmas"](spark, "/root/testdata/sf0.001").where("violations > 0").count() == 0
    assert "branches" in entry.queries()["profile_inventory"](spark, "/root/testdata/sf0.001").columns


def test_inventory_writes_no_graph(spark, fx):
    """Graphs are counted as plans: nothing is written to the shared folder, and the session's settings stay."""
    from forkline import graph as gr
    from forkline.sources import tables

    key = spark.sparkContext.applicationId
    before, kept = len(tables._made.get(key, [])), spark.conf.get(tables._CLEANUP, None)
    assert [tuple(r) for r in gr.inventory([fx]).collect()] == [("fx", False, 10, 9)]
    from forkline.plans import experiments as x

    assert x.x13_inventory(spark, "/root/testdata/sf0.001", ["order_mesh"]).first()["vertices"] == 1500
    assert len(tables._made.get(key, [])) == before and spark.conf.get(tables._CLEANUP, None) == kept
