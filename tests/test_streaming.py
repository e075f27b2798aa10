import datetime as dt

from forkline.graph import graph_of
from forkline.operators.components import components_unconditional
from forkline.streaming import edges as st


def test_components_over_micro_batches(spark, tmp_path):
    start = dt.datetime(2024, 1, 1)
    rows = [(i, start + dt.timedelta(minutes=37 * i), i % 7, "view", 1.0, "{}") for i in range(60)]
    frame = spark.createDataFrame(rows, st.EVENTS)
    for k in range(3):
        frame.where(f"event_id % 3 = {k}").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    query, state = st.stream_components(st.edge_stream(spark, str(tmp_path / "in")), str(tmp_path / "state"), str(tmp_path / "ck"))
    query.awaitTermination()
    hours = frame.selectExpr("user_id * 2 AS a", "timestampdiff(HOUR, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts) * 2 + 1 AS b")
    want = components_unconditional(graph_of(hours, "all")).labels
    assert state.labels().exceptAll(want).count() == 0 and want.exceptAll(state.labels()).count() == 0


def test_windows_and_time_join(spark, tmp_path):
    start = dt.datetime(2024, 1, 1)
    rows = [(i, start + dt.timedelta(minutes=m), u, "view", 1.0, "{}") for i, (m, u) in enumerate([(0, 1), (1, 2), (5, 3), (6, 1), (1500, 4)])]
    frame = spark.createDataFrame(rows, st.EVENTS)
    assert sorted(map(tuple, st.event_pairs(frame, 2).collect())) == [(1, 2), (1, 3)]
    got = {r["day"]: (r["vertices"], r["components"]) for r in st.windowed_components(frame.select("event_id", "user_id", "ts")).collect()}
    assert got == {"2024-01-01": (4, 1), "2024-01-02": (2, 1)}
    assert {r["event_id"]: r["previous_id"] for r in st.previous_event(frame).collect()}[3] == 0
    frame.coalesce(1).write.parquet(str(tmp_path / "in"))
    counts = st.window_counts(st.edge_stream(spark, str(tmp_path / "in")), "1 hour", "1 minute")
    query = counts.writeStream.format("memory").queryName("w").outputMode("append").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    query.awaitTermination()
    assert [r["edges"] for r in spark.sql("SELECT edges FROM w ORDER BY start").collect()][:1] == [4]


def test_state_survives_a_restart_and_a_batch_that_runs_again(spark, tmp_path):
    batch = lambda pairs: spark.createDataFrame(pairs, "src bigint, dst bigint")
    as_dict = lambda s: {r["id"]: r["component"] for r in s.labels().collect()}
    first = st.ComponentState(spark, f"file://{tmp_path}/state")
    assert first.last() is None
    first.update(batch([(1, 2), (2, 3)]), 0)
    again = st.ComponentState(spark, f"file://{tmp_path}/state")  # after a restart
    again.update(batch([(3, 4), (8, 9)]), 1)
    assert as_dict(again) == {1: 1, 2: 1, 3: 1, 4: 1, 8: 8, 9: 8}
    again.update(batch([(9, 4)]), 2)
    again.update(batch([(3, 4), (8, 9)]), 1)  # a late rerun reads batch 0, and replaces batch 1 alone
    assert set(as_dict(again).values()) == {1}
    (tmp_path / "state/labels/batch=2/_SUCCESS").unlink()  # never finished
    assert again.last() == 1 and as_dict(again)[9] == 8
