import datetime as dt

import numpy as np
import pytest

from compresslab.operators import calibrate, codecs, significance
from compresslab.sources import tables
from compresslab.sources.scratch import scratch_path
from compresslab.streaming import events as ev
from compresslab.streaming import ingest


def at(minutes):
    return dt.datetime(2024, 1, 1) + dt.timedelta(minutes=minutes)


def events(spark, rows):
    return spark.createDataFrame([(i, at(m), 1, "view", 1.0, "{}") for i, m in rows], tables.SCHEMAS["events"])


def in_files(spark, *chunks):
    path = scratch_path(spark, "late")
    for rows in chunks:
        events(spark, rows).coalesce(1).write.mode("append").parquet(path)
    return path


def test_a_row_behind_the_watermark_is_dropped_and_one_before_it_is_not(spark):
    # after the second file the newest row is at 300 minutes, so rows before 240 are late; rows are dropped from one micro-batch later on
    path = in_files(spark, [(0, 10)], [(1, 300)], [(4, 301)], [(2, 250), (3, 20)])
    out = scratch_path(spark, "windows")
    ev.drain(ev.tumbling(ev.event_stream(spark, path), late="1 hour"), out, "update")
    last = ev.by_clock(spark.read.parquet(out)).groupBy("window_start").agg({"n": "max"}).collect()
    assert {tuple(r) for r in last} == {(at(0), 1), (at(240), 1), (at(300), 2)}


def test_windows_of_a_stream_equal_those_of_the_table(spark, sf):
    e = tables.table(spark, sf, "events").selectExpr("event_id", "cast(ts as timestamp_ntz) ts", "user_id", "event_type", "value", "props")
    found = ev.over_stream(e, lambda s: ev.tumbling(s, late="2 hours"), ("window_start", "event_type"))
    assert {tuple(r) for r in found.collect()} == {tuple(r) for r in ev.tumbling(e).collect()}
    assert ev.replay_in_order(e.where("false"), 3)  # nothing to write


def test_two_streams_meet_across_files(spark):
    path = in_files(spark, [(0, 0), (1, 50)], [(2, 60), (3, 111)], [(4, 500)])
    out = scratch_path(spark, "pairs")
    ev.drain(ev.interval_stream(ev.event_stream(spark, path), ev.event_stream(spark, path), "user_id", "1 HOUR", "2 hours"), out, "append")
    found = {(r["left_id"], r["right_id"]) for r in spark.read.parquet(out).collect()}
    assert found == {(0, 1), (0, 2), (1, 2), (2, 3)}


def test_batches_may_learn_their_own_thresholds(spark, sf):
    e = tables.table(spark, sf, "embeddings")
    out = scratch_path(spark, "codes")
    ingest.encode_stream(ingest.vector_stream(spark, ingest.replay(e, 2)), codecs.binary("median"), None, out)
    rows = spark.read.parquet(out).collect()
    own = {i: calibrate.quantiles(e.where(f"vec_id % 2 = {i}"), (0.5,)).at(0.5) for i in (0, 1)}
    native = {r["vec_id"]: np.array(r["embedding"]) for r in e.collect()}
    assert len(rows) == len(native)
    assert all((np.array(r["code"]) == (native[r["vec_id"]] > own[r["vec_id"] % 2])).all() for r in rows)


def test_drift_is_none_where_batches_are_alike(spark):
    e = spark.createDataFrame([(i, [float(i // 2), 1.0], i % 2) for i in range(20)], "vec_id long, embedding array<float>, b int")
    assert {r["b"]: r["moved"] for r in ingest.drift(e, "b", method="exact").collect()} == {0: 0.0, 1: 0.0}


def test_holm_over_a_frame_equals_the_list_form(spark):
    p = [0.01, 0.04, 0.03, 0.5, 0.03]
    t = spark.createDataFrame([(f"c{i}", 1, x) for i, x in enumerate(p)] + [("c0", 2, 0.9)], "variant string, tier int, p double")
    found = {(r["variant"], r["tier"]): r["p_holm"] for r in significance.with_holm(t, ("tier",)).collect()}
    assert [found[f"c{i}", 1] for i in range(5)] == pytest.approx(significance.holm(p))
    assert found["c0", 2] == 0.9


def test_zeros_may_be_ranked_before_they_go(spark):
    pairs = spark.createDataFrame([("a", 1.0, x) for x in (1.0, 0.9, 1.2, 0.7)], "k string, base double, other double")
    ours = {z: significance.statistic(pairs, ("k",), z).first() for z in ("wilcox", "pratt")}
    assert (ours["wilcox"]["n"], ours["wilcox"]["w_plus"]) == (3, 2.0)
    assert (ours["pratt"]["n"], ours["pratt"]["w_plus"]) == (3, 3.0)


def test_options_of_codecs(spark):
    x = np.array([[3.0, 4.0, 9.0], [0.0, 0.0, 1.0]])
    none = calibrate.Calibration()
    assert codecs.truncate(2, renormalize=True).encode(x, none) == pytest.approx(np.array([[0.6, 0.8], [0.0, 0.0]]))
    big = np.array([[1e6, -1e6]])
    assert np.isinf(codecs.float_cast("fp16").encode(big, none)).all()
    assert codecs.float_cast("fp16", saturate=True).encode(big, none).tolist() == [[65504.0, -65504.0]]


def test_sources_of_every_form_and_the_registry(spark, sf):
    e = spark.createDataFrame([(1, "one"), (2, None)], "item_id long, text string")
    for form in ("parquet", "orc", "json", "csv"):
        path = scratch_path(spark, form)
        e.write.format(form).save(path)
        assert {tuple(r) for r in tables.read(spark, path, "item_id long, text string", form).collect()} == {(1, "one"), (2, None)}
    tables.register_dataset("two_rows", lambda spark, sf_dir: e)
    assert "two_rows" in tables.datasets() and tables.dataset("two_rows", spark, sf).count() == 2
    tables.register_dataset("odd", lambda spark, sf_dir: e.select("text"))
    with pytest.raises(ValueError):
        tables.dataset("odd", spark, sf)
    out = scratch_path(spark, "records")
    tables.write_metrics(e, out)
    assert spark.read.json(out).count() == 2


def test_join_hints_choose_the_strategy(spark, sf):
    from compresslab.operators import relational

    plan = relational.join_hints(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert all(x in plan for x in ("BroadcastHashJoin", "SortMergeJoin", "ShuffledHashJoin"))
    assert len({tuple(r)[:3] for r in relational.join_hints(spark, sf).collect()}) == 5
