"""Global adjustment, dual routing, windows, merger and interval join of streams."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from geoherald.functions.geometry import Grid
from geoherald.operators import adjust, matching, routing
from geoherald.operators.assignment import Assignment, Leaf, whole_world
from geoherald.operators.sample import Sample, take_sample
from geoherald.plans import experiments
from geoherald.sources.shared import settle
from geoherald.streaming import engine

GRID = Grid(4, 1)
SUBS = "sub_id long, owner long, dnf array<array<string>>, x0 long, x1 long, y0 long, y1 long, reg_seq long, cancel_seq long"


@pytest.fixture(scope="module")
def scene(spark):
    objects = spark.createDataFrame([(k, k % 4, k // 4 % 4, ["a", "b"] if k % 2 else ["b", "c"], 10 * k) for k in range(16)], "obj_id long, x long, y long, terms array<string>, seq long")
    subs = spark.createDataFrame([(k, 1, [["a"]] if k % 2 else [["b", "c"], ["a"]], 0, k % 4, 0, 3, 20 * k, 20 * k + 100 if k % 3 == 0 else None) for k in range(6)], SUBS)
    return settle(objects, "objects"), settle(subs, "subs")


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_two_versions_deliver_the_same(spark, scene):
    objects, subs = scene
    freq = routing.term_freq(objects)
    halves = Assignment(GRID, 2, [Leaf(0, 0, 2, 1, [0]), Leaf(0, 1, 2, 2, [1])])
    words = whole_world(GRID, 2, [0, 1], {"a": 0, "b": 1, "c": 1})
    want = rows(matching.run(objects, subs, whole_world(GRID, 1), freq)["matches"])
    dual = adjust.DualRouting(halves, words, 50, freq)
    assert rows(dual.run(objects, subs)) == want
    assert dual.retire(subs, 1000, 0) is dual
    assert rows(dual.retire(subs, 1000, 10).run(objects, subs)) == want


def test_sample_and_new_partition(scene):
    objects, subs = scene
    sample = take_sample(objects, subs, GRID, n_objects=8, n_subs=4)
    assert len(sample.objects) == 8 and len(sample.subs) == 4
    assert sample == take_sample(objects, subs, GRID, n_objects=8, n_subs=4)
    assert adjust.needs_repartition(sample, whole_world(GRID, 1), 1, gain=0.1) is None
    # everything at both workers by text, where space would do
    apart = Sample(Grid(16, 2), [(k % 4, k // 4 % 4, frozenset("ab")) for k in range(64)], [(k % 4, k % 4, k // 4 % 4, k // 4 % 4, frozenset("ab"), ("a", "b")) for k in range(32)])
    fresh = adjust.needs_repartition(apart, whole_world(Grid(16, 2), 2, [0, 1], {"a": 0, "b": 1}), 2)
    assert fresh is not None and fresh.version == 1


def test_move_of_cells_keeps_matches(spark, scene):
    objects, subs = scene
    halves = Assignment(GRID, 2, [Leaf(0, 0, 2, 1, [0]), Leaf(0, 1, 2, 2, [1])])
    parts = matching.run(objects, subs, halves)
    index = adjust.apply(parts["index"], (0, 1), 0, 1)
    assert {r.worker for r in index.select("worker").distinct().collect()} == {1}
    routed = routing.route_objects(objects, routing.live_map(index), GRID)
    assert rows(matching.merge(matching.match(objects, routed, index, GRID))) == rows(parts["matches"])


def drained(query_of, path, tmp_path):
    query = query_of.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination()


def slices(spark, tmp_path, schema, *batches):
    for batch in batches:
        spark.createDataFrame(batch, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))


def at(minutes):
    return dt.datetime(2024, 1, 1) + dt.timedelta(minutes=minutes)


def test_merger_on_a_stream(spark, tmp_path):
    stream = slices(spark, tmp_path, "sub_id long, obj_id long, ts timestamp", [(1, 1, at(0)), (1, 1, at(0))], [(1, 1, at(1)), (2, 1, at(1))], [(3, 3, at(90))])
    drained(engine.merged_stream(stream), None, tmp_path)
    assert rows(spark.read.parquet(str(tmp_path / "out")).select("sub_id", "obj_id")) == [(1, 1), (2, 1), (3, 3)]


def test_load_per_window(spark, tmp_path):
    stream = slices(spark, tmp_path, "op string, ts timestamp", [("obj", at(0)), ("obj", at(10)), ("reg", at(20))], [("obj", at(250))], [("obj", at(2000))])
    drained(engine.load_per_window(stream).select("window.start", "op", "n"), None, tmp_path)
    assert [(r.op, r.n) for r in spark.read.parquet(str(tmp_path / "out")).filter(F.col("start") == at(0)).orderBy("op").collect()] == [("obj", 2), ("reg", 1)]


def test_standing_by_interval_join(spark, tmp_path):
    regs = slices(spark, tmp_path / "r", "sub_id long, ts timestamp", [(1, at(0)), (2, at(0))], [(3, at(200_000))])
    cancels = slices(spark, tmp_path / "k", "sub_id long, ts timestamp", [(1, at(5))], [(9, at(200_000))])
    drained(engine.standing(regs, cancels), None, tmp_path)
    got = rows(spark.read.parquet(str(tmp_path / "out")).select("sub_id", F.col("cancel_ts").isNotNull()))
    assert (1, True) in got and (2, False) in got


def test_drift_study_counts_all_rows(spark, monkeypatch):
    """All epochs of the ids, and loads that do not depend on how many rows the sample has."""
    folder = "/root/testdata/sf0.001"
    monkeypatch.setattr(experiments, "PLANNED", 50)
    monkeypatch.setattr(experiments, "MU", 800)
    got = experiments.drift_study(spark, folder).collect()
    ids = [r.sub_id for r in experiments.subscriptions(spark, folder, "Q3").select("sub_id").collect()]
    assert sorted({r.epoch for r in got}) == sorted({k // 800 for k in ids})
    seen = experiments.object_source(spark, folder, "wide").count()
    # what 50 objects and 50 subscriptions can cost at most, by the model, on one worker
    assert seen > 50 and all(r.total > 50 * 50 + 50 + 50 for r in got)
