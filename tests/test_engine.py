"""Routing, matching and streams on small tables with known answers."""

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from geoherald.functions.expr import matches, parse_simple, tokens
from geoherald.functions.geometry import Grid, inside
from geoherald.operators import load, matching, routing
from geoherald.operators.assignment import Assignment, Leaf, whole_world
from geoherald.operators.measures import queued
from geoherald.plans import catalog
from geoherald.sources.shared import settle
from geoherald.streaming import engine

GRID = Grid(4, 1)
SUBS = "sub_id long, owner long, dnf array<array<string>>, x0 long, x1 long, y0 long, y1 long"


@pytest.fixture(scope="module")
def scene(spark):
    objects = spark.createDataFrame([(1, 1, 1, ["a", "b"]), (2, 0, 3, ["a"]), (3, 3, 0, ["b", "c"]), (4, 3, 3, ["a", "d"])], "obj_id long, x long, y long, terms array<string>")
    subs = spark.createDataFrame([(1, 7, [["a", "b"]], 0, 1, 0, 3), (2, 8, [["b"], ["c"]], 1, 3, 0, 1)], SUBS)
    return settle(objects, "objects"), settle(subs, "subs")


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_worked_example(spark, scene):
    objects, subs = scene
    assignment = Assignment(GRID, 2, [Leaf(0, 0, 2, 1, [0]), Leaf(0, 1, 2, 2, [1])])
    assignment.check()
    parts = matching.run(objects, subs, assignment)
    assert rows(parts["routed_subs"].select("sub_id", "worker", "cell", "term")) == [(1, 0, 0, "b"), (1, 1, 2, "b"), (2, 0, 0, "b"), (2, 0, 0, "c"), (2, 0, 1, "b"), (2, 0, 1, "c")]
    assert rows(parts["routed_objects"].select("obj_id", "worker")) == [(1, 0), (3, 0)]
    assert rows(parts["matches"]) == [(1, 1), (2, 1), (2, 3)]
    assert parts["pairs"].filter("sub_id = 2 and obj_id = 3").count() == 2
    loads = load.worker_load(parts["routed_objects"], parts["routed_subs"], 2)
    assert rows(loads.select("worker", "load")) == [(0, 8.0), (1, 1.0)]
    assert load.balance(loads).first()["ratio"] == 8.0
    assert rows(routing.dropped_objects(objects, parts["routed_objects"]).select("obj_id")) == [(2,), (4,)]


def test_all_ways_agree(spark, scene):
    objects, subs = scene
    want = rows(matching.match_nested_loop(objects, subs))
    text = whole_world(GRID, 3, [0, 1, 2], {"a": 0, "b": 1, "c": 2})
    for got in (
        matching.match_single(objects, subs, GRID),
        matching.match_fast(objects, subs, GRID),
        matching.match_inverted_only(objects, subs),
        matching.match_grid_only(objects, subs, GRID),
        matching.run(objects, subs, text)["matches"],
        matching.run(objects, subs, text, drop_unmatched=False)["matches"],
    ):
        assert rows(got) == want


def test_borders_and_odd_rows(spark):
    objects = spark.createDataFrame([(1, 2, 2, ["a"]), (2, 3, 3, []), (3, 9, -5, ["a", "a"])], "obj_id long, x long, y long, terms array<string>")
    subs = spark.createDataFrame([(1, 1, [["a"]], 2, 9, -9, 2), (2, 1, [["never"]], 0, 9, 0, 9)], SUBS)
    assert rows(matching.match_fast(objects, subs, GRID)) == [(1, 1), (1, 3)] == rows(matching.match_nested_loop(objects, subs))


def test_expressions(spark):
    df = spark.createDataFrame([("x AND y or z",), ("a",)], "e string").select(parse_simple(F.col("e")).alias("dnf"))
    assert [r.dnf for r in df.collect()] == [[["x", "y"], ["z"]], [["a"]]]
    one = spark.createDataFrame([(["a", "b"], [["b", "c"], ["a"]])], "t array<string>, d array<array<string>>")
    assert one.select(matches(F.col("t"), F.col("d"))).first()[0]
    assert spark.range(1).select(tokens(F.lit("Été, x ab12cd!"))).first()[0] == ["été", "ab", "cd"]
    assert spark.range(1).select(tokens(F.lit(None).cast("string"))).first()[0] == []
    assert spark.range(1).select(inside(*[F.lit(v) for v in (1, 1, 1, 1, 2, 2)])).first()[0]


def test_lazy_and_eager_deletion_agree(spark, scene):
    objects, subs = scene
    parts = matching.run(objects, subs, whole_world(GRID, 1))
    gone = subs.filter("sub_id = 2")
    dead = matching.cancel(None, gone)
    lazy = matching.merge(matching.match(objects, parts["routed_objects"], parts["index"], GRID, dead))
    eager = matching.merge(matching.match(objects, parts["routed_objects"], matching.cancel_eager(parts["index"], gone), GRID))
    assert rows(lazy) == rows(eager) == [(1, 1)]
    touched = spark.createDataFrame([(c, t) for c in range(4) for t in "abc"], "cell int, term string")
    index, left = matching.purge(parts["index"], dead, touched)
    assert index.filter("sub_id = 2").isEmpty() and left.isEmpty()


def test_live_map_is_kept_up(spark, scene):
    objects, subs = scene
    routed = routing.route_subs(subs, whole_world(GRID, 1), routing.term_freq(objects))
    live = routing.live_map(routed)
    back = routing.maintained(live, routed.limit(0), routed.filter("sub_id = 2"))
    assert rows(back.select("cell", "term", "n_live")) == [(0, "b", 1), (2, "b", 1)]


def test_cosine(spark):
    o = spark.createDataFrame([(0, "x"), (0, "x"), (0, "y"), (1, "x")], "g int, term string")
    q = spark.createDataFrame([(0, "x")], "g int, term string")
    assert [round(r.sim, 6) for r in load.cosine(o, q, "g").orderBy("g").collect()] == [0.894427, 0.0]


def test_queue_delays(spark):
    t = spark.createDataFrame([(0, 1, 0.0), (0, 2, 1.0), (0, 3, 100.0)], "worker int, seq long, arrive_ms double")
    assert [r.ms for r in queued(t, F.lit(10.0)).orderBy("seq").collect()] == [10.0, 19.0, 10.0]


@pytest.mark.parametrize("slices", [1, 4])
def test_stream_equals_batch(spark, tmp_path, slices):
    objects, subs = catalog._timed(spark, "/root/testdata/sf0.001")
    assignment, freq = catalog.planned("kdtree", objects, subs, catalog.GRID, 4)
    want = rows(matching.run(objects, subs, assignment, freq)["matches"])
    engine.write_slices(engine.as_tuples(objects, subs), str(tmp_path / "t"), slices)
    state = engine.Replay(spark, assignment, freq, str(tmp_path))
    engine.replay(engine.source(spark, str(tmp_path / "t")), state, str(tmp_path / "c"))
    assert rows(state.matches()) == want
    again = engine.Replay(spark, assignment, freq, str(tmp_path))
    engine.replay(engine.source(spark, str(tmp_path / "t")), again, str(tmp_path / "c"))
    assert rows(again.matches()) == want


def test_keyed_state_equals_batch(spark, tmp_path, scene):
    objects, subs = scene
    objects = objects.withColumn("seq", F.col("obj_id") * 10)
    subs = subs.withColumn("reg_seq", F.col("sub_id") - 100).withColumn("cancel_seq", F.when(F.col("sub_id") == 1, 5).cast("long"))
    engine.write_slices(engine.as_tuples(objects, subs), str(tmp_path / "t"), 1)
    assignment, freq = whole_world(GRID, 1), routing.term_freq(objects)
    out = engine.stateful(engine.source(spark, str(tmp_path / "t")), assignment, freq)
    query = out.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination()
    assert rows(spark.read.parquet(str(tmp_path / "out")).distinct()) == rows(matching.run(objects, subs, assignment, freq)["matches"])


def same(spark, name, folder="/root/testdata/sf0.001"):
    con = duckdb.connect()
    for t in ("region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations").split():
        con.execute(f"create view {t} as select * from '{folder}/{t}.parquet'")
    got = catalog.queries()[name](spark, folder)
    names = sorted(got.columns)
    want = con.execute(catalog.oracle_sql()[name]).fetchall()
    order = [c[0] for c in con.description]
    assert sorted(order) == names
    plain = lambda v: tuple(map(plain, v)) if isinstance(v, list) else round(v, 6) if isinstance(v, float) else v
    a = sorted((repr(tuple(plain(r[n]) for n in names)) for r in got.collect()))
    b = sorted((repr(tuple(plain(r[order.index(n)]) for n in names)) for r in want))
    assert a == b


@pytest.mark.parametrize("name", ["wide_objects", "subs_q3", "match_hybrid_q3", "match_hypergraph_q2", "match_rtree_q1", "cell_load", "select_ratio_greedy", "select_random", "sql_matches", "averaged_cell_subs", "live_counts"])
def test_against_sql(spark, name):
    same(spark, name)


def test_plans(spark):
    objects, subs = catalog.workload(spark, "/root/testdata/sf0.001", "Q1")
    plan = matching.match_fast(objects, subs, catalog.GRID)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan and "Python" not in plan


def test_entry(spark):
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
    assert __spark_entry__.entry(spark).columns == ["sub_id", "obj_id"]
