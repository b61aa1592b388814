"""What crosses the exchanges, who places what, and the functions around the studies."""

import os
import re
import time

import pytest
from pyspark.sql import functions as F

from geoherald.functions.expr import can_match, matches, signature
from geoherald.functions.geometry import Grid
from geoherald.operators import adjust, load, matching, measures, migrate, routing
from geoherald.operators.assignment import Assignment, Leaf, hashed_part, part_of, whole_world
from geoherald.plans import catalog, experiments, surface
from geoherald.sources import shared, tables, workload
from geoherald.sources.shared import settle
from geoherald.sources.world import wide_objects
from geoherald.streaming import engine

FOLDER = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def work(spark):
    objects, subs = catalog._timed(spark, FOLDER, "Q3")
    assignment, freq = catalog.planned("hybrid", objects, subs, catalog.GRID)
    return objects, subs, assignment, freq


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def exchanged(df, keys):
    """Columns that go through the exchanges by ``keys``."""
    text = df.sparkSession._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")
    found = re.findall(r"\(\d+\) Exchange\nInput \[\d+\]: \[(.*)\]\nArguments: hashpartitioning\((.*?), \d+\)", text)
    return [{re.sub(r"#\d+L?", "", c) for c in columns.split(", ")} for columns, by in found if set(re.findall(r"(\w+)#", by)) == set(keys)]


def test_terms_stay_behind(spark, work):
    objects, subs, assignment, freq = work
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        found = exchanged(matching.run(objects, subs, assignment, freq)["matches"], ("worker", "cell", "term"))
        assert found and not any("terms" in columns for columns in found)
        found = exchanged(matching.match_fast(objects, subs, catalog.GRID), ("cell", "term", "salt"))
        assert len(found) == 2 and not any("terms" in columns for columns in found)
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_signatures_never_lose_a_match(spark):
    data = [([f"t{k * i % 97}" for i in range(1, 9)], [[f"t{k % 97}", f"t{j % 97}"], [f"t{3 * j % 97}"]]) for k in range(1, 30) for j in range(1, 10)]
    df = spark.createDataFrame(data, "terms array<string>, dnf array<array<string>>").select("*", signature(F.col("terms")).alias("bits"), F.transform("dnf", signature).alias("masks"))
    df = df.select(matches(F.col("terms"), F.col("dnf")).alias("is"), can_match(F.col("bits"), F.col("masks")).alias("may"))
    got = df.groupBy("is", "may").count().collect()
    assert {(r["is"], r["may"]) for r in got} >= {(True, True), (False, False)} and (True, False) not in {(r["is"], r["may"]) for r in got}


def test_no_pair_crosses_an_exchange(spark, work):
    """Short texts are settled where posting and probe meet; a subscription of several lists finds an object once."""
    objects, subs, assignment, freq = work
    plain = objects.drop("seq"), subs.drop("reg_seq", "cancel_seq")
    for found in (matching.run(*plain, assignment, freq)["matches"], matching.match_fast(*plain, catalog.GRID)):
        text = found.sparkSession._jvm.PythonSQLUtils.explainString(found._jdf.queryExecution(), "formatted")
        crossing = [{re.sub(r"#\d+L?", "", c) for c in columns.split(", ")} for columns in re.findall(r"Exchange\nInput \[\d+\]: \[(.*)\]", text)]
        assert crossing and not any({"sub_id", "obj_id"} <= columns for columns in crossing)
        assert rows(found) == rows(matching.match_nested_loop(*plain))


def test_codes_settle_each_pair_once(spark, monkeypatch):
    objects = spark.createDataFrame([(1, 0, 0, ["a", "b", "c"]), (2, 0, 0, ["b"]), (3, 9, 9, ["a"])], "obj_id long, x long, y long, terms array<string>")
    dnf = [[["a"], ["b"], ["c"]], [["a", "b"], ["b", "c"]], [["a", "b"], ["a", "z"]], [["z"], ["c"]]]
    subs = spark.createDataFrame([(k, 1, d, 0, 5, 0, 5) for k, d in enumerate(dnf)], "sub_id long, owner long, dnf array<array<string>>, x0 long, x1 long, y0 long, y1 long")
    objects, subs = settle(objects, "objects"), settle(subs, "subs")
    want = [(0, 1), (0, 2), (1, 1), (2, 1), (3, 1)]
    grid = Grid(16, 1)
    assert matching.told_apart(objects, subs)
    assert rows(matching.run(objects, subs, whole_world(grid, 1))["matches"]) == rows(matching.match_fast(objects, subs, grid)) == want
    monkeypatch.setattr(matching, "CARRIED", 2)
    assert not matching.told_apart(objects, subs)
    assert rows(matching.run(objects, subs, whole_world(grid, 1))["matches"]) == rows(matching.match_fast(objects, subs, grid)) == want


def test_many_objects_meet_subscriptions_by_cell(spark, work, monkeypatch):
    """An object goes through the exchange once for its cell, not for each term; cut cells, steps and workers lose no pair and repeat none."""
    monkeypatch.setattr(matching, "GATHERED", 0)
    monkeypatch.setattr(matching, "SHARES", 5000)
    monkeypatch.setattr(matching.cellmatch, "TOGETHER", 50)
    monkeypatch.setattr(matching.cellmatch, "TABLE", 50_000)
    objects, subs, assignment, freq = work
    plain = objects.drop("seq"), subs.drop("reg_seq", "cancel_seq")
    want = rows(matching.match_nested_loop(*plain))
    by_text = whole_world(catalog.GRID, 3, [0, 1, 2], {r.term: r.df % 3 for r in freq.limit(500).collect()})
    for found in (*(matching.run(*plain, a, freq)["matches"] for a in (assignment, by_text)), matching.match_fast(*plain, catalog.GRID)):
        text = found.sparkSession._jvm.PythonSQLUtils.explainString(found._jdf.queryExecution(), "formatted")
        crossing = [{re.sub(r"#\d+L?", "", c) for c in columns.split(", ")} for columns in re.findall(r"Exchange\nInput \[\d+\]: \[(.*)\]", text)]
        met = [c for c in crossing if "cell" in c]
        assert met and not any("term" in c or "terms" in c or {"sub_id", "obj_id"} <= c for c in met)
        assert rows(found) == want
    living = rows(matching.match_once(objects, assignment, matching.build_index(routing.route_subs(subs, assignment, freq)), catalog.GRID).select("sub_id", "obj_id"))
    assert 0 < len(living) < len(want) and rows(matching.run(objects, subs, assignment, freq)["matches"]) == living
    keyed = routing.subs_at_cells(plain[1], freq, catalog.GRID).select("cell", "term").distinct()
    for a in (assignment, by_text):
        chart = matching.cellmatch.Chart(*a.chart())
        placed = a.place(keyed).select("cell", F.xxhash64("term").alias("code"), "worker").collect()
        assert all(chart.worker(r.cell, matching.cellmatch.np.array([r.code]))[0] == r.worker for r in placed)


def test_matches_are_made_of_what_was_routed(spark, work, monkeypatch):
    """Postings and objects go to the worker that the kd-tree gives them: what a worker does not get, it does not find."""
    monkeypatch.setattr(matching, "GATHERED", 0)
    objects, subs, _, freq = work
    plain = objects.drop("seq"), subs.drop("reg_seq", "cancel_seq")
    tree, _ = catalog.planned("kdtree", *plain, catalog.GRID)
    whole = matching.run(*plain, tree, freq, drop_unmatched=False)
    want = rows(matching.match_nested_loop(*plain))
    assert rows(whole["matches"]) == want
    at = {r.obj_id: r.worker for r in whole["routed_objects"].collect()}
    some = [(q, o) for q, o in want if at[o] != at[want[0][1]]]
    assert 0 < len(some) < len(want)
    for table in ("sent", "index"):
        less = matching.run(*plain, tree, freq, drop_unmatched=False)
        less[table] = less[table].filter(F.col("worker") != at[want[0][1]])
        assert rows(less["matches"]) == some
    # a place has one worker, and so have the rows of a block
    cm, places = matching.cellmatch, tree.places()
    assert places.tolist() == tree.place(spark.range(4096).select(F.col("id").cast("int").alias("cell"))).orderBy("cell").toPandas()["worker"].tolist()
    empty = cm.np.zeros(0, dtype=cm.np.int64)
    seen = matching._seen(whole["sent"], False, "cell", "worker").mapInArrow(lambda b: cm.placed(b, 1, 64, empty, (empty, empty, empty), places), "cell int, salt int, kind int, block binary").collect()
    assert all(places[r.cell + (r.kind - 1) // 2 * 64 + (r.kind - 1) % 2] == r.salt // cm.PIECES for r in seen) and len({r.salt // cm.PIECES for r in seen}) > 1


def test_cells_settle_each_pair_once(spark, monkeypatch):
    """Clauses that overlap, and a place that is not known, which no rectangle has."""
    monkeypatch.setattr(matching, "GATHERED", 0)
    objects = spark.createDataFrame([(1, 0, 0, ["a", "b", "c"]), (2, 0, 0, ["b"]), (3, 9, 9, ["a"]), (4, None, 0, ["a"]), (5, 1, 5, []), (6, 5, 5, ["c"])], "obj_id long, x long, y long, terms array<string>")
    dnf = [[["a"], ["b"], ["c"]], [["a", "b"], ["b", "c"]], [["a", "b"], ["a", "z"]], [["z"], ["c"]]]
    subs = spark.createDataFrame([(k, 1, d, -3, 5, 0, 5) for k, d in enumerate(dnf)], "sub_id long, owner long, dnf array<array<string>>, x0 long, x1 long, y0 long, y1 long")
    objects, subs = settle(objects, "objects"), settle(subs, "subs")
    want = [(0, 1), (0, 2), (0, 6), (1, 1), (2, 1), (3, 1), (3, 6)]
    grid = Grid(16, 1)
    assert rows(matching.run(objects, subs, whole_world(grid, 1))["matches"]) == rows(matching.match_fast(objects, subs, grid)) == want


def test_rows_go_to_their_cells_in_blocks(spark, work, monkeypatch):
    """No row of an object or a subscription crosses the exchange by itself; with cells cut, few rows to a block and words that the table lacks, the pairs are the same."""
    monkeypatch.setattr(matching, "GATHERED", 0)
    monkeypatch.setattr(matching, "SHARES", 5000)
    monkeypatch.setattr(matching, "LIGHT", 0)
    monkeypatch.setattr(matching.cellmatch, "PACKED", 100)
    objects, subs, assignment, freq = work
    want = rows(matching.match_once(objects, assignment, matching.build_index(routing.route_subs(subs, assignment, freq)), catalog.GRID).select("sub_id", "obj_id"))
    for words in (0, 50, 1_000_000):
        monkeypatch.setattr(matching, "WORDS", words)
        found = matching.match_by_cell(objects, subs, freq, catalog.GRID, assignment)
        assert exchanged(found, ("cell", "salt")) == [{"cell", "salt", "kind", "block"}]
        assert rows(found) == want
    turned = subs.limit(1).select("sub_id", "owner", F.col("x1").alias("x0"), F.col("x0").alias("x1"), "y0", "y1", "dnf")
    assert matching.match_by_cell(objects.drop("seq"), turned, freq, catalog.GRID).isEmpty()


def test_blocks_give_back_their_columns():
    np, low, high = matching.cellmatch.np, -(1 << 63), (1 << 63) - 1
    columns = [np.array(c, dtype=np.int64) for c in ([], [7], [low, high, 0, -1], [5, 5, 5], [300, -2, 70000])]
    back = matching.cellmatch.spread(matching.cellmatch.squeeze(columns))
    assert [c.tolist() for c in back] == [c.tolist() for c in columns]
    same = np.full(10_000, 12_345_678_901, dtype=np.int64)
    assert len(matching.cellmatch.squeeze([same])) < 100


def test_a_subscription_goes_once_to_each_tile():
    """Over four cells of one tile it is in one block; over the borders of four tiles in four; objects keep their cell."""
    cm = matching.cellmatch
    pa, np = cm.pa, cm.np
    names = ("id", "x0", "x1", "y0", "y1", "cx0", "cx1", "cy0", "cy1", "since", "until")

    def sent(kind, at, keys):
        x0, x1, y0, y1 = at
        row = [7, x0 * 10, x1 * 10, y0 * 10, y1 * 10, x0, x1, y0, y1, 0, 9]
        batch = pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in row] + [pa.array([keys], pa.list_(pa.list_(pa.int64())))], [*names, "keys"])
        empty = np.zeros(0, dtype=np.int64)
        return [r for out in cm.packed(iter([batch]), kind, 8, np.array([30, 20, 10]), (empty, empty, empty)) for r in out.to_pylist()]

    keys = [[10, 5, 30], [], [20]]
    whole, over = sent(0, (2, 3, 2, 3), keys), sent(0, (1, 2, 1, 2), keys)
    assert [(r["cell"], r["kind"]) for r in whole] == [(18, 0)] and [r["cell"] for r in over] == [0, 2, 16, 18]
    near = cm.Rows.of(whole[0]["block"], np.array([30, 20, 10]))
    assert near.n_words.tolist() == [3, 0, 1] and sorted(near.codes[:3]) == [5, 10, 30] and near.codes[3:].tolist() == [20]
    assert [len(near.within(cell, 8, 10).id) for cell in (18, 19, 26, 27, 17, 20, 34)] == [1, 1, 1, 1, 0, 0, 0]
    assert [(r["cell"], r["kind"]) for r in sent(1, (3, 3, 2, 2), [[10]])] == [(18, 2)]


def test_settled_tables_leave_no_shuffle_files(spark):
    folders = list(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString())
    shuffled = lambda: {f for top in folders for _, _, names in os.walk(top) for f in names if f.startswith("shuffle_")}
    before, setting = shuffled(), spark.conf.get(shared.CLEANUP)
    counted = settle(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count(), "counted")
    for _ in range(50):
        if not (left := shuffled() - before):
            break
        time.sleep(0.1)
    assert not left and spark.conf.get(shared.CLEANUP) == setting
    assert sorted(r["count"] for r in counted.collect()) == [142] + [143] * 6


def test_rarest_terms_are_found_where_the_text_is(spark, monkeypatch):
    """The subscriptions' rarest terms cross no exchange term by term, and are those that shuffling finds."""
    objects = settle(wide_objects(spark, FOLDER), "objects")
    found = workload.subscriptions(spark, FOLDER, "Q2", objects=objects)
    text = spark._jvm.PythonSQLUtils.explainString(found._jdf.queryExecution(), "formatted")
    crossing = [{re.sub(r"#\d+L?", "", c) for c in columns.split(", ")} for columns in re.findall(r"Exchange\nInput \[\d+\]: \[(.*)\]", text)]
    assert crossing and not any({"term", "kt", "terms"} & columns for columns in crossing)
    held = rows(found)
    monkeypatch.setattr(workload, "HELD_TERMS", 0)
    assert held and rows(workload.subscriptions(spark, FOLDER, "Q2", objects=objects)) == held


def test_subscriptions_are_written_in_parts(spark):
    """Parts have no text in common, put no table down in between, and are all rows together."""
    objects = settle(wide_objects(spark, FOLDER), "objects")
    tables = lambda: {t for t in os.listdir(shared.shared_folder(spark).removeprefix("file:")) if t.startswith("centred")}
    for group in ("Q1", "Q3"):
        whole, before = rows(workload.subscriptions(spark, FOLDER, group, objects=objects)), tables()
        parts = list(workload.subscription_parts(spark, FOLDER, group, objects=objects, texts_at_once=-(-objects.count() // 3)))
        found = [rows(p) for p in parts]
        assert len(found) == 3 and all(found) and sorted(r for f in found for r in f) == sorted(whole) and tables() == before
        assert rows(shared.settle_parts(parts, "parts")) == whole


def test_planner_and_engine_hash_alike(spark):
    words = ["a", "été", "zebra", "日本", "x" * 50]
    df = spark.createDataFrame([(w,) for w in words], "term string")
    for parts in (2, 3, 7):
        assert [r[0] for r in df.select(hashed_part(F.col("term"), F.lit(parts))).collect()] == [part_of(w, parts) for w in words]


def test_tree_and_grid_place_alike(spark, work):
    objects, subs, assignment, freq = work
    keyed = routing.subs_at_cells(subs, freq, catalog.GRID).select("sub_id", "cell", "term")
    by_grid, by_tree = (assignment.place(keyed, by_tree=t).select("sub_id", "cell", "term", "worker") for t in (False, True))
    assert rows(by_grid) == rows(by_tree)


def test_four_workers_in_space_and_text(spark):
    """A region of one worker, one whose terms two workers share, and one whose terms three share."""
    grid = Grid(8, 2)
    leaves = [Leaf(0, 0, 4, 1, [0]), Leaf(0, 1, 4, 2, [0, 1], {"a": 0, "b": 1}), Leaf(0, 2, 4, 4, [1, 2, 3], {"a": 0, "b": 1, "c": 2})]
    assignment = Assignment(grid, 4, leaves)
    assignment.check()
    objects = spark.createDataFrame([(1, 0, 0, ["a", "b", "c"]), (2, 0, 2, ["a", "b"]), (3, 0, 2, ["b"]), (4, 0, 6, ["a", "b", "c"]), (5, 0, 6, ["a", "c"])], "obj_id long, x long, y long, terms array<string>")
    everywhere = spark.createDataFrame([(k, 1, [[t]], 0, 7, 0, 7) for k, t in enumerate("abc")], "sub_id long, owner long, dnf array<array<string>>, x0 long, x1 long, y0 long, y1 long")
    objects, everywhere = settle(objects, "objects"), settle(everywhere, "subs")
    parts = matching.run(objects, everywhere, assignment)
    sent = {r.obj_id: sorted(r.w) for r in parts["routed_objects"].groupBy("obj_id").agg(F.collect_set("worker").alias("w")).collect()}
    assert sent == {1: [0], 2: [0, 1], 3: [1], 4: [1, 2, 3], 5: [1, 3]}
    assert rows(parts["matches"]) == rows(matching.match_nested_loop(objects, everywhere))


def test_every_term_has_one_worker(spark, work):
    _, _, assignment, freq = work
    assert load.check_partition(spark, assignment, freq).isEmpty()
    with pytest.raises(ValueError):
        load.check_partition(spark, Assignment(catalog.GRID, 1, [Leaf(0, 0, 3, 3)]), freq)


def test_nested_loop_has_a_bound(spark, work, monkeypatch):
    monkeypatch.setattr(matching, "NESTED_SUBS", 3)
    with pytest.raises(ValueError):
        matching.match_nested_loop(work[0], work[1])


def test_share_to_move_restores_the_balance(spark):
    loads = spark.createDataFrame([(0, 1000, 500), (1, 200, 100), (2, 400, 300)], "worker int, n_obj long, n_reg long").withColumn("load", F.col("n_obj") * F.col("n_reg") * 1.0)
    share = adjust.share_to_move(loads, 0, 1, 1.5)
    left, more = 1000 * 500 * (1 - share) ** 2, (200 + share * 1000) * (100 + share * 500)
    assert 0 < share < 0.5 and left / more <= 1.55 and max(left, more) < 500_000
    assert adjust.share_to_move(loads, 0, 0, 0.5) == 0


def test_selectors_as_tables_and_in_any_order(spark):
    cells = spark.createDataFrame([(0, k, float(5 + 7 * k % 11), 100 + 13 * k % 29) for k in range(40)], "worker int, cell int, load double, size_bytes long")
    picked = migrate.prefix_selected(cells, 60.0, [F.desc("size_bytes"), "cell"])
    assert {r.cell for r in picked.collect()} == set(migrate.select(cells, 60.0, "largest_first").cells)
    assert migrate.select(cells, 60.0, "random_pick") == migrate.select(cells.orderBy(F.desc("cell")), 60.0, "random_pick")


def test_measures_around_a_run(spark, work):
    objects, subs, assignment, freq = work
    parts = matching.run(objects, subs, assignment, freq)
    loads = settle(load.worker_load(parts["routed_objects"], parts["index"], assignment.m), "loads")
    assert measures.model_throughput(loads, 1000).first()[0] == 1000 / loads.agg(F.max("load")).first()[0]
    with_cancels = load.worker_load(parts["routed_objects"], parts["index"], assignment.m, routing.route_cancels(subs.filter("cancel_seq is not null"), assignment, freq))
    assert with_cancels.agg(F.sum("load")).first()[0] > loads.agg(F.sum("load")).first()[0]
    cell = parts["index"].first()
    cost = measures.migration_cost(parts["index"], (cell.cell,), cell.worker).first()
    assert cost.subs == parts["index"].filter((F.col("cell") == cell.cell) & (F.col("worker") == cell.worker)).select("sub_id").distinct().count() and cost.bytes >= 48 * cost.subs
    costs = load.calibrate(objects, subs, catalog.GRID)
    assert min(costs.check, costs.obj, costs.reg, costs.cancel) > 0
    assert measures.latency([{"numInputRows": 1, "durationMs": {"triggerExecution": 10}}, {"numInputRows": 3, "durationMs": {"triggerExecution": 30}}]) == 25
    sends = routing.sends_by_dispatcher(objects, parts["routed_objects"], 3).collect()
    assert sum(r.n_obj for r in sends) == objects.count() and sum(r.sends for r in sends) == parts["routed_objects"].select("obj_id", "worker").distinct().count()


def test_service_counts_the_entries_of_the_lists(spark, work):
    """The lengths of the lists give what going through them gave, without looking at an entry."""
    objects, subs, assignment, freq = work
    plain = subs.drop("reg_seq", "cancel_seq")
    parts = matching.run(objects, plain, assignment, freq)
    want = matching.candidates(objects, parts["routed_objects"], parts["index"], catalog.GRID).groupBy("worker", "seq").agg(F.count(F.lit(1)).alias("n"))
    got = experiments.served(objects, routing.posted(plain, freq, catalog.GRID), assignment, True, 1.0, 0.0)
    assert rows(got.select("worker", "seq", F.col("service").cast("long"))) == rows(want)


def test_measures_are_those_of_the_routed_tables(spark, work):
    objects, subs, assignment, freq = work
    got = experiments.measured(experiments.Laid.of(objects, subs, freq, catalog.GRID), assignment, True)
    parts = matching.run(objects, subs, assignment, freq)
    loads = load.worker_load(parts["routed_objects"], parts["index"], assignment.m).collect()
    assert got["total"] == sum(r.load for r in loads) and got["top"] == max(r.load for r in loads)
    rep = routing.replication(objects, parts["routed_objects"], subs, parts["index"]).first()
    assert (got["sends"], got["copies"]) == (rep["sends_per_object"], rep["copies_per_sub"])


def test_index_grows_and_is_written_by_worker(spark, work, tmp_path):
    objects, subs, assignment, freq = work
    odd, even = (matching.build_index(routing.route_subs(subs.filter(f"sub_id % 2 = {k}"), assignment, freq)) for k in (1, 0))
    whole = matching.insert(odd, routing.route_subs(subs.filter("sub_id % 2 = 0"), assignment, freq))
    assert whole.count() == odd.count() + even.count()
    tables.write_by_worker(whole.drop("dnf"), str(tmp_path / "index"))
    assert spark.read.parquet(str(tmp_path / "index")).filter("worker = 0").count() == whole.filter("worker = 0").count()
    assert tables.rate_source(spark, 5, 1).isStreaming


def test_sketches_come_near(spark):
    exact, near = (dict(rows(q(spark, FOLDER))) for q in (surface.union_sizes, surface.union_sketches))
    assert exact.keys() == near.keys() and all(abs(exact[k] - near[k]) <= 0.05 * exact[k] for k in exact)


def test_cells_change_hands_while_the_stream_runs(spark, tmp_path):
    grid = Grid(4, 1)
    objects = spark.createDataFrame([(k, k % 2, 0, ["a"], 10 * k) for k in range(40)], "obj_id long, x long, y long, terms array<string>, seq long")
    subs = spark.createDataFrame([(k, 1, [["a"]], k % 2, k % 2, 0, 0, -1 - k, 350 if k == 0 else None) for k in range(6)], "sub_id long, owner long, dnf array<array<string>>, x0 long, x1 long, y0 long, y1 long, reg_seq long, cancel_seq long")
    assignment = Assignment(grid, 2, [Leaf(0, 0, 1, 1, [0]), Leaf(1, 0, 2, 1, [0]), Leaf(0, 1, 2, 2, [1])])
    freq = routing.term_freq(objects)
    want = rows(matching.run(objects, subs, whole_world(grid, 1), freq)["matches"])
    stream = settle(engine.as_tuples(objects, subs), "tuples")
    engine.write_slices(stream, str(tmp_path / "t"), 3)
    hook = engine.Adjuster(1.2)
    state = engine.Replay(spark, assignment, freq, str(tmp_path), hook, late_s=20)
    engine.replay(engine.source(spark, str(tmp_path / "t")), state, str(tmp_path / "c"))
    assert rows(state.matches()) == want
    assert state.late_objects() == 0 and len(hook.tops) == 3 and state.wait_ms() > 0
    assert hook.moves and state.assignment.version == len(hook.moves)
    # an object from before the last batches counts as late and is matched all the same
    extra = objects.filter("obj_id = 1").withColumn("obj_id", F.lit(99).cast("long")).withColumn("seq", F.lit(20).cast("long"))
    late = engine.as_tuples(extra, subs.limit(0))
    state.on_batch(late, 3)
    assert state.late_objects() == 1 and state.matches().filter("obj_id = 99").count() == 3
    # a compaction loses what was cancelled, and nothing else
    before = state.table(state._held("index"), 3).select("sub_id").distinct().count()
    state.compact(1000)
    held = state.table(state._held("index"), 3).select("sub_id").distinct()
    assert rows(held) == [(k,) for k in range(1, 6)] and before == 6
    assert state.table(state._held("tombstones")).isEmpty()


def test_loads_are_counted_from_blocks(spark, work):
    """No row of a posting or an object crosses an exchange by itself when loads are counted, and the counts are those of the rows."""
    objects, subs, assignment, freq = work
    parts = matching.run(objects, subs, assignment, freq)
    routed, index = settle(parts["routed_objects"], "routed"), settle(parts["index"], "index")
    for found in (load.worker_load(routed, index, assignment.m), load.cell_load(routed, index)):
        text = spark._jvm.PythonSQLUtils.explainString(found._jdf.queryExecution(), "formatted")
        crossing = [{re.sub(r"#\d+L?", "", c) for c in columns.split(", ")} for columns in re.findall(r"Exchange\nInput \[\d+\]: \[(.*)\]", text)]
        assert crossing and not any({"obj_id", "sub_id", "id"} & columns for columns in crossing)
    counted = {r.worker: (r.n_obj, r.n_reg) for r in load.worker_load(routed, index, assignment.m).collect()}
    per = lambda df, key: {r.worker: r.n for r in df.groupBy("worker").agg(F.countDistinct(key).alias("n")).collect()}
    n_obj, n_reg = per(routed, "obj_id"), per(index, "sub_id")
    assert counted == {w: (n_obj.get(w, 0), n_reg.get(w, 0)) for w in range(assignment.m)}
    cells = rows(load.cell_load(routed.union(routed), index.union(index)).select("worker", "cell", "n_obj", "avg_subs", "size_bytes"))
    stored = index.select("worker", "cell", "sub_id", load.sub_bytes(F.col("dnf")).alias("b")).distinct().groupBy("worker", "cell").agg(F.count(F.lit(1)).cast("double").alias("n"), F.sum("b").alias("b"))
    there = routed.distinct().groupBy("worker", "cell").agg(F.count(F.lit(1)).alias("o"))
    assert cells == rows(stored.join(there, ["worker", "cell"], "full").select("worker", "cell", F.coalesce("o", F.lit(0)), F.coalesce("n", F.lit(0.0)), F.coalesce("b", F.lit(0))))
