"""Answers of every index and partitioner against scans, updates, streams, and a set of queries against their SQL."""

from __future__ import annotations

import pytest
from conftest import same
from pyspark.sql import functions as F

from kinetic import queries as kq
from kinetic.functions import sqlfuncs
from kinetic.operators import index_box, index_curve, measures, partitions, query, update
from kinetic.sources import generator
from kinetic.sources import standins as st

CHECKED = [
    "mo_orders", "mo_lineitem", "mo_events", "mo_embed", "q_range", "q_knn", "velocity_from_samples", "latest_status", "layers_equal_width", "layers_distinct", "cell_rollup", "chi2_uniformity_4x4", "merged_tiling",
    "nu_one_quad_choice", "range_costs", "range_costs_speed", "optimal_plan", "plan_fixed_k", "heuristic_plans", "assign_parts", "range_box", "range_curve_hilbert", "range_pushdown", "knn_box", "knn_growing", "knn_merged",
    "seed_parts", "axis_parts_outliers_first_round", "node_accesses_opt", "curve_intervals", "false_hits", "update_migrations", "stream_latest", "stream_hourly_speed", "stream_sessions",
]


@pytest.mark.parametrize("name", CHECKED)
def test_equals_sql(spark, sf, duck, name):
    same(kq.QUERIES[name](spark, sf), duck, kq.ORACLES[name])


@pytest.fixture(scope="module")
def parted(spark, sf):
    return kq.parted10(spark, sf).persist()


def pairs(df):
    return sorted((r["qid"], r["oid"]) for r in df.select("qid", "oid").collect())


@pytest.mark.parametrize("t", [0, 90, 120])
def test_answers_equal_the_scan(spark, sf, parted, t):
    q = st.q_range(spark, sf, 1000, t)
    want = pairs(query.range_scan(st.mo_orders(spark, sf), q))
    assert want
    for way in (query.range_box, query.range_curve, query.range_pushdown):
        assert pairs(way(parted, q)) == want


def test_more_neighbours_than_objects(spark, sf, parted):
    few = parted.where("oid <= 20")
    q = st.q_knn(spark, sf, 100).where("qid = 0")
    n = few.count()
    assert n and query.knn_box(few, q).count() == n == query.knn_growing(few, q).count()


def test_nodes_hold_their_members(parted):
    objects = index_box.build_nodes(parted, 20)
    boxes = index_box.node_boxes(objects)
    assert boxes.agg(F.max("n")).first()[0] <= 20
    joined = objects.join(boxes.withColumnRenamed("n", "m"), ["part", "quadrant", "node"])
    for t in (0, 60, 120):
        out = joined.where((F.col("x") + F.col("vx") * t < F.col("xlo") + F.col("vxlo") * t - 1e-6) | (F.col("x") + F.col("vx") * t > F.col("xhi") + F.col("vxhi") * t + 1e-6))
        assert out.count() == 0


def test_curves_fill_the_grid(spark):
    cells = spark.range(1024).select((F.col("id") % 32).alias("gx"), F.floor(F.col("id") / 32).cast("long").alias("gy"))
    for name, curve in index_curve.CURVES.items():
        rows = sorted((r["k"], r["gx"], r["gy"]) for r in cells.select("gx", "gy", curve(F.col("gx"), F.col("gy"), 5).alias("k")).collect())
        assert [k for k, _, _ in rows] == list(range(1024))
        if name == "hilbert":
            assert all(abs(a[1] - b[1]) + abs(a[2] - b[2]) == 1 for a, b in zip(rows, rows[1:], strict=False))


def test_every_object_has_one_part(spark, sf, parted):
    assert parted.count() == st.mo_orders(spark, sf).count()
    edge = spark.createDataFrame([(1, 0.0, 0.0, 8.0, 0.0, 8.0, 0.0), (2, 0.0, 0.0, 99.0, 0.0, 99.0, 0.0), (3, 0.0, 0.0, 0.0, 0.0, 0.0, 0.0)], "oid long, x double, y double, vx double, vy double, speed double, t_ref double")
    got = {r["oid"]: r["part"] for r in partitions.assign_parts(edge, kq.demo_plan(spark)).collect()}
    assert got == {1: 1, 2: 3, 3: 1}


def test_updates_in_any_split(spark, sf):
    rows = st.mo_events(spark, sf)
    plan = kq.demo_plan(spark)
    none = rows.where("false").select("oid", *update.STATE)
    whole, _ = update.apply_updates(none, rows, plan)
    half, _ = update.apply_updates(none, rows.where("event_id % 2 = 0"), plan)
    both, moves = update.apply_updates(half.select("oid", *update.STATE), rows.where("event_id % 2 = 1"), plan)
    assert sorted(whole.select("oid", "event_id", "part").collect()) == sorted(both.select("oid", "event_id", "part").collect())
    assert {r["action"] for r in moves.select("action").distinct().collect()} <= {"insert", "update", "migrate", "late"}


def test_layout_prunes(spark, sf, parted, tmp_path):
    info = partitions.write_layout(parted, str(tmp_path / "layout"))
    q = st.q_range(spark, sf).first().asDict()
    got = query.layout_range(spark, info.path, q)
    assert sorted(r["oid"] for r in got.collect()) == sorted(r["oid"] for r in query.range_scan(parted, st.q_range(spark, sf).where(F.col("qid") == q["qid"])).collect())
    plan = got._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(x)" in plan and "PartitionFilters" in plan


def test_generations(spark, parted, tmp_path):
    rows = parted.withColumn("ts", F.lit(0).cast("timestamp")).withColumn("event_id", F.col("oid"))
    path = str(tmp_path / "gen")
    update.commit(rows, path, 0)
    update.commit(rows.where("oid < 50").withColumn("vx", F.lit(1.0)), path, 1)
    now = update.current(spark, path)
    assert now.count() == rows.count() and now.where("oid < 50 AND vx <> 1").count() == 0


def test_sql_functions(spark, sf):
    sqlfuncs.register(spark, st.mo_orders(spark, sf))
    q = st.q_range(spark, sf, 1000).first()
    n = spark.sql(f"SELECT count(*) FROM range_query({q['xlo']}D, {q['ylo']}D, {q['xhi']}D, {q['yhi']}D, {q['t']}D)").first()[0]
    assert n == query.range_scan(st.mo_orders(spark, sf), st.q_range(spark, sf, 1000).where(F.col("qid") == q["qid"])).count()
    assert spark.sql("SELECT nu_one(2D, 0D, 3D)").first()[0] == 12


def test_traffic_stays_on_roads(spark, sf):
    legs = generator.traffic(spark, sf)
    at = generator.traffic_at(legs, 60.0)
    assert at.count() == spark.read.parquet(f"{sf}/orders.parquet").count()
    off = at.where((F.abs(F.col("x") % 2000 - 1000) > 1e-6) & (F.abs(F.col("y") % 2000 - 1000) > 1e-6))
    assert off.count() == 0
    assert generator.segments(spark, sf).count() == 40


def test_plans_have_no_cartesian_of_objects(spark, sf, parted):
    text = index_box.build_nodes(parted)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in text


def test_stored_index_answers_as_the_scan(spark, sf, parted, tmp_path):
    from kinetic.operators.stored import open_index, store_index

    q, k, mo = st.q_range(spark, sf, 1000, 90), st.q_knn(spark, sf, 7, 90), st.mo_orders(spark, sf)
    near = sorted((r["qid"], r["rank"], r["oid"]) for r in query.knn_scan(mo, k).collect())
    for kind in ("box", "curve"):
        store_index(parted, str(tmp_path / kind), kind, 20)
        index = open_index(spark, str(tmp_path / kind), kind)
        assert pairs(index.range(q)) == pairs(query.range_scan(mo, q))
        assert sorted((r["qid"], r["rank"], r["oid"]) for r in index.neighbours(k).collect()) == near
    assert store_index(parted.limit(0), str(tmp_path / "none")).range(q).count() == 0


def test_neighbours_are_cut_before_the_shuffle(spark, sf):
    text = query.knn_scan(st.mo_orders(spark, sf), st.q_knn(spark, sf))._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in text


def test_many_windows_meet_in_cells(spark, sf, parted, monkeypatch):
    q = st.q_range(spark, sf, 1000, 60)
    want = pairs(query.range_scan(parted, q))
    for literal, broadcast in ((0, 10**9), (0, 0)):
        monkeypatch.setattr(query, "LITERAL_WINDOWS", literal)
        monkeypatch.setattr(query, "BROADCAST_CELLS", broadcast)
        assert pairs(query.range_pushdown(parted, q)) == want


def test_rivals_route_new_objects_by_their_fitted_rule(spark, sf):
    from kinetic import workloads as w

    mo = st.mo_orders(spark, sf)
    for way in w.WAYS:
        route = w.router(spark, sf, way)
        whole = {r["oid"]: (r["part"], r["quadrant"]) for r in route(mo).select("oid", "part", "quadrant").collect()}
        half = {r["oid"]: (r["part"], r["quadrant"]) for r in route(mo.where("oid % 2 = 0")).select("oid", "part", "quadrant").collect()}
        assert len(whole) == mo.count() and all(whole[o] == p for o, p in half.items())


def test_plans_are_made_from_the_tables_as_they_are_now(spark, sf, duck, tmp_path):
    def objects() -> int:
        return kq.QUERIES["range_costs"](spark, str(tmp_path)).agg(F.max("n")).first()[0]

    duck.execute(f"COPY customer TO '{tmp_path}/customer.parquet' (FORMAT parquet)")
    for n in (1000, 600):
        duck.execute(f"COPY (SELECT * FROM orders ORDER BY o_orderkey LIMIT {n}) TO '{tmp_path}/orders.parquet' (FORMAT parquet)")
        spark.catalog.refreshByPath(f"{tmp_path}/orders.parquet")
        assert objects() == n


def test_hilbert_keys_of_the_objects_cells(spark, sf, duck):
    same(kq.QUERIES["curve_hilbert_definition"](spark, sf), duck, kq.ORACLES["curve_hilbert_definition"])


def test_hilbert_keys_of_the_whole_grid(spark):
    cells = spark.range(4096).select((F.col("id") % 64).alias("gx"), F.expr("id div 64").alias("gy"))
    at = {r["key"]: (r["gx"], r["gy"]) for r in cells.withColumn("key", index_curve.hilbert_code(F.col("gx"), F.col("gy"), 6)).collect()}
    assert sorted(at) == list(range(4096))
    assert all(abs(at[k][0] - at[k + 1][0]) + abs(at[k][1] - at[k + 1][1]) == 1 for k in range(4095))
    for k in range(1, 6):
        assert len({(key >> 2 * k, x >> k, y >> k) for key, (x, y) in at.items()}) == 4 ** (6 - k)


def test_windows_meet_objects_in_cells(spark):
    """Two times, places beyond the grid, edges on cells, and windows that are empty or null; no pair of every object with every window."""
    mo = spark.createDataFrame([(i, (i * 37 % 240) * 50.0 - 1000, (i * 91 % 240) * 50.0 - 1000, i % 7 - 3.0, i % 5 - 2.0, 3.0, 0.0) for i in range(500)], "oid long, x double, y double, vx double, vy double, speed double, t_ref double")
    windows = [(i, (i * 53 % 24) * 500.0 - 1500, (i * 29 % 24) * 500.0 - 1500, (i * 53 % 24) * 500.0, (i * 29 % 24) * 500.0 - 200, float(i % 2 * 60)) for i in range(60)]
    windows += [(60, 500.0, 0.0, 400.0, 10000.0, 60.0), (61, None, 0.0, 10000.0, 10000.0, 60.0), (62, 0.0, 0.0, 10000.0, 10000.0, None)]
    q = spark.createDataFrame(windows, "qid long, xlo double, ylo double, xhi double, yhi double, t double")
    want = sorted((w[0], o["oid"]) for o in mo.collect() for w in windows if None not in w and w[1] <= o["x"] + o["vx"] * w[5] <= w[3] and w[2] <= o["y"] + o["vy"] * w[5] <= w[4])
    got = query.range_scan(mo, q)
    assert len(want) > 100 and pairs(got) == want
    parted = partitions.single_part(mo)
    assert pairs(query.range_box(parted, q)) == want
    assert "_cell" in got._jdf.queryExecution().optimizedPlan().toString()


def test_candidates_are_counted_without_pairs(spark, sf, parted):
    keyed = index_curve.curve_keys(parted)
    runs = index_curve.curve_intervals(st.q_range(spark, sf, 900, 100), index_curve.key_stats(keyed))
    listed = index_curve.probe_intervals(keyed, runs)
    want = keyed.select("oid", "part", "quadrant", "label", "key").join(runs, ["part", "quadrant", "label"]).where("key BETWEEN key_lo AND key_hi")
    assert pairs(listed) == pairs(want)
    counted = {r["qid"]: r["candidates"] for r in index_curve.count_candidates(keyed, runs).collect()}
    assert counted == {r["qid"]: r["count"] for r in want.groupBy("qid").count().collect()}


def test_pairs_that_repeat_are_counted_as_often_as_they_are_there(spark):
    a = spark.createDataFrame([(1, 7), (1, 7), (1, 8), (2, 9)], "qid long, oid long")
    got = {r["qid"]: (r["answers"], r["truth"], r["hits"]) for r in measures.answer_quality(a, a.where("oid <> 8")).collect()}
    assert got == {1: (3, 2, 2), 2: (1, 1, 1)}


def test_a_sweep_leaves_no_index_behind(spark, sf):
    from pathlib import Path

    from kinetic import workloads
    from kinetic.sources.shared import checkpoint_folder

    root = Path(checkpoint_folder(spark).removeprefix("file:"))
    before = set(root.rglob("objects"))
    q = st.q_range(spark, sf, 2000)
    got = workloads.sweep_accesses(spark, sf, {3: q}, ways=("one",)).collect()
    assert {(r["kind"], r["value"], r["answers"]) for r in got} == {(k, 3, query.range_scan(st.mo_orders(spark, sf), q).count()) for k in ("box", "curve")}
    assert set(root.rglob("objects")) == before


def test_steps_of_vehicles_run_once(spark, sf):
    plan = generator.traffic(spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("aggregate(sequence(") <= 1


def test_windows_of_all_sizes_of_sets_are_counted_without_pairs(spark, sf, duck, monkeypatch):
    monkeypatch.setattr(query, "in_windows", None)  # it makes a row for each object in each window
    same(kq.QUERIES["w5_objects_range"](spark, sf), duck, kq.ORACLES["w5_objects_range"])


def test_counts_are_the_sizes_of_the_answers(spark, monkeypatch):
    monkeypatch.setattr(query, "COUNTED", 50)
    place = "cast(id * 37 % 23 * 500 - 500 as double)"
    mo = spark.range(300).selectExpr("id AS oid", f"{place} AS x", "cast(id % 7 * 1500 as double) AS y", "cast(id % 3 - 1 as double) * 10 AS vx", "5D AS vy", "sqrt(vx * vx + 25) AS speed", "cast(id % 2 as double) AS t_ref")
    asked = [(1, 0.0, 0.0, 10000.0, 10000.0, 0.0), (2, 500.0, 0.0, 500.0, 9000.0, 1.0), (3, -1e9, -1e9, 1e9, 1e9, 60.0), (4, 3.0, 3.0, 2.0, 9.0, 0.0), (5, 1.0, 1.0, 2.0, 2.0, 1.0), (6, 0.0, 0.0, 9e3, 9e3, None), (2, 500.0, 0.0, 500.0, 9000.0, 1.0), (None, 0.0, 0.0, 5e3, 1e300, 1.0)]
    q = spark.createDataFrame(asked, "qid long, xlo double, ylo double, xhi double, yhi double, t double")
    want = query.in_windows(mo, q).groupBy("qid").count().collect()
    assert sorted(map(str, want)) == sorted(str(r).replace("answers", "count") for r in query.counts_in_windows(mo, q).collect()) and len(want) == 4
    assert query.counts_in_windows(mo, q.where("qid = 4")).count() == 0 == query.counts_in_windows(mo.limit(0), q).count()
    monkeypatch.setattr(query, "MOST_WINDOWS", 1)
    assert sorted(map(str, want)) == sorted(str(r).replace("answers", "count") for r in query.counts_in_windows(mo, q).collect())


def test_a_box_index_is_written_by_one_shuffle_of_its_objects(parted):
    rows = index_box.build_nodes(parted, 20, dealt=True)
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "rangepartitioning(part" in plan and "hashpartitioning(part#" not in plan.split("BroadcastExchange")[0]
    other = index_box.build_nodes(parted, 20)
    assert sorted(map(str, rows.select("oid", "part", "quadrant", "node").collect())) == sorted(map(str, other.select("oid", "part", "quadrant", "node").collect()))


def test_accesses_are_counted_without_pairs(spark, sf, parted, tmp_path, monkeypatch):
    from kinetic.operators import stored

    q = st.q_range(spark, sf, 900, 100).unionByName(st.q_range(spark, sf, 300, 0).withColumn("qid", F.col("qid") + 1000))
    odd = [(9001, 900.0, 0.0, 100.0, 9000.0, 60.0), (9002, 0.0, 0.0, 9000.0, 9000.0, None), (9003, -1e9, -1e9, 1e9, 1e9, 60.0), (9004, 2e8, 0.0, 3e8, 1.0, 60.0)]
    q = q.unionByName(spark.createDataFrame(odd, "qid long, xlo double, ylo double, xhi double, yhi double, t double"))
    for kind in ("box", "curve"):
        index = stored.store_index(parted, f"file://{tmp_path}/{kind}", kind, 8)
        if kind == "box":
            want = measures.node_accesses(index_box.candidate_nodes(index.catalog, q))
        else:
            want = index_curve.page_accesses(index.catalog, index_curve.curve_intervals(q, index.stats))
        want = {(r["qid"], r["accesses"]) for r in want.collect()}
        answers = {(r["qid"], r["count"]) for r in query.range_scan(parted, q).groupBy("qid").count().collect()}
        with monkeypatch.context() as m:
            m.setattr(index_box, "candidate_nodes", lambda nodes, queries, t0=0.0, f=index_box.candidate_nodes: f(nodes, queries.where("qid > 9000"), t0))
            m.setattr(index_curve, "page_accesses", None)
            m.setattr(query, "in_windows", None)
            assert {(r["qid"], r["accesses"]) for r in index.accesses(q).collect()} == want
            assert {(r["qid"], r["answers"]) for r in index.range_counts(q).collect()} == answers and len(answers) > 10


def test_only_a_querys_own_runs_answer_it(spark, parted):
    keyed = index_curve.curve_keys(parted)
    stats = index_curve.key_stats(keyed).withColumns({c: F.lit(0.0) for c in ("vxlo", "vxhi", "vylo", "vyhi")})  # too narrow: runs leave objects out
    q = spark.createDataFrame([(i, 400.0 * i, 900.0, 400.0 * i + 1500, 5900.0, 30.0 * (i % 3)) for i in range(20)], "qid long, xlo double, ylo double, xhi double, yhi double, t double")
    want = query._answers(query.curve_candidates(None, q, keyed=keyed, stats=stats).join(F.broadcast(q), "qid").where(partitions.inside()))
    got = query.range_curve(None, q, keyed=keyed, stats=stats)
    assert pairs(got) == pairs(want) and len(pairs(want)) < query.range_scan(parted, q).count()
    counted = {(r["qid"], r["answers"]) for r in query.range_curve_counts(q, keyed, stats).collect()}
    assert counted == {(r["qid"], r["count"]) for r in want.groupBy("qid").count().collect()}


def test_pairs_of_traffic_are_compared_where_they_are_made(spark, sf, monkeypatch):
    from kinetic import workloads

    plans, compared = [], measures.answer_quality

    def quality(answers, truth):
        out = compared(answers, truth)
        plans.append(out._jdf.queryExecution().executedPlan().toString())
        return out

    monkeypatch.setattr(measures, "answer_quality", quality)
    got = workloads.traffic_answers(spark, sf).collect()
    assert len({r["truth"] for r in got}) == 1 and all(r["answers"] == r["truth"] == r["hits"] > 0 for r in got)
    assert len(plans) == 3 and not any("hashpartitioning(qid#" in p and ", oid#" in p.split("hashpartitioning(qid#")[1].split(")")[0] for p in plans)
