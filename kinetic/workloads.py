"""The experiments: sweeps over sets, sizes, nodes, times, windows, neighbours and hours, for every partitioner and index."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from concurrent.futures import Future, ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kinetic import oracle as o
from kinetic.functions import motion
from kinetic.operators import baselines, index_box, index_curve, measures, partitions, query, update
from kinetic.operators.stored import StoredIndex, store_index
from kinetic.plans import optimise as opt
from kinetic.plans.params import OptimizerParams, capacity_of
from kinetic.sources import generator
from kinetic.sources import standins as st
from kinetic.sources.shared import checkpoint_folder, dropped, kept

#: Sweeps; the middle of each is its default.
NODE_BYTES = (1024, 2048, 4096, 8192, 16384)
TIMES = (0, 30, 60, 90, 120)
WINDOWS = (200, 400, 600, 800, 1000)
NEIGHBOURS = (10, 20, 30, 40, 50)
SIXTHS = (1, 2, 3, 4, 5)
LAYERS = (10, 25, 50, 75, 100)

DATA: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "orders": st.mo_orders,
    "mix-S": lambda s, d: st.mo_orders(s, d, "mix-S"),
    "mix-L": lambda s, d: st.mo_orders(s, d, "mix-L"),
    "mix-B": lambda s, d: st.mo_orders(s, d, "mix-B"),
    "dir-any": lambda s, d: st.mo_orders(s, d, any_direction=True),
    "lineitem": st.mo_lineitem,
    "embed": st.mo_embed,
    **{f"lineitem-{m}": (lambda s, d, m=m: st.mo_lineitem(s, d, m)) for m in SIXTHS},
}

_plans: dict[tuple, opt.Optimised] = {}


def micro(c: Column | str) -> Column:
    return F.floor((F.col(c) if isinstance(c, str) else c) * 1000000 + F.lit(0.5)).cast("long")


def optimised(spark: SparkSession, sf_dir: str, p: OptimizerParams, data: str = "orders") -> opt.Optimised:
    """The optimiser's tables for a set, made once in a query (see ``afresh``)."""
    key = (spark.sparkContext.applicationId, sf_dir, p, data)
    if key not in _plans:
        made = _sets.get((spark.sparkContext.applicationId, sf_dir, data))
        _plans[key] = opt.optimise(made if made is not None else DATA[data](spark, sf_dir), p)
    return _plans[key]


def afresh(fn: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    """A query that makes its plans from the tables as they are now, not from what an earlier query has read of them."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        for made in (_plans, _hours, _sets):
            made.clear()
        return fn(spark, sf_dir)

    return run


P10 = OptimizerParams(q=10)
_sets: dict[tuple, DataFrame] = {}


def stored_set(spark: SparkSession, sf_dir: str, data: str) -> DataFrame:
    """A set's objects as a table, made once in a query that goes over them many times."""
    key = (spark.sparkContext.applicationId, sf_dir, data)
    if key not in _sets:
        _sets[key] = kept(DATA[data](spark, sf_dir), "set")
    return _sets[key]


def router(spark: SparkSession, sf_dir: str, way: str, data: str = "orders", p: OptimizerParams = P10) -> Callable[[DataFrame], DataFrame]:
    """The rule of a partitioner fitted to a set: optimal, one, quadrants, seed, seed_refined, seed_enlargement, axis, axis_3."""
    if way == "optimal":
        plan = optimised(spark, sf_dir, p, data).plan
        return lambda rows: partitions.assign_parts(rows, plan)
    if way in ("one", "quadrants"):
        return lambda rows: partitions.single_part(rows, way == "quadrants")
    mo = stored_set(spark, sf_dir, data)
    return {
        "seed": lambda: baselines.seed_router(mo), "seed_refined": lambda: baselines.seed_router(mo, refine=20), "seed_enlargement": lambda: baselines.seed_router(mo, refine=20, how="enlargement"),
        "axis": lambda: baselines.axis_router(mo), "axis_3": lambda: baselines.axis_router(mo, axes=3, outliers=False),
    }[way]()


def partitioned(spark: SparkSession, sf_dir: str, way: str, data: str = "orders", p: OptimizerParams = P10) -> DataFrame:
    """A set under one of the partitioners."""
    route = router(spark, sf_dir, way, data, p)
    made = _sets.get((spark.sparkContext.applicationId, sf_dir, data))
    return route(made if made is not None else DATA[data](spark, sf_dir))


_indexes: dict[tuple, StoredIndex] = {}


def stored(spark: SparkSession, sf_dir: str, way: str = "optimal", kind: str = "box", data: str = "orders", p: OptimizerParams = P10, capacity: int = 102) -> StoredIndex:
    """A written index of a set under a partitioner, made once in a session."""
    root = checkpoint_folder(spark).rstrip("/")
    key = (spark.sparkContext.applicationId, root, sf_dir, way, kind, data, p, capacity)
    if key not in _indexes:
        _indexes[key] = store_index(partitioned(spark, sf_dir, way, data, p), f"{root}/index-{way}-{kind}-{data}-{capacity}-{time.time_ns()}", kind, capacity)
    return _indexes[key]


WAYS = ("optimal", "one", "quadrants", "seed", "seed_refined", "seed_enlargement", "axis", "axis_3")
#: The paper's own and its rivals.
RIVALS = ("optimal", "one", "seed_refined", "axis")
KINDS = ("box", "curve")


def _union(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def total_accesses(parted: DataFrame, queries: DataFrame, capacity: int = 102) -> DataFrame:
    """One row: leaf accesses of all queries, nodes, and objects answered."""
    objects = index_box.build_nodes(parted, capacity)
    nodes = index_box.node_boxes(objects)
    return index_box.candidate_nodes(nodes, queries).agg(F.count(F.lit(1)).alias("accesses"))


def partitioner_comparison(spark: SparkSession, sf_dir: str, data: str = "orders", ways: tuple[str, ...] = WAYS, t: int = 60) -> DataFrame:
    """way, accesses, swept: node accesses over all range queries and measured expansion of every partitioner."""
    rows = []
    for way in ways:
        objects = index_box.build_nodes(partitioned(spark, sf_dir, way, data))
        hits = index_box.candidate_nodes(index_box.node_boxes(objects), st.q_range(spark, sf_dir, t=t)).agg(F.count(F.lit(1)).alias("accesses"))
        swept = measures.layout_expansion(objects, 120.0).agg(F.sum("measured").alias("swept"), F.sum("nodes").alias("nodes"))
        rows.append(hits.crossJoin(swept).select(F.lit(way).alias("way"), "accesses", "nodes", "swept"))
    return _union(rows)


def best_of(comparison: DataFrame) -> DataFrame:
    """way, accesses, rank."""
    from pyspark.sql import Window

    return comparison.withColumn("rank", F.row_number().over(Window.orderBy("accesses", "way"))).select("way", "accesses", F.col("rank").cast("long").alias("rank"))  # as many rows as partitioners


def _range_answers(spark: SparkSession, sf_dir: str, data: str, label: str, value: int, q: DataFrame, way: str = "optimal", index: str = "box", capacity: int = 102) -> DataFrame:
    return stored(spark, sf_dir, way, index, data, capacity=capacity).range_counts(q).select(F.lit(label).alias("setting"), F.lit(value).cast("long").alias("value"), "qid", "answers")


def store_sixths(spark: SparkSession, sf_dir: str) -> None:
    """The sets by sixths, which lie in one another, as one stored table."""
    most = kept(st.mo_lineitem(spark, sf_dir, max(SIXTHS), keep_sixth=True), "sixths")
    for m in SIXTHS:
        _sets[spark.sparkContext.applicationId, sf_dir, f"lineitem-{m}"] = most.where(F.col("sixth") < m).drop("sixth")


def objects_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """setting, value (sixths of the objects), qid, answers of every range query."""
    store_sixths(spark, sf_dir)
    q = kept(st.q_range(spark, sf_dir))
    with ThreadPoolExecutor(AT_A_TIME) as pool:
        jobs = [pool.submit(inheritable_thread_target(spark)(_range_answers), spark, sf_dir, f"lineitem-{m}", "m", m, q) for m in SIXTHS]
        return _union([j.result() for j in jobs])


def _knn_answers(spark: SparkSession, sf_dir: str, data: str, label: str, value: int, q: DataFrame, index: str = "box") -> DataFrame:
    got = stored(spark, sf_dir, "optimal", index, data).neighbours(q)
    return got.select(F.lit(label).alias("setting"), F.lit(value).cast("long").alias("value"), "qid", "rank", "oid")


def _several(sets: dict[int, DataFrame]) -> DataFrame:
    """The query sets of a sweep as one, with the value of each in its ids."""
    return _union([q.withColumn("qid", F.col("qid") + F.lit(v).cast("long") * SETS) for v, q in sets.items()])


#: Ids of one query set lie below this.
SETS = 10_000_000


#: Indexes of a sweep that are built and queried at a time.
AT_A_TIME = 3


def sweep_accesses(spark: SparkSession, sf_dir: str, sets: dict[int, DataFrame], data: str = "orders", ways: tuple[str, ...] = RIVALS, capacity: int = 102) -> DataFrame:
    """way, kind, value, accesses, answers: leaf or page accesses and answers of each query set, for every partitioner under both indexes.

    The objects are stored once for all partitioners. An index that the sweep
    has written goes when its rows are counted, so that few are there at a time.
    Accesses and answers are counted without their pairs, whose number grows
    with objects times queries.
    """
    q, mo = kept(_several(sets)), stored_set(spark, sf_dir, data)
    root = f"{checkpoint_folder(spark).rstrip('/')}/sweep-{uuid.uuid4().hex}"
    value = F.expr(f"qid div {SETS}").alias("value")

    def counted(way: str, kind: str, route: Future) -> DataFrame:
        path = f"{root}/{way}-{kind}"
        index = store_index(route.result()(mo), path, kind, capacity)
        seen = index.accesses(q).groupBy(value).agg(F.sum("accesses").alias("accesses"))
        got = index.range_counts(q).groupBy(value).agg(F.sum("answers").alias("answers"))
        out = kept(seen.join(got, "value", "left").select(F.lit(way).alias("way"), F.lit(kind).alias("kind"), "value", "accesses", F.coalesce("answers", F.lit(0)).alias("answers")))
        dropped(spark, path)
        return out

    with ThreadPoolExecutor(AT_A_TIME) as pool:
        routes = {way: pool.submit(inheritable_thread_target(spark)(router), spark, sf_dir, way, data) for way in ways}  # before the jobs that wait for them
        jobs = [pool.submit(inheritable_thread_target(spark)(counted), way, kind, routes[way]) for way in ways for kind in KINDS]
        return _union([j.result() for j in jobs])


def objects_compared(spark: SparkSession, sf_dir: str) -> DataFrame:
    """way, kind, value (sixths of the objects), accesses, answers."""
    store_sixths(spark, sf_dir)
    return _union([sweep_accesses(spark, sf_dir, {m: st.q_range(spark, sf_dir)}, f"lineitem-{m}", ("optimal", "one", "axis")) for m in SIXTHS])


def sweep_times(spark: SparkSession, sf_dir: str, sets: dict[int, DataFrame], what: str, data: str = "orders", ways: tuple[str, ...] = RIVALS, capacity: int = 102) -> DataFrame:
    """experiment, setting, seconds of range queries or neighbours for each query set, partitioner and index."""
    rows = []
    for way in ways:
        for kind in KINDS:
            index = stored(spark, sf_dir, way, kind, data, capacity=capacity)
            for value, q in sets.items():
                got = measures.timed(what, lambda i=index, x=q: i.range(x) if what == "range" else i.neighbours(x), repeats=1, warmup=0)
                rows.append((f"{what} {kind} {value}", way, got["value"]))
    return _timings(rows, spark)


def _timings(rows: list[tuple[str, str, float]], spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(rows, "experiment string, setting string, seconds double")


def optimiser_times(spark: SparkSession, sf_dir: str, by: str) -> DataFrame:
    """Seconds of the optimiser by number of objects or of layers."""
    rows = []
    cases = [(f"m={m}", f"lineitem-{m}", OptimizerParams()) for m in SIXTHS] if by == "n" else [(f"q={q}", "orders", OptimizerParams(q=q)) for q in LAYERS]
    for setting, data, p in cases:
        start = time.perf_counter()
        opt.optimise(DATA[data](spark, sf_dir), p).plan.collect()  # as many rows as parts
        rows.append((f"optimiser by {by}", setting, time.perf_counter() - start))
    return _timings(rows, spark)


def throughput(spark: SparkSession, state: DataFrame, updates: DataFrame, route: Callable[[DataFrame], DataFrame], path: str) -> float:
    """Seconds that it takes to route updates by a partitioner's own rule and to write the rows that change, by part."""
    start = time.perf_counter()
    after, _ = update.apply_updates(state, updates, route)
    update.commit(after.join(updates.select("oid").distinct(), "oid", "left_semi"), path, 1)
    return time.perf_counter() - start


def memory_and_disk(spark: SparkSession, sf_dir: str, ways: tuple[str, ...] = RIVALS) -> DataFrame:
    """Seconds of range queries and neighbours over cached and over written indexes, and of updates, for each partitioner and both indexes."""
    rows = []
    root = f"{checkpoint_folder(spark)}/updates-{time.time_ns()}"
    q, k, mo = st.q_range(spark, sf_dir), st.q_knn(spark, sf_dir), stored_set(spark, sf_dir, "orders")
    for way in ways:
        for kind in KINDS:
            disk = stored(spark, sf_dir, way, kind)
            cached = StoredIndex(disk.path, kind, *(t.select("*").persist() for t in (disk.objects, disk.catalog, disk.stats)))
            for t in (cached.objects, cached.catalog, cached.stats):
                t.count()
            for store, index in (("memory", cached), ("disk", disk)):
                for name, fn in (("range", lambda i=index: i.range(q)), ("neighbours", lambda i=index: i.neighbours(k))):
                    rows.append((f"{store}: {name} {kind}", way, measures.timed(name, fn, repeats=1, warmup=0)["value"]))
            for t in (cached.objects, cached.catalog, cached.stats):
                t.unpersist()
        state = mo.withColumn("ts", F.lit(0).cast("timestamp")).withColumn("event_id", F.lit(0).cast("long"))
        new = state.withColumn("ts", F.lit(1).cast("timestamp")).withColumn("vx", -F.col("vx"))
        route = router(spark, sf_dir, way)
        rows.append(("updates", way, throughput(spark, state, new, route, f"{root}/{way}")))
    return _timings(rows, spark)


P25 = OptimizerParams(q=10, capacity=25)


def hourly_events(spark: SparkSession, sf_dir: str, rush: bool = False) -> DataFrame:
    return st.mo_events(spark, sf_dir, rush, one_object_per_event=True)


def hourly_plans(spark: SparkSession, sf_dir: str, p: OptimizerParams = P25, rush: bool = False) -> dict[int, opt.Optimised]:
    """Plans of all hours of the day, refreshed every hour."""
    key = (spark.sparkContext.applicationId, sf_dir, p, rush)
    if key not in _hours:
        _hours[key] = update.refresh_plan(hourly_events(spark, sf_dir, rush), p)
    return _hours[key]


_hours: dict[tuple, dict[int, opt.Optimised]] = {}
#: Parts of an hour are numbered from the hour times this.
HOUR = 1000


def hourly_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event under its own hour's plan; part is hour * HOUR + part, so that one index holds all hours."""
    plans = update.plans_by(hourly_plans(spark, sf_dir))
    ends = plans.groupBy("hr").agg(F.min("part").alias("first"), F.max("part").alias("last"))
    edges = plans.join(ends, "hr").select(
        F.col("hr").alias("p_hr"), (F.col("hr") * HOUR + F.col("part")).alias("part"), "quadrants", F.when(F.col("part") == F.col("first"), float("-inf")).otherwise(F.col("lo")).alias("lo"), F.when(F.col("part") == F.col("last"), float("inf")).otherwise(F.col("hi")).alias("hi")
    )
    rows = motion.valid(hourly_events(spark, sf_dir))
    out = rows.join(F.broadcast(edges), (F.col("hr") == F.col("p_hr")) & (F.col("speed") > F.col("lo")) & (F.col("speed") <= F.col("hi")))  # a row for each hour and part
    return out.select(*st.COLUMNS, "hr", "part", F.when(F.col("quadrants") == 1, motion.quadrant_of()).otherwise(0).alias("quadrant"))


def _hourly_index(spark: SparkSession, sf_dir: str) -> StoredIndex:
    root = checkpoint_folder(spark).rstrip("/")
    key = (spark.sparkContext.applicationId, root, sf_dir, "hours")
    if key not in _indexes:
        _indexes[key] = store_index(hourly_parts(spark, sf_dir), f"{root}/index-hours-{time.time_ns()}", "box", 25)
    return _indexes[key]


def _every_hour(queries: DataFrame) -> DataFrame:
    """A query set once for each hour, with the hour in its ids."""
    hours = queries.sparkSession.range(24).select(F.col("id").cast("int").alias("q_hr"))
    return queries.crossJoin(F.broadcast(hours)).withColumn("qid", F.col("qid") + F.col("q_hr") * SETS)


def hourly_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """setting, value (hour), qid, answers of every range query in every hour."""
    index, q = _hourly_index(spark, sf_dir), _every_hour(st.q_range(spark, sf_dir))
    hits = index_box.candidate_nodes(index.catalog, q, scope=F.expr(f"n.part div {HOUR} = q.q_hr"))
    rows = index.objects.join(hits, ["part", "quadrant", "node"]).join(F.broadcast(q), "qid").where(partitions.inside())
    return rows.groupBy("qid").agg(F.count(F.lit(1)).alias("answers")).select(F.lit("hr").alias("setting"), F.expr(f"qid div {SETS}").alias("value"), (F.col("qid") % SETS).alias("qid"), "answers")


def hourly_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """setting, value (hour), qid, rank, oid of every neighbour query in every hour."""
    index, q = _hourly_index(spark, sf_dir), _every_hour(st.q_knn(spark, sf_dir))
    got = query.knn_box(None, q, objects=index.objects.drop("hr"), nodes=index.catalog, scope=F.expr(f"n.part div {HOUR} = q.q_hr"))
    return got.select(F.lit("hr").alias("setting"), F.expr(f"qid div {SETS}").alias("value"), (F.col("qid") % SETS).alias("qid"), "rank", "oid")


def hourly_throughput(spark: SparkSession, sf_dir: str) -> DataFrame:
    """hr, way, updates, per_second: each hour's updates applied to the state before it, under the plan of that hour and with one part."""
    root, rows = f"{checkpoint_folder(spark)}/hours-{time.time_ns()}", []
    events = st.mo_events(spark, sf_dir)
    for hr, x in hourly_plans(spark, sf_dir).items():
        new = events.where(F.col("hr") == hr)
        old = motion.latest_status(events.where(F.col("hr") == (hr + 23) % 24), columns=update.STATE)
        n = new.count()
        for way, route in (("optimal", lambda r, plan=x.plan: partitions.assign_parts(r, plan)), ("one", partitions.single_part)):
            rows.append((hr, way, n, n / throughput(spark, old, new, route, f"{root}/{way}-{hr}")))
    return spark.createDataFrame(rows, "hr int, way string, updates long, per_second double")


def hourly_plan_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    plans = update.plans_by(hourly_plans(spark, sf_dir))
    return plans.select(F.col("hr").cast("int").alias("hr"), *[F.col(c).cast("long").alias(c) for c in ("part", "lo_layer", "hi_layer")], "quadrants")


def plan_regret(spark: SparkSession, sf_dir: str) -> DataFrame:
    """hr, regret_4, refresh: what the plan of each hour before costs with an injected peak, against the hour's own plan."""
    plans = hourly_plans(spark, sf_dir, rush=True)
    return _union([update.needs_refresh(plans[(h + 23) % 24], x).select(F.lit(h).alias("hr"), F.floor(F.col("regret") * 10000).cast("long").alias("regret_4"), "refresh") for h, x in plans.items() if (h + 23) % 24 in plans])


def quad_share_by_speed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """part, quadrants of the default plan: fast parts are split, slow ones are not."""
    return optimised(spark, sf_dir, OptimizerParams(q=10)).plan.select(F.col("part").cast("long").alias("part"), "quadrants")


def ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """variant, parts, accesses: what each choice of the estimate does to the plan and to the queries."""
    variants = {
        "default": {}, "grain off": {"quadrant_grain": "off"}, "grain on": {"quadrant_grain": "on"}, "grain region": {"quadrant_grain": "region"}, "rounding floor": {"node_rounding": "floor"}, "rounding exact": {"node_rounding": "exact"},
        "depth 0": {"max_depth": 0}, "depth 3": {"max_depth": 3}, "alpha 0.01": {"alpha": 0.01}, "bins 4": {"bins": 4}, "equal depth": {"layering": "equal_depth"}, "maximum speeds": {"representative": "max"}, "horizon 30": {"horizon": 30.0}, "clamped": {"clamp_quadrant": True},
    }
    rows = []
    for name, change in variants.items():
        x = optimised(spark, sf_dir, OptimizerParams(**({"q": 10} | change)))
        parted = partitions.assign_parts(st.mo_orders(spark, sf_dir), x.plan)
        rows.append(total_accesses(parted, st.q_range(spark, sf_dir)).crossJoin(x.plan.agg(F.count(F.lit(1)).alias("parts"))).select(F.lit(name).alias("variant"), "parts", "accesses"))
    return _union(rows)


def traffic_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vehicles under way and stopped each 30 seconds of the simulation."""
    legs = generator.traffic(spark, sf_dir)
    return _union([generator.traffic_at(legs, float(t)).agg(F.count(F.lit(1)).alias("vehicles"), F.sum((F.col("speed") == 0).cast("long")).alias("stopped")).select(F.lit(t).alias("t"), "vehicles", "stopped") for t in (0, 30, 60, 90)])


#: Pairs of queries and objects that a task compares, on average.
PAIRS = 400_000


def traffic_answers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """way, answers, truth, hits: range queries over the vehicles under way after a minute, planned for them, against the scan.

    Objects are dealt by oid before they meet the windows, those of an index
    too, so that pairs of answers and truth are compared in the task that makes
    them and none is written; there are as many tasks as their number asks for.
    """
    mo, q = kept(generator.traffic_at(generator.traffic(spark, sf_dir), 60.0), "traffic"), kept(st.q_range(spark, sf_dir, t=90))
    pairs = query.counts_in_windows(motion.valid(mo), q).agg(F.sum("answers")).first()[0] or 0
    tasks = max(200, int(spark.conf.get("spark.sql.shuffle.partitions")), pairs // PAIRS)

    def deal(rows: DataFrame) -> DataFrame:
        return rows.repartition(tasks, "oid")

    def box(parted: DataFrame) -> DataFrame:
        index = store_index(parted, f"{root}/index", "box")
        return query.range_box(None, q, objects=deal(index.objects), nodes=index.catalog)

    plan, truth = opt.optimise(mo, P10).plan, query.range_scan(deal(mo), q)
    ways = {"optimal box": lambda: box(partitions.assign_parts(mo, plan)), "optimal curve": lambda: query.range_curve(partitions.assign_parts(deal(mo), plan), q), "one box": lambda: box(partitions.single_part(mo))}
    out = []
    for name, way in ways.items():
        root = f"{checkpoint_folder(spark).rstrip('/')}/traffic-{uuid.uuid4().hex}"
        quality = measures.answer_quality(way(), truth).agg(*[F.sum(c).alias(c) for c in ("answers", "truth", "hits")])
        out.append(kept(quality.select(F.lit(name).alias("way"), "answers", "truth", "hits")))
        dropped(spark, root)
    return _union(out)


def _counts_sql(cases: list[tuple[str, int, str, str]]) -> str:
    return " UNION ALL ".join(f"SELECT '{label}' AS setting, CAST({value} AS BIGINT) AS value, qid, answers FROM ({o.range_counts(mo, q)})" for label, value, mo, q in cases)


def _knn_sql(cases: list[tuple[str, int, str, str]]) -> str:
    return " UNION ALL ".join(f"SELECT '{label}' AS setting, CAST({value} AS BIGINT) AS value, qid, rank, oid FROM ({o.knn_answers(mo, q)})" for label, value, mo, q in cases)


def add_workloads(add) -> None:
    r, k = st.q_range, st.q_knn
    add("w1_optimiser_time_by_objects", lambda s, d: optimiser_times(s, d, "n"))
    add("w2_optimiser_time_by_layers", lambda s, d: optimiser_times(s, d, "q"))
    add("w3_memory_and_disk", memory_and_disk)
    add("w4_cities_range", lambda s, d: _union([_range_answers(s, d, c, c, 0, r(s, d)) for c in ("mix-S", "mix-L", "mix-B")]), _counts_sql([(c, 0, o.orders(c), o.ranges()) for c in ("mix-S", "mix-L", "mix-B")]))
    add("w4_cities_neighbours", lambda s, d: _union([_knn_answers(s, d, c, c, 0, k(s, d)) for c in ("mix-S", "mix-L", "mix-B")]), _knn_sql([(c, 0, o.orders(c), o.knns()) for c in ("mix-S", "mix-L", "mix-B")]))
    add("w4_cities_compared", lambda s, d: _union([sweep_accesses(s, d, {0: r(s, d)}, c).withColumn("city", F.lit(c)) for c in ("mix-S", "mix-L", "mix-B")]))
    add("w5_objects_compared", objects_compared)
    add("w5_objects_neighbours", lambda s, d: _union([_knn_answers(s, d, f"lineitem-{m}", "m", m, k(s, d)) for m in SIXTHS]), _knn_sql([("m", m, o.lineitem(m), o.knns()) for m in SIXTHS]))
    add("w6_node_sizes_compared", lambda s, d: _union([sweep_accesses(s, d, {b: r(s, d)}, "orders", ("optimal", "one"), capacity_of(b)) for b in NODE_BYTES]))
    add("w7_times_compared", lambda s, d: sweep_accesses(s, d, {t: r(s, d, 400, t) for t in TIMES}))
    add("w7_times_neighbours_curve", lambda s, d: _union([_knn_answers(s, d, "orders", "t", t, k(s, d, 30, t), "curve") for t in TIMES]), _knn_sql([("t", t, o.orders(), o.knns(30, t)) for t in TIMES]))
    add("w8_windows_compared", lambda s, d: sweep_accesses(s, d, {x: r(s, d, x) for x in WINDOWS}))
    add("w8_windows_range_curve", lambda s, d: _union([_range_answers(s, d, "orders", "window", x, r(s, d, x), index="curve") for x in WINDOWS]), _counts_sql([("window", x, o.orders(), o.ranges(x)) for x in WINDOWS]))
    add("w9_neighbours_times", lambda s, d: sweep_times(s, d, {x: k(s, d, x) for x in (NEIGHBOURS[0], NEIGHBOURS[-1])}, "neighbours"))
    add("w9_neighbours_curve", lambda s, d: _union([_knn_answers(s, d, "orders", "k", x, k(s, d, x), "curve") for x in NEIGHBOURS]), _knn_sql([("k", x, o.orders(), o.knns(x)) for x in NEIGHBOURS]))
    add("w5_objects_range", objects_range, _counts_sql([("m", m, o.lineitem(m), o.ranges()) for m in SIXTHS]))
    add("w6_node_sizes_range", lambda s, d: _union([_range_answers(s, d, "orders", "bytes", b, r(s, d), capacity=capacity_of(b)) for b in NODE_BYTES]), _counts_sql([("bytes", b, o.orders(), o.ranges()) for b in NODE_BYTES]))
    add("w7_times_range", lambda s, d: _union([_range_answers(s, d, "orders", "t", t, r(s, d, 400, t)) for t in TIMES]), _counts_sql([("t", t, o.orders(), o.ranges(400, t)) for t in TIMES]))
    add("w7_times_range_curve", lambda s, d: _union([_range_answers(s, d, "orders", "t", t, r(s, d, 400, t), index="curve") for t in TIMES]), _counts_sql([("t", t, o.orders(), o.ranges(400, t)) for t in TIMES]))
    add("w7_times_neighbours", lambda s, d: _union([_knn_answers(s, d, "orders", "t", t, k(s, d, 30, t)) for t in TIMES]), _knn_sql([("t", t, o.orders(), o.knns(30, t)) for t in TIMES]))
    add("w8_windows_range", lambda s, d: _union([_range_answers(s, d, "orders", "window", x, r(s, d, x)) for x in WINDOWS]), _counts_sql([("window", x, o.orders(), o.ranges(x)) for x in WINDOWS]))
    add("w9_neighbours", lambda s, d: _union([_knn_answers(s, d, "orders", "k", x, k(s, d, x)) for x in NEIGHBOURS]), _knn_sql([("k", x, o.orders(), o.knns(x)) for x in NEIGHBOURS]))
    hours = o.events(oid="event_id")
    add("w10_hourly_plans", hourly_plan_rows, " UNION ALL ".join(f"SELECT * FROM (WITH {o.optimiser(f'SELECT oid, x, y, vx, vy, speed, t_ref FROM ({hours}) WHERE hr = {h}', c=25)} SELECT {h} AS hr, part, lo_layer, hi_layer, quadrants FROM plan)" for h in range(24)))
    add("w10_hours_range", hourly_range, _counts_sql([("hr", h, f"SELECT * FROM ({hours}) WHERE hr = {h}", o.ranges()) for h in range(24)]))
    add("w10_hours_neighbours", hourly_neighbours, _knn_sql([("hr", h, f"SELECT * FROM ({hours}) WHERE hr = {h}", o.knns()) for h in range(24)]))
    add("w10_hours_throughput", hourly_throughput)
    add("plan_regret", plan_regret)
    add("w11_traffic", traffic_rows)
    add("w11_traffic_range", traffic_answers)
    add("w12_ablations", ablations)
    add("w13_continuous_velocities", lambda s, d: _union([_range_answers(s, d, "embed", way, 0, r(s, d, 1000), way, capacity=25) for way in ("optimal", "seed", "axis")]), _counts_sql([(way, 0, o.embed(), o.ranges(1000)) for way in ("optimal", "seed", "axis")]))
    add("partitioners_compared", lambda s, d: best_of(partitioner_comparison(s, d)))
    add("partitioners_compared_dir_any", lambda s, d: best_of(partitioner_comparison(s, d, "dir-any")))
    add("quad_share_by_speed", quad_share_by_speed, f"WITH {o.optimiser(o.orders())} SELECT part, quadrants FROM plan")
    add("estimate_rank_correlation", estimate_rank_correlation)
    add("migration_after_refresh", migration_after_refresh)
    add_streams(add)


def estimate_rank_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spearman's correlation of estimated and measured expansion over plans, in hundredths."""
    x = optimised(spark, sf_dir, OptimizerParams(q=10))
    rows = []
    for name, plan in (("optimal", x.plan), *((f"{how}-{k}", opt.heuristic_plan(x.layers, x.cost, k, how)) for how, k in (("single", 1), ("equal_width", 2), ("equal_width", 3), ("equal_depth", 2), ("equal_depth", 4), ("each", 10)))):
        est = plan.agg(F.sum("cost").alias("estimated"))
        meas = measures.layout_expansion(index_box.build_nodes(partitions.assign_parts(st.mo_orders(spark, sf_dir), plan)), 120.0).agg(F.sum("measured").alias("measured"))
        rows.append(est.crossJoin(meas).withColumn("plan", F.lit(name)))
    return measures.rank_correlation(_union(rows), "estimated", "measured").select(F.floor(F.col("spearman") * 100 + F.lit(0.5)).cast("long").alias("spearman_100"))


def migration_after_refresh(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Objects that move when the plan of three equal widths gives way to the optimum, by old and new part."""
    x = optimised(spark, sf_dir, OptimizerParams(q=10))
    old = opt.heuristic_plan(x.layers, x.cost, 3, "equal_width")
    return update.migrate(st.mo_orders(spark, sf_dir), old, x.plan).groupBy(F.col("old_part").cast("long").alias("old_part"), F.col("new_part").cast("long").alias("new_part")).agg(F.count(F.lit(1)).alias("n"))


def add_streams(add) -> None:
    from kinetic.streaming import controller as c

    def into(spark: SparkSession, name: str) -> str:
        return f"{checkpoint_folder(spark)}/stream-{name}-{time.time_ns()}"

    def latest(s: SparkSession, d: str) -> DataFrame:
        """All updates through the stream, then the newest of each object."""
        rows = c.run_to_end(c.updates_source(s, d), into(s, "latest"))
        return motion.latest_status(rows).select("oid", "event_id", "speed")

    events = o.events()
    add("stream_latest", latest, f"SELECT oid, event_id, speed FROM (SELECT *, row_number() OVER (PARTITION BY oid ORDER BY us DESC, event_id DESC) AS rn FROM ({events})) WHERE rn = 1")

    def hourly(s: SparkSession, d: str) -> DataFrame:
        """Closed hours only reach the sink, so open ones at the end are told by the watermark."""
        rows = c.run_to_end(c.hourly_speeds(c.updates_source(s, d)), into(s, "hourly"))
        return rows.select(F.unix_micros("hour").alias("hour_us"), "bin", "n")

    last = f"(SELECT max(us) - 600000000 AS mark FROM ({events}))"
    add("stream_hourly_speed", hourly, f"SELECT us // 3600000000 * 3600000000 AS hour_us, CAST(floor(speed / 5) AS BIGINT) AS bin, count(*) AS n FROM ({events}), {last} WHERE us // 3600000000 * 3600000000 + 3600000000 <= mark GROUP BY 1, 2")

    def sessions(s: SparkSession, d: str) -> DataFrame:
        rows = c.run_to_end(c.trips(c.updates_source(s, d)), into(s, "trips"))
        return rows.select("oid", F.unix_micros("start").alias("start_us"), F.unix_micros("stop").alias("stop_us"), "n")

    gap = 6 * 3600 * 1000000
    add("stream_sessions", sessions, f"WITH e AS (SELECT oid, us, CASE WHEN us - lag(us) OVER (PARTITION BY oid ORDER BY us) < {gap} THEN 0 ELSE 1 END AS new FROM ({events})), g AS (SELECT *, sum(new) OVER (PARTITION BY oid ORDER BY us ROWS UNBOUNDED PRECEDING) AS g FROM e), z AS (SELECT oid, min(us) AS start_us, max(us) + {gap} AS stop_us, count(*) AS n FROM g GROUP BY oid, g) SELECT oid, start_us, stop_us, n FROM z, {last} WHERE stop_us <= mark")

    demo = [(1, 0, 1, 0.0, 8.0, 0, 1.0), (2, 1, 2, 8.0, 16.0, 1, 1.0), (3, 2, 3, 16.0, 1e9, 1, 1.0)]

    def controller(s: SparkSession, d: str, params: OptimizerParams | None) -> tuple[DataFrame, DataFrame, DataFrame]:
        """The controller over the events in four slices of time."""
        plan = s.createDataFrame(demo, "part int, lo_layer int, hi_layer int, lo double, hi double, quadrants int, cost double")
        path = into(s, "routed")
        folder = c.events_by_time(s, d, f"{path}/source")
        c.stream_controller(c.updates_source(s, folder, 1), plan, f"{path}/layout", f"{path}/checkpoint", params, "1 day").awaitTermination()
        return c.controlled(s, f"{path}/layout")

    part = "CASE WHEN speed <= 8 THEN 1 WHEN speed <= 16 THEN 2 ELSE 3 END"
    newest = f"(SELECT * FROM ({events}) QUALIFY row_number() OVER (PARTITION BY oid ORDER BY us DESC, event_id DESC) = 1)"
    add("stream_controller", lambda s, d: controller(s, d, None)[0].groupBy(F.col("part").cast("long").alias("part")).agg(F.count(F.lit(1)).alias("n")), f"SELECT part, count(*) AS n FROM (SELECT CAST({part} AS BIGINT) AS part FROM {newest}) GROUP BY part")
    # a slice of time is a batch; its newest status of each object meets the newest before
    place = f"{part} AS part, CASE WHEN speed <= 8 THEN 0 ELSE 2 * CAST(vx >= 0 AS INT) + CAST(vy >= 0 AS INT) END AS quadrant"
    add("stream_migrations", lambda s, d: controller(s, d, None)[1].groupBy(F.col("gen").cast("long").alias("gen"), "action").agg(F.count(F.lit(1)).alias("n")),
        f"WITH e AS (SELECT *, {place} FROM ({events})), b AS (SELECT min(us) AS a, max(us) - min(us) + 1 AS w FROM e), s AS (SELECT e.*, least(3, CAST(floor((us - a) * 4 / w::double) AS BIGINT)) AS gen FROM e, b), l AS (SELECT * FROM s QUALIFY row_number() OVER (PARTITION BY oid, gen ORDER BY us DESC, event_id DESC) = 1), "
        "m AS (SELECT oid, gen, part, quadrant, lag(part) OVER o AS p, lag(quadrant) OVER o AS q FROM l WINDOW o AS (PARTITION BY oid ORDER BY gen)) SELECT gen, CASE WHEN p IS NULL THEN 'insert' WHEN p = part AND q = quadrant THEN 'update' ELSE 'migrate' END AS action, count(*) AS n FROM m GROUP BY 1, 2")  # fmt: skip
    add("stream_replanned", lambda s, d: controller(s, d, OptimizerParams(q=10, capacity=25))[2].groupBy(F.col("gen").cast("long").alias("gen")).agg(F.count(F.lit(1)).alias("parts"), F.max("since").alias("since")))

    def sliding(s: SparkSession, d: str) -> DataFrame:
        rows = c.run_to_end(c.sliding_speeds(c.updates_source(s, d)), into(s, "sliding"))
        return rows.select(F.unix_micros("start").alias("start_us"), "n", F.floor(F.col("fastest") * 1000 + F.lit(0.5)).cast("long").alias("fastest_milli"))

    quarter = 900000000
    add("stream_sliding_speed", sliding, f"SELECT us // {quarter} * {quarter} - k * {quarter} AS start_us, count(*) AS n, CAST(floor(max(speed) * 1000 + 0.5) AS BIGINT) AS fastest_milli FROM ({events}), {last}, generate_series(0, 3) AS g(k) WHERE us // {quarter} * {quarter} - k * {quarter} + 3600000000 <= mark GROUP BY 1")
