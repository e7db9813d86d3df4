"""Predictive range and nearest-neighbour queries, over scans, boxes and curve keys."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from kinetic.functions.motion import at_time, valid
from kinetic.operators import index_box, index_curve
from kinetic.operators.counts import Asked, held
from kinetic.operators.partitions import fan_out, inside, part_stats
from kinetic.sources.shared import kept

_ANSWER = ["qid", "oid", "px", "py"]


def _answers(rows: DataFrame) -> DataFrame:
    return rows.withColumn("px", at_time(F.col("t"))).withColumn("py", at_time(F.col("t"), "y", "vy")).select(*_ANSWER)


#: Cells of a side of the grid that places at the queries' times and windows meet in.
CELLS = 64


def _cell(c: str, side: float) -> Column:
    return F.least(F.lit(CELLS - 1), F.greatest(F.lit(0), F.floor(F.col(c) / side * CELLS))).cast("int")


def _placed(objects: DataFrame, times: DataFrame, cover: index_curve.Cover | None, *more: str) -> DataFrame:
    """oid, px, py: the objects at each of the times (_t and ``more``), with what ``cover`` asks for."""
    rows = objects.crossJoin(F.broadcast(times)) if cover is None else cover.placed(objects, times)
    rows = rows.withColumns({"px": at_time(F.col("_t")), "py": at_time(F.col("_t"), "y", "vy")})
    return rows.select("oid", "_t", "px", "py", *more, *([] if cover is None else cover.columns()))


def in_windows(objects: DataFrame, queries: DataFrame, side: float = 10000.0, cover: index_curve.Cover | None = None) -> DataFrame:
    """qid, oid, px, py: the objects in each window at its time.

    Every object is placed at every time that queries ask for (few), and meets
    in one cell the windows that cover it; places beyond the grid are in its
    outer cells, as the windows' edges are. The queries' cells are broadcast
    behind a check of their number. ``cover``: what a curve's runs leave out of
    keyed objects is left out.
    """
    times = queries.where("xlo <= xhi AND ylo <= yhi AND t IS NOT NULL").select(F.col("t").alias("_t")).distinct()
    return _met(_placed(objects, times, cover), queries, cover, side)


def _met(placed: DataFrame, queries: DataFrame, cover: index_curve.Cover | None, side: float = 10000.0) -> DataFrame:
    def cell(c: str) -> Column:
        return _cell(c, side)

    asked = queries.where("xlo <= xhi AND ylo <= yhi AND t IS NOT NULL")
    n = asked.agg(F.sum((cell("xhi") - cell("xlo") + 1).cast("long") * (cell("yhi") - cell("ylo") + 1))).first()[0] or 0
    windows = asked.select("qid", F.col("t").alias("_t"), "xlo", "xhi", "ylo", "yhi", F.explode(F.sequence(cell("xlo"), cell("xhi"))).alias("_gx"), F.sequence(cell("ylo"), cell("yhi")).alias("_ys"))
    windows = windows.withColumn("_gy", F.explode("_ys")).withColumn("_cell", (F.col("_gx") * CELLS + F.col("_gy")).cast("long")).drop("_gx", "_gy", "_ys")
    placed = placed.withColumn("_cell", (cell("px") * CELLS + cell("py")).cast("long"))
    inside_ = (F.col("px") >= F.col("xlo")) & (F.col("px") <= F.col("xhi")) & (F.col("py") >= F.col("ylo")) & (F.col("py") <= F.col("yhi"))
    windows = F.broadcast(windows) if n <= BROADCAST_CELLS else windows.hint("shuffle_hash")
    return placed.join(windows, ["_t", "_cell"]).where(inside_ if cover is None else inside_ & cover.holds()).select(*_ANSWER)


#: Objects that are counted at a time, and windows up to which counts are made from arrays of them.
COUNTED, MOST_WINDOWS = 1 << 22, 2_000_000


def counts_in_windows(objects: DataFrame, queries: DataFrame, cover: index_curve.Cover | None = None) -> DataFrame:
    """qid, answers: how many objects ``in_windows`` finds for each query that has any, without their pairs.

    Every object is placed at every time that queries ask for (few); each task
    counts its places, COUNTED at a time. Queries are a given, small set. With
    ``cover``, places that are not sure to be covered (``Cover.sure``) are
    met one by one.
    """
    asked = queries.where("xlo <= xhi AND ylo <= yhi AND t IS NOT NULL").select("qid", "xlo", "xhi", "ylo", "yhi", "t")
    if asked.count() > MOST_WINDOWS:
        return in_windows(objects, queries, cover=cover).groupBy("qid").agg(F.count(F.lit(1)).alias("answers"))
    windows = Asked(asked)
    if not windows.times:
        return objects.select(F.lit(None).cast(queries.schema["qid"].dataType).alias("qid"), F.lit(0).cast("long").alias("answers")).limit(0)
    windows.windows = [np.where(np.isnan(a), np.inf, a) if i % 2 else a for i, a in enumerate(windows.windows)]  # Spark orders what is no number last
    placed = _placed(objects, windows.times_of(objects.sparkSession), cover, "_i").where("px IS NOT NULL AND py IS NOT NULL")
    if cover is None:
        return windows.counts(placed.select("_i", "px", "py"), held, "answers", COUNTED)
    seen = Observation()
    sure = placed.select("_i", "px", "py", "_sure").observe(seen, F.count_if(~F.col("_sure")).alias("others")).where("_sure").drop("_sure")
    counts = kept(windows.counts(sure, held, "answers", COUNTED))
    if not seen.get["others"]:
        return counts
    others = _met(placed.where("NOT _sure"), asked, cover).groupBy("qid").agg(F.count(F.lit(1)).alias("answers"))
    return counts.unionByName(others).groupBy("qid").agg(F.sum("answers").alias("answers"))


def range_scan(mo: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, oid, px, py: every object, at the queries' times, against the windows; the truth of the others. Queries are a given, small set."""
    return in_windows(valid(mo), queries)


def range_box(parted: DataFrame | None, queries: DataFrame, capacity: int = 102, two_levels: bool = True, objects: DataFrame | None = None, nodes: DataFrame | None = None) -> DataFrame:
    """By boxes: leaves that meet a window, then the objects in them. ``objects`` and ``nodes``: an index that is there already.

    The queries go through the index together: a leaf is read once, whatever
    number of windows it meets, and its objects meet these windows in cells.
    """
    given = nodes is not None
    objects = objects if objects is not None else index_box.build_nodes(parted, capacity)
    nodes = nodes if given else index_box.node_boxes(objects)
    visited = index_box.visited_nodes(nodes, queries, two_levels=two_levels)
    visited = F.broadcast(visited) if given and nodes.count() <= BROADCAST_LEAVES else visited
    return in_windows(objects.join(visited, ["part", "quadrant", "node"], "left_semi"), queries)


#: Leaves of an index up to which those that are visited are broadcast.
BROADCAST_LEAVES = 1_000_000


def range_box_counts(objects: DataFrame, nodes: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, answers: the sizes of ``range_box``'s answers, from the objects in the same leaves."""
    visited = index_box.visited_nodes(nodes, queries)
    visited = F.broadcast(visited) if nodes.count() <= BROADCAST_LEAVES else visited
    return counts_in_windows(objects.join(visited, ["part", "quadrant", "node"], "left_semi"), queries)


def range_curve(parted: DataFrame | None, queries: DataFrame, bits: int = index_curve.BITS, curve: str = "z", keyed: DataFrame | None = None, stats: DataFrame | None = None) -> DataFrame:
    """By curve keys: runs of keys, then the objects in them. ``keyed`` and ``stats``: an index that is there already.

    The queries go through the index together: a key is read once, whatever
    number of runs it lies in, and its objects meet the windows in cells. An
    object answers a query only if its key lies in that query's runs.
    """
    return in_windows(*_read_keys(parted, queries, bits, curve, keyed, stats))


def _read_keys(parted: DataFrame | None, queries: DataFrame, bits: int, curve: str, keyed: DataFrame | None, stats: DataFrame | None) -> tuple:
    """Objects whose key lies in a run of any query, the queries, the grid's side and the check of each query's own runs."""
    keyed = keyed if keyed is not None else index_curve.curve_keys(parted, bits, curve)
    stats = kept(stats if stats is not None else index_curve.key_stats(keyed))
    visited = index_curve.visited_keys(queries, stats, bits, curve)
    return keyed.join(F.broadcast(visited), ["part", "quadrant", "label", "key"], "left_semi"), queries, 10000.0, index_curve.Cover(stats, bits)


def range_curve_counts(queries: DataFrame, keyed: DataFrame, stats: DataFrame) -> DataFrame:
    """qid, answers: the sizes of ``range_curve``'s answers, from the objects under the same keys."""
    objects, queries, _, cover = _read_keys(None, queries, index_curve.BITS, "z", keyed, stats)
    return counts_in_windows(objects, queries, cover)


def curve_candidates(parted: DataFrame | None, queries: DataFrame, bits: int = index_curve.BITS, curve: str = "z", keyed: DataFrame | None = None, stats: DataFrame | None = None) -> DataFrame:
    keyed = keyed if keyed is not None else index_curve.curve_keys(parted, bits, curve)
    runs = index_curve.curve_intervals(queries, stats if stats is not None else index_curve.key_stats(keyed), bits, curve)
    return index_curve.probe_intervals(keyed, runs)


#: Cells of a side of the grid that windows and objects meet in where their bounds are not literal.
GRID = 16
#: Windows by part up to which literal bounds are written into the scans, and cells of windows up to which they are broadcast.
LITERAL_WINDOWS, BROADCAST_CELLS = 512, 2_000_000


def range_pushdown(parted: DataFrame, queries: DataFrame, stats: DataFrame | None = None, side: float = 10000.0) -> DataFrame:
    """By bounds on the stored columns that each part's velocities imply.

    A few windows become literals: each part is one scan, whose filters prune
    partitions and row groups of a layout. More of them meet the objects in the
    cells of a grid that they cover, by an equi-join. ``stats`` (a row for each
    part and quadrant) come from the objects if the layout has none.
    """
    f = kept(fan_out(queries, stats if stats is not None else part_stats(parted)))
    n = f.count()
    if n <= LITERAL_WINDOWS:
        return _literal_scans(parted, queries, f.collect())

    def cell(c: str) -> Column:
        return F.least(F.lit(GRID - 1), F.greatest(F.lit(0), F.floor(F.col(c) / side * GRID))).cast("int")

    across = f.withColumn("gx", F.explode(F.sequence(cell("sxlo"), cell("sxhi")))).withColumn("gy", F.explode(F.sequence(cell("sylo"), cell("syhi")))).alias("f")
    across = F.broadcast(across) if n * GRID * GRID <= BROADCAST_CELLS else across
    o = parted.withColumn("gx", cell("x")).withColumn("gy", cell("y")).alias("o")
    met = (F.col("o.part") == F.col("f.part")) & (F.col("o.quadrant") == F.col("f.quadrant")) & (F.col("o.gx") == F.col("f.gx")) & (F.col("o.gy") == F.col("f.gy"))
    rows = o.join(across, met & F.col("o.x").between(F.col("sxlo"), F.col("sxhi")) & F.col("o.y").between(F.col("sylo"), F.col("syhi")))
    return _answers(rows.select("o.*", *[F.col(f"f.{c}") for c in ("qid", "t", "xlo", "xhi", "ylo", "yhi")]).where(inside()))


def _literal_scans(parted: DataFrame, queries: DataFrame, windows: list) -> DataFrame:
    """One scan for each part and quadrant, with the bounds of all its windows as literals."""
    by: dict[tuple, Column] = {}
    for w in windows:
        key = (w["part"], w["quadrant"])
        met = F.col("x").between(w["sxlo"], w["sxhi"]) & F.col("y").between(w["sylo"], w["syhi"])
        by[key] = by[key] | met if key in by else met
    out = None
    for (part, quadrant), met in by.items():
        one = parted.where((F.col("part") == part) & (F.col("quadrant") == quadrant)).where(met)
        out = one if out is None else out.unionByName(one)
    out = out if out is not None else parted.limit(0)
    return _answers(out.join(F.broadcast(queries), inside()))


def layout_range(spark, path: str, query: dict) -> DataFrame:
    """One query over a written layout: literal bounds for each part reach the Parquet scan as pushed filters."""
    one = spark.createDataFrame([tuple(query[c] for c in ("qid", "xlo", "ylo", "xhi", "yhi", "t"))], "qid long, xlo double, ylo double, xhi double, yhi double, t double")
    return range_pushdown(spark.read.parquet(path), one)


def _dist2() -> Column:
    dx, dy = at_time(F.col("t")) - F.col("cx"), at_time(F.col("t"), "y", "vy") - F.col("cy")
    return dx * dx + dy * dy


def greatest_k(queries: DataFrame) -> int:
    """The largest k of a given, small set of queries."""
    return int(queries.agg(F.max("k")).first()[0] or 0)


def top_k(rows: DataFrame, most: int) -> DataFrame:
    """The k nearest of each query (ties by id). ``most``, the greatest k, is a literal, so that no task sends more rows of a query into the shuffle."""
    w = Window.partitionBy("qid").orderBy("dist2", "oid")
    return rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= most).where("rank <= k").select("qid", F.col("rank").cast("long").alias("rank"), "oid", "dist2", "k")


def knn_scan(mo: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, rank, oid, dist2 over every object; the truth of the others."""
    rows = valid(mo).join(F.broadcast(queries), F.lit(True)).select("qid", "oid", _dist2().alias("dist2"), "k")
    return top_k(rows, greatest_k(queries)).drop("k")


def knn_box(parted: DataFrame | None, queries: DataFrame, capacity: int = 102, objects: DataFrame | None = None, nodes: DataFrame | None = None, scope: Column | None = None) -> DataFrame:
    """By boxes: parents, then leaves that may hold a neighbour, then the objects in them. ``objects`` and ``nodes``: an index that is there already."""
    objects = objects if objects is not None else index_box.build_nodes(parted, capacity)
    nodes = nodes if nodes is not None else index_box.node_boxes(objects)
    most = greatest_k(queries)
    rows = objects.join(index_box.nearest_nodes(nodes, queries, most, scope=scope), ["part", "quadrant", "node"]).select("qid", "oid", _dist2().alias("dist2"), "k")
    return top_k(rows, most).drop("k")


def knn_merged(parted: DataFrame, queries: DataFrame) -> DataFrame:
    """The k nearest of every part, then of those."""
    most = greatest_k(queries)
    rows = parted.join(F.broadcast(queries), F.lit(True)).select("qid", "part", "oid", _dist2().alias("dist2"), "k")
    local = Window.partitionBy("qid", "part").orderBy("dist2", "oid")
    near = rows.withColumn("_r", F.row_number().over(local)).where(F.col("_r") <= most).where("_r <= k")
    return top_k(near.drop("_r", "part"), most).drop("k")


def knn_growing(parted: DataFrame | None, queries: DataFrame, side: float = 10000.0, bits: int = index_curve.BITS, keyed: DataFrame | None = None, stats: DataFrame | None = None) -> DataFrame:
    """By range queries over curve keys: a radius from the density, doubled for the queries that have fewer than k objects inside it, until all are answered."""
    total = (keyed if keyed is not None else parted).count()
    if not total:
        return knn_scan(keyed if keyed is not None else parted, queries)
    most = greatest_k(queries)
    reach = F.lit(side) * F.sqrt(F.col("k") / (math.pi * total))
    todo, out = queries.withColumn("radius", reach), None
    while True:
        box = todo.select("qid", (F.col("cx") - F.col("radius")).alias("xlo"), (F.col("cy") - F.col("radius")).alias("ylo"), (F.col("cx") + F.col("radius")).alias("xhi"), (F.col("cy") + F.col("radius")).alias("yhi"), "t")
        near = curve_candidates(parted, box, bits, keyed=keyed, stats=stats).join(F.broadcast(todo), "qid").select("qid", "oid", _dist2().alias("dist2"), "k", "radius").where("dist2 <= radius * radius")
        best = kept(top_k(near, most))
        full = best.groupBy("qid", "k").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= F.least(F.col("k"), F.lit(total))).select("qid")
        part = best.join(F.broadcast(full), "qid", "left_semi")
        out = part if out is None else out.unionByName(part)
        todo = kept(todo.join(F.broadcast(full), "qid", "left_anti").withColumn("radius", F.col("radius") * 2))
        if todo.isEmpty():
            return out.drop("k")


def last_known(samples: DataFrame, queries: DataFrame) -> DataFrame:
    """What a store of timestamped places answers: objects whose last known place lies in the window."""
    from kinetic.functions.motion import latest_status

    rows = latest_status(samples).join(F.broadcast(queries), F.col("x").between(F.col("xlo"), F.col("xhi")) & F.col("y").between(F.col("ylo"), F.col("yhi")))
    return rows.select("qid", "oid", F.col("x").alias("px"), F.col("y").alias("py"))
