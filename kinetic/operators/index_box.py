"""Time-parameterised boxes: leaf nodes of at most c objects with a box and a velocity box, and their parents."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kinetic.operators.counts import Asked, meeting

#: Columns of the domain that strips are cut at.
COLUMNS = 4096
_NODE = ["part", "quadrant", "node"]


def build_nodes(parted: DataFrame, capacity: int = 102, pack_at: float = 0.0, side: float = 10000.0, dealt: bool = False) -> DataFrame:
    """+node: objects packed by strips of x and runs of y at the time ``pack_at``.

    Strips are runs of narrow columns with about sqrt(N / c) * c objects each,
    from a count by column; runs are numbered inside a strip, so that no
    window holds a whole part. ``pack_at`` of half the horizon packs by where
    objects will be (velocity-aware). ``dealt``: tasks get ranges of strips, so
    that rows leave in the order of their nodes by one shuffle.
    """
    rows = parted.withColumn("_px", F.col("x") + F.col("vx") * (F.lit(pack_at) - F.col("t_ref"))).withColumn("_py", F.col("y") + F.col("vy") * (F.lit(pack_at) - F.col("t_ref")))
    rows = rows.withColumn("_col", F.least(F.lit(COLUMNS - 1), F.greatest(F.lit(0), F.floor(F.col("_px") / side * COLUMNS))).cast("int"))
    group = Window.partitionBy("part", "quadrant")
    counts = rows.groupBy("part", "quadrant", "_col").agg(F.count(F.lit(1)).alias("_n"))
    counts = counts.withColumn("_all", F.sum("_n").over(group)).withColumn("_before", F.sum("_n").over(group.orderBy("_col").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("_n"))
    strips = counts.select("part", "quadrant", "_col", F.expr(f"_before * cast(ceil(sqrt(_all / {capacity})) as bigint) div _all").alias("_strip"))
    rows = rows.join(F.broadcast(strips), ["part", "quadrant", "_col"])  # parts x quadrants x COLUMNS rows at most
    if dealt:
        rows = rows.repartitionByRange("part", "quadrant", "_strip")
    run = F.row_number().over(Window.partitionBy("part", "quadrant", "_strip").orderBy("_py", "oid"))
    return rows.withColumn("_run", run).withColumn("node", F.expr(f"_strip * 1048576 + (_run - 1) div {capacity}")).drop("_px", "_py", "_col", "_strip", "_run")


def node_boxes(objects: DataFrame, t0: float = 0.0) -> DataFrame:
    """part, quadrant, node, n, boxes of position at t0 and of velocity."""
    px, py = (F.col(c) + F.col(v) * (F.lit(t0) - F.col("t_ref")) for c, v in (("x", "vx"), ("y", "vy")))
    return objects.groupBy(*_NODE).agg(
        F.count(F.lit(1)).alias("n"), F.min(px).alias("xlo"), F.max(px).alias("xhi"), F.min(py).alias("ylo"), F.max(py).alias("yhi"),
        F.min("vx").alias("vxlo"), F.max("vx").alias("vxhi"), F.min("vy").alias("vylo"), F.max("vy").alias("vyhi"),
    )


def parents(nodes: DataFrame, fanout: int = 102) -> DataFrame:
    """+parent and the parents' boxes: runs of ``fanout`` nodes of a strip."""
    return nodes.withColumn("parent", F.expr(f"(node div 1048576) * 1048576 + (node % 1048576) div {fanout}"))


def parent_boxes(nodes: DataFrame, fanout: int = 102) -> DataFrame:
    up = parents(nodes, fanout).groupBy("part", "quadrant", "parent")
    lo, hi = ("xlo", "ylo", "vxlo", "vylo"), ("xhi", "yhi", "vxhi", "vyhi")
    return up.agg(F.sum("n").alias("n"), *[F.min(c).alias(c) for c in lo], *[F.max(c).alias(c) for c in hi]).withColumnRenamed("parent", "node")


def _meets(dt: Column) -> Column:
    """The node's box, grown for dt, meets the window q*. Works forward and backward in time."""
    xlo, xhi = F.least(F.col("vxlo") * dt, F.col("vxhi") * dt), F.greatest(F.col("vxlo") * dt, F.col("vxhi") * dt)
    ylo, yhi = F.least(F.col("vylo") * dt, F.col("vyhi") * dt), F.greatest(F.col("vylo") * dt, F.col("vyhi") * dt)
    return (F.col("n.xlo") + xlo <= F.col("q.xhi")) & (F.col("n.xhi") + xhi >= F.col("q.xlo")) & (F.col("n.ylo") + ylo <= F.col("q.yhi")) & (F.col("n.yhi") + yhi >= F.col("q.ylo"))


def candidate_nodes(nodes: DataFrame, queries: DataFrame, t0: float = 0.0, two_levels: bool = True, scope: Column | None = None) -> DataFrame:
    """qid, part, quadrant, node: leaves whose grown box meets the window at the query's time.

    ``two_levels`` tests parents first; leaves then join by their parent. The
    queries are a given, small set; the nodes are not broadcast. ``scope``: a
    condition on n (nodes) and q (queries) that has to hold besides.
    """
    q = F.broadcast(queries.alias("q"))
    dt = F.col("t") - F.lit(t0)
    meets = _meets(dt) if scope is None else _meets(dt) & scope
    if not two_levels:
        return nodes.alias("n").join(q, meets).select("qid", "part", "quadrant", "node")
    tops = parent_boxes(nodes).alias("n").join(q, meets).select("qid", "part", "quadrant", F.col("node").alias("parent"))
    leaves = parents(nodes).join(tops, ["part", "quadrant", "parent"]).alias("n")
    return leaves.join(q, (F.col("n.qid") == F.col("q.qid")) & _meets(dt)).select(F.col("n.qid").alias("qid"), "part", "quadrant", "node")


def visited_nodes(nodes: DataFrame, queries: DataFrame, t0: float = 0.0, two_levels: bool = True) -> DataFrame:
    """part, quadrant, node: leaves (below such parents, with ``two_levels``) whose grown box meets the window of any query. A node stops at the first."""
    return _visited(nodes, queries, t0, two_levels).select(*_NODE)


def _visited(nodes: DataFrame, queries: DataFrame, t0: float, two_levels: bool) -> DataFrame:
    q = F.broadcast(queries.alias("q"))
    meets = _meets(F.col("q.t") - F.lit(t0))
    if two_levels:
        tops = parent_boxes(nodes).alias("n").join(q, meets, "left_semi").select("part", "quadrant", F.col("node").alias("parent"))
        nodes = parents(nodes).join(tops, ["part", "quadrant", "parent"], "left_semi")
    return nodes.alias("n").join(q, meets, "left_semi")


#: Boxes of a task that are counted at a time, and windows up to which counts are made from arrays of them.
COUNTED, MOST_WINDOWS = 1 << 20, 2_000_000


def count_nodes(nodes: DataFrame, queries: DataFrame, t0: float = 0.0) -> DataFrame:
    """qid, accesses: how many leaves ``candidate_nodes`` gives for each query that has any, without their pairs.

    Leaves that no query meets, or whose parent none meets, drop out first; the
    others' boxes are grown for each time that queries ask for (few) and
    counted against the windows of that time. Windows that end before they
    begin, and bounds that are no numbers, meet the leaves one by one.
    """
    bounds = ("xlo", "xhi", "ylo", "yhi", "t")
    plain = F.expr("xlo <= xhi AND ylo <= yhi AND " + " AND ".join(f"{c} IS NOT NULL AND NOT isnan({c})" for c in bounds))
    asked, others = queries.where(plain), queries.where(~F.coalesce(plain, F.lit(False)))
    one_by_one = lambda q: candidate_nodes(nodes, q, t0).groupBy("qid").agg(F.count(F.lit(1)).alias("accesses"))
    if asked.count() > MOST_WINDOWS:
        return one_by_one(queries)
    windows = Asked(asked)
    if not windows.times:
        return one_by_one(others)
    dt = F.col("_t") - F.lit(t0)
    grown = [F.col(f"{a}lo") + F.least(F.col(f"v{a}lo") * dt, F.col(f"v{a}hi") * dt) if low else F.col(f"{a}hi") + F.greatest(F.col(f"v{a}lo") * dt, F.col(f"v{a}hi") * dt) for a in "xy" for low in (True, False)]
    boxes = _visited(nodes, asked, t0, True).crossJoin(windows.times_of(nodes.sparkSession)).select("_i", *[c.alias(f"_b{i}") for i, c in enumerate(grown)])
    counts = windows.counts(boxes, meeting, "accesses", COUNTED)
    return counts if others.isEmpty() else counts.unionByName(one_by_one(others))


def with_distances(rows: DataFrame, t0: float = 0.0) -> DataFrame:
    """Nodes beside queries +mind2, maxd2: squared distances of the centre to the nearest and farthest place a member can have at the query's time."""
    dt = F.col("t") - F.lit(t0)
    x0, x1 = F.col("xlo") + F.least(F.col("vxlo") * dt, F.col("vxhi") * dt), F.col("xhi") + F.greatest(F.col("vxlo") * dt, F.col("vxhi") * dt)
    y0, y1 = F.col("ylo") + F.least(F.col("vylo") * dt, F.col("vyhi") * dt), F.col("yhi") + F.greatest(F.col("vylo") * dt, F.col("vyhi") * dt)
    near = [F.greatest(a - F.col(c), F.lit(0.0), F.col(c) - b) for a, b, c in ((x0, x1, "cx"), (y0, y1, "cy"))]
    far = [F.greatest(F.abs(a - F.col(c)), F.abs(b - F.col(c))) for a, b, c in ((x0, x1, "cx"), (y0, y1, "cy"))]
    return rows.withColumn("mind2", near[0] * near[0] + near[1] * near[1]).withColumn("maxd2", far[0] * far[0] + far[1] * far[1])


def nearest_nodes(nodes: DataFrame, queries: DataFrame, most: int, t0: float = 0.0, scope: Column | None = None) -> DataFrame:
    """qid, k, cx, cy, t, part, quadrant, node: leaves that may hold one of the k nearest.

    Every parent is met by every query; leaves only where their parent may hold
    a neighbour. ``most``: the greatest k.
    """
    tops = parent_boxes(nodes).alias("n").join(F.broadcast(queries.alias("q")), scope if scope is not None else F.lit(True))
    tops = _may_hold(with_distances(tops, t0), most).select("qid", "k", "cx", "cy", "t", "part", "quadrant", F.col("node").alias("parent"))
    leaves = parents(nodes).join(tops, ["part", "quadrant", "parent"])
    return _may_hold(with_distances(leaves, t0), most).select("qid", "k", "cx", "cy", "t", *_NODE)


def _may_hold(far: DataFrame, most: int) -> DataFrame:
    """Rows that may hold one of the query's k nearest: not farther than the farthest member of the first nodes that hold k together."""
    w = Window.partitionBy("qid").orderBy("maxd2", *_NODE)
    # k nodes hold k objects; the literal bound keeps as many rows of each task before the shuffle
    first = far.select("qid", "k", "n", "maxd2", *_NODE).withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= most)
    first = first.withColumn("_sum", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    certain = first.groupBy("qid").agg(F.coalesce(F.min(F.when(F.col("_sum") >= F.col("k"), F.col("maxd2"))), F.lit(float("inf"))).alias("_tau"))
    return far.join(F.broadcast(certain), "qid").where("mind2 <= _tau").drop("_tau")
