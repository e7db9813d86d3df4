"""Quad trees of uniform cells, by layer and merged over ranges of layers.

Cells are (level, code) with the base-4 path as code; all steps after the
count are tables of at most q * 4**depth rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kinetic.plans.domain import layered, sums_of_speed
from kinetic.plans.params import OptimizerParams


def cell_code(p: OptimizerParams, depth: int, x: str = "x", y: str = "y") -> Column:
    """Path of the cell that holds a point; points outside the domain count to its border."""
    cells = 1 << depth
    gx, gy = (F.least(F.lit(cells - 1), F.greatest(F.lit(0), F.floor((F.col(c) - o) / p.side * cells))).cast("long") for c, o in ((x, p.x0), (y, p.y0)))
    code = F.lit(0).cast("long")
    for i in range(depth):
        code = code.bitwiseOR(F.shiftleft(F.shiftright(gx, i).bitwiseAND(F.lit(1)), 2 * i)).bitwiseOR(F.shiftleft(F.shiftright(gy, i).bitwiseAND(F.lit(1)), 2 * i + 1))
    return code


def finest_counts(mo: DataFrame, p: OptimizerParams, *by: str) -> DataFrame:
    """by, edge, top, width, code, n, sum, most at the deepest counted level: the one step that reads every object."""
    rows = layered(mo, p, *by).select(*by, "edge", "top", "width", "speed", cell_code(p, p.counted_depth).alias("code"))
    return rows.groupBy(*by, "edge", "top", "width", "code").agg(*sums_of_speed())


def _renumbered(cube: DataFrame, layers: DataFrame) -> DataFrame:
    return cube.join(F.broadcast(layers.select("layer", "edge")), "edge").select("layer", "level", "code", "n")


def cell_counts(mo: DataFrame, p: OptimizerParams, layers: DataFrame) -> DataFrame:
    """layer, level, code, n for all levels: counted once at the deepest level, then summed over path prefixes."""
    return cells_of(finest_counts(mo, p), p, layers)


def cells_of(finest: DataFrame, p: OptimizerParams, layers: DataFrame) -> DataFrame:
    """``cell_counts`` from ``finest_counts``."""
    d = p.counted_depth
    levels = finest.select("edge", "code", "n", F.explode(F.sequence(F.lit(0), F.lit(d))).alias("level"))
    cube = levels.select("edge", "level", F.expr(f"shiftright(code, 2 * ({d} - level))").alias("code"), "n").groupBy("edge", "level", "code").agg(F.sum("n").alias("n"))
    return _renumbered(cube, layers)


def cell_counts_rollup(mo: DataFrame, p: OptimizerParams, layers: DataFrame) -> DataFrame:
    """The same cube by one rollup over the digits of the path."""
    d = p.counted_depth
    digits = [f"_d{i}" for i in range(1, d + 1)]
    rows = finest_counts(mo, p).select("edge", "n", *[F.expr(f"shiftright(code, {2 * (d - i)}) & 3").alias(c) for i, c in enumerate(digits, 1)])
    cube = rows.rollup("edge", *digits).agg(F.sum("n").alias("n"), F.grouping("edge").alias("_all"), *[F.grouping(c).alias(f"g{c}") for c in digits]).where("_all = 0")
    level = sum((1 - F.col(f"g{c}") for c in digits), F.lit(0)).cast("int")
    code = F.lit(0).cast("long")
    for c in digits:
        code = F.when(F.col(f"g{c}") == 1, code).otherwise(code * 4 + F.coalesce(F.col(c), F.lit(0)))
    return _renumbered(cube.select("edge", level.alias("level"), code.alias("code"), "n"), layers)


def uniformity(cells: DataFrame, p: OptimizerParams) -> DataFrame:
    """layer, level, code, n, stat, uniform: chi-square of the counts in the children (2 x 2) or grandchildren (4 x 4)."""
    down = 1 if p.bins == 2 else 2
    bins = p.bins * p.bins
    parts = cells.where(F.col("level") >= down).groupBy("layer", (F.col("level") - down).alias("level"), F.shiftright("code", 2 * down).alias("code")).agg(F.sum(F.col("n") * F.col("n")).alias("_sq"), F.sum("n").alias("n"))
    parts = parts.where(F.col("level") < p.max_depth)
    stat = F.col("_sq") * bins / F.col("n") - F.col("n")
    return parts.withColumn("stat", stat).select("layer", "level", "code", "n", "stat", ((F.col("stat") <= p.critical) | (F.col("stat") <= F.col("n") * p.effect)).cast("int").alias("uniform"))


def split_cells(tested: DataFrame) -> DataFrame:
    """layer, level, code of the cells that a layer's tree splits: not uniform, and neither is any cell above."""
    rough = tested.where("uniform = 0").select("layer", "level", "code")
    chain = rough.withColumn("up", F.explode(F.sequence(F.lit(0), F.col("level")))).withColumn("above", F.expr("shiftright(code, 2 * (level - up))"))
    met = chain.join(rough.select(F.col("layer").alias("l2"), F.col("level").alias("up"), F.col("code").alias("above")).withColumnRenamed("l2", "layer"), ["layer", "up", "above"])
    return met.groupBy("layer", "level", "code").agg(F.count(F.lit(1)).alias("_c")).where("_c = level + 1").drop("_c")


def _children(cells: DataFrame) -> DataFrame:
    return cells.withColumn("_k", F.explode(F.array(*[F.lit(i) for i in range(4)]))).withColumn("code", F.col("code") * 4 + F.col("_k")).withColumn("level", F.col("level") + 1).drop("_k")


def tree_leaves(splits: DataFrame, layers: DataFrame) -> DataFrame:
    """layer, level, code of each layer's leaves; they tile the domain, empty cells too."""
    roots = layers.select("layer", F.lit(0).alias("level"), F.lit(0).cast("long").alias("code"))
    return roots.unionByName(_children(splits)).join(splits, ["layer", "level", "code"], "left_anti")


def candidate_cells(splits: DataFrame, layers: DataFrame) -> DataFrame:
    """level, code, own, par: every cell of any tree, with the counts over layers 0..q of splits of it and of its parent up to each layer."""
    q = layers.agg(F.max("layer").alias("q")).where("q IS NOT NULL")
    by_cell = splits.groupBy("level", "code").agg(F.collect_list("layer").alias("cuts"))  # at most q layers
    kids = _children(by_cell).select("level", "code", F.col("cuts").alias("par_cuts"))
    root = q.select(F.lit(0).alias("level"), F.lit(0).cast("long").alias("code"), F.sequence(F.lit(1), F.col("q")).alias("par_cuts"))
    every = root.unionByName(kids).join(by_cell, ["level", "code"], "left").crossJoin(F.broadcast(q))

    def upto(cuts: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.col("q")), lambda i: F.size(F.filter(cuts, lambda c: c <= i)))

    return every.select("level", "code", upto(F.coalesce("cuts", F.array().cast("array<int>"))).alias("own"), upto(F.col("par_cuts")).alias("par"), "q")


def merged_tiling(splits: DataFrame, layers: DataFrame) -> DataFrame:
    """s, r, level, code: the common tiling of the layers (s, r] for all s < r; the finest division of any layer wins."""
    cells = candidate_cells(splits, layers)
    pairs = cells.withColumn("s", F.explode(F.sequence(F.lit(0), F.col("q") - 1))).withColumn("r", F.explode(F.sequence(F.col("s") + 1, F.col("q"))))
    inside = F.expr("own[r] - own[s] = 0 AND par[r] - par[s] > 0")
    return pairs.where(inside).select("s", "r", "level", "code")


def layer_counts(cells: DataFrame, layers: DataFrame) -> DataFrame:
    """level, code, cum: objects in the layers 1..i for i = 0..q."""
    q = layers.agg(F.max("layer").alias("q"))
    lists = cells.groupBy("level", "code").agg(F.map_from_entries(F.collect_list(F.struct("layer", "n"))).alias("_m")).crossJoin(F.broadcast(q))
    counts = F.transform(F.sequence(F.lit(1), F.col("q")), lambda i: F.coalesce(F.try_element_at("_m", i), F.lit(0).cast("long")))
    return lists.withColumn("_n", counts).select("level", "code", F.expr("aggregate(_n, array(0L), (a, v) -> concat(a, array(element_at(a, -1) + v)))").alias("cum"))


def merge_reference(trees: dict[int, set[tuple[int, int]]], s: int, r: int) -> set[tuple[int, int]]:
    """Leaves of the common tiling by walking the split sets of layers s+1..r from the root; for tests on small cases."""
    out, todo = set(), [(0, 0)]
    while todo:
        level, code = todo.pop()
        if any((level, code) in trees.get(i, ()) for i in range(s + 1, r + 1)):
            todo += [(level + 1, code * 4 + k) for k in range(4)]
        else:
            out.add((level, code))
    return out


def cumulative_window(by: list[str], order: str):
    return Window.partitionBy(*by).orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
