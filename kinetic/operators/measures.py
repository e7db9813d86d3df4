"""Cost and accuracy measures of layouts, plans and answers."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kinetic.operators import index_box
from kinetic.plans.expansion import measured_expansion


def estimated_expansion(plan: DataFrame) -> DataFrame:
    """part, estimated."""
    return plan.select("part", F.col("cost").alias("estimated"))


def layout_expansion(objects: DataFrame, horizon: float) -> DataFrame:
    """part, measured: swept area of the real nodes of each part."""
    return measured_expansion(index_box.node_boxes(objects), horizon).groupBy("part").agg(F.sum("swept").alias("measured"), F.count(F.lit(1)).alias("nodes"))


def parent_expansion(objects: DataFrame, horizon: float, fanout: int = 102) -> DataFrame:
    """Swept area of the level above the leaves, which the estimate leaves out."""
    return measured_expansion(index_box.parent_boxes(index_box.node_boxes(objects), fanout), horizon).groupBy("part").agg(F.sum("swept").alias("measured_parents"))


def estimate_accuracy(estimated: DataFrame, measured: DataFrame) -> DataFrame:
    """part, estimated, measured, ratio."""
    return estimated.join(measured, "part").withColumn("ratio", F.col("estimated") / F.col("measured"))


def rank_correlation(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Spearman's correlation of two columns over a few rows (plans)."""
    rows = pairs.withColumn("_a", F.rank().over(Window.orderBy(a))).withColumn("_b", F.rank().over(Window.orderBy(b)))
    return rows.agg(F.corr("_a", "_b").alias("spearman"))


def node_accesses(hits: DataFrame) -> DataFrame:
    """qid, accesses: leaf nodes that a query visits."""
    return hits.groupBy("qid").agg(F.count(F.lit(1)).alias("accesses"))


def false_hits(candidates: DataFrame, answers: DataFrame) -> DataFrame:
    """qid, candidates, answers, false_hits; ``candidates``: their number by qid."""
    a = answers.groupBy("qid").agg(F.count(F.lit(1)).alias("answers"))
    return candidates.join(a, "qid", "full_outer").select("qid", F.coalesce("candidates", F.lit(0)).alias("candidates"), F.coalesce("answers", F.lit(0)).alias("answers")).withColumn("false_hits", F.col("candidates") - F.col("answers"))


def answer_quality(answers: DataFrame, truth: DataFrame) -> DataFrame:
    """qid, answers, truth, hits: recall is hits / truth, precision hits / answers.

    Both sides are counted by pair of query and object: where objects are dealt
    by oid, and stay so, no pair is sent anywhere.
    """
    a = answers.select("qid", "oid", F.lit(1).cast("long").alias("a"), F.lit(0).cast("long").alias("b"))
    t = truth.select("qid", "oid", F.lit(0).cast("long").alias("a"), F.lit(1).cast("long").alias("b"))
    both = a.unionByName(t).groupBy("qid", "oid").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    return both.groupBy("qid").agg(F.sum("a").alias("answers"), F.sum("b").alias("truth"), F.sum(F.least("a", "b")).alias("hits"))


def plan_summary(plan: DataFrame, parted: DataFrame) -> DataFrame:
    """part, quadrants, n, sub_parts."""
    sizes = parted.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("quadrant").alias("sub_parts"))
    return plan.join(sizes, "part", "left").select("part", "lo_layer", "hi_layer", "quadrants", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("sub_parts", F.lit(0)).alias("sub_parts"))


def migration_rate(moves: DataFrame) -> DataFrame:
    """action, n, share of all updates."""
    n = moves.groupBy("action").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy()))


def page_counts(parted: DataFrame, entry_bytes: int = 40, node_bytes: int = 4096) -> DataFrame:
    """part, n, pages: pages of node_bytes that the part's entries fill."""
    return parted.groupBy("part").agg(F.count(F.lit(1)).alias("n")).withColumn("pages", F.ceil(F.col("n") * entry_bytes / node_bytes))


def timed(metric: str, fn: Callable[[], DataFrame], repeats: int = 3, warmup: int = 1) -> dict:
    """Seconds of a query whose result goes nowhere: the least of ``repeats`` runs after ``warmup``."""
    best = float("inf")
    for i in range(warmup + repeats):
        start = time.perf_counter()
        fn().write.format("noop").mode("overwrite").save()
        if i >= warmup:
            best = min(best, time.perf_counter() - start)
    return {"metric": metric, "value": best}
