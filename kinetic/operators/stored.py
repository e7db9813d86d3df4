"""Indexes that are written once and read by queries: objects by part and node or page, the catalog above them, and the parts' statistics."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from kinetic.operators import index_box, index_curve, query
from kinetic.operators.partitions import part_stats


@dataclass
class StoredIndex:
    """objects carry node (box) or label, key and leaf (curve); catalog has a row for each node or page, stats one for each part and quadrant (and label)."""

    path: str
    kind: str
    objects: DataFrame
    catalog: DataFrame
    stats: DataFrame

    def range(self, queries: DataFrame) -> DataFrame:
        if self.kind == "box":
            return query.range_box(None, queries, objects=self.objects, nodes=self.catalog)
        return query.range_curve(None, queries, keyed=self.objects, stats=self.stats)

    def range_counts(self, queries: DataFrame) -> DataFrame:
        """qid, answers of the queries that have any."""
        if self.kind == "box":
            return query.range_box_counts(self.objects, self.catalog, queries)
        return query.range_curve_counts(queries, self.objects, self.stats)

    def neighbours(self, queries: DataFrame) -> DataFrame:
        if self.kind == "box":
            return query.knn_box(None, queries, objects=self.objects, nodes=self.catalog)
        return query.knn_growing(None, queries, keyed=self.objects, stats=self.stats)

    def pushed(self, queries: DataFrame) -> DataFrame:
        return query.range_pushdown(self.objects, queries, self.stats)

    def accesses(self, queries: DataFrame) -> DataFrame:
        """qid, accesses of leaves or pages by range queries."""
        if self.kind == "box":
            return index_box.count_nodes(self.catalog, queries)
        return index_curve.count_pages(self.catalog, queries, self.stats)


def store_index(parted: DataFrame, path: str, kind: str = "box", capacity: int = 102) -> StoredIndex:
    """Writes objects partitioned by part and quadrant and sorted by node or key, then the catalog and the statistics read from them."""
    spark = parted.sparkSession
    if kind == "box":
        rows = index_box.build_nodes(parted, capacity, dealt=True)
    else:
        rows = index_curve.leaf_pages(index_curve.curve_keys(parted), capacity, dealt=True)
    rows.write.partitionBy("part", "quadrant").parquet(f"{path}/objects")
    objects = spark.read.schema(rows.schema).parquet(f"{path}/objects")
    catalog = index_box.node_boxes(objects) if kind == "box" else index_curve.page_catalog(objects)
    stats = part_stats(objects) if kind == "box" else index_curve.key_stats(objects)
    catalog.write.parquet(f"{path}/catalog")
    stats.coalesce(1).write.parquet(f"{path}/stats")
    return StoredIndex(path, kind, objects, *(spark.read.schema(t.schema).parquet(f"{path}/{n}") for n, t in (("catalog", catalog), ("stats", stats))))


def open_index(spark: SparkSession, path: str, kind: str = "box") -> StoredIndex:
    """An index that an earlier session has written."""
    return StoredIndex(path, kind, *(spark.read.parquet(f"{path}/{t}") for t in ("objects", "catalog", "stats")))
