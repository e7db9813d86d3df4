"""Jaccard join on word n-grams by MinHash banding.

Documents with one n-gram set are one class. Classes that share a band's hash
are candidates, and only those are verified, on their full n-gram sets: the
classes of a band are dealt into blocks, each pair of blocks is one task's
group, and of a block only counts and a few edges leave. Bands with the same
members are verified once, and a pair counts in its first common band. No pair
is listed, and no group is gathered whole.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kinetic.llm.common import WordIds, grouped, mixed, rows_of, text_or_empty, written

WORDS, SIMILARITY, RECALL, ROWS = 5, 0.8, 0.9999, 5
#: A block holds about so many classes and n-grams at most.
BLOCK_CLASSES, BLOCK_GRAMS = 128, 500_000
#: Parts that the members of one class or label are dealt into where they meet it in a join.
SALTS = 16
#: Classes to verify are broadcast to the texts up to so many, by count (some 40 bytes each); more meet them in a shuffle.
BROADCAST_CLASSES = 1_000_000
#: Stands for no id, behind all ids.
_NO_ID = 2**63 - 1

_ids: WordIds | None = None


def bands_for(similarity: float = SIMILARITY, recall: float = RECALL, rows: int = ROWS) -> int:
    """Bands of ``rows`` hashes, so that a pair of that similarity meets in at least one with probability ``recall``."""
    return math.ceil(math.log(1 - recall) / math.log(1 - similarity**rows))


def gram_set(text: str, words: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word n-grams of a whole text (lower case, cut at white space).

    A text of fewer words is one n-gram of all its words; one without words has none.
    """
    global _ids
    _ids = _ids or WordIds()
    h = _ids.of(text.lower().split())
    if not len(h):
        return h
    k = min(words, len(h))
    total = np.full(len(h) - k + 1, k, np.uint64)
    for i in range(k):
        total = mixed(total * np.uint64(0x9E3779B97F4A7C15) + h[i : i + len(total)])
    return np.unique(total)


def _permutations(n: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20240229)
    return rng.integers(0, 2**32, n, np.uint32) | np.uint32(1), rng.integers(0, 2**32, n, np.uint32)


def signatures(grams: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    out = np.full(len(a), 0xFFFFFFFF, np.uint32)
    h = (grams >> np.uint64(32)).astype(np.uint32)
    for at in range(0, len(h), 4096):
        out = np.minimum(out, (h[at : at + 4096, None] * a + b).min(0))
    return out


def sketch(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, similarity: float = SIMILARITY, recall: float = RECALL, rows: int = ROWS) -> DataFrame:
    """doc_id, h (hash of the text), k1, k2 (128-bit hash of the n-gram set), grams (size), bands (a 64-bit hash for each band; none without words)."""
    bands = bands_for(similarity, recall, rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        a, b = _permutations(bands * rows)
        powers = np.array([pow(0x9E3779B97F4A7C15, i + 1, 2**64) for i in range(rows)], np.uint64)
        tags = mixed(np.arange(1, bands + 1, dtype=np.uint64))
        for batch in batches:
            ids, k1, k2, sizes, out, lengths = [], [], [], [], [], [0]
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("t").to_pylist(), strict=True):
                g = gram_set(text, words)
                key = xxhash.xxh3_128(g.tobytes()).intdigest()
                ids.append(doc)
                k1.append((key >> 64) - 2**63)
                k2.append((key & (2**64 - 1)) - 2**63)
                sizes.append(len(g))
                if len(g):
                    s = signatures(g, a, b).astype(np.uint64).reshape(bands, rows)
                    out.append(mixed((s * powers).sum(1, dtype=np.uint64) + tags).view(np.int64))
                lengths.append(lengths[-1] + (bands if len(g) else 0))
            flat = pa.array(np.concatenate(out) if out else np.zeros(0, np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(k1, pa.int64()), pa.array(k2, pa.int64()), pa.array(sizes, pa.int64()), pa.ListArray.from_arrays(pa.array(lengths, pa.int32()), flat), batch.column("h")], names=["doc_id", "k1", "k2", "grams", "bands", "h"])

    return df.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("t")).withColumn("h", F.xxhash64("t")).mapInArrow(run, "doc_id long, k1 long, k2 long, grams long, bands array<long>, h long")


def _every_salt() -> Column:
    return F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long")))


def components(edges: DataFrame) -> DataFrame:
    """v, c: the least node of each node's component, for nodes of edges (a, b) of any type with an order.

    Labels fall to the least of their neighbours', then to the label of their
    label, until none falls any more; each round is a table in the shared
    folder, and one number tells whether anything fell.
    """
    both = written(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = written(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("c")).select(F.col("a").alias("v"), "c"), "labels")
    while True:
        near = both.join(labels, both["b"] == labels["v"]).groupBy("a").agg(F.min("c").alias("m"))
        fell = labels.join(near, labels["v"] == near["a"]).select("v", F.col("c").alias("was"), F.least("c", "m").alias("c"))
        # a label that many nodes have is dealt over salts; labels that stand for themselves lead nowhere
        up = fell.where("c <> v").select(F.col("v").alias("u"), F.col("c").alias("cu"), _every_salt().alias("salt"))
        dealt = fell.withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(SALTS)))
        jumped = dealt.join(up, (dealt["c"] == up["u"]) & (dealt["salt"] == up["salt"]), "left").select("v", "was", F.least("c", F.coalesce("cu", "c")).alias("c"))
        labels = written(jumped.select("v", "c", (F.col("c") != F.col("was")).alias("fell")), "labels")
        if not labels.where("fell").limit(1).count():
            return labels.select("v", "c")


def _links(left: list[tuple], right: list[tuple] | None, similarity: float, before: int) -> tuple[np.ndarray, np.ndarray, list[tuple[int, int]]]:
    """Links of the classes (copies, grams, bands) of a block among each other (right None) or to another block's.

    Pairs that share one of the first ``before`` bands count there. Returns the
    documents linked to each class of either block, and edges (left, other) of
    places, so that what hangs together in the block hangs together by the edges.
    """
    other = left if right is None else right
    grams = np.concatenate([x[1] for x in other])
    sizes = np.array([len(x[1]) for x in other])
    owner = np.repeat(np.arange(len(other)), sizes)
    order = np.argsort(grams, kind="stable")
    grams, owner = grams[order], owner[order]
    copies = np.array([x[0] for x in other], np.int64)
    bands = np.array([x[2][:before] for x in other]).reshape(len(other), before)
    n_left, n_right, edges = np.zeros(len(left), np.int64), np.zeros(len(other), np.int64), []
    parent = list(range(len(left) + len(other)))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    for i, (own, g, b) in enumerate(left):
        lo, hi = np.searchsorted(grams, g, "left"), np.searchsorted(grams, g, "right")
        runs = hi - lo
        where = np.repeat(lo - np.concatenate([[0], np.cumsum(runs)[:-1]]), runs) + np.arange(runs.sum())
        shared = np.bincount(owner[where], minlength=len(other))
        # s / (a + b - s) >= similarity, in exact terms of counts
        hit = shared >= similarity * (len(g) + sizes - shared) - 1e-9
        if right is None:
            hit[: i + 1] = False
        at = np.flatnonzero(hit)
        at = at[~(bands[at] == b[:before]).any(1)]
        if len(at):
            n_left[i] += copies[at].sum()
            n_right[at] += own
            for j in at.tolist():
                x, y = root(i), root(j if right is None else len(left) + j)
                if x != y:
                    parent[max(x, y)] = min(x, y)
                    edges.append((i, j))
    return n_left, n_right, edges


def _verified(spark, df: DataFrame, classes: DataFrame, id_col: str, text_col: str, words: int, similarity: float) -> DataFrame:
    """a, b, n: (class, null, linked documents) and (class, class, 0) for edges, from all classes that share a band."""
    banded = classes.select("v", "grams", F.posexplode("bands").alias("p", "band"))
    groups = banded.groupBy("band").agg(F.min("p").alias("p"), F.count(F.lit(1)).alias("m"), F.sum("grams").alias("g"), F.min("v").alias("u"), F.bit_xor(F.xxhash64("v")).alias("x"), F.bit_xor(F.xxhash64("v", F.lit(1))).alias("y")).where("m > 1")
    # of bands with the same members the first is enough
    groups = groups.groupBy("u", "x", "y", "m", "g").agg(F.min(F.struct("p", "band")).alias("first"))
    blocks = F.greatest(F.ceil(F.col("m") / BLOCK_CLASSES), F.ceil(F.col("g") / BLOCK_GRAMS)).cast("long")
    members = written(banded.join(groups.select("first.band", blocks.alias("blocks")), "band").select("v", "p", "band", "blocks"), "mates")
    held = written(classes.join(members.select("v").distinct(), "v").select("v", "k", "h", "copies", "bands"), "held")
    asked = held.select("v", "k", "h")
    asked = F.broadcast(asked) if held.count() <= BROADCAST_CLASSES else asked.hint("shuffle_hash")
    texts = df.select(F.coalesce(F.col(id_col).cast("long"), F.lit(_NO_ID)).alias("k"), text_or_empty(text_col).alias("t")).withColumn("h", F.xxhash64("t"))
    texts = texts.join(asked, ["k", "h"]).select("v", "t").dropDuplicates(["v"])
    # a class goes to every pair of blocks that holds its own
    placed = members.withColumn("own", F.pmod(F.xxhash64("v", "band"), F.col("blocks"))).withColumn("o", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    placed = placed.select("v", "p", "band", "own", F.least("own", "o").alias("i"), F.greatest("own", "o").alias("j"))
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = placed.join(held.select("v", "copies", "bands").join(texts, "v"), "v").select("band", "i", "j", "own", "p", "v.*", "copies", "bands", "t")
    dealt = dealt.repartition(tasks, "band", "i", "j").sortWithinPartitions("band", "i", "j", "own", "rep", "k1", "k2")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def narrow() -> Iterator[tuple]:
            for band, i, j, own, p, rep, k1, k2, copies, bands, t in rows_of(batches, ["band", "i", "j", "own", "p", "rep", "k1", "k2", "copies", "bands", "t"]):
                yield band, i, j, own, p, (rep, k1, k2), copies, gram_set(t, words), np.array(bands, np.int64)

        for (_, i, j), members in grouped(narrow(), 3):
            left, before = [m for m in members if m[3] == i], members[0][4]
            right = None if i == j else [m for m in members if m[3] == j]
            if not left or right == []:
                continue
            n_left, n_right, edges = _links([m[6:] for m in left], None if right is None else [m[6:] for m in right], similarity, before)
            other = left if right is None else right
            counts = zip(left, (n_left + n_right).tolist(), strict=True) if right is None else [*zip(left, n_left.tolist(), strict=True), *zip(right, n_right.tolist(), strict=True)]
            out = [(*m[5], None, None, None, n) for m, n in counts if n] + [(*left[a][5], *other[b][5], 0) for a, b in edges]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*out, strict=True)], names=["a1", "a2", "a3", "b1", "b2", "b3", "n"])

    found = dealt.mapInArrow(run, "a1 long, a2 long, a3 long, b1 long, b2 long, b3 long, n long")
    node = [F.struct(*[F.col(f"{x}{i + 1}").alias(c) for i, c in enumerate(("rep", "k1", "k2"))]) for x in "ab"]
    return written(found.select(node[0].alias("a"), F.when(F.col("b2").isNotNull(), node[1]).alias("b"), "n"), "links")


def classed(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, similarity: float = SIMILARITY, recall: float = RECALL, rows: int = ROWS) -> DataFrame:
    """doc_id, h, worded, copy, class (structs that begin with the least id), n_links for every row; null structs for texts without words."""
    spark = df.sparkSession
    found = written(sketch(df, id_col, text_col, words, similarity, recall, rows), "sketches")
    key = F.coalesce("doc_id", F.lit(_NO_ID))
    classes = found.where("grams > 0").groupBy("k1", "k2", "grams", "bands").agg(F.min(F.struct(key.alias("k"), F.col("h").alias("h"))).alias("_r"), F.count(F.lit(1)).alias("copies"))
    classes = written(classes.select(F.struct(F.col("_r.k").alias("rep"), "k1", "k2").alias("v"), "k1", "k2", "_r.k", "_r.h", "grams", "bands", "copies"), "classes")
    links = _verified(spark, df, classes, id_col, text_col, words, similarity)
    joined = components(links.where("b IS NOT NULL").select("a", "b"))
    counts = links.where("b IS NULL").groupBy("a").agg(F.sum("n").alias("n"))
    known = classes.join(joined, "v", "left").join(counts.withColumnRenamed("a", "v"), "v", "left")
    # members of a class with copies are dealt over salts, which such classes are repeated for
    salts = F.when(F.col("copies") == 1, F.array(F.pmod(F.xxhash64("k", "h"), F.lit(SALTS)))).otherwise(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long")))
    known = known.select("k1", "k2", F.col("v").alias("copy"), F.coalesce("c", "v").alias("class"), (F.col("copies") - 1 + F.coalesce("n", F.lit(0))).alias("n_links"), F.explode(salts).alias("salt"))
    rows_ = found.select("doc_id", "h", "k1", "k2", (F.col("grams") > 0).alias("worded"), F.pmod(F.xxhash64(key, "h"), F.lit(SALTS)).alias("salt"))
    out = rows_.join(known, ["k1", "k2", "salt"], "left")
    return out.select("doc_id", "h", "worded", *[F.when(F.col("worded"), F.col(c)).alias(c) for c in ("copy", "class")], F.when(F.col("worded"), F.col("n_links")).otherwise(0).alias("n_links"))


def _id(struct: str) -> Column:
    return F.when(F.col(struct).isNotNull() & (F.col(f"{struct}.rep") != _NO_ID), F.col(f"{struct}.rep"))


def ngram_join(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, similarity: float = SIMILARITY, recall: float = RECALL, rows: int = ROWS) -> DataFrame:
    """doc_id, class_id, copy_id, n_links for every row.

    copy_id is the least id of the documents with the same n-gram set, class_id
    the least id of all that hang together by links (Jaccard similarity of
    ``similarity`` or more on whole n-gram sets), n_links the number of other
    documents with a link to this one, copies included. Texts without words
    (null, empty, white space) link to nothing and are classes of their own.
    Rows with null ids link like all others; a class without any id has a null
    class_id. An id may repeat: its rows count as copies or as different texts,
    each with its own links. An empty table gives an empty result.
    """
    out = classed(df, id_col, text_col, words, similarity, recall, rows)
    return out.select("doc_id", F.when(F.col("worded"), _id("class")).otherwise(F.col("doc_id")).alias("class_id"), F.when(F.col("worded"), _id("copy")).otherwise(F.col("doc_id")).alias("copy_id"), "n_links")


def one_of_each(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, similarity: float = SIMILARITY) -> DataFrame:
    """The rows of df that stay: of each class the one with the least id (null ids last, then the least hash of the text), and all texts without words."""
    low = F.coalesce(F.col(id_col).cast("long"), F.lit(_NO_ID))
    out = classed(df, id_col, text_col, words, similarity).select(F.coalesce("doc_id", F.lit(_NO_ID)).alias("k"), "h", "worded", "class")
    first = out.where("worded").groupBy("class").agg(F.min(F.struct("k", "h")).alias("r")).select("r.k", "r.h", F.lit(True).alias("one"))
    keys = first.unionByName(out.where("NOT worded").select("k", "h", F.lit(False).alias("one")).distinct()).select(F.struct("k", "h").alias("key"), "one")
    rows = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), F.struct(low.alias("k"), F.xxhash64(text_or_empty(text_col)).alias("h")).alias("key"))
    # rows that are equal in id and text are one group's; those without words stay apart
    alone = F.when(~F.col("one"), F.monotonically_increasing_id())
    place = F.row_number().over(Window.partitionBy("key", alone).orderBy(F.lit(1)))
    return rows.join(keys, "key").withColumn("place", place).where("place = 1").select(*[F.col(f"row.`{c}`").alias(c) for c in df.columns])
