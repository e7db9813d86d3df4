"""Quality by nearest-neighbour voting over latent-semantic vectors.

Texts become counts of lexical and surface terms; a truncated singular value
decomposition of a bounded labelled sample gives the latent space. The labelled
vectors are broadcast, and every document takes exact cosine products with all
of them, block by block; its nearest neighbours vote with their similarity.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetic.llm.common import fold, text_or_empty

TERMS, LEXICAL, DIMENSIONS = 2048, 1024, 48
#: Labelled rows to fit on, at most, for each label: those with the least hash of their id.
SAMPLE_PER_LABEL = 2048
NEIGHBOURS = 15
#: Similarities are raised to this power before they vote.
SHARPNESS = 8
#: Documents whose products are taken at a time.
BLOCK = 512
#: Score from which a document counts as good.
CUT = 0.3

_SHAPES = ((re.compile(r"[^\W\d_]*[A-ZÀ-ÖØ-Þ][^\W\d_]*[A-ZÀ-ÖØ-Þ][^\W\d_]*"), "X"), (re.compile(r"[^\W\d_]+"), "x"), (re.compile(r"\d+"), "0"), (re.compile(r"\s+"), " "))


def _hash(term: str) -> int:
    import xxhash

    return xxhash.xxh32_intdigest(term)


def shape(word: str) -> str:
    """Letters of a word as x (X with two capitals or more), digits as 0; other characters stay, at most three of a kind in a row."""
    for pattern, sign in _SHAPES:
        word = pattern.sub(lambda m, s=sign: s if m[0] not in ("X", "x") else m[0], word)
    return re.sub(r"(.)\1{3,}", r"\1\1\1", word)


class _Terms(dict):
    """word -> (lexical term, surface term, id); emptied when it has grown."""

    def __missing__(self, word: str) -> tuple[int, int, int]:
        if len(self) > 300_000:
            self.clear()
        t = self[word] = (_hash("w" + word.strip(".,;:!?").lower()) % LEXICAL, LEXICAL + _hash("s" + shape(word)) % (TERMS - LEXICAL - 64), _hash("i" + word))
        return t


_terms = _Terms()


def term_counts(text: str) -> np.ndarray:
    """TERMS weights of a whole text: lexical terms, surface shapes, and how much of it repeats; each kind with its own norm."""
    words = text.split()
    out = np.zeros(TERMS, np.float32)
    if not words:
        out[TERMS - 1] = 1
        return out
    t = np.array(list(map(_terms.__getitem__, words)), np.int64)
    counts = np.bincount(t[:, 0], minlength=LEXICAL).astype(np.float32)
    lexical = np.log1p(counts)
    surface = np.sqrt(np.bincount(t[:, 1] - LEXICAL, minlength=TERMS - LEXICAL - 64).astype(np.float32) / len(words))
    distinct = len(np.unique(t[:, 2])) / len(words)
    beside = float((t[1:, 2] == t[:-1, 2]).mean()) if len(words) > 1 else 0.0
    # of words that have room to repeat: a text of n words from a large vocabulary has about so many distinct ones
    extra = np.zeros(64, np.float32)
    extra[0], extra[1], extra[2] = beside, 1 - beside, max(0.0, 1 - distinct / min(1.0, 8 / len(words) ** 0.35))
    out[:LEXICAL] = 0.3 * lexical / np.linalg.norm(lexical)
    out[LEXICAL : TERMS - 64] = surface / np.linalg.norm(surface)
    out[TERMS - 64 :] = extra
    return out


@dataclass
class Neighbours:
    """Projection to the latent space, unit vectors of the labelled rows, their labels and their weights."""

    axes: np.ndarray
    vectors: np.ndarray
    labels: np.ndarray
    weights: np.ndarray
    prior: float
    neighbours: int = NEIGHBOURS

    def project(self, counts: np.ndarray) -> np.ndarray:
        v = counts @ self.axes
        return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-12)

    def score(self, counts: np.ndarray) -> np.ndarray:
        """Share of the vote for label 1, from 0 to 1; the prior where nothing was learned."""
        if not len(self.labels):
            return np.full(len(counts), self.prior)
        near = self.project(counts) @ self.vectors.T
        k = min(self.neighbours, len(self.labels))
        at = np.argpartition(-near, k - 1, axis=1)[:, :k]
        vote = np.maximum(np.take_along_axis(near, at, 1), 0) ** SHARPNESS * self.weights[at]
        total = vote.sum(1)
        return np.where(total > 0, (vote * self.labels[at]).sum(1) / np.maximum(total, 1e-30), self.prior)


def fit(counts: np.ndarray, labels: np.ndarray, share: float, dimensions: int = DIMENSIONS) -> Neighbours:
    """Latent axes of the sample (a row for each text) and its vectors. ``share``: of label 1 among all labelled rows."""
    if not len(labels):
        return Neighbours(np.zeros((TERMS, 1), np.float32), np.zeros((0, 1), np.float32), labels, labels, 0.5)
    gram = counts.T.astype(np.float64) @ counts
    values, vectors = np.linalg.eigh(gram)
    axes = vectors[:, ::-1][:, : min(dimensions, len(labels))].astype(np.float32)
    model = Neighbours(axes, np.zeros((0, axes.shape[1]), np.float32), labels, labels, share)
    model.vectors = model.project(counts).astype(np.float32)
    ones = max(1, int((labels == 1).sum()))
    zeros = max(1, int((labels == 0).sum()))
    model.weights = np.where(labels == 1, share / ones, (1 - share) / zeros).astype(np.float64) * len(labels)
    return model


def _sample(docs: DataFrame, labels: DataFrame, label_col: str, per_label: int) -> tuple[DataFrame, float]:
    """At most per_label rows of each label, and the share of label 1 among all that may be learned from."""
    known = labels.where(F.col(label_col).isNotNull() & F.col("doc_id").isNotNull() & (fold() != 0)).select(F.col("doc_id").alias("d"), F.col(label_col).cast("int").alias("y"))
    n = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect() if r["y"] in (0, 1)}
    share = n.get(1, 0) / max(1, sum(n.values()))
    parts = [known.where(F.col("y") == y).orderBy(F.xxhash64("d"), "d").limit(per_label) for y in (0, 1)]
    # of a checked size: 2 * per_label ids
    rows = docs.join(F.broadcast(parts[0].unionByName(parts[1])), docs["doc_id"] == F.col("d"))
    return rows.groupBy("d", "y").agg(F.min("t").alias("t")).select("d", "t", "y"), share  # of texts that share an id the least


def good_rows(df: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", per_label: int = SAMPLE_PER_LABEL, cut: float = CUT) -> DataFrame:
    """The rows of df, with its columns, whose score is ``cut`` or more."""
    whole = df.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text_col}`").alias("text"), F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("whole"))
    scored = quality_scores(whole, labels, "id", "text", label_col, per_label, cut, keep=["whole"])
    return scored.where("predicted = 1").select(*[F.col(f"whole.`{c}`").alias(c) for c in df.columns])


def quality_scores(df: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", per_label: int = SAMPLE_PER_LABEL, cut: float = CUT, keep: list[str] | None = None) -> DataFrame:
    """doc_id, held_out, score, predicted for every whole text (``keep``: score, predicted and these input columns instead).

    Learns from at most ``per_label`` labelled ids of each label outside the
    held-out fold; of texts that share such an id the least counts. Null texts
    are empty; null ids are scored too. Without labels every score is 0.5. An
    empty table gives an empty result.
    """
    keep = keep or []
    docs = df.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("t"))
    rows, share = _sample(docs, labels, label_col, per_label)

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, at, values = [], [], []
            for t in b.column("t").to_pylist():
                c = term_counts(t)
                nz = np.flatnonzero(c)
                at.append(nz.astype(np.int32).tobytes())
                values.append(c[nz].tobytes())
            ids = b.column("d")
            yield pa.RecordBatch.from_arrays([ids, b.column("y"), pa.array(at, pa.binary()), pa.array(values, pa.binary())], names=["d", "y", "at", "values"])

    got = sorted(rows.mapInArrow(counted, "d long, y int, at binary, values binary").collect())  # 2 * per_label rows
    counts = np.zeros((len(got), TERMS), np.float32)
    for k, (_, _, at, values) in enumerate(got):
        counts[k, np.frombuffer(at, np.int32)] = np.frombuffer(values, np.float32)
    model = df.sparkSession.sparkContext.broadcast(fit(counts, np.array([r[1] for r in got], np.int64), share))

    extra = df.select(*[F.col(f"`{c}`") for c in keep]).schema.fields
    asked = df.select(F.col(id_col).cast("long").alias("_doc"), text_or_empty(text_col).alias("_text"), (fold(id_col) == 0).alias("_held"), *[F.col(f"`{c}`") for c in keep])

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model.value
        for whole in batches:
            for start in range(0, whole.num_rows, BLOCK):
                b = whole.slice(start, BLOCK)
                s = np.clip(m.score(np.stack([term_counts(t) for t in b.column("_text").to_pylist()])), 0, 1)
                yield pa.RecordBatch.from_arrays([b.column("_doc"), b.column("_held"), pa.array(s, pa.float64()), pa.array((s >= cut).astype(np.int32)), *b.columns[3:]], names=["doc_id", "held_out", "score", "predicted", *[f"_{i}" for i in range(len(keep))]])

    from pyspark.sql.types import BooleanType, DoubleType, IntegerType, LongType, StructField, StructType

    made = [StructField("doc_id", LongType()), StructField("held_out", BooleanType()), StructField("score", DoubleType()), StructField("predicted", IntegerType())]
    out = asked.mapInArrow(scored, StructType([*made, *[StructField(f"_{i}", f.dataType) for i, f in enumerate(extra)]]))
    return out if not keep else out.select("score", "predicted", *[F.col(f"_{i}").alias(c) for i, c in enumerate(keep)])
