"""Helpers shared by the document operators."""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Labels of rows whose remainder is 0 are never learned from.
FOLDS = 5


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(col: str | Column = "text") -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def fold(id_col: str | Column = "doc_id") -> Column:
    """crc32 of the id as text, modulo FOLDS."""
    c = F.col(id_col) if isinstance(id_col, str) else id_col
    return F.crc32(c.cast("string").cast("binary")) % FOLDS


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or one set here where it is unset and all runs on one machine (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        sc = spark.sparkContext
        named = sc._jsc.sc().getCheckpointDir()
        named = named.get() if named.isDefined() else None
        if not named:
            if not sc.master.startswith("local"):
                raise RuntimeError("spark.checkpoint.dir has to name a folder that all executors share")
            import tempfile

            named = "file://" + tempfile.mkdtemp(prefix="kinetic-shared-")
            sc.setCheckpointDir(named)
    return named.rstrip("/")


def fresh_path(spark: SparkSession, what: str) -> str:
    return f"{shared_folder(spark)}/kinetic-{what}-{uuid.uuid4().hex}"


def written(df: DataFrame, what: str) -> DataFrame:
    """df as a Parquet table in the shared folder, reread: lineage ends here and survives lost executors."""
    path = fresh_path(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def utf8(values: pa.Array) -> list[bytes]:
    """UTF-8 bytes of each text; null is empty."""
    return [b"" if v is None else v for v in values.cast(pa.large_binary()).to_pylist()]


def rows_of(batches: Iterable[pa.RecordBatch], names: list[str]) -> Iterator[tuple]:
    for b in batches:
        yield from zip(*(b.column(n).to_pylist() for n in names), strict=True)


def grouped(rows: Iterable[tuple], width: int) -> Iterator[tuple[tuple, list[tuple]]]:
    """Runs of rows with equal first ``width`` fields, from rows sorted by them."""
    key, held = None, []
    for r in rows:
        k = r[:width]
        if held and k != key:
            yield key, held
            held = []
        key = k
        held.append(r)
    if held:
        yield key, held


class WordIds(dict):
    """word -> 64-bit hash, kept per worker and emptied when it has grown to ``most`` entries."""

    def __init__(self, most: int = 300_000):
        import xxhash

        self.most, self.hash = most, xxhash.xxh64_intdigest

    def __missing__(self, word: str) -> int:
        if len(self) >= self.most:
            self.clear()
        h = self[word] = self.hash(word)
        return h

    def of(self, words: list[str]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mixed(h: np.ndarray) -> np.ndarray:
    """splitmix64 finaliser, so that sums of hashes are spread again."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))
