"""Toxicity by class-conditional Kneser-Ney models over the letters of words.

Expressions with many endings are as common as single words, so the models
predict each letter of a word from the letters before it. Toxic and ordinary
documents have counts of their own for long histories; both fall back on
continuation counts of short histories that they share. What toxic counts leave
over behind a history goes to the ordinary probability there, so that a history
speaks as far as toxic documents have counted it: not at all where none has it,
a little behind a rare one. A document's score comes from the difference of the
log-likelihoods of all its words divided by their number, with what single
words tell beyond a threshold beside it.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kinetic.llm.common import fold, text_or_empty, written

#: Letters of history that each class counts, and those of the shared orders below.
HISTORY, SHARED = 7, (3, 1)
#: Discount of absolute discounting (fixed value).
DISCOUNT = 0.75
#: Log ratio from which a word counts as evidence of its own.
EVIDENCE = 2.0
#: Labelled rows of the calibration fold that the score is fitted on, at most, for each label.
CALIBRATION_ROWS = 2048
CALIBRATION_FOLD = 4
#: Labels up to so many rows are broadcast to the documents; more meet them in a shuffle.
BROADCAST_LABELS = 2_000_000
#: Models up to so many grams, of 16 bytes each, are broadcast to the documents; words meet the grams of larger ones in a join. Scores are the same.
BROADCAST_GRAMS = 2**22
CUT = 0.5
#: Spark's seed of xxhash64 (fixed value).
SEED = 42
_EDGES = ".,;:!?\"'()[]*#$%&|-_"
_OPEN, _CLOSE = "\x02", "\x03"


def plain(word: str) -> str:
    return word.strip(_EDGES).lower()


def words_of(text: str) -> set[str]:
    """Distinct words, without the punctuation around them and in lower case."""
    return {plain(w) for w in set(text.split())} - {""}


def grams_of(word: str, history: int = HISTORY) -> list[str]:
    """Each letter of a word (and its end) behind at most ``history`` letters (and its beginning)."""
    s = f"{_OPEN}{word}{_CLOSE}"
    return [s[max(0, k - history) : k + 1] for k in range(1, len(s))]


def _cuts(word: str) -> Column:
    """``grams_of`` of a column of plain words."""
    s = F.concat(F.lit(_OPEN), F.col(word), F.lit(_CLOSE))
    return F.transform(F.sequence(F.lit(2), F.length(word) + 2), lambda e: F.substring(s, F.greatest(F.lit(1), e - HISTORY), F.least(e, F.lit(HISTORY + 1))))


def _count_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: tuple[Counter, Counter] = (Counter(), Counter())

    def out() -> pa.RecordBatch:
        words = list(held[0].keys() | held[1].keys())
        return pa.RecordBatch.from_arrays([pa.array(words, pa.string()), *(pa.array([held[y][w] for w in words], pa.int64()) for y in (1, 0))], names=["w", "t", "o"])

    for b in batches:
        for text, y in zip(b.column("text").to_pylist(), b.column("y").to_pylist(), strict=True):
            held[y].update(words_of(text))
            if len(held[0]) + len(held[1]) > 400_000:
                yield out()
                held[0].clear()
                held[1].clear()
    if held[0] or held[1]:
        yield out()


def training_rows(df: DataFrame, labels: DataFrame, id_col: str, text_col: str, label_col: str) -> DataFrame:
    """d, text, y, fold of the rows that may be learned from."""
    known = labels.where(F.col(label_col).isin(0, 1) & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias("d"), F.col(label_col).cast("int").alias("y"), fold().alias("fold")).where("fold <> 0")
    if known.count() <= BROADCAST_LABELS:
        known = F.broadcast(known)
    return df.select(F.col(id_col).cast("long").alias("d"), text_or_empty(text_col).alias("text")).join(known, "d").select("d", "text", "y", "fold")


def log_ratios(rows: DataFrame) -> DataFrame:
    """gram, ratio: log of a letter's probability in toxic documents over that in ordinary ones, behind every history of toxic documents.

    ``rows``: text, y. A word counts once in a document. Behind the other histories the ratio is 0, as for grams that are not in the table.
    """
    words = written(rows.select("text", "y").mapInArrow(_count_words, "w string, t long, o long").groupBy("w").agg(F.sum("t").alias("t"), F.sum("o").alias("o")), "words")
    grams = words.select(F.explode(_cuts("w")).alias("gram"), "t", "o").groupBy("gram").agg(F.sum("t").alias("t"), F.sum("o").alias("o"))
    grams = written(grams.select("gram", F.expr("substring(gram, 1, length(gram) - 1)").alias("past"), F.right("gram", F.lit(1)).alias("letter"), "t", "o"), "grams")
    # shared orders: in how many longer histories a letter follows a short one
    tables, upper = [], grams.select("past", "letter")
    for h in SHARED:
        upper = upper.select(F.right("past", F.lit(h)).alias("past"), "letter", F.lit(1).alias("n")).groupBy("past", "letter").agg(F.sum("n").alias("n"))
        whole = upper.groupBy("past").agg(F.sum("n").alias("all"), F.count(F.lit(1)).alias("kinds"))
        tables.append((h, upper.join(whole, "past")))
    alphabet = max(1, tables[-1][1].select("letter").distinct().count())
    lower = None
    for h, table in reversed(tables):
        if lower is None:
            below = F.lit(1.0 / alphabet)
            table = table.withColumn("below", below)
        else:
            table = table.withColumn("short", F.right("past", F.lit(lower[0]))).join(lower[1].select(F.col("past").alias("short"), "letter", F.col("p").alias("below")), ["short", "letter"])
        lower = (h, written(table.select("past", "letter", ((F.col("n") - DISCOUNT) / F.col("all") + DISCOUNT * F.col("kinds") / F.col("all") * F.col("below")).alias("p")), "shared"))
    past = grams.groupBy("past").agg(F.sum("t").alias("all_t"), F.sum("o").alias("all_o"), F.sum((F.col("t") > 0).cast("long")).alias("kinds_t"), F.sum((F.col("o") > 0).cast("long")).alias("kinds_o")).where("all_t > 0")
    known = grams.join(past, "past").withColumn("short", F.right("past", F.lit(SHARED[0])))
    known = known.join(lower[1].select(F.col("past").alias("short"), "letter", "p"), ["short", "letter"])

    def probability(c: str, below: Column) -> Column:
        """A class's discounted share; the rest, which is all where the class has no count, falls to what lies below."""
        share = (F.greatest(F.col(c) - DISCOUNT, F.lit(0.0)) + DISCOUNT * F.col(f"kinds_{c}") * below) / F.col(f"all_{c}")
        return F.when(F.col(f"all_{c}") > 0, share).otherwise(below)

    known = known.withColumn("p_o", probability("o", F.col("p")))
    return written(known.select("gram", F.ln(probability("t", F.col("p_o")) / F.col("p_o")).cast("float").alias("ratio")).where("ratio <> 0"), "ratios")


class Ratios:
    """Log ratios of words, from a table of grams' hashes (XXH64 with Spark's seed)."""

    def __init__(self, keys: np.ndarray, ratio: np.ndarray):
        order = np.argsort(keys)
        self.keys, self.ratio = keys[order], ratio[order].astype(np.float64)

    @staticmethod
    def _hashes(grams: list[str]) -> np.ndarray:
        import xxhash

        return np.fromiter((xxhash.xxh64_intdigest(g, SEED) for g in grams), np.uint64, len(grams))

    def of(self, words: list[str]) -> np.ndarray:
        parts = [grams_of(plain(w)) for w in words]
        sizes = np.fromiter(map(len, parts), np.int64, len(parts))
        keys = self._hashes([g for p in parts for g in p])
        if not len(self.keys) or not len(keys):
            return np.zeros(len(words))
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.add.reduceat(np.where(self.keys[at] == keys, self.ratio[at], 0.0), np.cumsum(sizes) - sizes)

    def documents(self, texts: list[str], kept: dict[str, float], most: int = 300_000) -> list[tuple[float, float, int]]:
        """Over all words of each text: sum of their log ratios, sum of what goes beyond EVIDENCE, and their number."""
        cut = [t.split() for t in texts]
        new = [w for w in set().union(*cut) if w not in kept]
        if len(kept) + len(new) > most:
            kept.clear()
            new = list(set().union(*cut))
        for at in range(0, len(new), 20_000):
            part = new[at : at + 20_000]
            kept.update(zip(part, self.of(part).tolist(), strict=True))
        out = []
        for words in cut:
            v = np.fromiter(map(kept.__getitem__, words), np.float64, len(words))
            out.append((float(v.sum()), float(np.maximum(v - EVIDENCE, 0).sum()), len(words)))
        return out


def _joined_differences(rows: DataFrame, ratios: DataFrame) -> DataFrame:
    """``_differences`` by joins: distinct words meet the grams, then documents their words."""
    from pyspark.sql.types import ArrayType, LongType, StringType, StructField, StructType

    fields = [f for f in rows.schema.fields if f.name != "text"]
    names = [F.col(f"`{f.name}`") for f in fields]
    word = StructType([StructField("w", StringType()), StructField("n", LongType())])
    schema = StructType([*fields, StructField("_row", LongType()), StructField("_w", ArrayType(word))])

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part = b.slice(at, 500)
                counts = [Counter(map(plain, t.split())) for t in part.column("text").to_pylist()]
                ends = pa.array(np.cumsum([0, *map(len, counts)]), pa.int32())
                pairs = pa.StructArray.from_arrays([pa.array([w for c in counts for w in c], pa.string()), pa.array([n for c in counts for n in c.values()], pa.int64())], names=["w", "n"])
                yield pa.RecordBatch.from_arrays([*[part.column(f.name) for f in fields], part.column("_row"), pa.ListArray.from_arrays(ends, pairs)], names=schema.names)

    lists = written(rows.select(*names, F.monotonically_increasing_id().alias("_row"), "text").mapInArrow(listed, schema), "words")
    pairs = lists.select("_row", F.inline("_w"))
    grams = pairs.select("w").distinct().select("w", F.explode(_cuts("w")).alias("gram"))
    values = grams.join(ratios, "gram").groupBy("w").agg(F.sum(F.col("ratio").cast("double")).alias("v"))
    beyond = F.greatest(F.col("v") - EVIDENCE, F.lit(0.0))
    sums = pairs.join(values, "w").groupBy("_row").agg(F.sum(F.col("v") * F.col("n")).alias("total"), F.sum(beyond * F.col("n")).alias("evidence"))
    none, words = F.lit(0.0), F.aggregate("_w", F.lit(0).cast("long"), lambda a, x: a + x["n"])
    return lists.join(sums, "_row", "left").select(*names, F.coalesce("total", none).alias("total"), F.coalesce("evidence", none).alias("evidence"), words.alias("words"))


def _differences(rows: DataFrame, ratios: DataFrame) -> DataFrame:
    """rows (other columns, text) -> other columns, total, evidence, words."""
    if ratios.count() > BROADCAST_GRAMS:
        return _joined_differences(rows, ratios)
    spark = rows.sparkSession
    fields = [f for f in rows.schema.fields if f.name != "text"]
    from pyspark.sql.types import DoubleType, LongType, StructField, StructType

    schema = StructType([*fields, StructField("total", DoubleType()), StructField("evidence", DoubleType()), StructField("words", LongType())])
    table = ratios.select(F.xxhash64("gram").alias("key"), "ratio").toArrow()  # BROADCAST_GRAMS rows at most
    model = spark.sparkContext.broadcast(Ratios(table.column("key").to_numpy().view(np.uint64), table.column("ratio").to_numpy()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict[str, float] = {}
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                b = whole.slice(at, 500)
                got = model.value.documents(b.column("text").to_pylist(), kept)
                yield pa.RecordBatch.from_arrays([*[b.column(f.name) for f in fields], *(pa.array([g[i] for g in got], t) for i, t in enumerate((pa.float64(), pa.float64(), pa.int64())))], names=schema.names)

    return rows.mapInArrow(run, schema)


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 1e-2) -> np.ndarray:
    """Coefficients (the last is the constant) of a ridge logistic regression, by Newton steps."""
    x = np.column_stack([x, np.ones(len(x))])
    b = np.zeros(x.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        g = x.T @ (weight * (y - p)) - ridge * b
        hess = (x * (weight * p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(b))
        step = np.linalg.solve(hess, g)
        b += step
        if np.abs(step).max() < 1e-8:
            break
    return b


def toxicity_scores(df: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", cut: float = CUT) -> DataFrame:
    """doc_id, held_out, score, predicted for every whole text.

    Counts come from all labelled rows of the folds 1 to 3, the score's scale
    from a bounded sample of fold 4; fold 0 is held out. Null and empty texts
    have a difference of 0. Rows that repeat an id are scored each; null ids
    too. With labels of one kind or none, every score is that kind's, or 0.5.
    """
    rows = training_rows(df, labels, id_col, text_col, label_col)
    ratios = log_ratios(rows.where(F.col("fold") != CALIBRATION_FOLD))
    own = rows.where(F.col("fold") == CALIBRATION_FOLD)
    n = {r["y"]: r["n"] for r in own.select("y").groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}
    ids = own.select("d", "y").distinct()
    sample = [ids.where(F.col("y") == y).orderBy(F.xxhash64("d"), "d").limit(CALIBRATION_ROWS) for y in (0, 1)]
    chosen = F.broadcast(sample[0].unionByName(sample[1]).select("d"))  # 2 * CALIBRATION_ROWS ids
    got = _differences(own.join(chosen, "d").select("y", "text"), ratios).toArrow()
    total, evidence, words, y = (got.column(c).to_numpy().astype(np.float64) for c in ("total", "evidence", "words", "y"))
    words = np.maximum(words, 1)
    if n.get(0) and n.get(1):
        weight = np.where(y == 1, n[1] / (y == 1).sum(), n[0] / (y == 0).sum())
        b = fit_logistic(np.column_stack([total / words, np.sqrt(evidence / words), np.log1p(evidence)]), y, weight / weight.mean())
    else:
        b = np.array([0.0, 0.0, 0.0, 30.0 if n.get(1) else -30.0 if n.get(0) else 0.0])
    asked = df.select(F.col(id_col).cast("long").alias("doc_id"), (fold(id_col) == 0).alias("held_out"), text_or_empty(text_col).alias("text"))
    out = _differences(asked, ratios)
    length = F.greatest("words", F.lit(1))
    x = F.col("total") / length * float(b[0]) + F.sqrt(F.col("evidence") / length) * float(b[1]) + F.log1p("evidence") * float(b[2]) + float(b[3])
    return out.select("doc_id", "held_out", (1 / (1 + F.exp(-x))).alias("score")).select("doc_id", "held_out", "score", (F.col("score") >= cut).cast("int").alias("predicted"))
