"""Quartile bucket digests: hashed byte triplets counted in buckets, each bucket coded by its quartile.

A digest is hexadecimal: two digits of a length class, two of quartile ratios,
then two bits for each bucket. The difference of two digests adds the bucket
distances, the distance of length classes and that of the ratios; it is
bounded, so a likeness from 0 to 1 follows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kinetic.llm.common import text_or_empty

BUCKETS = 256
#: Odd multipliers, one for each pattern of three bytes out of a window of four.
_MULTIPLIERS = (0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D)
#: Bucket codes that lie further apart than one quartile weigh more (fixed values).
_FAR = (0, 1, 2, 6)
#: A step of the length class and of a ratio counts as so many bucket steps; length classes further apart than this count alike.
_LENGTH_STEP, _RATIO_STEP, _LENGTH_MOST = 6, 2, 24
WORST = 6 * BUCKETS + _LENGTH_STEP * _LENGTH_MOST + 2 * 15 * _RATIO_STEP
#: Likeness reaches 0 at this share of the worst difference: unrelated texts lie near it.
_SCALE = 0.5


def bucket_counts(texts: list[bytes]) -> np.ndarray:
    """int64 matrix texts x BUCKETS: how many byte triplets fall into each bucket."""
    n = len(texts)
    sizes = np.fromiter(map(len, texts), np.int64, n)
    data = np.frombuffer(b"".join(texts), np.uint8).astype(np.uint32)
    counts = np.zeros(n * BUCKETS, np.int64)
    if len(data) < 3:
        return counts.reshape(n, BUCKETS)
    row = np.repeat(np.arange(n, dtype=np.int64), sizes)
    end = np.repeat(np.cumsum(sizes), sizes)
    at = np.arange(len(data), dtype=np.int64)
    for (i, j), k in zip(((1, 2), (1, 3), (2, 3)), _MULTIPLIERS, strict=True):
        m = len(data) - j
        inside = (at[:m] + j) < end[:m]
        h = data[:m] | (data[i : m + i] << np.uint32(8)) | (data[j:] << np.uint32(16))
        h = (h * np.uint32(k)) ^ (h >> np.uint32(7))
        h = (h * np.uint32(_MULTIPLIERS[0])) >> np.uint32(24)
        counts += np.bincount((row[:m] * BUCKETS + h)[inside], minlength=n * BUCKETS)
    return counts.reshape(n, BUCKETS)


def digests(texts: list[bytes]) -> list[str]:
    """Equal texts have equal digests; a text of fewer than three bytes has empty buckets only."""
    if not texts:
        return []
    counts = bucket_counts(texts)
    quarters = np.sort(counts, axis=1)[:, [BUCKETS // 4 - 1, BUCKETS // 2 - 1, 3 * BUCKETS // 4 - 1]]
    codes = (counts[:, :, None] > quarters[:, None, :]).sum(2).astype(np.uint8)
    sizes = np.fromiter(map(len, texts), np.float64, len(texts))
    length = np.minimum(255, np.round(np.log(sizes + 1) / np.log(1.25))).astype(np.uint8)
    top = np.maximum(quarters[:, 2], 1)
    ratios = ((quarters[:, 0] * 15 // top) << 4 | (quarters[:, 1] * 15 // top)).astype(np.uint8)
    packed = codes[:, 0::4] << 6 | codes[:, 1::4] << 4 | codes[:, 2::4] << 2 | codes[:, 3::4]
    return [bytes(x).hex() for x in np.column_stack([length, ratios, packed])]


def _unpacked(fingerprints: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    raw = np.frombuffer(bytes.fromhex("".join(fingerprints)), np.uint8).reshape(len(fingerprints), 2 + BUCKETS // 4)
    codes = np.empty((len(fingerprints), BUCKETS), np.int16)
    for k in range(4):
        codes[:, k::4] = raw[:, 2:] >> (6 - 2 * k) & 3
    return codes, raw[:, 0].astype(np.int16), np.column_stack([raw[:, 1] >> 4, raw[:, 1] & 15]).astype(np.int16)


def differences(a: list[str], b: list[str]) -> np.ndarray:
    """Difference of each pair: 0 for equal digests, at most WORST."""
    if not a:
        return np.zeros(0, np.int64)
    (ca, la, ra), (cb, lb, rb) = _unpacked(a), _unpacked(b)
    far = np.array(_FAR)[np.abs(ca - cb)].sum(1)
    return far + _LENGTH_STEP * np.minimum(_LENGTH_MOST, np.abs(la - lb)) + _RATIO_STEP * np.abs(ra - rb).sum(1)


def likeness(a: list[str], b: list[str]) -> np.ndarray:
    """1 for equal digests, falling to 0 with the difference."""
    return np.maximum(0.0, 1 - differences(a, b) / (_SCALE * WORST))


def with_fingerprints(df: DataFrame, text_col: str = "text", name: str = "fingerprint") -> DataFrame:
    """+fingerprint of every whole text (null: as empty); a clashing column is replaced. No shuffle."""
    from pyspark.sql.types import StringType, StructField, StructType

    rest = df.drop(name)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = pa.array(_in_parts([(t or "").encode() for t in b.column(text_col).to_pylist()]), pa.string())
            yield pa.RecordBatch.from_arrays([*b.columns, out], names=[*b.schema.names, name])

    return rest.mapInArrow(run, StructType([*rest.schema.fields, StructField(name, StringType())]))


def _in_parts(texts: list[bytes], most: int = 2_000_000) -> list[str]:
    """digests() over runs of about ``most`` bytes, so that memory stays bounded."""
    out, part, size = [], [], 0
    for t in texts:
        part.append(t)
        size += len(t)
        if size >= most:
            out += digests(part)
            part, size = [], 0
    return out + digests(part)


def edited(text: str, following: str) -> str:
    """The last third of the text replaced by as many first code points of the following one (or all)."""
    m = len(text) // 3
    return text[: len(text) - m] + following[:m]


_OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


#: Rows of a range, about, and ranges at most: their bounds are two numbers each, held by the driver and by every task.
RANGE_ROWS, MOST_RANGES = 8_000, 16_384
#: Rows that are drawn for each range, to set the bounds by.
DRAWN = 24


def _range_bounds(rows: DataFrame, rows_per_range: int) -> list[tuple[int, int]]:
    """Greatest (k, h) of each range but the last, and of all; from a bounded draw and one pass. Empty for an empty table."""
    n = rows.count()
    if not n:
        return []
    ranges = min(MOST_RANGES, -(-n // rows_per_range))
    share = min(1.0, DRAWN * ranges / n)
    drawn = rows.select(F.struct("k", "h").alias("key"), (F.rand(11) < share).alias("hit"))
    got = drawn.agg(F.max("key").alias("top"), F.collect_list(F.when(F.col("hit"), F.col("key"))).alias("drawn")).first()  # DRAWN * MOST_RANGES pairs, about
    drawn, top = sorted(tuple(r) for r in got["drawn"]), tuple(got["top"])
    cuts = {drawn[i * len(drawn) // ranges] for i in range(1, ranges)} if drawn else set()
    return [*sorted(c for c in cuts if c < top), top]


def neighbour_fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", rows_per_range: int = RANGE_ROWS) -> DataFrame:
    """Digests of every whole text and of its edited text, with their likeness to each other and to the next document's.

    Documents follow each other by descending id, and after the last comes the
    first. Equal ids follow each other by a hash of their text; null ids come
    last. A table of one row has itself as next; an empty table gives no rows.
    Rows are dealt by ranges of id and hash, so that a repeated id is no single
    range; each range gets a copy of the first document of the next one and is
    read once in order: one shuffle of the texts. Rows that are equal in id and
    text share a range.
    """
    from kinetic.llm.common import rows_of

    low = -(2**63)
    rows = df.select(F.coalesce(F.col(id_col).cast("long"), F.lit(low)).alias("k"), F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("t")).withColumn("h", F.xxhash64("t"))
    bounds = _range_bounds(rows.select("k", "h"), rows_per_range)
    if not bounds:
        return df.sparkSession.createDataFrame([], _OUT)
    # range r holds what lies above bounds[r - 1], up to bounds[r]; ranges are read from the last to the first
    ranged = rows.withColumn("r", _range_of(F.col("k"), F.col("h"), bounds)).withColumn("top", F.struct(_nth([k for k, _ in bounds], F.col("r")).alias("k"), _nth([h for _, h in bounds], F.col("r")).alias("h")))
    own = F.struct(F.col("r"), F.lit(0).alias("guest"))
    guest = F.struct(F.when(F.col("r") + 1 < len(bounds), F.col("r") + 1).otherwise(0).alias("r"), F.lit(1).alias("guest"))  # the last range is read first, and follows the first one's last row
    dealt = ranged.select("k", "h", "doc_id", "t", F.explode(F.when(F.struct("k", "h") == F.col("top"), F.array(own, guest)).otherwise(F.array(own))).alias("x"))
    order = ["r", "guest", F.desc("k"), F.desc("h"), "t"]
    dealt = dealt.select(F.col("x.r").alias("r"), F.col("x.guest").alias("guest"), "k", "h", "doc_id", "t").repartitionById(len(bounds), F.col("r")).sortWithinPartitions(*order).select("r", "guest", "doc_id", "t")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []  # rows that await the row behind them: r, guest, doc_id, text
        size, closed = 0, None

        def out(rows: list[tuple]) -> pa.RecordBatch:
            """For all but the last of rows that follow each other."""
            own = _in_parts([t.encode() for *_, t in rows])
            changed = [edited(a[3], b[3]).encode() for a, b in zip(rows, rows[1:], strict=False)]
            prints = _in_parts(changed)
            return pa.RecordBatch.from_arrays([
                pa.array([r[2] for r in rows[:-1]], pa.int64()), pa.array([len(r[3]) for r in rows[:-1]], pa.int64()),
                pa.array([hashlib.sha256(x).hexdigest() for x in changed], pa.string()), pa.array(own[:-1], pa.string()), pa.array(prints, pa.string()),
                pa.array(likeness(own[:-1], prints), pa.float64()), pa.array(likeness(own[:-1], own[1:]), pa.float64()),
            ], names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

        for r, guest, doc, text in rows_of(batches, ["r", "guest", "doc_id", "t"]):
            if closed == r and guest:
                continue  # of equal ids only the first is next
            if held and held[0][0] != r:
                held, size = [], 0
            held.append((r, guest, doc, text))
            size += len(text)
            if guest:
                closed = r
            if (guest or size > 4_000_000) and len(held) > 1:
                yield out(held)
                held, size = held[-1:], len(text)

    return dealt.mapInArrow(run, _OUT)


def _nth(values: list[int], at: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, values)), at + 1)


def _range_of(k: Column, h: Column, bounds: list[tuple[int, int]]) -> Column:
    """How many bounds lie below (k, h), by halving an array of them."""
    ks, hs = (F.array(*[F.lit(b[i]) for b in bounds]) for i in (0, 1))

    def step(a: Column, _: Column) -> Column:
        mid = F.floor((a["lo"] + a["hi"]) / 2).cast("int")
        below = (F.element_at(ks, mid + 1) < k) | ((F.element_at(ks, mid + 1) == k) & (F.element_at(hs, mid + 1) < h))
        done = a["lo"] >= a["hi"]
        return F.struct(F.when(~done & below, mid + 1).otherwise(a["lo"]).alias("lo"), F.when(~done & ~below, mid).otherwise(a["hi"]).alias("hi"))

    start = F.struct(F.lit(0).alias("lo"), F.lit(len(bounds) - 1).alias("hi"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(len(bounds).bit_length())), start, step, lambda a: a["lo"])
