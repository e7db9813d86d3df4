"""Best-fit packing of documents into sequences, certified by lower bounds.

Pieces are dealt into groups; each group packs its pieces by best-fit
decreasing and proves with dual feasible functions how many sequences it needs
at least. A group with a gap first exchanges pieces between its own sequences;
groups that still need more than their bound, and the remainders of the others,
hand documents over to fewer, newly dealt groups, which pack again until all
are certified or nothing more is gained.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetic.llm.common import written
from kinetic.llm.mixing import mix_sources
from kinetic.llm.tokens import crc32, default_tokenizer, encoder

CAPACITY = 1024
#: Pieces that one group packs at a time.
GROUP_PIECES = 16_384
#: A round that hands over more than this share of what it got gains nothing: its groups are then left as they are.
GAIN = 0.75
#: Draws of full sequences that a group with a gap repacks with those that are not full.
DRAWS = 8
#: Pieces that one group packs at a time where sequences follow an order: no piece is further from its place than about as many.
ORDERED_PIECES = 1_024
#: Pieces of one document that sequence numbers in an order tell apart.
_PIECES = 2**24


def lower_bound(sizes: np.ndarray, capacity: int, counts: np.ndarray | None = None) -> int:
    """Sequences that pieces of these sizes (1..capacity) need at least, by dual feasible functions.

    Functions: x/C above a small size with all larger than C minus it counted
    whole (for each threshold), and the rounding function with k = 1..20,
    alone and after thresholds. Sums are exact integers. ``counts``: how often
    each size occurs.
    """
    if not len(sizes):
        return 0
    hist = np.zeros(capacity + 1, np.int64)
    np.add.at(hist, sizes, 1 if counts is None else counts)
    x = np.arange(capacity + 1, dtype=np.int64)
    count = np.concatenate([[0], np.cumsum(hist)])  # pieces smaller than i
    load = np.concatenate([[0], np.cumsum(hist * x)])
    n, best = count[-1], -(-load[-1] // capacity)
    for small in range(1, capacity // 2 + 1):
        whole = n - count[capacity - small + 1]
        middle = load[capacity - small + 1] - load[small]
        best = max(best, whole + -(-middle // capacity))
    steps = sorted({1, *(capacity // d for d in range(3, 12)), capacity // 2})
    for k in range(1, 21):
        scaled = (k + 1) * x
        rounded = np.where(scaled % capacity == 0, x * k, scaled // capacity * capacity)  # in units of 1/(k C)
        for small in steps:
            f = np.where(x > capacity - small, k * capacity, np.where(x < small, 0, rounded)) if small > 1 else rounded
            best = max(best, -(-int((f * hist).sum()) // (k * capacity)))
    return int(best)


def best_fit(sizes: np.ndarray, capacity: int, keys: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best-fit decreasing: sequence and offset of each piece, and the tokens in each sequence.

    Pieces go by ``keys`` (their sizes), the greatest first, equal ones in their
    given order; of equally full sequences the latest opened takes a piece.
    """
    place, offset = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64)
    free: list[list[int]] = [[] for _ in range(capacity + 1)]  # sequences by what they have left
    open_mask, used = 0, []
    for i in np.argsort(-(sizes if keys is None else keys), kind="stable").tolist():
        s = int(sizes[i])
        fits = open_mask >> s
        if fits:
            left = s + (fits & -fits).bit_length() - 1
            b = free[left].pop()
            if not free[left]:
                open_mask &= ~(1 << left)
        else:
            b, left = len(used), capacity
            used.append(0)
        place[i], offset[i] = b, used[b]
        used[b] += s
        left -= s
        if left:
            free[left].append(b)
            open_mask |= 1 << left
    return place, offset, np.array(used, np.int64)


def certified_fit(sizes: np.ndarray, capacity: int, draws: int = DRAWS) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """``best_fit`` and the lower bound.

    While there is a gap, all sequences that are not full and half of the full
    ones are packed anew, in a nearly decreasing order, for ``draws`` draws;
    what needs fewer sequences stays.
    """
    place, offset, used = best_fit(sizes, capacity)
    bound = lower_bound(sizes, capacity)
    rng = np.random.default_rng(len(sizes))
    for _ in range(draws):
        if len(used) <= bound:
            break
        opened = (used < capacity) | (rng.random(len(used)) < 0.5)
        inside = np.flatnonzero(opened[place])
        p, o, u = best_fit(sizes[inside], capacity, sizes[inside] * rng.uniform(0.8, 1.0, len(inside)))
        if len(u) < opened.sum():
            kept = np.cumsum(~opened) - 1  # numbers of the sequences that stay closed
            place, offset = kept[place], offset.copy()
            place[inside], offset[inside] = p + (~opened).sum(), o
            used = np.concatenate([used[~opened], u])
    return place, offset, used, bound


def cut_documents(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None, capacity: int = CAPACITY, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, keep, pieces (piece, start, length, ids_crc32): a row for each document; ones longer than capacity are cut, the first piece takes the rest of the division."""
    tokenizer = tokenizer or default_tokenizer()
    kept = df.select(F.col(id_col).cast("long").alias("doc_id"), *[F.col(f"`{c}`") for c in keep])
    from pyspark.sql.types import ArrayType, IntegerType, LongType, StructField, StructType

    piece = StructType([StructField("piece", IntegerType()), *(StructField(c, LongType()) for c in ("start", "length", "ids_crc32"))])
    schema = StructType([*kept.schema.fields, StructField("pieces", ArrayType(piece))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = encoder(tokenizer)
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                b = whole.slice(at, 500)
                ends, out = [0], []
                for ids in codec.documents(b.column("_t").to_pylist()):
                    start, size = 0, (len(ids) - 1) % capacity + 1
                    for k in range(-(-len(ids) // capacity)):
                        out.append((k, start, size, crc32(ids[start : start + size])))
                        start, size = start + size, capacity
                    ends.append(len(out))
                k, start, length, crc = zip(*out, strict=True)
                struct = pa.StructArray.from_arrays([pa.array(k, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))], names=piece.names)
                yield pa.RecordBatch.from_arrays([*[b.column(c) for c in schema.names[:-1]], pa.ListArray.from_arrays(pa.array(ends, pa.int32()), struct)], names=schema.names)

    return df.select(F.col(id_col).cast("long").alias("doc_id"), *[F.col(f"`{c}`") for c in keep], F.col(text_col).alias("_t")).mapInArrow(run, schema)


def pieces_of(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: every document's ids with the end id, cut to the capacity."""
    return cut_documents(df, id_col, text_col, tokenizer, capacity).select("doc_id", F.inline("pieces"))


def _packer(columns: list[str], capacity: int, r: int, last: bool, order: str | None = None):
    """Packs one group of round r; after the last round nothing is handed over. With an order, a sequence has the number of its first piece."""
    if order:
        columns = [order, *(c for c in columns if c != order)]

    def run(key: tuple, group: pa.Table) -> pa.Table:
        group = group.select(columns).sort_by([(c, "ascending") for c in columns])
        g = key[0].as_py()
        sizes = group.column("length").to_numpy().astype(np.int64)
        place, offset, used, bound = certified_fit(sizes, capacity)
        stay = np.ones(len(used), bool)
        if not last:
            if len(used) > bound:
                stay = used == capacity
            elif used.min() < capacity:
                stay[used.argmin()] = False
        number = (r << 56) + (g << 24) + place
        if order:
            first = np.full(len(used), np.iinfo(np.int64).max)
            np.minimum.at(first, place, group.column(order).to_numpy() * _PIECES + group.column("piece").to_numpy())
            number = first[place]
            group = group.append_column("_g", pa.array(np.full(len(place), g), pa.int64()))
        made = {"sequence_id": number, "offset": offset, "placed": stay[place], "group_bound": np.full(len(place), bound), "group_sequences": np.full(len(place), len(used))}
        for name, values in made.items():
            group = group.append_column(name, pa.array(values))
        return group

    return run


def _ranges(rest: DataFrame, groups: int) -> DataFrame:
    """Joins neighbouring groups _g to ``groups`` new ones of about equally many pieces."""
    counts = sorted((r["_g"], r["n"]) for r in rest.groupBy("_g").agg(F.count(F.lit(1)).alias("n")).collect())  # a row for each ORDERED_PIECES documents
    total, before, new = sum(n for _, n in counts), 0, []
    for g, n in counts:
        new.append((g, (2 * before + n) * groups // (2 * total)))
        before += n
    return rest.join(F.broadcast(rest.sparkSession.createDataFrame(new, "_g long, _new long")), "_g").drop("_g").withColumnRenamed("_new", "_g")


def pack(pieces: DataFrame, capacity: int = CAPACITY, group_pieces: int = GROUP_PIECES, order: str | None = None) -> DataFrame:
    """+sequence_id, offset, group_bound, group_sequences for pieces with a length of 1..capacity; other columns stay.

    Whole pieces fill a sequence each. A group is certified when it needs no
    more sequences than its lower bound; it then hands over the emptiest one
    only, a group with a gap all that are not full. Rounds end when one group
    has packed all that was handed over, or when a round hands nearly all of it
    over again. group_bound and group_sequences tell of the group that placed a
    piece how many sequences its pieces need at least and how many it made.
    Rows may repeat: each is placed, and dealt by its place in ``pieces``, which
    has to be a stored table. An empty table gives an empty result.

    ``order``: a column with a number from 0 for each document, without large
    gaps. Groups are then ranges of it, neighbours hand over to each other, and
    sequence_id grows with the first piece in a sequence.
    """
    from pyspark.sql.types import BooleanType, LongType, StructField, StructType

    columns, one = pieces.columns, F.lit(1).cast("long")
    full = pieces.where(F.col("length") >= capacity).withColumn("sequence_id", F.col(order) * _PIECES + F.col("piece") if order else -1 - F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long"))
    rest, done = pieces.where(F.col("length") < capacity), [full.withColumns({"group_bound": one, "group_sequences": one})]
    columns_of_rest = [*[F.col(f"`{c}`") for c in columns], *([F.col("_g")] if order else [])]
    if order:
        rest = rest.withColumn("_g", F.floor(F.col(order) / group_pieces).cast("long"))
    made = [StructField(c, LongType()) for c in ("sequence_id", "offset")] + [StructField("placed", BooleanType())] + [StructField(c, LongType()) for c in ("group_bound", "group_sequences")]
    schema = StructType([*pieces.schema.fields, *([StructField("_g", LongType())] if order else []), *made])
    r, before = 0, None
    while n := rest.count():
        groups = -(-n // group_pieces)
        last = groups == 1 or (before is not None and n > GAIN * before)
        dealt = _ranges(rest, groups) if order else rest.withColumn("_g", F.pmod(F.xxhash64(F.lit(r), F.monotonically_increasing_id()), F.lit(groups)))
        packed = written(dealt.groupBy("_g").applyInArrow(_packer(columns, capacity, r, last, order), schema), "packed")
        done.append(packed.where("placed").drop("placed", "_g") if order else packed.where("placed").drop("placed"))
        rest = packed.where("NOT placed").select(*columns_of_rest)
        if last:
            break
        r, before = r + 1, n
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    return out


def certificate(packed: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """One row: sequences, the lower bound for all pieces together, and the gap. At most ``capacity`` lengths reach the driver."""
    lengths = {r["length"]: r["n"] for r in packed.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    sizes = np.fromiter(lengths, np.int64, len(lengths))
    bound = lower_bound(sizes, capacity, np.fromiter(lengths.values(), np.int64, len(lengths)))
    used = packed.select("sequence_id").distinct().count()
    return packed.sparkSession.createDataFrame([(used, bound, used - bound)], "sequences long, bound long, gap long")


def pack_documents(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """Every piece of every document with its sequence and place. Null texts are empty documents of one id."""
    return pack(written(pieces_of(df, id_col, text_col, tokenizer, capacity), "pieces"), capacity)


def pack_mixed(df: DataFrame, weights: dict[str, float] | None = None, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", tokenizer: str | None = None, capacity: int = CAPACITY, group_pieces: int = ORDERED_PIECES) -> DataFrame:
    """``pack_documents`` +mix_position, with sequences in the order of the mix: any beginning of them has the sources at their target weights, but for about a group.

    Positions follow from ids, sources and weights alone, so they are those of ``in_mixed_order`` however its files are read.
    """
    cut = written(cut_documents(df, id_col, text_col, tokenizer, capacity, (source_col,)), "cut")
    pieces = mix_sources(cut, weights, "doc_id", source_col).select("doc_id", "mix_position", F.inline("pieces"))
    return pack(written(pieces, "pieces"), capacity, group_pieces, "mix_position")
