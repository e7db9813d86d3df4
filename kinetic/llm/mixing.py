"""Mixing sources to target weights by Pfair scheduling.

A source's documents form blocks. With weight k of K, its block j is released
at slot floor(j K / k) and due by slot ceil((j + 1) K / k); earliest deadline
first gives each slot to a released block. The schedule repeats after K slots,
so one period stands for it at any length, and at every slot each source is
less than one block from its share. When a source has no block left the others
go on by their weights among themselves. Weights are never rounded.
"""

from __future__ import annotations

import heapq
import math
from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BLOCK_DOCS = 64
#: Rows that are ranked together, about: sources are dealt into as many parts as that takes, and into LEAST_PARTS at least.
RANKED_ROWS, LEAST_PARTS = 50_000, 32
#: Default targets are whole numbers of this many parts.
PARTS = 1000
#: Slots of all stretches' periods together, at most: they are worked out on the driver. Weights that need more are refused.
MOST_SLOTS = 5_000_000


def period(weights: dict[str, int]) -> list[str]:
    """The source of each slot of one period of sum(weights) slots, by earliest deadline first."""
    total = sum(weights.values())
    released: list[tuple[int, str, int]] = []
    future = [(0, s, 0) for s in sorted(weights)]
    heapq.heapify(future)
    slots = []
    for t in range(total):
        while future and future[0][0] <= t:
            _, s, j = heapq.heappop(future)
            heapq.heappush(released, (-(-(j + 1) * total // weights[s]), s, j))
        _, s, j = heapq.heappop(released)
        slots.append(s)
        if j + 1 < weights[s]:
            heapq.heappush(future, ((j + 1) * total // weights[s], s, j + 1))
    return slots


def phases(blocks: dict[str, int], weights: dict[str, int]) -> list[dict]:
    """Stretches of the schedule with the same sources: slot and blocks of each source that come before, and the period."""
    done = dict.fromkeys(blocks, 0)
    live, slot, out = {s for s, n in blocks.items() if n}, 0, []
    while live:
        w = {s: weights[s] for s in live}
        order = period(w)
        total = len(order)
        # whole periods that every source has blocks for, then slots up to the first one without
        rounds = min((blocks[s] - done[s]) // w[s] for s in live)
        left = {s: blocks[s] - done[s] - rounds * w[s] for s in live}
        extra = 0
        for s in order:
            if left[s] == 0:
                break
            left[s] -= 1
            extra += 1
        out.append({"slot": slot, "done": dict(done), "weights": w, "order": order, "until": {s: blocks[s] - left[s] for s in live}})
        for s in live:
            done[s] = blocks[s] - left[s]
        slot += rounds * total + extra
        live = {s for s in live if left[s]}
    return out


def exact_weights(weights: dict[str, float]) -> dict[str, int]:
    """The whole numbers that stand in exactly the ratios of the weights, which are read as the decimal numbers that they print as."""
    if any(not math.isfinite(w) or w < 0 for w in weights.values()):
        raise ValueError("weights have to be finite and not negative")
    parts = {s: Fraction(str(w)) for s, w in weights.items()}
    whole = math.lcm(*(f.denominator for f in parts.values())) if parts else 1
    counts = {s: int(f * whole) for s, f in parts.items()}
    shared = math.gcd(*counts.values()) or 1
    return {s: n // shared for s, n in counts.items()}


def root_weights(sizes: dict[str, int]) -> dict[str, int]:
    """Default targets: a source's share of the square roots of all sizes in parts of PARTS, one at least; small sources are lifted."""
    total = sum(n**0.5 for n in sizes.values())
    return {s: max(1, round(PARTS * n**0.5 / total)) for s, n in sizes.items()}


_MADE = ("mix_source", "mix_block", "mix_release", "mix_deadline", "mix_slot", "mix_position")


def mix_sources(df: DataFrame, weights: dict[str, float] | None = None, id_col: str = "doc_id", source_col: str = "source", block: int = BLOCK_DOCS) -> DataFrame:
    """df +mix_source, mix_block, mix_release, mix_deadline, mix_slot, mix_position: every row, once; clashing columns are replaced.

    A source's rows are ordered by a hash of their id (rows without an id by
    their place in the table), and ``block`` of them make a block; the last one
    may be shorter. Null sources are the source ''. Sources that ``weights``
    does not name have the least weight that it gives above 0. A source of
    weight 0 has no turn: its rows come back with null in the columns from
    mix_block on. mix_position orders the other rows; rows that repeat an id lie
    side by side in any order. Weights hold exactly: after every slot each
    source is less than one block from its share, until one of them ends.
    Weights whose ratios take more than MOST_SLOTS slots to come round are
    refused with a ValueError. Release and deadline are slots of the whole
    schedule, in the stretch that the block falls into. An empty table gives an
    empty result.
    """
    spark = df.sparkSession
    rest = [c for c in df.columns if c not in _MADE]
    # all columns of the input travel in one, so that none meets a name that is used here
    rows = df.select(F.coalesce(F.col(f"`{source_col}`").cast("string"), F.lit("")).alias("s"), F.col(f"`{id_col}`").alias("id"), F.struct(*[F.col(f"`{c}`") for c in rest]).alias("row") if rest else F.lit(None).alias("row"))
    rows = rows.withColumn("h", F.when(F.col("id").isNotNull(), F.xxhash64("id")).otherwise(F.xxhash64(F.monotonically_increasing_id())))
    sizes = {r["s"]: r["n"] for r in rows.groupBy("s").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row for each source
    given = weights or root_weights(sizes)
    least = min((w for w in given.values() if w > 0), default=1)
    whole = exact_weights({s: given.get(s, least) for s in sizes})
    served = {s: w for s, w in whole.items() if w > 0}
    if sum(served.values()) * len(served) > MOST_SLOTS:
        raise ValueError(f"the weights of {len(served)} sources come round after {sum(served.values())} slots only: give rounder ones")
    parts = max(LEAST_PARTS, -(-max(sizes.values(), default=0) // RANKED_ROWS))
    # rank within a source without gathering it: its parts follow each other, so the rows of the parts before are added
    rows = rows.withColumn("part", F.pmod("h", F.lit(parts)).cast("int"))
    before = rows.groupBy("s", "part").agg(F.count(F.lit(1)).alias("n"))
    before = before.select("s", "part", F.coalesce(F.sum("n").over(Window.partitionBy("s").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    ranked = rows.withColumn("rank", F.row_number().over(Window.partitionBy("s", "part").orderBy("h", "id")))
    ranked = ranked.join(before, ["s", "part"])  # sources x parts rows: a row for each RANKED_ROWS rows of a source, or LEAST_PARTS
    ranked = ranked.withColumn("at", F.col("before") + F.col("rank") - 1).withColumn("block", F.floor(F.col("at") / block).cast("long"))
    plan, turns = [], []
    for p, ph in enumerate(phases({s: -(-n // block) for s, n in sizes.items() if s in served}, served)):
        for s, w in ph["weights"].items():
            if ph["until"][s] > ph["done"][s]:
                plan.append((p, s, ph["done"][s], ph["until"][s], ph["slot"], w, len(ph["order"])))
        seen: dict[str, int] = {}
        for t, s in enumerate(ph["order"]):
            turns.append((p, s, seen.get(s, 0), t))
            seen[s] = seen.get(s, 0) + 1
    # sources x stretches and slots x stretches: MOST_SLOTS rows at most
    stretch = spark.createDataFrame(plan, "phase int, p_s string, from long, until long, slot long, w long, total long")
    turn = spark.createDataFrame(turns, "t_phase int, t_s string, turn long, t long")
    fits = (F.col("s") == F.col("p_s")) & (F.col("block") >= F.col("from")) & (F.col("block") < F.col("until"))
    out = ranked.join(F.broadcast(stretch), fits, "left").withColumn("j", F.col("block") - F.col("from"))
    turn = F.broadcast(turn) if len(turns) <= 200_000 else turn
    out = out.join(turn, (F.col("phase") == F.col("t_phase")) & (F.col("s") == F.col("t_s")) & (F.pmod("j", F.col("w")) == F.col("turn")), "left")
    position = {
        "mix_source": F.col("s"), "mix_block": F.when(F.col("w").isNotNull(), F.col("block")), "mix_release": F.expr("slot + j * total div w"), "mix_deadline": F.expr("slot + ((j + 1) * total + w - 1) div w"),
        "mix_slot": F.expr("slot + (j div w) * total + t"), "mix_position": F.expr(f"(slot + (j div w) * total + t) * {block} + at % {block}"),
    }
    return out.select(*[F.col(f"row.`{c}`").alias(c) for c in rest], *[c.alias(n) for n, c in position.items()])


def in_mixed_order(df: DataFrame, weights: dict[str, float] | None = None, id_col: str = "doc_id", source_col: str = "source", block: int = BLOCK_DOCS) -> DataFrame:
    """The rows of df, dealt into files in the order of the mix, with rows of weight 0 behind all others; columns as in df."""
    whole = df.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{source_col}`").alias("source"), F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("whole"))
    mixed = mix_sources(whole, weights, "id", "source", block)
    order = F.asc_nulls_last("mix_position")
    return mixed.repartitionByRange(order).sortWithinPartitions(order).select(*[F.col(f"whole.`{c}`").alias(c) for c in df.columns])
