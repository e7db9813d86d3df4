"""Exact dedup by skew-safe combining, in DataFrame functions only.

Copies meet in three steps, each of which compares the whole normalised text:
the map side of the first aggregate removes copies within a task, salted
digest groups are merged, and the winners of all salts are combined.
"""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Characters that do not count: space, tab, line feed, vertical tab, form feed, carriage return (fixed values).
IGNORED = (" ", "\t", "\n", "\x0b", "\x0c", "\r")
#: Parts into which the copies of one text are dealt before they are combined.
SALTS = 8
_WIDE = "decimal(38,0)"


def normalised(text: Column) -> Column:
    out = F.coalesce(text, F.lit(""))
    for c in IGNORED:
        out = F.replace(out, F.lit(c), F.lit(""))
    return out


def _top() -> Column:
    """Above every id."""
    return F.lit(Decimal(2**63)).cast(_WIDE)


def _rank(chars: Column, doc: Column) -> Column:
    """One number that is largest for the longest original text, then the smallest id (a null id last)."""
    return chars.cast(_WIDE) * F.lit(Decimal(2**65)).cast(_WIDE) + F.coalesce(_top() - doc.cast(_WIDE), F.lit(0).cast(_WIDE))


def _salt(doc: Column, salts: int) -> Column:
    return F.pmod(F.xxhash64(doc), F.lit(salts)).cast("int")


def exact_groups(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """One row per distinct normalised text: digest (binary sha256), content, keep_id, group_size."""
    rows = df.select(F.col(id_col).alias("d"), F.coalesce(F.col(text_col), F.lit("")).alias("t")).select("d", F.char_length("t").alias("n"), normalised(F.col("t")).alias("content"))
    rows = rows.select(F.unhex(F.sha2("content", 256)).alias("digest"), "content", _salt(F.col("d"), salts).alias("salt"), _rank(F.col("n"), F.col("d")).alias("best"))
    salted = rows.groupBy("digest", "content", "salt").agg(F.max("best").alias("best"), F.count(F.lit(1)).alias("n"))
    whole = salted.groupBy("digest", "content").agg(F.max("best").alias("best"), F.sum("n").alias("group_size"))
    behind = F.pmod(F.col("best"), F.lit(Decimal(2**65)).cast(_WIDE))  # 0: only null ids
    return whole.select("digest", "content", F.when(behind > 0, (_top() - behind).cast("long")).alias("keep_id"), "group_size")


def exact_dedup(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", salts: int = SALTS) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row, dropped ones too.

    Texts are equal when they are identical after IGNORED characters are
    deleted; null is empty, and all empty texts are one group. Of equal texts
    the one with most code points in the original stays, then the smallest id.
    Every row with the id that stays is kept, also where a table repeats an id;
    rows with a null id stay only if their text has no other id. An empty
    table gives an empty result. Two texts with one digest stop the query with
    an error rather than meet as one group.
    """
    groups = exact_groups(df, id_col, text_col, salts).groupBy("digest").agg(F.count(F.lit(1)).alias("texts"), F.max("keep_id").alias("keep_id"), F.max("group_size").alias("group_size"))
    groups = groups.withColumn("group_size", F.when(F.col("texts") == 1, F.col("group_size")).otherwise(F.raise_error(F.lit("two texts have one digest")).cast("long")))
    # the members of a frequent digest are dealt over all salts; a text that occurs once needs the salt of its only row
    groups = groups.select("digest", "keep_id", "group_size", F.explode(F.when(F.col("group_size") == 1, F.array(_salt(F.col("keep_id"), salts))).otherwise(F.sequence(F.lit(0), F.lit(salts - 1)))).alias("salt"))
    rows = df.select(F.col(id_col).alias("doc_id"), F.unhex(F.sha2(normalised(F.col(text_col)), 256)).alias("digest")).withColumn("salt", _salt(F.col("doc_id"), salts))
    kept = F.coalesce(F.col("doc_id") == F.col("keep_id"), F.col("keep_id").isNull())
    return rows.join(groups, ["digest", "salt"]).select("doc_id", "keep_id", "group_size", kept.alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))
