"""Exact de-duplication: one hash aggregate, byte comparison inside each group, DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import ascii_lower
from ..plans.shared import materialise, skew_safe_lookup


#: Bits of the map of repeated hashes, and bits of one row of it.
MAP_BITS, ROW_BITS = 26, 15


def _collisions(texts: DataFrame, repeated: DataFrame) -> DataFrame:
    """(_h): the hashes under which different texts stand."""
    place = F.pmod(F.xxhash64("_h"), F.lit(1 << MAP_BITS))
    row, bit = F.shiftright(place, ROW_BITS), F.pmod(place, F.lit(1 << ROW_BITS))
    marks = repeated.groupBy(row.alias("_row")).agg(F.bitmap_construct_agg(bit).alias("_map"))  # at most 2^11 rows of 4 KB
    byte = F.conv(F.hex(F.expr("substring(_map, cast(_bit div 8 as int) + 1, 1)")), 16, 10).cast("int")
    near = texts.withColumn("_place", row).withColumn("_bit", bit).join(F.broadcast(marks), F.col("_place") == F.col("_row"))
    near = near.filter(byte.bitwiseAND(F.expr("shiftleft(1, cast(_bit % 8 as int))")) != 0)
    return near.groupBy("_h").agg((F.min("_norm") != F.max("_norm")).alias("_mixed")).filter("_mixed").select("_h")


def exact_dedup(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", hash_bits: int = 128
) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when they are identical after lower-casing A to Z. Groups are formed
    by the leading ``hash_bits`` bits of the text's SHA-256, counted without the texts. Then bytes are compared inside every group of two or
    more: a bit map of such groups' hashes, 8 MB at any size, keeps other texts out of the exchange, and least and greatest text of
    a group aggregate before it, so a group of a third of all rows arrives as one row per map task. A group in which they differ is taken
    apart by whole text. ``keep`` names the row that stays: ``min`` or ``max`` id.

    Null text: the empty text. Null ids are ignored in the choice unless a group has no
    other; then keep_id is null and its rows stay. Rows that repeat an id share its decision.
    Empty table: no rows. Other columns are ignored, whatever their names.
    """
    if keep not in ("min", "max"):
        raise ValueError("keep is 'min' or 'max'")
    if hash_bits % 8 or not 8 <= hash_bits <= 256:
        raise ValueError("hash_bits is a multiple of 8 from 8 to 256")
    text = F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit(""))
    base = docs.select(F.col(f"`{id_col}`").alias("doc_id"), ascii_lower(text).alias("_norm")).withColumn(
        "text_sha256", F.sha2("_norm", 256)
    )
    base = base.withColumn("_h", F.unhex(F.substring("text_sha256", 1, hash_bits // 4)))

    pick = F.min if keep == "min" else F.max
    counted = lambda df: df.groupBy("_h").agg(F.count(F.lit(1)).alias("group_size"), pick("doc_id").alias("keep_id"))
    groups = materialise(counted(base.select("_h", "doc_id")), "content-groups")
    bad = materialise(_collisions(base.select("_h", "_norm"), groups.filter("group_size > 1").select("_h")), "collisions")
    if not bad.isEmpty():
        # the whole text takes the place of the hash for the rows of those groups
        base = base.join(bad.select(F.col("_h").alias("_bad")), F.col("_h") == F.col("_bad"), "left")
        whole = F.concat(F.lit("t").cast("binary"), F.encode("_norm", "UTF-8"))
        base = base.withColumn("_h", F.when(F.col("_bad").isNull(), F.concat(F.lit("h").cast("binary"), "_h")).otherwise(whole)).drop("_bad")
        groups = materialise(counted(base.select("_h", "doc_id")), "content-groups")
    total = groups.agg(F.coalesce(F.sum("group_size"), F.lit(0))).first()[0]
    out = skew_safe_lookup(
        base.select("doc_id", "text_sha256", "_h"), groups, "_h", "group_size", total, ["keep_id", "group_size"]
    )
    return out.select(
        "doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256"
    )
