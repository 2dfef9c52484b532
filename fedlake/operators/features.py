"""One-hot slots of side features."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

USER_FIELDS = ("segment", "nation", "region", "decile")
ITEM_FIELDS = ("brand", "type", "size", "price_band", "words")


def long_fields(df: DataFrame, ident: str, fields: tuple[str, ...]) -> DataFrame:
    """(id, field, value): one row per feature value; arrays give one row per element."""
    kinds = dict(df.dtypes)

    def named(field: str):
        pair = lambda v: F.struct(F.lit(field).alias("field"), v.cast("string").alias("value"))
        return F.transform(F.col(field), pair) if kinds[field].startswith("array") else F.array(pair(F.col(field)))

    values = [named(f) for f in fields]
    return df.select(ident, F.explode(F.concat(*values)).alias("p")).select(ident, "p.field", "p.value").where("value is not null")


def vocabulary(long: DataFrame, side: str) -> DataFrame:
    """(side, field, value, slot): slots from 1 in order of field and value; 0 stays for unknown values.

    Values are numbered inside ranges of equal beginnings, after the counted ranges before them.
    """
    distinct = long.select("field", "value").distinct().withColumn("_c", F.substring("value", 1, 4))
    sizes = distinct.groupBy("field", "_c").agg(F.count("*").alias("_n"))
    before = Window.orderBy("field", "_c").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("field", "_c", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_off"))
    place = F.row_number().over(Window.partitionBy("field", "_c").orderBy("value"))
    return distinct.join(offsets, ["field", "_c"]).select(F.lit(side).alias("side"), "field", "value", (F.col("_off") + place).cast("int").alias("slot"))


def slots(long: DataFrame, vocab: DataFrame, ident: str) -> DataFrame:
    """(id, slot) of every feature value."""
    return long.join(vocab.select("field", "value", "slot"), ["field", "value"], "left").select(ident, F.coalesce("slot", F.lit(0)).alias("slot"))


def pack_slots(slotted: DataFrame, ident: str) -> DataFrame:
    """(id, slots array<int>), sorted."""
    return slotted.groupBy(ident).agg(F.sort_array(F.collect_list("slot")).alias("slots"))
