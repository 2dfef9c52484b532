"""Activity sequences and their masked views."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.functions.hashing import uniform

GAP = 24 * 3600
#: Shortest session with masked views, shortest and longest masked segment.
MIN_VIEW = 3
SEGMENT = (2, 4)
NEGATIVES = 8


def seconds(ts: str) -> Column:
    """Seconds of a zone-less time since 2000."""
    return F.expr(f"timestampdiff(SECOND, TIMESTAMP_NTZ'2000-01-01 00:00:00', {ts})")


def with_sessions(rows: DataFrame, gap: int = GAP, ident: str = "event_id") -> DataFrame:
    """Rows with session_id (from 0 per client) and pos (from 0 in the session): a pause over ``gap`` seconds opens a session."""
    order = Window.partitionBy("client_id").orderBy("_s", ident)
    timed = rows.withColumn("_s", seconds("ts"))
    opened = timed.withColumn("_new", (F.col("_s") - F.lag("_s").over(order) > gap).cast("int"))
    numbered = opened.withColumn("session_id", F.coalesce(F.sum("_new").over(order.rowsBetween(Window.unboundedPreceding, 0)), F.lit(0)))
    inside = Window.partitionBy("client_id", "session_id").orderBy("_s", ident)
    return numbered.withColumn("pos", F.row_number().over(inside) - 1).drop("_new", "_s")


def sessions(rows: DataFrame, gap: int = GAP, min_len: int = 1, max_len: int | None = None, ident: str = "event_id") -> DataFrame:
    """client_id, session_id, n, start_ts, end_ts, items (in order); longer ones keep their first ``max_len`` items."""
    placed = with_sessions(rows, gap, ident)
    if max_len:
        placed = placed.where(F.col("pos") < max_len)
    packed = placed.groupBy("client_id", "session_id").agg(F.count("*").alias("n"), F.min("ts").alias("start_ts"), F.max("ts").alias("end_ts"), F.sort_array(F.collect_list(F.struct("pos", "item_id"))).alias("_p"))
    return packed.where(F.col("n") >= min_len).select("client_id", "session_id", "n", "start_ts", "end_ts", F.transform("_p", lambda p: p["item_id"]).alias("items"))


def item_ordinals(items: DataFrame) -> DataFrame:
    """(item_id, ordinal from 0) in order of id, by counts of id ranges: no task sorts all items."""
    whole = dict(items.dtypes)["item_id"] in ("bigint", "int")
    chunk = F.floor(F.col("item_id") / 1000) if whole else F.substring("item_id", 1, 4)
    marked = items.select("item_id").distinct().withColumn("_c", chunk)
    sizes = marked.groupBy("_c").agg(F.count("*").alias("_n"))
    offsets = sizes.withColumn("_off", F.coalesce(F.sum("_n").over(Window.orderBy("_c").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_n")
    return marked.join(offsets, "_c").withColumn("ordinal", F.col("_off") + F.row_number().over(Window.partitionBy("_c").orderBy("item_id")) - 1).select("item_id", "ordinal")


def drawn_item(total: int, seed: str, *key) -> Column:
    """Ordinal of a hashed item."""
    return F.floor(uniform(seed, *key) * total).cast("long")


def mask_item(sess: DataFrame, items: DataFrame, seed: str = "mask") -> DataFrame:
    """One view per session of at least ``MIN_VIEW`` items: the item at a hashed position becomes a hashed other item.

    client_id, session_id, pos (from 0), target, negative, view.
    """
    placed = item_ordinals(items)
    total = items.select("item_id").distinct().count()
    long = sess.where(F.size("items") >= MIN_VIEW)
    pos = F.floor(uniform(seed + ":pos", F.col("client_id"), F.col("session_id")) * F.size("items")).cast("int")
    drawn = long.withColumn("pos", pos).withColumn("target", F.element_at("items", F.col("pos") + 1)).withColumn("ordinal", drawn_item(total, seed, F.col("client_id"), F.col("session_id")))
    named = drawn.join(placed.withColumnRenamed("item_id", "_a"), "ordinal").withColumn("ordinal", (F.col("ordinal") + 1) % total).join(placed.withColumnRenamed("item_id", "_b"), "ordinal")
    chosen = named.withColumn("negative", F.when(F.col("_a") == F.col("target"), F.col("_b")).otherwise(F.col("_a")))
    view = F.transform("items", lambda x, k: F.when(k == F.col("pos"), F.col("negative")).otherwise(x))
    return chosen.select("client_id", "session_id", "pos", "target", "negative", view.alias("view"))


def mask_segment(sess: DataFrame, seed: str = "segment") -> DataFrame:
    """One view per session that has a neighbour session: a hashed span becomes the start of the client's next session.

    client_id, session_id, pos, len, target (array), negative (array), view. The
    next session is the following one, after the last the first; it must be long
    enough for the span.
    """
    order = Window.partitionBy("client_id").orderBy("session_id")
    first = F.first("items").over(Window.partitionBy("client_id").orderBy("session_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    long = sess.where(F.size("items") >= MIN_VIEW).withColumn("_other", F.coalesce(F.lead("items").over(order), first))
    low, high = SEGMENT
    length = (F.lit(low) + F.floor(uniform(seed + ":len", F.col("client_id"), F.col("session_id")) * (high - low + 1))).cast("int")
    spanned = long.withColumn("len", F.least(length, F.size("items") - 1)).where(F.size("_other") >= F.col("len"))
    pos = F.floor(uniform(seed + ":pos", F.col("client_id"), F.col("session_id")) * (F.size("items") - F.col("len") + 1)).cast("int")
    cut = spanned.withColumn("pos", pos).withColumn("target", F.slice("items", F.col("pos") + 1, F.col("len"))).withColumn("negative", F.slice("_other", F.lit(1), F.col("len")))
    view = F.concat(F.slice("items", F.lit(1), F.col("pos")), F.col("negative"), F.slice("items", F.col("pos") + F.col("len") + 1, F.size("items")))
    return cut.select("client_id", "session_id", "pos", "len", "target", "negative", view.alias("view"))


def negative_items(views: DataFrame, items: DataFrame, count: int = NEGATIVES, seed: str = "neg") -> DataFrame:
    """(client_id, session_id, j, item_id): hashed items for each view, none of them the target."""
    placed = item_ordinals(items)
    total = items.select("item_id").distinct().count()
    draws = views.select("client_id", "session_id", "target", F.explode(F.sequence(F.lit(0), F.lit(count - 1))).alias("j"))
    drawn = draws.withColumn("ordinal", drawn_item(total, seed, F.col("client_id"), F.col("session_id"), F.col("j")))
    return drawn.join(placed, "ordinal").where(F.col("item_id") != F.col("target")).select("client_id", "session_id", "j", "item_id")


def negative_segments(views: DataFrame, sess: DataFrame, count: int = 2) -> DataFrame:
    """(client_id, session_id, j, other_session, start_pos): the first ``count`` other sessions of the client, by session number, that are long enough."""
    others = sess.where(F.size("items") >= MIN_VIEW).select("client_id", F.struct("session_id", F.size("items").alias("n")).alias("o"))
    lists = others.groupBy("client_id").agg(F.sort_array(F.collect_list("o")).alias("_all"))
    joined = views.select("client_id", "session_id", "len").join(lists, "client_id")
    fit = joined.withColumn("_fit", F.slice(F.filter("_all", lambda o: (o["session_id"] != F.col("session_id")) & (o["n"] >= F.col("len"))), 1, count))
    return fit.select("client_id", "session_id", F.posexplode("_fit").alias("j", "o")).select("client_id", "session_id", "j", F.col("o.session_id").alias("other_session"), F.floor(uniform("start", F.col("client_id"), F.col("session_id"), F.col("j")) * (F.col("o.n") - 1)).cast("int").alias("start_pos"))
