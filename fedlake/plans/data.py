"""From a universe to packed clients: slots of users and items, one row per client."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.operators import features, protocol
from fedlake.operators.sequences import item_ordinals
from fedlake.plans.ranking import ItemTable
from fedlake.sources.universes import Universe

#: Items whose slots the ranking kernel takes as one table; a longer catalogue must be ranked with ``scoring.ranks``, which goes in blocks.
MOST_ITEMS = 1 << 24
#: Parts of users a core.
DEALT = 4


@dataclass
class Prepared:
    """Slot tables and sizes of a universe. users: client_id, uf, us; items: item_no, item_id, f, s."""

    universe: Universe
    users: DataFrame
    items: DataFrame
    rows: DataFrame
    n_users_slots: int
    n_item_slots: int
    user_fields: int
    item_fields: int
    n_items: int
    #: The catalogue as the ranking kernel takes it, once it has been read.
    table: ItemTable | None = None
    #: The test users as the ranking kernel takes them, where several rankings read them.
    cases: DataFrame | None = None


def _fields(df: DataFrame, ident: str) -> tuple[str, ...]:
    return tuple(c for c in df.columns if c != ident)


def _packed_slots(long: DataFrame, vocab: DataFrame, ident: str, fields: tuple[str, ...]) -> DataFrame:
    number = F.element_at(F.create_map(*[x for k, f in enumerate(fields) for x in (F.lit(f), F.lit(k))]), F.col("field"))
    joined = long.join(vocab.select("field", "value", "slot"), ["field", "value"], "left").select(ident, number.alias("f"), F.coalesce("slot", F.lit(0)).alias("s"))
    packed = joined.groupBy(ident).agg(F.sort_array(F.collect_list(F.struct("f", "s"))).alias("p"))
    return packed.select(ident, F.transform("p", lambda x: x["f"]).alias("f"), F.transform("p", lambda x: x["s"]).alias("s"))


def prepare(universe: Universe, features_used: str = "all") -> Prepared:
    """Vocabularies from training users and the catalogue; ``features_used='ids'`` keeps item ids only (constant user side)."""
    user_fields, item_fields = _fields(universe.users, "client_id"), _fields(universe.items, "item_id")
    ordinals = item_ordinals(universe.items.select("item_id")).withColumnRenamed("ordinal", "item_no").cache()
    n_items = ordinals.count()
    user_long = features.long_fields(universe.users, "client_id", user_fields)
    user_vocab = features.vocabulary(user_long.where(protocol.user_split(F.col("client_id")) == "train"), "user").cache()
    item_long = features.long_fields(universe.items, "item_id", item_fields)
    item_vocab = features.vocabulary(item_long, "item").cache()
    n_user, n_item = user_vocab.count() + 1, item_vocab.count() + 1
    if features_used == "ids":
        users = universe.users.select("client_id", F.array(F.lit(0)).alias("uf"), F.array(F.lit(0)).alias("us"))
        items = ordinals.select("item_no", "item_id", F.array(F.lit(0)).alias("f"), F.array(F.col("item_no").cast("int") + 1).alias("s"))
        n_user, n_item, nu, nv = 1, 1, 1, 1
    else:
        users = _packed_slots(user_long, user_vocab, "client_id", user_fields).withColumnRenamed("f", "uf").withColumnRenamed("s", "us")
        side = _packed_slots(item_long, item_vocab, "item_id", item_fields)
        items = ordinals.join(side, "item_id").select("item_no", "item_id", F.concat("f", F.array(F.lit(len(item_fields)))).alias("f"), F.concat("s", F.array((F.col("item_no") + n_item).cast("int"))).alias("s"))
        nu, nv = len(user_fields), len(item_fields) + 1
    rows = universe.interactions.join(items.select("item_id", "item_no"), "item_id").select("client_id", "item_no", "label", "stars").cache()  # every round, sweep and ranking reads them
    return Prepared(universe, users, items.cache(), rows, n_user, n_item + n_items, nu, nv, n_items)


def pack(prep: Prepared, rows: DataFrame) -> DataFrame:
    """One row per client: client_id, uf, us, items (ordered array of item_no, f, s, y), n."""
    wide = rows.join(prep.items.select("item_no", "f", "s"), "item_no")
    packed = wide.groupBy("client_id").agg(F.sort_array(F.collect_list(F.struct("item_no", "f", "s", F.col("label").cast("double").alias("y")))).alias("items"))
    return packed.join(prep.users, "client_id").withColumn("n", F.size("items"))


def item_table(prep: Prepared) -> ItemTable:
    """The catalogue's slots for the ranking kernel."""
    if prep.n_items > MOST_ITEMS:
        raise ValueError(f"{prep.n_items} items are more than the kernel's table may hold")
    if prep.table is None:
        found = prep.items.select("item_no", "f", "s").toArrow().sort_by("item_no")
        prep.table = ItemTable.of(np.asarray(found.column("item_no")), found.column("f").combine_chunks(), found.column("s").combine_chunks())
    return prep.table


def dealt(users: DataFrame) -> DataFrame:
    """Users in several even parts a core: what a kernel does for one of them is long, and the engine would join small parts."""
    return users.repartition(DEALT * users.sparkSession.sparkContext.defaultParallelism, "client_id")


def ranking_users(prep: Prepared, test: DataFrame) -> DataFrame:
    """Test users for personalise-and-rank: the tuning half packed, all touched items, positives of the ranking half.

    test: client_id, item_no, label, row_split.
    """
    mine = F.when((F.col("row_split") == "rank") & (F.col("label") == 1), F.col("item_no"))
    cases = test.groupBy("client_id").agg(F.sort_array(F.collect_set("item_no")).alias("seen"), F.sort_array(F.collect_list(mine)).alias("positives")).where(F.size("positives") > 0)
    return cases.join(pack(prep, test.where("row_split = 'tune'")), "client_id")


def cases(prep: Prepared) -> DataFrame:
    """All test users for personalise-and-rank, dealt to the cores."""
    return prep.cases if prep.cases is not None else dealt(ranking_users(prep, splits(prep)[1]))


def keep_cases(prep: Prepared) -> Prepared:
    """Holds ``cases``: experiments that rank several times pack the test users once."""
    prep.cases = cases(prep).persist()
    return prep


def splits(prep: Prepared) -> tuple[DataFrame, DataFrame]:
    """(rows of training users, rows of test users with row_split)."""
    train = prep.rows.where(protocol.user_split(F.col("client_id")) == "train")
    test = protocol.split_rows(prep.rows.where(protocol.user_split(F.col("client_id")) == "test").withColumn("item_id", F.col("item_no"))).drop("item_id")
    return train, test
