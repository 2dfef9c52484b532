"""Popularity and random rankers: the floor of the leaderboard."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.operators import scoring
from fedlake.plans import data as D


def _rank(prep: D.Prepared, score) -> DataFrame:
    test = D.splits(prep)[1].select("client_id", F.col("item_no").alias("item_id"), "label", "row_split")
    return scoring.ranks(scoring.test_cases(test), prep.items.select(F.col("item_no").alias("item_id")), score)


def popular(prep: D.Prepared) -> DataFrame:
    counts = D.splits(prep)[0].groupBy("item_no").agg(F.count("*").alias("n")).toArrow()
    table = np.zeros(prep.n_items)
    table[np.asarray(counts.column("item_no"))] = np.asarray(counts.column("n"))
    return _rank(prep, lambda client, items: table[items])


def random(prep: D.Prepared) -> DataFrame:
    return _rank(prep, scoring.fixed_score)
