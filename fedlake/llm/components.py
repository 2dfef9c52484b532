"""Connected components of an edge table, by alternating star contractions.

Every round is two aggregations and two joins over the current edges; the
edges stay distributed and are cut through the checkpoint folder, so nothing
but a count and a checksum reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.llm.runtime import cut


def _smallest(edges: DataFrame) -> DataFrame:
    """Per u the smallest of u and its neighbours."""
    return edges.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return both.join(_smallest(both), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    joined = down.join(_smallest(down), "u")
    return joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(joined.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def _sign(edges: DataFrame) -> tuple:
    # decimal sums: they can't overflow and don't depend on the order
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(u, v) links of any order to (u, root): root is the smallest id that u reaches; ids without links don't appear.

    Self links and repeated links are allowed; null ends are ignored. Raises if
    the contraction hasn't settled after ``max_rounds``; it halves chains, so
    sixty rounds pass any real graph.
    """
    links = edges.where("u is not null and v is not null and u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    links = cut(links.distinct())
    seen = _sign(links)
    for _ in range(max_rounds):
        if seen[0] == 0:
            break
        links = cut(_small_star(_large_star(links)))
        now = _sign(links)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    return links.select("u", F.col("v").alias("root")).unionAll(links.select(F.col("v").alias("u"), F.col("v").alias("root")).distinct())
