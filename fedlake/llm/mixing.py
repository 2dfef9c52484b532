"""Mixing sources to target weights with hash-threshold histograms (DataFrame functions only).

Every document has a 48-bit hash of its id and text. A source that is to take ``t`` of
its ``s`` words takes all documents ``floor(t / s)`` times and, for the rest
of the budget, once more those whose hash lies at or below a threshold. The
threshold is found without sorting: tokens are summed by source and the first
twelve hash bits, the bucket in which the running sum crosses the budget is the
boundary, and only the documents of that bucket are summed by the next twelve
bits, until all 48 bits are fixed. The last cell holds documents of one hash, that
is one document or equal ones. Only where equal ones meet in it, their order of
place in the table is refined in the same way until one is left; that one is
taken if it brings the sum nearer to the budget.

Histograms have at most 4,096 rows a source and level, whatever the input, and
are summed before the shuffle, so a source with a third of all rows costs no
more than others.

Defined results: a null text has size 0; null is a source of its own and comes
last; a source without words takes nothing; documents of size 0 take 0;
rows that repeat as a whole are taken by number, so that as many as the target
needs count once more; an empty table gives an empty result; extra columns with
clashing names are ignored by ``mix_documents`` and kept by ``apply_mix``, whose
input must give its rows in the same order when it is read again.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.llm.runtime import cut

LEVELS = 4
BITS = 12
WORD = r"[^\x20\x09-\x0D]+"
#: Weights by the order of the sources' names, repeating.
WEIGHTS = (5, 2, 1)
SHARE = 1.5
REPEATS = 2.0


def word_count(text: Column) -> Column:
    """Number of words of ``text``, which holds no separators of other kinds; null counts 0."""
    marks = F.translate(F.coalesce(text.cast("string"), F.lit("")), "\t\n\x0b\x0c\r", "     ")
    return F.size(F.filter(F.split(marks, " "), lambda w: w != "")).cast("long")


def source_key(source: Column) -> Column:
    """A non-null key that sorts by code point, null last."""
    return F.when(source.isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), source.cast("string")))


def row_hash(doc_id: Column, text: Column) -> Column:
    """48 bits of the MD5 of id and text, equal in any engine; nulls hash as empty texts."""
    plain = lambda c: F.coalesce(c.cast("string"), F.lit(""))
    both = F.concat(plain(doc_id), F.lit(":"), F.md5(plain(text).cast("binary")))
    return F.conv(F.substring(F.md5(both.cast("binary")), 1, 12), 16, 10).cast("long")


def row_place() -> Column:
    """48 bits that tell rows of one scan apart."""
    return F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(1 << LEVELS * BITS))


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, repeats: float = REPEATS) -> DataFrame:
    """(source_key, source_size) to that plus ``target``.

    Sources share ``share`` times all words by weight, none above ``repeats``
    times its own; the excess goes to the others by weight. The fixed point is a
    water level: sources in order of ``cap / weight`` are capped while the level
    of the rest lies above them.
    """
    by_name = Window.orderBy("source_key")
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    weighted = sizes.withColumn("weight", F.element_at(cycle, (F.row_number().over(by_name) - 1) % len(weights) + 1)).withColumn("cap", F.col("source_size") * F.lit(float(repeats)))
    weighted = weighted.withColumn("ratio", F.col("cap") / F.col("weight"))
    by_ratio = Window.orderBy("ratio", "source_key")
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    budget = F.sum("source_size").over(whole) * F.lit(float(share))
    level = (budget - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    levelled = weighted.withColumn("level", level)
    # the first source that the level of the remaining ones doesn't reach fixes it for all
    marked = levelled.withColumn("open", F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", "source_key", "level")))
    final = F.min("open").over(whole)["level"]
    return marked.withColumn("final", final).select("source_key", "source_size", F.when(F.col("final").isNull(), F.col("cap")).otherwise(F.least("cap", F.col("weight") * F.col("final"))).alias("target"))


def _refine(rows: DataFrame, by: str, level: int) -> DataFrame:
    """One more twelve-bit digit of the boundary of every source; rows: source_key, ``by``, size, need.

    ``need`` is what is still to be taken inside the rows' cell.
    """
    shift = BITS * (LEVELS - 1 - level)
    cells = rows.groupBy("source_key", "need", F.shiftright(by, shift).alias("cell")).agg(F.sum("size").alias("held"), F.sum(F.col("size").cast("boolean").cast("long")).alias("n"))
    running = Window.partitionBy("source_key").orderBy("cell")
    summed = cells.withColumn("upto", F.sum("held").over(running))
    crossing = summed.where((F.col("upto") >= F.col("need")) & (F.col("held") > 0))
    first = crossing.groupBy("source_key").agg(F.min(F.struct("cell", "held", "upto", "need", "n")).alias("c"))
    return first.select("source_key", F.col("c.cell").alias("prefix"), (F.col("c.need") - (F.col("c.upto") - F.col("c.held"))).alias("need"), F.col("c.held").alias("held"), F.col("c.n").alias("n"))


#: Plans up to this many sources (one short row each) are broadcast; larger ones are joined by shuffle.
BROADCAST_SOURCES = 100_000


def _sized(plan: DataFrame, sizes: DataFrame) -> DataFrame:
    """The plan, marked for broadcast where the counted sources bound its size."""
    return F.broadcast(plan) if sizes.count() <= BROADCAST_SOURCES else plan


def _boundary(rows: DataFrame, edge: DataFrame, by: str, small: bool) -> DataFrame:
    """The cell of all bits of ``by`` in which the running sum reaches ``need``. edge: source_key, need."""
    edge = edge.withColumn("prefix", F.lit(0).cast("long"))
    for level in range(LEVELS):
        above = BITS * (LEVELS - level)
        inside = rows.join(F.broadcast(edge) if small else edge, "source_key").where(F.shiftright(by, above) == F.col("prefix")).select("source_key", "need", "size", by)
        edge = _refine(inside, by, level)
        edge = edge if level == LEVELS - 1 else edge.select("source_key", "need", "prefix")
    return edge


def _upto(by: str) -> Column:
    """The first value that isn't taken: the boundary cell counts if that is nearer to the need."""
    return F.when(F.col("held") - F.col("need") <= F.col("need"), F.col(by) + 1).otherwise(F.col(by))


def thresholds(docs: DataFrame, targets: DataFrame, sizes: DataFrame) -> DataFrame:
    """(source_key, copies, bound, place_bound): take ``copies`` of all, one more where (hash, place) < (bound, place_bound).

    docs: source_key, hash, place, size; sizes: one row per source.
    """
    small = sizes.count() <= BROADCAST_SOURCES
    copies = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    plan = targets.withColumn("copies", copies).withColumn("need", F.col("target") - F.col("copies") * F.col("source_size"))
    edge = cut(_boundary(docs, plan.where("need > 0").select("source_key", "need"), "hash", small).withColumnRenamed("prefix", "hash"))
    ends = edge.select("source_key", F.when(F.col("n") > 1, F.col("hash")).otherwise(_upto("hash")).alias("bound"), F.lit(0).cast("long").alias("place_bound"))
    tied = edge.where("n > 1").select("source_key", F.col("hash").alias("tied"), "need")
    if tied.limit(1).count():  # equal documents at a boundary
        equal = docs.join(F.broadcast(tied.select("source_key", "tied")) if small else tied.select("source_key", "tied"), "source_key").where("hash = tied")
        last = _boundary(equal.select("source_key", "place", "size"), tied.select("source_key", "need"), "place", small)
        found = last.select("source_key", _upto("prefix").alias("found"))
        ends = ends.drop("place_bound").join(found, "source_key", "left").select("source_key", "bound", F.coalesce("found", F.lit(0).cast("long")).alias("place_bound"))
    none = F.lit(0).cast("long")
    return plan.join(ends, "source_key", "left").select("source_key", "source_size", "target", "copies", F.coalesce("bound", none).alias("bound"), F.coalesce("place_bound", none).alias("place_bound"))


def _extra() -> Column:
    """1 for rows before the boundary."""
    before = (F.col("hash") < F.col("bound")) | ((F.col("hash") == F.col("bound")) & (F.col("place") < F.col("place_bound")))
    return F.when(before, F.lit(1)).otherwise(F.lit(0))


def mix_documents(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, repeats: float = REPEATS) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, taken (words taken, repeats counted)."""
    rows = cut(  # a few numbers a document; the texts are read once, not at every level
        docs.select(
            F.col("doc_id").cast("long").alias("doc_id"),
            source_key(F.col("source")).alias("source_key"),
            word_count(F.col("text")).alias("size"),
            row_hash(F.col("doc_id"), F.col("text")).alias("hash"),
            row_place().alias("place"),
        )
    )
    sizes = cut(rows.groupBy("source_key").agg(F.sum("size").alias("source_size")))
    plan = thresholds(rows.select("source_key", "hash", "place", "size"), source_targets(sizes, weights, share, repeats), sizes)
    return rows.join(_sized(plan, sizes), "source_key").select("doc_id", "size", "source_size", "target", (F.col("size") * (F.col("copies") + _extra())).cast("long").alias("taken"))


def apply_mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, repeats: float = REPEATS, copies_column: str | None = None) -> DataFrame:
    """The mixed corpus: every document as often as the mix takes it, all columns kept.

    ``copies_column`` keeps one row a document and adds the number of copies.
    Documents without words carry no tokens; they stay as often as their
    source is taken whole.
    """
    key, hashed, place = source_key(F.col("source")).alias("source_key"), row_hash(F.col("doc_id"), F.col("text")).alias("hash"), row_place().alias("place")
    sized = cut(docs.select(key, hashed, place, word_count(F.col("text")).alias("size")))
    sizes = cut(sized.groupBy("source_key").agg(F.sum("size").alias("source_size")))
    plan = thresholds(sized, source_targets(sizes, weights, share, repeats), sizes)
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), key, hashed, place)
    count = (F.col("copies") + _extra()).cast("int")
    counted = keyed.join(_sized(plan.select("source_key", "copies", "bound", "place_bound"), sizes), "source_key").select("row", count.alias("count"))
    if copies_column:
        return counted.where("count > 0").select("row.*", F.col("count").alias(copies_column))
    return counted.where("count > 0").select("row", F.explode(F.sequence(F.lit(1), F.col("count")))).select("row.*")


def oracle_sql(weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, repeats: float = REPEATS) -> str:
    """The same mix in SQL, by sorting: running sums over the documents of each source in order of hash."""
    n = len(weights)
    cycle = "CASE (k - 1) % " + str(n) + "".join(f" WHEN {i} THEN {float(w)}::DOUBLE" for i, w in enumerate(weights)) + " END"
    return f"""
WITH d AS (
  SELECT doc_id, CASE WHEN source IS NULL THEN '1' ELSE '0' || source END AS sk,
         len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '') || ':' || md5(coalesce(text, ''))), 1, 12))::BIGINT AS h
  FROM documents),
n AS (SELECT *, row_number() OVER (PARTITION BY sk, h) AS place FROM d),
s AS (SELECT sk, sum(size)::DOUBLE AS ss FROM d GROUP BY sk),
w AS (SELECT sk, ss, {cycle} AS wt FROM (SELECT *, row_number() OVER (ORDER BY sk) AS k FROM s)),
lv AS (
  SELECT sk, ss, wt, ss * {float(repeats)} AS cap, ss * {float(repeats)} / wt AS ratio,
         (sum(ss) OVER () * {float(share)} - coalesce(sum(ss * {float(repeats)}) OVER p, 0)) / (sum(wt) OVER () - coalesce(sum(wt) OVER p, 0)) AS lvl
  FROM w WINDOW p AS (ORDER BY ss * {float(repeats)} / wt, sk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
f AS (SELECT lvl AS final FROM lv WHERE lvl <= ratio ORDER BY ratio, sk LIMIT 1),
t AS (SELECT sk, ss, CASE WHEN (SELECT final FROM f) IS NULL THEN cap ELSE least(cap, wt * (SELECT final FROM f)) END AS target FROM lv),
p AS (SELECT *, CASE WHEN ss > 0 THEN floor(target / ss) ELSE 0 END AS copies FROM t),
q AS (SELECT *, target - copies * ss AS need FROM p),
c AS (SELECT sk, h, place, size AS held, sum(size::DOUBLE) OVER (PARTITION BY sk ORDER BY h, place) AS upto FROM n),
e AS (SELECT c.sk, min((c.h, c.place)) AS edge FROM c JOIN q USING (sk) WHERE q.need > 0 AND c.upto >= q.need AND c.held > 0 GROUP BY c.sk),
b AS (SELECT e.sk, c.h AS bound, CASE WHEN c.upto - q.need <= q.need - (c.upto - c.held) THEN c.place + 1 ELSE c.place END AS place_bound
      FROM e JOIN c ON c.sk = e.sk AND (c.h, c.place) = e.edge JOIN q ON q.sk = e.sk)
SELECT n.doc_id, n.size, q.ss::BIGINT AS source_size, q.target,
       (n.size * (q.copies + CASE WHEN n.h < b.bound OR (n.h = b.bound AND n.place < b.place_bound) THEN 1 ELSE 0 END))::BIGINT AS taken
FROM n JOIN q USING (sk) LEFT JOIN b USING (sk)"""
