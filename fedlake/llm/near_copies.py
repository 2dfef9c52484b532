"""Near copies by word shingles: sets of five-word shingles with a Jaccard similarity of 0.8 or more.

SimHash comes first: every text gets the fingerprint of its shingles, the index
over byte positions of ``simhash`` links those within two bits, and what is linked
is a list to verify. Similar pairs whose fingerprints are further apart, most at
0.8, are added by an index over the bands of a min-hash signature. In a list of
either kind a pair is first filtered by the count of equal signature values and
then verified on the exact shingle sets. At a similarity of 0.8 a pair shares no band with a probability of
about 3e-6 and falls under the count filter with one of about 1e-6; more similar
pairs less often. Only verified pairs become links, so no text goes for a wrong one.

Texts with equal shingle sets collapse before the index. A posting list of any
length is verified in parts of bounded size: first it is dealt by hash into
parts, each of which gives a spanning forest of its links. Lists whose members
are in different components after that are compared across parts, members of
their largest component only with all the others. No pair of one component is
compared, and no task holds a whole long list.

Defined results: a null text has no words; texts without words are copies of
each other; fewer words than a shingle form one shingle; rows without a doc_id
stay and link nothing; of different texts under one doc_id each stands for
itself; of rows that repeat doc_id and text one stays.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.llm.components import connected_components
from fedlake.llm.runtime import cut_free, fresh, slices, spread, utf8
from fedlake.llm.simhash import fingerprint, fingerprint_links, shingle_hashes

WIDTH = 5
SIMILARITY = 0.8
#: Bits in which linked fingerprints differ at most.
RADIUS = 2
BANDS = 32
ROWS = 5
#: Equal signature values that a pair must reach: the expected 128 less five standard deviations.
COUNT = 102
#: Shingles whose values are computed at a time.
BLOCK = 512
#: Members and shingles of one part of a posting list, about.
PART_MEMBERS = 256
PART_SHINGLES = 1 << 20
#: Tables of two numbers a row are broadcast up to this many rows; larger ones are joined by shuffle.
BROADCAST_ROWS = 500_000
_RANDOM = np.random.default_rng(20)
_TURN = _RANDOM.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32)
_FACTOR = _RANDOM.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32) | np.uint32(1)


def shingle_set(text: bytes) -> np.ndarray:
    """Hashes of the distinct shingles, ascending."""
    return _distinct(shingle_hashes(text, WIDTH))


def _distinct(hashes: list[int]) -> np.ndarray:
    return np.unique(np.array(hashes, np.uint64))


def signature(shingles: np.ndarray) -> np.ndarray:
    """Per hash function the smallest value of the set."""
    low = np.full(BANDS * ROWS, 0xFFFFFFFF, np.uint32)
    x = (shingles >> np.uint64(32)).astype(np.uint32)
    for k in range(0, len(x), BLOCK):
        np.minimum(low, ((x[k : k + BLOCK, None] ^ _TURN) * _FACTOR).min(axis=0), out=low)
    return low


def node(shingles: np.ndarray) -> int:
    """Names a shingle set."""
    return int(np.uint64(xxhash.xxh3_64_intdigest(shingles.tobytes())).astype(np.int64))


def band_keys(values: np.ndarray) -> list[int]:
    raw = values.tobytes()
    step = 4 * ROWS
    return [xxhash.xxh3_64_intdigest(raw[k * step : (k + 1) * step], k) for k in range(BANDS)]


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether two ascending sets reach the similarity."""
    if min(len(a), len(b)) < SIMILARITY * max(len(a), len(b)):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both >= SIMILARITY * (len(a) + len(b) - both) - 1e-9


def list_links(sets: list[np.ndarray], signatures: np.ndarray, group: np.ndarray | None = None) -> list[tuple[int, int]]:
    """A spanning forest of the similar pairs, as index pairs; members that ``group`` has together already aren't compared."""
    group = np.arange(len(sets)) if group is None else group.copy()
    out = []
    for i in range(1, len(sets)):
        likely = ((signatures[:i] == signatures[i]).sum(axis=1) >= COUNT) & (group[:i] != group[i])
        for j in np.flatnonzero(likely).tolist():
            if group[j] != group[i] and similar(sets[j], sets[i]):
                group[group == group[i]] = group[j]
                out.append((j, i))
    return out


def _text(docs: DataFrame) -> DataFrame:
    text = F.col("text").cast("string")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), _text_key(docs).alias("text_key"))


def _text_key(docs: DataFrame):
    return F.xxhash64(F.coalesce(docs["text"].cast("string"), F.lit("")))


def _prints(docs: DataFrame) -> DataFrame:
    """(doc_id, text_key, node, fp, size, keys) of each row; fp is the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text"):
            names, fps, sizes, keys = [], [], [], []
            for text in utf8(part, "text"):
                hashes = shingle_hashes(text, WIDTH)
                s = _distinct(hashes)
                names.append(node(s))
                fps.append(fingerprint(hashes))
                sizes.append(len(s))
                keys += band_keys(signature(s))
            ends = np.arange(len(names) + 1, dtype=np.int32) * BANDS
            held = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.array(keys, np.uint64).view(np.int64)))
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_key"), pa.array(names, pa.int64()), pa.array(np.array(fps, np.uint64).view(np.int64)), pa.array(sizes, pa.int64()), held], ["doc_id", "text_key", "node", "fp", "size", "keys"])

    return _text(docs).mapInArrow(run, "doc_id long, text_key long, node long, fp long, size long, keys array<long>")


def _fingerprint_posts(prints: DataFrame) -> DataFrame:
    """(key, node, size): every shingle set under the group of linked fingerprints of its texts."""
    held = cut_free(prints.groupBy("node", "fp").agg(F.first("size").alias("size")))
    reach = connected_components(fingerprint_links(spread(held.select("fp").distinct()), RADIUS)).withColumnRenamed("u", "fp")
    grouped = held.join(reach, "fp", "left").select(F.xxhash64(F.lit("fingerprints"), F.coalesce("root", "fp")).alias("key"), "node", "size")
    return grouped.distinct()


def _sets(docs: DataFrame) -> DataFrame:
    """(node, shingles, signature) of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text"):
            sets = [shingle_set(t) for t in utf8(part, "text")]
            columns = [pa.array([node(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary()), pa.array([signature(s).tobytes() for s in sets], pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, ["node", "shingles", "signature"])

    return docs.select("text").mapInArrow(run, "node long, shingles binary, signature binary")


def _verified(lists: DataFrame) -> DataFrame:
    """Links (u, v) of the parts: rows with ``members``, an array of (node, group, shingles, signature)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for members in batch.column("members"):
                rows = members.as_py()
                sets = [np.frombuffer(r["shingles"], np.uint64) for r in rows]
                values = np.array([np.frombuffer(r["signature"], np.uint32) for r in rows])
                found = list_links(sets, values, np.array([r["group"] for r in rows], np.int64))
                u, v = [rows[i]["node"] for i, _ in found], [rows[j]["node"] for _, j in found]
                yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])

    return lists.mapInArrow(run, "u long, v long")


def _sized(table: DataFrame) -> DataFrame:
    """A materialised table, marked for broadcast where its count bounds its size."""
    return F.broadcast(table) if table.count() <= BROADCAST_ROWS else table


def _parts(members, shingles):
    """How many parts keep members and shingles of a part within bounds."""
    return F.greatest(F.ceil(members / F.lit(PART_MEMBERS)), F.ceil(shingles / F.lit(PART_SHINGLES)), F.lit(1)).cast("int")


def _gathered(rows: DataFrame, sets: DataFrame, keys: list[str]) -> DataFrame:
    return rows.join(sets, "node").groupBy(*keys).agg(F.collect_list(F.struct("node", "group", "shingles", "signature")).alias("members")).select("members")


def _across(met: DataFrame, reach: DataFrame, sets: DataFrame) -> DataFrame:
    """Parts that compare the members of long lists across components. met: key, node, size, parts; reach: node, root."""
    hot = met.where("parts > 1").join(reach, "node", "left").withColumn("group", F.coalesce("root", "node")).drop("root")
    each = hot.groupBy("key", "group").agg(F.count("*").alias("n"), F.sum("size").alias("s"))
    whole = each.groupBy("key").agg(F.max(F.struct("n", "group", "s")).alias("top"), F.sum("n").alias("n"), F.sum("s").alias("s"), F.count("*").alias("groups")).where("groups > 1")
    dealt = whole.select("key", F.col("top.group").alias("main"), _parts(F.col("top.n"), F.col("top.s")).alias("mains"), _parts(F.col("n") - F.col("top.n"), F.col("s") - F.col("top.s")).alias("others"))
    rows = hot.join(dealt, "key").withColumn("inside", F.col("group") == F.col("main"))
    rows = rows.withColumn("own", F.pmod(F.xxhash64("node", "key"), F.when(F.col("inside"), F.col("mains")).otherwise(F.col("others"))).cast("int"))
    upto = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    place = lambda a, b, mixed: F.struct(a.alias("a"), b.alias("b"), F.lit(mixed).alias("mixed"))
    with_main = F.transform(upto("mains"), lambda j: place(F.col("own"), j, True))
    with_others = F.transform(upto("others"), lambda i: place(F.least(i, F.col("own")), F.greatest(i, F.col("own")), False))
    places = F.when(F.col("inside"), F.transform(upto("others"), lambda i: place(i, F.col("own"), True))).otherwise(F.concat(with_main, with_others))
    return _gathered(rows.select("key", "node", "group", F.explode(places).alias("at")), sets, ["key", "at"])


def near_groups(docs: DataFrame) -> DataFrame:
    """(doc_id, text_key, component_id, first) of the rows with a doc_id.

    component_id is the smallest doc_id of the group; ``first`` holds it with the
    text_key that stands for the group.
    """
    docs = docs.where("doc_id is not null")
    prints = cut_free(_prints(docs))
    distinct = cut_free(prints.groupBy("node").agg(F.min(F.struct("doc_id", "text_key")).alias("first"), F.first("size").alias("size"), F.first("keys").alias("keys")))
    posts = spread(distinct.select("node", "size", "keys")).select(F.explode("keys").alias("key"), "node", "size").unionByName(_fingerprint_posts(prints)).repartition("key")  # counted and joined where it lies
    counts = posts.groupBy("key").agg(F.count("*").alias("n"), F.sum("size").alias("s")).where("n > 1")
    met = cut_free(posts.join(counts.select("key", _parts(F.col("n"), F.col("s")).alias("parts")), "key"))
    dealt = met.groupBy("key", F.pmod(F.xxhash64("node", "key"), F.col("parts")).alias("part")).agg(F.sort_array(F.collect_set("node")).alias("nodes"))
    lists = cut_free(dealt.where(F.size("nodes") > 1).select("nodes").distinct().select(F.xxhash64("nodes").alias("list"), F.explode("nodes").alias("node")).withColumn("group", F.col("node")))
    wanted = cut_free(met.select("node").distinct().join(distinct.select("node", "first"), "node").select(F.col("first.doc_id").alias("w_doc"), F.col("first.text_key").alias("w_text")))
    chosen = _text(docs)
    sets = cut_free(_sets(chosen.join(_sized(wanted), (F.col("doc_id") == F.col("w_doc")) & (F.col("text_key") == F.col("w_text")), "left_semi")).dropDuplicates(["node"]))
    links = cut_free(_verified(_gathered(lists, sets, ["list"])))
    reach = connected_components(links).select(F.col("u").alias("node"), "root")
    more = cut_free(_verified(_across(met, reach, sets)))
    if more.limit(1).count():
        reach = connected_components(links.unionAll(more)).select(F.col("u").alias("node"), "root")
    placed = distinct.join(reach, "node", "left").select("node", F.coalesce("root", "node").alias("root"), "first")
    best = placed.groupBy("root").agg(F.min("first").alias("first"))
    labelled = placed.select("node", "root").join(best, "root").select("node", "first")
    return prints.select("doc_id", "text_key", "node").join(labelled, "node").select("doc_id", "text_key", F.col("first.doc_id").alias("component_id"), "first")


def one_per_group(docs: DataFrame) -> DataFrame:
    """The documents that stand for their groups, and those without a doc_id; all columns stay.

    Only pairs of numbers are joined with the documents: the rows to drop, and
    the kept rows that repeat as a whole, of which one stays.
    """
    doc, key = (fresh(n, docs.columns) for n in ("doc", "key"))
    mine = F.struct("doc_id", "text_key") == F.col("first")
    rows = near_groups(docs.select("doc_id", "text")).groupBy(F.col("doc_id").alias(doc), F.col("text_key").alias(key)).agg(F.max(mine).alias("kept"), F.count("*").alias("n"))
    rows = cut_free(rows.where("not kept or n > 1"))
    same = (docs["doc_id"].cast("long") == F.col(doc)) & (_text_key(docs) == F.col(key))
    once = docs.join(_sized(rows.select(doc, key)), same, "left_anti")
    again = rows.where("kept").select(doc, key)
    if not again.limit(1).count():
        return once
    keyed = docs.join(_sized(again), same).dropDuplicates([doc, key]).drop(doc, key)
    return once.unionByName(keyed)
