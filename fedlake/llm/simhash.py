"""SimHash near-duplicates through an inverted index over byte positions.

Two 64-bit fingerprints within ``radius`` bits agree in at least
``8 - radius`` of their eight byte positions. The positions form ``radius + 2``
groups, of which such a pair shares two or more whole. The index posts each
distinct fingerprint under every two groups with the bytes found there (six
postings at radius 2). Inside a posting list the positional bytes that each pair
shares are tallied over all eight positions; pairs that reach the guaranteed
number are retained and their bit distance is verified. Lists are counted first:
postings that meet no other go no further, and a list longer than ``DENSE_LIST``
is never gathered but posted again under every choice of ``8 - radius`` positions
that contains its own. Those lists are bounded (at most 65,536 distinct values
share six bytes) and hold only pairs with the guaranteed number, so the longest of
them enumerate the few bit changes that the open bytes allow. Every list yields a
spanning forest of its links, not all pairs, and the components follow from a
distributed star contraction.

Exact copies collapse to one fingerprint before the index, so a large group of
copies costs one posting.

Defined results: a null text has no words; no words give the zero fingerprint,
linked like any other; fewer words than a shingle form one shingle; repeated
rows share their component; a null doc_id keeps its row and is no candidate for
component_id unless its group has no other; clashing extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fedlake.llm.components import connected_components
from fedlake.llm.runtime import cut, fresh, slices, spread, utf8

LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
SEED = 42
#: Fingerprints of a list up to which all its pairs are tallied at once.
DENSE_LIST = 512
#: Shingle hashes whose bits are counted at a time.
BIT_ROWS = 1 << 16


def shingle_hashes(text: bytes, width: int) -> list[int]:
    """XXH64 of each space-joined shingle of the lower-cased words (ASCII letters only), repeats included."""
    words = text.translate(LOWER).split()  # bytes.split cuts at exactly \x20 and \x09-\x0D
    if not words:
        return []
    if len(words) < width:
        return [xxhash.xxh64_intdigest(b" ".join(words), SEED)]
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.r_[0, ends[:-1] + 1]
    digest = xxhash.xxh64_intdigest
    return [digest(joined[a:b], SEED) for a, b in zip(starts[: len(words) - width + 1].tolist(), ends[width - 1 :].tolist(), strict=True)]


def fingerprint(hashes: list[int]) -> int:
    """Bit k is set if it is set in over half the hashes."""
    if not hashes:
        return 0
    rows = np.array(hashes, ">u8").view(np.uint8).reshape(-1, 8)
    counts = np.zeros(64, np.int64)
    for k in range(0, len(rows), BIT_ROWS):
        counts += np.unpackbits(rows[k : k + BIT_ROWS], axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > len(rows)).tobytes(), "big")


def fingerprints(docs: DataFrame, width: int = 3) -> DataFrame:
    """(doc_id, fp): one pass, no shuffle; fp is the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text"):
            values = np.array([fingerprint(shingle_hashes(t, width)) for t in utf8(part, "text")], np.uint64)
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(values.view(np.int64))], ["doc_id", "fp"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, fp long")


def _position_groups(radius: int) -> list[tuple[int, ...]]:
    """The eight byte positions in ``radius + 2`` groups of about equal size: ``radius`` changed bytes leave two untouched."""
    return [tuple(int(p) for p in g) for g in np.array_split(np.arange(8), radius + 2)]


def _keys(choices: list[tuple[int, ...]]) -> Column:
    """One key per choice of positions: the choice as a bit set, and the bytes found there."""
    keys = []
    for positions in choices:
        mask = sum(255 << (8 * p) for p in positions)
        signed = mask - (1 << 64) if mask >= 1 << 63 else mask
        keys.append(F.struct(F.lit(sum(1 << p for p in positions)).alias("choice"), F.col("fp").bitwiseAND(F.lit(signed)).alias("bytes")))
    return F.array(*keys)


def _posting_lists(distinct: DataFrame, radius: int) -> DataFrame:
    """(fps) of at least two distinct fingerprints that share the bytes of a key; every pair within the radius is in some list."""
    short = [a + b for a, b in combinations(_position_groups(radius), 2)]
    postings = distinct.select("fp", F.explode(_keys(short)).alias("key")).select("key.choice", "key.bytes", "fp")
    counted = cut(postings.groupBy("choice", "bytes").agg(F.count("*").alias("n")).where("n > 1"))
    shared = postings.join(counted, ["choice", "bytes"])
    light = shared.where(F.col("n") <= DENSE_LIST).groupBy("choice", "bytes").agg(F.collect_list("fp").alias("fps")).select("fps")
    wide = list(combinations(range(8), 8 - radius))
    again = F.lit(None)
    for positions in short:
        bits = sum(1 << p for p in positions)
        again = F.when(F.col("choice") == bits, _keys([w for w in wide if set(positions) <= set(w)])).otherwise(again)
    reposted = shared.where(F.col("n") > DENSE_LIST).select("fp", F.explode(again).alias("key")).select("key.choice", "key.bytes", "fp").distinct()
    heavy = reposted.groupBy("choice", "bytes").agg(F.collect_list("fp").alias("fps")).where(F.size("fps") > 1).select("fps")
    return light.unionAll(heavy)


def list_links(values: np.ndarray, radius: int, shared: int) -> list[tuple[int, int]]:
    """A spanning forest of the pairs of one posting list within ``radius`` bits, as index pairs.

    Lists above ``DENSE_LIST`` must share ``shared`` bytes throughout.
    """
    n = len(values)
    root = list(range(n))

    def top(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    out: list[tuple[int, int]] = []

    def join(pairs) -> None:
        for a, b in pairs:
            x, y = top(a), top(b)
            if x != y:
                root[max(x, y)] = min(x, y)
                out.append((a, b))

    if n <= DENSE_LIST:
        tally = np.zeros((n, n), np.uint8)  # shared positional bytes of each pair
        for place in values.view(np.uint8).reshape(n, 8).T:
            tally += place[:, None] == place[None, :]
        a, b = np.nonzero(np.triu(tally >= shared, 1))
        near = np.bitwise_count(values[a] ^ values[b]) <= radius
        join(zip(a[near].tolist(), b[near].tolist(), strict=True))
        return out
    varying = int(np.bitwise_or.reduce(values ^ values[0]))
    bits = [1 << k for k in range(64) if varying >> k & 1]
    order = np.argsort(values)
    ranked = values[order]
    for size in range(1, radius + 1):
        for chosen in combinations(bits, size):
            turned = values ^ np.uint64(sum(chosen))
            at = np.minimum(np.searchsorted(ranked, turned), n - 1)
            hit = np.flatnonzero((ranked[at] == turned) & (values < turned))
            join(zip(hit.tolist(), order[at[hit]].tolist(), strict=True))
    return out


def fingerprint_links(distinct: DataFrame, radius: int = 2) -> DataFrame:
    """Links (u, v) between distinct fingerprints; their components are those of all pairs within the radius."""
    if not 0 <= radius <= 4:
        raise ValueError("the index covers a radius of 0 to 4 bits")
    lists = _posting_lists(distinct, radius)
    shared = 8 - radius

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column("fps")
            flat = np.asarray(column.flatten()).view(np.uint64)
            ends = np.cumsum(np.asarray(pc.list_value_length(column)))
            starts = np.r_[0, ends[:-1]]
            pairs = np.flatnonzero(ends - starts == 2)
            a, b = flat[starts[pairs]], flat[starts[pairs] + 1]
            apart = a ^ b
            tally = (apart.view(np.uint8).reshape(-1, 8) == 0).sum(axis=1)
            near = (tally >= shared) & (np.bitwise_count(apart) <= radius)
            left, right = [a[near]], [b[near]]
            for k in np.flatnonzero(ends - starts > 2).tolist():
                values = flat[starts[k] : ends[k]]
                found = list_links(np.ascontiguousarray(values), radius, shared)
                if found:
                    i, j = np.array(found).T
                    left.append(values[i])
                    right.append(values[j])
            u, v = np.concatenate(left), np.concatenate(right)
            yield pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(v.view(np.int64))], ["u", "v"])

    return lists.mapInArrow(run, "u long, v long")


def near_groups(docs: DataFrame, width: int = 3, radius: int = 2) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable)."""
    prints = cut(fingerprints(docs, width))
    distinct = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("first_doc")))
    reach = connected_components(fingerprint_links(spread(distinct.select("fp")), radius)).withColumnRenamed("u", "fp")
    placed = distinct.join(reach, "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), "first_doc")
    best = placed.groupBy("root").agg(F.min("first_doc").alias("component_id"))
    labelled = placed.join(best, "root").select("fp", "component_id")
    return prints.join(labelled, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_per_group(docs: DataFrame, width: int = 3, radius: int = 2) -> DataFrame:
    """The documents whose doc_id is their group's smallest; all columns stay.

    Of rows that repeat doc_id and text one stays; different texts of one doc_id
    stay while that id is some group's smallest. Rows without a doc_id can't be
    named as a group's first and stay.
    """
    groups = near_groups(docs.select("doc_id", "text"), width, radius)
    first = fresh("first", docs.columns)
    firsts = groups.where("doc_id = component_id").select(F.col("doc_id").alias(first)).distinct()
    named = docs.where("doc_id is not null").join(firsts, F.col("doc_id") == F.col(first), "left_semi").dropDuplicates(["doc_id", "text"])
    return named.unionByName(docs.where("doc_id is null"))
