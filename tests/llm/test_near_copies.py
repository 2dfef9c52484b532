"""The corpus' near copies: five-word shingles, similarity 0.8, whatever the distance of three-word fingerprints."""

import time

import numpy as np

import corpus_pipeline
from fedlake.llm import near_copies, simhash


def _texts():
    """Groups of texts in which some words differ, and texts of their own."""
    r = np.random.default_rng(3)
    texts = []
    for k in range(30):
        words = [f"w{x}" for x in r.integers(0, 5000, 200)]
        texts.append(" ".join(words))
        for _ in range(k % 3):
            other = list(words)
            for at in r.integers(0, 200, k % 6):
                other[at] = f"x{r.integers(1 << 30)}"
            texts.append(" ".join(other))
    return [*texts, "", None, "one two", "One two"]


def test_stage_drops_what_brute_force_links(spark):
    texts = _texts()
    sets = [near_copies.shingle_set((t or "").encode()) for t in texts]
    group = list(range(len(texts)))
    beyond = 0
    for i in range(len(texts)):
        for j in range(i):
            a, b = set(sets[i].tolist()), set(sets[j].tolist())
            if a == b or len(a & b) >= 0.8 * len(a | b):
                group = [min(group[i], group[j]) if g in (group[i], group[j]) else g for g in group]
                prints = [simhash.fingerprint(simhash.shingle_hashes((texts[k] or "").encode(), 3)) for k in (i, j)]
                beyond += (prints[0] ^ prints[1]).bit_count() > 2
    assert beyond > 5  # what two bits of three-word fingerprints would leave
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    kept = corpus_pipeline.drop_near_copies(spark, docs, "")
    assert sorted(r.doc_id for r in kept.collect()) == sorted(set(group))


def test_joined_pairs_are_exact():
    a = np.arange(100, dtype=np.uint64)
    assert near_copies.similar(a, a[:80]) and not near_copies.similar(a, a[:79])


def test_long_lists_are_compared_across_parts(spark, monkeypatch):
    r = np.random.default_rng(8)
    base = [f"w{k}" for k in range(120)]
    texts = []
    for k in range(60):  # one family of very different closeness: links, and pairs that share lists without one
        words = list(base)
        for at in r.integers(0, 120, int(r.integers(0, 9))):
            words[at] = f"x{r.integers(1 << 30)}"
        texts.append(" ".join(words))
    sets = [set(near_copies.shingle_set(t.encode()).tolist()) for t in texts]
    group = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if group[i] != group[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                low, high = sorted((group[i], group[j]))
                group = [low if g == high else g for g in group]
    assert 1 < len(set(group)) < 50
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    for members in (3, 7, 256):
        monkeypatch.setattr(near_copies, "PART_MEMBERS", members)
        assert {x.doc_id: x.component_id for x in near_copies.near_groups(docs).collect()} == dict(enumerate(group))


def test_texts_of_one_id_stand_for_themselves(spark):
    rows = [(1, "alpha beta gamma", "u"), (1, "other words here", "u"), (1, "alpha beta gamma", "u"), (2, "alpha beta gamma", "v"), (None, "alpha beta gamma", "w"), (None, None, "w"), (3, None, "z"), (4, "", "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, first string")
    kept = near_copies.one_per_group(docs)
    assert kept.columns == docs.columns
    got = sorted(((r.doc_id, r.text) for r in kept.collect()), key=str)
    assert got == sorted([(1, "alpha beta gamma"), (1, "other words here"), (None, "alpha beta gamma"), (None, None), (3, None)], key=str)
    assert near_copies.one_per_group(docs.limit(0)).count() == 0


def test_linked_fingerprints_meet(spark):
    r = np.random.default_rng(11)
    texts = []
    for _ in range(12):
        words = [f"w{x}" for x in r.integers(0, 9000, 900)]
        for k in range(4):
            texts.append(" ".join([*words, *[f"x{x}" for x in r.integers(0, 1 << 30, k)]]))
    prints = [simhash.fingerprint(simhash.shingle_hashes(t.encode(), near_copies.WIDTH)) for t in texts]
    near = [(i, j) for i in range(len(texts)) for j in range(i) if (prints[i] ^ prints[j]).bit_count() <= 2]
    assert len(near) > 10
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    keys = {x.node: x.key for x in near_copies._fingerprint_posts(near_copies._prints(docs)).collect()}
    node = [near_copies.node(near_copies.shingle_set(t.encode())) for t in texts]
    assert all(keys[node[i]] == keys[node[j]] for i, j in near)
    assert len(set(keys.values())) < len(set(node))


def test_shuffle_files_go_while_the_stage_runs(spark):
    """What a materialised table was made from is freed at once, not when the driver happens to collect its garbage."""
    disk = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()

    def held() -> set:
        files = disk.getAllFiles()
        return {n for n in (files.apply(k).getName() for k in range(files.size())) if n.startswith("shuffle_")}

    before = held()
    docs = spark.createDataFrame(list(enumerate(_texts())), "doc_id long, text string").repartition(4)
    groups = near_copies.near_groups(docs)
    for _ in range(50):
        if len(held() - before) < 60:
            break
        time.sleep(0.2)
    assert len(held() - before) < 60
    assert groups.count() == len(_texts())
