"""Queries with SQL twins, and every pipeline stage on its own input."""

from __future__ import annotations

import pytest

from fedlake.llm import language_id, mixing, near_copies, quality_classifier
from fedlake.llm import queries as Q


@pytest.mark.parametrize("name", sorted(Q.oracle_sql()))
def test_twin(name, spark, folder, duck, compare):
    compare(Q.queries()[name](spark, folder).toPandas(), duck.execute(Q.oracle_sql()[name]).df())


def first_of_each_group(texts):
    """Smallest ids of the groups that links of exact five-word Jaccard similarity 0.8 or more form, by all pairs."""
    sets = {k: set(near_copies.shingle_set((t or "").encode()).tolist()) for k, t in texts.items()}
    group = {k: k for k in texts}
    for a in sets:
        for b in sets:
            if a < b and group[a] != group[b] and (sets[a] == sets[b] or len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])):
                low, high = sorted((group[a], group[b]))
                group = {k: low if g == high else g for k, g in group.items()}
    return set(group.values())


def test_stages(spark, folder, tmp_path):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{folder}/documents.parquet")
    columns = docs.columns
    for n, (name, stage) in enumerate(P.STAGES):
        out = stage(spark, docs, folder)
        if n < len(P.STAGES) - 1:
            assert out.columns == columns
        out.write.parquet(f"file:{tmp_path}/{name}")
        before, docs = docs, spark.read.parquet(f"file:{tmp_path}/{name}")
        if name == "quality_classifier":
            model = quality_classifier.fit(before, spark.read.parquet(f"{folder}/labels.parquet"))
            kept = {r.doc_id for r in quality_classifier.score(before, model).where("kept").collect()}
            assert {r.doc_id for r in docs.collect()} == kept
        elif name == "language_id":
            model = language_id.fit(before.where(~language_id.held_out(before.doc_id)), Q.vocabulary().pieces)
            kept = {r.doc_id for r in language_id.predict(before, model).where("lang_pred <> 'und' and score >= 0.5").collect()}
            assert {r.doc_id for r in docs.collect()} == kept
        elif name == "simhash_near_dedup":
            assert sorted(r.doc_id for r in docs.collect()) == sorted(first_of_each_group({r.doc_id: r.text for r in before.collect()}))
        elif name == "source_mix":
            assert abs(docs.count() - before.count()) < before.count()
            taken = sum(r.taken for r in mixing.mix_documents(before).collect())
            assert taken == docs.select(mixing.word_count(docs.text).alias("n")).groupBy().sum("n").first()[0]
        else:
            assert docs.count() == before.count() and docs.where("n_tokens < 2").count() == 0


def test_pipeline_runs(spark, folder):
    import corpus_pipeline as P

    assert P.run(spark, folder).count() > 0
