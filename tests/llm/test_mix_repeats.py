"""The mix with rows that repeat, ids that are missing, and equal ids of different texts."""

import pytest

from fedlake.llm import mixing

SCHEMA = "doc_id long, text string, source string"


def rows_of(spark, kind):
    text = "ten words are in this text and these are ten"
    equal = [(None, text, "a")] * 100
    ids = {"null": equal, "same id": [(7, text, "a")] * 100, "different texts": [(7, f"{text[:-3]} {k}", "a") for k in range(100)], "some": equal[:50] + [(k, text, "a") for k in range(50)]}
    return spark.createDataFrame(ids[kind], SCHEMA).repartition(3)


@pytest.mark.parametrize("kind", ["null", "same id", "different texts", "some"])
def test_a_source_of_repeats_meets_its_target(spark, kind):
    docs = rows_of(spark, kind)
    got = mixing.mix_documents(docs).collect()
    assert len(got) == 100 and sum(r.taken for r in got) == 1500 and all(r.taken in (r.size, 2 * r.size) for r in got)
    assert mixing.apply_mix(docs).count() == 150


def test_twin_takes_as_many(spark, compare):
    import duckdb

    for kind in ("null", "some"):
        frame = rows_of(spark, kind)
        c = duckdb.connect()
        c.register("documents", frame.toPandas().astype({"doc_id": "Int64"}))
        compare(mixing.mix_documents(frame).drop("doc_id").toPandas(), c.execute(mixing.oracle_sql()).df().drop(columns="doc_id"))
