"""Python functions and recursion as queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from fedlake.functions import udfs
from fedlake.operators.local_models import FIXED_WEIGHTS
from fedlake.queries.privacy import V_SQL, vectors
from fedlake.queries.registry import query
from fedlake.queries.sequences import SESSION_SQL, event_sessions
from fedlake.queries.training import X_SQL, _fixed, _p, rows
from fedlake.sources.tables import load


@query("udf_scores", f"WITH {X_SQL} SELECT client_id, item_id, round({_p(_fixed)}, 6) AS p FROM x")
def udf_scores(spark, d):
    return rows(spark, d).select("client_id", "item_id", F.round(udfs.score_udf(FIXED_WEIGHTS)("x1", "x2"), 6).alias("p"))


@query("udaf_vector_mean", f"WITH {V_SQL}, x AS (SELECT label, unnest(range(len(e)))::INTEGER AS pos, unnest(e) AS v FROM v) SELECT label, pos, round(avg(v), 6) + 0.0 AS value FROM x GROUP BY 1, 2")
def udaf_vector_mean(spark, d):
    means = vectors(spark, d).groupBy("label").agg(udfs.vector_mean_udf()("vec").alias("m"))
    return means.select("label", F.posexplode("m").alias("pos", "value")).select("label", "pos", (F.round("value", 6) + 0.0).alias("value"))


@query("udtf_session_items", f"WITH {SESSION_SQL} SELECT client_id, session_id, pos, item_id FROM s3")
def udtf_session_items(spark, d):
    udfs.register(spark)
    event_sessions(spark, d).createOrReplaceTempView("udtf_sessions")
    return spark.sql("SELECT client_id, session_id, t.pos, t.item_id FROM udtf_sessions, LATERAL session_items(items) t")


@query("recursive_steps", "WITH RECURSIVE t AS (SELECT avg(l_quantity) AS goal FROM lineitem), s(k, w, goal) AS (SELECT 0, 0.0::DOUBLE, goal FROM t UNION ALL SELECT k + 1, w - 0.1::DOUBLE * (w - goal), goal FROM s WHERE k < 20) SELECT k, round(w, 6) AS w FROM s")
def recursive_steps(spark, d):
    """Gradient steps on the squared distance to the mean quantity, one per level of a recursive query."""
    goal = load(spark, d, "lineitem", ["l_quantity"]).agg(F.avg("l_quantity").alias("goal"))
    return udfs.iterate_sql(goal, "0", "w - 0.1D * (w - goal)", 20).select("k", F.round("w", 6).alias("w"))
