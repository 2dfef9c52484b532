"""Scores, losses, local updates and one-round server steps of the checkable small model; baselines' closed forms."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fedlake.functions.hashing import uniform, uniform_sql
from fedlake.functions.vectors import sigmoid
from fedlake.operators import local_models as M
from fedlake.operators import protocol, sampling
from fedlake.operators.graph import co_user_means, ring_neighbours
from fedlake.queries.data import DRAW_SQL, P_SQL, ROUND, customers
from fedlake.queries.registry import query
from fedlake.sources import universes as U
from fedlake.sources.tables import load

RATE, STEPS, SERVER = 0.5, 3, 0.7
W = M.FIXED_WEIGHTS


def rows(spark, d):
    """client_id, item_id, x1 (part size), x2 (balance), y."""
    parts = load(spark, d, "part", ["p_partkey", "p_size"]).select(F.col("p_partkey").alias("item_id"), ((F.col("p_size") - 25) / F.lit(25.0)).alias("x1"))
    users = load(spark, d, "customer", ["c_custkey", "c_acctbal"]).select(F.col("c_custkey").alias("client_id"), ((F.col("c_acctbal") - 4500) / F.lit(5500.0)).alias("x2"))
    return U.purchases(spark, d).select("client_id", "item_id", F.col("label").cast("double").alias("y")).join(parts, "item_id").join(users, "client_id")


X_SQL = f"""{P_SQL}, x AS (
  SELECT p.client_id, p.item_id, (p_size - 25) / 25.0::DOUBLE AS x1, (c_acctbal - 4500) / 5500.0::DOUBLE AS x2, label::DOUBLE AS y
  FROM p JOIN part ON item_id = p_partkey JOIN customer ON client_id = c_custkey)"""
_z = lambda w: f"({w[0]} + {w[1]} * x1 + {w[2]} * x2)"
_fixed = [f"{v}::DOUBLE" for v in W]
_p = lambda w: f"(1 / (1 + exp(-{_z(w)})))"


@query("sigmoid_scores", f"WITH {X_SQL} SELECT client_id, item_id, round({_p(_fixed)}, 6) AS p FROM x")
def sigmoid_scores(spark, d):
    return rows(spark, d).select("client_id", "item_id", F.round(sigmoid(M.linear(M.weights(W), F.col("x1"), F.col("x2"))), 6).alias("p"))


@query("logloss_by_client", f"WITH {X_SQL} SELECT client_id, round(-avg(y * ln({_p(_fixed)}) + (1 - y) * ln(1 - {_p(_fixed)})), 6) AS loss FROM x GROUP BY 1")
def logloss_by_client(spark, d):
    p = sigmoid(M.linear(M.weights(W), F.col("x1"), F.col("x2")))
    return rows(spark, d).groupBy("client_id").agg(F.round(-F.avg(F.col("y") * F.log(p) + (1 - F.col("y")) * F.log(1 - p)), 6).alias("loss"))


@query("squared_loss_by_client", f"WITH {P_SQL}, x AS (SELECT client_id, stars, (3 + (p_size - 25) / 25.0::DOUBLE) AS guess FROM p JOIN part ON item_id = p_partkey) SELECT client_id, round(avg((guess - stars) * (guess - stars)), 6) AS loss FROM x GROUP BY 1")
def squared_loss_by_client(spark, d):
    parts = load(spark, d, "part", ["p_partkey", "p_size"]).select(F.col("p_partkey").alias("item_id"), (3 + (F.col("p_size") - 25) / F.lit(25.0)).alias("guess"))
    gap = F.col("guess") - F.col("stars")
    return U.purchases(spark, d).join(parts, "item_id").groupBy("client_id").agg(F.round(F.avg(gap * gap), 6).alias("loss"))


# fixed weights of a two-tower network with two hidden units
TOWER = {"u": ((0.5, -0.25), (0.1, 0.2)), "v": ((-0.3, 0.6), (0.05, -0.1)), "mlp": ((0.4, -0.2, 0.3, 0.1), (-0.1, 0.5, 0.2, -0.3)), "out": (0.7, -0.6, 0.05)}


def _tower_columns(relu, x1, x2):
    """The network on plain values; ``relu`` works on columns or on SQL text."""
    (ua, ub), (va, vb) = TOWER["u"], TOWER["v"]
    hidden = [relu(x2 * ua[k] + ub[k]) for k in range(2)] + [relu(x1 * va[k] + vb[k]) for k in range(2)]
    top = []
    for w in TOWER["mlp"]:
        s = hidden[0] * w[0]
        for h, c in zip(hidden[1:], w[1:], strict=True):
            s = s + h * c
        top.append(relu(s))
    a, b, c = TOWER["out"]
    return top[0] * a + top[1] * b + c


class _Sql(str):
    """SQL text that composes by arithmetic."""

    def __mul__(self, o):
        return _Sql(f"({self} * {o}::DOUBLE)")

    def __add__(self, o):
        return _Sql(f"({self} + {o})") if isinstance(o, str) else _Sql(f"({self} + {o}::DOUBLE)")


_TOWER_SQL = _tower_columns(lambda s: _Sql(f"greatest({s}, 0.0::DOUBLE)"), _Sql("x1"), _Sql("x2"))


@query("tower_score_small", f"WITH {X_SQL} SELECT client_id, item_id, round(1 / (1 + exp(-{_TOWER_SQL})), 6) AS score FROM x")
def tower_score_small(spark, d):
    score = sigmoid(_tower_columns(lambda c: F.greatest(c, F.lit(0.0)), F.col("x1"), F.col("x2")))
    return rows(spark, d).select("client_id", "item_id", F.round(score, 6).alias("score"))


def drawn(spark, d):
    return rows(spark, d).join(sampling.draw_fixed(customers(spark, d), ROUND, 1).select("client_id"), "client_id", "left_semi")


def _sgd_sql(steps: int, source: str = "x", where: str = "", rate: float = RATE) -> str:
    """CTEs s0..s<steps>: weights of the drawn clients after each full-batch step from zero."""
    out = [f"d AS (SELECT * FROM {source} WHERE client_id IN (SELECT client_id FROM draw WHERE round = 0){where})", "s0 AS (SELECT DISTINCT client_id, 0.0::DOUBLE AS w0, 0.0::DOUBLE AS w1, 0.0::DOUBLE AS w2 FROM d)"]
    for k in range(1, steps + 1):
        e = "(1 / (1 + exp(-(w0 + w1 * x1 + w2 * x2))) - y)"
        out.append(f"s{k} AS (SELECT client_id, any_value(w0) - {rate}::DOUBLE * avg({e}) AS w0, any_value(w1) - {rate}::DOUBLE * avg({e} * x1) AS w1, any_value(w2) - {rate}::DOUBLE * avg({e} * x2) AS w2 FROM d JOIN s{k - 1} USING (client_id) GROUP BY client_id)")
    return ", ".join(out)


def _unpivot(sel: str) -> str:
    return " UNION ALL ".join(f"SELECT {k} AS coord, round({sel.format(k=k)}, 6) + 0.0 AS value" for k in range(3))


def updates(spark, d, steps: int):
    """Packed drawn clients with their weights after ``steps`` local steps from zero."""
    return M.pack(drawn(spark, d)).withColumn("w", M.sgd(F.col("rows"), M.weights((0, 0, 0)), steps, RATE))


def _coords(df, values):
    return df.agg(*[v.alias(f"a{k}") for k, v in enumerate(values)]).select(M.coordinates([F.col(f"a{k}") for k in range(3)]).alias("p")).select("p.coord", (F.round("p.value", 6) + 0.0).alias("value"))


@query("local_sgd_unrolled", f"WITH {X_SQL}, {DRAW_SQL}, {_sgd_sql(STEPS)} SELECT client_id, round(w0, 6) + 0.0 AS w0, round(w1, 6) + 0.0 AS w1, round(w2, 6) + 0.0 AS w2 FROM s{STEPS}")
def local_sgd_unrolled(spark, d):
    return updates(spark, d, STEPS).select("client_id", *[(F.round(F.col(f"w.w{k}"), 6) + 0.0).alias(f"w{k}") for k in range(3)])


@query("reptile_round", f"WITH {X_SQL}, {DRAW_SQL}, {_sgd_sql(STEPS)} " + _unpivot(f"{SERVER}::DOUBLE * sum(w{{k}}) / {ROUND}").replace(" UNION", f" FROM s{STEPS} UNION") + f" FROM s{STEPS}")
def reptile_round(spark, d):
    """Server step along the mean displacement over the fixed round size."""
    return _coords(updates(spark, d, STEPS), [F.lit(SERVER) * F.sum(f"w.w{k}") / ROUND for k in range(3)])


@query("fedavg_round", f"WITH {X_SQL}, {DRAW_SQL}, {_sgd_sql(STEPS)}, n AS (SELECT client_id, count(*) AS n FROM d GROUP BY 1), s AS (SELECT * FROM s{STEPS} JOIN n USING (client_id)) " + _unpivot("sum(n * w{k}) / sum(n)").replace(" UNION", " FROM s UNION") + " FROM s")
def fedavg_round(spark, d):
    return _coords(updates(spark, d, STEPS), [F.sum(F.col("n") * F.col(f"w.w{k}")) / F.sum("n") for k in range(3)])


@query("sgd_one_step_round", f"WITH {X_SQL}, {DRAW_SQL}, {_sgd_sql(1)} " + _unpivot(f"{SERVER}::DOUBLE * sum(w{{k}}) / {ROUND}").replace(" UNION", " FROM s1 UNION") + " FROM s1")
def sgd_one_step_round(spark, d):
    return _coords(updates(spark, d, 1), [F.lit(SERVER) * F.sum(f"w.w{k}") / ROUND for k in range(3)])


_E = "(1 / (1 + exp(-(w0 + w1 * x1 + w2 * x2))) - y)"


@query(
    "fomaml_round",
    f"""WITH {X_SQL}, {DRAW_SQL}, h AS (SELECT *, {protocol.ROW_SPLIT_SQL} AS half FROM x),
    {_sgd_sql(1, 'h', " AND half = 'tune'")}, v AS (SELECT client_id, avg({_E}) AS g0, avg({_E} * x1) AS g1, avg({_E} * x2) AS g2 FROM h JOIN s1 USING (client_id) WHERE half = 'rank' GROUP BY 1) """
    + _unpivot(f"-{SERVER}::DOUBLE * sum(g{{k}}) / {ROUND}").replace(" UNION", " FROM v UNION")
    + " FROM v",
)
def fomaml_round(spark, d):
    """First-order meta gradient: taken on the query half at the weights adapted on the support half."""
    halves = protocol.split_rows(drawn(spark, d))
    packed = halves.groupBy("client_id").agg(F.sort_array(F.collect_list(F.struct("item_id", "x1", "x2", "y", "row_split"))).alias("rows"))
    part = lambda name: F.filter("rows", lambda r: r["row_split"] == name)
    adapted = packed.withColumn("support", part("tune")).withColumn("query", part("rank")).where(F.size("query") > 0).withColumn("w", M.sgd(F.col("support"), M.weights((0, 0, 0)), 1, RATE))
    return _coords(adapted.withColumn("g", M.mean_gradient(F.col("query"), F.col("w"))), [F.lit(-SERVER) * F.sum(f"g.g{k}") / ROUND for k in range(3)])


# -- baselines in closed form ---------------------------------------------
REG, CONF = 0.1, 1.0


def item_factors(ids):
    return ids.withColumns({f"q{k}": 0.1 + uniform(f"fcf{k}", F.col("item_id")) for k in range(2)})


FCF_SQL = f"""{P_SQL}, f AS (
  SELECT client_id, item_id, label, 1 + {CONF}::DOUBLE * stars AS c, 0.1::DOUBLE + {uniform_sql('fcf0', 'item_id')} AS q0, 0.1::DOUBLE + {uniform_sql('fcf1', 'item_id')} AS q1 FROM p),
n AS (SELECT client_id, sum(c * q0 * q0) + {REG}::DOUBLE AS a, sum(c * q0 * q1) AS b, sum(c * q1 * q1) + {REG}::DOUBLE AS d, sum(c * q0 * label) AS r0, sum(c * q1 * label) AS r1 FROM f GROUP BY 1),
x AS (SELECT client_id, (d * r0 - b * r1) / (a * d - b * b) AS f0, (a * r1 - b * r0) / (a * d - b * b) AS f1 FROM n)"""


def fcf_rows(spark, d):
    return item_factors(U.purchases(spark, d).select("client_id", "item_id", "label", (1 + CONF * F.col("stars")).alias("c")))


def fcf_users(rows_):
    """Each client's factor by its own weighted ridge regression; the two-by-two system is inverted in place."""
    s = rows_.groupBy("client_id").agg(
        (F.sum(F.col("c") * F.col("q0") * F.col("q0")) + REG).alias("a"), F.sum(F.col("c") * F.col("q0") * F.col("q1")).alias("b"), (F.sum(F.col("c") * F.col("q1") * F.col("q1")) + REG).alias("d"), F.sum(F.col("c") * F.col("q0") * F.col("label")).alias("r0"), F.sum(F.col("c") * F.col("q1") * F.col("label")).alias("r1")
    )
    det = F.col("a") * F.col("d") - F.col("b") * F.col("b")
    return s.select("client_id", ((F.col("d") * F.col("r0") - F.col("b") * F.col("r1")) / det).alias("f0"), ((F.col("a") * F.col("r1") - F.col("b") * F.col("r0")) / det).alias("f1"))


@query("fcf_user_factor", f"WITH {FCF_SQL} SELECT client_id, round(f0, 6) + 0.0 AS f0, round(f1, 6) + 0.0 AS f1 FROM x")
def fcf_user_factor(spark, d):
    return fcf_users(fcf_rows(spark, d)).select("client_id", *[(F.round(f"f{k}", 6) + 0.0).alias(f"f{k}") for k in range(2)])


@query("fcf_item_gradient", f"WITH {FCF_SQL} SELECT item_id, round(sum(c * (label - f0 * q0 - f1 * q1) * f0) - {REG}::DOUBLE * any_value(q0), 6) + 0.0 AS g0, round(sum(c * (label - f0 * q0 - f1 * q1) * f1) - {REG}::DOUBLE * any_value(q1), 6) + 0.0 AS g1 FROM f JOIN x USING (client_id) GROUP BY 1")
def fcf_item_gradient(spark, d):
    r = fcf_rows(spark, d)
    j = r.join(fcf_users(r), "client_id")
    error = F.col("c") * (F.col("label") - F.col("f0") * F.col("q0") - F.col("f1") * F.col("q1"))
    return j.groupBy("item_id", "q0", "q1").agg(*[F.sum(error * F.col(f"f{k}")).alias(f"s{k}") for k in range(2)]).select("item_id", *[(F.round(F.col(f"s{k}") - REG * F.col(f"q{k}"), 6) + 0.0).alias(f"g{k}") for k in range(2)])


RING_SQL = f"""{P_SQL}, k AS (SELECT client_id, item_id, md5('k#' || item_id::VARCHAR) AS hid, {uniform_sql('ring', 'client_id', 'item_id')} AS u FROM p),
e AS (SELECT client_id, lead(client_id) OVER w AS a, lead(client_id, 2) OVER w AS b FROM k WINDOW w AS (PARTITION BY hid ORDER BY u, client_id)),
nb AS (SELECT client_id, neighbour, count(*) AS common FROM (SELECT client_id, a AS neighbour FROM e UNION ALL SELECT client_id, b FROM e) WHERE neighbour IS NOT NULL GROUP BY 1, 2)"""


@query("graph_ring_neighbours", f"WITH {RING_SQL} SELECT client_id, neighbour, common FROM nb")
def graph_ring_neighbours(spark, d):
    """The bounded graph: two co-users an item."""
    return ring_neighbours(U.purchases(spark, d))


@query(
    "graph_mean_aggregate",
    f"""WITH {P_SQL}, k AS (SELECT DISTINCT client_id, md5('k#' || item_id::VARCHAR) AS hid FROM p),
    o AS (SELECT client_id, avg({uniform_sql('gnn0', 'item_id')}) AS v0, avg({uniform_sql('gnn1', 'item_id')}) AS v1 FROM p GROUP BY 1),
    s AS (SELECT hid, count(*) AS n, sum(v0) AS s0, sum(v1) AS s1 FROM k JOIN o USING (client_id) GROUP BY 1),
    m AS (SELECT k.client_id, avg((s0 - v0) / (n - 1)) AS m0, avg((s1 - v1) / (n - 1)) AS m1 FROM k JOIN s USING (hid) JOIN o ON o.client_id = k.client_id WHERE n > 1 GROUP BY 1),
    z AS (SELECT o.client_id, (v0 + coalesce(m0, v0)) / 2 AS z0, (v1 + coalesce(m1, v1)) / 2 AS z1 FROM o LEFT JOIN m USING (client_id))
    SELECT client_id, 0 AS pos, round(z0, 6) AS value FROM z UNION ALL SELECT client_id, 1, round(z1, 6) FROM z""",
)
def graph_mean_aggregate(spark, d):
    """One message round: a client's item mean averaged with the mean over its items of all other users' means."""
    p = U.purchases(spark, d)
    own = p.groupBy("client_id").agg(*[F.avg(uniform(f"gnn{k}", F.col("item_id"))).alias(f"v{k}") for k in range(2)])
    met = co_user_means(p, own, ["v0", "v1"]).select("client_id", F.col("v0").alias("m0"), F.col("v1").alias("m1"))
    z = own.join(met, "client_id", "left").select("client_id", F.posexplode(F.array(*[(F.col(f"v{k}") + F.coalesce(f"m{k}", f"v{k}")) / 2 for k in range(2)])).alias("pos", "value"))
    return z.select("client_id", "pos", F.round("value", 6).alias("value"))


SILO_SLOTS = 8


@query(
    "crosssilo_round",
    f"""WITH t AS (SELECT d.doc_id, source, quality, unnest(string_split(lower(text), ' ')) AS w FROM documents d JOIN labels USING (doc_id)),
    c AS (SELECT doc_id, source, quality, floor({uniform_sql('silo', 'w')} * {SILO_SLOTS})::INTEGER AS slot, count(*)::DOUBLE AS n FROM t WHERE w <> '' GROUP BY ALL),
    x AS (SELECT doc_id, source, quality, slot, n / sum(n) OVER (PARTITION BY doc_id) AS x FROM c),
    s AS (SELECT source, count(DISTINCT doc_id) AS docs FROM x GROUP BY 1),
    g AS (SELECT source, slot, sum((0.5 - quality) * x) AS g FROM x GROUP BY 1, 2)
    SELECT slot AS coord, round(-{RATE}::DOUBLE * sum(g / docs) / (SELECT count(*) FROM s), 6) + 0.0 AS value FROM g JOIN s USING (source) GROUP BY 1""",
)
def crosssilo_round(spark, d):
    """Institutions as clients: one averaged gradient step of a logistic model over hashed token shares, one silo per source."""
    docs = load(spark, d, "documents", ["doc_id", "source", "text"]).join(load(spark, d, "labels", ["doc_id", "quality"]), "doc_id")
    words = docs.select("doc_id", "source", "quality", F.explode(F.split(F.lower("text"), " ")).alias("w")).where("w <> ''")
    counts = words.groupBy("doc_id", "source", "quality", F.floor(uniform("silo", F.col("w")) * SILO_SLOTS).cast("int").alias("slot")).agg(F.count("*").alias("n"))
    shares = counts.withColumn("x", F.col("n") / F.sum("n").over(Window.partitionBy("doc_id")))
    silos = shares.groupBy("source").agg(F.countDistinct("doc_id").alias("docs"))
    steps = shares.groupBy("source", "slot").agg(F.sum((0.5 - F.col("quality")) * F.col("x")).alias("g"))
    total = silos.count()
    return steps.join(silos, "source").groupBy(F.col("slot").alias("coord")).agg((F.round(F.lit(-RATE) * F.sum(F.col("g") / F.col("docs")) / total, 6) + 0.0).alias("value"))
