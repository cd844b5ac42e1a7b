"""Registered queries of the engine, and the SQL that checks them in another engine.

Entries of the form ``name: (function, sql)``; queries whose result SQL cannot express have no SQL.
Floating-point results are rounded to six places (sums of money to two), since the order of a sum differs
between engines; 0.0 is added so that zeros carry no sign.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from meshspan.functions.linalg import Powers
from meshspan.functions.vectors import vec_dot
from meshspan.operators import consensus, cost, encode, loops, metrics, moments, partition, subspace, topology
from meshspan.plans import workloads
from meshspan.plans.chains import Chain, edges_sql
from meshspan.plans import stopping
from meshspan.plans.schedules import RULES, Explicit, Fixed, Ramp, schedule_table
from meshspan.sources import features
from meshspan.sources.tables import load_table, stored
from meshspan.streaming import incremental

Query = Callable[[SparkSession, str], DataFrame]
REGISTRY: dict[str, tuple[Query, str | Callable[[], str] | None]] = {}


def query(sql: str | Callable[[], str] | None = None):
    def register(f: Query) -> Query:
        REGISTRY[f.__name__] = (f, sql)
        return f

    return register


def r6(c: Column, places: int = 6) -> Column:
    return F.round(c, places) + 0.0


# ---------------------------------------------------------------- schedules and costs

_RULES_SQL = """(VALUES ('half_floor', 0.5, 1, 50, 0), ('half_ceil', 0.5, 1, 50, 1), ('t+1', 1, 1, 50, 0), ('2t+1', 2, 1, 50, 0), ('50', 0, 50, 50, 0),
 ('5t+1,200', 5, 1, 200, 0), ('2t+1,100', 2, 1, 100, 0), ('5t+1,100', 5, 1, 100, 0), ('100', 0, 100, 100, 0)) AS r(rule, slope, shift, cap, up)"""
_ROUNDS_SQL = f"""SELECT rule, CAST(t AS INT) AS t, CAST(least(cap, CASE WHEN up = 1 THEN ceil(slope * t + shift) ELSE floor(slope * t + shift) END) AS BIGINT) AS rounds
 FROM {_RULES_SQL}, range(400) AS g(t)"""


_DAYS_SQL = "(SELECT o_orderdate AS day, row_number() OVER (ORDER BY o_orderdate) - 1 AS t, count(*) AS orders FROM orders WHERE o_orderdate IS NOT NULL GROUP BY o_orderdate)"


def _days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Days with orders, numbered from 0 as outer steps: one row a day, so one task numbers them."""
    days = load_table(spark, sf_dir, "orders").where("o_orderdate is not null").groupBy(F.col("o_orderdate").alias("day")).agg(F.count("*").alias("orders"))
    return days.withColumn("t", (F.row_number().over(Window.orderBy("day")) - 1).cast("int"))


@query(f"""WITH s AS ({_ROUNDS_SQL.replace("range(400) AS g(t)", f"{_DAYS_SQL} AS g").replace("SELECT rule,", "SELECT rule, orders,")})
 SELECT rule, t, orders, rounds, CAST(sum(rounds) OVER (PARTITION BY rule ORDER BY t) AS BIGINT) AS inner_total FROM s""")
def schedule_rounds(spark, sf_dir):
    """An outer step per day with orders: its rounds under every rule, with the running total (the total-iterations axis)."""
    days = stored(_days(spark, sf_dir).select("t", "orders"), "days")
    return schedule_table(spark, RULES, days.count(), days)


#: Configurations of the published tables: mean degree, outer steps and rule.
PUBLISHED = [
    (table, config, degree, outer, rule)
    for table, config, degree, outer, rules in (
        ("t1", "gap .3", 4.62, 200, ("half_floor", "t+1", "2t+1", "50")), ("t1", "gap .7", 4.95, 200, ("half_floor", "t+1", "2t+1", "50")),
        ("t1", "gap .9", 4.83, 200, ("half_floor", "t+1", "2t+1", "50")), ("t2", "p .5", 9.67, 200, ("2t+1", "50")), ("t2", "p .1", 2.45, 200, ("2t+1", "50", "5t+1,200")),
        ("t3", "ring", 2.0, 200, ("2t+1", "50", "5t+1,200")), ("t4", "centre", 19.0, 200, ("2t+1", "50", "2t+1,100", "5t+1,100", "100")),
        ("t4", "edge", 1.0, 200, ("2t+1", "50", "2t+1,100", "5t+1,100", "100")), ("t6", "20 nodes", 4.4, 400, ("t+1", "2t+1", "50")), ("t6", "100 nodes", 5.0, 200, ("t+1", "2t+1", "50")),
        ("t7", "20 nodes", 4.1, 400, ("t+1", "2t+1", "50")), ("t8", "p .25", 4.8, 200, ("t+1", "2t+1", "50")), ("t8", "p .5", 9.4, 200, ("t+1", "2t+1", "50")),
        ("t9", "10 nodes", 4.0, 200, ("t+1", "2t+1", "50")), ("t9", "20 nodes", 3.7, 200, ("t+1", "2t+1", "50")), ("t9", "100 nodes", 5.46, 200, ("t+1", "2t+1", "50")),
        ("t9", "200 nodes", 5.74, 200, ("t+1", "2t+1", "50")),
    )
    for rule in rules
]


#: Networks of the same configurations on the given tables: nodes, density and seed (rings and stars: of all nodes with lines).
NETWORKS = {
    ("t1", "gap .3"): (20, 0.25, 1), ("t1", "gap .7"): (20, 0.25, 2), ("t1", "gap .9"): (20, 0.25, 3), ("t2", "p .5"): (20, 0.5, 1), ("t2", "p .1"): (20, 0.1, 1),
    ("t6", "20 nodes"): (20, 0.25, 4), ("t6", "100 nodes"): (100, 0.05, 1), ("t7", "20 nodes"): (20, 0.25, 5), ("t8", "p .25"): (20, 0.25, 6), ("t8", "p .5"): (20, 0.5, 2),
    ("t9", "10 nodes"): (10, 0.5, 1), ("t9", "20 nodes"): (20, 0.25, 7), ("t9", "100 nodes"): (100, 0.05, 2), ("t9", "200 nodes"): (200, 0.03, 1),
}
_NETWORKS_SQL = ", ".join(f"('{a}', '{b}', {n}, {p}, {seed})" for (a, b), (n, p, seed) in NETWORKS.items())
_PUBLISHED_SQL = ", ".join(f"('{a}', '{b}', {d}, '{e}')" for a, b, _, d, e in PUBLISHED)
_DEGREES_SQL = f"""w AS MATERIALIZED (SELECT l_partkey % 200 AS a, l_suppkey % 200 AS b, count(*) AS c FROM lineitem WHERE l_partkey IS NOT NULL AND l_suppkey IS NOT NULL GROUP BY 1, 2), net(tab, config, n, p, seed) AS (VALUES {_NETWORKS_SQL}),
 q AS MATERIALIZED (SELECT n, least(a % n, b % n) AS src, greatest(a % n, b % n) AS dst, CAST(sum(c) AS BIGINT) AS lines FROM w, (SELECT DISTINCT n FROM net) WHERE a % n <> b % n GROUP BY 1, 2, 3),
 k AS (SELECT count(DISTINCT i) AS k FROM (SELECT a % 20 AS i FROM w UNION ALL SELECT b % 20 FROM w)),
 g AS (SELECT tab, config, 2e0 * count(q.src) / net.n AS degree FROM net LEFT JOIN q ON q.n = net.n AND {{fraction}} < net.p GROUP BY tab, config, net.n
  UNION ALL SELECT 't3', 'ring', least(2, k - 1) FROM k UNION ALL SELECT 't4', 'centre', k - 1 FROM k UNION ALL SELECT 't4', 'edge', least(1, k - 1) FROM k)"""


def _fraction_sql(seed) -> str:
    return f"CAST(('0x' || substr(md5({seed} || '|' || src || '|' || dst || '|' || lines), 1, 8)) AS BIGINT) / 4294967296.0"


@query(f"""WITH s AS ({_ROUNDS_SQL}), {_DEGREES_SQL.format(fraction=_fraction_sql("seed"))}, p AS (SELECT v.tab, v.config, round(CAST(degree AS DOUBLE), 6) AS degree, outer_steps, rule FROM (VALUES {_PUBLISHED_SQL}) AS v(tab, config, outer_steps, rule) JOIN g ON g.tab = v.tab AND g.config = v.config)
SELECT tab, config, p.rule, CAST(degree AS DOUBLE) AS degree, CAST(outer_steps AS BIGINT) AS outer_steps, CAST(sum(rounds) AS BIGINT) AS rounds_total,
 round(CAST(degree AS DOUBLE) * sum(rounds) / 1000, 3) + 0.0 AS p2p_k FROM p JOIN s ON s.rule = p.rule AND s.t < p.outer_steps GROUP BY tab, config, p.rule, degree, outer_steps""")
def published_messages(spark, sf_dir):
    """Messages per node, in thousands, of the published configurations from rule and mean degree, their networks being
    drawn among nodes that exchange lines. One scan counts lines between 200 nodes; fewer nodes are sums of those."""
    keys = load_table(spark, sf_dir, "lineitem").select(F.pmod("l_partkey", F.lit(200)).alias("a"), F.pmod("l_suppkey", F.lit(200)).alias("b"))
    fine = stored(keys.where("a is not null and b is not null").groupBy("a", "b").agg(F.count("*").alias("lines")), "traffic")
    found = fine.select(F.explode(F.array(F.col("a") % 20, F.col("b") % 20))).distinct().count()
    degrees = {("t3", "ring"): min(2, found - 1), ("t4", "centre"): found - 1, ("t4", "edge"): min(1, found - 1)}
    pairs = {n: stored(topology.traffic(fine, "a", "b", n, "lines"), "pairs") for n in {n for n, _, _ in NETWORKS.values()}}
    for at, (n, density, seed) in NETWORKS.items():
        degrees[at] = round(2 * topology.drawn_edges(pairs[n], density, seed).count() / n, 6)
    p = spark.createDataFrame([(a, b, float(degrees[a, b]), d, e) for a, b, _, d, e in PUBLISHED], "tab string, config string, degree double, outer_steps long, rule string")
    s = schedule_table(spark, RULES, 400).select("rule", "t", "rounds")
    joined = s.join(F.broadcast(p), "rule").where("t < outer_steps")
    total = F.sum("rounds")
    return joined.groupBy("tab", "config", "rule", "degree", "outer_steps").agg(total.alias("rounds_total"), r6(F.col("degree") * total / 1000, 3).alias("p2p_k"))


def _drawn_sql(p: float, n: int = 20, seed: int = 1) -> str:
    return f"""SELECT src, dst FROM (SELECT CAST(least(a, b) AS INT) AS src, CAST(greatest(a, b) AS INT) AS dst, count(*) AS lines FROM (SELECT l_partkey % {n} AS a, l_suppkey % {n} AS b FROM lineitem) WHERE a <> b GROUP BY 1, 2)
 WHERE {_fraction_sql(seed)} < {p}"""


def _traffic(spark: SparkSession, sf_dir: str, n: int = 20) -> DataFrame:
    """Pairs of nodes by the lines that bring a part of one from a supplier of the other: one scan of lineitem."""
    return stored(topology.traffic(load_table(spark, sf_dir, "lineitem"), "l_partkey", "l_suppkey", n), "traffic")


@query(_drawn_sql(0.25))
def random_graph_edges(spark, sf_dir):
    """Random network among the nodes that exchange lines."""
    return topology.drawn_edges(_traffic(spark, sf_dir), 0.25, 1)


_GRAPHS_SQL = f"""SELECT 'random' AS graph, src, dst FROM ({_drawn_sql(0.25)}) UNION ALL
 SELECT 'ring', CAST(least(i, (i + 1) % 20) AS INT), CAST(greatest(i, (i + 1) % 20) AS INT) FROM range(20) r(i) UNION ALL SELECT 'star', 0, CAST(i AS INT) FROM range(1, 20) s(i)"""


def _graphs(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = topology.drawn_edges(_traffic(spark, sf_dir), 0.25, 1).withColumn("graph", F.lit("random"))
    for graph in (topology.ring(20), topology.star(20)):
        out = out.unionByName(graph.edge_table(spark).withColumn("graph", F.lit(graph.kind)))
    return out.select("graph", "src", "dst")


@query(f"""WITH e AS ({_GRAPHS_SQL}), b AS (SELECT graph, src AS node FROM e UNION ALL SELECT graph, dst FROM e), d AS (SELECT graph, node, count(*) AS degree FROM b GROUP BY graph, node),
 s AS (SELECT rule, CAST(sum(rounds) AS BIGINT) AS rounds_total FROM ({_ROUNDS_SQL}) WHERE t < 200 GROUP BY rule) SELECT graph, node, degree, rule, rounds_total, degree * rounds_total AS sends FROM d, s""")
def messages_per_node(spark, sf_dir):
    return cost.p2p_plan(_graphs(spark, sf_dir), schedule_table(spark, RULES, 200))


@query(f"""WITH e AS ({_GRAPHS_SQL}), b AS (SELECT graph, src AS node FROM e UNION ALL SELECT graph, dst FROM e), d AS (SELECT graph, node, count(*) AS degree FROM b GROUP BY graph, node),
 s AS (SELECT rule, CAST(sum(rounds) AS BIGINT) AS rounds_total FROM ({_ROUNDS_SQL}) WHERE t < 200 GROUP BY rule)
 SELECT coalesce(graph, 'all') AS graph, coalesce(rule, 'all') AS rule, round(avg(degree * rounds_total), 4) + 0.0 AS sends, count(*) AS n FROM d, s GROUP BY ROLLUP (graph, rule)""")
def message_report(spark, sf_dir):
    """Mean messages by graph and rule, with subtotals."""
    plan = cost.p2p_plan(_graphs(spark, sf_dir), schedule_table(spark, RULES, 200))
    return plan.rollup("graph", "rule").agg(r6(F.avg("sends"), 4).alias("sends"), F.count("*").alias("n")).select(
        F.coalesce("graph", F.lit("all")).alias("graph"), F.coalesce("rule", F.lit("all")).alias("rule"), "sends", "n"
    )


@query(f"""WITH s AS (SELECT sum(rounds) AS total FROM ({_ROUNDS_SQL}) WHERE t < 200 AND rule = '2t+1'), c AS (SELECT o_custkey, o_orderkey FROM orders WHERE o_custkey IS NOT NULL AND o_orderkey IS NOT NULL),
 d AS (SELECT 'centre' AS role, count(*) AS degree FROM c GROUP BY o_custkey UNION ALL SELECT 'edge', count(*) FROM c GROUP BY o_orderkey)
 SELECT role, count(*) AS nodes, round(CAST(sum(degree * total) AS DOUBLE) / count(*), 4) + 0.0 AS sends FROM d, s GROUP BY role""")
def star_messages(spark, sf_dir):
    """Stars of the orders: a customer is the centre, its orders are the edges (customers count from -1 downwards)."""
    spokes = load_table(spark, sf_dir, "orders").where("o_custkey is not null and o_orderkey is not null")
    edges = spokes.select(F.lit("star").alias("graph"), (-1 - F.col("o_custkey").cast("long")).alias("src"), F.col("o_orderkey").cast("long").alias("dst"))
    sends = cost.p2p_plan(edges, schedule_table(spark, {"2t+1": RULES["2t+1"]}, 200)).withColumn("role", F.when(F.col("node") < 0, "centre").otherwise("edge"))
    return cost.by_role(sends).withColumn("sends", r6(F.col("sends"), 4))


def _weights_sql(edges: str) -> str:
    return f"""WITH e AS MATERIALIZED ({edges}), b AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), d AS (SELECT src, count(*) AS deg FROM b GROUP BY src),
 o AS (SELECT b.src, b.dst, 1.0 / greatest(x.deg, y.deg) AS w FROM b JOIN d x ON x.src = b.src JOIN d y ON y.src = b.dst),
 w AS (SELECT src, dst, CAST(w AS DOUBLE) AS w FROM o UNION ALL SELECT CAST(i AS INT), CAST(i AS INT), 1 - coalesce((SELECT sum(CAST(w AS DOUBLE)) FROM o WHERE o.src = i), 0) FROM range(20) n(i))"""


_WEIGHTS_SQL = _weights_sql(edges_sql(20, 0.25, 1))
_LINE_WEIGHTS_SQL = _weights_sql(_drawn_sql(0.25))


def _line_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topology.weight_table(topology.drawn_edges(_traffic(spark, sf_dir), 0.25, 1), 20)


@query(f"{_LINE_WEIGHTS_SQL} SELECT src, dst, round(w, 6) + 0.0 AS w FROM w")
def local_degree_weights(spark, sf_dir):
    return _line_weights(spark, sf_dir).select("src", "dst", r6(F.col("w")).alias("w"))


@query(f"{_LINE_WEIGHTS_SQL} SELECT src AS node, round(sum(w), 6) + 0.0 AS given, round((SELECT sum(w) FROM w c WHERE c.dst = w.src), 6) + 0.0 AS taken FROM w GROUP BY src")
def weight_sums(spark, sf_dir):
    w = stored(_line_weights(spark, sf_dir), "weights")
    rows, columns = w.groupBy(F.col("src").alias("node")).agg(F.sum("w").alias("given")), w.groupBy(F.col("dst").alias("node")).agg(F.sum("w").alias("taken"))
    return rows.join(columns, "node").select("node", r6(F.col("given")).alias("given"), r6(F.col("taken")).alias("taken"))


def _node_means(spark: SparkSession, sf_dir: str, n: int = 20, d: int = 64) -> DataFrame:
    e = partition.by_hash(features.embeddings(spark, sf_dir, d), n)
    sums = e.groupBy("node").agg(*[F.sum(F.element_at("features", i + 1)).alias(f"s{i}") for i in range(d)])
    return sums.select("node", F.lit(0).alias("i"), F.array(*[f"s{i}" for i in range(d)]).alias("z"))


_NODE_SUMS_SQL = """z0 AS (SELECT CAST(vec_id % 20 AS INT) AS node, k - 1 AS k, sum(CAST(embedding[k] AS DOUBLE)) AS v FROM embeddings, range(1, 65) r(k) GROUP BY 1, 2)"""


def _round_sql(k: int) -> str:
    return f"z{k} AS (SELECT w.dst AS node, k, sum(w.w * v) AS v FROM z{k - 1} JOIN w ON w.src = node GROUP BY w.dst, k)"


_MIXED_SQL = f"{_WEIGHTS_SQL}, {_NODE_SUMS_SQL}, {', '.join(map(_round_sql, (1, 2, 3)))} SELECT node, CAST(k AS INT) AS k, round(v, 6) + 0.0 AS v FROM z3"


def _flat(values: DataFrame) -> DataFrame:
    return values.select("node", F.posexplode("z").alias("k", "v")).select("node", "k", r6(F.col("v")).alias("v"))


@query(_MIXED_SQL)
def averaging_literal(spark, sf_dir):
    """Three rounds of neighbour averaging, one join each."""
    return _flat(consensus.run_rounds(_node_means(spark, sf_dir), topology.weight_table(topology.random_edges(spark, 20, 0.25, 1), 20), 3))


@query(_MIXED_SQL)
def averaging_fused(spark, sf_dir):
    """The same by one product with the third power."""
    return _flat(consensus.run_fused(_node_means(spark, sf_dir), Powers(topology.Topology(20, _edges(20, 0.25, 1)).weights())[3]))


def _edges(n: int, p: float, seed: int) -> tuple[tuple[int, int], ...]:
    return topology.erdos_renyi(n, p, seed).edges


@query(f"""{_LINE_WEIGHTS_SQL}, p0 AS (SELECT CAST(i AS INT) AS node, CASE WHEN i = 0 THEN 1.0 ELSE 0.0 END AS v FROM range(20) r(i)), p1 AS (SELECT w.dst AS node, sum(w.w * v) AS v FROM p0 JOIN w ON w.src = node GROUP BY w.dst),
 p2 AS (SELECT w.dst AS node, sum(w.w * v) AS v FROM p1 JOIN w ON w.src = node GROUP BY w.dst) SELECT node, round(v, 6) + 0.0 AS anchor, v < 1e-12 AS unreached FROM p2""")
def anchor_entries(spark, sf_dir):
    """First column of the squared weights: what the sum is read by; zero where node 0 is over two steps away."""
    w = np.zeros((20, 20))
    for r in _line_weights(spark, sf_dir).collect():
        w[r["src"], r["dst"]] = r["w"]
    power = Powers(w)[2]
    return spark.createDataFrame([(i, float(round(v, 6)) + 0.0, bool(v < 1e-12)) for i, v in enumerate(power[:, 0])], "node int, anchor double, unreached boolean")


# ---------------------------------------------------------------- moments and feature views


@query("""SELECT CAST(label AS INT) AS node, CAST(i - 1 AS INT) AS i, CAST(j - 1 AS INT) AS j, count(*) AS n, round(sum(CAST(embedding[i] AS DOUBLE) * CAST(embedding[j] AS DOUBLE)), 6) + 0.0 AS v
 FROM embeddings, range(1, 65) a(i), range(1, 65) b(j) GROUP BY label, i, j""")
def node_scatter(spark, sf_dir):
    """Raw second moments of every label's embeddings."""
    e = features.embeddings(spark, sf_dir).withColumn("node", F.col("label"))
    return moments.local_scatter(e).select("node", "i", F.posexplode("row").alias("j", "v"), "n").select("node", "i", "j", "n", r6(F.col("v")).alias("v"))


_ORDER_SQL = """SELECT l_orderkey AS k, count(*) AS f0, sum(l_quantity) AS f1, sum(l_extendedprice) AS f2, sum(l_extendedprice * (1 - l_discount)) AS f3, sum(l_extendedprice * (1 - l_discount) * (1 + l_tax)) AS f4,
 avg(l_discount) AS f5, avg(l_tax) AS f6, max(l_quantity) AS f7 FROM lineitem GROUP BY l_orderkey"""


@query("""WITH e AS (SELECT CAST(embedding[i] AS DOUBLE) AS x, CAST(embedding[j] AS DOUBLE) AS y, i, j FROM embeddings, range(1, 65) a(i), range(1, 65) b(j))
 SELECT CAST(i - 1 AS INT) AS i, CAST(j - 1 AS INT) AS j, round(covar_pop(x, y), 8) + 0.0 AS v FROM e GROUP BY i, j""")
def embedding_covariance(spark, sf_dir):
    m = moments.global_moments(features.embeddings(spark, sf_dir))
    return spark.createDataFrame([(i, j, float(m.covariance[i, j])) for i in range(m.d) for j in range(m.d)], "i int, j int, v double").withColumn("v", r6(F.col("v"), 8))


@query("""SELECT CAST(l_suppkey % 5 AS INT) AS node, CAST(i AS INT) AS i, CAST(j AS INT) AS j, count(*) AS n, round(sum((CASE i WHEN 0 THEN l_quantity WHEN 1 THEN l_discount * 100 ELSE l_tax * 100 END) * (CASE j WHEN 0 THEN l_quantity WHEN 1 THEN l_discount * 100 ELSE l_tax * 100 END)), 3) + 0.0 AS v
 FROM lineitem, range(3) a(i), range(3) b(j) GROUP BY 1, 2, 3""")
def narrow_node_scatter(spark, sf_dir):
    """The same for three columns of lineitem by plain aggregates in generated code."""
    t = load_table(spark, sf_dir, "lineitem").select(F.pmod("l_suppkey", F.lit(5)).cast("int").alias("node"), F.array("l_quantity", F.col("l_discount") * 100, F.col("l_tax") * 100).alias("features"))
    return moments.narrow_scatter(t, 3).select("node", "i", F.posexplode("row").alias("j", "v"), "n").select("node", "i", "j", "n", r6(F.col("v"), 3).alias("v"))


@query(f"WITH f AS ({_ORDER_SQL}) SELECT k AS sample_id, CAST(f0 AS BIGINT) AS f0, round(f1, 2) + 0.0 AS f1, round(f3, 4) + 0.0 AS f3, round(f4, 6) + 0.0 AS f4, round(f5, 6) + 0.0 AS f5, f7 + 0.0 AS f7 FROM f")
def order_features(spark, sf_dir):
    f = features.line_aggregates(spark, sf_dir, "l_orderkey")
    at = lambda i: F.element_at("features", i + 1)
    return f.select("sample_id", at(0).cast("long").alias("f0"), r6(at(1), 2).alias("f1"), r6(at(3), 4).alias("f3"), r6(at(4), 6).alias("f4"), r6(at(5)).alias("f5"), (at(7) + 0.0).alias("f7"))


_TOKENS_SQL = "SELECT doc_id, unnest(regexp_split_to_array(lower(coalesce(text, '')), '\\s+')) AS w FROM documents"


@query(f"""WITH t AS ({_TOKENS_SQL}), c AS (SELECT doc_id, CAST(('0x' || substr(md5(w), 1, 8)) AS BIGINT) % 32 AS b, count(*) AS n FROM t WHERE w <> '' GROUP BY 1, 2)
 SELECT doc_id AS sample_id, CAST(b AS INT) AS b, round(n / CAST(sum(n) OVER (PARTITION BY doc_id) AS DOUBLE), 6) + 0.0 AS v FROM c""")
def hashed_documents(spark, sf_dir):
    """Non-zero entries of the hashed bags of words."""
    d = features.documents_hashed(spark, sf_dir, 32)
    return d.select("sample_id", F.posexplode("features").alias("b", "v")).where("v > 0").select("sample_id", "b", r6(F.col("v")).alias("v"))


@query("""SELECT user_id, CAST(hour(ts) AS INT) AS h, CAST(count(*) AS DOUBLE) AS n FROM events GROUP BY 1, 2""")
def user_hour_profile(spark, sf_dir):
    u = features.user_hours(spark, sf_dir)
    return u.select(F.col("sample_id").alias("user_id"), F.posexplode("features").alias("h", "n")).where("n > 0")


_STANDARD_SQL = f"""f AS ({_ORDER_SQL}), l AS (SELECT k, unnest([0, 1, 2, 3, 4, 5, 6, 7]) AS i, unnest([f0, f1, f2, f3, f4, f5, f6, f7]) AS x FROM f),
 s AS (SELECT i, avg(x) AS m, stddev_pop(x) AS sd, count(*) AS n FROM l GROUP BY i), z AS (SELECT k, l.i, (x - m) / sd AS x, n FROM l JOIN s USING (i)),
 c0 AS (SELECT a.i, b.i AS j, sum(a.x * b.x) / max(a.n) AS v FROM z a JOIN z b USING (k) GROUP BY 1, 2)"""


def _leading_sql(k: int, steps: int = 16) -> str:
    """Leading eigenvector's projector by repeated squaring, then deflation: the k-th chain of tables."""
    m = f"m{k - 1}"
    return f"""q{k} AS (SELECT 0 AS n, i, j, v / (SELECT sum(v) FROM {m} WHERE i = j) AS v FROM {m} UNION ALL
   SELECT n + 1, i, j, v / sum(CASE WHEN i = j THEN v ELSE 0 END) OVER () FROM (SELECT a.n, a.i, b.j, sum(a.v * b.v) AS v FROM q{k} a JOIN q{k} b ON a.j = b.i AND a.n = b.n WHERE a.n < {steps} GROUP BY a.n, a.i, b.j)),
 p{k} AS (SELECT i, j, v FROM q{k} WHERE n = {steps}), t{k} AS (SELECT sum(m.v * p.v) AS lambda FROM {m} m JOIN p{k} p ON p.i = m.i AND p.j = m.j),
 m{k} AS (SELECT m.i, m.j, m.v - t.lambda * p.v AS v FROM {m} m JOIN p{k} p ON p.i = m.i AND p.j = m.j, t{k} t)"""


_ORDER_PROJECTOR_SQL = f"""WITH RECURSIVE {_STANDARD_SQL}, m0 AS (SELECT i, j, v FROM c0), {', '.join(_leading_sql(k) for k in (1, 2, 3, 4))}
 SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, round(sum(v), 5) + 0.0 AS p FROM (SELECT * FROM p1 UNION ALL SELECT * FROM p2 UNION ALL SELECT * FROM p3 UNION ALL SELECT * FROM p4) GROUP BY i, j"""


def _projector(spark: SparkSession, q: np.ndarray, places: int = 6) -> DataFrame:
    p = q @ q.T
    return spark.createDataFrame([(i, j, float(p[i, j])) for i in range(len(p)) for j in range(len(p))], "i int, j int, p double").withColumn("p", r6(F.col("p"), places))


def _orders(spark, sf_dir):
    return features.standardized(features.line_aggregates(spark, sf_dir, "l_orderkey"))


@query(_ORDER_PROJECTOR_SQL)
def order_exact_subspace(spark, sf_dir):
    """Leading four directions of the order features: the eigensolver."""
    return _projector(spark, subspace.exact_subspace(_orders(spark, sf_dir), 4)[1], 5)


@query(f"SELECT CAST(o AS INT) AS node, i, j, p FROM ({_ORDER_PROJECTOR_SQL}), range(10) o(o)")
def order_row_split(spark, sf_dir):
    """The same from rows split over ten nodes of a random graph, at every node (averaging 150 rounds a step)."""
    samples = partition.by_hash(_orders(spark, sf_dir), 10)
    out = subspace.rowsplit_subspace(samples, topology.erdos_renyi(10, 0.5), 4, Fixed(150), 60)
    return _every_node(out.basis, 5)


@query(_ORDER_PROJECTOR_SQL)
def order_column_split(spark, sf_dir):
    """The same from columns split over eight nodes."""
    out = subspace.colsplit_subspace(_orders(spark, sf_dir), partition.column_blocks(8, 8), topology.complete(8), 4, Fixed(50), 60, push_rounds=None)
    return _every_node(out.basis.withColumn("node", F.lit(0)), 5).drop("node")


def _every_node(basis: DataFrame, places: int = 6) -> DataFrame:
    return metrics.projector(basis).select("node", "i", "j", r6(F.col("p"), places).alias("p"))


# ---------------------------------------------------------------- a few steps of every method, step by step


def shaped_nodes(spark: SparkSession, sf_dir: str, n: int = 10, d: int = 20, r: int = 5, delta: float = 0.4, tied: bool = False) -> DataFrame:
    return partition.by_hash(features.shaped(features.embeddings(spark, sf_dir, d), r, delta, tied), n)


_GRAPH = topology.erdos_renyi(10, 0.5)
_SEED = int(_GRAPH.kind.split("seed=")[1][:-1])
_BLOCKS = partition.column_blocks(64, 10)


def _ten(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition.by_hash(features.embeddings(spark, sf_dir), 10)


def _entries(basis: DataFrame) -> DataFrame:
    return basis.select("node", "i", F.posexplode("q").alias("k", "q")).select("node", "i", "k", r6(F.col("q")).alias("q"))


def _stepped(name: str, run: Callable[[DataFrame], subspace.SubspaceResult], sql: Callable[[Chain], str], doc: str) -> None:
    """A method begun at the first two axes: every node's basis after a few steps, all components."""

    def own(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _entries(run(_ten(spark, sf_dir)).basis)

    own.__doc__ = doc
    REGISTRY[name] = (own, lambda: (lambda c: c.select(sql(c)))(Chain(10, 64, 0.5, _SEED)))


def _row(schedule, outer: int = 3, **more):
    return lambda x: subspace.rowsplit_subspace(x, _GRAPH, 2, schedule, outer, "axes", **more)


def _base(name: str, **more):
    return lambda x: subspace.baseline(x, name, 2, _GRAPH, init="axes", **more)


def _columns(schedule, outer: int = 3, **more):
    return lambda x: subspace.colsplit_subspace(x, _BLOCKS, _GRAPH, 2, schedule, outer, "axes", **more)


_stepped("row_split_fixed", _row(Fixed(2)), lambda c: c.row_split([2, 2, 2]), "Fixed rounds.")
_stepped("row_split_ramped", _row(Ramp(2)), lambda c: c.row_split([1, 3, 5]), "Rounds that grow by two a step.")
_stepped("row_split_slow_ramp", _row(Ramp(1)), lambda c: c.row_split([1, 2, 3]), "Rounds that grow by one a step.")
_stepped("row_split_half_ramp", _row(Ramp(0.5, rounding="floor"), 4), lambda c: c.row_split([1, 1, 2, 2]), "Rounds that grow every other step.")
_stepped("row_split_half_ramp_up", _row(Ramp(0.5)), lambda c: c.row_split([1, 2, 2]), "The same, rounded up.")
_stepped("row_split_explicit", _row(Explicit((0, 1, 4))), lambda c: c.row_split([0, 1, 4]), "A list of rounds; without a round, a node that is not the anchor keeps its own product.")
_stepped("row_split_fused", _row(Fixed(2), mode="fused"), lambda c: c.row_split([2, 2, 2]), "Products as distributed jobs.")
_stepped("row_split_spread", _row(Fixed(2), 2, mode="spread"), lambda c: c.row_split([2, 2]), "Bases in tables.")
_stepped("row_split_literal", _row(Fixed(2), 2, mode="literal"), lambda c: c.row_split([2, 2]), "Every averaging round a join.")
_stepped("consensus_sequential", _base("sequential", schedule=Fixed(2), outer=4), lambda c: c.sequential(2, 2), "One vector after the other, averaged.")
_stepped("hebbian_steps", _base("hebbian", outer=3, step=0.1), lambda c: c.hebbian(3, 0.1), "Generalised Hebbian rule.")
_stepped("projected_gradient_steps", _base("projected_gradient", outer=3, step=0.1), lambda c: c.projected_gradient(3, 0.1), "Projected gradient.")
_stepped("gradient_tracking", _base("tracking", outer=3, rounds_per_step=2), lambda c: c.tracking(3, 2), "Gradient tracking.")
_stepped("central_orthogonal", _base("central", outer=3), lambda c: c.central(3), "Central orthogonal iteration.")
_stepped("central_sequential", _base("central_sequential", outer=4), lambda c: c.central_sequential(2), "Central sequential power steps.")
_stepped("column_split_cross", _columns(Fixed(2), push_rounds=None), lambda c: c.column_split(_BLOCKS, [2, 2, 2], None), "Columns split, exact inner products.")
_stepped("column_split_agreed", _columns(Ramp(1), push_rounds=3), lambda c: c.column_split(_BLOCKS, [1, 2, 3], 3), "Columns split, ramped, inner products as three rounds give them.")
_stepped("column_split_mgs", _columns(Fixed(2), qr="mgs", push_rounds=3), lambda c: c.column_split(_BLOCKS, [2, 2, 2], 3, "mgs"), "The same with modified Gram-Schmidt.")
_stepped("column_split_streamed", _columns(Fixed(2), mode="streamed", push_rounds=None), lambda c: c.column_split(_BLOCKS, [2, 2, 2], None), "One scan of the samples per step.")
_stepped("column_split_literal", _columns(Fixed(2), 1, mode="literal", push_rounds=None), lambda c: c.column_split(_BLOCKS, [2], None), "Scores of samples averaged by joins.")
_stepped("column_sequential", lambda x: subspace.colsplit_sequential(x, _BLOCKS, _GRAPH, 2, Fixed(2), 4, "axes", push_rounds=3), lambda c: c.column_sequential(_BLOCKS, 2, 2, 3), "Columns split, one vector after the other.")
_stepped("block_split", lambda x: subspace.blocksplit_subspace(x, _BLOCKS, _GRAPH, _GRAPH, 2, Fixed(2), 3, "axes"), lambda c: c.block_split(_BLOCKS, [2, 2, 2]), "Rows and columns split.")
# the last three hold one basis, not one per node
for _name in ("column_sequential", "block_split"):
    _run = REGISTRY[_name][0]
    _sql = REGISTRY[_name][1]
    REGISTRY[_name] = (_run, lambda sql=_sql: sql().replace(" SELECT node AS node,", " SELECT 0 AS node,"))


def _uniform_sql() -> str:
    c = Chain(10, 64, 0.5, _SEED)
    q = c.central(3)
    return c.select(c.add(f"SELECT CAST(o AS INT) AS node, i, k, v FROM {q}, range(10) o(o)"))


@query(_uniform_sql)
def row_split_complete(spark, sf_dir):
    """Uniform weights on the complete graph: one round is exact, so every node walks the central iteration."""
    return _entries(subspace.rowsplit_subspace(_ten(spark, sf_dir), topology.complete(10), 2, Fixed(1), 3, "axes", weights="uniform").basis)


def _measures_sql() -> str:
    c = Chain(10, 64, 0.5, _SEED)
    return c.measures(c.row_split([2, 2, 2]), c.central(3))


@query(_measures_sql)
def error_measures(spark, sf_dir):
    """Every node's basis after three steps against the central one: angle error, lost variance, orthonormality
    defect, distance, and the largest distance from the mean basis."""
    samples = _ten(spark, sf_dir)
    basis = subspace.rowsplit_subspace(samples, _GRAPH, 2, Fixed(2), 3, "axes").basis
    central = subspace.baseline(samples, "central", 2, init="axes", outer=3).as_matrix(0)
    truth = metrics.truth_table(spark, central)
    n = samples.count()
    lost = metrics.objective(subspace.centred(moments.local_scatter(samples)), basis).select("node", (F.col("lost") / n).alias("lost"))
    out = metrics.subspace_error(basis, truth).join(lost, "node").join(metrics.orthonormality_defect(basis), "node").join(metrics.distance_to_central(basis, truth).withColumnRenamed("distance", "from_central"), "node")
    return out.crossJoin(metrics.disagreement(basis)).select("node", *[r6(F.col(c)).alias(c) for c in ("error", "lost", "defect", "from_central", "disagreement")])


def _traced_sql() -> str:
    c = Chain(10, 64, 0.5, _SEED)
    central = c.central(6)
    parts = []
    for t, plan in enumerate(([1], [1, 3], [1, 3, 5])):
        q = c.row_split(plan)
        cross = c.add(f"SELECT q.node, sum(s * s) AS s FROM (SELECT q.node, q.k AS a, p.k AS b, sum(q.v * p.v) AS s FROM {q} q JOIN {central} p ON p.i = q.i GROUP BY q.node, q.k, p.k) q GROUP BY q.node")
        parts.append(f"SELECT {t} AS t, {sum(plan)} AS inner_total, node, round(1 - s / 2, 6) + 0e0 AS error FROM {cross}")
    return f"WITH {', '.join(c.parts)} SELECT CAST(t AS INT) AS t, CAST(inner_total AS BIGINT) AS inner_total, CAST(node AS INT) AS node, error FROM ({' UNION ALL '.join(parts)})"


@query(_traced_sql)
def flagship(spark, sf_dir):
    """Row-split estimation with ramped rounds: every node's error at every step, towards a far central iterate."""
    samples = _ten(spark, sf_dir)
    truth = subspace.baseline(samples, "central", 2, init="axes", outer=6).as_matrix(0)
    trace = subspace.rowsplit_subspace(samples, _GRAPH, 2, Ramp(2), 3, "axes", truth=truth).trace
    return trace.select("t", "inner_total", "node", r6(F.col("error")).alias("error"))


@query("SELECT o.mode, CAST(i AS INT) AS option, true AS same FROM (VALUES ('fused', 0), ('fused', 1), ('fused', 2), ('fused', 3), ('fused', 4), ('spread', 1), ('spread', 2), ('streamed', 0), ('streamed', 1), ('streamed', 2)) o(mode, i)")
def modes_agree(spark, sf_dir):
    """Whether other modes than the resident (row split) and cross (column split) ones give its bases, traces, last
    step and cost under stops, weights by node and centring."""
    x = partition.skewed(features.embeddings(spark, sf_dir), 10)
    options = [{"truth": np.eye(64)[:, :2]}, {"stop": stopping.subspace_change(0.2)}, {"local_scale": "mean"}, {"stop": stopping.message_budget(30), "every": 2}, {"center": "none", "stop": stopping.rayleigh_residual(0.01)}]
    rows = []

    def figures(out) -> tuple:
        trace = out.trace.orderBy("t", "node").toPandas()
        q = np.stack(out.basis.orderBy("node", "i").toPandas().q.to_list())
        return out.meta["steps"], out.cost.agg(F.sum("sends")).first()[0], trace[["t", "inner_total", "node", "error", "objective", "disagreement"]].astype(float).to_numpy(), q

    def same(a: tuple, b: tuple) -> bool:
        return a[:2] == b[:2] and all(u.shape == v.shape and np.allclose(u, v, atol=1e-7, equal_nan=True) for u, v in zip(a[2:], b[2:], strict=True))

    for i, o in enumerate(options):
        runs = {m: figures(subspace.rowsplit_subspace(x, _GRAPH, 2, Ramp(1), 3, "axes", mode=m, **o)) for m in ("resident", "fused", "spread")[: 3 if i in (1, 2) else 2]}
        rows += [(m, i, same(runs["resident"], own)) for m, own in runs.items() if m != "resident"]
    for i, o in enumerate(({"truth": np.eye(64)[:, :2]}, {"stop": stopping.subspace_change(0.2)}, {"stop": stopping.message_budget(4)})):
        runs = {m: figures(subspace.colsplit_subspace(x, _BLOCKS, _GRAPH, 2, Fixed(1), 2, "axes", mode=m, push_rounds=20, **o)) for m in ("cross", "streamed")}
        rows += [(m, i, same(runs["cross"], own)) for m, own in runs.items() if m != "cross"]
    return spark.createDataFrame(rows, "mode string, option int, same boolean")


# ---------------------------------------------------------------- methods on data of a known subspace

_AXES_SQL = "SELECT CAST(o AS INT) AS node, CAST(i AS INT) AS i, CAST(j AS INT) AS j, CASE WHEN i = j AND i < {r} THEN 1e0 ELSE 0e0 END AS p FROM range({n}) o(o), range({d}) a(i), range({d}) b(j)"
REGISTRY["row_split_tied"] = (lambda s, d: _every_node(subspace.rowsplit_subspace(shaped_nodes(s, d, tied=True), _GRAPH, 5, Ramp(1, cap=150), 180, every=180).basis), _AXES_SQL.format(n=10, r=5, d=20))
REGISTRY["fast_gradient_tracking"] = (lambda s, d: _every_node(subspace.baseline(shaped_nodes(s, d), "fast_tracking", 5, _GRAPH, outer=300, rounds_per_step=5, every=300).basis), _AXES_SQL.format(n=10, r=5, d=20))

_LOCAL_SQL = f"""WITH RECURSIVE {_STANDARD_SQL}, zn AS (SELECT CAST(k % 5 AS INT) AS node, k, i, x FROM z), mn AS (SELECT node, i, avg(x) AS m FROM zn GROUP BY node, i),
 cn AS (SELECT a.node, a.i, b.i AS j, avg((a.x - p.m) * (b.x - q.m)) AS v FROM zn a JOIN zn b ON a.k = b.k JOIN mn p ON p.node = a.node AND p.i = a.i JOIN mn q ON q.node = b.node AND q.i = b.i GROUP BY a.node, a.i, b.i),
 sq AS (SELECT 0 AS n, node, i, j, v / (SELECT sum(v) FROM cn d WHERE d.i = d.j AND d.node = cn.node) AS v FROM cn UNION ALL
  SELECT n + 1, node, i, j, v / sum(CASE WHEN i = j THEN v ELSE 0e0 END) OVER (PARTITION BY node) FROM (SELECT a.n, a.node, a.i, b.j, sum(a.v * b.v) AS v FROM sq a JOIN sq b ON a.node = b.node AND a.j = b.i AND a.n = b.n WHERE a.n < 16 GROUP BY a.n, a.node, a.i, b.j)),
 pn AS (SELECT node, i, j, v FROM sq WHERE n = 16)"""


@query(f"{_LOCAL_SQL} SELECT node, CAST(i AS INT) AS i, CAST(j AS INT) AS j, round(v, 5) + 0e0 AS p FROM pn")
def local_only(spark, sf_dir):
    """Every node alone: the leading direction of its own orders."""
    return _every_node(subspace.local_subspaces(partition.by_hash(_orders(spark, sf_dir), 5), 1), 5)


@query(f"""{_LOCAL_SQL}, av AS (SELECT i, j, avg(v) AS v FROM pn GROUP BY i, j), u AS (SELECT 0 AS n, i, j, v FROM av UNION ALL
  SELECT n + 1, i, j, v / sum(CASE WHEN i = j THEN v ELSE 0e0 END) OVER () FROM (SELECT a.n, a.i, b.j, sum(a.v * b.v) AS v FROM u a JOIN u b ON a.j = b.i AND a.n = b.n WHERE a.n < 16 GROUP BY a.n, a.i, b.j))
 SELECT CAST(i AS INT) AS i, CAST(j AS INT) AS j, round(v, 5) + 0e0 AS p FROM u WHERE n = 16""")
def one_shot_projectors(spark, sf_dir):
    """One round of talk: leading direction of the mean of the nodes' projectors."""
    return _projector(spark, subspace.one_shot_average(partition.by_hash(_orders(spark, sf_dir), 5), 1), 5)


# ---------------------------------------------------------------- using a basis

@query("""WITH x AS (SELECT vec_id, CAST(i AS INT) AS k, CAST(embedding[i + 1] AS DOUBLE) AS v FROM embeddings, range(64) r(i)), m AS (SELECT k, avg(v) AS m FROM x GROUP BY k)
 SELECT vec_id AS sample_id, k, round(v - m, 6) + 0.0 AS c FROM x JOIN m USING (k) WHERE k < 3""")
def encoded_axes(spark, sf_dir):
    """Codes of the embeddings in the basis of the first three axes, about the mean."""
    samples = features.embeddings(spark, sf_dir)
    coded = encode.encode(samples, np.eye(64)[:, :3], moments.global_moments(samples).mean)
    return coded.select("sample_id", F.posexplode("code").alias("k", "c")).select("sample_id", "k", r6(F.col("c")).alias("c"))


@query("""WITH x AS (SELECT i AS k, CAST(embedding[i + 1] AS DOUBLE) AS v FROM embeddings, range(64) r(i)), m AS (SELECT k, sum(v * v) - count(*) * avg(v) * avg(v) AS s FROM x GROUP BY k)
 SELECT round(sum(s), 5) + 0.0 AS total, round(sum(s) FILTER (WHERE k < 3), 5) + 0.0 AS kept, round(sum(s) FILTER (WHERE k >= 3), 5) + 0.0 AS lost FROM m""")
def reconstruction(spark, sf_dir):
    samples = features.embeddings(spark, sf_dir)
    out = encode.reconstruction_error(samples, np.eye(64)[:, :3], moments.global_moments(samples).mean)
    return out.select(*[r6(F.col(c), 5).alias(c) for c in ("total", "kept", "lost")])


@query("""SELECT CAST(k AS INT) AS k, round(l, 6) + 0.0 AS lambda, round(lead(l) OVER (ORDER BY k) / l, 6) + 0.0 AS ratio FROM
 (SELECT k, CASE WHEN k <= 5 THEN 1 - 0.05 * (k - 1) ELSE 0.32 - 0.16 * (k - 6) / 14 END AS l FROM range(1, 21) r(k))""")
def eigengap_table(spark, sf_dir):
    """Spectrum of the shaped samples, measured, with the ratio of neighbours."""
    values, _ = subspace.exact_subspace(shaped_nodes(spark, sf_dir), 5)
    return metrics.eigengaps(values, spark).select("k", r6(F.col("lambda")).alias("lambda"), r6(F.col("ratio")).alias("ratio"))


@query(f"""WITH s AS ({_ROUNDS_SQL}), n AS (SELECT t, o_custkey % 10 AS node, count(*) AS n FROM orders JOIN {_DAYS_SQL} AS d ON d.day = o_orderdate WHERE t < 200 AND o_custkey IS NOT NULL GROUP BY 1, 2)
 SELECT rule, round(sum(rounds * most) * 0.01, 4) + 0e0 AS makespan_s FROM s JOIN (SELECT t, max(n) AS most FROM n GROUP BY t) m ON m.t = s.t WHERE rule IN ('2t+1', '50') GROUP BY rule""")
def straggler_time(spark, sf_dir):
    """Synchronous time of the first 200 days' outer steps on ten nodes of customers: in every round a node is late by
    0.01 s for each order that it has on the day, and all wait for the latest."""
    orders = load_table(spark, sf_dir, "orders").select("o_orderdate", F.pmod("o_custkey", F.lit(10)).cast("int").alias("node")).where("node is not null")
    first = stored(_days(spark, sf_dir).where("t < 200").select("day", "t"), "days")
    work = stored(orders.join(F.broadcast(first), orders.o_orderdate == first.day).groupBy("t", "node").agg(F.count("*").alias("n")), "work")
    out = None
    for rule in ("2t+1", "50"):
        timing = cost.loaded_table(work, [RULES[rule].at(t) for t in range(200)], 0.01)
        own = cost.straggler_makespan(timing).select(F.lit(rule).alias("rule"), r6(F.col("makespan_s"), 4).alias("makespan_s"))
        out = own if out is None else out.union(own)
    return out


def _theory_sql() -> str:
    """Node norms by repeated squaring; R factors of three central steps; averaging error of twenty rounds."""
    c = Chain(10, 64, 0.5, _SEED)
    q, factors = c.axes(1), []
    for _ in range(3):
        z = c.combined((c.central_product(q), 10.0))
        first = c.unit(c.column(z, 0))
        rest = c.without(c.column(z, 1), first)
        factors.append(c.add(f"""SELECT (SELECT sqrt(sum(v * v)) FROM {z} WHERE k = 0) AS r11, (SELECT sum(z.v * f.v) FROM {z} z JOIN {first} f ON f.i = z.i WHERE z.k = 1) AS r12, (SELECT sqrt(sum(v * v)) FROM {rest}) AS r22"""))
        q = c.orthonormal(z)
    fs = c.add(" UNION ALL ".join(f"SELECT r11 * r11 + r12 * r12 + r22 * r22 AS f, r11 * r22 AS det FROM {r}" for r in factors))
    s = c.add("SELECT node, i, j, v / sum(CASE WHEN i = j THEN v ELSE 0e0 END) OVER (PARTITION BY node) AS v FROM m")
    for _ in range(14):
        s = c.add(f"SELECT node, i, j, v / sum(CASE WHEN i = j THEN v ELSE 0e0 END) OVER (PARTITION BY node) AS v FROM (SELECT a.node, a.i, b.j, sum(a.v * b.v) AS v FROM {s} a JOIN {s} b ON a.node = b.node AND a.j = b.i GROUP BY a.node, a.i, b.j)")
    norms = c.add(f"SELECT m.node, sum(m.v * s.v) AS s FROM m JOIN {s} s ON s.node = m.node AND s.i = m.i AND s.j = m.j GROUP BY m.node")
    known = c.add(f"SELECT (SELECT sum(s) FROM {norms}) AS alpha, (SELECT sqrt(sum(s * s)) FROM {norms}) AS gamma, (SELECT max(1 / sqrt((f - sqrt(f * f - 4 * det * det)) / 2)) FROM {fs}) AS beta")
    values = c.product(c.axes(c.n))
    mixed = c.mixed(values, 20)
    a = c.anchor(20)
    columns = c.mixed(c.add(f"SELECT CAST(n AS INT) AS node, CAST(i AS INT) AS i, 0 AS k, CASE WHEN n = i THEN 1e0 ELSE 0e0 END AS v FROM range({c.n}) n(n), range({c.n}) i(i)"), 20)
    delta = c.add(f"SELECT max(abs(p.v / a.v - 1)) AS s FROM {columns} p JOIN {a} a ON a.node = p.node")
    error = c.add(f"SELECT max(s) AS s FROM (SELECT z.node, sqrt(sum((z.v / a.v - t.v) ** 2)) AS s FROM {mixed} z JOIN {a} a ON a.node = z.node JOIN (SELECT i, k, sum(v) AS v FROM {values} GROUP BY i, k) t ON t.i = z.i AND t.k = z.k GROUP BY z.node)")
    size = c.add(f"SELECT sqrt(sum(s * s)) AS s FROM (SELECT sum(abs(v)) AS s FROM {values} GROUP BY i, k)")
    grow = "ln(1 / (3 * alpha * sqrt(2) * beta))"
    rows = {
        "alpha": "alpha", "beta": "beta", "gamma": "gamma", "log_delta_fixed": f"ln(alpha / (gamma * sqrt(2))) + 4 * 3 * {grow} + 3 * ln(0.5)",
        "log_delta_ramp_1": f"ln(alpha / (gamma * sqrt(2))) + 4 * 2 * {grow} + 3 * ln(0.5)", "outer_for_1e-8": "ceil(ln(1e8) / ln(1 / 0.4))", "bound_fixed_20": "0.4 ** 20 + 3 * 0.5 ** 20",
        "bound_ramp_20": "0.4 ** 20 + 2 * 0.5 ** 20", "push_rounds_1e-8": "ceil(ln(10) + ln(1e8))", "flops_row": "20 * 20 * 5 * 10 + 5 * 5 * 20 * 10", "flops_column": "500 * 20 * 5 + 25 * log2(10) + 25 * 20 / 10",
        "averaging_error": f"(SELECT s FROM {error})", "averaging_bound": f"(SELECT s FROM {delta}) * (SELECT s FROM {size})", "within": f"CASE WHEN (SELECT s FROM {error}) <= (SELECT s FROM {delta}) * (SELECT s FROM {size}) THEN 1 ELSE 0 END",
        "volume_row": "2 * (SELECT count(*) FROM e) * 9375 * 20 * 5", "volume_column": "2 * (SELECT count(*) FROM e) * (9375 * 500 * 5 + 200 * 50 * 25)",
    }
    return f"WITH {', '.join(c.parts)} " + " UNION ALL ".join(f"SELECT '{k}' AS measure, round(CAST({v} AS DOUBLE), 5) + 0e0 AS value FROM {known}" for k, v in rows.items())


@query(_theory_sql)
def theory_report(spark, sf_dir):
    """Constants of the analysis on the embeddings' node matrices, its closed forms, and both sides of the averaging
    inequality."""
    from meshspan.operators import theory

    m, q0 = workloads.node_matrices(_ten(spark, sf_dir), 10, 64), np.eye(64)[:, :2]
    c = theory.theory_constants(m, q0, 3)
    w = _GRAPH.weights()
    error, bound = theory.averaging_bound(m @ q0, w, 20)
    plan = [RULES["2t+1"].at(t) for t in range(200)]
    rows = {
        **c, "log_delta_fixed": theory.log_delta("fixed", c, 2, 3, 0.5), "log_delta_ramp_1": theory.log_delta("ramp", c, 2, 3, 0.5, 1), "outer_for_1e-8": theory.outer_needed(0.4, 1e-8),
        "bound_fixed_20": theory.theorem_bound(0.4, 20, 1.0), "bound_ramp_20": theory.theorem_bound(0.4, 20, 1.0, "ramp"), "push_rounds_1e-8": theory.push_rounds_needed(10, 1e-8),
        "flops_row": cost.flop_model("row", 500, 20, 5, 10), "flops_column": cost.flop_model("column", 500, 20, 5, 10), "averaging_error": error.max(), "averaging_bound": bound, "within": error.max() <= bound,
        "volume_row": cost.volume_model("row", _GRAPH, plan, 500, 20, 5), "volume_column": cost.volume_model("column", _GRAPH, plan, 500, 20, 5),
    }
    return spark.createDataFrame([(k, float(v)) for k, v in rows.items()], "measure string, value double").withColumn("value", r6(F.col("value"), 5))


@query("""WITH x AS (SELECT vec_id, label, CAST(i AS INT) AS i, CAST(embedding[i + 1] AS DOUBLE) AS v FROM embeddings, range(64) r(i) WHERE label IS NOT NULL), c AS (SELECT label AS guess, i, avg(v) AS m FROM x GROUP BY label, i),
 d AS (SELECT x.vec_id, max(x.label) AS label, guess, sum((v - m) * (v - m)) AS far FROM x JOIN c ON c.i = x.i GROUP BY x.vec_id, guess) SELECT round(avg(CASE WHEN guess = label THEN 1e0 ELSE 0e0 END), 6) + 0e0 AS accuracy, count(*) AS n FROM (SELECT vec_id, max(label) AS label, arg_min(guess, far) AS guess FROM d GROUP BY vec_id)""")
def nearest_centroids(spark, sf_dir):
    """Accuracy of the nearest label centroid on the plain embeddings."""
    return encode.nearest_centroid_accuracy(features.embeddings(spark, sf_dir).where("label is not null"), "label", "features").withColumn("accuracy", r6(F.col("accuracy")))


# ---------------------------------------------------------------- supporting operators


@query("SELECT n_nationkey AS node, count(c_custkey) AS customers, round(coalesce(avg(c_acctbal), 0), 4) + 0.0 AS mean_balance FROM nation LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY n_nationkey")
def nodes_with_customers(spark, sf_dir):
    """Left join: nodes without rows keep a zero."""
    n, c = load_table(spark, sf_dir, "nation"), load_table(spark, sf_dir, "customer").select("c_nationkey", "c_custkey", "c_acctbal")
    agg = c.groupBy("c_nationkey").agg(F.count("*").alias("customers"), F.avg("c_acctbal").alias("m"))
    return n.select(F.col("n_nationkey").alias("node")).join(agg, F.col("node") == F.col("c_nationkey"), "left").select("node", F.coalesce("customers", F.lit(0)).alias("customers"), r6(F.coalesce("m", F.lit(0.0)), 4).alias("mean_balance"))


@query("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def labelled_documents(spark, sf_dir):
    return load_table(spark, sf_dir, "documents").select("doc_id", "lang").join(load_table(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_semi")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def customers_without_orders(spark, sf_dir):
    return load_table(spark, sf_dir, "customer").select("c_custkey").join(load_table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@query("""WITH n AS (SELECT count(*) AS n FROM embeddings), b AS (SELECT i AS node, i * n // 7 AS lo, (i + 1) * n // 7 AS hi FROM range(7) r(i), n)
 SELECT CAST(node AS INT) AS node, count(*) AS n, min(vec_id) AS first_id FROM embeddings JOIN b ON vec_id >= lo AND vec_id < hi GROUP BY node""")
def contiguous_nodes(spark, sf_dir):
    """Range join of ids with the nodes' bounds."""
    e = load_table(spark, sf_dir, "embeddings").select("vec_id")
    n = e.count()
    bounds = spark.createDataFrame([(i, i * n // 7, (i + 1) * n // 7) for i in range(7)], "node int, lo long, hi long")
    return e.join(F.broadcast(bounds), (F.col("vec_id") >= F.col("lo")) & (F.col("vec_id") < F.col("hi"))).groupBy("node").agg(F.count("*").alias("n"), F.min("vec_id").alias("first_id"))


@query("""SELECT e.event_id, p.event_id AS last_purchase FROM events e ASOF LEFT JOIN (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND e.ts >= p.ts
 WHERE e.event_type <> 'purchase'""")
def last_purchase(spark, sf_dir):
    """As-of join as one window over one shuffle: each event with its user's latest purchase before it."""
    e = load_table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    bought = F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))
    return e.withColumn("p", F.max(bought).over(w)).where("event_type <> 'purchase'").select("event_id", F.col("p.event_id").alias("last_purchase"))


@query("""SELECT node, CAST(t AS INT) AS t FROM (SELECT o_custkey AS node, count(*) AS k FROM orders GROUP BY 1) v, LATERAL (SELECT unnest(range(k)) AS t)""")
def lateral_schedule(spark, sf_dir):
    """A step for every order of a customer."""
    v = load_table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("node")).agg(F.count("*").cast("int").alias("k"))
    v.createOrReplaceTempView("_meshspan_nodes")
    return spark.sql("SELECT node, t FROM _meshspan_nodes, LATERAL (SELECT explode(sequence(0, k - 1)) AS t)")


@query("""SELECT l_returnflag, l_linestatus, grouping(l_returnflag) + 2 * grouping(l_linestatus) AS level, count(*) AS n, round(avg(l_quantity), 6) + 0.0 AS mean FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)""")
def quantity_cube(spark, sf_dir):
    t = load_table(spark, sf_dir, "lineitem")
    return t.cube("l_returnflag", "l_linestatus").agg((F.grouping("l_returnflag").cast("long") + 2 * F.grouping("l_linestatus").cast("long")).alias("level"), F.count("*").alias("n"), r6(F.avg("l_quantity")).alias("mean"))


@query("""SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())""")
def document_sets(spark, sf_dir):
    load_table(spark, sf_dir, "documents").createOrReplaceTempView("_meshspan_documents")
    return spark.sql("SELECT lang, source, count(*) AS n FROM _meshspan_documents GROUP BY GROUPING SETS ((lang), (source), ())")


_MOST_KINDS = 10_000


@query("""SELECT user_id, kind, n FROM (SELECT user_id, event_type AS kind, count(*) AS n FROM events GROUP BY 1, 2)""")
def event_pivot(spark, sf_dir):
    """Pivot by a literal value list and back: the same counts."""
    e = load_table(spark, sf_dir, "events").select("user_id", "event_type")
    kinds = sorted(r[0] for r in e.select("event_type").where("event_type is not null").distinct().limit(_MOST_KINDS + 1).collect())
    if len(kinds) > _MOST_KINDS:
        raise ValueError(f"over {_MOST_KINDS} kinds are too many columns: keep the long form")
    wide = e.groupBy("user_id").pivot("event_type", kinds).count()
    return wide.unpivot(["user_id"], kinds, "kind", "n").where("n is not null")


@query("""SELECT label, CAST(i AS INT) AS i, round(quantile_cont(x, 0.5), 6) + 0.0 AS median, round(quantile_cont(x, 0.9), 6) + 0.0 AS p90 FROM (SELECT label, i, CAST(embedding[i + 1] AS DOUBLE) AS x FROM embeddings, range(64) r(i)) GROUP BY label, i""")
def spread_by_label(spark, sf_dir):
    e = features.embeddings(spark, sf_dir).select("label", F.posexplode("features").alias("i", "x"))
    return e.groupBy("label", "i").agg(r6(F.percentile("x", F.lit(0.5))).alias("median"), r6(F.percentile("x", F.lit(0.9))).alias("p90"))


@query("""SELECT vec_id, label, CAST(ntile(4) OVER (PARTITION BY label ORDER BY vec_id) - 1 AS INT) AS node FROM embeddings""")
def balanced_nodes(spark, sf_dir):
    e = features.embeddings(spark, sf_dir, 1)
    return partition.ranked(e, 4, "label").select(F.col("sample_id").alias("vec_id"), "label", F.col("node").cast("int").alias("node"))


@query("""SELECT o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS nth, lag(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS before,
 round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) + 0.0 AS rolling FROM orders""")
def order_windows(spark, sf_dir):
    o = load_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate", "o_totalprice")
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return o.select("o_orderkey", F.row_number().over(w).cast("long").alias("nth"), F.lag("o_totalprice").over(w).alias("before"), r6(F.avg("o_totalprice").over(w.rowsBetween(-2, 0)), 4).alias("rolling"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def top_orders(spark, sf_dir):
    return load_table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@query(f"""WITH e AS ({_drawn_sql(0.25)}), f AS ({_drawn_sql(0.5)}) SELECT 'both' AS part, count(*) AS n FROM (SELECT * FROM e INTERSECT SELECT * FROM f)
 UNION ALL SELECT 'only_dense', count(*) FROM (SELECT * FROM f EXCEPT SELECT * FROM e) UNION ALL SELECT 'either', count(*) FROM (SELECT * FROM e UNION SELECT * FROM f)""")
def graph_sets(spark, sf_dir):
    pairs = _traffic(spark, sf_dir)
    e, f = topology.drawn_edges(pairs, 0.25, 1), topology.drawn_edges(pairs, 0.5, 1)
    parts = {"both": e.intersect(f), "only_dense": f.exceptAll(e), "either": e.union(f).distinct()}
    out = None
    for name, df in parts.items():
        own = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("part"), "n")
        out = own if out is None else out.union(own)
    return out


@query("""SELECT user_id, CAST(time_bucket(INTERVAL 1 DAY, ts) AS TIMESTAMP) AS day, count(*) AS n, round(sum(value), 4) + 0.0 AS total FROM events GROUP BY 1, 2""")
def daily_activity(spark, sf_dir):
    e = load_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return incremental.windowed_activity(e).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("day"), "n", r6(F.col("total"), 4).alias("total"))


@query("""WITH o AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o)
 SELECT user_id, min(ts) AS start_ts, count(*) AS n FROM s GROUP BY user_id, k""")
def activity_sessions(spark, sf_dir):
    e = load_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return incremental.sessions(e).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start_ts"), "n")


@query("""SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events WHERE CAST(json_extract(props, '$.k') AS BIGINT) % 2 = 0""")
def event_properties(spark, sf_dir):
    e = load_table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))
    return e.where("k % 2 = 0")


@query("SELECT a.vec_id AS a, b.vec_id AS b, round(list_dot_product(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) + 0.0 AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def neighbour_products(spark, sf_dir):
    """Dot products in SQL expressions."""
    e = features.embeddings(spark, sf_dir)
    other = e.select((F.col("sample_id") - 1).alias("a"), F.col("sample_id").alias("b"), F.col("features").alias("y"))
    return e.join(other, F.col("sample_id") == F.col("a")).select("a", "b", r6(vec_dot(F.col("features"), F.col("y"))).alias("dot"))


@query(f"SELECT lang, count(DISTINCT w) AS words FROM (SELECT lang, unnest(regexp_split_to_array(lower(coalesce(text, '')), '\\s+')) AS w FROM documents) WHERE w <> '' GROUP BY lang")
def vocabulary(spark, sf_dir):
    """Distinct tokens per language: how wide a hashed bag of words is worth being."""
    d = load_table(spark, sf_dir, "documents").select("lang", F.explode(F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+")).alias("w")).where("w <> ''")
    return d.distinct().groupBy("lang").agg(F.count("*").alias("words"))


@query()
def approximate_vocabulary(spark, sf_dir):
    d = load_table(spark, sf_dir, "documents").select("lang", F.explode(F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+")).alias("w")).where("w <> ''")
    return d.groupBy("lang").agg(F.approx_count_distinct("w", 0.02).alias("words"))


@query()
def sampled_start(spark, sf_dir):
    """Warm start: row split begun from the subspace of a stratified sample of the rows."""
    samples = shaped_nodes(spark, sf_dir, delta=0.7)
    warm = subspace.exact_subspace(samples.sampleBy("node", {k: 0.2 for k in range(10)}, 3), 5)[1]
    out = subspace.rowsplit_subspace(samples, _GRAPH, 5, Ramp(2), 60, init=warm, truth=np.eye(20)[:, :5])
    return metrics.convergence(out.trace)


# ---------------------------------------------------------------- experiments


def _degree_sql(graph: str, n: int) -> str:
    if graph == "ring":
        return "2e0"
    if graph == "star":
        return f"2e0 * {n - 1} / {n}"
    seed = topology.erdos_renyi(n, float(graph[3:])).kind.split("seed=")[1][:-1]
    return f"(SELECT 2e0 * count(*) / {n} FROM ({edges_sql(n, float(graph[3:]), int(seed))}))"


def _grid_sql(work: workloads.Workload) -> str:
    """Exact counts of every setting from the edges of its graph and its rule, and that it shows what was reported."""
    rows, graphs = [], {}
    for c in work.grid:
        graphs.setdefault((c["graph"], c["nodes"]), f"g{len(graphs)}")
        known = "NULL" if work.claim is workloads.natural and c["method"] == "tracking" else "true"
        rule = c.get("rule", "-")
        rows.append(f"('{c['setting']}', '{c['method']}', '{rule}', '{rule if rule in RULES else 50}', {c['nodes']}, {c['rank']}, {c['outer']}, {c.get('mix', 3)}, '{graphs[c['graph'], c['nodes']]}', CAST({known} AS BOOLEAN))")
    degrees = ", ".join(f"('{name}', {_degree_sql(g, n)})" for (g, n), name in graphs.items())
    total = "(SELECT sum(rounds) FROM s WHERE s.rule = c.plan AND s.t < {steps})"
    return f"""WITH s AS MATERIALIZED ({_ROUNDS_SQL}), d(graph, degree) AS MATERIALIZED (VALUES {degrees}), c(setting, method, rule, plan, nodes, rank, outer_steps, mix, graph, holds) AS (VALUES {', '.join(rows)}),
 n AS (SELECT c.*, CAST(CASE WHEN method IN ('row', 'column') THEN {total.format(steps='c.outer_steps')} WHEN method IN ('sequential', 'column_sequential') THEN rank * {total.format(steps='c.outer_steps // c.rank')}
  WHEN method = 'central_sequential' THEN rank * (outer_steps // rank) WHEN method = 'tracking' THEN mix * outer_steps ELSE outer_steps END AS BIGINT) AS inner_total FROM c)
 SELECT setting, method, rule, CAST(nodes AS INT) AS nodes, CAST(rank AS INT) AS rank, CAST(outer_steps AS INT) AS outer_steps, inner_total, CASE WHEN method LIKE 'central%' THEN 0e0 ELSE round(degree * inner_total / 1000, 6) END AS p2p_k, holds FROM n JOIN d USING (graph)"""


for _name, _work in workloads.GRIDS.items():
    REGISTRY[_name] = (_work.checked, lambda work=_work: _grid_sql(work))
REGISTRY["w5_stragglers"] = (
    workloads.w5_stragglers,
    f"""WITH s AS ({_ROUNDS_SQL}) SELECT CAST(nodes AS INT) AS nodes, CAST(p AS DOUBLE) AS p, rule, CAST(sum(rounds) AS BIGINT) AS rounds_total, round(sum(rounds) * 0.01, 4) + 0e0 AS makespan_s,
 CAST(sum(rounds) FILTER (WHERE t < 5) AS BIGINT) AS rounds_run, true AS holds FROM s, (VALUES (10, 0.5), (20, 0.25)) v(nodes, p) WHERE t < 200 AND rule IN ('2t+1', '50') GROUP BY nodes, p, rule""",
)
for _name in ("w14_downstream", "w15_monte_carlo"):
    REGISTRY[_name] = (workloads.WORKLOADS[_name], None)


def queries() -> dict[str, Query]:
    return {name: f for name, (f, _) in REGISTRY.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql() if callable(sql) else sql for name, (_, sql) in REGISTRY.items() if sql}
