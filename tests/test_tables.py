"""Queries on networks and schedules take their nodes, links and steps from the given tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from meshspan.operators import topology
from meshspan.plans import queries
from meshspan.plans.schedules import RULES, rounds
from meshspan.sources.tables import load_table

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def changed(spark, tmp_path_factory):
    """Tables of which half the rows are left out."""
    where = str(tmp_path_factory.mktemp("half"))
    for name, key in (("lineitem", "l_orderkey"), ("orders", "o_orderkey")):
        load_table(spark, SF, name).where(F.crc32(F.col(key).cast("string")) % 2 == 0).write.parquet(f"{where}/{name}.parquet")
    return where


def differs(spark, changed, name):
    """Whether the query's rows depend on the rows of its table."""
    run = queries.queries()[name]
    return sorted(run(spark, SF).collect()) != sorted(run(spark, changed).collect())


def drawn(spark, p=0.25, n=20, seed=1):
    """Edges of the drawn network by brute force."""
    import hashlib
    from collections import Counter

    pairs = Counter()
    for r in load_table(spark, SF, "lineitem").select("l_partkey", "l_suppkey").collect():
        a, b = r[0] % n, r[1] % n
        if a != b:
            pairs[min(a, b), max(a, b)] += 1
    return {e for e, c in pairs.items() if int(hashlib.md5(f"{seed}|{e[0]}|{e[1]}|{c}".encode()).hexdigest()[:8], 16) / (1 << 32) < p}


def test_random_graph_is_drawn_among_nodes_that_exchange_lines(spark, changed):
    got = {(r["src"], r["dst"]) for r in queries.queries()["random_graph_edges"](spark, SF).collect()}
    assert got and got == drawn(spark) and differs(spark, changed, "random_graph_edges")


def test_traffic_leaves_out_loops_and_missing_keys(spark):
    rows = spark.createDataFrame([(1, 2), (22, 1), (3, 23), (None, 4), (5, None)], "a long, b long")
    assert [tuple(r) for r in topology.traffic(rows, "a", "b", 20).collect()] == [(1, 2, 2)]
    assert topology.traffic(rows.limit(0), "a", "b", 20).count() == 0


def test_graph_sets_compare_drawn_networks(spark):
    e, f = drawn(spark), drawn(spark, 0.5)
    got = {r["part"]: r["n"] for r in queries.queries()["graph_sets"](spark, SF).collect()}
    assert got == {"both": len(e & f), "only_dense": len(f - e), "either": len(e | f)}


def test_messages_per_node_follow_the_drawn_network(spark, changed):
    degree = np.bincount(np.array(sorted(drawn(spark))).ravel(), minlength=20)
    rows = queries.queries()["messages_per_node"](spark, SF).where("graph = 'random' and rule = '2t+1'").collect()
    assert {r["node"]: r["sends"] for r in rows} == {i: 9375 * int(g) for i, g in enumerate(degree) if g}
    assert differs(spark, changed, "messages_per_node")


def test_message_report_follows_the_drawn_network(spark):
    degree = np.bincount(np.array(sorted(drawn(spark))).ravel(), minlength=20)
    row = queries.queries()["message_report"](spark, SF).where("graph = 'random' and rule = '50'").first()
    assert row["n"] == (degree > 0).sum() and row["sends"] == pytest.approx(10_000 * degree[degree > 0].mean(), abs=1e-4)


def weights(spark):
    edges = drawn(spark)
    degree = np.bincount(np.array(sorted(edges)).ravel(), minlength=20)
    w = np.zeros((20, 20))
    for i, j in edges:
        w[i, j] = w[j, i] = 1 / max(degree[i], degree[j])
    return w + np.diag(1 - w.sum(1))


def test_weights_follow_the_drawn_network(spark):
    w, got = weights(spark), np.zeros((20, 20))
    for r in queries.queries()["local_degree_weights"](spark, SF).collect():
        got[r["src"], r["dst"]] = r["w"]
    assert np.allclose(got, w, atol=1e-6)


def test_weight_sums_read_lineitem(spark):
    run = queries.queries()["weight_sums"]
    assert [tuple(r) for r in run(spark, SF).orderBy("node").collect()] == [(i, 1.0, 1.0) for i in range(20)]
    with pytest.raises(Exception, match="lineitem"):
        run(spark, SF + "/missing").collect()


def test_anchor_entries_follow_the_drawn_network(spark, changed):
    got = {r["node"]: (r["anchor"], r["unreached"]) for r in queries.queries()["anchor_entries"](spark, SF).collect()}
    column = np.linalg.matrix_power(weights(spark), 2)[:, 0]
    assert all(got[i] == (pytest.approx(column[i], abs=1e-6), column[i] < 1e-12) for i in range(20)) and len(got) == 20
    assert differs(spark, changed, "anchor_entries")


def test_schedule_has_a_step_per_day_with_orders(spark):
    days = sorted(r[0] for r in load_table(spark, SF, "orders").select("o_orderdate").distinct().collect())
    rows = queries.queries()["schedule_rounds"](spark, SF).where("rule = 't+1'").orderBy("t").collect()
    assert [r["rounds"] for r in rows] == rounds(RULES["t+1"], len(days)) and rows[-1]["inner_total"] == sum(rounds(RULES["t+1"], len(days)))
    assert sum(r["orders"] for r in rows) == load_table(spark, SF, "orders").count()


def test_straggler_time_waits_for_the_busiest_node(spark):
    from collections import Counter

    rows = load_table(spark, SF, "orders").select("o_orderdate", "o_custkey").collect()
    at = {d: t for t, d in enumerate(sorted({r[0] for r in rows}))}
    busy = Counter((at[r[0]], r[1] % 10) for r in rows)
    most = {t: max(busy[t, n] for n in range(10)) for t in range(min(200, len(at)))}
    got = {r["rule"]: r["makespan_s"] for r in queries.queries()["straggler_time"](spark, SF).collect()}
    assert got == {k: pytest.approx(sum(RULES[k].at(t) * m for t, m in most.items()) * 0.01, abs=1e-4) for k in ("2t+1", "50")}


def test_star_messages_of_customers_and_orders(spark):
    keys = [r[0] for r in load_table(spark, SF, "orders").select("o_custkey").collect()]
    got = {r["role"]: (r["nodes"], r["sends"]) for r in queries.queries()["star_messages"](spark, SF).collect()}
    assert got == {"centre": (len(set(keys)), pytest.approx(9375 * len(keys) / len(set(keys)), abs=1e-4)), "edge": (len(keys), 9375.0)}


def test_lateral_schedule_has_a_step_per_order(spark):
    from collections import Counter

    k = Counter(r[0] for r in load_table(spark, SF, "orders").select("o_custkey").collect())
    got = sorted(tuple(r) for r in queries.queries()["lateral_schedule"](spark, SF).collect())
    assert got == sorted((c, t) for c, n in k.items() for t in range(n))


def test_published_messages_follow_drawn_networks(spark, changed):
    rows = {(r["tab"], r["config"], r["rule"]): r for r in queries.queries()["published_messages"](spark, SF).collect()}
    assert len(rows) == len(queries.PUBLISHED)
    for at, (n, p, seed) in queries.NETWORKS.items():
        row = rows[(*at, "2t+1")]
        assert row["degree"] == pytest.approx(2 * len(drawn(spark, p, n, seed)) / n, abs=1e-6)
        assert row["p2p_k"] == pytest.approx(row["degree"] * sum(rounds(RULES["2t+1"], row["outer_steps"])) / 1000, abs=1e-3)
    assert differs(spark, changed, "published_messages")
