"""One behaviour in all modes: bases, traces, stops and costs do not depend on the plan."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from meshspan.operators import moments, nodes, partition, subspace, topology
from meshspan.plans import stopping
from meshspan.plans.queries import shaped_nodes
from meshspan.plans.schedules import Fixed, Ramp
from meshspan.sources import features
from tests.conftest import SF

GRAPH = topology.erdos_renyi(5, 0.6)


def figures(out):
    trace = out.trace.orderBy("t", "node").toPandas()
    return trace, np.stack(out.basis.orderBy("node", "i").toPandas().q.to_list()), out.meta["steps"], out.meta["rounds"], out.cost.agg(F.sum("sends")).first()[0]


def agree(a, b):
    (trace_a, q_a, *rest_a), (trace_b, q_b, *rest_b) = a, b
    assert rest_a == rest_b
    assert np.allclose(q_a, q_b, atol=1e-9)
    for c in ("t", "inner_total", "node", "error", "objective", "disagreement"):
        assert np.allclose(trace_a[c].astype(float), trace_b[c].astype(float), atol=1e-8, equal_nan=True), c


@pytest.fixture(scope="module")
def samples(spark):
    return partition.skewed(features.shaped(features.embeddings(spark, SF, 8), 3, 0.4), 5).cache()


@pytest.mark.parametrize(
    "options",
    [
        {}, {"truth": np.eye(8)[:, :3], "every": 2}, {"local_scale": "mean", "truth": "exact"}, {"stop": stopping.subspace_change(0.05)}, {"stop": stopping.rayleigh_residual(0.2), "every": 3},
        {"stop": stopping.disagreement(0.2), "every": 2}, {"stop": stopping.message_budget(20), "center": "exact"}, {"center": "none"}, {"center": "consensus"},
    ],
)
def test_row_modes(samples, options):
    modes = ("resident", "fused", "spread") if options.keys() in ({"truth", "every"}, {"local_scale", "truth"}, {"stop"}) else ("resident", "fused")
    runs = [figures(subspace.rowsplit_subspace(samples, GRAPH, 3, Ramp(2), 4, mode=mode, **options)) for mode in modes]
    for other in runs[1:]:
        agree(runs[0], other)


def test_literal_rounds(samples):
    runs = [figures(subspace.rowsplit_subspace(samples, GRAPH, 3, Fixed(2), 2, mode=mode, truth="exact")) for mode in ("resident", "literal")]
    agree(*runs)


@pytest.mark.parametrize("options", [{"truth": np.eye(8)[:, :3]}, {"stop": stopping.subspace_change(0.05)}, {"stop": stopping.message_budget(10), "qr": "mgs"}, {"center": "none"}])
def test_column_modes(spark, samples, options):
    blocks, graph = partition.column_blocks(8, 4, "round_robin"), topology.erdos_renyi(4, 0.6)
    plain = samples.withColumn("features", F.transform("features", lambda v: v + 0.5))
    modes = ("cross", "streamed", "literal") if "qr" not in options else ("cross", "streamed")
    runs = [figures(subspace.colsplit_subspace(plain, blocks, graph, 3, Fixed(2), 3, mode=mode, push_rounds=20, **options)) for mode in modes]
    for other in runs[1:]:
        agree(runs[0], other)


@pytest.mark.parametrize("name", subspace.BASELINES)
def test_baselines_fused(samples, name):
    runs = [subspace.baseline(samples, name, 3, GRAPH, Fixed(5), 6, truth="exact", mode=mode) for mode in ("resident", "fused")]
    a, b = (r.trace.orderBy("t", "node").toPandas() for r in runs)
    assert np.allclose(a[["error", "objective"]], b[["error", "objective"]], atol=1e-9)


def test_cost_is_of_what_ran(samples):
    out = subspace.rowsplit_subspace(samples, GRAPH, 3, Fixed(3), 50, stop=stopping.max_outer(4))
    assert out.meta["steps"] == 4 and out.meta["rounds"] == 12
    assert out.cost.agg(F.sum("sends")).first()[0] == 2 * len(GRAPH.edges) * 12


def test_fused_without_truth_has_a_trace(samples):
    trace = subspace.rowsplit_subspace(samples, GRAPH, 3, Fixed(3), 4, mode="fused").trace.toPandas()
    assert len(trace) == 4 * 5 and trace.objective.notna().all() and trace.disagreement.notna().all()


def test_pieces_in_either_form(spark, monkeypatch):
    """Rows, matrices, flushes and salts give the same moments; pieces are no larger than the smaller form."""
    d = 12
    wide = partition.skewed(features.embeddings(spark, SF, d), 4).repartition(6).cache()
    m = moments.stacked(moments.local_scatter(wide).toPandas())[1]
    for flush, piece in ((256 << 20, 4 << 20), (2000, 400)):
        monkeypatch.setattr(nodes, "FLUSH_BYTES", flush)
        monkeypatch.setattr(nodes, "PIECE_BYTES", piece)
        table = nodes.node_pieces(wide, 4, d)
        assert np.allclose(table.local().matrices, m)
        assert np.allclose(nodes.SpreadNodes(table).apply(np.broadcast_to(np.eye(d), (4, d, d))), m)
        assert table.bytes <= 4 * d * d * 8 * 1.5
    few = partition.by_hash(wide.where("sample_id < 30"), 40)
    table = nodes.node_pieces(few, 40, d)
    local, spread = table.local(), nodes.SpreadNodes(table)
    assert local.rows is not None
    q = np.random.default_rng(1).standard_normal((40, d, 2))
    assert np.allclose(local.apply(q), spread.apply(q)) and np.allclose(local.kept(q), spread.kept(q)) and np.allclose(local.total, spread.total)
    assert local.trace == pytest.approx(spread.trace) and np.allclose(local.leading(3)[0], spread.leading(3)[0])
    q = q[0]
    assert np.allclose(local.mean_apply(q), spread.mean_apply(q))


def test_ragged_and_null_vectors_are_errors(spark):
    for rows in ([[1.0, 2.0], [1.0]], [[1.0, 2.0], None], [[1.0, 2.0], [None, 1.0]]):
        df = spark.createDataFrame([(i, 0, v) for i, v in enumerate(rows)], "sample_id long, node int, features array<double>").coalesce(1)
        with pytest.raises(Exception, match="vector"):
            nodes.node_pieces(df, 1, 2)


def test_no_exchange_over_the_pieces(spark, samples):
    table = nodes.node_pieces(samples, 5, 8)
    m = nodes.SpreadNodes(table)
    assert "Exchange" not in m.df._jdf.queryExecution().executedPlan().toString()
    pieces = subspace.stored_by(table.df, "node", 8)
    bases = spark.createDataFrame([(i, np.eye(8)[:, :2].tobytes()) for i in range(5)], "node int, q binary")
    plan = subspace.spread_product(pieces, bases, table, 2)._jdf.queryExecution().executedPlan().toString()
    over = [line for line in plan.splitlines() if "Exchange" in line]
    assert len(over) == 1, plan  # the bases alone are sent to the buckets


def test_shaped_nodes_keep_their_size(spark):
    assert shaped_nodes(spark, SF, n=5, d=8, r=3).select("node").distinct().count() == 5
