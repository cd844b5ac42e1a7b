"""Modes against each other, reductions, invariants, the published counts and the reported behaviour."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from meshspan.functions import linalg
from meshspan.operators import consensus, cost, encode, loops, metrics, moments, partition, subspace, theory, topology
from meshspan.plans import stopping, workloads
from meshspan.plans.api import MeshSpan
from meshspan.plans.queries import PUBLISHED, shaped_nodes
from meshspan.plans.schedules import RULES, Explicit, Fixed, Ramp, TheorySchedule, rounds
from meshspan.sources import features, tables

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def nodes():
    """Node matrices with an exact diagonal mean: the truth is the first axes."""
    x = np.random.default_rng(3).standard_normal((400, 12))
    x -= x.mean(0)
    values, vectors = np.linalg.eigh(x.T @ x / len(x))
    x = x @ vectors / np.sqrt(values) * np.sqrt(features.spectrum(12, 4, 0.5))
    m = np.stack([x[i::8].T @ x[i::8] * 8 / len(x) for i in range(8)])
    return m, np.eye(12)[:, :4]


def last(steps):
    out = None
    for out in steps:
        pass
    return out


# ---------------------------------------------------------------- published counts


def test_round_totals():
    total = lambda rule, outer=200: sum(rounds(RULES[rule], outer))
    assert [total(k) for k in ("half_floor", "half_ceil", "t+1", "2t+1", "50")] == [7550, 7599, 8775, 9375, 10000]
    assert [total("t+1", 400), total("2t+1", 400), total("50", 400)] == [18775, 19375, 20000]
    assert [total("5t+1,200"), total("2t+1,100"), total("5t+1,100"), total("100")] == [35940, 17500, 18970, 20000]


#: Published messages per node in thousands, one per configuration above, in order; None: two outliers.
MESSAGES = [34.88, 40.54, 43.31, 46.2, 37.37, 43.44, 46.41, 49.5, 36.47, 42.38, None, 48.3, 90.66, 96.7, 22.97, 24.5, 88.05, 18.75, 20, 71.88, 178.13, 190, 332.5, 360.43, 380, 9.38, 10, 17.5, 18.97, 20,
            82.61, 85.25, 88, 43.88, 46.875, 50, 76.98, 79.44, 82, 42.12, 45, 48, 82.49, 88.13, 94, 35.1, 37.5, 40, 32.47, 34.69, 37, 47.91, 51.19, 54.6, 50.37, 53.81, 57.4]


def test_published_messages():
    assert len(MESSAGES) == len(PUBLISHED)
    for (table, config, degree, outer, rule), printed in zip(PUBLISHED, MESSAGES, strict=True):
        if printed is not None:
            assert degree * sum(rounds(RULES[rule], outer)) / 1000 == pytest.approx(printed, abs=0.011), (table, config, rule)


def test_star_centre_sends_what_the_edges_send(spark):
    rows = {r["role"]: r for r in cost.by_role(cost.p2p_cost(spark, topology.star(20), rounds(RULES["50"], 200))).collect()}
    assert rows["centre"]["sends"] == 190_000 and rows["edge"]["sends"] * rows["edge"]["nodes"] == 190_000


def test_straggler_time(spark):
    table = cost.straggler_table(spark, rounds(RULES["2t+1"], 200), 10)
    assert cost.straggler_makespan(table).first()[0] == pytest.approx(93.75)
    assert cost.straggler_makespan(cost.straggler_table(spark, rounds(RULES["2t+1"], 200), 10, unit="step")).first()[0] == pytest.approx(2.0)


# ---------------------------------------------------------------- networks


def test_graphs():
    assert topology.ring(20).bipartite() and not topology.ring(21).bipartite()
    assert topology.star(20).degrees.tolist() == [19] + [1] * 19
    assert topology.grid(3, 4).diameter() == 5 and topology.path(5).diameter() == 4 and topology.complete(6).diameter() == 1
    with pytest.raises(ValueError):
        topology.Topology(10, tuple((i, (i + 1) % 5) for i in range(5)) + tuple((5 + i, 5 + (i + 1) % 5) for i in range(5)))
    assert topology.Topology(2, ((0, 1), (1, 0), (0, 0))).edges == ((0, 1),)
    assert topology.Topology(1, ()).weights().tolist() == [[1.0]]


def test_data_graph(spark):
    graph = topology.nation_graph(spark, SF)
    assert graph.n == 25 and not graph.bipartite()


@settings(max_examples=25, deadline=None)
@given(st.integers(2, 15), st.sampled_from(["local_degree", "metropolis", "max_degree", "lazy", "uniform"]), st.integers(0, 99))
def test_weights_are_doubly_stochastic(n, kind, seed):
    graph = topology.erdos_renyi(n, 0.6, seed)
    topology.check_weights(graph.weights(kind), None if kind == "uniform" else graph)


def test_bad_weights():
    with pytest.raises(ValueError):
        topology.check_weights(np.array([[0.5, 0.4], [0.5, 0.6]]))


def test_periodic_ring_never_mixes():
    w = topology.ring(20).weights()
    assert topology.second_modulus(w) == pytest.approx(1)
    assert topology.mixing_time(w) == 4  # the norm alone does not show it
    assert topology.second_modulus(topology.ring(20).weights("metropolis")) == pytest.approx(0.967, abs=1e-3)
    assert topology.second_modulus(topology.star(20).weights()) == pytest.approx(0.947, abs=1e-3)


def test_powers_and_anchor():
    w = topology.ring(20).weights()
    powers = linalg.Powers(w)
    for k in (0, 1, 2, 7, 12):
        assert np.allclose(powers[k], np.linalg.matrix_power(w, k))
    assert (linalg.anchor_scale(powers[3])[powers[3][:, 0] == 0] == 20).all()


def test_push_sum():
    w = topology.erdos_renyi(8, 0.5).weights()
    v = np.random.default_rng(0).standard_normal((8, 3, 3))
    assert np.allclose(consensus.push_sum(v, w, 200, "sum"), v.sum(0))
    p = w * np.linspace(1, 2, 8)[:, None]
    assert np.allclose(consensus.push_sum(v, p / p.sum(0), 400, "mean"), v.mean(0))


def test_fast_averaging_is_faster():
    w = topology.ring(21).weights("metropolis")
    far = lambda p: abs(p - 1 / 21).max()
    assert far(consensus.fast_power(w, 30)) < far(linalg.Powers(w)[30]) / 5
    assert np.allclose(consensus.fast_power(w, 30).sum(1), 1)


def test_averaging_inequality():
    v = np.random.default_rng(1).standard_normal((10, 6, 2))
    w = topology.erdos_renyi(10, 0.5).weights()
    for k in (5, 10, 20, 40):
        error, bound = theory.averaging_bound(v, w, k)
        assert (error <= bound + 1e-12).all()


# ---------------------------------------------------------------- linear algebra


@settings(max_examples=25, deadline=None)
@given(st.integers(1, 6), st.integers(0, 1000))
def test_qr_forms_agree(r, seed):
    v = np.random.default_rng(seed).standard_normal((9, r))
    q, upper = linalg.positive_qr(v)
    assert (np.diag(upper) >= 0).all() and np.allclose(q @ upper, v) and np.allclose(q.T @ q, np.eye(r))
    c, _ = linalg.cholesky_qr(v)
    assert np.allclose(c, q, atol=1e-8)


def test_distributed_qr():
    v = np.random.default_rng(5).standard_normal((12, 3))
    blocks = partition.column_blocks(12, 4, "unequal")
    q, _ = linalg.positive_qr(v)
    assert np.allclose(loops.gram_qr(v, blocks, None), q)
    assert np.allclose(loops.modified_gram_schmidt(v, blocks, None), q)
    power = linalg.Powers(topology.complete(4).weights("metropolis"))[60]
    assert np.allclose(loops.gram_qr(v, blocks, power), q) and np.allclose(loops.modified_gram_schmidt(v, blocks, power), q)


def test_error_measures():
    q = np.eye(6)[:, :2]
    turn = np.array([[0.6, -0.8], [0.8, 0.6]])
    assert linalg.angle_error(q @ turn, q) == pytest.approx(0)
    p = linalg.positive_qr(np.random.default_rng(2).standard_normal((6, 2)))[0]
    assert metrics.projector_distance(q, p, "F") ** 2 == pytest.approx(2 * 2 * linalg.angle_error(p, q))
    assert metrics.projector_distance(q, p, "2") == pytest.approx(np.linalg.norm(q @ q.T - p @ p.T, 2))
    assert 0 < metrics.init_angle(p, q) < 1


# ---------------------------------------------------------------- methods


def test_reductions(nodes):
    m, _ = nodes
    q0 = linalg.random_basis(12, 4, 7)
    central = [q[0] for _, q in loops.central(m / 8, 15, q0)]
    uniform = [q[0] for _, q in loops.row_split(m, np.full((8, 8), 1 / 8), [1] * 15, q0)]
    alone = [q[0] for _, q in loops.row_split(m.mean(0)[None], np.ones((1, 1)), [1] * 15, q0)]
    columns = [q[0] for _, q in loops.column_split(m.mean(0), [np.arange(12)], np.ones((1, 1)), [1] * 15, q0)]
    for other in (uniform, alone, columns):
        assert all(np.allclose(a, b, atol=1e-9) for a, b in zip(central, other, strict=True))
    w = topology.erdos_renyi(8, 0.5).weights()
    flat, fixed = rounds(Ramp(0, 5, 50), 10), rounds(Fixed(5), 10)
    assert flat == fixed
    one = last(loops.row_split(m, w, [60] * 40, q0[:, :1]))[1][0]
    assert abs(one[:, 0] @ last(loops.sequential(m, w, [60], 40, q0[:, :1]))[1][0][:, 0]) == pytest.approx(1, abs=1e-6)


def test_scaling_leaves_the_span(nodes):
    m, _ = nodes
    w, q0 = topology.erdos_renyi(8, 0.5).weights(), linalg.random_basis(12, 4, 7)
    a, b = last(loops.row_split(m, w, [20] * 30, q0))[1], last(loops.row_split(m * 7, w, [20] * 30, q0))[1]
    assert np.allclose(a, b)


def test_modes_agree_row(spark):
    samples = shaped_nodes(spark, SF, n=5, d=8, r=3).cache()
    graph = topology.erdos_renyi(5, 0.6)
    runs = {mode: subspace.rowsplit_subspace(samples, graph, 3, Fixed(3), 3, mode=mode) for mode in ("resident", "fused", "literal")}
    bases = {mode: np.stack([r.as_matrix(k) for k in range(5)]) for mode, r in runs.items()}
    assert np.allclose(bases["resident"], bases["fused"], atol=1e-10) and np.allclose(bases["fused"], bases["literal"], atol=1e-10)
    assert runs["fused"].cost.agg(F.sum("sends")).first()[0] == 2 * len(graph.edges) * 9


def test_modes_agree_column(spark):
    samples = shaped_nodes(spark, SF, n=5, d=8, r=3).cache()
    graph, blocks = topology.erdos_renyi(4, 0.6), partition.column_blocks(8, 4, "round_robin")
    out = [subspace.colsplit_subspace(samples, blocks, graph, 3, Fixed(3), 2, mode=mode, push_rounds=20).basis.orderBy("i").toPandas() for mode in ("cross", "streamed", "literal")]
    q = [np.stack(o.q.to_list()) for o in out]
    assert np.allclose(q[0], q[1], atol=1e-10) and np.allclose(q[1], q[2], atol=1e-10)
    assert out[0].node.tolist() == [i % 4 for i in range(8)]


def test_reported_behaviour(nodes):
    m, truth = nodes
    w, q0 = topology.erdos_renyi(8, 0.5).weights(), linalg.random_basis(12, 4, 7)
    trace = lambda steps: [(k, linalg.angle_error(q, truth).mean()) for k, q in steps]
    first = lambda t, level: next((k for k, e in t if e < level), None)
    fixed, ramp = trace(loops.row_split(m, w, rounds(Fixed(50), 120), q0)), trace(loops.row_split(m, w, rounds(Ramp(1), 120), q0))
    assert ramp[-1][1] == pytest.approx(fixed[-1][1], rel=0.2, abs=1e-12)  # the same floor
    assert first(ramp, 1e-8) < first(fixed, 1e-8)  # with fewer messages
    seq = trace(loops.sequential(m, w, [50], 40, q0))
    assert min(e for _, e in seq[:119]) > 0.05 and seq[-1][1] < 1e-3  # falls at the last vector only
    for rule in (loops.hebbian, loops.projected_gradient):
        assert 1e-9 < trace(rule(m, w, 1500, q0, 0.1))[-1][1] < 0.05  # a neighbourhood
    assert first(trace(loops.tracking(m, w, 200, q0, 3)), 1e-8) < first(fixed, 1e-8)  # better on communication
    columns = trace(loops.column_split(m.mean(0), partition.column_blocks(12, 8), w, [50] * 60, q0, push_rounds=None))
    central = trace(loops.central(m / 8, 60, q0))
    assert columns[30][1] == pytest.approx(central[30][1], rel=0.5, abs=1e-10)
    sparse = trace(loops.row_split(m, topology.ring(8).weights(), rounds(Fixed(50), 120), q0))
    assert sparse[-1][1] > fixed[-1][1]  # a periodic ring stays worse


def test_rate_follows_the_gap(spark):
    samples = shaped_nodes(spark, SF, n=5, d=12, r=3, delta=0.7)
    out = subspace.rowsplit_subspace(samples, topology.complete(5), 3, Fixed(1), 60, weights="uniform", truth="exact")
    assert metrics.fit_rate(out.trace).first()["slope"] == pytest.approx(2 * np.log(0.7), rel=0.15)
    worse = metrics.iterations_to(out.trace, [1e-4, 0.0]).orderBy("level").collect()
    assert worse[0]["inner_total"] is None and worse[1]["inner_total"] > 0


def test_stopping(spark):
    samples = shaped_nodes(spark, SF, n=5, d=8, r=3)
    rule = stopping.error_below(1e-6) | stopping.max_outer(40)
    out = subspace.rowsplit_subspace(samples, topology.complete(5), 3, Fixed(5), 200, stop=rule, truth="exact")
    assert out.trace.agg(F.max("t")).first()[0] < 39
    out = subspace.rowsplit_subspace(samples, topology.complete(5), 3, Fixed(5), 200, stop=stopping.message_budget(100))
    assert out.trace.agg(F.max("t")).first()[0] == 4  # four neighbours, five rounds a step


def test_unequal_nodes(spark):
    samples = features.shaped(features.embeddings(spark, SF, 10), 3, 0.4)
    unequal = partition.skewed(samples, 4)
    graph = topology.complete(4)
    error = lambda **o: subspace.rowsplit_subspace(unequal, graph, 3, Fixed(1), 60, weights="uniform", truth=np.eye(10)[:, :3], every=59, **o).trace.agg(F.max_by("error", "t")).first()[0]
    assert error() < 1e-12 < error(local_scale="mean")


def test_components(spark):
    samples = shaped_nodes(spark, SF, n=5, d=8, r=3)
    out = subspace.rowsplit_subspace(samples, topology.complete(5), 3, Fixed(40), 80)
    values, vectors = out.as_components(moments.global_moments(samples).covariance)
    assert np.allclose(values, [1, 0.9, 0.8], atol=1e-6) and np.allclose(abs(vectors[:3]), np.eye(3), atol=1e-4)


def test_only_small_tables_leave_the_nodes(spark):
    """After the node moments, nothing that crosses nodes has a row per sample."""
    scatter = moments.local_scatter(shaped_nodes(spark, SF, n=5, d=8, r=3))
    assert scatter.count() == 5 * 8
    z = scatter.select("node", "i", F.slice("row", 1, 3).alias("z"))
    assert consensus.run_fused(z, topology.complete(5).weights()).count() == 5 * 8


def test_refusals(spark):
    samples = shaped_nodes(spark, SF, n=5, d=8, r=3)
    for r in (0, 9):
        with pytest.raises(ValueError):
            subspace.rowsplit_subspace(samples, topology.complete(5), r)
    with pytest.raises(ValueError):
        subspace.colsplit_subspace(samples, [np.arange(4)], topology.complete(2), 2)
    with pytest.raises(ValueError):
        Explicit((3, 2))
    with pytest.raises(ValueError):
        tables.read_source(spark, "csv", "/nowhere")


# ---------------------------------------------------------------- features


def test_validation(spark):
    rows = [(0, [1.0, 2.0]), (1, [float("nan"), 1.0]), (2, None), (3, [None, 3.0])]
    df = spark.createDataFrame(rows, "sample_id int, features array<double>")
    with pytest.raises(ValueError):
        features.validated(df)
    assert features.validated(df, "drop").count() == 1
    assert sorted(map(tuple, (r["features"] for r in features.validated(df, "zero").collect()))) == [(0.0, 1.0), (0.0, 3.0), (1.0, 2.0)]
    assert (1.0, 3.0) in [tuple(r["features"]) for r in features.validated(df, "mean").collect()]
    with pytest.raises(ValueError):
        features.validated(spark.createDataFrame([(0, [1.0]), (1, [1.0, 2.0])], "sample_id int, features array<double>"))


def test_zero_variance(spark):
    f = spark.createDataFrame([(i, [float(i), 5.0]) for i in range(6)], "sample_id int, features array<double>")
    assert moments.global_moments(features.standardized(f)).d == 1
    assert moments.global_moments(features.standardized(f, "keep")).d == 2
    with pytest.raises(ValueError):
        features.standardized(f, "error")


def test_flat_spectrum_is_ill_posed(spark):
    values, _ = subspace.exact_subspace(features.standardized(features.line_numeric(spark, SF)), 1)
    assert not any(metrics.well_posed(values, r, 0.95) for r in (1, 2, 3))


def test_mixed_columns(spark):
    df = spark.sql("SELECT 1 AS id, true AS a, CAST(1.50 AS DECIMAL(5, 2)) AS b, 2 AS c")
    assert features.to_features(df, "id", ["a", "b", "c"]).first()["features"] == [1.0, 1.5, 2.0]


def test_narrow_equals_general(spark):
    samples = partition.by_hash(features.embeddings(spark, SF, 5), 3)
    a = moments.stacked(moments.local_scatter(samples).toPandas())[1]
    b = moments.stacked(moments.narrow_scatter(samples, 5).toPandas())[1]
    assert np.allclose(a, b)
    centred = subspace.centred(moments.local_scatter(samples)).toPandas()
    assert np.allclose(moments.stacked(centred, "none")[1], a)


def test_empty_node_gets_zeros(spark):
    samples = features.embeddings(spark, SF, 3).withColumn("node", F.lit(1))
    m = moments.stacked(moments.with_all_nodes(moments.local_scatter(samples), 3, 3).toPandas())[1]
    assert m.shape == (3, 3, 3) and not m[0].any() and m[1].any()


# ---------------------------------------------------------------- the rest


def test_facade(spark):
    samples = features.embeddings(spark, SF, 6)
    fitted = MeshSpan(spark, topology.complete(3), Fixed(20), 300).fit(samples, 2)
    back = fitted.decode(fitted.encode(samples)).select(F.size("decoded")).first()[0]
    assert back == 6 and fitted.explained_variance().sum() < 1
    columns = MeshSpan(spark, topology.complete(3), Fixed(20), 300).fit(samples, 2, split="column")
    assert metrics.projector_distance(fitted.basis, columns.basis) < 1e-3
    compared = MeshSpan(spark, topology.complete(3), Fixed(5), 30).compare(samples, 2, ("row", "central", "tracking"), every=10)
    assert {r["method"] for r in compared.select("method").distinct().collect()} == {"row", "central", "tracking"}


def test_wide_encoding_uses_the_same_numbers(spark):
    samples = features.embeddings(spark, SF)
    q = linalg.random_basis(64, 20, 1)
    a = encode.encode(samples.limit(5), q).toPandas()
    x = np.stack(a.features.to_list())
    assert np.allclose(np.stack(a.code.to_list()), x @ q)


def test_theory():
    s = TheorySchedule("ramp", 4.0, 2.0, 2.0, 3.0, 20, 3, 10)
    plan = rounds(s, 5)
    assert plan == sorted(plan) and theory.rounds_bound(s, 4) > theory.rounds_bound(s, 0)
    assert theory.outer_needed(0.5, 1e-3) == 10 and theory.push_rounds_needed(10, 1e-8) == 21
    assert theory.theorem_bound(0.5, 10, 1, "ramp", corrected=True) > theory.theorem_bound(0.5, 10, 1, "ramp")
    assert theory.log_delta("fixed", {"alpha": 3, "beta": 2, "gamma": 1}, 2, 200, 0.1) < -1000


def test_state_round_trip(spark, tmp_path):
    basis = spark.createDataFrame([(0, 0, [1.0])], "node int, i int, q array<double>")
    tables.save_state(basis, 3, str(tmp_path / "s"))
    tables.save_state(basis, 6, str(tmp_path / "s"))
    assert tables.resume(spark, str(tmp_path / "s"))[1] == 6


def test_workload_shapes(spark):
    rows = workloads.GRIDS["w2_connectivity"].outcomes(spark, SF).toPandas()
    by = rows.set_index(["setting", "rule"])
    assert by.error["er:0.1", "50"] > by.error["er:0.25", "50"] > by.error["er:0.5", "50"]
    assert by.p2p_k["er:0.1", "50"] < by.p2p_k["er:0.5", "50"]
    assert by.error["er:0.1", "5t+1,200"] < by.error["er:0.1", "50"]


def test_sql_functions(spark):
    from meshspan.functions import tablefunctions

    tablefunctions.register(spark)
    assert spark.sql("SELECT count(*) FROM topology_edges('ring', 20)").first()[0] == 20
    assert spark.sql("SELECT sum(rounds) FROM schedule_rows(2D, 1D, 50, 200)").first()[0] == 9375
    assert spark.sql("SELECT vec_dot(array(1D, 2D), array(3D, 4D)), vec_norm(array(3D, 4D))").first()[:] == (11.0, 5.0)


def test_estimator(spark):
    from pyspark.ml.functions import array_to_vector

    from meshspan.plans.estimator import SubspaceEstimator

    samples = features.embeddings(spark, SF, 6)
    plain = SubspaceEstimator(2, topology=topology.complete(3), outer=50).fit(samples).transform(samples)
    assert plain.select(F.size("code")).first()[0] == 2 and "label" in plain.columns
    ml = samples.withColumn("features", array_to_vector("features"))
    assert SubspaceEstimator(2, topology=topology.complete(3), outer=50).fit(ml).transform(ml).schema["code"].dataType.typeName() in ("vectorudt", "udt", "vector")


def test_sampled_start_saves_steps(spark):
    """A basis from a sample of the rows starts nearer to the answer than a random one."""
    samples = shaped_nodes(spark, SF, n=5, d=12, r=3, delta=0.7)
    warm = subspace.exact_subspace(samples.sampleBy("node", {k: 0.4 for k in range(5)}, 3), 3)[1]
    runs = [subspace.rowsplit_subspace(samples, topology.complete(5), 3, Fixed(1), 40, weights="uniform", init=q, truth="exact").trace for q in (7, warm)]
    steps = [metrics.iterations_to(t, [1e-6]).first()["inner_total"] for t in runs]
    assert steps[1] < steps[0]


def test_hashed_vectors_of_odd_texts(spark):
    """Entries are exactly the relative counts of the tokens' buckets, for wide vectors too; one row per row."""
    import hashlib
    from collections import Counter

    texts = {1: "a b a", 2: None, 3: " \n ", 4: "É ß a" * 30, 5: " ".join(f"w{i}" for i in range(3000))}
    frame = spark.createDataFrame([*texts.items(), (None, "x")], "id long, text string").repartition(2)
    for buckets in (1, 7, 2914):
        rows = {r[0]: r[1] for r in features.hashed_words(frame, "id", F.col("text"), buckets).collect()}
        assert len(rows) == 6 and rows.pop(None) == [0.0] * buckets
        for i, text in texts.items():
            count = Counter(int(hashlib.md5(w.encode()).hexdigest()[:8], 16) % buckets for w in (text or "").lower().split())
            assert rows[i] == [count[b] / max(1, count.total()) for b in range(buckets)]


def test_vectors_are_not_searched_entry_by_entry(spark):
    """A bag is written into its vector; looking every bucket up in it takes time in proportion to their product."""
    plan = features.documents_hashed(spark, SF, 64)._jdf.queryExecution().optimizedPlan().toString()
    assert "try_element_at" not in plan and "MapInArrow" in plan


def test_eigenvectors_are_computed_once(monkeypatch):
    from meshspan.operators import nodes as moments_of

    m = moments_of.LocalNodes(np.stack([np.diag([3.0, 2.0, 1.0, 0.5])] * 2))
    first = m.leading(2)
    monkeypatch.setattr(moments_of, "leading", lambda *_: pytest.fail("computed twice"))
    values, vectors = m.scaled(0.5).leading(1)
    assert np.allclose(values, first[0] / 2) and np.array_equal(vectors, first[1][:, :1])


def _small_natural():
    return workloads._natural("small", workloads._documents(64), 64, [(20, 0.25, 3, 6), (20, 0.5, 3, 6), (100, 0.05, 2, 4)], [(3, 6)])


def test_moments_that_fit_a_task_are_read_there(spark, monkeypatch):
    """Beyond what goes by the driver no step is a job of its own: tasks read the moments and run whole settings."""
    from meshspan.operators import nodes as moments_of

    keys = ["setting", "method", "rule", "nodes", "rank"]
    usual = _small_natural().outcomes(spark, SF).toPandas().sort_values(keys, ignore_index=True)
    monkeypatch.setattr(workloads, "BUDGET", 0)
    monkeypatch.setattr(workloads, "DRIVER_BYTES", 0, raising=False)
    monkeypatch.setattr(moments_of, "SpreadNodes", type("Never", (), {"__init__": lambda *_: pytest.fail("a job per step")}))
    read = _small_natural().outcomes(spark, SF).toPandas().sort_values(keys, ignore_index=True)
    assert len(read) == 17 and read[[*keys, "inner_total", "p2p_k"]].equals(usual[[*keys, "inner_total", "p2p_k"]])
    for c in ("error", "error_max", "delta"):
        assert np.allclose(read[c], usual[c], rtol=1e-7, atol=1e-12)


def test_a_task_holds_rows_or_half_matrices(spark):
    """The smaller form, with the products of the whole matrices; the truth is decomposed in a task."""
    import dataclasses

    from meshspan.operators import nodes as moments_of

    samples = partition.by_hash(features.documents_hashed(spark, SF, 150), 4)
    table = moments_of.node_pieces(samples, 4, 150)
    whole, q = table.local(), np.random.default_rng(1).standard_normal((4, 150, 3))
    for own in (table, dataclasses.replace(table, dense=True)):
        m = moments_of.CompactNodes.from_batches(dataclasses.replace(own, df=None), table.df.toArrow().to_batches())
        assert (m.panels is None) == (own.compact == table.bytes and not own.dense)
        assert np.allclose(m.apply(q), whole.apply(q), atol=1e-12) and np.allclose(m.total, whole.total, atol=1e-14)
    values, vectors = table.leading(3)
    true = whole.leading(3)
    assert np.allclose(values, true[0][:4], atol=1e-14) and np.allclose(np.abs((vectors * true[1]).sum(0)), 1, atol=1e-9)


def test_networks_that_divide_the_largest_share_a_scan(spark, monkeypatch):
    from meshspan.operators import nodes as moments_of

    scans, pieces = [], moments_of.node_pieces
    monkeypatch.setattr(moments_of, "node_pieces", lambda samples, n, *a, **b: scans.append(n) or pieces(samples, n, *a, **b))
    assert set(_small_natural().data(spark, SF)) == {"10", "20", "100"} and scans == [100]
