"""SimHash groups, components, pruned-graph links and hashed search against brute force."""

from itertools import combinations

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from meshspan.llm import common, hashed_search, pruned_graph, simhash

SF = "/root/testdata/sf0.001"


def plain_fingerprint(text):
    words = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    for c in "\t\n\x0b\x0c\r":
        words = words.replace(c, " ")
    words = [w for w in words.split(" ") if w]
    if not words:
        return 0
    grams = [" ".join(words[i : i + 4]) for i in range(len(words) - 3)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def groups_of(ids, links):
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in links:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_fingerprints():
    for text in (None, "", " \t", "One", "A b C d", "a b c d e f", "x y z", "été " * 50, "a b " * 40_000):
        assert simhash.fingerprint(text) == plain_fingerprint(text)


def test_groups_equal_brute_force(spark):
    d = spark.read.parquet(SF + "/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in d.collect()}
    prints = {i: plain_fingerprint(t) for i, t in texts.items()}
    want = groups_of(sorted(prints), [(a, b) for a, b in combinations(sorted(prints), 2) if (prints[a] ^ prints[b]).bit_count() <= 4])
    got = simhash.near_duplicate_groups(d).collect()
    assert {r["doc_id"]: r["component_id"] for r in got} == want
    assert {r["doc_id"]: r["fingerprint"] for r in got} == {i: f"{p:016x}" for i, p in prints.items()}
    kept = simhash.deduplicated(d, similarity=None)
    assert kept.columns == d.columns and sorted(r["doc_id"] for r in kept.collect()) == sorted(set(want.values()))


def flipped(value, bits):
    for b in bits:
        value ^= 1 << int(b)
    return value


def test_every_link_within_the_radius_is_found(spark):
    """Planted pairs at distances 0 to 6, at random bits: links join exactly those within four."""
    rng = np.random.default_rng(1)
    values = set()
    for _ in range(300):
        v = int(rng.integers(0, 2**63)) * 2 + int(rng.integers(0, 2))
        values |= {v, flipped(v, rng.choice(64, int(rng.integers(1, 7)), replace=False))}
    values = sorted(values)
    frame = spark.createDataFrame([(v - 2**64 if v >= 2**63 else v,) for v in values], "fp long")
    links = [(r["src"] % 2**64, r["dst"] % 2**64) for r in simhash.fingerprint_links(frame).collect()]
    assert all((a ^ b).bit_count() <= 4 for a, b in links)
    want = groups_of(values, [(a, b) for a, b in combinations(values, 2) if (a ^ b).bit_count() <= 4])
    assert groups_of(values, links) == want


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 2**32), st.integers(2, 80))
def test_long_runs_are_searched_exactly(seed, n):
    rng = np.random.default_rng(seed)
    base = int(rng.integers(0, 2**62))
    values = np.unique(np.array([flipped(base, rng.choice(64, int(rng.integers(0, 9)), replace=False)) for _ in range(n)], np.uint64))
    pairs = [(i, j) for i, j in combinations(range(len(values)), 2) if (int(values[i]) ^ int(values[j])).bit_count() <= 4]
    want = groups_of(range(len(values)), pairs)
    for dense in (4, 1000):
        assert dict(enumerate(simhash.linked_run(values, dense=dense).tolist())) == want


def test_simhash_edges(spark, docs):
    frame = docs(["Same words here now ok", None, "", "same words HERE now ok", "other", "other"], ids=[5, 3, 2, 1, None, 9])
    got = {(r["doc_id"], r["fingerprint"] == "0" * 16): r["component_id"] for r in simhash.near_duplicate_groups(frame).collect()}
    assert got == {(5, False): 1, (1, False): 1, (3, True): 2, (2, True): 2, (None, False): 9, (9, False): 9}
    twice = frame.union(frame)
    assert simhash.near_duplicate_groups(twice).count() == 12
    assert sorted(r["doc_id"] for r in simhash.deduplicated(twice, similarity=None).collect()) == [1, 2, 9]
    assert simhash.near_duplicate_groups(frame.limit(0)).count() == 0 and simhash.deduplicated(frame.limit(0)).count() == 0


def jaccard(a, b, n=5):
    a, b = ({tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} for w in (a.lower().split(), b.lower().split()))
    return len(a & b) / len(a | b)


def test_similar_texts_equal_brute_force(spark, docs, monkeypatch):
    """Copies with some words changed, of 3 to 400 words: groups are exactly those of all pairs whose shingle sets are
    at least 0.8 alike, chains included, also when groups are cut into chunks; one row of each group stays."""
    rng = np.random.default_rng(3)
    texts = []
    for n in [*rng.integers(60, 400, 40), *rng.integers(3, 45, 60)]:
        words = [f"w{int(x)}" for x in rng.integers(0, 5000, int(n))]
        texts.append(" ".join(words))
        for _ in range(int(rng.integers(0, 3))):
            copy = list(words)
            for at in rng.choice(len(copy), int(rng.integers(0, max(2, len(copy) // 25))), replace=False):
                copy[at] = "changed"
            texts.append(" ".join(copy + ["more"] * int(rng.integers(0, 2))))
    texts += [texts[0].upper(), None, "", " ", "one two", "One  two"]
    whole = [t or "" for t in texts]
    pairs = [(i, j) for i, j in combinations(range(len(texts)), 2) if (whole[i].split() and whole[j].split() and jaccard(whole[i], whole[j]) >= 0.8) or not (whole[i].split() or whole[j].split())]
    want = groups_of(range(len(texts)), pairs)
    for chunk in (2048, 2):
        monkeypatch.setattr(simhash, "_CHUNK", chunk)
        rows = simhash.similar_groups(docs(texts)).collect()
        low = {}
        for r in rows:
            low[r["component"]] = min(low.get(r["component"], 1 << 60), r["doc_id"])
        assert {r["doc_id"]: low[r["component"]] for r in rows} == want
        if chunk == 2048:
            kept = sorted(r["doc_id"] for r in simhash.deduplicated(docs(texts)).collect())
            assert kept == sorted(set(want.values()))
    assert simhash.similar_groups(docs(texts).limit(0)).count() == 0


def test_rows_without_ids_and_repeats_stay_once(spark):
    rows = [(None, "a lone text of its own", 1), (None, "another text without any id", 2), (5, "first under five", 3), (5, "quite another one under the same number", 4), (7, "said twice", 5), (7, "said twice", 5), (9, "Said twice", 6)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, fp int")
    kept = simhash.deduplicated(frame)
    assert kept.columns == frame.columns
    assert sorted((r["doc_id"] or 0, r["text"]) for r in kept.collect()) == sorted((i or 0, t) for i, t, _ in rows[:5])


def test_parts_find_all_that_meets():
    rng = np.random.default_rng(0)
    low_bits, values = 10, rng.integers(0, 1 << 16, 400).astype(np.uint16)
    fps = rng.integers(0, 2**63, (400, simhash.WIDE_WORDS)).astype(np.uint64)
    fps[200:] = fps[:200] ^ np.uint64(3)
    values[200:300] = values[:100]
    values[300:] = values[100:200] ^ np.uint16(4)
    entries = np.zeros(400, simhash._ENTRY)
    entries["value"], entries["id"], entries["fp"] = values, np.arange(400), fps
    a, b = simhash.linked_part(entries, 16, low_bits)
    assert groups_of(range(400), list(zip(a.tolist(), b.tolist(), strict=True))) == {i: i % 200 for i in range(400)}


def test_components(spark):
    chain = [(i, i + 1) for i in range(200)] + [(1000, 1001), (1001, 1000), (7, 7), (2000, 1001)]
    star = [(5000, i) for i in range(5001, 5050)]
    frame = spark.createDataFrame(chain + star, "src long, dst long")
    got = {r["node"]: r["component"] for r in common.connected_components(frame).collect()}
    want = groups_of({x for e in chain + star for x in e}, chain + star)
    assert got == want
    assert common.connected_components(frame.limit(0)).count() == 0


# ---------------------------------------------------------------- vectors


def vector_rows(seed=0, n=150):
    rng = np.random.default_rng(seed)
    rows, i = [], 0
    for label in (1, 2):
        for _ in range(n // 10):
            v = rng.standard_normal(16)
            for _ in range(int(rng.integers(1, 8))):
                w = v + rng.standard_normal(16) * rng.choice([0.0, 0.05, 0.2, 0.35])
                rows.append((i, w.tolist(), label))
                i += 1
    rows += [(i, None, 1), (i + 1, [0.0] * 16, 1), (i + 2, [float("nan")] * 16, 1), (i + 3, rows[0][1], None), (i + 4, [None] * 16, 2), (i + 5, rows[0][1], rows[0][2]), (i + 6, [float("inf")] + [1.0] * 15, 2)]
    return rows


def brute_links(rows, threshold=0.93):
    usable = [(i, np.array(v, float), label) for i, v, label in rows if label is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    links = []
    for (a, x, p), (b, y, q) in combinations(usable, 2):
        if p == q and x @ y / np.sqrt((x @ x) * (y @ y)) >= threshold:
            links.append((a, b))
    return links


def test_vector_links_equal_brute_force(spark):
    rows = vector_rows()
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    links = brute_links(rows)
    degree = {r[0]: sum(r[0] in pair for pair in links) for r in rows}
    got = {r["vec_id"]: r for r in pruned_graph.near_duplicate_vectors(frame, shard_rows=40).collect()}
    assert {i: r["n_links"] for i, r in got.items()} == degree
    want = groups_of([r[0] for r in rows], links)
    assert {i: r["component_id"] for i, r in got.items()} == want
    assert all(r["kept"] == (i == want[i]) for i, r in got.items())
    cut = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in pruned_graph.near_duplicate_vectors(frame, shard_rows=60, largest=16).collect()}
    assert cut == {i: (r["n_links"], r["component_id"]) for i, r in got.items()}
    assert pruned_graph.near_duplicate_vectors(frame.limit(0)).count() == 0


def test_links_across_shard_borders_are_found(spark):
    rng = np.random.default_rng(9)
    x = pruned_graph.unit(rng.standard_normal((8000, 32)))
    side = pruned_graph.unit(rng.standard_normal((2000, 32)))
    side = pruned_graph.unit(side - (side * x[:2000]).sum(1)[:, None] * x[:2000])
    cosine = rng.uniform(0.9301, 0.95, 2000)[:, None]
    x = np.vstack((x, cosine * x[:2000] + np.sqrt(1 - cosine**2) * side))
    frame = spark.createDataFrame([(i, v.tolist(), 1) for i, v in enumerate(x)], "vec_id long, embedding array<double>, label int")
    found = pruned_graph.near_duplicate_vectors(frame, shard_rows=64)
    got = {r["vec_id"]: r["n_links"] for r in found.collect()}
    want = (x @ x.T >= 0.93).sum(1) - 1
    assert want.sum() >= 4000 and all(got[i] <= n for i, n in enumerate(want))
    assert sum(got.values()) / want.sum() >= 0.998
    assert pruned_graph.recall(found, frame) >= 0.99


def test_overlap_grows_with_the_number_of_centres():
    rng = np.random.default_rng(2)
    x = pruned_graph.unit(rng.standard_normal((4000, 64)))
    few, many = (pruned_graph.overlap_needed(x, x[:n], 0.93, 4) for n in (20, 2000))
    assert 4 <= few <= many <= 200
    assert pruned_graph.overlap_needed(x, x[:3], 0.93, 4) == 4 and pruned_graph.overlap_needed(x[:0], x[:20], 0.93, 4) == 4
    assert pruned_graph.overlap_needed(np.ones((5, 1)), np.ones((9, 1)), 0.93, 4) == 4


def test_graph_search_alone_has_high_recall():
    rng = np.random.default_rng(4)
    centres = rng.standard_normal((60, 32))
    x = pruned_graph.unit(np.vstack([c + 0.12 * rng.standard_normal((10, 32)) for c in centres]))
    out = pruned_graph.pruned_neighbours(x, degree=16)
    links = np.zeros((len(x), len(x)), bool)
    i, slot = np.nonzero(out >= 0)
    links[i, out[i, slot]] = True
    a, b = pruned_graph.range_search(x, links | links.T, 0.93)
    found = set(zip(a.tolist(), b.tolist(), strict=True))
    want = {(i, j) for i, j in zip(*np.nonzero(x @ x.T >= 0.93), strict=True) if i != j}
    assert len(want & found) / len(want) > 0.97


def test_pruning_keeps_the_nearest_and_drops_the_covered():
    x = pruned_graph.unit(np.array([[1, 0], [1, 0.01], [1, 0.02], [0, 1.0]]))
    out = pruned_graph.pruned_neighbours(x, degree=3)
    assert out[0, 0] == 1 and 2 not in out[0]


def test_search_recall_and_scores(spark):
    d = spark.read.parquet(SF + "/embeddings.parquet")
    found = hashed_search.nearest(d, d.where("vec_id % 100 = 0"))
    rows = found.toPandas().sort_values(["query_id", "rank"])
    assert (rows.groupby("query_id").size() == 10).all() and hashed_search.recall(found, d) >= 0.9
    x = {r["vec_id"]: np.array(r["embedding"], float) for r in d.collect()}
    assert all(abs(np.sqrt(((x[q] - x[v]) ** 2).sum()) - s) < 1e-12 for q, v, s in zip(rows.query_id, rows.vec_id, rows.score, strict=True))
    assert (rows.query_id != rows.vec_id).all() and (rows.groupby("query_id").score.diff().dropna() >= 0).all()


def test_search_edges(spark):
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [0.9, 0.1]), (3, None), (4, [0.0, 0.0]), (5, [float("nan"), 1.0]), (None, [1.0, 1.0]), (6, [1.0, 0.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = [(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in hashed_search.nearest(frame, frame.where("vec_id in (0, 3, 4)")).orderBy("rank").collect()]
    assert [g[:3] for g in got] == [(0, 1, 1), (0, 2, 6), (0, 3, 2)] and got[0][3] == 0.0
    assert hashed_search.nearest(frame.limit(0), frame).count() == 0


@settings(max_examples=30, deadline=None)
@given(st.integers(0, 10_000), st.integers(0, 40))
def test_probing_retrieves_the_whole_ball(seed, radius):
    rng = np.random.default_rng(seed)
    codes = rng.integers(0, 2**63, 300).astype(np.uint64)
    query = flipped(int(codes[0]), rng.choice(64, 5, replace=False))
    got = hashed_search.SubstringIndex(codes).within(np.uint64(query), radius)
    assert got.tolist() == np.flatnonzero(np.bitwise_count(codes ^ np.uint64(query)) <= radius).tolist()


def test_rotation_is_orthogonal():
    x = np.random.default_rng(0).standard_normal((500, 64))
    mean, p = hashed_search.learn_rotation(x)
    assert p.shape == (64, 64) and np.allclose(p.T @ p, np.eye(64), atol=1e-9)


def test_unequal_vectors_are_refused():
    import pyarrow as pa

    for rows in ([[1.0, 2.0, 3.0], [1.0]], [[1.0, 2.0], None], [[1.0, None], [1.0, 2.0]]):
        with pytest.raises(ValueError):
            hashed_search.matrix(pa.array(rows, pa.list_(pa.float64())))
    assert hashed_search.matrix(pa.array([[1.0, 2.0]] * 3, pa.list_(pa.float64())).slice(1, 2)).shape == (2, 2)
