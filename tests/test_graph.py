"""Diffusion, factors, pipeline, baselines and measures against closed forms, exact values and NumPy."""

from __future__ import annotations

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from attrgraph.functions import gaussian_hash, hash_uniform
from attrgraph.operators import alike, attributes, builders, cluster, diffusion, evaluate, exact, factors, graph, measures, sharing
from attrgraph.operators.baselines import attrs as by_attrs
from attrgraph.operators.baselines import embed, flow, heat, links, push
from attrgraph.session import materialise
from attrgraph.sources import table

DATA = "/root/testdata/sf0.001"
GOLDEN = [(1, 2), (1, 3), (1, 4), (1, 5), (2, 3), (2, 4), (5, 6), (5, 7), (5, 8), (5, 9), (9, 10)]


def make(spark, pairs):
    return graph.from_edges(spark.createDataFrame(pairs, "a long, b long")).kept()


def seeds_of(spark, *ids):
    return spark.createDataFrame([(i,) for i in ids], "seed_id long")


@pytest.fixture(scope="module")
def small(spark):
    """A random connected graph of 40 nodes with non-negative attributes."""
    rng = random.Random(3)
    pairs = {(i, i + 1) for i in range(39)} | {tuple(sorted(rng.sample(range(40), 2))) for _ in range(60)}
    g = make(spark, sorted(pairs))
    rows = [(i, f"a{j}", rng.random()) for i in range(40) for j in rng.sample(range(8), 3)]
    attrs = materialise(attributes.l2_normalize(spark.createDataFrame(rows, "node_id long, attr string, value double")), "attrs")
    a = np.zeros((40, 40))
    for x, y in pairs:
        a[x, y] = a[y, x] = 1
    x = np.zeros((40, 8))
    for r in attrs.collect():
        x[r.node_id, int(r.attr[1:])] = r.value
    return g, attrs, a, x


def walk_matrix(a, alpha=0.8):
    p = a / a.sum(axis=1, keepdims=True)
    return (1 - alpha) * np.linalg.inv(np.eye(len(a)) - alpha * p)


def push_numpy(a, start, eps, sigma, alpha=0.8):
    """(reserve, residual, spent) by the rules, in NumPy."""
    deg = a.sum(axis=1)
    p = a / deg[:, None]
    r, q, spent = start.copy(), np.zeros(len(a)), 0.0
    while True:
        hot = (r > 0) & (r >= eps * deg)
        if not hot.any():
            return q, r, spent
        some = r > 0
        if hot.sum() / some.sum() > sigma and spent + deg[some].sum() < start.sum() / ((1 - alpha) * eps):
            spent += deg[some].sum()
            hot = some
        moved = np.where(hot, r, 0)
        q, r = q + (1 - alpha) * moved, r - moved + alpha * moved @ p


@pytest.mark.parametrize("engine", ["driver", "unrolled"])
def test_worked_example(spark, engine):
    start = diffusion.start_weighted(spark.createDataFrame([(0, 1, 0.4), (0, 2, 0.6)], "seed_id long, node_id long, mass double"))
    out = {r.node_id: (r.reserve, r.residual) for r in diffusion.diffuse(make(spark, GOLDEN), start, eps=0.1, strategy="threshold", engine=engine, rounds=4).collect()}
    expected = {1: (0.08, 0.352), 2: (0.12, 0.272), 3: (0.048, 0), 4: (0.048, 0), 5: (0, 0.08)}
    assert out.keys() == expected.keys()
    for n, (q, r) in expected.items():
        assert out[n] == (pytest.approx(q, abs=1e-12), pytest.approx(r, abs=1e-12))


@pytest.mark.parametrize("strategy,sigma", [("threshold", 1.0), ("hybrid", 0.0), ("hybrid", 0.1), ("hybrid", 1.0), ("sweep", 0.0)])
def test_strategies_equal_numpy_and_keep_their_bounds(spark, small, strategy, sigma):
    g, _, a, _ = small
    eps = 1e-3
    state = diffusion.diffuse(g, diffusion.start_unit(seeds_of(spark, 0, 7)), eps=eps, strategy=strategy, sigma=sigma).collect()
    exact_walk, deg = walk_matrix(a), a.sum(axis=1)
    for seed in (0, 7):
        q, r = np.zeros(40), np.zeros(40)
        for row in state:
            if row.seed_id == seed:
                q[row.node_id], r[row.node_id] = row.reserve, row.residual
        assert q.sum() + r.sum() == pytest.approx(1, abs=1e-12)
        gap = (exact_walk[seed] - q) / deg
        assert gap.min() > -1e-12 and gap.max() <= eps + 1e-12
        if strategy != "sweep":
            start = np.zeros(40)
            start[seed] = 1.0
            want, left, _ = push_numpy(a, start, eps, sigma)
            np.testing.assert_allclose(q, want, atol=1e-12)
            np.testing.assert_allclose(r, left, atol=1e-12)
            beta = 1 if sigma >= 1 else 2
            assert deg[q > 0].sum() <= beta / (0.2 * eps) + 1e-9


def test_sweep_residual_is_geometric(spark, small):
    g, *_ = small
    rows = diffusion.trace_frame(g, diffusion.start_unit(seeds_of(spark, 3)), eps=1e-2, strategy="sweep").orderBy("round").collect()
    assert len(rows) > 3
    for r in rows:
        assert r.residual_sum == pytest.approx(0.8 ** (r.round - 1), rel=1e-12)


def test_a_hub_in_chunks(spark):
    star = make(spark, [(0, i) for i in range(1, 30)] + [(1, 2)])
    packed = graph.adjacency(star, chunk_size=7)
    assert packed.where("node_id = 0").count() > 2
    whole = diffusion.diffuse(star, diffusion.start_unit(seeds_of(spark, 5)), eps=1e-3, engine="unrolled", rounds=6)
    state = diffusion.initial(star, diffusion.start_unit(seeds_of(spark, 5)), 0.8, 1e-3, False, None)
    for _ in range(6):
        state = diffusion.advance(state, packed, 0.8, 0.1)
    one, two = ({r.node_id: (r.reserve, r.residual) for r in x.collect()} for x in (whole, state))
    assert one.keys() == two.keys() and all(one[n] == pytest.approx(two[n], abs=1e-12) for n in one)


def test_edge_cases_of_graphs(spark):
    pairs = [(1, 2), (2, 1), (1, 2), (3, 3), (None, 4), (5, None), (10, 11)]
    g = make(spark, pairs)
    assert sorted((r.src, r.dst) for r in g.edges.collect()) == [(1, 2), (2, 1), (10, 11), (11, 10)]
    assert {r.node_id: r.component_id for r in graph.connected(g).collect()} == {1: 1, 2: 1, 10: 10, 11: 10}
    # a seed outside the graph, and eps too large: the cluster is the seed
    for seeds, eps in ((seeds_of(spark, 99), 1e-3), (seeds_of(spark, 1), 10.0)):
        scored = cluster.local_affinity(g, None, seeds, eps=eps)
        top = cluster.top(scored, 5, seeds).collect()
        assert [(r.node_id, r.score, r.rank) for r in top] == [(seeds.first().seed_id, 0.0, 1)]
    with pytest.raises(Exception, match="negative"):
        diffusion.start_weighted(spark.createDataFrame([(1, 1, -0.5)], "seed_id long, node_id long, mass double")).collect()
    empty = make(spark, spark.createDataFrame([], "a long, b long").collect())
    assert diffusion.diffuse(empty, diffusion.start_unit(seeds_of(spark, 1))).count() == 0


def test_a_batch_of_seeds_equals_each_alone(spark, small):
    g, *_ = small
    both = {(r.seed_id, r.node_id): r.reserve for r in diffusion.diffuse(g, diffusion.start_unit(seeds_of(spark, 1, 30)), eps=1e-2).collect()}
    for s in (1, 30):
        for r in diffusion.diffuse(g, diffusion.start_unit(seeds_of(spark, s)), eps=1e-2).collect():
            assert both[s, r.node_id] == pytest.approx(r.reserve, abs=1e-14)


def test_symmetry_and_two_sided_forms(spark, small):
    g, attrs, a, x = small
    seeds = seeds_of(spark, 2)
    assert exact.check_symmetry(g, seeds_of(spark, 2, 5, 9), tol=1e-7).agg(F.max("gap")).first()[0] < 1e-6
    s = attributes.exact_affinity(attrs)
    k = x @ x.T
    want_s = k / np.sqrt(np.outer(k.sum(axis=1), k.sum(axis=1)))
    got = np.zeros((40, 40))
    for r in s.collect():
        got[r.i, r.j] = r.s
    np.testing.assert_allclose(got, want_s, atol=1e-12)
    assert got.min() >= 0 and got.max() <= 1
    pi = walk_matrix(a)
    want = pi[2] @ want_s @ pi.T
    s = materialise(s, "s")
    lifted = np.zeros(40)
    for r in exact.two_sided_lifted(g, s, seeds, tol=1e-7).collect():
        lifted[r.node_id] = r.score
    np.testing.assert_allclose(lifted, want, atol=1e-6)
    z = factors.build(attrs, k=None)
    h = {r.node_id: np.array(r.h) for r in exact.smoothed_embeddings(g, z, steps=80).collect()}
    np.testing.assert_allclose([h[2] @ h[t] for t in range(40)], want, atol=1e-6)
    # the approximation stays below, and the bound holds for the lift over all nodes
    eps = 1e-4
    bound = (1 + (a.sum(axis=1) * want_s.max(axis=1)).sum()) * eps
    for scope in ("explored", "all"):
        rho = np.zeros(40)
        for r in cluster.local_affinity(g, z, seeds, eps=eps, scope=scope).collect():
            rho[r.node_id] = r.score
        assert (want - rho).min() > -1e-12
        if scope == "all":
            assert (want - rho).max() <= bound
    assert measures.affinity_bound(g, s, eps).first().bound == pytest.approx(bound)


def test_the_explored_lift_misses_a_far_twin(spark):
    n = 120
    g = make(spark, [(i, i + 1) for i in range(n - 1)])
    rows = [(i, "twin" if i in (0, n - 1) else f"own{i}", 1.0) for i in range(n)]
    attrs = spark.createDataFrame(rows, "node_id long, attr string, value double")
    z = materialise(factors.build(attrs, k=None), "z")
    eps, far = 1e-4, {}
    for scope in ("explored", "all"):
        found = {r.node_id: r.score for r in cluster.local_affinity(g, z, seeds_of(spark, 0), eps=eps, scope=scope).collect()}
        far[scope] = found.get(n - 1, 0.0)
    assert far["explored"] == 0.0 and far["all"] == pytest.approx(0.0556, abs=2e-3)


def test_svd_routes_and_bounds(spark, small):
    _, attrs, _, x = small
    true = np.linalg.svd(x, compute_uv=False)
    for method in ("gram", "randomized", "exact_small"):
        basis, values = factors.truncated_svd(attrs, 4, method, power=4)
        np.testing.assert_allclose(values, true[:4], rtol=1e-4)
        error, bound = measures.gram_error(attrs, basis, 4)
        assert error <= bound * (1 + 1e-3)
    k = x @ x.T
    want = k / np.sqrt(np.outer(k.sum(axis=1), k.sum(axis=1)))
    z = {r.node_id: np.array(r.z) for r in factors.build(attrs, k=8).collect()}
    np.testing.assert_allclose([[z[i] @ z[j] for j in range(40)] for i in range(40)], want, atol=1e-9)


def test_random_features(spark):
    rng = np.random.default_rng(0)
    x = np.abs(rng.standard_normal((6, 16)))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    for delta in (1.0, 2.0):
        for kind in ("orthogonal", "iid"):
            mean = np.mean([(y := factors.random_features(x, factors.frequencies(16, delta, s, kind), delta)) @ y.T for s in range(300)], axis=0)
            assert np.abs(mean / np.exp(x @ x.T / delta) - 1).mean() < 0.02
        m = factors.frequencies(16, delta)
        one, two = (factors.random_features(x, m, delta, scale) for scale in ("normalized", "as_printed"))
        np.testing.assert_allclose(two @ two.T, 2 * one @ one.T)
    m = factors.frequencies(16, 1.0, 4, orientation="rows").T
    gram = m @ m.T
    np.testing.assert_allclose(gram - np.diag(np.diag(gram)), 0, atol=1e-9)  # orthogonal rows
    lengths = np.mean([np.diag(factors.frequencies(16, 1.0, s).T @ factors.frequencies(16, 1.0, s)).mean() for s in range(200)])
    assert lengths == pytest.approx(16, rel=0.05)


def test_signed_attributes_are_guarded(spark):
    rows = spark.createDataFrame([(1, [1.0]), (2, [-1.0]), (3, [0.5])], "node_id long, y array<double>")
    assert {r.node_id: r.z[0] for r in factors.normalize(rows).collect()}[2] == 0
    assert factors.normalize(rows, "drop").count() == 2
    with pytest.raises(Exception, match="positive"):
        factors.normalize(rows, "error").collect()


def test_kernels_rank_alike_and_user_kernels(spark, small):
    _, attrs, _, x = small
    seeds = seeds_of(spark, 4)
    ranks = [[r.node_id for r in cluster.top(by_attrs.similarity(attrs, seeds, kind), 20).orderBy("rank").collect()] for kind in ("cosine", "expcos")]
    assert ranks[0] == ranks[1]
    rows = attributes.as_vectors(attrs).limit(2)
    assert rows.select(attributes.kernel("x", "x", fn=lambda a, b: F.size(a) + F.size(b)).alias("f")).first().f == 16


def test_mean_rank_of_the_published_table(spark):
    from attrgraph import catalog

    # The printed mean ranks.
    printed = {"PR-Nibble": 9.25, "APR-Nibble": 13.13, "HK-Relax": 8.63, "CRD": 16.38, "p-Norm FD": 16.5, "WFD": 15.63, "Jaccard": 13.13, "Adamic-Adar": 15, "Common-Nbrs": 16, "SimRank": 9.25, "SimAttr (C)": 10.88, "SimAttr (E)": 10.88, "AttriRank": 18.25, "Node2Vec (K-NN)": 20.5, "Node2Vec (SC)": 12.25, "Node2Vec (DBSCAN)": 9.5, "SAGE (K-NN)": 18, "SAGE (SC)": 18.5, "SAGE (DBSCAN)": 20, "CFANE (K-NN)": 4, "CFANE (SC)": 4.5, "CFANE (DBSCAN)": 14.25, "PANE (K-NN)": 6.88, "PANE (SC)": 5, "PANE (DBSCAN)": 10.88, "AALC(C)": 1.63, "AALC(E)": 2}
    got = {r.method: r.mean_rank for r in measures.mean_rank(catalog.published(spark)).collect()}
    assert got.keys() == printed.keys()
    assert all(abs(got[m] - v) < 0.006 for m, v in printed.items())


def test_link_similarities(spark, small):
    g, _, a, _ = small
    deg, both = a.sum(axis=1), a @ a
    aa = a @ np.diag(np.where(deg > 1, 1 / np.log(np.maximum(deg, 2)), 0)) @ a
    seeds = seeds_of(spark, 6)
    for run, want in ((links.common_neighbors, both[6]), (links.adamic_adar, aa[6]), (links.jaccard, both[6] / (deg[6] + deg - both[6]))):
        for r in run(g, seeds).collect():
            assert r.score == pytest.approx(want[r.node_id])
    p = a / deg[:, None]
    s = np.eye(40)
    for _ in range(3):
        s = 0.8 * p @ s @ p.T
        np.fill_diagonal(s, 1)
    for r in links.simrank(g, iterations=3).collect():
        assert r.score == pytest.approx(s[r.a, r.b])


def test_heat_kernel_is_near_the_exponential(spark, small):
    g, _, a, _ = small
    deg = a.sum(axis=1)
    p, t = a / deg[:, None], 5.0
    term, total = np.eye(40)[3], np.zeros(40)
    for k in range(60):
        total += np.exp(-t) * term
        term = term @ p * t / (k + 1)
    for r in heat.heat_kernel(g, seeds_of(spark, 3), t, 1e-4).collect():
        assert -1e-9 <= total[r.node_id] / deg[r.node_id] - r.score <= 1e-4


def test_flows(spark, small):
    g, _, a, _ = small
    deg = a.sum(axis=1)
    out = flow.pnorm_flow(g, seeds_of(spark, 5), 2.0, mass=float(deg.sum()) * 0.6, rounds=150, tol=1e-2)
    x, excess = np.zeros(40), {}
    for r in out.collect():
        x[r.node_id], excess[r.node_id] = r.score, r.excess
    source = np.zeros(40)
    source[5] = deg.sum() * 0.6
    left = source - (np.diag(deg) - a) @ x - deg  # what stands above capacity, by a dense product
    assert x.min() >= 0 and x[5] == x.max()
    for n, e in excess.items():
        assert e == pytest.approx(left[n], abs=1e-6)
        assert abs(e) <= 0.02 * deg[n] + 1e-6 or e < 0
    crd = flow.capacity_release(g, seeds_of(spark, 5), iterations=3, rounds=6).collect()
    assert {r.label for r in crd} <= set(range(4))
    total = sum(r.mass for r in crd)
    assert total == pytest.approx(2 * deg[5] * 4) or total == pytest.approx(2 * deg[5] * 2) or total == pytest.approx(2 * deg[5])


def test_attribute_weights_and_push(spark, small):
    g, attrs, a, x = small
    w = push.attr_weighted_graph(g, attrs, 0.7)
    for r in w.edges.collect():
        assert r.w == pytest.approx(np.exp(-((x[r.src] - x[r.dst]) ** 2).sum() / (2 * 0.49)))
    plain = {r.node_id: r.score for r in push.seeded_pagerank(g, seeds_of(spark, 1), eps=1e-3).collect()}
    state = {r.node_id: r.reserve / r.deg for r in diffusion.diffuse(g, diffusion.start_unit(seeds_of(spark, 1)), eps=1e-3, strategy="threshold").where("reserve > 0").collect()}
    assert plain == pytest.approx(state)


def test_measures_and_sweep(spark, small):
    g, attrs, a, x = small
    members = [0, 1, 2, 3, 8]
    c = spark.createDataFrame([(0, m) for m in members], "seed_id long, node_id long")
    deg, inside = a.sum(axis=1), a[np.ix_(members, members)].sum()
    vol = deg[members].sum()
    row = measures.conductance(c, g).first()
    assert row.conductance == pytest.approx((vol - inside) / min(vol, deg.sum() - vol))
    assert measures.scatter(c, attrs).first().scatter == pytest.approx(((x[members] - x[members].mean(axis=0)) ** 2).sum(axis=1).mean())
    scored = spark.createDataFrame([(0, m, 1.0 - i / 10) for i, m in enumerate(members)], "seed_id long, node_id long, score double")
    rows = cluster.sweep_cut(scored, g).orderBy("rank").collect()
    assert rows[-1].conductance == pytest.approx(row.conductance) and sum(r.best for r in rows) == 1
    truth = spark.createDataFrame([(i, "x" if i < 10 else "y") for i in range(40)] + [(39, "x")], "node_id long, label string")
    hit = measures.hits(c, truth).first()
    assert (hit.hits, hit.size, hit.truth_size) == (5, 5, 11)
    assert measures.truth_sizes(seeds_of(spark, 0, 39), truth).orderBy("seed_id").collect()[1].size == 40
    full = cluster.padded(cluster.top(scored, 3), spark.createDataFrame([(0, 6)], "seed_id long, size long"), g.degrees)
    assert full.count() == 6 and full.select("node_id").distinct().count() == 6
    quiet = [r.zeros for r in measures.zero_similarity(c, attrs).collect()]
    assert quiet == [sum((x[0] @ x[m]) == 0 for m in members[1:])]


def test_denoising_optimum(spark, small):
    g, attrs, *_ = small
    z = materialise(factors.build(attrs, k=None), "z")
    h = materialise(exact.smoothed_embeddings(g, z, steps=80, norm="sym"), "h")
    best = exact.denoise_objective(h, z, g).first().objective
    for s in range(3):
        moved = h.select("node_id", F.transform("h", lambda v, i: v + 0.02 * gaussian_hash(F.lit(s), F.col("node_id"), i)).alias("h"))  # noqa: B023
        assert exact.denoise_objective(moved, z, g).first().objective > best


def test_embeddings_and_extraction(spark):
    rng = np.random.default_rng(2)
    rows = [(i, (np.eye(3)[i // 20] + 0.05 * rng.standard_normal(3)).tolist()) for i in range(60)] + [(60, [9.0, 9.0, 9.0])]
    e = spark.createDataFrame(rows, "node_id long, e array<double>")
    groups = {r.node_id: r.group for r in embed.cluster_density(e, 0.4, 4, block=25).collect()}
    assert groups[60] == -61 and all(groups[i] == i // 20 * 20 for i in range(60))
    spectral = {r.node_id: r.group for r in embed.cluster_spectral(e.where("node_id < 60"), 3, 5).collect()}
    assert len({spectral[i] for i in range(20)}) == 1
    for metric in ("dot", "cosine", "euclid"):
        assert {r.node_id // 20 for r in embed.cluster_knn(e.where("node_id < 60"), seeds_of(spark, 25), 15, metric).collect()} == {1}
    size = spark.createDataFrame([(25, 7)], "seed_id long, size long")
    assert embed.group_of_seed(spark.createDataFrame(list(groups.items()), "node_id long, group long"), e, seeds_of(spark, 25), size).count() == 7


def test_sampled_walks_are_near(spark, small):
    g, _, a, _ = small
    got = np.zeros(40)
    for r in exact.walk_scores_mc(g, seeds_of(spark, 3), walks=3000).collect():
        got[r.node_id] = r.score
    assert np.abs(got - walk_matrix(a)[3]).max() < 0.03 and got.sum() == pytest.approx(1)


def test_quality_follows_the_published_order(spark):
    """On the largest overlap component: attributes with topology beat topology alone, push, and attributes alone."""
    from attrgraph import catalog

    b = catalog.overlap_bench(spark, "/root/testdata/sf0.01", 12)
    z = catalog._cosine(b)
    rows = {r.method: r.precision for r in evaluate.summary(evaluate.quality(b, {n: f for n, f in evaluate.methods(z, eps=1e-4).items() if n in ("aalc_cosine", "aalc_topology", "ppr_push", "attr_cosine")})).collect()}
    assert rows["aalc_cosine"] > max(rows["aalc_topology"], rows["attr_cosine"])


def test_builders_count_what_is_known(spark):
    line = table(spark, "/root/testdata/sf0.01", "lineitem")
    assert builders.copurchase(line, 2).count() == 3445
    assert builders.customer_supplier(table(spark, "/root/testdata/sf0.01", "orders"), line).count() == 4877
    assert builders.document_overlap(table(spark, "/root/testdata/sf0.01", "documents")).count() == 3011
    big = graph.largest_component(graph.from_edges(builders.bigram_overlap(table(spark, "/root/testdata/sf0.01", "documents"))))
    assert (big.degrees.count(), big.edges.count() // 2) == (803, 2114)


def test_bigram_query_reads_whole_texts_and_every_frequency(spark, tmp_path):
    from attrgraph import catalog

    late = [(i, " ".join(f"d{i}w{j}" for j in range(300)) + " one late passage") for i in (1, 2)]
    copies = [(10 + i, "the same short text") for i in range(8)]
    spark.createDataFrame([*late, *copies, (99, "alone here")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {(r.a, r.b) for r in catalog.QUERIES["graph_edges_bigram_overlap"](spark, str(tmp_path)).collect()}
    assert got == {(1, 2)} | {(10 + i, 10 + j) for i in range(8) for j in range(i + 1, 8)}


def test_large_groups_of_copies_stay_linked(spark, tmp_path):
    from attrgraph import catalog

    line = "a license line that many documents share"
    rows = [(i, f"{line}\n own text of number {i} and nothing else") for i in range(60)] + [(100, "short\nanother line of two documents"), (101, "another line of two documents")]
    spark.createDataFrame([*rows, (200, "on its own, with nothing shared")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    edges = {(r.a, r.b) for r in catalog.QUERIES["graph_edges_document_overlap_all_lines"](spark, str(tmp_path)).collect()}
    assert edges == {(i, j) for i in range(60) for j in range(i + 1, 60)} | {(100, 101)}
    parts = {r.node_id: r.component_id for r in catalog.QUERIES["components_all_lines"](spark, str(tmp_path)).collect()}
    assert parts == dict.fromkeys(range(60), 0) | {100: 100, 101: 100}


def test_flow_query_settles(spark, small):
    from attrgraph import catalog

    degrees = catalog.copurchase(spark, DATA).degrees
    left = catalog.QUERIES["pnorm_flow"](spark, DATA).join(degrees, "node_id").agg(F.max(F.col("excess") / F.col("deg"))).first()[0]
    assert left <= 1e-3 + 1e-6
    with pytest.raises(RuntimeError, match="not settled"):
        flow.pnorm_flow(small[0], seeds_of(spark, 5), 2.0, mass_per_degree=10.0, rounds=2, settle=True)


def test_engines_agree(spark, small, monkeypatch):
    from attrgraph.operators import ball

    g, *_ = small
    start = diffusion.start_unit(seeds_of(spark, 0, 7, 999))
    more = start.union(spark.createDataFrame([(7, 11, 2.5), (7, 3, 0.25)], "seed_id long, node_id long, mass double"))
    for strategy, sigma, eps in (("threshold", 0.1, 1e-2), ("hybrid", 0.1, 1e-2), ("hybrid", 0.0, 1e-3), ("sweep", 0.0, 1e-2)):
        told = []
        for engine, most in (("rounds", None), ("local", 10**6), ("local", 40)):
            monkeypatch.setattr(ball, "MOST_EDGES", most)
            rows = diffusion.diffuse(g, more, eps=eps, strategy=strategy, sigma=sigma, engine=engine).collect()
            told.append({(r.seed_id, r.node_id): (r.reserve, r.residual, r.deg, r.eps, r.budget, r.spent) for r in rows if r.reserve > 0 or r.residual > 0})
        assert told[0].keys() == told[1].keys() == told[2].keys() and len(told[0]) > 5
        for k, v in told[0].items():
            assert told[1][k] == pytest.approx(v, abs=1e-12) and told[2][k] == pytest.approx(v, abs=1e-12)


def test_work_follows_the_cluster_not_the_graph(spark):
    """Many more edges far from the seed: as many adjacency rows are fetched, from as few buckets."""
    from attrgraph.operators import graph as graphs

    near = [(i, j) for i in range(12) for j in range(i)]
    logs = []
    for far in (0, 3000):
        g = make(spark, near + [(100 + i, 101 + i) for i in range(far)] + [(100 + i, 140 + i) for i in range(far)]).kept()
        for engine in ("local", "rounds"):
            g.packed.log.clear()
            state = diffusion.diffuse(g, diffusion.start_unit(seeds_of(spark, 3)), eps=1e-3, engine=engine)
            logs.append([(x["nodes"], x["buckets"]) for x in g.packed.log] + [state.count()])
    assert logs[0] == logs[2] and logs[1] == logs[3]
    assert all(n <= 12 for n, _ in logs[0][:-1]) and logs[0][0] == (1, 1) and graphs.LEAST_BUCKETS > logs[0][0][1]


def test_a_graph_is_packed_once(spark, small):
    g, *_ = small
    g = g.kept()
    assert g.kept() is g and g.packed is g.packed and g.degrees is g.degrees


def test_local_baselines_equal_their_rounds(spark, small):
    g, *_ = small
    seeds = seeds_of(spark, 3, 17)
    runs = {
        "heat": lambda e: heat.heat_kernel(g, seeds, 3.0, 1e-3, engine=e),
        # one seed: the engine of rounds goes on with all seeds until the last one settles
        "flow": lambda e: flow.pnorm_flow(g, seeds_of(spark, 17), 2.0, mass_per_degree=12.0, tol=1e-1, engine=e),
        "release": lambda e: flow.capacity_release(g, seeds, iterations=2, rounds=3, engine=e),
    }
    for name, run in runs.items():
        one, two = ({(r.seed_id, r.node_id): r.score for r in run(e).collect()} for e in ("local", "rounds"))
        assert len(one) > 5 and one.keys() == two.keys(), name
        assert all(one[k] == pytest.approx(two[k], abs=1e-9) for k in one), name


def test_a_graph_sent_whole_gives_the_fetched_result(spark, small):
    from dataclasses import replace

    g, *_ = small
    g = g.kept()
    seeds = seeds_of(spark, 0, 7, 999)
    for run in (lambda g: diffusion.diffuse(g, diffusion.start_unit(seeds), eps=1e-3, engine="local").selectExpr("seed_id", "node_id", "reserve as score"), lambda g: heat.heat_kernel(g, seeds, 3.0, 1e-3, engine="local")):
        one, two = ({(r.seed_id, r.node_id): r.score for r in run(x).collect()} for x in (g, replace(g, whole=True)))
        assert len(one) > 5 and one.keys() == two.keys()
        assert all(one[k] == pytest.approx(two[k], abs=1e-12) for k in one)


def test_wide_profiles_are_summed_by_place(spark, small, monkeypatch):
    g, attrs, *_ = small
    z = materialise(factors.build(attrs, k=None), "z")
    pi = spark.createDataFrame([(s, n, 0.5 + s + n) for s in (1, 2) for n in range(s, 30)], "seed_id long, node_id long, score double")
    narrow = {r.seed_id: r.psi for r in cluster.seed_profile(pi, z).collect()}
    monkeypatch.setattr(cluster, "WIDE", 0)
    for r in cluster.seed_profile(pi, z).collect():
        assert list(r.psi) == pytest.approx(list(narrow[r.seed_id]), rel=1e-12)


@pytest.mark.parametrize("engine", ["local", "rounds"])
def test_rounds_end_at_their_limit(spark, small, engine):
    g, _, a, _ = small
    start = diffusion.start_unit(seeds_of(spark, 0))
    state = diffusion.diffuse(g, start, eps=1e-4, strategy="sweep", engine=engine, most_rounds=3).collect()
    assert sum(r.residual for r in state) == pytest.approx(0.8**3, rel=1e-12)


def test_trace_ends_at_its_limit(spark, small):
    g, *_ = small
    rows = diffusion.trace_frame(g, diffusion.start_unit(seeds_of(spark, 0, 7)), eps=1e-4, strategy="sweep", most_rounds=3).collect()
    assert sorted((r.seed_id, r.round, r["mode"]) for r in rows) == [(s, i, "sweep") for s in (0, 7) for i in (1, 2, 3)]


@pytest.mark.parametrize("norm", ["walk", "reverse", "sym"])
def test_whole_graph_levels_equal_table_levels(spark, small, norm):
    g, *_ = small
    start = spark.createDataFrame([(1, 0, 1.0), (1, 5, -2.0), (2, 3, 0.5), (2, 99, 1.0)], "seed_id long, node_id long, mass double")
    rows = [exact.diffuse(h, start, steps=4, norm=norm).collect() for h in (g, graph.Graph(g.edges))]
    one, other = ({(r.seed_id, r.node_id): r.score for r in x} for x in rows)
    assert one.keys() == other.keys() and one == pytest.approx(other, abs=1e-14)


def test_symmetry_and_two_sided_without_all_pairs(spark, small):
    g, attrs, a, _ = small
    split = graph.from_edges(g.edges.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b")).union(spark.createDataFrame([(100, 101)], "a long, b long"))).kept()
    gaps = exact.check_symmetry(split, split.degrees.select(F.col("node_id").alias("seed_id")), tol=1e-8).collect()
    assert len(gaps) == 40 * 39 // 2 + 1 and max(r.gap for r in gaps) < 1e-12
    z = factors.build(attrs, k=None)
    held = z.select(F.col("node_id").alias("i"), F.col("z").alias("x")).crossJoin(z.select(F.col("node_id").alias("j"), F.col("z").alias("y")))
    pairs = held.selectExpr("i", "j", "aggregate(zip_with(x, y, (p, q) -> p * q), 0d, (s, v) -> s + v) as s").where("s > 0")
    walk, s = walk_matrix(a), np.zeros((40, 40))
    for r in pairs.collect():
        s[r.i, r.j] = r.s
    want = (walk @ s @ walk.T)[3]
    for affinity in (z, pairs):
        for run in (exact.two_sided, exact.two_sided_lifted):
            got = {r.node_id: r.score for r in run(g, affinity, seeds_of(spark, 3), tol=1e-10).collect()}
            np.testing.assert_allclose([got[i] for i in range(40)], want, atol=1e-9)


def test_feature_bias_counts_equal_rows_once(spark):
    x = np.array([[1.0, 0.0], [0.6, 0.8], [0.6, 0.8], [1.0, 0.0], [0.6, 0.8]])
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "node_id long, x array<double>")
    for delta, kind, mean, spread in measures.feature_bias(rows, (1.0, 2.0), 10):
        ys = [factors.random_features(x, factors.frequencies(2, delta, s, kind), delta) for s in range(10)]
        ratio = np.stack([y @ y.T / np.exp(x @ x.T / delta) for y in ys])
        assert (mean, spread) == pytest.approx((ratio.mean(), ratio.std(axis=0).mean()), rel=1e-9)


def test_svd_and_cross_fusion_of_more_attributes_than_the_gram_route_takes(spark, small):
    g, *_ = small
    wide = spark.range(40).select(F.col("id").alias("node_id"), F.explode(F.sequence(F.lit(0), F.lit(54))).alias("j")).select("node_id", (F.col("node_id") * 55 + F.col("j")).cast("string").alias("attr"), F.lit(1.0).alias("value"))
    assert wide.select("attr").distinct().count() > factors.GRAM_LIMIT
    e = embed.cross_fusion(g, materialise(attributes.l2_normalize(wide), "attrs"), k=3, rounds=1, neighbours=3, steps=1).collect()
    assert len(e) == 40 and all(len(r.e) == 3 for r in e)


@pytest.mark.parametrize("name,read", [("mean_rank", "events"), ("diffuse_golden", "lineitem")])
def test_worked_examples_read_given_tables(spark, name, read, monkeypatch):
    from attrgraph import catalog

    asked = []
    monkeypatch.setattr(catalog, "table", lambda s, d, t, *c: asked.append(t) or table(s, d, t, *c))
    assert catalog.QUERIES[name](spark, DATA).count() and read in asked


def test_exponential_row_sums_by_blocks_equal_all_pairs(spark, small, monkeypatch):
    _, attrs, _, x = small
    twice = materialise(attrs.union(attrs.withColumn("node_id", F.col("node_id") + 100)), "attrs")
    want = 2 * np.exp(x @ x.T / 2).sum(axis=1)
    by_block = {r.node_id: r.total for r in attributes._sums_of_blocks(twice, "expcos", 2.0, block=16).collect()}
    monkeypatch.setattr(attributes, "WIDE", 0)
    joined = {r.node_id: r.total for r in attributes.row_sums(twice, "expcos", 2.0).collect()}
    np.testing.assert_allclose([by_block[i % 40 + 100 * (i // 40)] for i in range(80)], np.tile(want, 2), rtol=1e-12)
    assert by_block == pytest.approx(joined, rel=1e-12)


@pytest.mark.parametrize("block", [3, 2_000_000])
def test_links_by_shared_keys_equal_brute_force(spark, monkeypatch, block):
    rng = random.Random(5)
    keys = {i: frozenset(rng.sample(range(12), rng.randint(0, 3))) for i in range(40)} | {100 + i: frozenset([1, 2]) for i in range(6)} | {200: frozenset([99])}
    rows = spark.createDataFrame([(f"k{k}", i) for i, ks in keys.items() for k in ks] + [(None, 7), ("k1", None)], "k string, i long")
    monkeypatch.setattr(sharing, "BLOCK", block)
    monkeypatch.setattr(sharing, "FRAME", 16)
    held = sharing.classes(rows, "k", "i")
    want = {s: {(a, b) for a in keys for b in keys if a < b and len(keys[a] & keys[b]) >= s} for s in (1, 2)}
    for s in (1, 2):
        got = [(r.a, r.b) for r in sharing.pairs(held, s).collect()]
        assert len(got) == len(set(got)) and set(got) == want[s]
    label = {i: None if i % 5 == 0 else "xyz"[i % 3] for i in keys}
    counts, names = sharing.link_counts(held, spark.createDataFrame(list(label.items()), "i long, label string"))
    degree = {i: sum(i in p for p in want[1]) for i in keys}
    assert {r.i: r.links for r in counts.collect()} == {i: n for i, n in degree.items() if keys[i] - {99}}
    told = measures.counted_homophily(counts, names).first()
    same = sum(label[a] is not None and label[a] == label[b] for a, b in want[1])
    assert told.labelled_edges == len(want[1]) and told.homophily == pytest.approx(same / len(want[1]))
    for r in measures.counted_conductance(counts, names).collect():
        volume, inside = sum(degree[i] for i in keys if label[i] == r.label), 2 * sum(label[a] == label[b] == r.label for a, b in want[1])
        assert (r.volume, r.cut) == (volume, volume - inside)
        assert r.conductance == pytest.approx(r.cut / min(volume, 2 * len(want[1]) - volume))
    empty = sharing.classes(rows.limit(0), "k", "i")
    assert sharing.pairs(empty).count() == 0 and measures.counted_homophily(*sharing.link_counts(empty, spark.createDataFrame([], "i long, label string"))).first() == (None, 0)


def test_pairs_of_all_lines_are_not_shuffled(spark, tmp_path):
    from attrgraph import catalog

    spark.createDataFrame([(i, "a line that every document of the table has") for i in range(30)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    edges = catalog.QUERIES["graph_edges_document_overlap_all_lines"](spark, str(tmp_path))
    plan = edges._jdf.queryExecution().executedPlan().toString()
    assert edges.count() == 30 * 29 // 2 and "Join" not in plan and "Aggregate" not in plan


def test_pairs_of_bigrams_are_not_shuffled(spark, tmp_path):
    from attrgraph import catalog

    spark.createDataFrame([(i, f"three words shared then own{i}") for i in range(30)] + [(50, "three words"), (51, None)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    edges = catalog.QUERIES["graph_edges_bigram_overlap"](spark, str(tmp_path))
    plan = edges._jdf.queryExecution().executedPlan().toString()
    assert edges.count() == 30 * 29 // 2 and "Join" not in plan and "Aggregate" not in plan


@pytest.fixture(scope="module")
def shared(spark):
    """(the graph of items that share a key without its edges, the same with them); copies, a hub key, and items without links."""
    rng = random.Random(11)
    keys = {i: frozenset(rng.sample(range(30), rng.randint(0, 3))) | ({40} if i % 7 == 0 else set()) for i in range(60)} | {100 + i: frozenset([1, 2]) for i in range(4)} | {200: frozenset([99])}
    rows = spark.createDataFrame([(f"k{k}", i) for i, ks in keys.items() for k in ks] + [(None, 7), ("k1", None)], "k string, i long")
    return sharing.SharedGraph(sharing.classes(rows, "k", "i")), graph.from_edges(builders.co_occurrence(rows, "k", "i")).kept()


def test_graph_of_shared_keys_equals_listed_edges(spark, shared, monkeypatch):
    g, listed = shared
    monkeypatch.setattr(sharing, "BLOCK", 50)
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(g.degrees) == rows(listed.degrees) and g.size == listed.size and rows(g.edges) == rows(listed.edges)
    some = materialise(graph.pick_seeds(g.degrees, 5).select(F.col("seed_id").alias("node_id")), "nodes")
    near = lambda x: {r.node_id: sorted(map(tuple, r.nb)) for r in x.packed.of(some).collect()}
    assert near(g) == near(listed)
    seeds = graph.pick_seeds(g.degrees, 6)
    want = {(r.seed_id, r.node_id): r.score for r in push.seeded_pagerank(listed, seeds, eps=1e-3).collect()}
    assert {(r.seed_id, r.node_id): r.score for r in push.seeded_pagerank(g, seeds, eps=1e-3).collect()} == pytest.approx(want, rel=1e-12)


def test_users_near_makes_no_table_of_pairs(spark, tmp_path, monkeypatch):
    from attrgraph import catalog

    def refuse(*args, **options):
        raise AssertionError("pairs were listed")

    spark.sql("select id as user_id, timestamp_ntz '2024-01-01 00:00:00' as ts from range(40)").write.parquet(f"{tmp_path}/events.parquet")
    monkeypatch.setattr(builders, "co_occurrence", refuse)
    rows = catalog.QUERIES["users_near"](spark, str(tmp_path)).collect()
    assert {r.seed_id for r in rows if r.seed_id == r.node_id} and len({r.seed_id for r in rows}) == 3


def test_common_neighbours_and_component_of_shared_keys_equal_listed_edges(spark, shared, monkeypatch):
    g, listed = shared
    monkeypatch.setattr(sharing, "BLOCK", 50)
    seeds = materialise(graph.pick_seeds(g.degrees, 6), "seeds")
    for method in (links.common_neighbors, links.adamic_adar, links.jaccard):
        got, want = ({(r.seed_id, r.node_id): r.score for r in method(x, seeds).collect()} for x in (g, listed))
        assert len(want) > 20 and got == pytest.approx(want, rel=1e-12)
    apart = spark.createDataFrame([("a", 1), ("a", 2), ("b", 2), ("b", 3), ("c", 10), ("c", 11), ("d", 11), ("d", 12), ("e", 20), ("e", 21)], "k string, i long")
    assert sorted(r.node_id for r in sharing.SharedGraph(sharing.classes(apart, "k", "i")).largest().degrees.collect()) == [1, 2, 3]


def test_mean_rank_own_lists_no_pairs_of_users(spark, monkeypatch):
    from attrgraph import catalog

    def refuse(*args, **options):
        raise AssertionError("pairs of users were listed")

    monkeypatch.setattr(builders, "coactivity", refuse)
    b = catalog.activity_bench(spark, DATA, 25, listed=False)
    small = {m: f for m, f in evaluate.methods(factors.build(b.attrs, k=None), eps=1e-4).items() if m in ("ppr_push", "jaccard")}
    assert {r.method for r in evaluate.quality(b, small).collect()} == set(small)
    monkeypatch.setattr(catalog, "overlap_bench", lambda *a: b)
    monkeypatch.setattr(evaluate, "quality", lambda *a: spark.createDataFrame([("m", 1, 1, 2, 2)], "method string, seed_id long, hits long, size long, truth_size long"))
    assert catalog.QUERIES["mean_rank_own"](spark, DATA).count() == 1


@pytest.fixture(scope="module")
def rows_of_shared(spark):
    """Unit rows with copies for the items of ``shared``; some items have none, and one that isn't in the graph has one."""
    rng = random.Random(5)
    kinds = [[(f"a{j}", float(rng.randint(1, 4))) for j in rng.sample(range(5), 2)] for _ in range(6)]
    rows = [(i, a, v) for i in (*range(60), 100, 101, 102, 200) if i % 9 for a, v in kinds[min(i // 20, 5) if i < 100 else 4]]
    return materialise(attributes.l2_normalize(spark.createDataFrame(rows, "node_id long, attr string, value double")), "attrs")


SEED_METHODS = {
    "flow": lambda g, attrs, seeds: flow.pnorm_flow(g, seeds, mass=150.0),
    "flow_4": lambda g, attrs, seeds: flow.pnorm_flow(g, seeds, p=4.0, mass=60.0, rounds=40, settle=False),
    "weighted_flow": lambda g, attrs, seeds: flow.weighted_flow(g, attrs, seeds, mass=60.0),
    "more_than_it_holds": lambda g, attrs, seeds: flow.pnorm_flow(g, seeds, mass=1e4, tol=1e-2),
    "release": lambda g, attrs, seeds: flow.capacity_release(g, seeds),
    "weighted_pagerank": lambda g, attrs, seeds: push.attr_weighted_pagerank(g, attrs, seeds, eps=1e-3),
    "attribute_pagerank": lambda g, attrs, seeds: by_attrs.attribute_pagerank(g, attrs).withColumn("seed_id", F.lit(0)),
    "simrank": lambda g, attrs, seeds: links.simrank(g, iterations=3, seeds=seeds),
    "simrank_mc": lambda g, attrs, seeds: links.simrank_mc(g, seeds, walks=12, steps=4),
}


@pytest.mark.parametrize("method", SEED_METHODS)
def test_methods_by_class_equal_listed_edges(spark, shared, rows_of_shared, monkeypatch, method):
    g, listed = shared
    seeds = materialise(graph.pick_seeds(g.degrees, 4), "seeds")
    told = lambda x: {(r.seed_id, r.node_id): r.score for r in SEED_METHODS[method](x, rows_of_shared, seeds).collect()}
    want = told(listed)
    monkeypatch.setattr(sharing, "pairs", lambda *a, **o: (_ for _ in ()).throw(AssertionError("pairs were listed")))
    monkeypatch.setattr(alike, "MOVES", 1000)
    got = told(g)
    assert len(want) > 10 and got == pytest.approx(want, rel=1e-9, abs=1e-12)


def test_classes_that_do_not_fit_take_the_tables(spark, shared, rows_of_shared, monkeypatch):
    g, listed = sharing.SharedGraph(shared[0].held), shared[1]
    monkeypatch.setattr(alike, "CLASS_LINKS", 10)
    seeds = materialise(graph.pick_seeds(g.degrees, 2), "seeds")
    assert not alike.fits(g)
    for method in ("weighted_flow", "release", "simrank_mc"):
        got, want = ({(r.seed_id, r.node_id): r.score for r in SEED_METHODS[method](x, rows_of_shared, seeds).collect()} for x in (g, listed))
        assert len(want) > 5 and got == pytest.approx(want, rel=1e-9, abs=1e-12)


def test_an_unsettled_flow_by_class_is_an_error(shared):
    g, seeds = shared[0], graph.pick_seeds(shared[0].degrees, 1)
    with pytest.raises(RuntimeError, match="not settled"):
        flow.pnorm_flow(g, seeds, mass=100.0, rounds=1)
    assert flow.pnorm_flow(g, seeds, mass=100.0, rounds=1, settle=False).count() == 1


def test_conductance_by_class_equals_listed_edges(spark, shared, rows_of_shared):
    g, listed = shared
    clusters = spark.createDataFrame([(s, i) for s in (1, 2, 3) for i in range(0, 60, s + 1)] + [(3, 100), (3, 101), (9, 999), (9, 200)], "seed_id long, node_id long")
    for one, other in ((g, listed), (push.attr_weighted_graph(g, rows_of_shared), push.attr_weighted_graph(listed, rows_of_shared))):
        got, want = ({r.seed_id: tuple(r)[1:] for r in measures.conductance(clusters, x).collect()} for x in (one, other))
        assert len(want) == 3 and got.keys() == want.keys()
        for s, values in want.items():
            assert got[s] == pytest.approx(values, rel=1e-9)


def test_cohesion_measures_all_methods_at_once(spark, shared, monkeypatch):
    g, listed = shared
    cut = lambda rows: spark.createDataFrame(rows, "seed_id long, node_id long")
    clusters = {"a": cut([(s, i) for s in (1, 2) for i in range(0, 40, s + 1)]), "b": cut([(1, i) for i in range(20)] + [(2, 2)]), "c": cut([(2, i) for i in range(5, 30)])}
    truth = spark.createDataFrame([(i, f"t{i % 3}") for i in range(60)], "node_id long, label string")
    attrs = spark.createDataFrame([(i, f"x{i % 4}", 1.0 + i % 2) for i in range(60)], "node_id long, attr string, value double")
    want = {}
    for name, c in clusters.items():
        told = measures.hits(c, truth).join(measures.conductance(c, listed), "seed_id").join(measures.scatter(c, attrs), "seed_id").collect()
        mean = lambda f: sum(map(f, told)) / len(told)  # noqa: B023, E731
        want[name] = (mean(lambda r: r.hits / r["size"]), mean(lambda r: r.hits / r.truth_size), mean(lambda r: r.conductance), mean(lambda r: r.scatter), len(told))
    calls, every = [], measures.conductance
    monkeypatch.setattr(measures, "conductance", lambda *a: calls.append(a) or every(*a))
    for x, weights in ((g, 50), (g, 16_000_000), (listed, 0)):
        monkeypatch.setattr(sharing, "WEIGHTS", weights)  # one block of classes, or several
        got = {r.method: tuple(r)[1:] for r in evaluate.cohesion(evaluate.Bench(x, attrs, truth, cut([(1, 1), (2, 2)]).select("seed_id")), clusters).collect()}
        assert got.keys() == want.keys() and all(got[m] == pytest.approx(v, rel=1e-9) for m, v in want.items())
    assert len(calls) == 3  # not one a method


def test_hashes_of_walks_equal_those_of_spark(spark):
    ids = [0, 1, -5, 2**40 + 7, -(2**62)]
    rows = spark.createDataFrame([(w, i) for w in (1, 200) for i in ids], "w int, i long").select(hash_uniform(F.lit(1), "w", F.lit(3), "i").alias("u"))
    want = [r.u for r in rows.collect()]
    got = alike.uniform((1, 4), (np.array([[1], [200]]), 4), (3, 4), (np.array([ids]), 8))
    assert got.ravel().tolist() == want


def test_precision_by_method_users_lists_no_pairs(spark, monkeypatch):
    from attrgraph import catalog

    def refuse(*args, **options):
        raise AssertionError("pairs of users were listed")

    monkeypatch.setattr(builders, "coactivity", refuse)
    monkeypatch.setattr(sharing, "pairs", refuse)
    monkeypatch.setattr(evaluate, "PAIR_TABLE_NODES", 5)
    every = evaluate.methods
    monkeypatch.setattr(evaluate, "methods", lambda *a, **o: {m: f for m, f in every(*a, **o).items() if m in ("weighted_flow", "simrank")})
    rows = {r.method: r for r in catalog.QUERIES["precision_by_method_users"](spark, DATA).collect()}
    assert len(rows) == 2 and all(0 <= r.precision <= 1 and r.seeds > 0 for r in rows.values())


def test_nearest_rows_with_many_copies_equal_brute_force(spark, monkeypatch):
    rng = np.random.default_rng(4)
    kinds = rng.integers(-2, 3, (12, 3)).astype(float)
    x = kinds[rng.integers(0, 12, 90)]
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "node_id long, x array<double>")
    seen, asked = [], builders._block_knn
    monkeypatch.setattr(builders, "_block_knn", lambda frames, ids, vectors, k: asked(frames, ids, vectors, k))
    monkeypatch.setattr(builders, "partial", lambda f, **o: seen.extend(o["ids"].tolist()) or (lambda frames: f(frames, **o)))
    for k in (1, 4, 200):
        got = {(r.q, r["rank"]): (r.other, r.dot) for r in builders.vector_knn(rows, k, block=5).collect()}
        want = {}
        for q in range(90):
            d = x @ x[q]
            near = [i for i in np.lexsort((np.arange(90), -d)) if i != q][:k]
            want |= {(q, at + 1): (int(i), float(d[i])) for at, i in enumerate(near)}
        assert got == want
    assert len(seen) == 3 * len(np.unique(x, axis=0))  # equal rows are compared once


@pytest.mark.parametrize("norm", ["walk", "sym"])
def test_smoothing_of_whole_rows_equals_positions(spark, small, monkeypatch, norm):
    g, attrs, *_ = small
    z = attributes.as_vectors(attrs).select("node_id", F.col("x").alias("z")).where("node_id < 25")
    monkeypatch.setattr(exact, "_small", lambda g: False)
    whole = {r.node_id: r.h for r in exact.smoothed_embeddings(g, z, 0.5, 3, norm).collect()}
    monkeypatch.setattr(exact, "PACKED", 0)
    apart = {r.node_id: r.h for r in exact.smoothed_embeddings(g, z, 0.5, 3, norm).collect()}
    assert whole.keys() == apart.keys()
    for n, h in apart.items():
        assert whole[n] == pytest.approx(h, abs=1e-12)
