"""Goldens, brute force, invariants and statistics of the method."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from veilwalk.config import WalkConfig, check_bins, default_bins
from veilwalk.functions import draws
from veilwalk.operators import align, baselines, bins, classify, cooccur, cost, degree, encoder, metrics, predictor, skipgram, tree, walks
from veilwalk.plans import pipeline
from veilwalk.plans.lineage import Store, positions
from veilwalk.sources import graphs, tables

TRIANGLES = [(1, 2), (1, 3), (2, 3), (3, 4), (4, 5), (4, 6), (5, 6)]
DELTA = np.array([[0, 0, 2, 7, 6, 6], [0, 0, 2, 7, 6, 6], [2, 2, 0, 10, 7, 7], [7, 7, 10, 0, 2, 2], [6, 6, 7, 2, 0, 0], [6, 6, 7, 2, 0, 0]], float)


@pytest.fixture(scope="module")
def golden(spark):
    edges = graphs.symmetrize(spark.createDataFrame(TRIANGLES, "v long, u long")).cache()
    plan = spark.createDataFrame([(v, v - 1, 1 if v < 4 else 2) for v in range(1, 7)], "v long, ordinal long, bin int")
    vectors = degree.degree_vectors(degree.bin_counts(edges, plan, 2), None, 2)
    matrices = degree.ordered_matrices(edges, vectors).cache()
    dissim = align.pairs_within(matrices).cache()
    return edges, plan, vectors, matrices, dissim


def collect(df):
    return sorted(tuple(r) for r in df.collect())


def test_golden_vectors_and_orders(golden):
    _, _, vectors, matrices, _ = golden
    assert {r["v"]: r["c"] for r in vectors.collect()} == {1: [2, 0], 2: [2, 0], 3: [2, 1], 4: [1, 2], 5: [0, 2], 6: [0, 2]}
    assert {r["v"]: r["nbr_order"] for r in matrices.collect()} == {1: [2, 3], 2: [1, 3], 3: [1, 2, 4], 4: [5, 6, 3], 5: [6, 4], 6: [5, 4]}


def test_golden_dissimilarities(golden, spark):
    _, _, _, matrices, dissim = golden
    want = [(u, v, DELTA[u - 1, v - 1]) for u in range(1, 7) for v in range(u + 1, 7)]
    assert collect(dissim) == want
    pairs = dissim.select("u", "v")
    for kernel in ("arrow", "expr"):
        assert collect(align.dissimilarity(matrices, pairs, kernel=kernel).select("u", "v", "delta")) == want
    assert {x[2] for x in collect(align.dissimilarity(matrices, pairs, prune_above=6.0))} <= {x[2] for x in want}
    kept = {x[:2] for x in collect(align.dissimilarity(matrices, pairs, prune_above=6.0))}
    assert {x[:2] for x in want if x[2] <= 6} <= kept


def test_second_bin_plan(golden, spark):
    edges = golden[0]
    plan = spark.createDataFrame([(v, v - 1, 1 if v % 2 else 2) for v in range(1, 7)], "v long, ordinal long, bin int")
    m = degree.ordered_matrices(edges, degree.degree_vectors(degree.bin_counts(edges, plan, 2), None, 2))
    upper = [x[2] for x in collect(align.pairs_within(m))]
    assert upper == [2, 4, 5, 4, 6, 4, 2, 2, 4, 6, 1, 3, 4, 3, 2]


def test_golden_trees_and_laws(golden, spark):
    edges, plan, vectors, _, dissim = golden
    merges = tree.linkage(DELTA, "average")
    assert [m[:2] for m in merges[:4]] == [(0, 1), (4, 5), (0, 2), (3, 4)] and abs(merges[4][2] - 6.8889) < 1e-4
    for method in ("average", "hybrid", "single", "complete"):
        leaves = tree.build_tree(dissim, graphs.roster(edges), method)
        rows = collect(leaves)
        size = tree.lca_sizes([p for _, p in rows])
        assert size[0, 1] == 2 and size[0, 2] == size[1, 2] == 3 and size[3, 4] == 3 and size[4, 5] == 2 and (size[:3, 3:] == 6).all()
        bad = tree.tree_violations(leaves).first()
        assert (bad["leaves"], bad["internal"], bad["roots"], bad["violations"]) == (6, 5, 1, 0)
        pairs = dissim.select("u", "v")
        assert {(u, v): n for u, v, n in collect(tree.lca_leaves(leaves, pairs))} == {(u, v): size[u - 1, v - 1] for u in range(1, 7) for v in range(u + 1, 7)}
    law = {(r["v"], r["w"]): r["pr"] for r in encoder.law_rows(encoder.encoder_table(dissim, leaves, 0.1)).collect()}
    assert np.allclose([law[1, w] for w in range(1, 7)], [0.381905, 0.381905, 0.209594, 0.005727, 0.010435, 0.010435], atol=1e-6)
    assert np.allclose([law[3, w] for w in range(1, 7)], [0.257647, 0.257647, 0.469463, 0.001164, 0.007040, 0.007040], atol=1e-6)
    two = {(r["v"], r["w"]): r["pr"] for r in encoder.law_rows(encoder.encoder_table(dissim, leaves, 2.0)).collect()}
    assert abs(two[1, 1] - 0.499998) < 1e-6 and abs(two[3, 3] - 0.999988) < 1e-6
    wanted = predictor.demand(vectors, plan)
    for near in ("leaves", "hops", "depth"):
        pools = {r["u"]: r["pool"] for r in predictor.tree_pool(dissim, leaves, plan, wanted, near).collect()}
        assert near != "leaves" or (pools[1] == [2, 3] and pools[3] == [1, 2, 5]), pools
        assert {u: len(p) for u, p in pools.items()} == {1: 2, 2: 2, 3: 3, 4: 3, 5: 2, 6: 2}


def test_toy_alignments():
    a, b = np.array([[1, 2], [3, 1], [0, 0]], float), np.array([[1, 1], [2, 2]], float)
    assert align.align_many([a, a, a[:1]], [b, a, b[:1]]).tolist() == [7, 0, 1]
    assert align.align_many([np.zeros((1, 2))], [a])[0] == np.abs(a).sum()


def brute_align(a, b, one_sided=False):
    if one_sided and len(a) < len(b):
        a, b = b, a
    d = np.full((len(a) + 1, len(b) + 1), np.inf)
    d[0, 0] = 0
    for i in range(1, len(a) + 1):
        for j in range(1, len(b) + 1):
            steps = [d[i - 1, j - 1], d[i - 1, j]] + ([] if one_sided else [d[i, j - 1]])
            d[i, j] = np.abs(a[i - 1] - b[j - 1]).sum() + min(steps)
    return d[-1, -1]


def test_alignment_against_brute_force():
    rng = np.random.default_rng(0)
    left = [rng.normal(size=(rng.integers(1, 14), 3)) for _ in range(120)]
    right = [rng.normal(size=(rng.integers(1, 14), 3)) for _ in range(120)]
    for one_sided in (False, True):
        want = [brute_align(a, b, one_sided) for a, b in zip(left, right, strict=True)]
        assert np.allclose(align.align_many(left, right, one_sided), want)
    full = align.align_many(left, right)
    assert (align.align_many(left, right, band=2) >= full - 1e-9).all()
    assert np.allclose(align.align_many(left, right, band=50), full)
    assert np.allclose(align.align_many(right, left), full)
    assert all(align.lower_bound(a, b) <= f + 1e-9 for a, b, f in zip(left, right, full, strict=True))


def test_linkage_against_brute_force():
    rng = np.random.default_rng(1)
    for method in ("average", "single", "complete"):
        x = rng.normal(size=(14, 2))
        d = np.abs(x[:, None] - x[None]).sum(2)
        groups, heights = [[i] for i in range(14)], []
        how = {"average": np.mean, "single": np.min, "complete": np.max}[method]
        while len(groups) > 1:
            h, i, j = min((how(d[np.ix_(groups[i], groups[j])]), i, j) for i in range(len(groups)) for j in range(i + 1, len(groups)))
            groups[i] = groups[i] + groups.pop(j)
            heights.append(h)
        assert np.allclose(sorted(heights), sorted(m[2] for m in tree.linkage(d, method)))


def test_mutual_groups_stay_whole():
    rng = np.random.default_rng(2)
    x = np.r_[rng.normal(size=(6, 2)), 50 + 0.1 * rng.normal(size=(4, 2)), -50 + 0.1 * rng.normal(size=(3, 2))]
    d = np.abs(x[:, None] - x[None]).sum(2)
    groups = tree.mutual_groups(d)
    assert [6, 7, 8, 9] in groups and [10, 11, 12] in groups
    size = tree.lca_sizes(tree.hybrid_paths(d))
    assert size[np.ix_([6, 7, 8, 9], [6, 7, 8, 9])].max() == 4 and size[10, 12] <= 3


def test_bisected_tree_is_a_tree_and_exact_for_large_blocks(golden, monkeypatch):
    edges, _, _, matrices, dissim = golden
    small = tree.bisect_tree(matrices, 2)
    bad = tree.tree_violations(small).first()
    assert (bad["leaves"], bad["internal"], bad["roots"], bad["violations"]) == (6, 5, 1, 0)
    monkeypatch.setattr(tree, "PIVOT_FLOATS", 0)  # the way of many pivots gives the same tree
    assert collect(tree.bisect_tree(matrices, 2)) == collect(small)
    whole = collect(tree.bisect_tree(matrices, 100))
    assert whole == collect(tree.build_tree(dissim, graphs.roster(edges), "hybrid"))


def test_pruned_law_equals_exact_law_in_one_block(golden, spark):
    edges, _, _, _, dissim = golden
    leaves = tree.build_tree(dissim, graphs.roster(edges))
    exact = collect(encoder.law_rows(encoder.encoder_table(dissim, leaves, 0.1)))
    one = encoder.pruned_table(dissim, leaves, F.lit("x"), 6, 0.1)
    assert collect(encoder.law_rows(one)) == exact and {r["lost_mass"] for r in one.collect()} == {0.0}
    two = encoder.pruned_table(dissim, leaves, F.substring("path", 1, 1), 6, 0.1)
    assert all(0 < r["lost_mass"] <= 1 and len(r["targets"]) == 3 for r in two.collect())


def test_metric_goldens(spark):
    truth = spark.createDataFrame([(1, "a"), (2, "a"), (1, "b"), (3, "b"), (4, "c")], "v long, label string")
    pred = spark.createDataFrame([(1, "a"), (2, "a"), (5, "a"), (1, "b"), (9, "c")], "v long, label string")
    table = metrics.label_confusion(pred, truth)
    assert collect(table) == [("a", 2, 1, 0), ("b", 1, 0, 1), ("c", 0, 1, 1)]
    assert abs(metrics.macro_f1(table).first()[0] - 0.488889) < 1e-6 and abs(metrics.pooled_f1(table).first()[0] - 0.6) < 1e-12
    extra = metrics.label_confusion(pred, truth, spark.createDataFrame([("z",)], "label string"))
    assert abs(metrics.macro_f1(extra).first()[0] - 1.4666667 / 4) < 1e-6 and abs(metrics.macro_f1(extra, "seen").first()[0] - 0.488889) < 1e-6
    assert abs(table.agg(metrics.f1_summary_udf()("tp", "fp", "fn")).first()[0] - 0.6) < 1e-12
    assert metrics.score_gap(0.9, 1.0)["relative"] == pytest.approx(-0.1)


def test_message_formulas(spark):
    got = {(r["length"], r["p"]): r for r in cost.expected_messages(spark, [1, 2, 3, 4, 40], [0.0, 0.1, 0.2, 0.3, 0.4]).collect()}
    printed = {0.0: 39, 0.1: 35.355, 0.2: 32.306, 0.3: 29.716, 0.4: 27.490}
    literal = {0.0: 39, 0.1: 35.537, 0.2: 32.639, 0.3: 30.178, 0.4: 28.061}
    for p in printed:
        assert abs(got[40, p]["published"] - printed[p]) < 2e-3 and abs(got[40, p]["protocol"] - literal[p]) < 1e-3
        assert got[1, p]["protocol"] == 0 and got[2, p]["protocol"] == 1
        assert abs(got[3, p]["protocol"] - (2 - p)) < 1e-6 and abs(got[3, p]["published"] - (2 - 2 * p)) < 1e-6
        assert abs(got[4, p]["protocol"] - (3 - 2 * p + p * p)) < 1e-6 and abs(got[4, p]["published"] - (3 - 4 * p + 2 * p * p)) < 1e-6
    assert abs(got[40, 0.2]["saved"] - 6.694) < 1e-2


@pytest.fixture(scope="module")
def small(spark, sf):
    return Store(spark, "t").keep(graphs.document_terms(spark, sf))


def test_walk_bookkeeping_and_messages(spark, small):
    adj = graphs.adjacency(small)
    true = {(r["v"], r["u"]) for r in small.collect()}
    pools = predictor.exact_pool(adj)
    for charged, kind in ((True, "protocol"), (False, "published")):
        cfg = WalkConfig(length=20, per_vertex=12, jump=0.3, charge_final_jump=charged, rng="xx")
        rows = walks.true_walks(adj, cfg, pools).collect()
        hops = np.array([r["hops"] for r in rows])
        want = cost.expected_messages(spark, [20], [0.3]).first()[kind]
        assert abs(hops.mean() - want) < 5 * hops.std() / math.sqrt(len(hops))
        assert all(len(r["seq"]) == 20 for r in rows)
        if charged:
            assert all(r["hops"] == 19 - r["jumps"] for r in rows)
        assert all(tuple(p) in true for r in rows for p in zip([r["start"], *r["seq"]], r["seq"], strict=False))
    plain = walks.uniform_walks(adj, WalkConfig(length=5, per_vertex=1)).collect()
    assert {r["hops"] for r in plain} == {4} and len(plain) == adj.count()


@pytest.mark.parametrize("length,jump", [(1, 1.0), (2, 1.0), (3, 1.0), (3, 0.0)])
def test_short_walks(spark, golden, length, jump):
    adj = graphs.adjacency(golden[0])
    cfg = WalkConfig(length=length, per_vertex=3, jump=jump)
    rows = walks.true_walks(adj, cfg, predictor.exact_pool(adj)).collect()
    assert len(rows) == 18 and all(len(r["seq"]) == length for r in rows)
    assert {r["jumps"] for r in rows} == ({1} if length == 3 and jump else {0})


def test_local_walks_equal_distributed_ones(spark, golden):
    adj = graphs.adjacency(golden[0])
    cfg = WalkConfig(length=7, per_vertex=3, jump=0.0)
    key = lambda df: sorted((r["walk_id"], tuple(r["seq"])) for r in df.collect())
    assert key(walks.uniform_walks(adj, cfg)) == key(walks.local_walks(adj, cfg))
    back = walks.biased_walks(adj, cfg, 1e-9, 1.0).collect()
    assert sum(r["seq"][i] == r["seq"][i + 2] for r in back for i in range(5)) > 0.95 * 5 * len(back)
    starts = spark.createDataFrame([(1,)], "v long")
    assert walks.uniform_walks(adj, cfg, starts).count() == 3


def test_same_seed_same_walks_whatever_the_partitions(spark, small):
    adj = graphs.adjacency(small)
    cfg = WalkConfig(length=4, per_vertex=1)
    a = collect(walks.uniform_walks(adj, cfg))
    b = collect(walks.uniform_walks(adj.repartition(7), cfg))
    c = collect(walks.uniform_walks(adj, cfg.with_(seed="2")))
    assert a == b != c


def test_laplace_moments_and_bins(spark):
    df = spark.range(20000).select(draws.laplace(draws.number("s", "t", "id"), 0.5).alias("x"), draws.unit("s", "u", "id", rng="xx").alias("y"))
    r = df.agg(F.avg("x"), F.avg(F.abs("x")), F.avg("y")).first()
    assert abs(r[0]) < 0.02 and abs(r[1] - 0.5) < 0.02 and abs(r[2] - 0.5) < 0.01
    vertices = spark.range(100).select(F.col("id").alias("v"))
    for sizes in ("equal", "random"):
        plan = bins.assign_bins(bins.number_vertices(vertices), 4, sizes)
        counts = [r["count"] for r in plan.groupBy("bin").count().collect()]
        assert len(counts) == 4 and sum(counts) == 100 and (sizes == "random" or set(counts) == {25})
    assert [default_bins(n) for n in (1, 6, 169, 717, 2000, 20000)] == [1, 1, 5, 6, 7, 9]
    with pytest.raises(ValueError):
        check_bins(7, 717)
    assert check_bins(7, 717, True) == 7


def test_noise_bound_with_fixed_order(spark, small):
    """The mean added by noise stays below the per-pair bound when rows keep their order."""
    vertices = graphs.roster(small)
    plan = bins.assign_bins(bins.number_vertices(vertices), 5)
    counts = degree.bin_counts(small, plan, 5)
    clean = {r["v"]: np.array(r["m"]) for r in degree.ordered_matrices(small, degree.degree_vectors(counts, None, 5)).collect()}
    rng = np.random.default_rng(3)
    pairs = [(a, b) for a in list(clean)[:25] for b in list(clean)[25:50]]
    base = align.align_many([clean[a] for a, _ in pairs], [clean[b] for _, b in pairs])
    gaps = []
    for _ in range(8):
        noisy = {v: m + rng.laplace(0, 0.5, m.shape) for v, m in clean.items()}
        gaps.append(align.align_many([noisy[a] for a, _ in pairs], [noisy[b] for _, b in pairs]) - base)
    bound = np.array([3 * 5 * (len(clean[a]) + len(clean[b]) - 1) / 4 for a, b in pairs])
    assert (np.mean(gaps, axis=0) <= bound).mean() > 0.99


def test_dp_ratio_of_counts(spark):
    """Adding one link moves a released count by one, so frequencies of its values differ by e^eps at most."""
    eps = 1.0
    noise = draws.laplace(draws.number("a", "l", "id"), 1 / eps)
    one = spark.range(60000).select(F.floor(3 + noise).alias("x"))
    two = spark.range(60000).select(F.floor(4 + draws.laplace(draws.number("b", "l", "id"), 1 / eps)).alias("x"))
    near = lambda df: df.where("x between 1 and 6")
    assert cost.dp_ratio(near(one), near(two), "x").first()[0] < eps + 0.15


def test_privacy_and_linkability_are_told(spark, golden):
    edges, _, vectors, matrices, _ = golden
    got = cost.row_linkability(matrices, vectors).first()
    assert got["rows"] == 14 and 0 < got["linkable"] < 1
    w = walks.uniform_walks(graphs.adjacency(edges), WalkConfig(length=4, per_vertex=2))
    held = {}  # each element is emitted by the device that the walk has come to
    for r in w.collect():
        for v in [r["start"], *r["seq"]][: len(r["seq"])]:
            held[v] = held.get(v, 0) + 1
    assert {r["v"]: (r["emissions"], r["eps"]) for r in cost.privacy_ledger(w, 2.0, 0.5, 2).collect()} == {v: (n, 2.0 + n * 0.5) for v, n in held.items()}
    assert len({n for n in held.values()}) > 1
    jumping = walks.true_walks(graphs.adjacency(edges), WalkConfig(length=5, per_vertex=4, jump=1.0), predictor.exact_pool(graphs.adjacency(edges)))
    for r in jumping.collect():  # a jump's two elements come from the device that jumps
        assert r["emitters"] == [r["start"], r["start"], r["seq"][1], r["seq"][1], r["seq"][3]] and r["jumps"] == 2
    ledger = cost.message_ledger(edges, w, 2)
    assert ledger.where("kind = 'step'").first()["n"] == 6 * 2 * 3


def test_cooccurrence_by_hand(spark):
    w = spark.createDataFrame([(0, [1, 2, 1, 3])], "walk_id long, seq array<long>")
    got = {(a, b): n for a, b, n in collect(cooccur.cooccurrence(w, 2))}
    want = {}
    s = [1, 2, 1, 3]
    for i in range(4):
        for j in range(4):
            if i != j and abs(i - j) <= 2:
                want[s[i], s[j]] = want.get((s[i], s[j]), 0) + 1
    assert got == want
    assert abs(sum(r["p"] for r in cooccur.with_probability(cooccur.cooccurrence(w, 2)).collect()) - 1) < 1e-12


def test_skipgram_blocks_separate_two_groups(spark):
    rng = np.random.default_rng(5)
    seqs = [(i, rng.choice(10, 12).astype(int).tolist() if i % 2 else (10 + rng.choice(10, 12)).astype(int).tolist()) for i in range(200)]
    c = cooccur.cooccurrence(spark.createDataFrame(seqs, "walk_id long, seq array<long>"), 3)
    vec = {r["v"]: np.array(r["vec"]) for r in skipgram.skipgram_blocks(c, 8, blocks=2, epochs=12).collect()}
    unit = {v: x / np.linalg.norm(x) for v, x in vec.items()}
    inside = np.mean([unit[a] @ unit[b] for a in range(10) for b in range(10) if a != b])
    across = np.mean([unit[a] @ unit[b] for a in range(10) for b in range(10, 20)])
    assert len(vec) == 20 and inside > across + 0.2
    e = spark.createDataFrame([(int(v), [float(t) for t in x]) for v, x in vec.items()], "v long, vec array<float>")
    assert skipgram.most_similar(e, 0, 3).count() == 3
    assert skipgram.distance_fit(e, cooccur.walk_dissimilarity(c)).first()["mean_abs"] > 0


def test_private_vectors_keep_languages_apart(spark, small, sf):
    """Positive control: both methods tell languages well above chance; the private one is not far behind."""
    truth = tables.load(spark, sf, "documents").select(F.col("doc_id").alias("v"), F.col("lang").alias("label"))
    cfg = WalkConfig(length=10, per_vertex=5, window=5, dim=16)
    out = pipeline.sweep(small, truth, cfg, {"jump": [0.2]}, [0.5]).collect()
    got = {r["method"]: r["pooled_f1"] for r in out}
    top = truth.join(graphs.roster(small), "v", "left_semi").groupBy("label").count().agg(F.max("count") / F.sum("count")).first()[0]
    assert got["uniform"] > top + 0.15 and got["private"] > top + 0.1


def test_split_is_exact_and_decisions(spark):
    v = spark.range(101).select(F.col("id").alias("v"))
    s = classify.split(v, 0.3)
    assert s.where("is_train").count() == 30 and s.count() == 101
    scored = spark.createDataFrame([(1, "a", 0.9), (1, "b", 0.4), (1, "c", 0.6)], "v long, label string, score double")
    assert collect(classify.decide(scored)) == [(1, "a"), (1, "c")]
    truth = spark.createDataFrame([(1, "b")], "v long, label string")
    assert collect(classify.decide(scored, "known_count", truth)) == [(1, "a")]


def test_logistic_regression_separates(spark, monkeypatch):
    rng = np.random.default_rng(6)
    rows = [(i, [float(t) for t in rng.normal(size=3) + (3 if i % 2 else -3)]) for i in range(200)]
    f = spark.createDataFrame(rows, "v long, vec array<double>")
    labels = spark.createDataFrame([(i, "odd" if i % 2 else "even") for i in range(200)], "v long, label string")
    names, w = classify.fit_ovr(f, labels, rounds=40)
    monkeypatch.setattr(classify, "LOCAL_FLOATS", 0)
    assert np.allclose(w, classify.fit_ovr(f, labels, rounds=40)[1], atol=1e-6)
    got = metrics.pooled_f1(metrics.label_confusion(classify.decide(classify.scores(f, names, w)), labels)).first()[0]
    assert got > 0.97


def test_awkward_graphs(spark):
    make = lambda pairs: graphs.symmetrize(spark.createDataFrame(pairs, "v long, u long"))
    assert collect(make([(1, 1), (1, 2), (2, 1), (1, 2), (None, 3), (-1, 4)])) == [(-1, 4), (1, 2), (2, 1), (4, -1)]
    for pairs in ([(0, 1)], [(0, i) for i in range(1, 6)], [(a, b) for a in range(5) for b in range(a)], [(0, 1), (1, 2), (2, 3)]):
        edges = make(pairs)
        parts = pipeline.build_tree_parts(edges, WalkConfig(eps_degree=None))
        assert tree.tree_violations(parts.leaves).first()["violations"] == 0
        law, pools = pipeline.laws(parts, WalkConfig())
        w = walks.private_walks(graphs.adjacency(edges), law, pools, WalkConfig(length=4, per_vertex=1))
        assert w.count() == graphs.roster(edges).count()
    full = pipeline.build_tree_parts(make([(a, b) for a in range(5) for b in range(a)]), WalkConfig(eps_degree=None, bins=1))
    assert {r["delta"] for r in full.dissim.collect()} == {0.0}
    alone = degree.ordered_matrices(make([(0, 1)]), spark.createDataFrame([(0, [1.0]), (1, [1.0]), (7, [0.0])], "v long, c array<double>"))
    assert {r["v"]: r["m"] for r in alone.collect()}[7] == [[0.0]]


def test_empty_graph(spark):
    none = spark.createDataFrame([], "v long, u long")
    assert walks.uniform_walks(graphs.adjacency(none), WalkConfig(length=3, per_vertex=1)).count() == 0
    assert graphs.core(none, 2).count() == 0


def test_positions(spark):
    df = positions(spark.range(1000).select(F.xxhash64("id").alias("h"), "id"), Store(spark, "p"), "h")
    rows = sorted((r["h"], r["ordinal"]) for r in df.collect())
    assert [o for _, o in rows] == list(range(1000))


def test_edge_list_round_trip(spark, tmp_path, golden):
    path = f"file://{tmp_path}/edges"
    tables.write_edge_list(golden[0], path)
    assert collect(graphs.symmetrize(tables.read_edge_list(spark, path))) == collect(golden[0])


def test_randomized_response_and_two_hop(spark, golden):
    edges = golden[0]
    assert (1, 4) in collect(baselines.exact_two_hop(edges)) and (1, 2) not in collect(baselines.exact_two_hop(edges))
    assert collect(baselines.shared_neighbours(edges, 1, 2)) == [(3,)]
    pairs = spark.range(4000).select(F.col("id").alias("v"), F.lit(-1).cast("long").alias("u"))
    told = baselines.randomized_response(pairs, edges, 1.0).agg(F.avg("told")).first()[0]
    assert abs(told - 1 / (1 + math.e)) < 0.03


def test_pools_are_filled_past_their_blocks(spark):
    rng = np.random.default_rng(4)
    paths = [format(i, "05b") for i in range(32)]
    kinds = rng.integers(1, 3, 32)
    leaves = spark.createDataFrame([(i, p, p[:2]) for i, p in enumerate(paths)], "v long, path string, block string")
    plan = spark.createDataFrame([(i, i, int(b)) for i, b in enumerate(kinds)], "v long, ordinal long, bin int")
    need = {(u, b): int(rng.integers(0, (kinds == b).sum() - (kinds[u] == b) + 1)) for u in range(32) for b in (1, 2)}
    wanted = spark.createDataFrame([(u, b, m) for (u, b), m in need.items()], "u long, bin int, m long")
    dissim = spark.createDataFrame([(u, v, float(abs(u - v))) for u in range(32) for v in range(32) if u < v and u // 8 == v // 8], "u long, v long, delta double")
    inner = predictor.tree_pool(dissim, leaves, plan, wanted, block=F.col("block"))
    got = {r["u"]: r["pool"] for r in predictor.fill_pools(inner, leaves, plan, wanted).collect()}
    common = lambda a, b: next((k for k in range(5) if a[k] != b[k]), 5)
    for u in range(32):
        want = []
        for b in (1, 2):
            order = sorted((w for w in range(32) if w != u and kinds[w] == b), key=lambda w: (-common(paths[u], paths[w]), abs(u - w) if u // 8 == w // 8 else 0, w))
            want += order[: need[u, b]]
        assert got.get(u, []) == sorted(want)


def test_scale_query_keeps_all_rows(spark, sf, monkeypatch):
    from veilwalk.plans import queries

    seen = []
    monkeypatch.setattr(queries.pipeline, "fit_private", lambda edges, cfg, *a: seen.append(cfg) or pipeline.FitResult(edges, edges, None, edges))
    queries.copurchase_at_scale(spark, sf)
    assert seen[0].row_cap is None


def test_workloads_have_full_grids_and_parameters(spark, sf, monkeypatch):
    from veilwalk.plans import queries

    seen = []

    def record(edges, truth, cfg, grid, shares=(0.5,), seeds=("1",), baseline=True, trees=None):
        assert truth.join(graphs.roster(edges), "v", "left_semi").count() > 0
        seen.append(((cfg.length, cfg.per_vertex, cfg.window, cfg.dim), grid, list(shares)))
        return spark.range(1)

    monkeypatch.setattr(queries.pipeline, "sweep", record)
    ps, some, full = [0.0, 0.1, 0.2, 0.3, 0.4], [0.1, 0.2, 0.5, 0.6], (40, 80, 10, 128)
    for name in ("sweep_p", "full_sweep_p", "full_sweep_eps_succession", "full_private_against_uniform_copurchase", "sweep_k", "full_sweep_k_copurchase", "full_sweep_walks"):
        queries.queries()[name](spark, sf)
    assert seen[0] == ((10, 5, 5, 32), {"jump": ps}, some) and seen[1] == (full, {"jump": ps}, some)
    assert seen[2] == (full, {"eps": [0.5, 1.0, 2.0, 4.0]}, some) and seen[3] == (full, {"jump": [0.2]}, [0.1, 0.2, 0.3, 0.4, 0.5, 0.6])
    bounds = [default_bins(graphs.roster(g(spark, sf)).count()) for g in (graphs.document_terms, graphs.copurchase)]
    assert [s[1]["bins"] for s in seen[4:6]] == [list(range(2, k + 1)) for k in bounds]
    assert seen[6:] == [((40, n, 10, 128), {"jump": ps}, some) for n in (20, 40, 60, 80)]


def test_outside_mass_is_bounded(spark, small):
    """What the exact law gives to vertices outside a block never exceeds the bound; even draws from it keep every vertex possible."""
    cfg = WalkConfig(tree="bisect", block=12)
    parts = pipeline.build_tree_parts(small, cfg)
    leaves = Store(spark, "o").keep(parts.leaves.join(pipeline.tree_blocks(parts.leaves, 12), "v"))
    n, full = leaves.count(), Store(spark, "o").keep(align.pairs_within(parts.matrices))
    block = {r["v"]: r["block"] for r in leaves.collect()}
    for eps in (2.0, 0.01, 0.0005):
        law = Store(spark, "o").keep(encoder.pruned_table(parts.dissim, leaves, F.col("block"), n, eps, matrices=parts.matrices))
        lost, outside = {r["v"]: r["lost_mass"] for r in law.collect()}, dict.fromkeys(block, 0.0)
        for r in encoder.law_rows(encoder.encoder_table(full, leaves, eps)).collect():
            outside[r["v"]] += r["pr"] * (block[r["v"]] != block[r["w"]])
        assert all(outside[v] <= lost[v] + 1e-9 for v in block) and (eps > 0.001 or max(outside.values()) > 1e-4)
    whole = encoder.with_outside(law, n)
    asked = law.select("v").crossJoin(spark.range(200).select(F.col("id").alias("i")))
    drawn = encoder.encode(asked.withColumnRenamed("v", "x"), whole, "x", "w", "1", "x", "i")
    got = drawn.agg(F.count("*").alias("n"), F.count("w").alias("held"), F.count_distinct("w").alias("kinds")).first()
    assert got["n"] == got["held"] == 200 * n and got["kinds"] == n


def test_block_mode_is_told_and_keeps_its_options(spark, small):
    cfg = WalkConfig(length=4, per_vertex=1, dim=8, window=2, tree="bisect", block=24, calibrated=50.0, one_sided=True, outside="uniform")
    fit = pipeline.fit_private(small, cfg, "blocks")
    assert fit.mode == fit.tree.mode == "blocks" and fit.embedding.count() > 0
    assert pipeline.fit_uniform(small, cfg).mode == "uniform"
    short = pipeline.pool_shortfall(fit.tree, pipeline.laws(fit.tree, cfg)[1], cfg).first()
    assert short["mode"] == "blocks" and short["demanded"] == short["delivered"] > 0 and short["short"] == 0
    plain = encoder.law_rows(encoder.pruned_table(fit.tree.dissim, fit.tree.leaves.withColumn("b", F.lit("")), F.col("b"), 169, 2.0, calibrated=50.0)).collect()
    exact = encoder.law_rows(encoder.encoder_table(fit.tree.dissim, fit.tree.leaves, 2.0, calibrated=50.0)).collect()
    assert sorted(map(tuple, plain)) == sorted(map(tuple, exact))


def test_large_graphs_need_a_stated_mode(spark, small, monkeypatch):
    monkeypatch.setattr(tree, "EXACT_LIMIT", 50)
    with pytest.raises(ValueError, match="bisect"):
        pipeline.build_tree_parts(small, WalkConfig())


def test_biased_walks_follow_their_weights(spark):
    """Step frequencies of the distributed walks agree with the weights, and with the walks in one task."""
    edges = graphs.symmetrize(spark.createDataFrame([(0, 1), (0, 2), (1, 2), (1, 3), (1, 4), (3, 4), (2, 3)], "v long, u long"))
    nbrs = {}
    for r in edges.collect():
        nbrs.setdefault(r["v"], set()).add(r["u"])
    cfg, ret, inout = WalkConfig(length=6, per_vertex=400), 0.25, 4.0
    for rows in (walks.biased_walks(edges, cfg, ret, inout).collect(), walks.local_walks(graphs.adjacency(edges), cfg, None, ret, inout).collect()):
        seen = {}
        for r in rows:
            path = [r["start"], *r["seq"]]
            assert all(b in nbrs[a] for a, b in zip(path, path[1:], strict=False))
            for a, b, c in zip(path, path[1:], path[2:], strict=False):
                seen.setdefault((a, b), []).append(c)
        for (a, b), cs in seen.items():
            w = {c: 1 / ret if c == a else 1.0 if c in nbrs[a] else 1 / inout for c in nbrs[b]}
            for c in w:
                p = w[c] / sum(w.values())
                assert abs(cs.count(c) / len(cs) - p) < 5 * math.sqrt(p * (1 - p) / len(cs)) + 1e-3


def test_blocks_train_on_all_occurrences(spark):
    """A pair of many occurrences weighs more than one of five, and the loss of negative sampling falls towards that of a plain trainer."""
    rows = [(0, 1, 400), (1, 0, 400), (0, 2, 5), (2, 0, 5), (1, 2, 5), (2, 1, 5), (3, 4, 200), (4, 3, 200), (0, 3, 1), (3, 0, 1)]
    c = spark.createDataFrame(rows, "a long, b long, n long")
    events = [e for part in skipgram._events(np.array([7, 1, 0, 40]), np.random.default_rng(0), 8) for e in part]
    assert sorted(np.bincount(events, minlength=4).tolist()) == [0, 1, 7, 40]
    held = skipgram.EVENTS
    try:
        skipgram.EVENTS = 10
        assert np.bincount([e for part in skipgram._events(np.array([25, 3, 9]), np.random.default_rng(0), 4) for e in part]).tolist() == [25, 3, 9]
    finally:
        skipgram.EVENTS = held
    vec = {r["v"]: np.array(r["vec"]) for r in skipgram.skipgram_blocks(c, 8, blocks=2, epochs=6).collect()}
    cos = lambda a, b: vec[a] @ vec[b] / np.linalg.norm(vec[a]) / np.linalg.norm(vec[b])
    assert np.isfinite(np.stack(list(vec.values()))).all() and cos(0, 1) != cos(0, 3)
    assert skipgram.block_count(100, 64) == 4 and skipgram.block_count(10**9, 128) == -(-(10**9) * 128 // skipgram.BLOCK_FLOATS)


def test_sweep_of_pairs_and_gaps(spark, small, sf):
    truth = graphs.labels_of_documents(spark, sf)
    cfg = WalkConfig(length=6, per_vertex=2, window=3, dim=8)
    out = pipeline.sweep(small, truth, cfg, {"per_vertex*jump": [(1, 0.0), (2, 0.4)]}, [0.3, 0.5], ("1", "2"))
    rows = out.collect()
    assert len(rows) == 2 * 3 * 2 and {(r["value"], r["other"]) for r in rows if r["method"] == "private"} == {(1.0, 0.0), (2.0, 0.4)}
    assert all(0 < r[c] <= 1 for r in rows for c in pipeline.SCORES) and {r["mode"] for r in rows} == {"exact", "uniform"}
    assert {r["seeds"] for r in pipeline.repeated(out).collect()} == {2}
    assert pipeline.score_gaps(out).count() == 2 * len(pipeline.SCORES)


def test_grouped_evaluation_equals_the_distributed_one(spark, small, sf):
    truth = tables.load(spark, sf, "documents").select(F.col("doc_id").alias("v"), F.concat(F.lit("lang:"), "lang").alias("label"))
    fit = Store(spark, "e").keep(pipeline.fit_uniform(small, WalkConfig(length=8, per_vertex=4, window=3, dim=8)).embedding)
    for share in (0.2, 0.5):
        want = pipeline.evaluate(fit, truth, share).first()
        got = classify.evaluate_points(fit.select(F.lit(0).alias("point"), F.lit("1").alias("seed"), "v", "vec"), truth, [share]).where("rule = 'known_count'").first()
        assert got["n_test"] == want["n_test"] and abs(got["pooled_f1"] - want["pooled_f1"]) < 1e-9 and abs(got["macro_f1"] - want["macro_f1"]) < 1e-9


def test_unknown_labels_do_not_count():
    rng = np.random.default_rng(8)
    x = rng.normal(size=(60, 2))
    labels = [[f"q:{int(a > 0)}"] + ([f"t:{int(b > 0)}"] if i % 3 == 0 else []) for i, (a, b) in enumerate(x)]
    got = {r[0]: r for r in classify.evaluate_group(x, labels, np.arange(60) < 30)}
    assert got["known_count"][2] > 0.9 and got["threshold"][2] > 0.9


def test_succession_joins_hours_days_and_years(spark, tmp_path):
    rng = np.random.default_rng(2)
    from datetime import datetime, timedelta

    when = sorted(datetime(2019, 12, 30) + timedelta(minutes=int(m)) for m in rng.integers(0, 60 * 24 * 500, 120))
    rows = [(i, t, int(rng.integers(0, 25))) for i, t in enumerate(when)]
    spark.createDataFrame([(*r, "click", 1.0, "{}") for r in rows], "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").write.parquet(f"file://{tmp_path}/events.parquet")
    users = [u for _, _, u in rows]
    want = {(a, b) for a, b in zip(users, users[1:], strict=False) if a != b}
    assert set(collect(graphs.succession(spark, f"file://{tmp_path}"))) == want | {(b, a) for a, b in want}
