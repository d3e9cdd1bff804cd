"""Queries beyond the sizes at which they used to stop."""

import numpy as np
from pyspark.sql import functions as F

from veilwalk.config import WalkConfig
from veilwalk.functions.vectors import l1
from veilwalk.operators import align, encoder, groups, intervals, predictor, ranktree, tree
from veilwalk.plans import pipeline, queries
from veilwalk.sources import graphs


def test_interval_pairs_equal_brute_force_without_a_shuffle_of_pairs(spark, sf, monkeypatch):
    """All pairs, hubs and nulls included, for few and many blocks; what is dealt by pairs of users would be as many rows as pairs."""
    rng = np.random.default_rng(5)
    rows = [(int(u), int(t)) for u, t in zip(rng.integers(-4, 40, 500) ** 2 % 37 - 5, rng.integers(0, 3000, 500), strict=True)] + [(None, 5), (3, None)]
    want = {}
    for u, t in rows[:500]:
        for o, s in rows[:500]:
            if u < o and abs(t - s) <= 60:
                want[u, o] = want.get((u, o), 0) + 1
    events = spark.createDataFrame(rows, "user_id long, t long")
    for size in (1_000_000, 40):
        monkeypatch.setattr(intervals, "BLOCK_EVENTS", size)
        got = intervals.user_pairs(events, 60).collect()
        assert len(got) == len(want) and {(r["user_id"], r["other"]): r["n"] for r in got} == want
    assert intervals.user_pairs(events.limit(0), 60).count() == 0
    plan = queries.interval_user_pairs(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(user_id" not in plan


def test_rank_law_and_pools_equal_all_pairs_at_any_size(spark, sf, monkeypatch):
    """Tiles give what all pairs give, past the limit of the exact tree, and the short table draws as the whole law does."""
    monkeypatch.setattr(tree, "EXACT_LIMIT", 50)
    monkeypatch.setattr(ranktree, "TILE", 1000)
    b = queries.Base(spark, sf, queries.EPS)
    assert b.n > 50
    o = b.ranked.join(b.vectors, "v")
    other = o.toDF("w", "o", "d")
    leaves = tree.rank_lca(F.col("ordinal"), F.col("o"), F.lit(b.n).cast("long"))
    pairs = o.crossJoin(other).select("v", "w", leaves.alias("leaves"), l1(F.col("c"), F.col("d")).alias("delta"))
    pairs = b.store.keep(pairs.withColumn("score", encoder.walk_score(F.col("delta"), F.col("leaves"))))
    law = b.store.keep(encoder.exponential_mechanism(pairs, "v", "score", queries.LAW_EPS))
    got = {(r["v"], r["w"]): r["pr"] for r in ranktree.law_rows(b.ranks, queries.LAW_EPS, 0.0).collect()}
    want = {(r["v"], r["w"]): r["pr"] for r in law.collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-12 for k in want)
    monkeypatch.setattr(queries, "base", lambda *_: b)
    assert sorted(map(tuple, queries.encoder_audit(spark, sf).collect())) == sorted(map(tuple, encoder.encoder_audit(law).collect()))
    assert queries.encoder_utility(spark, sf).collect() == encoder.encoder_utility(law).collect()
    assert max(len(r["targets"]) for r in b.table.collect()) <= b.n
    draws = encoder.encode(b.vertices.withColumnRenamed("v", "x"), encoder.as_table(law), "x", "w", "1", "x").select("x", "w")
    assert sorted(map(tuple, draws.collect())) == sorted(map(tuple, encoder.encode(b.vertices.withColumnRenamed("v", "x"), b.table, "x", "w", "1", "x").select("x", "w").collect()))
    kinds = b.plan.select(F.col("v").alias("w"), "bin")
    near = pairs.select(F.col("v").alias("u"), "w", F.col("leaves").alias("near"), F.round("delta", 9).alias("delta")).join(kinds, "w")
    for rounding in ("round", "floor", "stochastic"):
        pools = predictor.jump_pool(near, predictor.demand(b.vectors, b.plan, rounding, "1"))
        assert sorted((r["u"], tuple(r["pool"])) for r in queries._pools(b, rounding).collect()) == sorted((r["u"], tuple(r["pool"])) for r in pools.collect())


def test_message_grid_reads_events(spark, sf):
    """Every number of events that a user has is a length, with all jump probabilities."""
    df = queries.expected_messages_grid(spark, sf)
    want = {r["n"] for r in spark.read.parquet(f"{sf}/events.parquet").groupBy("user_id").agg(F.count("*").alias("n")).collect()}
    assert "FileScan parquet" in df._jdf.queryExecution().executedPlan().toString()
    assert {(r["length"], r["p"]) for r in df.collect()} == {(n, p) for n in want for p in queries.JUMPS}


def test_trees_laws_and_pools_of_held_matrices_equal_those_of_pairs(spark, sf, monkeypatch):
    """Rows made in tasks give what all pairs give, in memory and in a scratch file, and the short table draws as the whole law does."""
    b = queries.Base(spark, sf, queries.EPS)
    wanted, sure = predictor.demand(b.vectors, b.plan), lambda df: sorted(map(str, df.collect()))
    for options, method, size, near in (({}, "average", 1 << 30, "hops"), ({"band": 2}, "hybrid", 0, "depth"), ({}, "hybrid", 0, "leaves")):
        monkeypatch.setattr(tree, "SQUARE_BYTES", size)
        held, dissim = align.Held(b.matrices, **options), b.store.keep(align.pairs_within(b.matrices, **options))
        leaves = tree.cluster_tree(held, method)
        assert sure(leaves) == sure(tree.build_tree(dissim, b.vertices, method))
        assert sure(predictor.held_pool(held, leaves, b.plan, wanted, near)) == sure(predictor.tree_pool(dissim, leaves, b.plan, wanted, near))
    for factor in (2.0, 0.001):
        whole = b.store.keep(encoder.encoder_table(dissim, leaves, factor))
        got = {(r["v"], r["w"]): r["pr"] for r in encoder.held_law(held, leaves, factor, 0.0).collect()}
        want = {(r["v"], r["w"]): r["pr"] for r in encoder.law_rows(whole).collect()}
        assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-12 for k in want)
        asked = b.vertices.select(F.col("v").alias("x"))
        assert sure(encoder.encode(asked, encoder.held_table(held, leaves, factor), "x", "w", "1", "x")) == sure(encoder.encode(asked, whole, "x", "w", "1", "x"))


def test_exact_trees_beyond_the_limit_of_pairs(spark):
    """Rings of more vertices than pairs are taken for as rows have a tree, a law and pools."""
    n = tree.PAIRS_LIMIT + 100
    ring = spark.range(n).select(F.col("id").alias("v"), F.when((F.col("id") + 1) % 7 == 0, F.col("id") - 6).otherwise(F.col("id") + 1).alias("u")).where(f"u < {n}")
    edges = graphs.symmetrize(ring)
    n, cfg = graphs.roster(edges).count(), WalkConfig(seed="1")
    assert n > tree.PAIRS_LIMIT
    parts = pipeline.build_tree_parts(edges, cfg)
    found = tree.tree_violations(parts.leaves).first()
    assert (parts.mode, found["leaves"], found["internal"], found["violations"]) == ("exact", n, n - 1, 0)
    law, pools = pipeline.laws(parts, cfg)
    assert law.count() == n
    short = pipeline.pool_shortfall(parts, pools, cfg).first()
    assert short["demanded"] == short["delivered"] > 0


def test_bisection_by_tasks_equals_bisection_by_levels(spark, sf, monkeypatch):
    b = pipeline.build_tree_parts(graphs.document_terms(spark, sf), WalkConfig(tree="bisect", block=16))
    found = lambda: {r["v"]: r["block"] for r in tree.bisect_blocks(b.matrices, 16).collect()}
    by_tasks = found()
    assert max(map(len, by_tasks.values())) > 2
    monkeypatch.setattr(tree, "NODE_FLOATS", 0)  # all levels by jobs
    assert found() == by_tasks == {r["v"]: r["block"] for r in pipeline.tree_blocks(b.leaves, 16).collect()}
    monkeypatch.setattr(tree, "PIVOT_FLOATS", 0)  # the way of many pivots
    assert found() == by_tasks


def test_pairs_of_blocks_are_aligned_once(spark, sf, monkeypatch):
    """The tree within blocks follows from the pairs that laws and pools take too, and is not aligned anew."""
    made = []

    def pairs(matrices, block, *options):
        both = matrices.select("block", "v").join(matrices.select("block", F.col("v").alias("u")), "block").where("u < v")
        made.append(both.select("u", "v", F.abs(F.col("u") - F.col("v")).cast("double").alias("delta")))
        return made[-1]

    monkeypatch.setattr(align, "pairs_within", pairs)
    b = pipeline.build_tree_parts(graphs.document_terms(spark, sf), WalkConfig(tree="bisect", block=100_000))
    assert len(made) == 1
    got = {r["v"]: r["path"] for r in b.leaves.collect()}
    ids = np.array(sorted(got))
    assert [got[v] for v in ids.tolist()] == tree.leaf_paths(np.abs(ids[:, None] - ids[None]).astype(float), "hybrid")


def test_diagonals_equal_steps_by_rows():
    rng = np.random.default_rng(7)
    left, right = ([rng.normal(size=(n, 3)) for n in rng.integers(1, 40, 200)] for _ in range(2))
    for one_sided in (False, True):
        with np.errstate(invalid="ignore"):
            want = [align._batch([a], [b], one_sided, None)[0] for a, b in zip(left, right, strict=True)]
        assert np.allclose(align._diagonals(left, right, one_sided), want, rtol=1e-12)


def test_hybrid_tree_without_a_square(spark, sf, monkeypatch):
    """Parts split by passes, equal matrices and large groups give the tree of the square; no table of pairs is written."""
    for eps in (queries.EPS, None):
        b = queries.Base(spark, sf, eps)
        held, written = align.Held(b.matrices), []
        want = {r["v"]: r["path"] for r in tree.build_tree(b.store.keep(align.pairs_within(b.matrices)), b.vertices).collect()}
        monkeypatch.setattr(held, "triangle", lambda: written.append(1))
        for part, first, nearest in ((4096, 256, 16), (8, 2, 2)):
            monkeypatch.setattr(groups, "PART", part)
            monkeypatch.setattr(groups, "FIRST", first)
            monkeypatch.setattr(groups, "NEAREST", nearest)
            assert {r["v"]: r["path"] for r in tree.cluster_tree(held).collect()} == want
        assert not written
