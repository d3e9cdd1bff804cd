"""The method and its baseline from graph to vectors, their evaluation, and sweeps over parameters."""

from __future__ import annotations

from collections.abc import Iterable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.config import WalkConfig, check_bins, default_bins
from veilwalk.operators import align, bins, classify, cooccur, cost, degree, encoder, metrics, predictor, skipgram, tree, walks
from veilwalk.plans.lineage import Store
from veilwalk.sources import graphs


@dataclass
class TreeParts:
    """Everything that walks need from the server: shared by all jump probabilities and walk lengths."""

    bins: DataFrame
    vectors: DataFrame
    matrices: DataFrame
    dissim: DataFrame
    leaves: DataFrame
    k: int
    mode: str = "exact"
    cache: dict = field(default_factory=dict)
    held: align.Held | None = None


@dataclass
class FitResult:
    """mode is 'exact', 'blocks' (laws and dissimilarities within blocks of the tree) or 'uniform'."""

    embedding: DataFrame
    walks: DataFrame
    tree: TreeParts | None
    ledger: DataFrame
    mode: str = "exact"


def build_tree_parts(edges: DataFrame, cfg: WalkConfig, allow_over_bound: bool = False) -> TreeParts:
    """Bin plan, noisy vectors, ordered matrices, dissimilarities and cluster tree.

    With cfg.tree 'bisect' the tree is bisected and only pairs within its blocks are aligned; all other trees need all
    pairs and refuse graphs beyond the exact limit. Their pairs are rows only where dissim is asked for.
    """
    held, store = None, Store(edges.sparkSession, "tree")
    vertices = store.keep(graphs.roster(edges))
    n = vertices.count()
    k = default_bins(n) if cfg.bins is None else check_bins(cfg.bins, n, allow_over_bound)
    plan = store.keep(bins.assign_bins(bins.number_vertices(vertices, cfg.seed, cfg.rng), k, cfg.bin_sizes, cfg.seed))
    vectors = store.keep(degree.degree_vectors(degree.bin_counts(edges, plan, k), cfg.eps_degree, k, cfg.sensitivity, cfg.seed, cfg.rng))
    matrices = degree.ordered_matrices(edges, vectors, cfg.eps_degree if cfg.perturb_rows else None, cfg.seed)
    matrices = store.keep(degree.cap_rows(matrices, cfg.row_cap) if cfg.row_cap else matrices)
    if cfg.tree != "bisect":
        if n > tree.EXACT_LIMIT:
            raise ValueError(f"{n} vertices exceed the limit {tree.EXACT_LIMIT} of all pairs; choose tree='bisect'")
        held = align.Held(matrices, cfg.one_sided, cfg.band)
        dissim = align.pairs_within(matrices, None, 64, cfg.one_sided, cfg.band)
        leaves = tree.cluster_tree(held, cfg.tree)
    else:
        blocks = tree.bisect_blocks(matrices, cfg.block, cfg.seed, cfg.one_sided, cfg.band)
        dissim = store.keep(align.pairs_within(matrices.join(blocks, "v"), "block", 64, cfg.one_sided, cfg.band))
        leaves = tree.block_leaves(blocks, dissim)
    return TreeParts(plan, vectors, matrices, dissim, leaves, k, "blocks" if cfg.tree == "bisect" else "exact", held=held)


def tree_blocks(leaves: DataFrame, block: int) -> DataFrame:
    """(v, block): the largest subtrees of at most block leaves, named by their paths."""
    cut = F.transform(F.sequence(F.lit(0), F.length("path")), lambda i: F.col("path").substr(F.lit(1), i))
    up = leaves.select("v", F.explode(cut).alias("block"))
    small = up.groupBy("block").agg(F.count("*").alias("n")).where(F.col("n") <= block).select("block")
    return up.join(small, "block").groupBy("v").agg(F.min_by("block", F.length("block")).alias("block"))


def laws(parts: TreeParts, cfg: WalkConfig) -> tuple[DataFrame | None, DataFrame]:
    """The substitution law (none without eps_walk) and the jump pools."""
    pool_key = ("pool", cfg.near, cfg.rounding, cfg.seed, cfg.block)
    law_key = ("law", cfg.eps_walk, cfg.score_scale, cfg.calibrated, cfg.block, cfg.outside)
    store, cache, exact = Store(parts.leaves.sparkSession, "laws"), parts.cache, parts.mode == "exact"
    if not exact and "blocks" not in cache:
        cache["blocks"] = store.keep(parts.leaves.join(tree_blocks(parts.leaves, cfg.block), "v"))
    if pool_key not in cache:
        wanted = predictor.demand(parts.vectors, parts.bins, cfg.rounding, cfg.seed)
        if exact:
            pools = predictor.held_pool(parts.held, parts.leaves, parts.bins, wanted, cfg.near)
        else:
            pools = predictor.tree_pool(parts.dissim, cache["blocks"], parts.bins, wanted, cfg.near, F.col("block"))
            pools = predictor.fill_pools(store.keep(pools), cache["blocks"], parts.bins, wanted)
        cache[pool_key] = store.keep(pools)
    if law_key not in cache:
        law = None
        if cfg.eps_walk is not None and exact:
            law = encoder.held_table(parts.held, parts.leaves, encoder.factor_of(cfg.eps_walk, cfg.score_scale, cfg.calibrated))
        elif cfg.eps_walk is not None:
            n = cache["blocks"].count()
            law = encoder.pruned_table(parts.dissim, cache["blocks"], F.col("block"), n, cfg.eps_walk, cfg.score_scale, cfg.calibrated, parts.matrices)
            law = law if cfg.outside == "drop" else encoder.with_outside(store.keep(law), n)
        cache[law_key] = None if law is None else store.keep(law)
    return cache[law_key], cache[pool_key]


def pool_shortfall(parts: TreeParts, pools: DataFrame, cfg: WalkConfig) -> DataFrame:
    """(mode, vertices, demanded, delivered, short): members that noisy counts ask for and pools hold, in one row."""
    wanted = predictor.demand(parts.vectors, parts.bins, cfg.rounding, cfg.seed).groupBy("u").agg(F.sum("m").alias("m"))
    both = wanted.join(pools.select("u", F.size("pool").cast("long").alias("n")), "u", "left").na.fill(0)
    return both.agg(F.lit(parts.mode).alias("mode"), F.count("*").alias("vertices"), F.sum("m").alias("demanded"), F.sum("n").alias("delivered"), F.count_if(F.col("n") < F.col("m")).alias("short"))


def embed(corpus: DataFrame, cfg: WalkConfig, backend: str = "mllib") -> DataFrame:
    if backend == "blocks":
        return skipgram.skipgram_blocks(cooccur.cooccurrence(corpus, cfg.window), cfg.dim)
    return skipgram.skipgram(corpus, cfg.dim, cfg.window)


def fit_private(edges: DataFrame, cfg: WalkConfig, backend: str = "mllib", parts: TreeParts | None = None, allow_over_bound: bool = False) -> FitResult:
    """The private method end to end."""
    store = Store(edges.sparkSession, "private")
    parts = parts or build_tree_parts(edges, cfg, allow_over_bound)
    law, pools = laws(parts, cfg)
    if cfg.exact_two_hop:
        pools = predictor.exact_pool(graphs.adjacency(edges))
    tables = parts.cache.get("walks") if parts.cache.get("pools") is pools else None
    corpus = store.keep(walks.private_walks(edges, law, pools, cfg, tables=tables))
    ledger = cost.privacy_ledger(corpus, cfg.eps_degree, cfg.eps_walk, parts.k, cfg.sensitivity)
    return FitResult(embed(corpus, cfg, backend), corpus, parts, ledger, parts.mode)


def fit_uniform(edges: DataFrame, cfg: WalkConfig, backend: str = "mllib") -> FitResult:
    """The centralized baseline with the same walks, window and dimension."""
    store = Store(edges.sparkSession, "uniform")
    corpus = store.keep(walks.uniform_walks(edges, cfg))
    return FitResult(embed(corpus, cfg, backend), corpus, None, cost.privacy_ledger(corpus, None, None, 0), "uniform")


def evaluate(embedding: DataFrame, truth: DataFrame, share: float, seed: str = "1", rule: str = "known_count") -> DataFrame:
    """(rule, n_test, pooled_f1, macro_f1) of labels predicted on the vertices that are not for training."""
    store = Store(embedding.sparkSession, "evaluate")
    known = truth.join(embedding.select("v"), "v", "left_semi").distinct()
    rows = store.keep(embedding.join(known.select("v").distinct(), "v", "left_semi").select("v", "vec"))
    parts = store.keep(classify.split(rows.select("v"), share, seed))
    train = rows.join(parts.where("is_train"), "v", "left_semi")
    test = store.keep(rows.join(parts.where("not is_train"), "v", "left_semi"))
    names, w = classify.fit_ovr(train, known.join(train.select("v"), "v", "left_semi"))
    goal = known.join(test.select("v"), "v", "left_semi")
    pred = classify.decide(classify.scores(test, names, w), rule, goal)
    table = store.keep(metrics.label_confusion(pred, goal, known.select("label")))
    both = metrics.pooled_f1(table).crossJoin(metrics.macro_f1(table))  # one row each
    return both.select(F.lit(rule).alias("rule"), F.lit(test.count()).cast("long").alias("n_test"), "pooled_f1", "macro_f1")


#: Points of a sweep that run at once: their jobs are many and small.
AT_ONCE = 8


def sweep(edges: DataFrame, truth: DataFrame, cfg: WalkConfig, grid: dict[str, Iterable], shares: Iterable[float] = (0.5,), seeds: Iterable[str] = ("1",), baseline: bool = True, trees: dict | None = None) -> DataFrame:
    """One row for each point of the grid, share and seed: (method, mode, parameter, value, seed, share, pooled_f1, macro_f1,
    pooled_f1_threshold, macro_f1_threshold, mean_messages). The first two scores are of the rule known_count.

    A name 'a*b' in the grid stands for pairs of values of a and b; its value is that of a, and other that of b.
    Trees are built once for each choice of bins and noise, and shared by sweeps of one graph that are given the same trees;
    walks once for each point; all points and shares are evaluated in one job. Points run AT_ONCE at a time.
    """
    spark, trees = edges.sparkSession, {} if trees is None else trees
    plans: list[tuple] = []
    for seed in seeds:
        if baseline:
            plans.append(("uniform", "", None, None, seed, cfg.with_(seed=seed)))
        for name, values in grid.items():
            for value in values:
                told = value if "*" in name else (value,)
                change = dict(zip(name.split("*"), told, strict=True))
                if "eps" in change:
                    change |= {"eps_degree": change["eps"], "eps_walk": change.pop("eps")}
                plans.append(("private", name, told[0], told[1] if len(told) > 1 else None, seed, cfg.with_(seed=seed, **change)))
    key = lambda c: (c.seed, c.bins, c.eps_degree, c.tree)
    missing = {key(p[-1]): p[-1] for p in plans if p[0] == "private" and key(p[-1]) not in trees}
    store = Store(spark, "sweep")

    def run(point: int) -> tuple[DataFrame, tuple]:
        method, name, value, other, seed, c = plans[point]
        fit = fit_uniform(edges, c) if method == "uniform" else fit_private(edges, c, parts=trees[key(c)])
        embedding = Store(spark, "point").keep(fit.embedding)
        messages = cost.walk_messages(fit.walks).first()["mean_messages"]
        number = lambda x: None if x is None else float(x)
        return embedding.select(F.lit(point).alias("point"), F.lit(seed).alias("seed"), "v", "vec"), (point, method, fit.mode, name, number(value), number(other), seed, messages)

    with ThreadPoolExecutor(AT_ONCE) as pool:
        trees |= dict(zip(missing, pool.map(lambda c: _with_laws(build_tree_parts(edges, c, allow_over_bound=True), edges, c), missing.values()), strict=True))
        alike = {}  # points of one configuration, such as the usual noise in several grids, are run once
        for point, plan in enumerate(plans):
            alike.setdefault((plan[0], plan[-1]), []).append(point)
        done = dict(zip(alike, pool.map(lambda ps: run(ps[0]), alike.values()), strict=True))
    if not plans:
        return spark.createDataFrame([], SWEEP)
    found = list(done.values())
    about_rows = []
    for ps, (_, row) in zip(alike.values(), found, strict=True):
        for p in ps:
            method, name, value, other, seed, _ = plans[p]
            about_rows.append((row[0], method, row[2], name, None if value is None else float(value), None if other is None else float(other), seed, row[7]))
    every = found[0][0]
    for embedding, _ in found[1:]:
        every = every.unionByName(embedding)
    scores = classify.evaluate_points(store.keep(every), truth, list(shares))
    at = scores.groupBy("point", "share").agg(*[F.max(F.when(F.col("rule") == r, F.col(c))).alias(c + s) for r, s in (("known_count", ""), ("threshold", "_threshold")) for c in ("pooled_f1", "macro_f1")])
    about = spark.createDataFrame(about_rows, "point int, method string, mode string, parameter string, value double, other double, seed string, mean_messages double")
    return store.keep(about.join(at, "point").select("method", "mode", "parameter", "value", "other", "seed", "share", "pooled_f1", "macro_f1", "pooled_f1_threshold", "macro_f1_threshold", "mean_messages"))


SWEEP = "method string, mode string, parameter string, value double, other double, seed string, share double, pooled_f1 double, macro_f1 double, pooled_f1_threshold double, macro_f1_threshold double, mean_messages double"


def _with_laws(parts: TreeParts, edges: DataFrame, cfg: WalkConfig) -> TreeParts:
    """parts with the laws, pools and walk tables that the points of a sweep share."""
    parts.cache["pools"] = laws(parts, cfg)[1]
    parts.cache["walks"] = walks.walk_tables(edges, parts.cache["pools"])
    return parts


def score_gaps(points: DataFrame) -> DataFrame:
    """(share, measure, uniform, private, points, relative): mean scores over seeds of both methods, and their gaps."""
    means = points.groupBy("share", "method").agg(*[F.avg(c).alias(c) for c in SCORES])
    long = means.select("share", "method", F.explode(F.array(*[F.struct(F.lit(c).alias("measure"), F.col(c).alias("score")) for c in SCORES])).alias("x")).select("share", "method", "x.*")
    both = long.groupBy("share", "measure").agg(*[F.max(F.when(F.col("method") == m, F.col("score"))).alias(m) for m in ("uniform", "private")])
    gap = F.col("private") - F.col("uniform")
    return both.select("share", "measure", "uniform", "private", gap.alias("points"), F.when(F.col("uniform") > 0, gap / F.col("uniform")).alias("relative"))


SCORES = ("pooled_f1", "macro_f1", "pooled_f1_threshold", "macro_f1_threshold")


def repeated(points: DataFrame) -> DataFrame:
    """Mean and spread of a sweep's scores over its seeds."""
    keys = ["method", "parameter", "value", "other", "share"]
    cells = [f(c).alias(f"{n}_{c}") for c in (*SCORES, "mean_messages") for n, f in (("mean", F.avg), ("spread", F.stddev_pop))]
    return points.groupBy(*keys).agg(F.count("*").alias("seeds"), *cells)
