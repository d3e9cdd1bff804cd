"""Queries of the method, its baselines, measures and workloads over the given tables, for __spark_entry__.py."""

from __future__ import annotations

from collections.abc import Callable
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from veilwalk.config import WalkConfig, default_bins
from veilwalk.functions.vectors import l1, total
from veilwalk.operators import align, baselines, bins, classify, cooccur, cost, degree, encoder, intervals, metrics, predictor, ranktree, skipgram, tree, walks
from veilwalk.plans import pipeline
from veilwalk.plans.lineage import Store, shared_root
from veilwalk.sources import graphs
from veilwalk.sources.tables import load
from veilwalk.streaming import edges as streams

CFG = WalkConfig(length=6, per_vertex=2, jump=0.2, window=3, dim=16, seed="1")
EPS = 2.0
#: Factor of the law of the rank tree.
LAW_EPS = 0.05
LANDMARKS = 3

Query = Callable[[SparkSession, str], DataFrame]


def r6(c: str | Column) -> Column:
    """Rounded to six places, without a negative zero."""
    return F.round(F.col(c) if isinstance(c, str) else c, 6) + F.lit(0.0)


class Base:
    """The document graph with what many queries of one session and folder share; each part is made when first asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str, eps: float | None):
        self.spark, self.sf_dir, self.eps, self.store = spark, sf_dir, eps, Store(spark, "base")

    @cached_property
    def clean(self) -> Base:
        return base(self.spark, self.sf_dir, None)

    @cached_property
    def edges(self) -> DataFrame:
        return self.clean.edges if self.eps is not None else self.store.keep(graphs.document_terms(self.spark, self.sf_dir))

    @cached_property
    def vertices(self) -> DataFrame:
        return self.clean.vertices if self.eps is not None else self.store.keep(graphs.roster(self.edges))

    @cached_property
    def n(self) -> int:
        return self.vertices.count()

    @property
    def k(self) -> int:
        return default_bins(self.n)

    @cached_property
    def plan(self) -> DataFrame:
        return self.clean.plan if self.eps is not None else self.store.keep(bins.assign_bins(bins.number_vertices(self.vertices, CFG.seed), self.k))

    @cached_property
    def counts(self) -> DataFrame:
        return self.clean.counts if self.eps is not None else self.store.keep(degree.bin_counts(self.edges, self.plan, self.k))

    @cached_property
    def vectors(self) -> DataFrame:
        return self.store.keep(degree.degree_vectors(self.counts, self.eps, self.k, seed=CFG.seed))

    @cached_property
    def matrices(self) -> DataFrame:
        return self.store.keep(degree.ordered_matrices(self.edges, self.vectors))

    @cached_property
    def ranked(self) -> DataFrame:
        return self.store.keep(tree.median_order(self.vectors))

    @cached_property
    def dissim(self) -> DataFrame:
        return self.store.keep(align.pairs_within(self.matrices))

    @cached_property
    def held(self) -> align.Held:
        return align.Held(self.matrices)

    @cached_property
    def hybrid(self) -> DataFrame:
        return tree.cluster_tree(self.held, "hybrid")

    @cached_property
    def ranks(self) -> ranktree.Ranks:
        return ranktree.Ranks(self.ranked, self.vectors)

    @cached_property
    def table(self) -> DataFrame:
        return self.store.keep(ranktree.law_table(self.ranks, LAW_EPS))

    @cached_property
    def pools(self) -> DataFrame:
        return _pools(self)

    @cached_property
    def jump_walks(self) -> DataFrame:
        return self.store.keep(walks.true_walks(graphs.adjacency(self.edges), CFG, self.pools))


_BASES: dict[tuple, Base] = {}


def base(spark: SparkSession, sf_dir: str, eps: float | None = EPS) -> Base:
    """The shared parts of a session, as long as the table of documents is the same."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/documents.parquet")
    status = path.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(path)
    key = (spark.sparkContext.applicationId, sf_dir, status.getModificationTime(), status.getLen(), shared_root(spark), eps)
    if key not in _BASES:
        _BASES[key] = Base(spark, sf_dir, eps)
    return _BASES[key]


# graphs

def g1_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.copurchase(spark, sf_dir)


def g2_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.document_terms(spark, sf_dir)


def g3_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.buys_from(spark, sf_dir)


def g4_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.succession(spark, sf_dir)


def g5_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.page_links(spark, sf_dir)


def g6_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.geo_star(spark, sf_dir)


def vector_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.vector_knn(spark, sf_dir)


def graph_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = {"copurchase": graphs.copurchase, "document_terms": graphs.document_terms, "buys_from": graphs.buys_from, "succession": graphs.succession, "geo_star": graphs.geo_star}
    out = None
    for name, make in made.items():
        one = graphs.statistics(make(spark, sf_dir)).select(F.lit(name).alias("graph"), "*")
        out = one if out is None else out.union(one)
    return out


def degree_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.copurchase(spark, sf_dir).groupBy("v").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("n"))


def degree_core(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.core(graphs.document_terms(spark, sf_dir), 10)


# bins, vectors, matrices

def bin_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return base(spark, sf_dir).plan


def bin_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return degree.long_form(base(spark, sf_dir).counts, "n", "n")


def degree_vectors_clean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return degree.long_form(base(spark, sf_dir, None).vectors, "c", "c")


def degree_vectors_noisy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return degree.long_form(base(spark, sf_dir).vectors, "c", "c").withColumn("c", r6("c"))


def estimated_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return degree.estimated_degree(base(spark, sf_dir).vectors).select("v", r6("est").alias("est"))


def neighbour_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    return base(spark, sf_dir).matrices.select("v", F.posexplode("nbr_order").alias("pos", "u"))


def matrix_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _cells(base(spark, sf_dir).matrices)


def matrix_rows_perturbed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Matrices whose rows devices have noised once more before they hand them on."""
    b = base(spark, sf_dir)
    return _cells(degree.ordered_matrices(b.edges, b.vectors, EPS, CFG.seed))


def _cells(matrices: DataFrame) -> DataFrame:
    rows = matrices.select("v", F.posexplode("m").alias("pos", "row"))
    return rows.select("v", "pos", F.posexplode("row").alias("bin", "c")).select("v", "pos", (F.col("bin") + 1).alias("bin"), r6("c").alias("c"))


def row_l1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """L1 distance of the noisy vectors of linked vertices."""
    b = base(spark, sf_dir)
    c = b.vectors
    both = b.edges.where("v < u").join(c, "v").join(c.withColumnsRenamed({"v": "u", "c": "cu"}), "u")
    return both.select("v", "u", r6(l1(F.col("c"), F.col("cu"))).alias("distance"))


def _landmark_pairs(b: Base, matrices: DataFrame) -> DataFrame:
    marks = b.plan.where(F.col("ordinal") < LANDMARKS).select("v")
    return align.pairs_to(matrices, marks)


def _aligned(spark: SparkSession, sf_dir: str, eps: float | None, **more) -> tuple[Base, DataFrame, DataFrame]:
    b = base(spark, sf_dir, eps)
    m = b.matrices
    return b, m, align.dissimilarity(m, _landmark_pairs(b, m), **more)


def align_clean(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Alignment of every vertex to three landmarks on exact counts, whose ties go by id."""
    return _aligned(spark, sf_dir, None)[2].select("u", "v", r6("delta").alias("delta"))


def align_noisy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _aligned(spark, sf_dir, EPS)[2].select("u", "v", r6("delta").alias("delta"))


def align_expr(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by array expressions alone."""
    return _aligned(spark, sf_dir, EPS, kernel="expr")[2].select("u", "v", r6("delta").alias("delta"))


def align_one_sided(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _aligned(spark, sf_dir, EPS, one_sided=True)[2].select("u", "v", r6("delta").alias("delta"))


def align_banded(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _aligned(spark, sf_dir, EPS, band=8)[2].select("u", "v", r6("delta").alias("delta"))


def align_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs that are not dearer than 500 after a lower bound has taken most away."""
    return _aligned(spark, sf_dir, EPS, prune_above=500.0)[2].where("delta <= 500").select("u", "v", r6("delta").alias("delta"))


def align_error_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What noise adds to the alignment, per pair, beside its bounds."""
    b, m, noisy = _aligned(spark, sf_dir, EPS)
    clean = align.dissimilarity(b.clean.matrices, noisy.select("u", "v"))
    out = align.dissimilarity_error(noisy, clean, m, EPS, b.k)
    return out.select("u", "v", r6("error").alias("error"), r6("pair_bound").alias("pair_bound"), r6("bound").alias("bound"))


def degree_list_align(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = base(spark, sf_dir)
    m = b.store.keep(degree.degree_lists(b.edges))
    return align.dissimilarity(m, _landmark_pairs(b, m)).select("u", "v", r6("delta").alias("delta"))


def overlap_dissim(spark: SparkSession, sf_dir: str) -> DataFrame:
    return align.overlap_dissimilarity(graphs.document_terms(spark, sf_dir)).select("u", "v", r6("delta").alias("delta"))


def dissim_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Alignment of all pairs of the document graph."""
    return base(spark, sf_dir).dissim.select("u", "v", r6("delta").alias("delta"))


def capped_matrices(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = base(spark, sf_dir)
    m = degree.cap_rows(b.matrices, 5)
    return m.select("v", F.posexplode("m").alias("pos", "row")).select("v", "pos", r6(total(F.col("row"))).alias("row_sum"))


# trees

def median_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return base(spark, sf_dir).ranked


def lca_leaves(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = base(spark, sf_dir)
    o = b.ranked
    pairs = b.edges.where("v < u").join(o, "v").join(o.select(F.col("v").alias("u"), F.col("ordinal").alias("p")), "u")
    return pairs.select("v", "u", tree.rank_lca(F.col("ordinal"), F.col("p"), F.lit(b.n).cast("long")).alias("leaves"))


def encoder_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest log-ratios of the law between vertices, by output."""
    return ranktree.audit(base(spark, sf_dir).ranks, LAW_EPS)


def encoder_law(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Substitutes of probability 0.000001 and more."""
    rows = ranktree.law_rows(base(spark, sf_dir).ranks, LAW_EPS, 4e-7)  # below that all are rounded to 0
    return rows.select("v", "w", r6("pr").alias("pr")).where("pr > 0")


def encoder_draws(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three substitutes drawn for each vertex."""
    b = base(spark, sf_dir)
    table = b.table
    asked = table.select(F.col("v").alias("x"), F.explode(F.array(*[F.lit(i) for i in range(3)])).alias("i"))
    return encoder.encode(asked, table, "x", "w", CFG.seed, "x", "i").select(F.col("x").alias("v"), "i", "w")


def encoder_utility(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ranktree.utility(base(spark, sf_dir).ranks, LAW_EPS)


def encoder_calibrated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The textbook factor for a stated sensitivity of 100."""
    return ranktree.utility(base(spark, sf_dir).ranks, encoder.factor_of(EPS, calibrated=100.0))


def _pools(b: Base, rounding: str = "round") -> DataFrame:
    wanted = predictor.demand(b.vectors, b.plan, rounding, CFG.seed)
    return b.store.keep(ranktree.pools(b.ranks, b.plan, b.ranked, wanted))


def jump_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    return base(spark, sf_dir).pools.select("u", F.explode("pool").alias("w"))


def jump_pool_floor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _pools(base(spark, sf_dir), "floor").select("u", F.explode("pool").alias("w"))


def jump_pool_stochastic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pools whose sizes are drawn so that their means are the noisy counts."""
    return _pools(base(spark, sf_dir), "stochastic").select("u", F.explode("pool").alias("w"))


def _tree_pools(spark: SparkSession, sf_dir: str, near: str) -> DataFrame:
    b = base(spark, sf_dir)
    wanted = predictor.demand(b.vectors, b.plan, "round", CFG.seed)
    return predictor.held_pool(b.held, b.hybrid, b.plan, wanted, near).select("u", F.explode("pool").alias("w"))


def jump_pool_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pools by the cluster tree of aligned matrices: leaves of the common subtree, then dissimilarity, then id."""
    return _tree_pools(spark, sf_dir, "leaves")


def jump_pool_hops(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tree_pools(spark, sf_dir, "hops")


def jump_pool_depth(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tree_pools(spark, sf_dir, "depth")


def jump_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = base(spark, sf_dir)
    return predictor.jump_precision(b.pools, b.edges)


def tree_checks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree.tree_violations(base(spark, sf_dir).hybrid)


def hybrid_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return base(spark, sf_dir).hybrid


def average_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree.cluster_tree(base(spark, sf_dir).held, "average")


def bisect_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree.bisect_tree(base(spark, sf_dir).matrices, 128, seed=CFG.seed)


def encoder_law_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The law of aligned dissimilarities and the cluster tree, substitutes of probability 0.000001 and more."""
    b = base(spark, sf_dir)
    rows = encoder.held_law(b.held, b.hybrid, 0.001, 4e-7)  # below that all are rounded to 0
    return rows.select("v", "w", r6("pr").alias("pr")).where("pr > 0")


def outside_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(v, lost_mass, outside): for laws by block, the bound of the mass outside and the exact law's mass there."""
    b = base(spark, sf_dir)
    leaves = b.store.keep(tree.bisect_tree(b.matrices, 64, seed=CFG.seed).transform(lambda t: t.join(pipeline.tree_blocks(t, 64), "v")))
    exact = encoder.law_rows(encoder.encoder_table(b.dissim, leaves, 0.001))
    block = leaves.select("v", "block")
    beyond = exact.join(block, "v").join(block.select(F.col("v").alias("w"), F.col("block").alias("other")), "w")
    true = beyond.groupBy("v").agg(F.sum(F.when(F.col("block") != F.col("other"), F.col("pr")).otherwise(0.0)).alias("outside"))
    law = encoder.pruned_table(b.dissim, leaves, F.col("block"), b.n, 0.001, matrices=b.matrices)
    return law.select("v", r6("lost_mass").alias("lost_mass")).join(true, "v").select("v", "lost_mass", r6("outside").alias("outside"))


# walks and vectors

def _flat(found: DataFrame) -> DataFrame:
    return found.select("walk_id", "hops", "jumps", F.posexplode("seq").alias("pos", "x"))


def uniform_walks(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges = graphs.document_terms(spark, sf_dir)
    return _flat(walks.uniform_walks(graphs.adjacency(edges), CFG)).drop("hops", "jumps")


def biased_walks(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges = graphs.document_terms(spark, sf_dir)
    return _flat(walks.biased_walks(edges, CFG, 0.5, 2.0)).drop("hops", "jumps")


def jump_walks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Walks with jumps, of true vertices."""
    return _flat(base(spark, sf_dir).jump_walks)


def jump_walks_intermediate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Walks whose jumps emit the neighbour that they pass over for a second time."""
    b = base(spark, sf_dir)
    return _flat(walks.true_walks(graphs.adjacency(b.edges), CFG.with_(jump_emits="intermediate"), b.pools))


def private_walks(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = base(spark, sf_dir)
    return _flat(walks.private_walks(graphs.adjacency(b.edges), b.table, b.pools, CFG))


def walks_without_privacy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ablation: jumps by pools of exact counts, and no substitution."""
    b = base(spark, sf_dir, None)
    return _flat(walks.private_walks(graphs.adjacency(b.edges), None, b.pools, CFG.with_(eps_walk=None)))


def walk_messages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cost.walk_messages(base(spark, sf_dir).jump_walks)


def messages_by_p(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean messages of walks of 40 by jump probability, under both accountings, beside their expectations."""
    store, ps = Store(spark, "messages"), [0.0, 0.1, 0.2, 0.3, 0.4]
    edges = store.keep(graphs.document_terms(spark, sf_dir))
    p = F.element_at(F.array(*[F.lit(x) for x in ps]), F.col("rep") % len(ps) + 1)
    charged = F.col("rep") < len(ps)
    cfg = CFG.with_(length=40, per_vertex=2 * len(ps), rng="xx")
    found = walks.true_walks(edges, cfg, predictor.exact_pool(graphs.adjacency(edges)), None, p, charged)
    means = found.groupBy(p.alias("p"), charged.alias("charge_final_jump")).agg(F.count("*").alias("walks"), r6(F.avg("hops")).alias("mean_messages"))
    want = cost.expected_messages(spark, [40], ps).select("p", "protocol", "published")
    return means.join(F.broadcast(want), "p").select("p", "charge_final_jump", "walks", "mean_messages", F.when(F.col("charge_final_jump"), F.col("protocol")).otherwise(F.col("published")).alias("expected"))


def expected_messages_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Expected messages by jump probability of walks as long as the sequences of events of users."""
    lengths = load(spark, sf_dir, "events").where("user_id is not null").groupBy("user_id").agg(F.count("*").cast("int").alias("length")).select("length").distinct()
    return cost.messages_of(lengths.select("length", F.explode(F.array(*[F.lit(p) for p in JUMPS])).alias("p")))


def total_saving(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What jumps save over all walks of the document graph at the usual parameters."""
    n = graphs.roster(graphs.document_terms(spark, sf_dir)).agg(F.count("*").alias("n"))
    one = cost.expected_messages(spark, [40], [0.0, 0.1, 0.2, 0.3, 0.4])
    return one.crossJoin(F.broadcast(n)).select("p", F.col("n").alias("vertices"), F.round(F.col("n") * 80 * F.col("saved"), 2).alias("total_saved"))


def _uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Store(spark, "walks").keep(walks.uniform_walks(graphs.adjacency(graphs.document_terms(spark, sf_dir)), CFG))


def cooccurrence(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cooccur.cooccurrence(_uniform(spark, sf_dir), CFG.window)


def cooccurrence_prob(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cooccur.with_probability(cooccurrence(spark, sf_dir)).select("a", "b", "n", F.round("p", 9).alias("p"))


def pmi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cooccur.pmi(cooccurrence(spark, sf_dir), 5.0).select("a", "b", r6("pmi").alias("pmi"))


def walk_dissim(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cooccur.walk_dissimilarity(cooccurrence(spark, sf_dir)).select("a", "b", F.round("dissim", 9).alias("dissim"))


def skipgram_mllib(spark: SparkSession, sf_dir: str) -> DataFrame:
    return skipgram.skipgram(_uniform(spark, sf_dir), CFG.dim, CFG.window)


def skipgram_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return skipgram.skipgram_blocks(cooccurrence(spark, sf_dir), CFG.dim, epochs=2)


def vectors_most_similar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten vertices most alike to the first one, by vectors of uniform walks."""
    e = Store(spark, "similar").keep(skipgram_mllib(spark, sf_dir))
    return skipgram.most_similar(e, e.agg(F.min("v")).first()[0], 10)


def distance_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How far distances of vectors are from the walk dissimilarities they should approximate."""
    e = Store(spark, "fit").keep(skipgram_mllib(spark, sf_dir))
    return skipgram.distance_fit(e, walk_dissim(spark, sf_dir))


# labels and measures

def label_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels of the documents of the graph."""
    edges = graphs.document_terms(spark, sf_dir)
    return graphs.labels_of_documents(spark, sf_dir).join(graphs.roster(edges), "v", "left_semi").distinct()


def split_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("v")).distinct()
    out = None
    for share in (0.1, 0.2, 0.5, 0.6):
        one = classify.split(docs, share, CFG.seed).groupBy("is_train").agg(F.count("*").alias("n"), F.sum("v").alias("sum_v")).select(F.lit(share).alias("share"), "*")
        out = one if out is None else out.union(one)
    return out


def _majority_confusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges = graphs.document_terms(spark, sf_dir)
    truth = load(spark, sf_dir, "documents").where("lang is not null").select(F.col("doc_id").alias("v"), F.col("lang").alias("label"))
    pred = baselines.neighbour_majority(edges, truth)
    return metrics.label_confusion(pred, truth.join(graphs.roster(edges), "v", "left_semi"), truth.select("label"))


def label_confusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = metrics.per_label(_majority_confusion(spark, sf_dir))
    return out.select("label", "tp", "fp", "fn", *[r6(c).alias(c) for c in ("precision", "recall", "f1")])


def macro_f1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.macro_f1(_majority_confusion(spark, sf_dir)).select(r6("macro_f1").alias("macro_f1"))


def pooled_f1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.pooled_f1(_majority_confusion(spark, sf_dir)).select(r6("pooled_f1").alias("pooled_f1"))


def chance_f1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pooled F1 of the most frequent language and of languages drawn at random."""
    truth = load(spark, sf_dir, "documents").where("lang is not null").select(F.col("doc_id").alias("v"), F.col("lang").alias("label"))
    out = None
    for name, pred in (("majority", baselines.majority_label(truth, truth)), ("random", baselines.random_label(truth, truth, CFG.seed))):
        one = metrics.pooled_f1(metrics.label_confusion(pred, truth)).select(F.lit(name).alias("predictor"), r6("pooled_f1").alias("pooled_f1"))
        out = one if out is None else out.union(one)
    return out


def message_ledger_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = base(spark, sf_dir)
    ledger = cost.message_ledger(b.edges, b.jump_walks, b.k)
    return cost.ledger_cube(ledger).select(*[F.coalesce(c, F.lit("all")).alias(c) for c in ("phase", "src_role", "dst_role")], "n", "bytes")


def privacy_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Budgets of devices by the elements they emit on private walks; substitution does not move a walk."""
    return cost.privacy_ledger(base(spark, sf_dir).jump_walks, EPS, EPS, 1)


def row_linkability(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = base(spark, sf_dir, None)
    return cost.row_linkability(b.matrices, b.vectors)


def randomized_response(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs two links apart and their reports."""
    edges = graphs.document_terms(spark, sf_dir)
    pairs = baselines.exact_two_hop(edges).select("v", F.col("w").alias("u")).union(edges.select("v", "u"))
    told = baselines.randomized_response(pairs, edges, 1.0, CFG.seed)
    return told.groupBy("linked", "told").agg(F.count("*").alias("n"), F.sum(F.col("v") * 31 + F.col("u")).alias("stamp"))


def exact_two_hop(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.exact_two_hop(graphs.document_terms(spark, sf_dir))


def shared_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Numbers of common neighbours of linked vertices."""
    edges = graphs.document_terms(spark, sf_dir)
    both = edges.where("v < u").join(edges.select("v", F.col("u").alias("w")), "v").join(edges.select(F.col("v").alias("u"), F.col("u").alias("w")), ["u", "w"])
    return both.groupBy("v", "u").agg(F.count("*").alias("n"))


# other relational and event operators

def asof_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each purchase with the user's last earlier event of another kind."""
    ev = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    other = F.when(F.col("event_type") != "purchase", F.struct("event_id", "event_type"))
    seen = ev.withColumn("last", F.last(other, ignorenulls=True).over(w)).where("event_type = 'purchase'")
    return seen.select("event_id", "user_id", F.col("last.event_id").alias("last_id"), F.col("last.event_type").alias("last_type"))


def interval_user_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of users with events within ten minutes, by pairs of blocks of users."""
    ev = load(spark, sf_dir, "events").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    return intervals.user_pairs(ev, 600_000_000)


def event_props_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = load(spark, sf_dir, "events").select("event_type", F.get_json_object("props", "$.k").cast("int").alias("k"))
    return ev.groupBy("event_type", "k").agg(F.count("*").alias("n"))


def session_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of users, closed by thirty minutes of silence."""
    ev = load(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    got = ev.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return got.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


def sliding_activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = load(spark, sf_dir, "events").select("event_type", F.col("ts").cast("timestamp").alias("ts"))
    got = ev.groupBy("event_type", F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return got.select("event_type", F.unix_micros("w.start").alias("start_us"), "n")


def degree_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degree rank, share and quarter of each part within its brand."""
    deg = graphs.copurchase(spark, sf_dir).groupBy(F.col("v").alias("p_partkey")).agg(F.count("*").alias("degree"))
    rows = load(spark, sf_dir, "part").select("p_partkey", "p_brand").join(deg, "p_partkey")
    w = Window.partitionBy("p_brand").orderBy("degree", "p_partkey")
    return rows.select("p_partkey", "p_brand", "degree", F.dense_rank().over(w).alias("band"), r6(F.percent_rank().over(w)).alias("share"), F.ntile(4).over(w).alias("quarter"))


def stream_bin_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.bin_counts_of_events(spark, sf_dir)


# end to end and workloads

SMALL = WalkConfig(length=10, per_vertex=5, window=5, dim=32, seed="1")


def _languages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").where("lang is not null").select(F.col("doc_id").alias("v"), F.concat(F.lit("lang:"), "lang").alias("label"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(v, vec, messages): vectors of the private method and the messages of each vertex's walks."""
    edges = Store(spark, "flagship").keep(graphs.document_terms(spark, sf_dir))
    fit = pipeline.fit_private(edges, SMALL)
    sent = fit.walks.groupBy(F.col("start").alias("v")).agg(F.sum("hops").cast("long").alias("messages"))
    return fit.embedding.join(sent, "v", "left").select("v", "vec", F.coalesce("messages", F.lit(0)).alias("messages"))


#: Seeds over which the workloads are repeated.
SEEDS = ("1", "2", "3")
#: Parameters and grids of the workloads as surveyed; SMALL takes the same grids with shorter and fewer walks.
FULL = WalkConfig(length=40, per_vertex=80, window=10, dim=128, seed="1")
SHARES = [0.1, 0.2, 0.3, 0.4, 0.5, 0.6]
SPARSE = [0.01, 0.02, 0.03, 0.04, 0.05, 0.06, 0.07, 0.08, 0.09, 0.1]
SOME_SHARES = [0.1, 0.2, 0.5, 0.6]
JUMPS = [0.0, 0.1, 0.2, 0.3, 0.4]
NOISES = [0.5, 1.0, 2.0, 4.0]


def _graph(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """Kept edges of a workload's graph, and its labels."""
    make, truth = {"documents": (graphs.document_terms, graphs.labels_of_documents), "copurchase": (graphs.copurchase, graphs.labels_of_parts), "succession": (graphs.succession, graphs.labels_of_users)}[name]
    return Store(spark, "workload").keep(make(spark, sf_dir)), truth(spark, sf_dir)


def _compare(spark: SparkSession, sf_dir: str, shares: list[float], cfg: WalkConfig = SMALL, graph: str = "documents") -> DataFrame:
    return pipeline.sweep(*_graph(spark, sf_dir, graph), cfg, {"jump": [0.2]}, shares, SEEDS)


def _sweep(spark: SparkSession, sf_dir: str, cfg: WalkConfig, grid: dict[str, list], graph: str = "documents", seeds: tuple[str, ...] = SEEDS) -> DataFrame:
    return pipeline.sweep(*_graph(spark, sf_dir, graph), cfg, grid, SOME_SHARES, seeds, baseline=False)


def _sweep_k(spark: SparkSession, sf_dir: str, cfg: WalkConfig, graph: str = "documents") -> DataFrame:
    """All numbers of bins from two to their bound."""
    edges, truth = _graph(spark, sf_dir, graph)
    most = default_bins(graphs.roster(edges).count())
    return pipeline.sweep(edges, truth, cfg, {"bins": list(range(2, most + 1))}, SOME_SHARES, SEEDS, baseline=False)


def _sweep_walks(spark: SparkSession, sf_dir: str, cfg: WalkConfig, numbers: list[int]) -> DataFrame:
    """All pairs of walks per vertex and jump probability; trees are shared."""
    edges, truth = _graph(spark, sf_dir, "documents")
    trees, out = {}, None
    for n in numbers:
        rows = pipeline.sweep(edges, truth, cfg.with_(per_vertex=n), {"jump": JUMPS}, SOME_SHARES, baseline=False, trees=trees).withColumn("per_vertex", F.lit(n))
        out = rows if out is None else out.unionByName(rows)
    return out


def private_against_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both methods by share of training vertices."""
    return _compare(spark, sf_dir, SHARES)


def private_against_uniform_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both methods with few training vertices."""
    return _compare(spark, sf_dir, SPARSE)


def sweep_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sweep_k(spark, sf_dir, SMALL)


def sweep_eps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Noise of counts and of walks together, and each alone at the usual amount of the other."""
    return _sweep(spark, sf_dir, SMALL, {"eps": NOISES, "eps_degree": NOISES, "eps_walk": NOISES})


def score_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gaps of the private method to uniform walks, as means over seeds, by share of training vertices."""
    found = pipeline.score_gaps(private_against_uniform(spark, sf_dir))
    return found.select("share", "measure", *[r6(c).alias(c) for c in ("uniform", "private", "points", "relative")])


def sweep_p_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Means and spreads of the jump sweep over its seeds."""
    return pipeline.repeated(sweep_p(spark, sf_dir))


def private_against_uniform_succession(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A control: users who merely follow one another tell nothing about one another's kinds of events."""
    return _compare(spark, sf_dir, SHARES, SMALL, "succession")


def no_privacy_against_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ablation without any noise or substitution, against uniform walks and the full method."""
    edges, truth = _graph(spark, sf_dir, "documents")
    bare = pipeline.sweep(edges, truth, SMALL.with_(eps_degree=None, eps_walk=None), {"jump": [0.2]}, SOME_SHARES, SEEDS)
    return bare.withColumn("method", F.when(F.col("method") == "private", "no privacy").otherwise(F.col("method")))


def sweep_p(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sweep(spark, sf_dir, SMALL, {"jump": JUMPS})


def sweep_walks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sweep_walks(spark, sf_dir, SMALL, [2, 5, 10, 20])


def full_private_against_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _compare(spark, sf_dir, SHARES, FULL)


def full_private_against_uniform_copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _compare(spark, sf_dir, SHARES, FULL, "copurchase")


def full_private_against_uniform_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _compare(spark, sf_dir, SPARSE, FULL)


def full_private_against_uniform_sparse_copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _compare(spark, sf_dir, SPARSE, FULL, "copurchase")


def full_sweep_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sweep_k(spark, sf_dir, FULL)


def full_sweep_k_copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sweep_k(spark, sf_dir, FULL, "copurchase")


def full_sweep_eps(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sweep(spark, sf_dir, FULL, {"eps": NOISES})


def full_sweep_eps_succession(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sweep(spark, sf_dir, FULL, {"eps": NOISES}, "succession")


def full_sweep_p(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sweep(spark, sf_dir, FULL, {"jump": JUMPS})


def full_sweep_walks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sweep_walks(spark, sf_dir, FULL, [20, 40, 60, 80])


def copurchase_at_scale(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors of the large co-purchase graph: tree by bisection, laws by block, pools by block and its parents, all rows."""
    store = Store(spark, "scale")
    edges = store.keep(graphs.copurchase(spark, sf_dir))
    cfg = SMALL.with_(tree="bisect", block=128, per_vertex=1, rng="xx")
    fit = pipeline.fit_private(edges, cfg, "blocks")
    return fit.embedding.withColumn("mode", F.lit(fit.mode))


def pool_shortfall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Members that pools by block want and hold on the large co-purchase graph."""
    edges = Store(spark, "scale").keep(graphs.copurchase(spark, sf_dir))
    cfg = SMALL.with_(tree="bisect", block=128, rng="xx")
    parts = pipeline.build_tree_parts(edges, cfg)
    return pipeline.pool_shortfall(parts, pipeline.laws(parts, cfg)[1], cfg)


def ovr_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of languages for all vertices from vectors of uniform walks."""
    e = Store(spark, "ovr").keep(skipgram_mllib(spark, sf_dir))
    names, w = classify.fit_ovr(e, _languages(spark, sf_dir).join(e.select("v"), "v", "left_semi"))
    return classify.scores(e, names, w)


NAMES = """g1_edges g2_edges g3_edges g4_edges g5_edges g6_edges vector_knn graph_stats degree_histogram degree_core bin_plan bin_counts
degree_vectors_clean degree_vectors_noisy estimated_degree neighbour_order matrix_rows row_l1 align_clean align_noisy align_expr align_one_sided
align_banded align_pruned align_error_bound degree_list_align overlap_dissim dissim_all capped_matrices median_tree lca_leaves encoder_law
encoder_draws encoder_utility encoder_calibrated jump_pool jump_pool_floor jump_precision tree_checks hybrid_tree average_tree bisect_tree
uniform_walks biased_walks jump_walks private_walks walk_messages messages_by_p expected_messages_grid total_saving cooccurrence
cooccurrence_prob pmi walk_dissim skipgram_mllib skipgram_blocks label_matrix split_counts label_confusion macro_f1 pooled_f1 chance_f1
message_ledger_cube privacy_ledger row_linkability randomized_response exact_two_hop shared_neighbours asof_segment interval_user_pairs
event_props_json session_windows sliding_activity degree_bands stream_bin_counts flagship private_against_uniform
private_against_uniform_sparse sweep_k sweep_eps sweep_p sweep_walks full_private_against_uniform
full_private_against_uniform_copurchase full_private_against_uniform_sparse full_private_against_uniform_sparse_copurchase full_sweep_k
full_sweep_k_copurchase full_sweep_eps full_sweep_eps_succession full_sweep_p full_sweep_walks copurchase_at_scale ovr_scores
matrix_rows_perturbed encoder_audit encoder_law_tree outside_mass jump_pool_stochastic jump_pool_tree jump_pool_hops jump_pool_depth
jump_walks_intermediate walks_without_privacy vectors_most_similar distance_fit score_gaps sweep_p_means private_against_uniform_succession
no_privacy_against_uniform pool_shortfall""".split()
#: Workloads at full parameters take from many minutes to hours for each call: experiments.py runs them by name.
LONG = [name for name in NAMES if name.startswith("full_")]


def queries() -> dict[str, Query]:
    return {name: globals()[name] for name in NAMES}
