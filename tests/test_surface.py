"""SQL functions, sinks and sources."""

from pyspark.sql import functions as F

from veilwalk.config import WalkConfig
from veilwalk.functions import registry
from veilwalk.operators import cooccur, cost, walks
from veilwalk.sources import graphs, sinks, tables


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_sql_functions(spark):
    registry.register(spark)
    got = spark.sql("select align_dissimilarity(a, b) from values (array(array(1d,2d),array(3d,1d),array(0d,0d)), array(array(1d,1d),array(2d,2d))), (null, array(array(1d))) t(a, b)")
    assert [r[0] for r in got.collect()] == [7.0, None]
    w = spark.createDataFrame([(0, [1, 2, 1, 3]), (1, [4])], "walk_id long, seq array<long>")
    w.createOrReplaceTempView("walk_table")
    pairs = spark.sql("select p.a, p.b from walk_table, lateral walk_pairs(seq, 2) p")
    assert rows(pairs) == rows(cooccur.walk_pairs(w, 2))
    near = spark.sql("select * from nearest_leaves(5, 11, 4)")
    assert [tuple(r) for r in near.collect()] == [(4, 2), (6, 4), (7, 4), (0, 8)]


def test_sinks_round_trip(spark, tmp_path):
    edges = graphs.symmetrize(spark.createDataFrame([(1, 2), (2, 3), (3, 1)], "v long, u long"))
    w = walks.uniform_walks(graphs.adjacency(edges), WalkConfig(length=3, per_vertex=2))
    path = f"file://{tmp_path}"
    sinks.write_walks(w, f"{path}/walks")
    assert rows(sinks.read_walks(spark, f"{path}/walks").select("walk_id", "rep")) == rows(w.select("walk_id", "rep"))
    one = sinks.read_walks(spark, f"{path}/walks", [1])
    assert one.count() == 3 and "PartitionFilters: [isnotnull(rep" in one._jdf.queryExecution().executedPlan().toString()
    ledger = cost.message_ledger(edges, w, 2)
    sinks.write_ledger(ledger, f"{path}/ledger")
    assert rows(sinks.read_ledger(spark, f"{path}/ledger")) == rows(ledger)
    sinks.write_orc(edges, f"{path}/orc")
    assert rows(spark.read.orc(f"{path}/orc").select("v", "u")) == rows(edges)


def test_bucketed_join_deals_one_side(spark):
    edges = graphs.symmetrize(spark.createDataFrame([(a, a + 1) for a in range(50)], "v long, u long"))
    sinks.write_bucketed(edges, "bucketed_edges", "v", 4)
    other = spark.range(50).select(F.col("id").alias("v"))
    plan = spark.table("bucketed_edges").hint("merge").join(other, "v")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") <= 1
    spark.sql("drop table bucketed_edges")


def test_views(spark, sf):
    tables.register_views(spark, {"g2": graphs.document_terms(spark, sf)})
    assert spark.sql("select count(*) from g2").first()[0] > 0
