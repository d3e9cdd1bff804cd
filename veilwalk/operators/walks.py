"""Random walks over devices: uniform, biased, and private with two-hop jumps and substituted vertices.

A walk's course never depends on substituted vertices, so walks are run on true ones and all substitutions are drawn in
one join at the end. Pools depend on a vertex alone and are joined like its neighbours.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from veilwalk.config import WalkConfig
from veilwalk.functions.draws import SPAN, number, unit
from veilwalk.operators.encoder import encode
from veilwalk.plans.lineage import Store

#: Rounds between two tables.
EVERY = 4
LOCAL_EDGES = 2_000_000


def seeds(starts: DataFrame, per_vertex: int) -> DataFrame:
    """(walk_id, start, rep): walks of each start; ids follow from start and repetition."""
    reps = F.explode(F.sequence(F.lit(0), F.lit(per_vertex - 1)))
    return starts.select(F.col("v").alias("start"), reps.alias("rep")).select((F.col("start") * per_vertex + F.col("rep")).alias("walk_id"), "start", "rep")


def indexed_edges(graph: DataFrame, pools: DataFrame | None) -> DataFrame:
    """(v, i, u, du, pu): the i-th neighbour u of v, u's degree and the size of u's pool.

    graph is an adjacency, or edges (v, u), whose hubs then never form an array. A walk at a hub needs one row of it,
    and walks at one hub need different rows, so hubs are no hot keys.
    """
    if "nbrs" in graph.columns:
        rows = graph.select("v", F.posexplode("nbrs").alias("i", "u"))
    else:
        rows = graph.select("v", (F.row_number().over(Window.partitionBy("v").orderBy("u")) - 1).alias("i"), "u")
    deg = rows.groupBy(F.col("v").alias("u")).agg(F.count("*").alias("du"))
    rows = rows.join(deg, "u")
    if pools is None:
        return rows.select("v", F.col("i").cast("long").alias("i"), "u", "du", F.lit(0).cast("long").alias("pu"))
    sizes = pools.select("u", F.size("pool").cast("long").alias("pu"))
    return rows.join(sizes, "u", "left").select("v", F.col("i").cast("long").alias("i"), "u", "du", F.coalesce("pu", F.lit(0)).alias("pu"))


def walk_tables(graph: DataFrame, pools: DataFrame | None) -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """Kept tables that all walks of a graph and its pools share: numbered edges, degrees, numbered pool members."""
    store = Store(graph.sparkSession, "walktables")
    edges = store.keep(indexed_edges(graph, pools))
    deg = store.keep(edges.groupBy("v").agg(F.count("*").alias("deg")))
    if pools is None:
        return edges, deg, None
    held = pools.select(F.col("u").alias("_u"), F.posexplode("pool").alias("_j", "w"))
    return edges, deg, store.keep(held.join(deg.select(F.col("v").alias("w"), F.col("deg").alias("dw")), "w").select("_u", F.col("_j").cast("long").alias("_j"), "w", "dw"))


def true_walks(graph: DataFrame, cfg: WalkConfig, pools: DataFrame | None = None, starts: DataFrame | None = None, jump: Column | None = None, charged: Column | None = None, tables: tuple | None = None) -> DataFrame:
    """(walk_id, start, rep, seq, hops, jumps, pool_empty, emitters): walks of true vertices over an adjacency or edges.

    Each round moves every open walk one step: it draws the number of its next neighbour and is joined with that one
    row. A step emits a neighbour u. With more than two left to emit and a draw below the jump probability, it also
    emits a vertex u' of u's pool and goes there at once; an empty pool leaves the step as it is. emitters names the
    device that holds the walk and emits each element: a jump's two elements come from one device. All rounds are
    expressions over deterministic draws, so a task that runs again repeats its walks; a table every few rounds keeps
    plans short. jump and charged, expressions of rep, take the place of the configuration's for walks that differ.
    """
    store = Store(graph.sparkSession, "walks")
    pools = None if not cfg.jump and jump is None else pools
    jump = F.lit(cfg.jump) if jump is None else jump
    charged = F.lit(cfg.charge_final_jump) if charged is None else charged
    edges, deg, jumps = walk_tables(graph, pools) if tables is None else tables
    jumps = None if pools is None else jumps
    begin = deg if starts is None else deg.join(starts.select("v"), "v", "left_semi")
    first = seeds(begin.select("v"), cfg.per_vertex).join(begin.select(F.col("v").alias("start"), "deg"), "start")
    state = first.select(
        "walk_id", "start", "rep", F.col("start").alias("at"), "deg", F.lit(cfg.length).alias("left"), F.array().cast("array<long>").alias("seq"),
        F.lit(0).alias("hops"), F.lit(0).alias("jumps"), F.lit(0).alias("pool_empty"), F.array().cast("array<long>").alias("emitters"),
    )
    ended = []
    for step in range(cfg.length):
        open_ = F.col("left") > 0
        drawn = state.withColumn("_i", F.when(open_, F.floor(unit(cfg.seed, "step", "walk_id", "left", rng=cfg.rng) * F.col("deg"))))
        moved = drawn.join(edges, (F.col("at") == F.col("v")) & (F.col("_i") == F.col("i")), "left").drop("v", "i", "_i")
        fired = jumped = F.lit(False)
        to, onward = F.col("u"), F.col("du")
        if jumps is not None:
            fired = (F.col("left") > 2) & (unit(cfg.seed, "jump", "walk_id", "left", rng=cfg.rng) < jump)
            jumped = fired & (F.col("pu") > 0)
            far = F.floor(unit(cfg.seed, "pool", "walk_id", "left", rng=cfg.rng) * F.col("pu"))
            moved = moved.withColumn("_f", F.when(jumped, far)).join(jumps, (F.col("u") == F.col("_u")) & (F.col("_f") == F.col("_j")), "left").drop("_u", "_j", "_f")
            to, onward = F.when(jumped, F.col("w")).otherwise(F.col("u")), F.when(jumped, F.col("dw")).otherwise(F.col("du"))
        second = F.col("u") if cfg.jump_emits == "intermediate" else to
        left = F.col("left") - F.when(jumped, 2).otherwise(1)
        sends = (left > 0) & (charged | ~(jumped & (left <= 2)))
        stay = lambda name, new: F.when(open_, new).otherwise(F.col(name)).alias(name)
        state = moved.select(
            "walk_id", "start", "rep", stay("at", to), stay("deg", onward), stay("left", left),
            stay("seq", F.concat("seq", F.when(jumped, F.array(F.col("u"), second)).otherwise(F.array("u")))),
            stay("hops", F.col("hops") + sends.cast("int")), stay("jumps", F.col("jumps") + jumped.cast("int")),
            stay("pool_empty", F.col("pool_empty") + (fired & ~jumped).cast("int")),
            stay("emitters", F.concat("emitters", F.when(jumped, F.array("at", "at")).otherwise(F.array("at")))),
        )
        if step % EVERY == EVERY - 1 or step == cfg.length - 1:
            state = store.keep(state)
            if 2 * (step + 1) >= cfg.length:
                ended.append(state.where("left <= 0"))
                state = state.where("left > 0")
    out = ended[0]
    for more in ended[1:]:
        out = out.union(more)
    return out.select("walk_id", "start", "rep", "seq", "hops", "jumps", "pool_empty", "emitters")


def uniform_walks(graph: DataFrame, cfg: WalkConfig, starts: DataFrame | None = None) -> DataFrame:
    """The centralized baseline: no jumps, no substitution."""
    return true_walks(graph, cfg.with_(jump=0.0), None, starts)


def substituted(walks: DataFrame, table: DataFrame | None, cfg: WalkConfig) -> DataFrame:
    """walks with seq replaced by substitutes; without a law they stay true."""
    if table is None or cfg.eps_walk is None:
        return walks
    flat = walks.select("walk_id", F.posexplode("seq").alias("i", "x"))
    drawn = encode(flat, table, "x", "y", cfg.seed, "walk_id", "i", rng=cfg.rng)
    seq = drawn.groupBy("walk_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "y"))), lambda r: r["y"]).alias("seq"))
    return walks.drop("seq").join(seq, "walk_id").select("walk_id", "start", "rep", "seq", "hops", "jumps", "pool_empty", "emitters")


def private_walks(graph: DataFrame, table: DataFrame | None, pools: DataFrame | None, cfg: WalkConfig, starts: DataFrame | None = None, tables: tuple | None = None) -> DataFrame:
    return substituted(true_walks(graph, cfg, pools, starts, tables=tables), table, cfg)


def local_walks(adjacency: DataFrame, cfg: WalkConfig, starts: DataFrame | None = None, ret: float = 1.0, inout: float = 1.0) -> DataFrame:
    """Uniform or biased second-order walks with the graph in each task, for graphs up to LOCAL_EDGES; biased_walks has no such limit.

    ret and inout weigh the return to the previous vertex, and vertices it has no link to, by their inverses.
    """
    edges = adjacency.agg(F.coalesce(F.sum("deg"), F.lit(0)).alias("n")).first()["n"]
    if edges > LOCAL_EDGES:
        raise ValueError("graph too large for local walks")
    graph = {r["v"]: np.array(r["nbrs"]) for r in adjacency.select("v", "nbrs").collect()}  # checked: at most LOCAL_EDGES
    sets = {v: set(n.tolist()) for v, n in graph.items()} if (ret, inout) != (1.0, 1.0) else {}
    shared = adjacency.sparkSession.sparkContext.broadcast((graph, sets))
    length, seed = cfg.length, cfg.seed

    def run(batches):
        import hashlib

        graph, sets = shared.value
        draw = lambda *k: int(hashlib.md5("|".join(map(str, (seed, *k))).encode()).hexdigest()[:13], 16) / float(1 << 52)
        for pdf in batches:
            seqs = []
            for walk, start in zip(pdf["walk_id"], pdf["start"], strict=True):
                at, last, seq = start, None, []
                for left in range(length, 0, -1):
                    nbrs, u = graph[at], draw("step", walk, left)
                    if last is None or not sets:
                        to = nbrs[int(u * len(nbrs))]
                    else:
                        w = np.array([1 / ret if n == last else 1.0 if n in sets[last] else 1 / inout for n in nbrs.tolist()])
                        c = np.cumsum(w)
                        to = nbrs[min(int(np.searchsorted(c, u * c[-1], "right")), len(nbrs) - 1)]
                    seq.append(int(to))
                    last, at = at, int(to)
                seqs.append(seq)
            yield pd.DataFrame({"walk_id": pdf["walk_id"], "start": pdf["start"], "rep": pdf["rep"], "seq": seqs, "hops": length - 1, "jumps": 0, "pool_empty": 0})

    begin = adjacency.select("v") if starts is None else starts.select("v")
    schema = "walk_id long, start long, rep int, seq array<long>, hops int, jumps int, pool_empty int"
    return seeds(begin, cfg.per_vertex).mapInPandas(run, schema)


def biased_walks(graph: DataFrame, cfg: WalkConfig, ret: float, inout: float, starts: DataFrame | None = None) -> DataFrame:
    """Second-order walks (walk_id, start, rep, seq, hops, jumps, pool_empty) over edges or an adjacency of any size.

    A step is a race of exponential clocks among the neighbours of a walk's vertex: each has a draw of its own, divided
    by its weight, and the least one wins; so no walk needs the sum of its weights, and a task hands on one candidate
    for each walk. The weight is 1 / ret for the previous vertex, 1 for vertices linked to it, 1 / inout for others.
    """
    store = Store(graph.sparkSession, "biased")
    edges = store.keep(graph.select("v", F.explode("nbrs").alias("u")) if "nbrs" in graph.columns else graph.select("v", "u"))
    begin = edges.select("v").distinct() if starts is None else starts.select("v").join(edges, "v", "left_semi")
    state = seeds(begin, cfg.per_vertex).select("walk_id", "start", "rep", F.col("start").alias("at"), F.lit(None).cast("long").alias("last"), F.array().cast("array<long>").alias("seq"))
    linked = edges.select(F.col("v").alias("last"), "u", F.lit(True).alias("linked"))
    for step in range(cfg.length):
        near = state.join(edges, F.col("at") == F.col("v")).drop("v").join(linked, ["last", "u"], "left")
        weight = F.when(F.col("u") == F.col("last"), 1 / ret).when(F.col("last").isNull() | F.col("linked"), 1.0).otherwise(1 / inout)
        clock = -F.log((number(cfg.seed, "race", "walk_id", F.lit(cfg.length - step), "u", rng=cfg.rng) + F.lit(0.5)) / F.lit(SPAN)) / weight
        first = near.groupBy("walk_id").agg(*[F.first(c).alias(c) for c in ("start", "rep", "at", "seq")], F.min_by("u", F.struct(clock, "u")).alias("to"))
        state = first.select("walk_id", "start", "rep", F.col("to").alias("at"), F.col("at").alias("last"), F.concat("seq", F.array("to")).alias("seq"))
        if step % EVERY == EVERY - 1:
            state = store.keep(state)
    return store.keep(state.select("walk_id", "start", "rep", "seq", F.lit(cfg.length - 1).alias("hops"), F.lit(0).alias("jumps"), F.lit(0).alias("pool_empty")))
