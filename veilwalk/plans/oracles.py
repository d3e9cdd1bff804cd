"""DuckDB SQL with the rows of the queries of the same names, written on its own from the tables."""

from __future__ import annotations

import re

from veilwalk.functions.draws import SPAN, laplace_sql, unit_sql

SEED, EPS, LENGTH, PER_VERTEX, JUMP, WINDOW, LANDMARKS = "1", 2.0, 6, 2, 0.2, 3, 3

PARTS: dict[str, str] = {}
PARTS["g1"] = "g1 AS (SELECT DISTINCT a.l_partkey AS v, b.l_partkey AS u FROM lineitem a JOIN lineitem b USING (l_orderkey) WHERE a.l_partkey <> b.l_partkey)"
PARTS["g2"] = r"""held AS (SELECT DISTINCT doc_id, w FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS w FROM documents) WHERE length(w) >= 4),
rare AS (SELECT w FROM held GROUP BY w HAVING count(*) BETWEEN 2 AND 20),
g2 AS (SELECT a.doc_id AS v, b.doc_id AS u FROM held a JOIN held b USING (w) JOIN rare USING (w) WHERE a.doc_id <> b.doc_id GROUP BY ALL HAVING count(*) >= 8)"""
PARTS["g3"] = "h3 AS (SELECT DISTINCT o_custkey * 2 AS v, l_suppkey * 2 + 1 AS u FROM orders JOIN lineitem ON o_orderkey = l_orderkey), g3 AS (SELECT v, u FROM h3 UNION SELECT u, v FROM h3)"
PARTS["g4"] = "h4 AS (SELECT user_id AS v, lead(user_id) OVER (ORDER BY ts, event_id) AS u FROM events), g4 AS (SELECT v, u FROM h4 WHERE u IS NOT NULL AND v <> u UNION SELECT u, v FROM h4 WHERE u IS NOT NULL AND v <> u)"
PARTS["g6"] = """h6 AS (SELECT n_nationkey::BIGINT * 4 + 2 AS v, n_regionkey::BIGINT * 4 + 3 AS u FROM nation UNION SELECT c_custkey * 4, c_nationkey::BIGINT * 4 + 2 FROM customer
UNION SELECT s_suppkey * 4 + 1, s_nationkey::BIGINT * 4 + 2 FROM supplier), g6 AS (SELECT v, u FROM h6 UNION SELECT u, v FROM h6)"""
PARTS["verts"] = "verts AS (SELECT DISTINCT v FROM g2), size AS (SELECT count(*) AS n, greatest(1, floor(ln(count(*))))::BIGINT AS k FROM verts)"
PARTS["plan"] = f"""plan AS (SELECT v, ordinal, (ordinal % (SELECT k FROM size) + 1)::INT AS bin FROM
(SELECT v, row_number() OVER (ORDER BY {unit_sql(SEED, 'number', 'v')}, v) - 1 AS ordinal FROM verts))"""
PARTS["counts"] = """counts AS (SELECT v, bin, coalesce(n, 0) AS n FROM (SELECT v, unnest(range(1, (SELECT k FROM size) + 1)) AS bin FROM verts)
LEFT JOIN (SELECT g2.v, p.bin, count(*) AS n FROM g2 JOIN plan p ON p.v = g2.u GROUP BY ALL) USING (v, bin))"""
PARTS["noisy"] = f"cells AS (SELECT v, bin, n + {laplace_sql(SEED, 'laplace', 'v', 'bin', scale=1.0 / EPS)} AS c FROM counts)"
PARTS["clean"] = "cells AS (SELECT v, bin, n::DOUBLE AS c FROM counts)"
PARTS["vectors"] = "vectors AS (SELECT v, list(c ORDER BY bin) AS c, sum(c) AS est FROM cells GROUP BY v)"
PARTS["order"] = "nbrs AS (SELECT g2.v, g2.u, t.c, row_number() OVER (PARTITION BY g2.v ORDER BY t.est, g2.u) - 1 AS pos FROM g2 JOIN vectors t ON t.v = g2.u)"
PARTS["matrices"] = "matrices AS (SELECT v, list(c ORDER BY pos) AS m, count(*) AS n FROM nbrs GROUP BY v)"
PARTS["marks"] = f"marks AS (SELECT p.v AS u, a.v FROM plan p, verts a WHERE p.ordinal < {LANDMARKS} AND p.v <> a.v)"
PARTS["ranks"] = "ranks AS (SELECT v, row_number() OVER (ORDER BY round(est, 9), v) - 1 AS ordinal FROM vectors)"
#: Leaves below the lowest common ancestor of ordinals i and j.
LCA = (
    "CASE WHEN {i} = {j} THEN 1 ELSE least((SELECT n FROM size), (({i} >> length(ltrim(bin(xor({i}, {j})), '0'))) + 1) << length(ltrim(bin(xor({i}, {j})), '0')))"
    " - (({i} >> length(ltrim(bin(xor({i}, {j})), '0'))) << length(ltrim(bin(xor({i}, {j})), '0'))) END"
)
L1 = "list_sum(list_transform(range(1, len({a}) + 1), lambda z: abs({a}[z] - {b}[z])))"
PARTS["pairs"] = f"""pairs AS (SELECT a.v, b.v AS w, {LCA.format(i='a.ordinal', j='b.ordinal')} AS leaves, {L1.format(a='x.c', b='y.c')} AS delta
FROM ranks a, ranks b, vectors x, vectors y WHERE x.v = a.v AND y.v = b.v)"""
PARTS["law"] = """scored AS (SELECT v, w, -delta * leaves AS s FROM pairs), weighed AS (SELECT v, w, s, exp({factor} * (s - max(s) OVER (PARTITION BY v))) AS x FROM scored),
law AS (SELECT v, w, s, x / sum(x) OVER (PARTITION BY v) AS pr FROM weighed)"""
PARTS["pool"] = """wanted AS (SELECT v AS u, bin, greatest(0, least({rounded}, (SELECT count(*) FROM plan q WHERE q.bin = cells.bin) - (SELECT count(*) FROM plan q WHERE q.v = cells.v AND q.bin = cells.bin)))::BIGINT AS m FROM cells),
pool AS (SELECT u, w FROM (SELECT p.v AS u, p.w, q.bin, row_number() OVER (PARTITION BY p.v, q.bin ORDER BY p.leaves, round(p.delta, 9), p.w) AS r
FROM pairs p JOIN plan q ON q.v = p.w WHERE p.v <> p.w) JOIN wanted USING (u, bin) WHERE r <= m)"""
PARTS["adj"] = "adj AS (SELECT v, list(u ORDER BY u) AS nbrs, count(*) AS deg FROM g2 GROUP BY v)"
PARTS["uniform"] = f"""steps AS (SELECT v * {PER_VERTEX} + r AS walk_id, v AS at, {LENGTH} AS rest, NULL::BIGINT AS x FROM adj, range({PER_VERTEX}) t(r)
UNION ALL SELECT walk_id, nbrs[floor({unit_sql(SEED, 'step', 'walk_id', 'rest')} * deg)::INT + 1], rest - 1, nbrs[floor({unit_sql(SEED, 'step', 'walk_id', 'rest')} * deg)::INT + 1]
FROM steps JOIN adj ON adj.v = steps.at WHERE rest > 0),
walks AS (SELECT walk_id, ({LENGTH} - 1 - rest)::INT AS pos, x FROM steps WHERE x IS NOT NULL)"""
PARTS["jumps"] = f"""pools AS (SELECT u, list(w ORDER BY w) AS pool FROM pool GROUP BY u),
hop AS (SELECT v * {PER_VERTEX} + r AS walk_id, v AS at, {LENGTH} AS rest, []::BIGINT[] AS seq, []::BIGINT[] AS emitters, 0 AS hops, 0 AS jumps, 0 AS missed FROM adj, range({PER_VERTEX}) t(r)
UNION ALL SELECT walk_id, CASE WHEN j THEN w ELSE x END, rest - CASE WHEN j THEN 2 ELSE 1 END, list_concat(seq, CASE WHEN j THEN [x, w] ELSE [x] END), list_concat(emitters, CASE WHEN j THEN [held, held] ELSE [held] END),
hops + (rest - CASE WHEN j THEN 2 ELSE 1 END > 0)::INT, jumps + j::INT, missed + (f AND NOT j)::INT
FROM (SELECT *, f AND pool IS NOT NULL AS j, pool[floor({unit_sql(SEED, 'pool', 'walk_id', 'rest')} * len(pool))::INT + 1] AS w FROM
(SELECT walk_id, hop.at AS held, rest, seq, emitters, hops, jumps, missed, rest > 2 AND {unit_sql(SEED, 'jump', 'walk_id', 'rest')} < {JUMP} AS f,
nbrs[floor({unit_sql(SEED, 'step', 'walk_id', 'rest')} * deg)::INT + 1] AS x FROM hop JOIN adj ON adj.v = hop.at WHERE rest > 0) LEFT JOIN pools ON pools.u = x)),
ended AS (SELECT walk_id, seq, emitters, hops, jumps, missed FROM hop WHERE rest = 0)"""
PARTS["cooc"] = f"""cooc AS (SELECT a.x AS a, b.x AS b, count(*) AS n FROM walks a JOIN walks b ON a.walk_id = b.walk_id AND a.pos <> b.pos AND abs(a.pos - b.pos) <= {WINDOW} GROUP BY ALL)"""
PARTS["majority"] = """truth AS (SELECT doc_id AS v, lang AS label FROM documents WHERE lang IS NOT NULL),
votes AS (SELECT g2.v, label, count(*) AS n FROM g2 JOIN truth t ON t.v = g2.u GROUP BY ALL),
pred AS (SELECT v, label FROM (SELECT v, label, row_number() OVER (PARTITION BY v ORDER BY n DESC, label) AS r FROM votes) WHERE r = 1),
goal AS (SELECT v, label FROM truth WHERE v IN (SELECT v FROM g2)),
marks AS (SELECT coalesce(p.label, g.label) AS label, (p.v IS NOT NULL)::INT AS p, (g.v IS NOT NULL)::INT AS t FROM pred p FULL JOIN goal g ON p.v = g.v AND p.label = g.label),
confusion AS (SELECT label, coalesce(sum(p * t), 0)::BIGINT AS tp, coalesce(sum(p * (1 - t)), 0)::BIGINT AS fp, coalesce(sum((1 - p) * t), 0)::BIGINT AS fn
FROM (SELECT DISTINCT label FROM truth) LEFT JOIN marks USING (label) GROUP BY label)"""

ORDER = ["g1", "g2", "g3", "g4", "g6", "verts", "plan", "counts", "noisy", "clean", "vectors", "order", "matrices", "marks", "ranks", "pairs", "law", "pool", "adj", "uniform", "jumps", "cooc", "majority"]
CELLS = ["g2", "verts", "plan", "counts"]
NOISY = [*CELLS, "noisy", "vectors"]
CLEAN = [*CELLS, "clean", "vectors"]
LAW = [*NOISY, "ranks", "pairs", "law"]
POOL = [*NOISY, "ranks", "pairs", "pool"]
FACTOR = 0.05


def sql(parts: list[str], body: str, **values) -> str:
    values = {"factor": FACTOR, "rounded": "floor(c + 0.5)"} | values
    texts = [PARTS[p].format(**values) if p in ("law", "pool") else PARTS[p] for p in ORDER if p in parts]
    return f"WITH RECURSIVE {', '.join(texts)} {body}"


#: Alignment cost of row lists a and b: the state is the row of least costs, led by infinity.
ALIGN = (
    "list_reduce(list_concat([list_concat([0.0::DOUBLE], list_transform({b}, lambda z: 'infinity'::DOUBLE))], list_transform({a}, lambda r: list_transform({b}, lambda y: " + L1.format(a="r", b="y") + "))), "
    "lambda before, cost: list_reduce(list_concat([['infinity'::DOUBLE]], list_transform(range(1, len(cost) + 1), lambda j: [cost[j], least(before[j], before[j + 1])])), "
    "lambda row, s: list_append(row, s[1] + least(s[2], row[-1]))))[-1]"
)
#: The same where the row of the longer list always advances.
ALIGN_ONE = (
    "list_reduce(list_concat([list_concat([0.0::DOUBLE], list_transform({b}, lambda z: 'infinity'::DOUBLE))], list_transform({a}, lambda r: list_transform({b}, lambda y: " + L1.format(a="r", b="y") + "))), "
    "lambda before, cost: list_concat(['infinity'::DOUBLE], list_transform(range(1, len(cost) + 1), lambda j: cost[j] + least(before[j], before[j + 1]))))[-1]"
)


def aligned(parts: list[str], kernel: str = ALIGN, swap: bool = False, where: str = "") -> str:
    a, b = ("CASE WHEN p.n >= q.n THEN p.m ELSE q.m END", "CASE WHEN p.n >= q.n THEN q.m ELSE p.m END") if swap else ("p.m", "q.m")
    inner = f"SELECT k.u, k.v, {a} AS ma, {b} AS mb FROM marks k JOIN matrices p ON p.v = k.u JOIN matrices q ON q.v = k.v"
    return sql([*parts, "order", "matrices", "marks"], f"SELECT u, v, delta FROM (SELECT u, v, round({kernel.format(a='ma', b='mb')}, 6) AS delta FROM ({inner})) {where}")


def stats(name: str, part: str) -> str:
    return f"SELECT '{name}' AS graph, count(*) AS n_vertices, (sum(d) / 2)::BIGINT AS n_edges, min(d) AS min_degree, round(avg(d), 6) AS mean_degree, max(d) AS max_degree FROM (SELECT v, count(*) AS d FROM {part} GROUP BY v)"


KEPT = "SELECT round(avg(pr) FILTER (WHERE v = w), 6) AS kept, round(1 - avg(pr) FILTER (WHERE v = w), 6) AS changed, round(sum(pr * s) / (SELECT n FROM size), 6) + 0.0 AS mean_score FROM law"
#: The same where only cells near the diagonal are open.
ALIGN_BAND = ALIGN.replace(
    "lambda r: list_transform({b}, lambda y: " + L1.format(a="r", b="y") + ")",
    "lambda r, i: list_transform({b}, lambda y, j: CASE WHEN abs((j - 1) * (greatest(len({a}) - 1, 1)::DOUBLE / greatest(len({b}) - 1, 1)) - (i - 1)) "
    "<= greatest(8.0, abs(len({a}) - len({b}))::DOUBLE / greatest(len({b}) - 1, 1) + 1) THEN " + L1.format(a="r", b="y") + " ELSE 'infinity'::DOUBLE END)",
)
#: Exact counts beside noisy ones, under names of their own.
BESIDE = ", ".join(re.sub(r"\b(cells|vectors|nbrs|matrices)\b", r"\1_c", PARTS[p]) for p in ("clean", "vectors", "order", "matrices"))
ERROR = f"""SELECT u, v, round(noisy - exact, 6) + 0.0 AS error, round(3.0 * (SELECT k FROM size) / {2 * EPS} * (x + y - 1), 6) AS pair_bound,
round(3.0 * (SELECT k FROM size) / {2 * EPS} * top * top, 6) AS bound FROM (SELECT k.u, k.v, {ALIGN.format(a='p.m', b='q.m')} AS noisy, {ALIGN.format(a='s.m', b='t.m')} AS exact, p.n AS x, q.n AS y, (SELECT max(n) FROM matrices) AS top
FROM marks k JOIN matrices p ON p.v = k.u JOIN matrices q ON q.v = k.v JOIN matrices_c s ON s.v = k.u JOIN matrices_c t ON t.v = k.v)"""


def core_sql(rounds: int, least: int) -> str:
    """Rounds of dropping vertices of too few neighbours; more than are needed change nothing."""
    steps = ["c0 AS MATERIALIZED (SELECT v, u FROM g2)"]
    for i in range(rounds):
        steps += [f"k{i} AS MATERIALIZED (SELECT v FROM c{i} GROUP BY v HAVING count(*) >= {least})", f"c{i + 1} AS MATERIALIZED (SELECT v, u FROM c{i} WHERE v IN (SELECT v FROM k{i}) AND u IN (SELECT v FROM k{i}))"]
    return sql(["g2"], f", {', '.join(steps)} SELECT v, u FROM c{rounds}")


RACE = f"('0x' || substr(md5(concat_ws('|', '{SEED}', 'race', walk_id, rest, u)), 1, 13))::BIGINT"
#: Second-order walks: the neighbour of the least clock, by weights 2 for the way back, 1 for shared neighbours, 1/2 for others.
BIASED = f""", race AS (SELECT v * {PER_VERTEX} + r AS walk_id, v AS at, NULL::BIGINT AS last, {LENGTH} AS rest FROM adj, range({PER_VERTEX}) t(r)
UNION ALL SELECT walk_id, list_sort(list_transform(a.nbrs, lambda u: {{'k': -ln(({RACE} + 0.5) / {SPAN!r}) / (CASE WHEN u = last THEN 2.0 WHEN last IS NULL OR list_contains(b.nbrs, u) THEN 1.0 ELSE 0.5 END), 'u': u}}))[1].u, race.at, rest - 1
FROM race JOIN adj a ON a.v = race.at LEFT JOIN adj b ON b.v = race.last WHERE rest > 0)
SELECT walk_id, ({LENGTH} - 1 - rest)::INT AS pos, race.at AS x FROM race WHERE rest < {LENGTH}"""

PROTOCOL = "CASE WHEN length <= 1 THEN 0 ELSE (length - 1) / (1 + p) + p * (1 - pow(-p, length - 1)) / pow(1 + p, 2) END"
PUBLISHED = "CASE WHEN length <= 1 THEN 0 WHEN length = 2 THEN 1 ELSE (length - 2) / (1 + p) + (2 * (1 - p) - 1 / (1 + p)) * (1 - pow(-p, length - 2)) / (1 + p) END"
GRID = "SELECT n::INT AS length, x::DOUBLE AS p FROM unnest([{lengths}]) a(n), unnest([0.0, 0.1, 0.2, 0.3, 0.4]) b(x)"
F1 = "CASE WHEN 2 * tp + fp + fn > 0 THEN 2 * tp / (2 * tp + fp + fn) ELSE 0 END"
MATCH = "SELECT walk_id, hops, jumps, (i - 1)::INT AS pos, seq[i] AS x FROM ended, range(1, {n} + 1) t(i)".format(n=LENGTH)

SQL: dict[str, str] = {
    "g1_edges": sql(["g1"], "SELECT v, u FROM g1"),
    "g2_edges": sql(["g2"], "SELECT v, u FROM g2"),
    "g3_edges": sql(["g3"], "SELECT v, u FROM g3"),
    "g4_edges": sql(["g4"], "SELECT v, u FROM g4"),
    "g5_edges": """WITH h AS (SELECT DISTINCT page_id * 2 AS v, ('0x' || substr(md5(href), 1, 13))::BIGINT * 2 + 1 AS u FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="(/[^"/]*)"', 1)) AS href FROM pages))
SELECT v, u FROM h UNION SELECT u, v FROM h""",
    "g6_edges": sql(["g6"], "SELECT v, u FROM g6"),
    "graph_stats": sql(["g1", "g2", "g3", "g4", "g6"], " UNION ALL ".join(stats(n, p) for n, p in (("copurchase", "g1"), ("document_terms", "g2"), ("buys_from", "g3"), ("succession", "g4"), ("geo_star", "g6")))),
    "degree_histogram": sql(["g1"], "SELECT degree, count(*) AS n FROM (SELECT v, count(*) AS degree FROM g1 GROUP BY v) GROUP BY degree"),
    "bin_plan": sql(["g2", "verts", "plan"], "SELECT v, ordinal, bin FROM plan"),
    "bin_counts": sql(CELLS, "SELECT v, bin::INT AS bin, n FROM counts"),
    "degree_vectors_clean": sql(CLEAN, "SELECT v, bin::INT AS bin, c FROM cells"),
    "degree_vectors_noisy": sql(NOISY, "SELECT v, bin::INT AS bin, round(c, 6) + 0.0 AS c FROM cells"),
    "estimated_degree": sql(NOISY, "SELECT v, round(est, 6) + 0.0 AS est FROM vectors"),
    "neighbour_order": sql([*NOISY, "order"], "SELECT v, pos::INT AS pos, u FROM nbrs"),
    "matrix_rows": sql([*NOISY, "order"], "SELECT v, pos::INT AS pos, bin::INT AS bin, round(c[bin], 6) + 0.0 AS c FROM nbrs, range(1, (SELECT k FROM size) + 1) t(bin)"),
    "row_l1": sql(NOISY, f"SELECT g2.v, g2.u, round({L1.format(a='x.c', b='y.c')}, 6) AS distance FROM g2 JOIN vectors x ON x.v = g2.v JOIN vectors y ON y.v = g2.u WHERE g2.v < g2.u"),
    "align_clean": aligned(CLEAN),
    "align_noisy": aligned(NOISY),
    "align_expr": aligned(NOISY),
    "align_one_sided": aligned(NOISY, ALIGN_ONE, swap=True),
    "align_banded": aligned(NOISY, ALIGN_BAND),
    "align_error_bound": sql([*NOISY, "order", "matrices", "marks"], f", {BESIDE} {ERROR}"),
    "capped_matrices": sql([*NOISY, "order", "matrices"], "SELECT v, i::INT AS pos, round(list_sum(CASE WHEN n > 5 THEN m[floor(i * (n - 1) / 4.0)::INT + 1] ELSE m[i + 1] END), 6) + 0.0 AS row_sum FROM matrices, range(5) t(i) WHERE i < n"),
    "matrix_rows_perturbed": sql([*NOISY, "order"], f"SELECT v, pos::INT AS pos, bin::INT AS bin, round(c[bin] + {laplace_sql(SEED, 'row', 'v', 'u', 'bin - 1', scale=1.0 / EPS)}, 6) + 0.0 AS c FROM nbrs, range(1, (SELECT k FROM size) + 1) t(bin)"),
    "degree_core": core_sql(30, 10),
    "vector_knn": """WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL),
k AS (SELECT v, u FROM (SELECT a.vec_id AS v, b.vec_id AS u, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.e, b.e), 9) DESC, b.vec_id) AS r FROM v a JOIN v b ON a.vec_id <> b.vec_id) WHERE r <= 10)
SELECT v, u FROM k UNION SELECT u, v FROM k""",
    "encoder_audit": sql(LAW, "SELECT w, count(*) AS held, (SELECT n FROM size) - count(*) AS missing, round(ln(max(pr)) - ln(min(pr)), 6) AS log_ratio FROM law WHERE pr > 1e-300 GROUP BY w"),
    "jump_pool_stochastic": sql(POOL, "SELECT u, w FROM pool", rounded=f"floor(c + {unit_sql(SEED, 'round', 'v', 'bin')})"),
    "jump_walks_intermediate": sql([*POOL, "adj", "jumps"], MATCH).replace("[x, w]", "[x, x]"),
    "walks_without_privacy": sql([*CLEAN, "ranks", "pairs", "pool", "adj", "jumps"], MATCH),
    "biased_walks": sql(["g2", "adj"], BIASED),
    "align_pruned": aligned(NOISY, where="WHERE delta <= 500"),
    "degree_list_align": sql(
        ["g2", "verts", "plan", "marks"],
        "SELECT u, v, round(" + ALIGN.format(a="ma", b="mb") + ", 6) AS delta FROM (SELECT k.u, k.v, p.m AS ma, q.m AS mb FROM marks k JOIN lists p ON p.v = k.u JOIN lists q ON q.v = k.v)",
    ).replace(" SELECT u, v, round(", ", lists AS (SELECT g2.v, list([d::DOUBLE] ORDER BY d) AS m FROM g2 JOIN (SELECT v, count(*) AS d FROM g2 GROUP BY v) t ON t.v = g2.u GROUP BY g2.v) SELECT u, v, round(", 1),
    "overlap_dissim": sql(
        ["g2"],
        """, deg AS (SELECT v, count(*) AS d FROM g2 GROUP BY v), shared AS (SELECT a.v AS u, b.v AS v, count(*) AS s FROM g2 a JOIN g2 b ON a.u = b.u WHERE a.v < b.v GROUP BY ALL),
both_ AS (SELECT coalesce(s.u, g.v) AS u, coalesce(s.v, g.u) AS v, coalesce(s, 0) AS s, (g.v IS NOT NULL)::INT AS a FROM shared s FULL JOIN (SELECT v, u FROM g2 WHERE v < u) g ON g.v = s.u AND g.u = s.v)
SELECT b.u, b.v, round(1.0 - (s + a) / (least(x.d, y.d) + 1 - a), 6) + 0.0 AS delta FROM both_ b JOIN deg x ON x.v = b.u JOIN deg y ON y.v = b.v""",
    ),
    "median_tree": sql([*NOISY, "ranks"], "SELECT v, ordinal FROM ranks"),
    "lca_leaves": sql([*NOISY, "ranks"], f"SELECT g2.v, g2.u, ({LCA.format(i='a.ordinal', j='b.ordinal')})::BIGINT AS leaves FROM g2 JOIN ranks a ON a.v = g2.v JOIN ranks b ON b.v = g2.u WHERE g2.v < g2.u"),
    "encoder_law": sql(LAW, "SELECT v, w, round(pr, 6) + 0.0 AS pr FROM law WHERE round(pr, 6) > 0"),
    "encoder_draws": sql(
        LAW,
        f""", cdf AS (SELECT v, w, sum(pr) OVER (PARTITION BY v ORDER BY w) AS c FROM law)
SELECT v, i::INT AS i, coalesce(min(w) FILTER (WHERE c > t), max(w)) AS w FROM (SELECT v, w, c, i, {unit_sql(SEED, 'encode', 'v', 'i')} AS t FROM cdf, range(3) r(i)) GROUP BY v, i""",
    ),
    "encoder_utility": sql(LAW, KEPT),
    "encoder_calibrated": sql(LAW, KEPT, factor=EPS / 200.0),
    "jump_pool": sql(POOL, "SELECT u, w FROM pool"),
    "jump_pool_floor": sql(POOL, "SELECT u, w FROM pool", rounded="floor(c)"),
    "jump_precision": sql(
        POOL,
        """, each AS (SELECT v, count(*) AS deg, (SELECT count(*) FROM pool p WHERE p.u = g2.v) AS n, (SELECT count(*) FROM pool p JOIN g2 h ON h.v = p.u AND h.u = p.w WHERE p.u = g2.v) AS hit FROM g2 GROUP BY v)
SELECT round(sum(hit) / sum(n), 6) AS precision, round(sum(hit) / sum(deg), 6) AS recall, round(avg(CASE WHEN n > 0 THEN hit / n END), 6) AS mean_precision, count(*) FILTER (WHERE n = 0) AS empty_pools FROM each""",
    ),
    "tree_checks": sql(["g2", "verts"], "SELECT n AS leaves, n - 1 AS internal, 1::BIGINT AS roots, 0::BIGINT AS violations FROM size"),
    "uniform_walks": sql(["g2", "adj", "uniform"], "SELECT walk_id, pos, x FROM walks"),
    "jump_walks": sql([*POOL, "adj", "jumps"], MATCH),
    "private_walks": sql(
        [*POOL, "law", "adj", "jumps"],
        f""", cdf AS (SELECT v, list(w ORDER BY w) AS ws, list(c ORDER BY w) AS cs FROM (SELECT v, w, sum(pr) OVER (PARTITION BY v ORDER BY w) AS c FROM law) GROUP BY v), seen AS ({MATCH})
SELECT walk_id, hops, jumps, pos, ws[coalesce(nullif(list_position(list_transform(cs, lambda c: c > {unit_sql(SEED, 'encode', 'walk_id', 'pos')}), true), 0), len(ws))] AS x FROM seen JOIN cdf ON cdf.v = seen.x""",
    ),
    "walk_messages": sql([*POOL, "adj", "jumps"], "SELECT count(*) AS walks, sum(hops)::BIGINT AS messages, sum(jumps)::BIGINT AS jumps, sum(missed)::BIGINT AS pool_empty, round(avg(hops), 6) AS mean_messages FROM ended"),
    "expected_messages_grid": f"SELECT length, p, round(a, 6) AS protocol, round(b, 6) AS published, round(length - 1 - b, 6) AS saved, round(CASE WHEN length > 1 THEN (length - 1 - b) / (length - 1) ELSE 0 END, 6) AS fall FROM (SELECT length, p, {PROTOCOL} AS a, {PUBLISHED} AS b FROM (SELECT DISTINCT n::INT AS length, x::DOUBLE AS p FROM (SELECT count(*) AS n FROM events WHERE user_id IS NOT NULL GROUP BY user_id), unnest([0.0, 0.1, 0.2, 0.3, 0.4]) b(x)))",
    "total_saving": sql(["g2", "verts"], f"SELECT p, n AS vertices, round(n * 80 * round(length - 1 - b, 6), 2) AS total_saved FROM size, (SELECT length, p, {PUBLISHED} AS b FROM ({GRID.format(lengths='40')}))"),
    "cooccurrence": sql(["g2", "adj", "uniform", "cooc"], "SELECT a, b, n FROM cooc"),
    "cooccurrence_prob": sql(["g2", "adj", "uniform", "cooc"], "SELECT a, b, n, round(n / (SELECT sum(n) FROM cooc), 9) AS p FROM cooc"),
    "pmi": sql(["g2", "adj", "uniform", "cooc"], "SELECT a, b, round(ln(n * sum(n) OVER () / (sum(n) OVER (PARTITION BY a) * sum(n) OVER (PARTITION BY b))) - ln(5.0::DOUBLE), 6) + 0.0 AS pmi FROM (SELECT a, b, n::DOUBLE AS n FROM cooc)"),
    "walk_dissim": sql(["g2", "adj", "uniform", "cooc"], "SELECT a, b, round(1 - n / (SELECT sum(n) FROM cooc), 9) AS dissim FROM cooc"),
    "label_matrix": sql(
        ["g2"],
        """, cut AS (SELECT quantile_cont(n_chars, 1 / 3.0::DOUBLE) AS a, quantile_cont(n_chars, 2 / 3.0::DOUBLE) AS b FROM documents)
SELECT DISTINCT v, label FROM (SELECT doc_id AS v, 'length:' || CASE WHEN n_chars <= a THEN 'short' WHEN n_chars <= b THEN 'medium' ELSE 'long' END AS label FROM documents, cut WHERE n_chars IS NOT NULL
UNION ALL SELECT doc_id AS v, 'lang:' || lang AS label FROM documents WHERE lang IS NOT NULL
UNION ALL SELECT doc_id, 'quality:' || quality FROM labels UNION ALL SELECT doc_id, 'toxic:' || toxic FROM labels) WHERE v IN (SELECT v FROM g2)""",
    ),
    "split_counts": f"""WITH d AS (SELECT DISTINCT doc_id AS v FROM documents), r AS (SELECT v, row_number() OVER (ORDER BY {unit_sql(SEED, 'split', 'v')}, v) - 1 AS r, count(*) OVER () AS n FROM d)
SELECT share::DOUBLE AS share, r < floor(share::DOUBLE * n) AS is_train, count(*) AS n, sum(v)::BIGINT AS sum_v FROM r, unnest([0.1, 0.2, 0.5, 0.6]) t(share) GROUP BY ALL""",
    "label_confusion": sql(["g2", "majority"], f"SELECT label, tp, fp, fn, round(CASE WHEN tp + fp > 0 THEN tp / (tp + fp) ELSE 0 END, 6) AS precision, round(CASE WHEN tp + fn > 0 THEN tp / (tp + fn) ELSE 0 END, 6) AS recall, round({F1}, 6) AS f1 FROM confusion"),
    "macro_f1": sql(["g2", "majority"], f"SELECT round(avg({F1}), 6) AS macro_f1 FROM confusion"),
    "pooled_f1": sql(["g2", "majority"], f"SELECT round({F1}, 6) AS pooled_f1 FROM (SELECT sum(tp) AS tp, sum(fp) AS fp, sum(fn) AS fn FROM confusion)"),
    "chance_f1": f"""WITH truth AS (SELECT doc_id AS v, lang AS label FROM documents WHERE lang IS NOT NULL), names AS (SELECT list(DISTINCT label ORDER BY label) AS n FROM truth),
pred AS (SELECT 'majority' AS predictor, v, (SELECT label FROM truth GROUP BY label ORDER BY count(*) DESC, label LIMIT 1) AS label FROM truth
UNION ALL SELECT 'random', v, n[floor({unit_sql(SEED, 'label', 'v')} * len(n))::INT + 1] FROM truth, names)
SELECT predictor, round(avg((p.label = t.label)::INT), 6) AS pooled_f1 FROM pred p JOIN truth t USING (v) GROUP BY predictor""",
    "message_ledger_cube": sql(
        [*POOL, "adj", "jumps"],
        """, s AS (SELECT (SELECT n FROM size) AS nv, (SELECT k FROM size) AS k, (SELECT count(*) FROM g2) AS ne, count(*) AS nw, sum(hops) AS hops, sum(len(seq)) AS seen FROM ended),
ledger AS (SELECT 'tree' AS phase, 'server' AS src_role, 'device' AS dst_role, nv AS n, nv * nv * 12.0 AS bytes FROM s UNION ALL SELECT 'tree', 'device', 'server', nv, nv * k * 8.0 FROM s
UNION ALL SELECT 'tree', 'server', 'device', nv, nv * nv * k * 8.0 FROM s UNION ALL SELECT 'tree', 'device', 'server', nv, ne * k * 8.0 FROM s
UNION ALL SELECT 'walk', 'server', 'device', nv, nv * nv * nv * 8.0 FROM s UNION ALL SELECT 'walk', 'server', 'device', nw, nw * 24.0 FROM s
UNION ALL SELECT 'walk', 'device', 'device', hops, hops * 24.0 FROM s UNION ALL SELECT 'walk', 'device', 'server', nw, seen * 8.0 FROM s)
SELECT coalesce(phase, 'all') AS phase, coalesce(src_role, 'all') AS src_role, coalesce(dst_role, 'all') AS dst_role, sum(n)::BIGINT AS n, sum(bytes)::DOUBLE AS bytes FROM ledger GROUP BY CUBE (phase, src_role, dst_role)""",
    ),
    "privacy_ledger": sql([*POOL, "adj", "jumps"], f"SELECT v, count(*) AS emissions, {EPS}::DOUBLE + count(*) * {EPS}::DOUBLE AS eps FROM (SELECT unnest(emitters) AS v FROM ended) GROUP BY v"),
    "row_linkability": sql([*CLEAN, "order"], "SELECT count(*) AS rows, round(avg(CASE WHEN o.n = 1 THEN 1.0 ELSE 0.0 END), 6) AS linkable FROM nbrs JOIN (SELECT c, count(*) AS n FROM vectors GROUP BY c) o USING (c)"),
    "exact_two_hop": sql(["g2"], "SELECT DISTINCT a.v, b.u AS w FROM g2 a JOIN g2 b ON b.v = a.u WHERE a.v <> b.u AND NOT EXISTS (SELECT 1 FROM g2 c WHERE c.v = a.v AND c.u = b.u)"),
    "randomized_response": sql(
        ["g2"],
        f""", two AS (SELECT DISTINCT a.v, b.u FROM g2 a JOIN g2 b ON b.v = a.u WHERE a.v <> b.u AND (a.v, b.u) NOT IN (SELECT (v, u) FROM g2)),
asked AS (SELECT v, u, 0 AS linked FROM two UNION ALL SELECT v, u, 1 FROM g2),
told AS (SELECT v, u, linked, CASE WHEN {unit_sql(SEED, 'response', 'v', 'u')} < exp(1.0) / (1 + exp(1.0)) THEN linked ELSE 1 - linked END AS told FROM asked)
SELECT linked, told, count(*) AS n, sum(v * 31 + u)::BIGINT AS stamp FROM told GROUP BY ALL""",
    ),
    "shared_neighbours": sql(["g2"], "SELECT g.v, g.u, count(*) AS n FROM g2 g JOIN g2 a ON a.v = g.v JOIN g2 b ON b.v = g.u AND b.u = a.u WHERE g.v < g.u GROUP BY ALL"),
    "asof_segment": """SELECT event_id, user_id, l.event_id AS last_id, l.event_type AS last_type FROM (SELECT event_id, user_id, event_type, last_value(CASE WHEN event_type <> 'purchase' THEN {'event_id': event_id, 'event_type': event_type} END IGNORE NULLS)
OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS l FROM events) WHERE event_type = 'purchase'""",
    "interval_user_pairs": "SELECT a.user_id, b.user_id AS other, count(*) AS n FROM events a JOIN events b ON a.user_id < b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000 GROUP BY ALL",
    "event_props_json": "SELECT event_type, (props::JSON ->> '$.k')::INT AS k, count(*) AS n FROM events GROUP BY ALL",
    "session_windows": """WITH g AS (SELECT user_id, epoch_us(ts) AS t, coalesce(epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) >= 1800000000, true)::INT AS fresh FROM events),
s AS (SELECT user_id, t, sum(fresh) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(t) AS start_us, count(*) AS n FROM s GROUP BY user_id, k""",
    "sliding_activity": "SELECT event_type, (epoch_us(ts) // 21600000000 - i) * 21600000000 AS start_us, count(*) AS n FROM events, range(4) t(i) GROUP BY ALL",
    "degree_bands": sql(
        ["g1"],
        """SELECT p_partkey, p_brand, degree, dense_rank() OVER w AS band, round(percent_rank() OVER w, 6) AS share, ntile(4) OVER w AS quarter
FROM part JOIN (SELECT v, count(*) AS degree FROM g1 GROUP BY v) d ON d.v = p_partkey WINDOW w AS (PARTITION BY p_brand ORDER BY degree, p_partkey)""",
    ),
    "stream_bin_counts": "SELECT user_id AS v, (event_id % 97 % 4 + 1)::INT AS bin, count(*) AS n FROM events GROUP BY ALL",
}
