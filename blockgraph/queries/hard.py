"""Hard clustering: statistics, entropies, move scores, rounds and fits over the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import init
from ..graph import vertices
from ..hard import fit as hf
from ..hard import score, stats
from ..hard.problems import BipartiteGraph, DirectedGraph, ObservedWeights, SimpleGraph
from ..plans.state import write_state
from ..rng import portable, portable_sql
from ..sources import tables as t
from .base import cost_sql, query, xlogx_sql

K, SEED, FRAC = 4, 7, 0.3
MOST_BITS = 20


def _graph(spark, sf_dir):
    return t.g1_copurchase(spark, sf_dir).select("src", "dst")


def _labels(edges, k=K, seed=SEED):
    return init.random_labels(vertices(edges), k, seed)


def _setup(spark, sf_dir):
    edges = _graph(spark, sf_dir)
    labels = _labels(edges)
    return edges, labels, stats.block_pairs(edges, labels, K)


def label_sql(k=K, seed=SEED, source="g"):
    return f"SELECT id, CAST(floor({portable_sql(seed, 'label', 'id')} * {k}) AS INTEGER) AS lab FROM (SELECT src AS id FROM {source} UNION SELECT dst FROM {source})"


def stats_cte(lab="lab", suffix="", k=K, graph="g"):
    """sz, st (a <= b) and fu (both orders) for a labeling."""
    return f"""
ga{suffix} AS (SELECT CAST(r.range AS INTEGER) AS a FROM range({k}) r),
sz{suffix} AS (SELECT a, count(l.id) AS n FROM ga{suffix} LEFT JOIN {lab} l ON l.lab = a GROUP BY a),
en{suffix} AS (SELECT least(x.lab, y.lab) AS a, greatest(x.lab, y.lab) AS b FROM {graph} JOIN {lab} x ON x.id = src JOIN {lab} y ON y.id = dst),
hi{suffix} AS (SELECT a, b, count(*) AS hit FROM en{suffix} GROUP BY a, b),
st{suffix} AS (SELECT *, pairs - hit AS miss FROM (SELECT x.a, y.a AS b, x.n AS na, y.n AS nb,
  CASE WHEN x.a = y.a THEN CAST(x.n AS DOUBLE) * (x.n - 1) / 2 ELSE CAST(x.n AS DOUBLE) * y.n END AS pairs, coalesce(h.hit, 0) AS hit
  FROM sz{suffix} x JOIN sz{suffix} y ON x.a <= y.a LEFT JOIN hi{suffix} h ON h.a = x.a AND h.b = y.a)),
fu{suffix} AS (SELECT * FROM st{suffix} UNION ALL SELECT b, a, nb, na, pairs, hit, miss FROM st{suffix} WHERE a < b)"""


def table_cte(lab="lab", suffix="", graph="g"):
    """li (links with own block), ct (cost tables), sc (table scores), mv (moves)."""
    partners, stay_miss = "(nb - CASE WHEN b = y THEN 1 ELSE 0 END)", "(nb - CASE WHEN b = y THEN 1 ELSE 0 END - x)"
    return f"""
li{suffix} AS (SELECT id, y, b, CAST(sum(x) AS BIGINT) AS x FROM (
  SELECT o.id, o.lab AS y, p.lab AS b, 1 AS x FROM (SELECT src AS id, dst AS other FROM {graph} UNION ALL SELECT dst, src FROM {graph}) e JOIN {lab} o ON o.id = e.id JOIN {lab} p ON p.id = e.other
  UNION ALL SELECT id, lab, lab, 0 FROM {lab}) GROUP BY id, y, b),
ct{suffix} AS (SELECT a, b, na, nb, hit, miss, {cost_sql('hit', 'miss + nb')} - {cost_sql('hit', 'miss')} AS enter,
  {cost_sql('hit', 'miss')} - {cost_sql('hit', 'miss - (nb - CASE WHEN a = b THEN 1 ELSE 0 END)')} AS leave FROM fu{suffix}),
tot{suffix} AS (SELECT a, sum(enter) AS enter_all, sum(leave) AS leave_all FROM ct{suffix} GROUP BY a),
co{suffix} AS (SELECT id, y, a, sum(CASE WHEN a = y THEN {cost_sql('hit', 'miss')} - {cost_sql('hit - x', f'miss - {stay_miss}')} - leave
  ELSE {cost_sql('hit + x', f'miss + {stay_miss}')} - {cost_sql('hit', 'miss')} - enter END) AS corr FROM li{suffix} JOIN ct{suffix} USING (b) GROUP BY id, y, a),
sc{suffix} AS (SELECT id, y, co{suffix}.a, corr + CASE WHEN co{suffix}.a = y THEN leave_all ELSE enter_all END AS score FROM co{suffix} JOIN tot{suffix} ON tot{suffix}.a = co{suffix}.a)""".replace(partners, partners)


def move_cte(suffix="", scores="sc"):
    return f"""
mv{suffix} AS (SELECT id, CAST(CASE WHEN stay - least_score > 1e-9 THEN best ELSE y END AS INTEGER) AS lab FROM (
  SELECT id, y, min(score) AS least_score, max(CASE WHEN a = y THEN score END) AS stay, arg_min(a, (round(score, 9), a)) AS best FROM {scores}{suffix} GROUP BY id, y))"""


BASE = f"WITH g AS (SELECT src, dst FROM ({t.G1})), lab AS ({label_sql()}), {stats_cte()}"
SCORED = f"{BASE}, {table_cte()}"


@query(f"{BASE} SELECT a, n FROM sz")
def block_sizes(spark, sf_dir):
    return stats.block_sizes(_labels(_graph(spark, sf_dir)), K)


@query(f"{BASE} SELECT a, b, pairs, hit, CAST(miss AS DOUBLE) AS miss FROM st")
def block_pairs(spark, sf_dir):
    return _setup(spark, sf_dir)[2].select("a", "b", "pairs", "hit", "miss")


@query(f"{SCORED} SELECT id, b, x FROM li WHERE x > 0")
def vertex_links(spark, sf_dir):
    edges, labels, _ = _setup(spark, sf_dir)
    return stats.vertex_links(edges, labels)


@query(f"{BASE} SELECT round(sum({cost_sql('hit', 'miss')}), 6) AS entropy FROM st")
def hard_entropy_simple(spark, sf_dir):
    return stats.simple_entropy(_setup(spark, sf_dir)[2]).select(F.round("entropy", 6).alias("entropy"))


@query(f"{SCORED} SELECT a, b, round(enter, 6) AS enter, round(leave, 6) AS leave FROM ct")
def cost_tables(spark, sf_dir):
    return stats.cost_tables(_setup(spark, sf_dir)[2]).select("a", "b", F.round("enter", 6).alias("enter"), F.round("leave", 6).alias("leave"))


@query(f"{SCORED} SELECT id, a, round(score, 6) AS score FROM sc")
def move_scores_table(spark, sf_dir):
    edges, labels, st = _setup(spark, sf_dir)
    return score.score_table(stats.vertex_links(edges, labels), labels, st).select("id", "a", F.round("score", 6).alias("score"))


@query(f"{SCORED}, {move_cte()} SELECT id, lab FROM mv")
def best_move_table(spark, sf_dir):
    edges, labels, st = _setup(spark, sf_dir)
    return score.best_moves(score.score_table(stats.vertex_links(edges, labels), labels, st)).select("id", "lab")


_P = "greatest(1e-9, least(1 - 1e-9, coalesce(hit / nullif(pairs, 0), 1e-9)))"
PLUGIN = f"""{SCORED}, pl AS (SELECT id, y, f.a, sum(-l0 * ln({_P}) - ((nb - CASE WHEN f.b = y THEN 1 ELSE 0 END) - l0) * ln(1 - {_P})) AS score
FROM (SELECT lab.id, lab.lab AS y, ga.a AS b, coalesce(li.x, 0) AS l0 FROM lab CROSS JOIN ga LEFT JOIN li ON li.id = lab.id AND li.b = ga.a) d JOIN fu f ON f.b = d.b GROUP BY id, y, f.a),
{move_cte('_p', 'pl').replace('pl_p', 'pl')} SELECT id, lab FROM mv_p"""


@query(PLUGIN)
def best_move_plugin(spark, sf_dir):
    edges, labels, st = _setup(spark, sf_dir)
    return score.best_moves(score.score_plugin(stats.vertex_links(edges, labels), labels, st)).select("id", "lab")


_GH = "(CASE WHEN f.a = d.y THEN d.x WHEN f.b = d.y THEN o.x ELSE 0 END)"
_GA = "(CASE WHEN f.a = d.y THEN d.s WHEN f.b = d.y THEN o.s ELSE 0 END)"
EXACT_CTE = f"""dn AS (SELECT lab.id, lab.lab AS y, sz.a AS b, coalesce(li.x, 0) AS x, sz.n - CASE WHEN sz.a = lab.lab THEN 1 ELSE 0 END AS s
  FROM lab CROSS JOIN sz LEFT JOIN li ON li.id = lab.id AND li.b = sz.a),
red AS (SELECT d.id, d.y, f.a, d.x, d.s, f.hit - {_GH} AS h, f.miss - ({_GA} - {_GH}) AS m FROM dn d JOIN fu f ON f.b = d.b JOIN dn o ON o.id = d.id AND o.b = f.a),
ex AS (SELECT id, y, a, sum({cost_sql('h + x', 'm + s - x')} - {cost_sql('h', 'm')}) AS score FROM red GROUP BY id, y, a)"""


@query(f"{SCORED}, {EXACT_CTE} SELECT e.id, e.a, round(e.score - s.score, 6) AS delta FROM ex e JOIN ex s ON s.id = e.id AND s.a = s.y")
def move_delta_exact(spark, sf_dir):
    """Entropy change of each single move, staying included as 0."""
    edges, labels, st = _setup(spark, sf_dir)
    scores = score.score_exact(stats.vertex_links(edges, labels), labels, st)
    stay = scores.where("a = y").select("id", F.col("score").alias("stay"))
    return scores.join(stay, "id").select("id", "a", F.round(F.col("score") - F.col("stay"), 6).alias("delta"))


TOY = "(SELECT * FROM (VALUES (0,1),(0,2),(1,2),(3,4),(3,5),(4,5),(2,3)) x(src, dst))"
TOY_EDGES = [(0, 1), (0, 2), (1, 2), (3, 4), (3, 5), (4, 5), (2, 3)]
TOY_LABELS = "SELECT * FROM (VALUES (0,0),(1,0),(2,0),(3,1),(4,1),(5,1)) x(id, lab)"


def toy(spark, labels=(0, 0, 0, 1, 1, 1)):
    return spark.createDataFrame(TOY_EDGES, "src long, dst long"), spark.createDataFrame(list(enumerate(labels)), "id long, lab int")


@query(
    f"""WITH g AS ({t.G10}), lab AS (SELECT id, CAST(CASE WHEN id % 2 = 0 THEN 0 ELSE 1 END AS INTEGER) AS lab FROM (SELECT src AS id FROM g UNION SELECT dst FROM g)), {stats_cte(k=2)}, {table_cte()}, {EXACT_CTE},
    gains AS (SELECT e.id, max(CASE WHEN a = y THEN score END) - min(score) AS gain FROM ex e GROUP BY e.id)
    SELECT round(max(gain), 6) AS gain, max(gain) <= 1e-9 AS locally_optimal FROM gains"""
)
def local_opt_certificate(spark, sf_dir):
    """Whether a single move improves the blocks {segments}, {priorities} of the graph of orders."""
    edges = write_state(t.g10_urgency(spark, sf_dir), "edges")
    labels = vertices(edges).select("id", F.pmod("id", F.lit(2)).cast("int").alias("lab"))
    return hf.local_optimality(edges, labels, 2).select(F.round("gain", 6).alias("gain"), "locally_optimal")


@query(
    f"""WITH g AS ({t.G10}), v AS (SELECT id, row_number() OVER (ORDER BY id) - 1 AS bit FROM (SELECT src AS id FROM g UNION SELECT dst FROM g)),
    code AS (SELECT unnest(range(1 << CAST(n AS BIGINT))) AS z, n FROM (SELECT count(*) AS n FROM v)), l AS (SELECT z, id, n, CAST((z >> bit) & 1 AS INTEGER) AS lab FROM code, v),
    s AS (SELECT z, sum(lab) AS n1, max(n) - sum(lab) AS n0 FROM l GROUP BY z),
    h AS (SELECT l.z, sum(CASE WHEN l.lab = 0 AND r.lab = 0 THEN 1 ELSE 0 END) AS h0, sum(CASE WHEN l.lab <> r.lab THEN 1 ELSE 0 END) AS hx, sum(CASE WHEN l.lab = 1 AND r.lab = 1 THEN 1 ELSE 0 END) AS h1
      FROM g JOIN l ON l.id = g.src JOIN l r ON r.id = g.dst AND r.z = l.z GROUP BY l.z),
    e AS (SELECT z, {cost_sql('h0', 'n0 * (n0 - 1) / 2 - h0')} + {cost_sql('hx', 'n0 * n1 - hx')} + {cost_sql('h1', 'n1 * (n1 - 1) / 2 - h1')} AS entropy FROM s JOIN h USING (z))
    SELECT CAST(z AS BIGINT) AS labeling, round(entropy, 6) AS entropy FROM e"""
)
def brute_force_toy(spark, sf_dir):
    """Entropy of all two-block labelings of the graph of orders; bit i of labeling is the block of the i-th vertex."""
    edges = write_state(t.g10_urgency(spark, sf_dir), "edges")
    ids = sorted(r["id"] for r in vertices(edges).limit(MOST_BITS + 1).collect())
    if len(ids) > MOST_BITS:
        raise ValueError(f"more than {MOST_BITS} vertices: too many labelings")
    bits = spark.createDataFrame([(v, i) for i, v in enumerate(ids)], "id long, bit int")
    bit = spark.range(1 << len(ids)).withColumnRenamed("id", "labeling").crossJoin(F.broadcast(bits)).select("labeling", "id", F.expr("(labeling >> bit) & 1").alias("lab"))
    size = bit.groupBy("labeling").agg(F.sum("lab").alias("n1")).withColumn("n0", len(ids) - F.col("n1"))
    ends = F.broadcast(edges).join(bit.select("labeling", F.col("id").alias("src"), F.col("lab").alias("a")), "src").join(bit.select("labeling", F.col("id").alias("dst"), F.col("lab").alias("b")), ["labeling", "dst"])
    both = F.col("a") + F.col("b")
    hits = ends.groupBy("labeling").agg(*[F.count_if(both == k).alias(f"h{k}") for k in range(3)])
    n0, n1 = F.col("n0"), F.col("n1")
    cells = ((F.col("h0"), n0 * (n0 - 1) / 2), (F.col("h1"), n0 * n1), (F.col("h2"), n1 * (n1 - 1) / 2))
    entropy = sum((stats.pair_cost(h, p - h) for h, p in cells), F.lit(0.0))
    return size.join(hits, "labeling").select("labeling", F.round(entropy, 6).alias("entropy"))


@query(f"WITH g AS (SELECT src, dst FROM ({t.G1})), lab AS ({label_sql()}) SELECT id, CAST(CASE WHEN id = 5 THEN 3 ELSE lab END AS INTEGER) AS lab FROM lab")
def single_move_labels(spark, sf_dir):
    return stats.with_move(_labels(_graph(spark, sf_dir)), 5, 3)


def round_cte(number: int, k: int = K, frac: float = FRAC, seed: int = SEED) -> str:
    """lab{number} from lab{number - 1} by one table-scored round."""
    s, before = f"_{number}", f"lab{number - 1}"
    return f"""{stats_cte(before, s, k)}, {table_cte(before, s)}, {move_cte(s)},
lab{number} AS (SELECT l.id, CASE WHEN {portable_sql(seed, 'choose', str(number), 'l.id')} < {frac} THEN m.lab ELSE l.lab END AS lab FROM {before} l JOIN mv{s} m ON m.id = l.id)"""


ROUND1 = f"WITH g AS (SELECT src, dst FROM ({t.G1})), lab0 AS ({label_sql()}), {round_cte(1)}"


@query(f"{ROUND1} SELECT id, lab FROM lab1")
def hard_round_labels(spark, sf_dir):
    edges = _graph(spark, sf_dir)
    return hf.one_round(edges, _labels(edges), K, FRAC, "table", SEED, 1).select("id", "lab")


def _trace(spark, edges, labels, rounds, frac=FRAC):
    out, edges = None, write_state(edges, "edges")
    for k in range(rounds + 1):
        if k:
            labels = write_state(hf.one_round(edges, labels, K, frac, "table", SEED, k).select("id", "lab"), "labels")
        part = stats.simple_entropy(stats.block_pairs(edges, labels, K)).select(F.lit(k).alias("iter"), F.round("entropy", 6).alias("entropy"))
        out = part if out is None else out.unionAll(part)
    return out


@query(
    f"{ROUND1}, {round_cte(2)}, {stats_cte('lab2', '_3')} "
    + " UNION ALL ".join(f"SELECT {k - 1} AS iter, round(sum({cost_sql('hit', 'miss')}), 6) AS entropy FROM st_{k}" for k in (1, 2, 3))
)
def hard_entropy_trace(spark, sf_dir):
    edges = _graph(spark, sf_dir)
    return _trace(spark, edges, _labels(edges), 2)


@query(
    f"{ROUND1} SELECT count(*) AS n, count(*) FILTER (WHERE a.lab <> b.lab) AS moved, round(count(*) FILTER (WHERE a.lab <> b.lab) / count(*), 6) AS share FROM lab0 a JOIN lab1 b USING (id)"
)
def moved_share(spark, sf_dir):
    edges = _graph(spark, sf_dir)
    after = hf.one_round(edges, _labels(edges), K, FRAC, "table", SEED, 1)
    return after.agg(F.count("*").alias("n"), F.count_if(F.col("lab") != F.col("was")).alias("moved")).withColumn("share", F.round(F.col("moved") / F.col("n"), 6))


@query(
    f"""{BASE.replace(label_sql(), label_sql(K, 11))} SELECT 'random' AS kind, round(sum({cost_sql('hit', 'miss')}), 6) AS entropy FROM st"""
)
def random_labels_entropy(spark, sf_dir):
    edges = _graph(spark, sf_dir)
    return stats.simple_entropy(stats.block_pairs(edges, _labels(edges, K, 11), K)).select(F.lit("random").alias("kind"), F.round("entropy", 6).alias("entropy"))


def _by_blocks_sql():
    parts, ctes = [], [f"g AS (SELECT src, dst FROM ({t.G1}))"]
    for k in (2, 5, 10):
        ctes.append(f"lab{k} AS ({label_sql(k)}), {stats_cte(f'lab{k}', f'_{k}', k)}")
        parts.append(f"SELECT {k} AS n_blocks, round(sum({cost_sql('hit', 'miss')}), 6) AS entropy FROM st_{k}")
    return f"WITH {', '.join(ctes)} {' UNION ALL '.join(parts)}"


@query(_by_blocks_sql())
def entropy_by_nblocks(spark, sf_dir):
    """Entropy of random labelings, which hardly moves with the number of blocks."""
    edges, out = _graph(spark, sf_dir), None
    for k in (2, 5, 10):
        part = stats.simple_entropy(stats.block_pairs(edges, _labels(edges, k), k)).select(F.lit(k).alias("n_blocks"), F.round("entropy", 6).alias("entropy"))
        out = part if out is None else out.unionAll(part)
    return out


DIRECTED = f"""WITH g AS ({t.G7}), lab AS ({label_sql(3)}), s AS (SELECT lab AS a, count(*) AS n FROM lab GROUP BY 1),
h AS (SELECT x.lab AS a, y.lab AS b, count(*) AS hit FROM g JOIN lab x ON x.id = src JOIN lab y ON y.id = dst WHERE src <> dst GROUP BY 1, 2),
st AS (SELECT coalesce(hit, 0) AS hit, CASE WHEN x.a = y.a THEN x.n * (x.n - 1) ELSE x.n * y.n END AS pairs FROM s x CROSS JOIN s y LEFT JOIN h ON h.a = x.a AND h.b = y.a)
SELECT round(sum({cost_sql('hit', '(pairs - hit)')}), 6) AS entropy FROM st"""


@query(DIRECTED)
def hard_entropy_directed(spark, sf_dir):
    edges = t.g7_trade(spark, sf_dir)
    labels = init.random_labels(vertices(edges), 3, SEED)
    st = stats.block_pairs(edges.where("src <> dst"), labels, 3, directed=True)
    return stats.simple_entropy(st).select(F.round("entropy", 6).alias("entropy"))


def side_sql(name, column, k, seed, source="g"):
    return f"{name} AS (SELECT DISTINCT {column} AS id, CAST(floor({portable_sql(seed, 'label', column)} * {k}) AS INTEGER) AS lab FROM {source})"


def _sides(edges, left_blocks=3, right_blocks=4, seed=SEED):
    left = init.random_labels(edges.select(F.col("src").alias("id")).distinct(), left_blocks, seed)
    right = init.random_labels(edges.select(F.col("dst").alias("id")).distinct(), right_blocks, seed + 1)
    return left, right


LIKE = f"""WITH g AS ({t.G5}), {side_sql('l', 'src', 3, SEED)}, {side_sql('r', 'dst', 4, SEED + 1)},
sl AS (SELECT lab AS a, count(*) AS n FROM l GROUP BY 1), sr AS (SELECT lab AS b, count(*) AS n FROM r GROUP BY 1),
h AS (SELECT l.lab AS a, r.lab AS b, count(*) AS hit FROM g JOIN l ON l.id = src JOIN r ON r.id = dst GROUP BY 1, 2),
st AS (SELECT coalesce(hit, 0) AS hit, sl.n * sr.n AS pairs FROM sl CROSS JOIN sr LEFT JOIN h USING (a, b))
SELECT round(sum({cost_sql('hit', '(pairs - hit)')}), 6) AS entropy FROM st"""


@query(LIKE)
def hard_entropy_like(spark, sf_dir):
    """Bipartite graph of likes: all user x item pairs are possible."""
    edges = t.g5_like(spark, sf_dir)
    left, right = _sides(edges)
    return stats.simple_entropy(stats.block_pairs(edges, left, 3, right, 4)).select(F.round("entropy", 6).alias("entropy"))


RATED = f"WITH g AS ({t.G4}), {side_sql('l', 'src', 3, SEED)}, {side_sql('r', 'dst', 4, SEED + 1)}, en AS (SELECT src, dst, cat, w, trials, l.lab AS a, r.lab AS b FROM g JOIN l ON l.id = src JOIN r ON r.id = dst)"


@query(
    f"{RATED}, c AS (SELECT a, b, cat, count(*) AS n FROM en GROUP BY 1, 2, 3), p AS (SELECT a, b, sum(n) AS n FROM c GROUP BY 1, 2) SELECT round((SELECT sum({xlogx_sql('n')}) FROM p) - (SELECT sum({xlogx_sql('n')}) FROM c), 6) AS entropy"
)
def hard_entropy_rating(spark, sf_dir):
    edges = t.g4_rating(spark, sf_dir)
    return stats.profile_rating_entropy(edges, *_sides(edges)).select(F.round("entropy", 6).alias("entropy"))


@query(f"{RATED}, c AS (SELECT a, b, sum(w) AS w, sum(trials - w) AS rest FROM en GROUP BY 1, 2) SELECT round(sum({cost_sql('w', 'rest')}), 6) AS entropy FROM c")
def hard_entropy_binomial(spark, sf_dir):
    edges = t.g4_rating(spark, sf_dir)
    return stats.binomial_entropy(edges, *_sides(edges)).select(F.round("entropy", 6).alias("entropy"))


_N, _X = "coalesce(n, 0)", "x"
_BASE = f"({_N} - CASE WHEN k.a = q.y THEN x ELSE 0 END)"
RATING_ROUND = f"""{RATED}, c AS (SELECT a, b, cat, count(*) AS n FROM en GROUP BY 1, 2, 3), p AS (SELECT a, b, count(*) AS n FROM en GROUP BY 1, 2),
lc AS (SELECT src AS id, a AS y, b, cat, count(*) AS x FROM en GROUP BY 1, 2, 3, 4), lp AS (SELECT src AS id, a AS y, b, count(*) AS x FROM en GROUP BY 1, 2, 3),
k AS (SELECT DISTINCT lab AS a FROM l),
parts AS (SELECT q.id, q.y, k.a, {xlogx_sql(f'{_BASE} + x')} - {xlogx_sql(_BASE)} AS part FROM lp q CROSS JOIN k LEFT JOIN p ON p.a = k.a AND p.b = q.b
  UNION ALL SELECT q.id, q.y, k.a, -({xlogx_sql(f'{_BASE} + x')} - {xlogx_sql(_BASE)}) FROM lc q CROSS JOIN k LEFT JOIN c ON c.a = k.a AND c.b = q.b AND c.cat = q.cat),
sc AS (SELECT id, y, a, sum(part) AS score FROM parts GROUP BY 1, 2, 3), {move_cte()}
SELECT l.id, CASE WHEN {portable_sql(SEED, 'choosel', '1', 'l.id')} < {FRAC} THEN mv.lab ELSE l.lab END AS lab FROM l JOIN mv ON mv.id = l.id"""


@query(RATING_ROUND)
def hard_rating_round(spark, sf_dir):
    edges = t.g4_rating(spark, sf_dir)
    left, right = _sides(edges)
    return hf.rating_round(edges, left, right, FRAC, SEED, 1, "l").select("id", "lab")


@query()
def hard_fit_trace(spark, sf_dir):
    """A whole fit of the co-purchase graph: entropy and moves of each round."""
    edges = write_state(_graph(spark, sf_dir), "edges")
    from ..em.loop import Stop

    return hf.fit_simple(edges, K, 0.1, seed=SEED, stop=Stop(max_iter=30), backend="packed").trace.to_df(spark)


@query()
def hard_fit_frames_trace(spark, sf_dir):
    """The first rounds of the same fit with all tables distributed: the same entropies and moves."""
    from ..em.loop import Stop

    return hf.fit_simple(_graph(spark, sf_dir), K, 0.1, seed=SEED, stop=Stop(max_iter=3)).trace.to_df(spark).drop("elapsed_s")


@query(f"{ROUND1} SELECT id, lab FROM lab1")
def hard_round_arrow(spark, sf_dir):
    """hard_round_labels with table scores in numpy batches."""
    edges = _graph(spark, sf_dir)
    return hf.one_round(edges, _labels(edges), K, FRAC, "arrow", SEED, 1).select("id", "lab")


def _one_turn(problem, state, side):
    """Labels of a side after one generic round."""
    moves = hf.plan_moves(problem, state, side, FRAC, SEED, 1, problem.statistics(state))
    return hf.apply_moves(state[side], moves).select("id", "lab")


@query(f"{ROUND1} SELECT id, lab FROM lab1")
def reassign_simple(spark, sf_dir):
    """One round of the generic reassignment on the simple-graph problem."""
    edges = _graph(spark, sf_dir)
    return _one_turn(SimpleGraph(edges, K), {"": _labels(edges)}, "")


def _dense_sql(links: str, table: str, sizes: str, hit: str, own: bool) -> str:
    """Score part by all partner blocks: links(id, b, x), table(a, b, hit, miss), sizes(b, n)."""
    s = "(s.n - CASE WHEN s.b = l.lab THEN 1 ELSE 0 END)" if own else "s.n"
    x = "coalesce(k.x, 0)"
    stay = f"{cost_sql(f't.{hit}', 't.miss')} - {cost_sql(f't.{hit} - {x}', f't.miss - ({s} - {x})')}"
    enter = f"{cost_sql(f't.{hit} + {x}', f't.miss + ({s} - {x})')} - {cost_sql(f't.{hit}', 't.miss')}"
    return f"SELECT l.id, l.lab AS y, t.a, CASE WHEN t.a = l.lab THEN {stay} ELSE {enter} END AS part FROM l JOIN {table} t ON TRUE JOIN {sizes} s ON s.b = t.b LEFT JOIN {links} k ON k.id = l.id AND k.b = t.b"


def _picked_sql(side: str = "") -> str:
    return f"SELECT l.id, CASE WHEN {portable_sql(SEED, f'choose{side}', '1', 'l.id')} < {FRAC} THEN mv.lab ELSE l.lab END AS lab FROM l JOIN mv ON mv.id = l.id"


DIRECTED_ROUND = f"""WITH g0 AS ({t.G7}), l AS ({label_sql(3, source='g0')}), g AS (SELECT src, dst FROM g0 WHERE src <> dst), nn AS (SELECT lab AS b, count(*) AS n FROM l GROUP BY 1),
h AS (SELECT x.lab AS a, y.lab AS b, count(*) AS hit FROM g JOIN l x ON x.id = src JOIN l y ON y.id = dst GROUP BY 1, 2),
so AS (SELECT x.b AS a, y.b AS b, coalesce(hit, 0) AS hit, CASE WHEN x.b = y.b THEN x.n * (x.n - 1) ELSE x.n * y.n END - coalesce(hit, 0) AS miss FROM nn x CROSS JOIN nn y LEFT JOIN h ON h.a = x.b AND h.b = y.b),
si AS (SELECT b AS a, a AS b, hit, miss FROM so),
lo AS (SELECT src AS id, lab AS b, count(*) AS x FROM g JOIN l ON l.id = dst GROUP BY 1, 2), li AS (SELECT dst AS id, lab AS b, count(*) AS x FROM g JOIN l ON l.id = src GROUP BY 1, 2),
sc AS (SELECT id, y, a, sum(part) AS score FROM ({_dense_sql('lo', 'so', 'nn', 'hit', True)} UNION ALL {_dense_sql('li', 'si', 'nn', 'hit', True)}) GROUP BY 1, 2, 3), {move_cte()}
{_picked_sql()}"""


@query(DIRECTED_ROUND)
def reassign_directed(spark, sf_dir):
    edges = t.g7_trade(spark, sf_dir)
    labels = init.random_labels(vertices(edges), 3, SEED)
    return _one_turn(DirectedGraph(edges.where("src <> dst").select("src", "dst"), 3), {"": labels}, "")


BIPARTITE_ROUND = f"""WITH g AS ({t.G5}), {side_sql('l', 'src', 3, SEED)}, {side_sql('r', 'dst', 4, SEED + 1)},
na AS (SELECT lab AS a, count(*) AS n FROM l GROUP BY 1), nn AS (SELECT lab AS b, count(*) AS n FROM r GROUP BY 1),
h AS (SELECT l.lab AS a, r.lab AS b, count(*) AS hit FROM g JOIN l ON l.id = src JOIN r ON r.id = dst GROUP BY 1, 2),
st AS (SELECT na.a, nn.b, coalesce(hit, 0) AS hit, na.n * nn.n - coalesce(hit, 0) AS miss FROM na CROSS JOIN nn LEFT JOIN h ON h.a = na.a AND h.b = nn.b),
lk AS (SELECT src AS id, lab AS b, count(*) AS x FROM g JOIN r ON r.id = dst GROUP BY 1, 2),
sc AS (SELECT id, y, a, sum(part) AS score FROM ({_dense_sql('lk', 'st', 'nn', 'hit', False)}) GROUP BY 1, 2, 3), {move_cte()}
{_picked_sql('l')}"""


@query(BIPARTITE_ROUND)
def reassign_bipartite(spark, sf_dir):
    """One turn of the left side where all pairs are possible."""
    edges = t.g5_like(spark, sf_dir).select("src", "dst")
    left, right = _sides(edges)
    return _one_turn(BipartiteGraph(edges, 3, 4), {"l": left, "r": right}, "l")


_B2 = "coalesce(c.{0}, 0) - CASE WHEN k.a = q.y THEN q.{0} ELSE 0 END"
_W2, _R2 = f"({_B2.format('w')})", f"({_B2.format('rest')})"
BINOMIAL_ROUND = f"""{RATED}, c AS (SELECT a, b, sum(w) AS w, sum(trials - w) AS rest FROM en GROUP BY 1, 2), k AS (SELECT DISTINCT lab AS a FROM l),
q AS (SELECT src AS id, a AS y, b, sum(w) AS w, sum(trials - w) AS rest FROM en GROUP BY 1, 2, 3),
sc AS (SELECT q.id, q.y, k.a, sum({cost_sql(f'{_W2} + q.w', f'{_R2} + q.rest')} - {cost_sql(_W2, _R2)}) AS score FROM q CROSS JOIN k LEFT JOIN c ON c.a = k.a AND c.b = q.b GROUP BY 1, 2, 3), {move_cte()}
{_picked_sql('l')}"""


@query(BINOMIAL_ROUND)
def reassign_binomial(spark, sf_dir):
    """One turn of the left side with binomial weights on observed edges."""
    edges = t.g4_rating(spark, sf_dir)
    left, right = _sides(edges)
    return _one_turn(ObservedWeights.binomial(edges, 3, 4), {"l": left, "r": right}, "l")


@query(f"{RATING_ROUND}")
def reassign_rating(spark, sf_dir):
    """One turn of the left side with ratings on observed edges."""
    edges = t.g4_rating(spark, sf_dir)
    left, right = _sides(edges)
    return _one_turn(ObservedWeights.ratings(edges, 3, 4), {"l": left, "r": right}, "l")


MIN_BLOCK = 250
MIN_SIZE = f"""{ROUND1.replace(f'lab1 AS', 'lab9 AS')}, go AS (SELECT s.id, s.y, m.lab, s.stay - s.least_score AS gain FROM (SELECT id, y, min(score) AS least_score, max(CASE WHEN a = y THEN score END) AS stay FROM sc_1 GROUP BY 1, 2) s JOIN mv_1 m USING (id)
  WHERE m.lab <> s.y AND {portable_sql(SEED, 'choose', '1', 's.id')} < {FRAC}),
rk AS (SELECT *, row_number() OVER (PARTITION BY y ORDER BY round(gain, 7) DESC, id) AS k FROM go)
SELECT a AS lab, n - least(n_go, greatest(0, n - {MIN_BLOCK})) AS stays FROM sz_1 JOIN (SELECT y, count(*) AS n_go FROM rk GROUP BY 1) ON y = a"""


@query(MIN_SIZE)
def min_size_refusal(spark, sf_dir):
    """How many members each block keeps when departures below MIN_BLOCK are refused."""
    edges = _graph(spark, sf_dir)
    after = hf.one_round(edges, _labels(edges), K, FRAC, "table", SEED, 1, MIN_BLOCK)
    left = after.groupBy(F.col("was").alias("lab")).agg(F.count_if(F.col("lab") == F.col("was")).alias("stays"), F.count_if(F.col("lab") != F.col("was")).alias("left"))
    return left.where("left > 0 OR stays >= 0").select("lab", "stays")


@query(
    f"""WITH g AS (SELECT * FROM {TOY} q), lab AS ({TOY_LABELS}), {stats_cte(k=2)}, {table_cte()}, {EXACT_CTE},
    gains AS (SELECT e.id, max(CASE WHEN a = y THEN score END) - min(score) AS gain FROM ex e GROUP BY e.id)
    SELECT CAST(id AS BIGINT) AS id, lab FROM lab WHERE (SELECT max(gain) <= 1e-9 FROM gains)"""
)
def polished_labels(spark, sf_dir):
    """Single exact moves from 000011 on the toy graph end in its locally optimal labeling."""
    edges, start = toy(spark, (0, 0, 0, 0, 1, 1))
    return hf.polish(edges, start, 2)[0]


@query()
def hard_rating_fit_trace(spark, sf_dir):
    from ..em.loop import Stop

    return hf.fit_rating(t.planted_rating(spark, sf_dir), 4, 3, 0.3, SEED, Stop(max_iter=3)).trace.to_df(spark)


@query(f"SELECT p_partkey AS id FROM part WHERE {portable_sql(SEED, 'choose', '1', 'p_partkey')} < {FRAC}")
def hash_sample_vertices(spark, sf_dir):
    parts = t.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"))
    return hf.choose(parts, FRAC, SEED, 1)
