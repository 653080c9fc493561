"""Soft clustering, prediction and accuracy over the rating graph."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from .. import init
from ..em.loop import Stop
from ..graph import categorise, vertices
from ..hard.stats import labelled
from ..metrics import fit as mf
from ..plans.state import write_state
from ..rng import cumulative, draw_block, portable, portable_sql
from ..soft import model, predict, steps
from ..sources import tables as t
from .base import query
from .hard import SEED, K, _labels, _sides, label_sql, side_sql

A, B, C, DRAWS = 2, 3, 5, 4
SIZES = (A, B, C)


def _edges(spark, sf_dir):
    return t.g4_rating(spark, sf_dir).select("src", "dst", (F.col("cat") - 1).alias("cat"))


def _state(spark, sf_dir):
    edges = write_state(_edges(spark, sf_dir), "edges")
    return edges, *steps.starts(edges, SIZES, SEED)


def mem_sql(name, ids, blocks, side, seed=SEED):
    u = portable_sql(seed, f"mem{side}", "id", "k")
    return f"{name} AS (SELECT id, CAST(k AS INTEGER) AS k, raw / sum(raw) OVER (PARTITION BY id) AS p FROM (SELECT id, k, {u} + 0.05 AS raw FROM ({ids}), (SELECT range AS k FROM range({blocks}))))"


def cat_sql(a=A, b=B, c=C, seed=SEED):
    u = portable_sql(seed, "cat", "a", "b", "c")
    return f"cat0 AS (SELECT a, b, c, raw / sum(raw) OVER (PARTITION BY a, b) AS p FROM (SELECT CAST(x.range AS INTEGER) AS a, CAST(y.range AS INTEGER) AS b, CAST(z.range AS INTEGER) AS c, {u.replace('CAST(a AS', 'CAST(x.range AS').replace('CAST(b AS', 'CAST(y.range AS').replace('CAST(c AS', 'CAST(z.range AS')} + 0.05 AS raw FROM range({a}) x, range({b}) y, range({c}) z))"


START = f"""WITH e AS (SELECT src, dst, cat - 1 AS cat FROM ({t.G4})), {mem_sql('ml0', 'SELECT DISTINCT src AS id FROM e', A, 'l')}, {mem_sql('mr0', 'SELECT DISTINCT dst AS id FROM e', B, 'r')}, {cat_sql()}"""


def resp_cte(n: int) -> str:
    return f"""w{n} AS (SELECT src, dst, e.cat, l.k AS a, r.k AS b, l.p * r.p * c.p AS w FROM e JOIN ml{n} l ON l.id = src JOIN mr{n} r ON r.id = dst JOIN cat{n} c ON c.a = l.k AND c.b = r.k AND c.c = e.cat),
q{n} AS (SELECT *, w / greatest(sum(w) OVER (PARTITION BY src, dst), 1e-300) AS resp FROM w{n})"""


def update_cte(n: int) -> str:
    m = n + 1
    return f"""dl{n} AS (SELECT src, count(*) AS deg FROM e GROUP BY 1), dr{n} AS (SELECT dst, count(*) AS deg FROM e GROUP BY 1),
ml{m} AS (SELECT q.src AS id, a AS k, sum(resp) / any_value(deg) AS p FROM q{n} q JOIN dl{n} d ON d.src = q.src GROUP BY 1, 2),
mr{m} AS (SELECT q.dst AS id, b AS k, sum(resp) / any_value(deg) AS p FROM q{n} q JOIN dr{n} d ON d.dst = q.dst GROUP BY 1, 2),
cat{m} AS (SELECT c.a, c.b, c.c, CASE WHEN sum(coalesce(m, 0)) OVER (PARTITION BY c.a, c.b) > 0 THEN coalesce(m, 0) / sum(coalesce(m, 0)) OVER (PARTITION BY c.a, c.b) ELSE c.p END AS p
  FROM cat{n} c LEFT JOIN (SELECT a, b, cat, sum(resp) AS m FROM q{n} GROUP BY 1, 2, 3) x ON x.a = c.a AND x.b = c.b AND x.cat = c.c)"""


def entropy_select(n: int) -> str:
    return f"SELECT {n} AS iter, round(-sum(ln(p)), 6) AS entropy FROM (SELECT sum(w) AS p FROM w{n} GROUP BY src, dst)"


EXACT1 = f"{START}, {resp_cte(0)}, {update_cte(0)}"


def _long(mem, value="p"):
    return mem.select("id", F.posexplode("vec").alias("k", "x")).select("id", "k", F.round("x", 6).alias(value))


@query(f"{START} SELECT id, k, round(p, 6) AS p FROM ml0")
def init_mem(spark, sf_dir):
    return _long(steps.starts(_edges(spark, sf_dir), SIZES, SEED)[0])


@query(
    f"""WITH raw AS (SELECT CAST(x.range AS INTEGER) AS a, CAST(y.range AS INTEGER) AS b, c, {portable_sql(SEED, 'cat', 'x.range', 'y.range', 'c')} + 0.05 AS u
    FROM range({A}) x, range({B}) y, (SELECT DISTINCT cat - 1 AS c FROM ({t.G4})))
    SELECT a, b, c, round(u / sum(u) OVER (PARTITION BY a, b), 6) AS p FROM raw"""
)
def init_cat(spark, sf_dir):
    """A random distribution for each block pair over the ratings that occur."""
    found = t.g4_rating(spark, sf_dir).select((F.col("cat") - 1).alias("c")).distinct()
    return init.random_cat_of(found, A, B, SEED).select("a", "b", "c", F.round("p", 6).alias("p"))


@query(f"WITH g AS (SELECT src, dst FROM ({t.G1})) {label_sql()}")
def init_labels(spark, sf_dir):
    return _labels(t.g1_copurchase(spark, sf_dir).select("src", "dst"))


@query(
    f"SELECT id, CAST((row_number() OVER (ORDER BY u, id) - 1) % {K} AS INTEGER) AS lab FROM (SELECT p_partkey AS id, {portable_sql(SEED, 'balanced', 'p_partkey')} AS u FROM part)"
)
def balanced_labels(spark, sf_dir):
    return init.balanced_labels(t.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id")), K, SEED)


@query(f"{START}, {resp_cte(0)} SELECT round(-sum(ln(p)), 6) AS entropy FROM (SELECT sum(w) AS p FROM w0 GROUP BY src, dst)")
def soft_entropy(spark, sf_dir):
    return model.entropy(*_state(spark, sf_dir), SIZES).select(F.round("entropy", 6).alias("entropy"))


@query(f"{START}, {resp_cte(0)} SELECT src, dst, a, b, round(resp, 6) AS resp FROM q0")
def soft_responsibilities(spark, sf_dir):
    return model.responsibilities(*_state(spark, sf_dir)).select("src", "dst", "a", "b", F.round("resp", 6).alias("resp"))


@query(f"{EXACT1} SELECT 'l' AS side, id, k, round(p, 6) AS p FROM ml1 UNION ALL SELECT 'r', id, k, round(p, 6) FROM mr1")
def exact_em_mem_1(spark, sf_dir):
    left, right, _ = steps.exact_step(*_state(spark, sf_dir), SIZES)
    return _long(left).withColumn("side", F.lit("l")).unionAll(_long(right).withColumn("side", F.lit("r")))


@query(f"{EXACT1} SELECT a, b, c, round(p, 6) AS p FROM cat1")
def exact_em_cat_1(spark, sf_dir):
    return steps.exact_step(*_state(spark, sf_dir), SIZES)[2].select("a", "b", "c", F.round("p", 6).alias("p"))


def _trace_df(spark, rows):
    return spark.createDataFrame([(k, round(x, 6)) for k, x in enumerate(rows)], "iter int, entropy double")


@query(f"{EXACT1}, {resp_cte(1)}, {update_cte(1)}, {resp_cte(2)}, {update_cte(2)}, {resp_cte(3)} {' UNION ALL '.join(entropy_select(n) for n in range(4))}")
def exact_em_entropy_trace(spark, sf_dir):
    return _trace_df(spark, steps.fit_exact(_edges(spark, sf_dir), *SIZES, seed=SEED, stop=Stop(max_iter=3)).trace.entropies)


def draw_cte(n: int, round_: int, seed=SEED) -> str:
    m = n + 1
    left, right = portable_sql(seed, "drawl", str(round_), "src", "dst", "t"), portable_sql(seed, "drawr", str(round_), "src", "dst", "t")
    return f"""cl{n} AS (SELECT id, list(s ORDER BY k) AS cum FROM (SELECT id, k, sum(p) OVER (PARTITION BY id ORDER BY k) AS s FROM ml{n}) GROUP BY id),
cr{n} AS (SELECT id, list(s ORDER BY k) AS cum FROM (SELECT id, k, sum(p) OVER (PARTITION BY id ORDER BY k) AS s FROM mr{n}) GROUP BY id),
ur{n} AS (SELECT src, dst, cat, t, l.cum AS lc, r.cum AS rc, {left} AS ul, {right} AS u_r FROM e JOIN cl{n} l ON l.id = src JOIN cr{n} r ON r.id = dst, (SELECT range AS t FROM range({DRAWS}))),
da{n} AS (SELECT src, dst, cat, t, CAST(least(len(list_filter(lc, lambda x: x <= ul)), {A - 1}) AS INTEGER) AS a, CAST(least(len(list_filter(rc, lambda x: x <= u_r)), {B - 1}) AS INTEGER) AS b FROM ur{n}),
q{n} AS (SELECT d.*, c.p / sum(c.p) OVER (PARTITION BY src, dst) AS resp FROM da{n} d JOIN cat{n} c ON c.a = d.a AND c.b = d.b AND c.c = d.cat),
dl{n} AS (SELECT src, count(*) AS deg FROM e GROUP BY 1), dr{n} AS (SELECT dst, count(*) AS deg FROM e GROUP BY 1),
ml{m} AS (SELECT x.id, x.k, coalesce(s, 0) AS p FROM ml{n} x LEFT JOIN (SELECT q.src AS id, a AS k, sum(resp) / any_value(deg) AS s FROM q{n} q JOIN dl{n} d ON d.src = q.src GROUP BY 1, 2) y ON y.id = x.id AND y.k = x.k),
mr{m} AS (SELECT x.id, x.k, coalesce(s, 0) AS p FROM mr{n} x LEFT JOIN (SELECT q.dst AS id, b AS k, sum(resp) / any_value(deg) AS s FROM q{n} q JOIN dr{n} d ON d.dst = q.dst GROUP BY 1, 2) y ON y.id = x.id AND y.k = x.k),
cat{m} AS (SELECT c.a, c.b, c.c, CASE WHEN sum(coalesce(m, 0)) OVER (PARTITION BY c.a, c.b) > 0 THEN coalesce(m, 0) / sum(coalesce(m, 0)) OVER (PARTITION BY c.a, c.b) ELSE c.p END AS p
  FROM cat{n} c LEFT JOIN (SELECT a, b, cat, sum(resp) AS m FROM q{n} GROUP BY 1, 2, 3) x ON x.a = c.a AND x.b = c.b AND x.cat = c.c)"""


SAMPLED1 = f"{START}, {draw_cte(0, 1)}"


@query(f"{SAMPLED1} SELECT 'l' AS side, id, k, round(p, 6) AS p FROM ml1 UNION ALL SELECT 'r', id, k, round(p, 6) FROM mr1")
def sampled_em_mem_1(spark, sf_dir):
    left, right, _ = steps.sampled_step(*_state(spark, sf_dir), SIZES, DRAWS, SEED, 1)
    return _long(left).withColumn("side", F.lit("l")).unionAll(_long(right).withColumn("side", F.lit("r")))


@query(f"{SAMPLED1} SELECT a, b, c, round(p, 6) AS p FROM cat1")
def sampled_em_cat_1(spark, sf_dir):
    return steps.sampled_step(*_state(spark, sf_dir), SIZES, DRAWS, SEED, 1)[2].select("a", "b", "c", F.round("p", 6).alias("p"))


_W = "w{n} AS (SELECT src, dst, l.p * r.p * c.p AS w FROM e JOIN ml{n} l ON l.id = src JOIN mr{n} r ON r.id = dst JOIN cat{n} c ON c.a = l.k AND c.b = r.k AND c.c = e.cat)"


@query(f"{SAMPLED1}, {_W.format(n=0)}, {_W.format(n=1)} {entropy_select(0)} UNION ALL {entropy_select(1)}")
def sampled_em_entropy_trace(spark, sf_dir):
    fit = steps.fit_sampled(_edges(spark, sf_dir), *SIZES, draws=DRAWS, seed=SEED, stop=Stop(max_iter=1), uniform=portable)
    return _trace_df(spark, fit.trace.entropies)


@query(
    f"""{START}, cl AS (SELECT id, list(s ORDER BY k) AS cum FROM (SELECT id, k, sum(p) OVER (PARTITION BY id ORDER BY k) AS s FROM mr0) GROUP BY id), u AS (SELECT id, cum, {portable_sql(SEED, 'draw', 'id')} AS v FROM cl)
    SELECT id, CAST(least(len(list_filter(cum, lambda x: x <= v)), {B - 1}) AS INTEGER) AS block FROM u"""
)
def discrete_draw(spark, sf_dir):
    right = steps.starts(_edges(spark, sf_dir), SIZES, SEED)[1]
    return right.select("id", cumulative(F.col("vec")).alias("cum")).select("id", draw_block(F.col("cum"), portable(SEED, "draw", F.col("id")), B).alias("block"))


UNI = f"""WITH e AS (SELECT src, dst, CASE WHEN w >= 2 THEN 1 ELSE 0 END AS cat FROM ({t.G1})), {mem_sql('m0', 'SELECT src AS id FROM e UNION SELECT dst FROM e', 2, 'l')}, {cat_sql(2, 2, 2)},
w AS (SELECT src, dst, e.cat, l.k AS a, r.k AS b, l.p * r.p * c.p AS w FROM e JOIN m0 l ON l.id = src JOIN m0 r ON r.id = dst JOIN cat0 c ON c.a = l.k AND c.b = r.k AND c.c = e.cat),
q AS (SELECT *, w / sum(w) OVER (PARTITION BY src, dst) AS resp FROM w), s AS (SELECT src AS id, a AS k, resp FROM q UNION ALL SELECT dst, b, resp FROM q),
d AS (SELECT id, count(*) AS deg FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY 1)"""


@query(f"{UNI} SELECT s.id, k, round(sum(resp) / any_value(deg), 6) AS p FROM s JOIN d ON d.id = s.id GROUP BY 1, 2")
def soft_step_unipartite(spark, sf_dir):
    """One exact round where both ends share one vertex set."""
    edges = write_state(t.g1_copurchase(spark, sf_dir).select("src", "dst", F.when(F.col("w") >= 2, 1).otherwise(0).alias("cat")), "edges")
    mem, _, cat = steps.starts(edges, (2, 2, 2), SEED, bipartite=False)
    return _long(steps.exact_step(edges, mem, mem, cat, (2, 2, 2), bipartite=False, symmetric=True)[0])


@query(f"SELECT src, dst, CASE WHEN w >= 5 THEN 2 WHEN w >= 2 THEN 1 ELSE 0 END AS cat FROM ({t.G1})")
def edge_categories(spark, sf_dir):
    return t.g1_copurchase(spark, sf_dir).select("src", "dst", categorise(F.col("w"), [2, 5]).alias("cat"))


@query(f"{START}, {resp_cte(0)}, s AS (SELECT src, dst, a, sum(resp) AS x FROM q0 GROUP BY 1, 2, 3) SELECT src AS id, a AS k, round(avg(x), 6) AS p FROM s GROUP BY 1, 2")
def neighbour_mean(spark, sf_dir):
    return _long(steps.exact_step(*_state(spark, sf_dir), SIZES)[0])


@query(f"{START} SELECT id, CAST(arg_max(k, (p, -k)) AS INTEGER) AS lab FROM ml0 GROUP BY id")
def harden_labels(spark, sf_dir):
    return model.harden(steps.starts(_edges(spark, sf_dir), SIZES, SEED)[0])


@query(f"{START} SELECT c_custkey AS id, CAST(x.range AS INTEGER) AS k, round(coalesce(p, 1.0 / {A}), 6) AS p FROM customer, range({A}) x LEFT JOIN ml0 ON ml0.id = c_custkey AND ml0.k = x.range")
def cold_start_fill(spark, sf_dir):
    """Every customer gets a membership, those without an order the uniform one."""
    left = steps.starts(_edges(spark, sf_dir), SIZES, SEED)[0]
    return _long(model.fill_cold(left, t.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id")), A))


def _values(spark):
    return spark.createDataFrame([(c, float(c + 1)) for c in range(C)], "c int, value double")


PRED = f"{START}, pr AS (SELECT src, dst, sum(l.p * r.p * c.p * (c.c + 1)) AS pred FROM e JOIN ml0 l ON l.id = src JOIN mr0 r ON r.id = dst JOIN cat0 c ON c.a = l.k AND c.b = r.k GROUP BY 1, 2)"


@query(f"{PRED} SELECT src, dst, round(pred, 6) AS pred FROM pr")
def predict_soft(spark, sf_dir):
    edges, left, right, cat = _state(spark, sf_dir)
    return predict.soft(edges.select("src", "dst"), left, right, cat, _values(spark)).select("src", "dst", F.round("pred", 6).alias("pred"))


@query(f"{PRED} SELECT round(sqrt(avg((e.cat + 1 - pred) ** 2)), 6) AS rmse FROM pr JOIN e USING (src, dst)")
def rmse_soft(spark, sf_dir):
    edges, left, right, cat = _state(spark, sf_dir)
    pred = predict.soft(edges.select("src", "dst", (F.col("cat") + 1).alias("value")), left, right, cat, _values(spark))
    return mf.rmse(pred).select(F.round("rmse", 6).alias("rmse"))


FOLD = portable_sql(42, "fold", "src", "dst")
FOLDS = f"WITH f AS (SELECT src, dst, cat AS value, CAST(floor({FOLD} * 5) AS INTEGER) AS fold FROM ({t.G4})), tr AS (SELECT * FROM f WHERE fold <> 0), te AS (SELECT * FROM f WHERE fold = 0)"
HARD_PRED = f"""{FOLDS}, g AS (SELECT src, dst FROM f), {side_sql('l', 'src', 3, SEED)}, {side_sql('r', 'dst', 4, SEED + 1)},
m AS (SELECT l.lab AS a, r.lab AS b, avg(value) AS mean FROM tr JOIN l ON l.id = src JOIN r ON r.id = dst GROUP BY 1, 2),
pr AS (SELECT src, dst, value, fold, coalesce(mean, (SELECT avg(value) FROM tr)) AS pred FROM te LEFT JOIN l ON l.id = src LEFT JOIN r ON r.id = dst LEFT JOIN m ON m.a = l.lab AND m.b = r.lab)"""


def _folds(spark, sf_dir):
    folds = write_state(mf.with_fold(t.g4_rating(spark, sf_dir).select("src", "dst", F.col("cat").alias("value"))), "folds")
    return folds, folds.where("fold <> 0"), folds.where("fold = 0")


@query(f"{HARD_PRED} SELECT src, dst, round(pred, 6) AS pred FROM pr")
def predict_hard(spark, sf_dir):
    folds, train, test = _folds(spark, sf_dir)
    return predict.hard(test, *_sides(folds), train).select("src", "dst", F.round("pred", 6).alias("pred"))


@query(f"{HARD_PRED} SELECT round(sqrt(avg((value - pred) ** 2)), 6) AS rmse FROM pr")
def rmse_hard(spark, sf_dir):
    folds, train, test = _folds(spark, sf_dir)
    return mf.rmse(predict.hard(test, *_sides(folds), train)).select(F.round("rmse", 6).alias("rmse"))


@query(
    f"""{START}, dn AS (SELECT a, b, p FROM cat0 WHERE c = 1) SELECT src, dst, round(sum(l.p * r.p * dn.p), 6) AS pred FROM e JOIN ml0 l ON l.id = src JOIN mr0 r ON r.id = dst JOIN dn ON dn.a = l.k AND dn.b = r.k GROUP BY 1, 2"""
)
def predict_exists(spark, sf_dir):
    edges, left, right, cat = _state(spark, sf_dir)
    return predict.exists(edges.select("src", "dst"), left, right, cat.where("c = 1").select("a", "b", "p")).select("src", "dst", F.round("pred", 6).alias("pred"))


@query(
    f"""{START}, di AS (SELECT src, dst, c.c, sum(l.p * r.p * c.p) AS p FROM e JOIN ml0 l ON l.id = src JOIN mr0 r ON r.id = dst JOIN cat0 c ON c.a = l.k AND c.b = r.k GROUP BY 1, 2, 3)
    SELECT src, dst, CAST(arg_max(c, (round(p, 9), -c)) AS INTEGER) AS c FROM di GROUP BY 1, 2"""
)
def predict_mode(spark, sf_dir):
    edges, left, right, cat = _state(spark, sf_dir)
    return predict.mode(edges.select("src", "dst"), left, right, write_state(cat, "cat"))


TOP = """u AS (SELECT id FROM ml0 WHERE id IN (SELECT c_custkey FROM customer WHERE c_nationkey = 0))"""


@query(
    f"""{START}, {TOP}, p AS (SELECT u.id AS src, r.id AS dst FROM u, (SELECT DISTINCT id FROM mr0) r EXCEPT SELECT src, dst FROM e),
    s AS (SELECT src, dst, sum(l.p * r.p * c.p * (c.c + 1)) AS pred FROM (SELECT DISTINCT * FROM p) JOIN ml0 l ON l.id = src JOIN mr0 r ON r.id = dst JOIN cat0 c ON c.a = l.k AND c.b = r.k GROUP BY 1, 2),
    n AS (SELECT src, dst, pred, row_number() OVER (PARTITION BY src ORDER BY round(pred, 9) DESC, dst) AS rank FROM s) SELECT src, dst, CAST(rank AS INTEGER) AS rank, round(pred, 6) AS pred FROM n WHERE rank <= 5"""
)
def recommend_top_n(spark, sf_dir):
    """Five unseen parts for each customer of nation 0."""
    edges, left, right, cat = _state(spark, sf_dir)
    wanted = t.table(spark, sf_dir, "customer").where("c_nationkey = 0").select(F.col("c_custkey").alias("id"))
    seen = edges.join(wanted.withColumnRenamed("id", "src"), "src", "left_semi")
    return predict.top_n_all(seen, left.join(wanted, "id", "left_semi"), right, cat, _values(spark), 5).select("src", "dst", "rank", F.round("pred", 6).alias("pred"))


@query()
def recommend_top_n_all(spark, sf_dir):
    """Five unseen parts for every customer; no twin, all pairs are too many for it."""
    edges, left, right, cat = _state(spark, sf_dir)
    return predict.top_n_all(edges, left, right, cat, _values(spark), 5).select("src", "dst", "rank", F.round("pred", 6).alias("pred"))


@query(f"{FOLDS} SELECT round(sqrt(avg((value - (SELECT avg(value) FROM tr)) ** 2)), 6) AS rmse FROM te")
def rmse_constant(spark, sf_dir):
    _, train, test = _folds(spark, sf_dir)
    return mf.rmse(mf.constant(train, test)).select(F.round("rmse", 6).alias("rmse"))


def _mean_sql(key):
    return f"{FOLDS}, m AS (SELECT {key}, avg(value) AS own FROM tr GROUP BY 1) SELECT round(sqrt(avg((value - coalesce(own, (SELECT avg(value) FROM tr))) ** 2)), 6) AS rmse FROM te LEFT JOIN m USING ({key})"


@query(_mean_sql("src"))
def rmse_user_mean(spark, sf_dir):
    _, train, test = _folds(spark, sf_dir)
    return mf.rmse(mf.mean_by(train, test, "src")).select(F.round("rmse", 6).alias("rmse"))


@query(_mean_sql("dst"))
def rmse_item_mean(spark, sf_dir):
    _, train, test = _folds(spark, sf_dir)
    return mf.rmse(mf.mean_by(train, test, "dst")).select(F.round("rmse", 6).alias("rmse"))


@query(
    f"""WITH f AS (SELECT src, dst, cat AS value, CAST(floor({FOLD} * 5) AS INTEGER) AS fold FROM ({t.G4})), k AS (SELECT CAST(range AS INTEGER) AS k FROM range(5)),
    m AS (SELECT k, avg(value) AS mean FROM f, k WHERE fold <> k GROUP BY k) SELECT fold, round(sqrt(avg((value - mean) ** 2)), 6) AS rmse FROM f JOIN m ON m.k = fold GROUP BY fold"""
)
def rmse_by_fold(spark, sf_dir):
    """Five-fold cross-validation of the constant predictor."""
    folds, _, _ = _folds(spark, sf_dir)
    whole = folds.groupBy("fold").agg(F.sum("value").alias("s"), F.count("*").alias("n"))
    sums = whole.agg(F.sum("s").alias("all_s"), F.sum("n").alias("all_n"))
    means = whole.join(F.broadcast(sums)).select("fold", ((F.col("all_s") - F.col("s")) / (F.col("all_n") - F.col("n"))).alias("pred"))
    return folds.join(F.broadcast(means), "fold").groupBy("fold").agg(F.round(F.sqrt(F.avg(F.pow(F.col("value") - F.col("pred"), 2))), 6).alias("rmse"))


@query(
    f"WITH g AS ({t.G4}), n AS (SELECT count(DISTINCT src) AS u, count(DISTINCT dst) AS v FROM g) SELECT 'soft' AS kind, CAST(u * {A - 1} + v * {B - 1} + {A * B * (C - 1)} AS BIGINT) AS dof, CAST(0 AS BIGINT) AS discrete FROM n UNION ALL SELECT 'hard', {A * B * (C - 1)}, CAST(u + v AS BIGINT) FROM n"
)
def dof(spark, sf_dir):
    """Free parameters of the soft and the hard model on the rating graph."""
    n = t.g4_rating(spark, sf_dir).agg(F.countDistinct("src").alias("u"), F.countDistinct("dst").alias("v"))
    free = A * B * (C - 1)
    soft = n.select(F.lit("soft").alias("kind"), (F.col("u") * (A - 1) + F.col("v") * (B - 1) + free).alias("dof"), F.lit(0).cast("long").alias("discrete"))
    return soft.unionAll(n.select(F.lit("hard"), F.lit(free).cast("long"), F.col("u") + F.col("v")))


@query(
    f"WITH n AS (SELECT count(*) AS m, count(DISTINCT src) + count(DISTINCT dst) AS v FROM ({t.G4})) SELECT 'exact' AS method, round(m * 100.0, 6) AS touches FROM n UNION ALL SELECT 'sampled', round(m * (10 + 20 * log2(10)), 6) FROM n UNION ALL SELECT 'hard', round(0.1 * least(2 * m * 10, v * 100), 6) FROM n"
)
def cost_model(spark, sf_dir):
    n = t.g4_rating(spark, sf_dir).agg(F.count("*").alias("m"), (F.countDistinct("src") + F.countDistinct("dst")).alias("v"))
    m, v = F.col("m").cast("double"), F.col("v").cast("double")
    rows = F.array(*[F.struct(F.lit(k).alias("method"), F.round(x, 6).alias("touches")) for k, x in (("exact", m * 100), ("sampled", m * (10 + 20 * F.lit(math.log2(10)))), ("hard", 0.1 * F.least(2 * m * 10, v * 100)))])
    return n.select(F.explode(rows).alias("r")).select("r.*")


FOLDIN = f"""{START}, u AS (SELECT src, dst, cat FROM e WHERE src = (SELECT min(src) FROM e)),
w AS (SELECT src, dst, l.k AS a, sum(l.p * r.p * c.p) AS w FROM u JOIN (SELECT range AS k, 1.0 / {A} AS p FROM range({A})) l ON TRUE JOIN mr0 r ON r.id = dst JOIN cat0 c ON c.a = l.k AND c.b = r.k AND c.c = u.cat GROUP BY 1, 2, 3),
s AS (SELECT *, w / sum(w) OVER (PARTITION BY src, dst) AS x FROM w) SELECT src AS id, CAST(a AS INTEGER) AS k, round(avg(x), 6) AS p FROM s GROUP BY 1, 2"""


@query(FOLDIN)
def fold_in_user(spark, sf_dir):
    """Membership of one user from its edges alone, tensor and items frozen: one exact round from the uniform row."""
    from ..streaming.live import fold_in

    edges, _, right, cat = _state(spark, sf_dir)
    first = edges.agg(F.min("src").alias("src"))
    return _long(fold_in(edges.join(F.broadcast(first), "src"), right, cat, SIZES))


@query()
def soft_fit_planted(spark, sf_dir):
    """Exact mixed EM on planted ratings with the numpy backend: entropy of each round."""
    edges = t.planted_rating(spark, sf_dir).select("src", "dst", (F.col("cat") - 1).alias("cat"))
    return steps.fit_arrow(write_state(edges, "p2"), 5, 5, 5, None, SEED, Stop(max_iter=8)).trace.to_df(spark)


@query()
def sampled_fit_planted(spark, sf_dir):
    edges = t.planted_rating(spark, sf_dir).select("src", "dst", (F.col("cat") - 1).alias("cat"))
    return steps.fit_arrow(write_state(edges, "p2"), 5, 5, 5, 20, SEED, Stop(max_iter=8)).trace.to_df(spark)
