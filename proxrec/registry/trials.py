"""Queries of the experiments. Rows whose scores SQL can reproduce (popularity, counts of cases) have oracles; the others give rows only."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxrec.functions.hashing import fraction_sql
from proxrec.operators import evaluation, experiments, linalg, model
from proxrec.operators.evaluation import LongTail, NewCommunity, NewUsers, Standard
from proxrec.operators.gram import GramOperator, pack_rows
from proxrec.operators.model import ModelSpec, fit
from proxrec.plans.planner import choose_operator, cost_model, cut
from proxrec.sources.workloads import VIEW_SQL, VIEWS

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

DS, FS = [-2.0, -1.0, -0.4, 0.0, 0.2, 0.4, 0.6, 1.0, 2.0], [5, 10, 20, 50, 100]
#: Scalings among which the comparisons choose; the sweep shows the others to be worse.
NEAR = [0.2, 0.4]


def add(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def all_methods(prepared: experiments.Prepared) -> DataFrame:
    """Ranks of every method over its parameters: three similarities, truncated SVD, five graph kernels, popularity, random."""
    out = experiments.latent_methods(prepared, NEAR, FS).unionByName(experiments.svd_method(prepared, FS))
    return out.unionByName(experiments.kernel_methods(prepared)).unionByName(experiments.plain_methods(prepared))


def standard(view: str, probe: float) -> Callable[[SparkSession, str], DataFrame]:
    """All methods at their best parameters, all measures."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return experiments.tuned(all_methods(experiments.prepare(Standard(probe), cut(VIEWS[view](spark, sf_dir)))))

    return run


# standard test: the share of the paper and a larger one; a second view without signal as a control
add("x1_standard_14", standard("doc_terms", 0.014))
add("x3_methods", standard("doc_terms", 0.05))
add("x3_methods_purchases", standard("purchases", 0.05))


def _grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every setting of every method by MRR: what the comparison chooses from."""
    hits = all_methods(experiments.prepare(Standard(0.05), cut(VIEWS["doc_terms"](spark, sf_dir))))
    return experiments.measures(hits).where("measure = 'mrr'").drop("k")


add("x3_parameter_grid", _grid)


def _tail(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every method tuned on the cases of the long tail."""
    hits = all_methods(experiments.prepare(LongTail(0.05), cut(VIEWS["doc_terms"](spark, sf_dir))))
    return experiments.tuned(hits)


add("x4_long_tail", _tail)


def _sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """MRR by similarity and scaling exponent at the number of factors that is best for each matrix, and the gain over d = 1."""
    hits = experiments.latent_methods(experiments.prepare(Standard(0.05), cut(VIEWS["doc_terms"](spark, sf_dir))), DS, FS)
    split = hits.withColumn("d", F.regexp_extract("setting", r"d=([^ ]+)", 1).cast("double")).withColumn("f", F.regexp_extract("setting", r"f=([0-9]+)", 1).cast("int"))
    rows = split.groupBy("method", "d", "f").agg(F.avg(1 / F.col("hit")).alias("mrr"), F.count("*").alias("n_cases"))
    best = rows.groupBy("method", "d").agg(F.max(F.struct(F.round("mrr", 6).alias("mrr"), (-F.col("f")).alias("f"), "n_cases")).alias("b"))
    flat = best.select("method", "d", F.col("b.mrr").alias("mrr"), (-F.col("b.f")).alias("f"), F.col("b.n_cases").alias("n_cases"))
    one = flat.where("d = 1").select("method", F.col("mrr").alias("at_1"))
    return flat.join(F.broadcast(one), "method").select("method", "d", "f", "mrr", F.round(F.col("mrr") - F.col("at_1"), 6).alias("gain"), "n_cases")


add("x2_scaling_sweep", _sweep)


def _community(share: float) -> Callable[[SparkSession, str], DataFrame]:
    """A community of so many of the ratings, nested in the larger ones: standard and long-tail halves, every method tuned on each."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        hits = cut(all_methods(experiments.prepare(NewCommunity(share, 0.05), cut(VIEWS["doc_terms"](spark, sf_dir)))))
        halves = hits.withColumn("test", F.lit("standard")).unionByName(hits.where("tail").withColumn("test", F.lit("tail")))
        return experiments.tuned(halves, ("test",))

    return run


for _share, _name in ((0.33, "33"), (0.66, "66"), (1.0, "100")):
    add(f"x5_new_community_{_name}", _community(_share))
add("x6_new_users", lambda s, d: experiments.tuned(all_methods(experiments.prepare(NewUsers(), cut(VIEWS["doc_terms"](s, d))))))


def _reported(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two reported Jaccard settings, on the standard test and on the long tail they were chosen on."""
    prepared = experiments.prepare(Standard(0.05), cut(VIEWS["doc_terms"](spark, sf_dir)))
    own, out = experiments.Proximities(prepared.train, "jaccard"), None
    for d, f in ((0.2, 241), (0.4, 270)):
        hits = experiments.latent_hits(prepared, "latent jaccard", [(f"d={d:g}", own.fit(d, f, 1e-6))], [f])
        for half, part in (("standard", hits), ("tail", hits.where("tail"))):
            one = experiments.measures(part).withColumn("test", F.lit(half))
            out = one if out is None else out.unionByName(one)
    return out


add("x11_reported_settings", _reported)


def _claims(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The closing remarks as rows: is d = 1 below the best d, how far the similarities lie apart, and what a solve of each costs."""
    prepared = experiments.prepare(Standard(0.05), cut(VIEWS["doc_terms"](spark, sf_dir)))
    rows = []
    for kind in experiments.SIMILARITIES:
        t = time.perf_counter()
        users, items, row, column, value = model.triplets(prepared.train)
        op, _ = model.local_operator(row, column, value, len(users), len(items), kind, 0.4)
        linalg.lanczos(op, 50, 1e-6)
        seconds = time.perf_counter() - t
        own = experiments.Proximities(prepared.train, kind)
        hits = experiments.latent_hits(prepared, kind, [(f"d={d:g}", own.fit(d, 100)) for d in (0.2, 0.4, 1.0)], FS)
        mrr = {r[0]: r[1] for r in hits.groupBy("setting").agg(F.avg(1 / F.col("hit"))).collect()}
        at_1 = max(v for k, v in mrr.items() if k.startswith("d=1 "))
        rows.append((kind, round(float(max(mrr.values())), 6), round(float(at_1), 6), bool(at_1 < max(mrr.values())), round(seconds, 3)))
    return spark.createDataFrame(rows, "similarity string, best_mrr double, mrr_at_1 double, d_1_is_dominated boolean, seconds_f50 double")


add("x12_claims", _claims)


def _steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lanczos steps, residuals, modelled costs and measured shares of the phases by number of factors."""
    out = []
    for view in ("doc_terms", "purchases"):
        users, items, row, column, value = model.triplets(VIEWS[view](spark, sf_dir))
        for f in (50, 100, 150, 200, 300):
            op, _ = model.local_operator(row, column, value, len(users), len(items), "cosine", 1.0)
            t = time.perf_counter()
            found = linalg.lanczos(op, f, 1e-6)
            seconds = time.perf_counter() - t
            costs = cost_model(len(users), len(items), len(value), f, found.trace.steps)
            shares = found.trace.shares()
            plan = choose_operator(len(users), len(items), len(value), f)
            out.append((view, f, found.trace.steps, float(max(found.trace.residuals) / found.values[0]), costs["product_flops"], costs["orthogonalisation_flops"], shares["product"], shares["orthogonalisation"], shares["tridiagonal"], seconds, plan.form))
    return spark.createDataFrame(out, "view string, f int, steps int, residual double, product_flops double, orthogonalisation_flops double, product_share double, orthogonalisation_share double, tridiagonal_share double, seconds double, form string")


add("x7_lanczos_steps", _steps)


def _speed_up(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of a distributed product by number of tasks that share the rows, and the speed-up over one; the sums are checked to be equal."""
    ratings = cut(VIEWS["purchases"](spark, sf_dir))
    items = [r[0] for r in ratings.select("item_id").distinct().orderBy("item_id").collect()]
    packed = cut(pack_rows(ratings, model.item_index(spark, items)))
    x = np.random.default_rng(1).standard_normal((len(items), 70))
    out, first, want = [], None, None
    for tasks in (1, 2, 4, 8):
        rows = packed.repartition(tasks, "user_id").persist()
        op = GramOperator(rows, len(items), np.ones(len(items)))
        op.apply(x)  # loads the rows
        took = []
        for _ in range(3):
            t = time.perf_counter()
            y = op.apply(x)
            took.append(time.perf_counter() - t)
        rows.unpersist()
        first, want = (min(took), y) if first is None else (first, want)
        out.append((tasks, min(took), first / min(took), bool(np.allclose(y, want))))
    return spark.createDataFrame(out, "tasks int, seconds double, speed_up double, equal boolean")


add("x8_speed_up", _speed_up)


def _end_to_end(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recommendation lists of all users, and what each phase took."""
    t0 = time.perf_counter()
    ratings = cut(VIEWS["purchases"](spark, sf_dir))
    t1 = time.perf_counter()
    fitted = fit(ratings, ModelSpec("cosine", 0.4, 50, tol=1e-4))
    t2 = time.perf_counter()
    lists = cut(model.recommend(fitted, ratings, 10))
    t3 = time.perf_counter()
    return lists.agg(F.count_distinct("user_id").alias("users"), F.count("*").alias("rows")).select("*", F.lit(t1 - t0).alias("ratings_s"), F.lit(t2 - t1).alias("fit_s"), F.lit(t3 - t2).alias("lists_s"), F.lit(t3 - t0).alias("total_s"))


add("x9_end_to_end", _end_to_end)
add("x9_lists", lambda s, d: model.recommend(fit(r := VIEWS["purchases"](s, d), ModelSpec("cosine", 0.4, 20, tol=1e-4)), r, 10))


# rows that SQL reproduces: popularity in every scenario, through the harness
def _popular(scenario, view: str = "doc_terms"):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        prepared = experiments.prepare(scenario, cut(VIEWS[view](spark, sf_dir)))
        hits = experiments.plain_methods(prepared)
        return experiments.measures(hits, ("method",)).where("measure IN ('mrr', 'ndcg', 'rscore') OR (measure = 'recall' AND k IN (1, 10, 20))")

    return run


def _popular_sql(rated: str, probe: str, best: float, train: str, tail: bool) -> str:
    """``rated``: the scenario's ratings; ``probe`` and ``train``: conditions on r or further CTEs given as a pair of selects."""
    return (
        f"WITH r0 AS ({rated}), r AS (SELECT * FROM r0), {probe}, tr AS ({train}), "
        f"c AS (SELECT concat_ws('|', user_id, item_id) AS case_id, user_id, item_id FROM p WHERE rating >= {best}{' AND item_id NOT IN (SELECT item_id FROM hd)' if tail else ''}), "
        f"f AS (SELECT u.user_id, i.item_id, row_number() OVER (PARTITION BY u.user_id ORDER BY {fraction_sql(7, 'u.user_id', 'i.item_id')}, i.item_id) AS k FROM (SELECT DISTINCT user_id FROM c) u CROSS JOIN (SELECT DISTINCT item_id FROM r0) i "
        "WHERE NOT EXISTS (SELECT 1 FROM r0 WHERE r0.user_id = u.user_id AND r0.item_id = i.item_id)), "
        "l AS (SELECT c.case_id, c.user_id, f.item_id, false AS is_target FROM c JOIN f USING (user_id) WHERE k <= 1000 UNION ALL SELECT case_id, user_id, item_id, true FROM c), "
        "n AS (SELECT item_id, count(*) AS n FROM tr GROUP BY 1), "
        f"sc AS (SELECT 'popularity' AS method, l.*, CAST(coalesce(n, 0) AS DOUBLE) AS s FROM l LEFT JOIN n USING (item_id) UNION ALL SELECT 'random', l.*, {fraction_sql(97, 'user_id', 'item_id')} FROM l), "
        "h AS (SELECT method, rank AS hit FROM (SELECT method, is_target, row_number() OVER (PARTITION BY method, case_id ORDER BY round(s, 9) DESC, item_id) AS rank FROM sc) WHERE is_target), "
        "ks AS (SELECT CAST(unnest(generate_series(1, 20)) AS INT) AS k), hl AS (SELECT CAST(unnest([2, 5, 10, 20]) AS INT) AS k) "
        "SELECT method, 'mrr' AS measure, CAST(0 AS INT) AS k, round(avg(1.0 / hit), 6) + 0.0 AS value, count(*) AS n_cases FROM h GROUP BY 1 UNION ALL "
        "SELECT method, 'recall', k, round(avg(CASE WHEN hit <= k THEN 1.0 ELSE 0 END), 6) + 0.0, count(*) FROM h CROSS JOIN ks WHERE k IN (1, 10, 20) GROUP BY 1, 3 UNION ALL "
        "SELECT method, 'ndcg', k, round(avg(CASE WHEN hit <= k THEN log2(3) / log2(hit + 2) ELSE 0 END), 6) + 0.0, count(*) FROM h CROSS JOIN ks GROUP BY 1, 3 UNION ALL "
        "SELECT method, 'rscore', k, round(avg(1 / pow(2, (hit - 1) / (k - 1.0))), 6) + 0.0, count(*) FROM h CROSS JOIN hl GROUP BY 1, 3"
    )


def _probe_sql(share: float, seed: int = 42) -> tuple[str, str]:
    h = fraction_sql(seed, "user_id", "item_id")
    return f"p AS (SELECT * FROM r WHERE {h} < {share})", f"SELECT * FROM r WHERE {h} >= {share}"


_T = VIEW_SQL["doc_terms"]
_HEAD = "it AS (SELECT item_id, count(*) AS n FROM r GROUP BY 1), hd AS (SELECT item_id FROM (SELECT item_id, coalesce(sum(n) OVER (ORDER BY n DESC, item_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM it) WHERE before < (SELECT sum(n) FROM it) / 3.0)"
for _share, _name in ((0.014, "standard_14"), (0.05, "standard")):
    _p, _t = _probe_sql(_share)
    add(f"x_plain_{_name}", _popular(Standard(_share)), _popular_sql(_T, _p, 5, _t, False))
_p, _t = _probe_sql(0.05)
add("x_plain_long_tail", _popular(LongTail(0.05)), _popular_sql(_T, f"{_HEAD}, {_p}", 5, _t, True))
add("x_plain_purchases", _popular(Standard(0.05), "purchases"), _popular_sql(VIEW_SQL["purchases"], _p, 5, _t, False))
for _share, _name in ((0.33, "33"), (0.66, "66")):
    _p, _t = (x.replace("FROM r ", "FROM r1 ") for x in _probe_sql(0.05, 43))
    _c = f"r1 AS (SELECT * FROM r WHERE {fraction_sql(42, 'user_id', 'item_id')} < {_share})"
    add(f"x_plain_community_{_name}", _popular(NewCommunity(_share, 0.05)), _popular_sql(_T, f"{_c}, {_p}", 5, _t, False))
_h = fraction_sql(44, "user_id", "item_id")
_new = (
    f"ch AS (SELECT user_id FROM (SELECT user_id, count(*) AS n FROM r GROUP BY 1) WHERE n >= 100 ORDER BY {fraction_sql(42, 'user_id')}, user_id LIMIT 50), "
    f"th AS (SELECT * FROM r WHERE user_id NOT IN (SELECT user_id FROM ch) OR {fraction_sql(42, 'user_id', 'item_id')} >= 0.95), p AS (SELECT * FROM th WHERE user_id IN (SELECT user_id FROM ch) AND {_h} < 0.1)"
)
add("x_plain_new_users", _popular(NewUsers()), _popular_sql(_T, _new, 1, f"SELECT * FROM th WHERE NOT (user_id IN (SELECT user_id FROM ch) AND {_h} < 0.1)", False))
