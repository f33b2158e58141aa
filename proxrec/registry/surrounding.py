"""Queries of the operators around the methods, batch and streaming, with their oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from proxrec.functions.hashing import fraction, fraction_sql
from proxrec.functions.vectors import register
from proxrec.sources.workloads import VIEW_SQL, VIEWS, load
from proxrec.streaming import folding

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def op(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


_B, _E = VIEW_SQL["brand_affinity"], VIEW_SQL["event_keys"]


@op("op_join_anti_seen", f"WITH r AS ({_E}) SELECT u.user_id, i.item_id FROM (SELECT DISTINCT user_id FROM r) u CROSS JOIN (SELECT DISTINCT item_id FROM r) i ANTI JOIN r ON r.user_id = u.user_id AND r.item_id = i.item_id")
def _anti(s, d):
    r = VIEWS["event_keys"](s, d)
    return r.select("user_id").distinct().crossJoin(F.broadcast(r.select("item_id").distinct())).join(r, ["user_id", "item_id"], "left_anti")


@op("op_join_semi_active", f"WITH r AS ({_E}) SELECT * FROM r WHERE user_id IN (SELECT user_id FROM r GROUP BY 1 HAVING count(*) >= 50)")
def _semi(s, d):
    r = VIEWS["event_keys"](s, d)
    return r.join(r.groupBy("user_id").agg(F.count("*").alias("n")).where("n >= 50"), "user_id", "left_semi")


@op("op_join_full_outer", "WITH a AS (SELECT l_suppkey AS k, count(*) AS n FROM lineitem WHERE l_quantity >= 49 GROUP BY 1), b AS (SELECT s_suppkey AS k, s_nationkey AS nation FROM supplier WHERE s_nationkey < 15) SELECT coalesce(a.k, b.k) AS k, n, nation FROM a FULL JOIN b ON a.k = b.k")
def _full(s, d):
    a = load(s, d, "lineitem").where("l_quantity >= 49").groupBy(F.col("l_suppkey").alias("k")).agg(F.count("*").alias("n"))
    return a.join(load(s, d, "supplier").where("s_nationkey < 15").select(F.col("s_suppkey").alias("k"), F.col("s_nationkey").alias("nation")), "k", "full")


@op("op_range_join", f"WITH r AS ({_B}), band(lo, hi, grade) AS (VALUES (1, 3, 'low'), (3, 5, 'middle'), (5, 6, 'high')) SELECT user_id, item_id, grade FROM r JOIN band ON rating >= lo AND rating < hi")
def _range(s, d):
    band = s.createDataFrame([(1, 3, "low"), (3, 5, "middle"), (5, 6, "high")], "lo int, hi int, grade string")
    return VIEWS["brand_affinity"](s, d).join(F.broadcast(band), F.expr("rating >= lo AND rating < hi")).select("user_id", "item_id", "grade")


@op("op_join_asof", "SELECT p.event_id, max_by(v.event_id, (v.ts, v.event_id)) AS view_id FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND (v.ts, v.event_id) < (p.ts, p.event_id) WHERE p.event_type = 'purchase' GROUP BY 1")
def _asof(s, d):
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = load(s, d, "events").select("event_id", "ts", "user_id", "event_type")
    return e.withColumn("view_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(order)).where("event_type = 'purchase'").select("event_id", "view_id")


@op("op_join_interval", "SELECT a.event_id AS first_id, b.event_id AS then_id, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def _interval(s, d):
    return folding.followed(folding.prepared(load(s, d, "events")))


@op("op_join_null_safe", "SELECT a.k, a.n AS n, b.n AS m FROM (SELECT CASE WHEN user_id % 7 = 0 THEN NULL ELSE user_id % 5 END AS k, count(*) AS n FROM events GROUP BY 1) a JOIN (SELECT CASE WHEN user_id % 3 = 0 THEN NULL ELSE user_id % 5 END AS k, count(*) AS n FROM events GROUP BY 1) b ON a.k IS NOT DISTINCT FROM b.k")
def _null_safe(s, d):
    e = load(s, d, "events")
    side = lambda k, n: e.groupBy(F.when(F.col("user_id") % k == 0, None).otherwise(F.col("user_id") % 5).alias("k")).agg(F.count("*").alias(n))
    a, b = side(7, "n"), side(3, "m").withColumnRenamed("k", "kb")
    return a.join(b, a.k.eqNullSafe(b.kb)).select("k", "n", "m")


@op("op_join_salted", "SELECT l_partkey, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def _salted(s, d):
    lines = load(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity").withColumn("salt", F.pmod(F.xxhash64("l_orderkey"), F.lit(8)))
    parts = load(s, d, "part").select("p_partkey").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(7).cast("long"))))
    joined = lines.join(parts, (lines.l_partkey == parts.p_partkey) & (lines.salt == parts.salt))
    return joined.groupBy("l_partkey").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


_DIMS = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _customers(s, d):
    c = load(s, d, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    n = F.broadcast(load(s, d, "nation").select("n_nationkey", "n_name", "n_regionkey"))
    r = F.broadcast(load(s, d, "region").select("r_regionkey", "r_name"))
    return c.join(n, c.c_nationkey == n.n_nationkey).join(r, F.col("n_regionkey") == F.col("r_regionkey"))


@op("op_cube", f"SELECT r_name, c_mktsegment, grouping(r_name)::INT * 2 + grouping(c_mktsegment)::INT AS g, count(*) AS n {_DIMS} GROUP BY CUBE (r_name, c_mktsegment)")
def _cube(s, d):
    return _customers(s, d).cube("r_name", "c_mktsegment").agg(F.grouping_id().cast("int").alias("g"), F.count("*").alias("n"))


@op("op_rollup_region", f"SELECT r_name, n_name, count(*) AS n {_DIMS} GROUP BY ROLLUP (r_name, n_name)")
def _rollup(s, d):
    return _customers(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@op("op_grouping_sets", f"SELECT r_name, c_mktsegment, count(*) AS n {_DIMS} GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")
def _sets(s, d):
    _customers(s, d).createOrReplaceTempView("_customers_dims")
    return s.sql("SELECT r_name, c_mktsegment, count(*) AS n FROM _customers_dims GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")


@op("op_pivot", "SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS {t}" for t in ("view", "purchase")) + " FROM events WHERE event_type IN ('view', 'purchase') GROUP BY 1")
def _pivot(s, d):
    return load(s, d, "events").where("event_type IN ('view', 'purchase')").groupBy("user_id").pivot("event_type", ["view", "purchase"]).agg(F.count(F.lit(1))).na.fill(0)


@op("op_unpivot", "SELECT r_regionkey, 'twice' AS name, r_regionkey * 2 AS value FROM region UNION ALL SELECT r_regionkey, 'thrice', r_regionkey * 3 FROM region")
def _unpivot(s, d):
    wide = load(s, d, "region").select("r_regionkey", (F.col("r_regionkey") * 2).alias("twice"), (F.col("r_regionkey") * 3).alias("thrice"))
    return wide.unpivot("r_regionkey", ["twice", "thrice"], "name", "value")


@op("op_topk_group", f"SELECT item_id, user_id, rating FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY rating DESC, user_id) AS k FROM ({_B})) WHERE k <= 3")
def _topk(s, d):
    order = Window.partitionBy("item_id").orderBy(F.desc("rating"), "user_id")
    return VIEWS["brand_affinity"](s, d).withColumn("k", F.row_number().over(order)).where("k <= 3").select("item_id", "user_id", "rating")


@op("op_window_ranks", "SELECT item_id, n, CAST(rank() OVER o AS INT) AS r, CAST(dense_rank() OVER o AS INT) AS dr, CAST(ntile(4) OVER o2 AS INT) AS quartile, round(cume_dist() OVER o, 6) + 0.0 AS cd, round(percent_rank() OVER o, 6) + 0.0 AS pr FROM (SELECT l_suppkey AS item_id, count(*) AS n FROM lineitem GROUP BY 1) WINDOW o AS (ORDER BY n DESC), o2 AS (ORDER BY n DESC, item_id)")
def _ranks(s, d):
    counts = load(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("item_id")).agg(F.count("*").alias("n"))
    o, o2 = Window.orderBy(F.desc("n")), Window.orderBy(F.desc("n"), "item_id")  # one row a supplier
    return counts.select("item_id", "n", F.rank().over(o).alias("r"), F.dense_rank().over(o).alias("dr"), F.ntile(4).over(o2).alias("quartile"), (F.round(F.cume_dist().over(o), 6) + 0.0).alias("cd"), (F.round(F.percent_rank().over(o), 6) + 0.0).alias("pr"))


@op("op_window_lag", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _lag(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"))


@op("op_window_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(epoch(ts) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
def _rng(s, d):
    w = Window.partitionBy("user_id").orderBy(F.col("t")).rangeBetween(-86400, 0)
    # whole seconds as the oracle's cast makes them: the nearest, halves to the even one
    t = F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long")
    return load(s, d, "events").withColumn("t", t).select("event_id", F.count("*").over(w).alias("n"))


@op("op_set_intersect", "SELECT user_id FROM events WHERE event_type = 'view' INTERSECT SELECT user_id FROM events WHERE event_type = 'purchase'")
def _intersect(s, d):
    e = load(s, d, "events")
    return e.where("event_type = 'view'").select("user_id").intersect(e.where("event_type = 'purchase'").select("user_id"))


@op("op_set_except_all", "SELECT user_id FROM events WHERE event_type = 'view' EXCEPT ALL SELECT user_id FROM events WHERE event_type = 'purchase'")
def _except(s, d):
    e = load(s, d, "events")
    return e.where("event_type = 'view'").select("user_id").exceptAll(e.where("event_type = 'purchase'").select("user_id"))


@op("op_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
def _json(s, d):
    return load(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@op("op_map_bag", f"SELECT user_id, count(*) AS n, max(rating) AS most FROM ({_B}) GROUP BY 1")
def _map(s, d):
    bag = VIEWS["brand_affinity"](s, d).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("item_id", "rating"))).alias("bag"))
    return bag.select("user_id", F.size("bag").cast("long").alias("n"), F.array_max(F.map_values("bag")).alias("most"))


@op("op_array_dot", "WITH e AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings) SELECT vec_id, round(list_dot_product(x, x), 6) + 0.0 AS d FROM e")
def _dot(s, d):
    register(s)
    return load(s, d, "embeddings").select("vec_id", (F.round(F.expr("aggregate(zip_with(embedding, embedding, (a, b) -> CAST(a AS DOUBLE) * CAST(b AS DOUBLE)), 0D, (s, v) -> s + v)"), 6) + 0.0).alias("d"))


@op("op_udf_vec_dot", ORACLES["op_array_dot"])
def _udf(s, d):
    register(s)
    return load(s, d, "embeddings").select("vec_id", (F.round(F.expr("vec_dot(CAST(embedding AS ARRAY<DOUBLE>), CAST(embedding AS ARRAY<DOUBLE>))"), 6) + 0.0).alias("d"))


@op("op_udaf_vec_sum", "SELECT label, round(sum(CAST(embedding[1] AS DOUBLE)), 6) + 0.0 AS first, round(sum(CAST(embedding[64] AS DOUBLE)), 6) + 0.0 AS last FROM embeddings GROUP BY 1")
def _udaf(s, d):
    register(s)
    sums = load(s, d, "embeddings").groupBy("label").agg(F.expr("vec_sum(CAST(embedding AS ARRAY<DOUBLE>))").alias("v"))
    return sums.select("label", (F.round(F.col("v")[0], 6) + 0.0).alias("first"), (F.round(F.col("v")[63], 6) + 0.0).alias("last"))


@op("op_udtf_expand", f"SELECT user_id, CAST(k AS INT) AS place, item_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY rating DESC, item_id) AS k FROM ({_B})) WHERE k <= 3")
def _udtf(s, d):
    register(s)
    lists = VIEWS["brand_affinity"](s, d).groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct((-F.col("rating")).alias("r"), "item_id"))).alias("l")).select("user_id", F.slice("l.item_id", 1, 3).alias("items"))
    lists.createOrReplaceTempView("_lists")
    return s.sql("SELECT user_id, place, item_id FROM _lists, LATERAL expand_list(items)")


@op("op_quantiles", f"SELECT item_id, round(quantile_cont(rating, 0.5), 6) + 0.0 AS median, round(quantile_cont(rating, 0.9), 6) + 0.0 AS p90 FROM ({_B}) GROUP BY 1")
def _quantiles(s, d):
    return VIEWS["brand_affinity"](s, d).groupBy("item_id").agg((F.round(F.percentile("rating", 0.5), 6) + 0.0).alias("median"), (F.round(F.percentile("rating", 0.9), 6) + 0.0).alias("p90"))


@op("op_popularity_gini", f"WITH c AS (SELECT item_id, count(*) AS n FROM ({VIEW_SQL['doc_terms']}) GROUP BY 1), o AS (SELECT n, row_number() OVER (ORDER BY n, item_id) AS k FROM c) SELECT round(2.0 * sum(k * n) / (count(*) * sum(n)) - (count(*) + 1.0) / count(*), 6) + 0.0 AS gini FROM o")
def _gini(s, d):
    # items of one number of ratings share their places' sum, so the running count goes over the distinct numbers only
    c = VIEWS["doc_terms"](s, d).groupBy("item_id").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("c"))
    o = c.withColumn("b", F.coalesce(F.sum("c").over(Window.orderBy("n").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    places = F.col("n") * (F.col("c") * F.col("b") + F.col("c") * (F.col("c") + 1) / 2)
    return o.agg((F.round(2.0 * F.sum(places) / (F.sum("c") * F.sum(F.col("c") * F.col("n"))) - (F.sum("c") + 1.0) / F.sum("c"), 6) + 0.0).alias("gini"))


@op("op_approx_distinct", "SELECT item_id, count(DISTINCT user_id) AS n, true AS near FROM (" + _B + ") GROUP BY 1")
def _approx(s, d):
    r = VIEWS["brand_affinity"](s, d)
    return r.groupBy("item_id").agg(F.count_distinct("user_id").alias("n"), F.approx_count_distinct("user_id", 0.02).alias("a")).select("item_id", "n", (F.abs(F.col("a") - F.col("n")) <= 0.1 * F.col("n")).alias("near"))


@op("op_max_by", f"SELECT item_id, max_by(user_id, (rating, user_id)) AS most, min_by(user_id, (rating, user_id)) AS least, bool_or(rating >= 5) AS any_best, count(*) FILTER (WHERE rating >= 5) AS best FROM ({_B}) GROUP BY 1")
def _max_by(s, d):
    by = F.struct("rating", "user_id")
    return VIEWS["brand_affinity"](s, d).groupBy("item_id").agg(F.max_by("user_id", by).alias("most"), F.min_by("user_id", by).alias("least"), F.bool_or(F.col("rating") >= 5).alias("any_best"), F.count_if(F.col("rating") >= 5).alias("best"))


@op("op_order_offset", "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1 ORDER BY n DESC, l_partkey LIMIT 10 OFFSET 5")
def _offset(s, d):
    return load(s, d, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_partkey").offset(5).limit(10)


@op("op_union_by_name", "SELECT n_nationkey AS id, n_name AS name FROM nation UNION ALL SELECT r_regionkey, r_name FROM region")
def _by_name(s, d):
    nations = load(s, d, "nation").select(F.col("n_nationkey").alias("id"), F.col("n_name").alias("name"))
    return nations.unionByName(load(s, d, "region").select(F.col("r_name").alias("name"), F.col("r_regionkey").alias("id")))


@op("op_set_intersect_all", "SELECT user_id FROM events WHERE event_type = 'view' INTERSECT ALL SELECT user_id FROM events WHERE event_type = 'purchase'")
def _intersect_all(s, d):
    e = load(s, d, "events")
    return e.where("event_type = 'view'").select("user_id").intersectAll(e.where("event_type = 'purchase'").select("user_id"))


@op("op_strings", "SELECT n_nationkey, lower(n_name) AS low, length(n_name) AS size, levenshtein(n_name, 'CANADA') AS distance, split_part(n_name, ' ', 1) AS first, concat_ws('-', n_name, n_nationkey) AS tag, regexp_replace(n_name, '[AEIOU]', '', 'g') AS bare FROM nation")
def _strings(s, d):
    n = F.col("n_name")
    return load(s, d, "nation").select("n_nationkey", F.lower(n).alias("low"), F.length(n).cast("long").alias("size"), F.levenshtein(n, F.lit("CANADA")).cast("long").alias("distance"), F.split(n, " ")[0].alias("first"), F.concat_ws("-", n, F.col("n_nationkey").cast("string")).alias("tag"), F.regexp_replace(n, "[AEIOU]", "").alias("bare"))


@op("op_dates", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days, CAST(CAST(o_orderdate AS DATE) + INTERVAL 7 DAY AS DATE) AS week_on, hour(o_orderdate) AS h FROM orders")
def _dates(s, d):
    t = F.col("o_orderdate")
    return load(s, d, "orders").select("o_orderkey", F.trunc(t.cast("date"), "month").alias("month"), F.datediff(t.cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"), F.date_add(t.cast("date"), 7).alias("week_on"), F.hour(t).cast("long").alias("h"))


@op("op_subqueries", "SELECT c_custkey, (SELECT max(n_name) FROM nation WHERE n_nationkey = c_nationkey) AS nation FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > (SELECT avg(o_totalprice) FROM orders)) AND c_nationkey IN (SELECT n_nationkey FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_regionkey <= 2)")
def _subqueries(s, d):
    """Correlated EXISTS and scalar, uncorrelated scalar, and IN."""
    for name in ("customer", "orders", "nation", "region"):
        load(s, d, name).createOrReplaceTempView(f"_sub_{name}")
    return s.sql(
        "SELECT c_custkey, (SELECT max(n_name) FROM _sub_nation WHERE n_nationkey = c_nationkey) AS nation FROM _sub_customer WHERE EXISTS (SELECT 1 FROM _sub_orders WHERE o_custkey = c_custkey AND o_totalprice > (SELECT avg(o_totalprice) FROM _sub_orders)) "
        "AND c_nationkey IN (SELECT n_nationkey FROM _sub_nation JOIN _sub_region ON n_regionkey = r_regionkey WHERE r_regionkey <= 2)"
    )


_DOUBLED = "WITH RECURSIVE t(k, n, f) AS (SELECT user_id % 10 AS k, 1 AS n, count(*) AS f FROM {0} GROUP BY 1 UNION ALL SELECT k, n + 1, f * 2 FROM t WHERE n < 12) SELECT k, n, f FROM t"


@op("op_recursive_cte", _DOUBLED.format("events"))
def _recursive(s, d):
    load(s, d, "events").createOrReplaceTempView("_recursive_events")
    return s.sql(_DOUBLED.format("_recursive_events"))


@op("op_sql_score", f"WITH r AS ({_B}), u AS (SELECT min(user_id) AS user_id FROM r) SELECT item_id, count(*) AS n, true AS same FROM r GROUP BY 1")
def _sql_score(s, d):
    """The SQL function latent_score(user, item) on each item's first rater, beside the join of pairs."""
    from proxrec.operators import model, surface

    r = VIEWS["brand_affinity"](s, d)
    fitted = model.fit(r, model.ModelSpec("cosine", 0.4, 3))
    surface.register(s, fitted, r, 3)
    first = r.groupBy("item_id").agg(F.min("user_id").alias("user_id"), F.count("*").alias("n"))
    first.createOrReplaceTempView("_firsts")
    by_sql = s.sql("SELECT item_id, n, user_id, latent_score(user_id, item_id) AS score FROM _firsts")
    plain = model.score_pairs(fitted, r, first.select("user_id", "item_id")).select("item_id", F.col("score").alias("other"))
    return by_sql.join(plain, "item_id").select("item_id", "n", (F.abs(F.col("score") - F.col("other")) < 1e-9).alias("same"))


@op("op_udtf_recommend", f"SELECT user_id, count(*) AS n FROM (SELECT DISTINCT user_id, unnest([1, 2, 3]) AS k FROM ({_B})) WHERE user_id IN (SELECT user_id FROM ({_B}) GROUP BY 1 HAVING count(*) <= 22) GROUP BY 1")
def _udtf_recommend(s, d):
    """The table function recommend_user(items, ratings, n) on packed rows; users with three items or more left get three."""
    from proxrec.operators import model, surface

    r = VIEWS["brand_affinity"](s, d)
    surface.register(s, model.fit(r, model.ModelSpec("cosine", 0.4, 3)), r, 3)
    r.groupBy("user_id").agg(F.collect_list("item_id").alias("items"), F.collect_list("rating").alias("marks")).where("size(items) <= 22").createOrReplaceTempView("_packed_users")
    return s.sql("SELECT user_id, place FROM _packed_users, LATERAL recommend_user(items, marks, 3)").groupBy("user_id").agg(F.count("*").alias("n"))


@op("op_hash_sample", f"SELECT event_id FROM events WHERE {fraction_sql(5, 'event_id')} < 0.1")
def _sample(s, d):
    return load(s, d, "events").where(fraction(5, "event_id") < 0.1).select("event_id")


@op("op_stratified_sample", f"SELECT event_id FROM (SELECT event_id, row_number() OVER (PARTITION BY event_type ORDER BY {fraction_sql(5, 'event_id')}, event_id) AS k FROM events) WHERE k <= 20")
def _stratified(s, d):
    order = Window.partitionBy("event_type").orderBy(fraction(5, "event_id"), "event_id")
    return load(s, d, "events").withColumn("k", F.row_number().over(order)).where("k <= 20").select("event_id")


@op("op_list_overlap", "WITH a AS (SELECT user_id, list(DISTINCT event_type) AS x FROM events WHERE event_id % 2 = 0 GROUP BY 1), b AS (SELECT user_id, list(DISTINCT event_type) AS y FROM events WHERE event_id % 2 = 1 GROUP BY 1) SELECT user_id, round(len(list_intersect(x, y)) / (len(x) + len(y) - len(list_intersect(x, y))), 6) + 0.0 AS overlap FROM a JOIN b USING (user_id)")
def _overlap(s, d):
    e = load(s, d, "events")
    part = lambda k, n: e.where(F.col("event_id") % 2 == k).groupBy("user_id").agg(F.collect_set("event_type").alias(n))
    return part(0, "x").join(part(1, "y"), "user_id").select("user_id", (F.round(F.size(F.array_intersect("x", "y")) / F.size(F.array_union("x", "y")), 6) + 0.0).alias("overlap"))


# streams, run over all that is there; oracles are batch SQL
_DAY = "SELECT date_trunc('day', ts) AS start, CAST(json_extract_string(props, '$.k') AS INT) AS item_id, count(*) AS n FROM events GROUP BY 1, 2"


def _plain(df: DataFrame, *times: str) -> DataFrame:
    return df.withColumns({t: F.col(t).cast("timestamp_ntz") for t in times})


@op("stream_popularity_tumbling", _DAY)
def _tumbling(s, d):
    return _plain(folding.run_to_table(folding.popularity(folding.event_stream(s, d)), "complete"), "start")


@op("stream_popularity_sliding", "SELECT date_trunc('day', ts) - to_days(CAST(o AS INT)) AS start, CAST(json_extract_string(props, '$.k') AS INT) AS item_id, count(*) AS n FROM events, range(7) t(o) GROUP BY 1, 2")
def _sliding(s, d):
    return _plain(folding.run_to_table(folding.popularity(folding.event_stream(s, d), "7 days", "1 day"), "complete"), "start")


@op("stream_sessions", "WITH g AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), h AS (SELECT user_id, ts, sum(f) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS \"end\", count(*) AS n FROM h GROUP BY user_id, k")
def _sessions(s, d):
    return _plain(folding.run_to_table(folding.sessions(folding.event_stream(s, d)), "complete"), "start", "end")


@op("stream_dedup", "SELECT event_id, user_id FROM events")
def _dedup(s, d):
    e = folding.event_stream(s, d)
    return folding.run_to_table(folding.deduplicated(e.unionAll(e)).select("event_id", "user_id"), "append")


@op("stream_capped_ratings", _E)
def _capped(s, d):
    deltas = folding.run_to_table(folding.capped_deltas(folding.event_stream(s, d)), "append")
    return deltas.groupBy("user_id", "item_id").agg(F.sum("delta").alias("rating"))


@op("stream_interval_join", ORACLES["op_join_interval"])
def _stream_join(s, d):
    return folding.run_to_table(folding.followed(folding.event_stream(s, d)), "append")


@op("stream_fold_in", "SELECT user_id, round(sum(1.0 / (1 + CAST(json_extract_string(props, '$.k') AS INT))), 6) + 0.0 AS p0, round(sum(CAST(json_extract_string(props, '$.k') AS INT) / 100.0), 6) + 0.0 AS p1 FROM events GROUP BY 1")
def _fold(s, d):
    latent = s.range(100).select(F.col("id").cast("int").alias("item_id"), F.array(1.0 / (1 + F.col("id")), F.col("id") / 100.0).alias("v"))
    kept = folding.run_to_table(folding.factors(folding.event_stream(s, d), latent), "complete")
    one = lambda k: (F.round(F.max(F.when(F.col("k") == k, F.col("p"))), 6) + 0.0).alias(f"p{k}")
    return kept.groupBy("user_id").agg(one(0), one(1))


@op("stream_late_rows", "WITH m AS (SELECT max(ts) AS t FROM events WHERE event_id % 4 = 0) SELECT date_trunc('hour', ts) AS start, CAST(count(*) AS INT) AS n FROM events, m WHERE event_id % 4 = 0 OR (event_id % 4 = 1 AND ts > t - INTERVAL 1 HOUR) OR (event_id % 4 = 2 AND date_trunc('hour', ts) + INTERVAL 1 HOUR > t - INTERVAL 2 HOUR) GROUP BY 1")
def _late(s, d):
    return _plain(folding.late_rows(folding.prepared(load(s, d, "events"))), "start").withColumn("n", F.col("n").cast("int"))


@op("stream_top_n", "WITH p AS (SELECT user_id, sum(1.0 / (1 + k)) AS p0, sum(k / 100.0) AS p1 FROM (SELECT user_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events) GROUP BY 1), s AS (SELECT user_id, CAST(i AS INT) AS item_id, p0 / (1 + i) + p1 * i / 100.0 AS s FROM p, range(100) t(i)) SELECT user_id, CAST(rank AS INT) AS rank, item_id FROM (SELECT user_id, item_id, row_number() OVER (PARTITION BY user_id ORDER BY round(s, 9) DESC, item_id) AS rank FROM s) WHERE rank <= 3")
def _stream_top(s, d):
    latent = s.range(100).select(F.col("id").cast("int").alias("item_id"), F.array(1.0 / (1 + F.col("id")), F.col("id") / 100.0).alias("v"))
    return folding.refreshed_lists(folding.event_stream(s, d), latent, 3).select("user_id", "rank", "item_id")


@op("stream_drift", f"WITH r AS ({_E}), a AS (SELECT item_id, sqrt(sum(rating * rating)) AS x FROM r GROUP BY 1), b AS (SELECT item_id, sqrt(sum(rating * rating)) AS y FROM r WHERE user_id % 2 = 0 GROUP BY 1), c AS (SELECT abs(coalesce(x, 0) - coalesce(y, 0)) / greatest(coalesce(x, 0), coalesce(y, 0), 1e-12) AS c FROM a FULL JOIN b USING (item_id)) SELECT round(avg(c), 6) + 0.0 AS change, avg(c) > 0.2 AS retrain FROM c")
def _drift(s, d):
    from proxrec.operators.ratings import item_stats

    model_items = item_stats(VIEWS["event_keys"](s, d).where("user_id % 2 = 0"))
    return folding.stream_drift(folding.event_stream(s, d), model_items).select((F.round("change", 6) + 0.0).alias("change"), "retrain")
