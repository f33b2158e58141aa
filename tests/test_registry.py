import numpy as np

import __spark_entry__
from proxrec.operators import proximity
from proxrec.operators.model import ModelSpec, fit
from proxrec.sources.workloads import VIEWS

SMALL = "/root/testdata/sf0.001"


def test_every_rated_pair_is_explained(spark):
    ratings = VIEWS["brand_affinity"](spark, SMALL)
    fitted = fit(ratings, ModelSpec("cosine", 0.4, 1))
    phi, at = fitted.phi(), {item: k for k, item in enumerate(fitted.items)}
    by_user: dict = {}
    for r in ratings.collect():
        by_user.setdefault(r["user_id"], {})[r["item_id"]] = r["rating"]
    want = {}
    for user, own in by_user.items():
        for item in own:
            parts = sorted((-round(v * phi[at[item], at[other]], 9), other) for other, v in own.items())
            want |= {(user, item, k + 1): (other, -c) for k, (c, other) in enumerate(parts[:3])}
    got = {(r["user_id"], r["item_id"], r["place"]): (r["rated_item"], r["contribution"]) for r in __spark_entry__.queries()["explain_brands_all"](spark, SMALL).collect()}
    assert got.keys() == want.keys() and {u for u, _, _ in got} == set(by_user)
    assert all(got[k][0] == want[k][0] and abs(got[k][1] - want[k][1]) < 1e-5 for k in want)
    some = {tuple(r) for r in __spark_entry__.queries()["explain_brands"](spark, SMALL).collect()}
    assert some <= {(*k[:2], v[0], k[2], v[1]) for k, v in got.items()}


def test_every_vector_meets_every_other(spark):
    table = spark.read.parquet(f"{SMALL}/embeddings.parquet")
    rows = sorted((r["vec_id"], r["embedding"]) for r in table.select("vec_id", "embedding").collect())
    x = np.array([v for _, v in rows], np.float64)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    s = x @ x.T
    want = {}
    for a, (i, _) in enumerate(rows):
        best = sorted((-round(s[a, b], 9), j) for b, (j, _) in enumerate(rows) if b != a)[:20]
        want |= {(i, k + 1): (j, -v) for k, (v, j) in enumerate(best)}
    repeated = table.unionByName(table.where("vec_id < 40"))
    for got in (__spark_entry__.queries()["sim_vector_embeddings_top20"](spark, SMALL), proximity.vector_top(repeated, "vec_id", "embedding", 20, block=60)):
        found = {(r["i"], r["rank"]): (r["j"], r["v"]) for r in got.collect()}
        assert found.keys() == want.keys() and max(i for i, _ in found) >= 60
        assert all(found[k][0] == want[k][0] and abs(found[k][1] - want[k][1]) < 1e-5 for k in want)
    assert proximity.vector_top(table.where("false"), "vec_id", "embedding").count() == 0


def test_range_windows_round_to_whole_seconds_as_their_sql(spark, tmp_path):
    rows = [(1, "2024-01-01 00:00:00.400000"), (2, "2024-01-02 00:00:00.600000"), (3, "2024-01-02 00:00:01.500000"), (4, "2024-01-03 00:00:02.400000")]
    table = spark.createDataFrame([(i, t, 7) for i, t in rows], "event_id long, t string, user_id long").selectExpr("event_id", "CAST(t AS TIMESTAMP_NTZ) AS ts", "user_id")
    table.write.parquet(f"{tmp_path}/events.parquet")
    # seconds 0, 86401, 86402 and 172802: the nearest ones
    assert dict(map(tuple, __spark_entry__.queries()["op_window_range"](spark, str(tmp_path)).collect())) == {1: 1, 2: 1, 3: 2, 4: 2}


def test_examples_are_of_the_given_events(spark):
    queries, events = __spark_entry__.queries(), spark.read.parquet(f"{SMALL}/events.parquet")
    doubled = queries["op_recursive_cte"](spark, SMALL).collect()
    assert sum(r["f"] for r in doubled if r["n"] == 1) == events.count() and max(r["n"] for r in doubled) == 12
    users = {r["user_id"] for r in VIEWS["event_keys"](spark, SMALL).where("item_id BETWEEN 1 AND 5").select("user_id").collect()}
    assert {r["user_id"] for r in queries["worked_example"](spark, SMALL).collect()} <= users and users
    newest = events.where("event_id % 4 = 0").selectExpr("max(ts)").first()[0]
    rows = [(r["event_id"], r["ts"]) for r in events.collect()]
    hour = lambda t: t.replace(minute=0, second=0, microsecond=0)
    want: dict = {}
    for k, t in rows:
        late = (newest - hour(t)).total_seconds() >= 3 * 3600
        if k % 4 == 0 or k % 4 == 1 and (newest - t).total_seconds() < 3600 or k % 4 == 2 and not late:
            want[hour(t)] = want.get(hour(t), 0) + 1
    assert {r["start"]: r["n"] for r in queries["stream_late_rows"](spark, SMALL).collect()} == want
