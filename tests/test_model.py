import numpy as np
import pytest

from proxrec.operators import evaluation, experiments, gram, kernels, model, proximity
from proxrec.operators.model import ModelSpec, fit
from proxrec.operators.ratings import canonical

ROWS = [(u, i, float(1 + (u * 7 + i * 3) % 5)) for u in range(20) for i in range(8) if (u * 5 + i * 11) % 3]


@pytest.fixture(scope="module")
def ratings(spark):
    return spark.createDataFrame(ROWS, "user_id long, item_id long, rating double")


def matrix():
    r = np.zeros((20, 8))
    for u, i, x in ROWS:
        r[u, i] = x
    return r


def test_truncated_svd_is_the_model_at_d1(ratings):
    _, _, vt = np.linalg.svd(matrix())
    fitted = model.tsvd(ratings, 2)
    assert np.abs(fitted.phi() - vt[:2].T @ vt[:2]).max() < 1e-8


@pytest.mark.parametrize("d", [-1.0, 0.0, 0.4])
def test_rescaled_identity_holds_for_spaces_not_scores(ratings, d):
    own, other = fit(ratings, ModelSpec("cosine", d, 2)), model.tsvd(model.rescaled(ratings, d), 2)
    assert np.abs(own.phi() - other.phi()).max() < 1e-8


def test_recommend_by_hand_and_blocks(ratings, spark):
    fitted = fit(ratings, ModelSpec("cosine", 0.4, 2))
    blocks = fit(ratings, ModelSpec("cosine", 0.4, 2, form="blocks"))
    assert np.abs(fitted.phi() - blocks.phi()).max() < 1e-6
    scores = matrix() @ fitted.phi()
    got = {}
    for r in model.recommend(fitted, ratings, 3).collect():
        got.setdefault(r["user_id"], []).append(r["item_id"])
    for u in range(20):
        free = [i for i in range(8) if matrix()[u, i] == 0]
        assert got.get(u, []) == sorted(free, key=lambda i: (-round(scores[u, i], 9), i))[:3]


def test_save_and_load(ratings, spark, tmp_path):
    fitted = fit(ratings, ModelSpec("cosine", 0.4, 2))
    fitted.save(spark, str(tmp_path / "m"))
    back = model.LatentModel.load(spark, str(tmp_path / "m"))
    assert np.allclose(back.phi(), fitted.phi()) and back.spec == fitted.spec


def test_large_models_keep_their_norms(spark, tmp_path):
    """5001 items: nothing changes by size when a model is saved, loaded and used."""
    m = 5001
    fitted = model.LatentModel(ModelSpec(f=2), list(range(m)), np.ones(m), np.random.default_rng(1).standard_normal((m, 2)), np.ones(2), model.linalg.Trace())
    own = spark.createDataFrame([(1, 7, 2.0), (2, 4999, 1.0)], "user_id long, item_id long, rating double")
    before = sorted(map(tuple, model.recommend(fitted, own, 5).collect()))
    fitted.save(spark, str(tmp_path / "m"))
    back = model.LatentModel.load(spark, str(tmp_path / "m"))
    assert (back.norms == 1).all() and sorted(map(tuple, model.recommend(back, own, 5).collect())) == before and len(before) == 10


def test_items_in_blocks_give_the_same(ratings):
    fitted = fit(ratings, ModelSpec("cosine", 0.4, 3))
    want = sorted((r["user_id"], r["rank"], r["item_id"], round(r["score"], 9)) for r in model.recommend(fitted, ratings, 3).collect())
    got = sorted((r["user_id"], r["rank"], r["item_id"], round(r["score"], 9)) for r in model.recommend(fitted, ratings, 3, block_bytes=3 * 3 * 8).collect())
    assert len(model.item_blocks(fitted, 72)) == 3 and got == want


def test_partial_sums_meet_in_bounded_groups(ratings, spark, monkeypatch):
    """Many tasks and small chunks: the tree of sums equals one sum, and no task reads more than FAN_IN values of a chunk."""
    users, items, row, column, value = model.triplets(ratings)
    rows = gram.pack_rows(ratings, model.item_index(spark, items)).repartition(13, "user_id")
    x = np.random.default_rng(0).standard_normal((len(items), 3))
    want = matrix().T @ (matrix() @ x)
    monkeypatch.setattr(gram, "DRIVER_SUMS", 0)
    monkeypatch.setattr(gram, "CHUNK_BYTES", 48)
    op = gram.GramOperator(rows, len(items), np.ones(len(items)))
    assert op.tasks == 13 and np.allclose(op.gram(x), want)
    partial, _, chunk = op.partial(x)
    assert chunk == 2 and partial.groupBy("chunk").count().agg({"count": "max"}).first()[0] == 13
    plan = gram.summed(partial, 10_000)._jdf.queryExecution().toString()
    assert plan.count("FlatMapGroupsInPandas") >= 3  # 10,000 tasks: three levels of 32
    assert np.allclose(gram.GramOperator(rows, len(items), np.ones(len(items))).apply(x), want)


def test_jaccard_pairs_stay_on_spark_beyond_the_driver(ratings, monkeypatch):
    want = fit(ratings, ModelSpec("jaccard", 0.4, 3))
    monkeypatch.setattr("proxrec.plans.planner.PAIR_ITEMS", 5)
    monkeypatch.setattr("proxrec.plans.planner.DENSE_ITEMS", 5)
    got = fit(ratings, ModelSpec("jaccard", 0.4, 3))
    assert got.trace.path == "block-subspace" and np.abs(got.phi() - want.phi()).max() < 1e-6


def test_relational_form_finds_several_factors(ratings):
    want = fit(ratings, ModelSpec("cosine", 0.4, 3))
    got = fit(ratings, ModelSpec("cosine", 0.4, 3, form="relational"))
    assert np.allclose(got.values, want.values, rtol=1e-6) and np.abs(got.phi() - want.phi()).max() < 1e-4


def test_given_pairs_and_other_scalings(ratings, spark):
    """A similarity given as pairs, by raters and by a joined weight, against the matrices."""
    r = matrix()
    norms, k = np.linalg.norm(r, axis=0), (r > 0).sum(0)
    cosine = (r.T @ r) / np.outer(norms, norms)
    lead = lambda a: np.linalg.eigh(a)[1][:, -2:] @ np.linalg.eigh(a)[1][:, -2:].T
    pairs = proximity.cosine_pairs(ratings)
    for form in ("auto", "blocks"):
        got = fit(ratings, ModelSpec("pairs", 0.4, 2, form=form), pairs=pairs)
        assert np.abs(got.phi() - lead(np.outer(norms**0.4, norms**0.4) * cosine)).max() < 1e-6
    weights = spark.createDataFrame([(i, 1.0 + i) for i in range(8)], "item_id long, w double")
    for scaling, s, more in ((proximity.CountScaling(0.5), k**0.5, None), (proximity.PropensityScaling("w", -1.0), 1 / (1.0 + np.arange(8)), weights)):
        for form in ("auto", "blocks"):
            got = fit(ratings, ModelSpec("cosine", 9.0, 2, form=form), scaling=scaling, weights=more)
            assert np.abs(got.phi() - lead(np.outer(s, s) * cosine)).max() < 1e-6
    with pytest.raises(ValueError):
        fit(ratings, ModelSpec("pairs", 0.4, 2))


def test_content_pairs_are_symmetric(spark):
    table = spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet")
    rows = {(r["i"], r["j"]): r["v"] for r in proximity.neighbour_pairs(table, "vec_id", "embedding", 3).collect()}
    assert all(abs(rows[j, i] - v) < 1e-12 for (i, j), v in rows.items()) and all(rows[i, i] == 1 for i, _ in rows)


def test_core_goes_on_until_stable(spark):
    """A chain that loses one item and one user a round takes more rounds than any fixed number."""
    from proxrec.operators.ratings import core

    rows = [(u, i, 1.0) for u in range(30) for i in (u, u + 1)]
    chain = spark.createDataFrame(rows, "user_id long, item_id long, rating double")
    assert core(chain, 2, 2).count() == 0


@pytest.mark.parametrize("kind", list(kernels.GRID))
def test_dense_graph_equals_the_solvers(ratings, kind):
    """Every kernel and parameter by the decomposition equals the one by products with the graph; a second component and a lone item included."""
    rows = [(u, i) for u, i, _ in ROWS] + [(20, 8), (21, 9), (20, 9)]
    row, column = map(np.array, zip(*rows, strict=True))
    g = kernels.Graph(row, column, np.ones(len(row)), 22, 11)
    dense, who = kernels.DenseGraph(g), np.arange(22)
    for how in kernels.GRID[kind]:
        want, got = kernels.user_rows(g, kind, who, **how), dense.rows(kind, who, **how)
        live = g.degree[22:] > 0
        assert np.abs(want[:, live] - got[:, live]).max() < 1e-6 * max(1, np.abs(want).max()), how


def test_ranks_of_the_harness_equal_ranked_lists(ratings):
    """The packed ranks equal those of the plain lists, for latent, kernel and popularity scores."""
    scenario = evaluation.Standard(0.3)
    prepared = experiments.prepare(scenario, ratings, 3)
    lists = experiments.lists_of(prepared)
    train, cases = scenario.split(ratings)
    assert lists.count() == evaluation.candidates(cases, ratings, 3).count() and cases.count() > 3
    fitted = fit(prepared.train, ModelSpec("cosine", 0.4, 3))
    got = {r["case_id"]: r["hit"] for r in experiments.latent_hits(prepared, "x", [("d=0.4", fitted)], [1, 3]).where("setting = 'd=0.4 f=3'").collect()}
    want = {r["case_id"]: r["hit"] for r in experiments.scored_hits(model.score_pairs(fitted, prepared.train, lists), "x", "y").collect()}
    assert got == want and len(got) == cases.count()
    own = experiments.Proximities(prepared.train, "cosine").fit(0.4, 3)
    assert np.abs(own.phi() - fitted.phi()).max() < 1e-8
    grid = {"forest": [{}], "commute": [{"damping": 0.5}]}
    key = lambda df: sorted((r["method"], r["setting"], r["case_id"], r["hit"]) for r in df.collect())
    assert key(experiments.kernel_methods(prepared, grid)) == key(experiments._kernel_lists(prepared, grid))
    table = {(r["measure"], r["k"]): r["value"] for r in experiments.measures(experiments.plain_methods(prepared).where("method = 'popularity'"), ("method",)).collect()}
    plain = evaluation.ranked(kernels.popularity(prepared.train, lists.drop("tail")))
    assert abs(table["mrr", 0] - evaluation.mrr(plain).first()["mrr"]) < 1e-6
    assert all(abs(table["recall", r["k"]] - r["recall"]) < 1e-6 and abs(table["precision", r["k"]] - r["precision"]) < 1e-6 for r in evaluation.recall_at(plain).collect())
    assert all(abs(table["ndcg", r["k"]] - r["ndcg"]) < 1e-6 for r in evaluation.ndcg_at(plain).collect())
    assert all(abs(table["rscore", int(r["half_life"])] - r["rscore"]) < 1e-6 for r in evaluation.rscore(plain, [2.0, 20.0]).collect())
    best = experiments.tuned(experiments.latent_methods(prepared, [0.2, 0.4], [1, 2], ("cosine",)))
    assert best.select("setting").distinct().count() == 1


def test_random_order_is_independent_of_the_split(ratings):
    """Held-out items have small hashes under the split's seed; a random ranking must not see that."""
    _, probe = evaluation.probe_split(ratings, 0.3)
    mean = kernels.random_rank(probe.select("user_id", "item_id")).agg({"score": "avg"}).first()[0]
    assert mean > 0.35


def test_head_items_equal_the_running_sum(ratings):
    counts = {}
    for _, i, _ in ROWS:
        counts[i] = counts.get(i, 0) + 1
    for share in (0.1, 1 / 3, 0.9):
        before, want = 0, {}
        for i in sorted(counts, key=lambda i: (-counts[i], i)):
            if before < len(ROWS) * share:
                want[i] = (counts[i], before)
            before += counts[i]
        assert {r["item_id"]: (r["n"], r["before"]) for r in evaluation.head_items(ratings, share).collect()} == want


def test_kernels_equal_inverses(ratings):
    users, items, row, column, value = model.triplets(ratings)
    g = kernels.Graph(row, column, np.ones(len(value)), len(users), len(items))
    n = g.n + g.m
    a = g.adjacent(np.eye(n))
    lap = np.diag(a.sum(1)) - a
    who = np.arange(g.n)
    assert np.allclose(kernels.user_rows(g, "forest", who), np.linalg.inv(np.eye(n) + lap)[: g.n, g.n :], atol=1e-8)
    assert np.allclose(kernels.user_rows(g, "lapinv", who), np.linalg.pinv(lap)[: g.n, g.n :], atol=1e-8)
    assert np.allclose(kernels.user_rows(g, "commute", who, damping=0.9), np.linalg.inv(np.diag(a.sum(1)) - 0.9 * a)[: g.n, g.n :], atol=1e-8)
    assert np.abs(kernels.user_rows(g, "diffusion", who, t=1)).max() == 0


def test_disconnected_graph_scores_zero_across():
    g = kernels.Graph(np.array([0, 1]), np.array([0, 1]), np.ones(2), 2, 2)
    assert np.allclose(kernels.user_rows(g, "lapinv", np.array([0])), [[-0.25, 0.0]])


def test_measures_by_hand(spark):
    lists = spark.createDataFrame([("a", i, 1.0 if i == 2 else 0.0, i) for i in range(1, 6)] + [("b", i, 0.0, i) for i in range(1, 6)], "case_id string, item_id int, rel double, rank int")
    assert {r["k"]: r["recall"] for r in evaluation.recall_at(lists, 3).collect()} == {1: 0.0, 2: 0.5, 3: 0.5}
    assert evaluation.mrr(lists).first()["mrr"] == 0.25
    assert abs({r["k"]: r["ndcg"] for r in evaluation.ndcg_at(lists, 3).collect()}[2] - np.log2(3) / np.log2(4) / 2) < 1e-12
    assert evaluation.rscore(lists, [2.0]).first()["rscore"] == 0.25
    with pytest.raises(ValueError):
        evaluation.rscore(lists, [1.0])


def test_split_is_disjoint_and_negatives_unrated(ratings):
    train, probe = evaluation.probe_split(ratings, 0.3)
    assert train.count() + probe.count() == len(ROWS)
    lists = evaluation.candidates(evaluation.test_cases(probe), ratings, 3)
    assert lists.where("NOT is_target").join(ratings, ["user_id", "item_id"]).count() == 0
    assert evaluation.community(ratings, 0.33).join(evaluation.community(ratings, 0.66), ["user_id", "item_id"], "left_anti").count() == 0


def test_tune_shares_one_solve_and_best_of(ratings, spark):
    grid = model.tune(ratings, ["cosine", "jaccard"], [0.2, 0.4], [1, 3], lambda m: float(m.values.sum()))
    assert len(grid) == 8 and all(a["value"] <= b["value"] for a, b in zip(grid[::2], grid[1::2], strict=True))
    rows = spark.createDataFrame([("a", "x", 0.1), ("a", "y", 0.3), ("b", "z", 0.2)], "method string, setting string, value double")
    assert {tuple(r) for r in evaluation.best_of(rows).collect()} == {("a", 0.3, "y"), ("b", 0.2, "z")}


@pytest.mark.parametrize("form", ["local", "blocks"])
@pytest.mark.parametrize("kind", ["cosine", "pearson", "jaccard"])
def test_forms_agree(ratings, kind, form):
    want = fit(ratings, ModelSpec(kind, 0.4, 1))
    assert np.abs(fit(ratings, ModelSpec(kind, 0.4, 1, form=form, solver="auto" if form == "blocks" and kind != "jaccard" else "lanczos")).phi() - want.phi()).max() < 1e-6


def test_new_users_and_tail(ratings):
    thin, chosen = evaluation.new_users(ratings, 3, 4, 0.95)
    assert chosen.count() == 3 and thin.count() < len(ROWS)
    cases = evaluation.test_cases(evaluation.probe_split(ratings, 0.5)[1])
    assert evaluation.tail_cases(cases, ratings).join(evaluation.head_items(ratings), "item_id").count() == 0


def test_bad_input(spark):
    twice = spark.createDataFrame([(1, 1, 2.0), (1, 1, 3.0)], "u long, i long, x double")
    assert canonical(twice, "u", "i", "x").first()["rating"] == 5.0
    with pytest.raises(Exception, match="negative"):
        canonical(spark.createDataFrame([(1, 1, -2.0)], "u long, i long, x double"), "u", "i", "x").collect()


def test_entry_has_its_functions(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0 and set(e.oracle_sql()) <= set(e.queries())


@pytest.mark.parametrize("kind", list(kernels.GRID))
def test_best_of_a_kernel_within_little_memory(spark, monkeypatch, kind):
    """Lists by small blocks of users and edges equal the ranking of every score, and no vector over all nodes is wider than its share of the bytes."""
    draw = np.random.default_rng(4)
    rows = [(u, i, 1.0) for u in range(30) for i in range(25) if draw.random() < 0.25]
    ratings = spark.createDataFrame(rows, "user_id long, item_id long, rating double")
    own = {(u, i) for u, i, _ in rows}
    by_user: dict = {}
    for r in kernels.kernel_scores(ratings, kind).collect():
        if (r["user_id"], r["item_id"]) not in own:
            by_user.setdefault(r["user_id"], []).append((-round(r["score"], 6), r["item_id"]))
    users, items, g = kernels.gathered_graph(ratings, False)
    monkeypatch.setattr(kernels, "WORKER_CELLS", 0)
    monkeypatch.setattr(kernels, "VECTOR_BYTES", 8 * 12 * (g.n + g.m) * 3)
    monkeypatch.setattr(kernels, "EDGE_BYTES", 200)
    assert g.width() == 3 and g.r.at.dtype == np.int32 and g.r.value is None
    x = draw.standard_normal((g.m, 3))
    assert np.allclose(g.r.dot(x), g.r.dense() @ x) and np.allclose(g.r.tdot(x[: g.n] if g.m >= g.n else np.vstack([x, x])[: g.n]), g.r.dense().T @ np.vstack([x, x])[: g.n])
    got = kernels.kernel_top(ratings, kind, 4).collect()
    assert len(got) == 4 * len(users) and len(got[0]) == 4
    for r in got:
        assert abs(sorted(by_user[r["user_id"]])[r["rank"] - 1][0] + r["score"]) < 2e-6 and (r["user_id"], r["item_id"]) not in own


def test_a_fit_works_its_ratings_out_once(spark, monkeypatch):
    monkeypatch.setattr(model, "LOCAL_NNZ", 10)
    read = spark.sparkContext.accumulator(0)

    def counted(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    rows = [(u, i, float((u * i) % 5 + 1)) for u in range(20) for i in range(6) if (u + i) % 3]
    table = spark.createDataFrame(rows, "user_id long, item_id long, rating double")
    for kind in ("cosine", "jaccard"):
        before = read.value
        model.fit(table.mapInArrow(counted, table.schema), ModelSpec(kind, 0.4, 1, form="local"))
        assert read.value - before == len(rows)
    kept = table.persist()
    model.fit(kept, ModelSpec("cosine", 0.4, 1, form="local"))
    assert kept.storageLevel.useMemory  # the caller's own
    kept.unpersist()


def test_a_kernel_works_its_ratings_out_once(spark):
    """The ratings are counted, indexed and packed for the graph, but read from their source once; nothing of them stays."""
    read = spark.sparkContext.accumulator(0)

    def noted(batches):
        for batch in batches:
            read.add(batch.num_rows)
            yield batch

    rows = spark.createDataFrame([(u, i, 1.0) for u in range(12) for i in range(u % 3, 9)], "user_id long, item_id long, rating double").mapInArrow(noted, "user_id long, item_id long, rating double")
    assert kernels.kernel_top(rows, "forest", 3).count() and read.value == 96
    assert not rows.storageLevel.useDisk


def test_edges_out_of_order_are_those_in_order():
    rng = np.random.default_rng(3)
    at = rng.permutation(np.flatnonzero(rng.random(60) < 0.5))
    row, column, value = at // 10, at % 10, rng.random(len(at))
    dense = np.zeros((6, 10))
    dense[row, column] = value
    edges = kernels.Edges(row, column, value, (6, 10))
    assert np.allclose(edges.dense(), dense) and np.allclose(edges.dot(np.eye(10)), dense) and np.allclose(edges.tdot(np.eye(6)), dense.T)


def test_entropy_rows_hold_few_copies(monkeypatch):
    """Of the users' rows over all nodes and of their scores there are three arrays at a time, besides a step's vectors."""
    import tracemalloc

    rng = np.random.default_rng(5)
    n, m = 3000, 400
    monkeypatch.setattr(kernels, "EDGE_BYTES", 100_000)
    at = np.flatnonzero(rng.random(n * m) < 0.01)
    g = kernels.Graph(at // m, at % m, None, n, m)
    users = np.arange(300)
    g.width = lambda arrays=12: 8  # narrow steps
    tracemalloc.start()
    kernels.user_rows(g, "entropy", users, t=2)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 8 * len(users) * (2 * (n + m) + m) * 1.2


@pytest.mark.parametrize("value", [False, True])
def test_sums_by_groups_of_rows(monkeypatch, value):
    """Rows that go alone, full and part groups and empty rows give the matrix' products; a solve takes the users that its own vectors leave room for."""
    rng = np.random.default_rng(6)
    dense = (rng.random((40, 30)) < 0.3) * (rng.random((40, 30)) if value else 1.0)
    dense[[3, 39]], dense[:, 7], dense[5] = 0, 0, 1
    row, column = np.nonzero(dense)
    for rows, long, bytes_ in ((4, 9, 200), (512, 2048, 1_000_000), (7, 0, 1)):
        monkeypatch.setattr(kernels, "ROWS", rows)
        monkeypatch.setattr(kernels, "LONG", long)
        monkeypatch.setattr(kernels, "EDGE_BYTES", bytes_)
        edges, x, y = kernels.Edges(row, column, dense[row, column], (40, 30)), rng.random((30, 5)), rng.random((40, 5))
        assert np.allclose(edges.dot(x), dense @ x) and np.allclose(edges.tdot(y), dense.T @ y) and np.allclose(edges.dense(), dense)
        assert edges.own(5).tolist() == list(np.flatnonzero(dense[5]))
    g = kernels.Graph(row, column, None, 40, 30)
    monkeypatch.setattr(kernels, "VECTOR_BYTES", 8 * 12 * 70 * 3)
    assert g.width() == 3 and g.solved() == 5


def slow_graph(parts: int = 3, apart: bool = False) -> kernels.Graph:
    """Groups of users and items with few edges between them, or none."""
    rng = np.random.default_rng(8)
    n, m = 60, 45
    dense = rng.random((n, m)) < np.where(np.arange(n)[:, None] * parts // n == np.arange(m) * parts // m, 0.5, 0 if apart else 0.01)
    return kernels.Graph(*np.nonzero(dense), None, n, m)


@pytest.mark.parametrize(("kind", "how"), [("forest", {}), ("commute", {"damping": 0.99})])
def test_leading_columns_shorten_the_solves(kind, how):
    """The same entries after fewer products."""
    g, who, products = slow_graph(), np.arange(60), []
    plain = g.r.dot
    g.r.dot = lambda x: products.append(1) or plain(x)
    want, long = kernels.user_rows(g, kind, who, **how), len(products)
    g.near = kernels.leading(g, *kernels.system(g, kind, **how), k=8)
    products.clear()
    got = kernels.user_rows(g, kind, who, **how)
    assert np.abs(got - want).max() < 1e-11 and len(products) < 0.75 * long


@pytest.mark.parametrize("apart", [False, True])
def test_leading_columns_shorten_the_singular_solves(spark, monkeypatch, apart):
    """The Laplacian's null vectors, one or several, are left to the centring; the query asks for the columns."""
    g, who, products = slow_graph(apart=apart), np.arange(60), []
    plain = g.r.dot
    g.r.dot = lambda x: products.append(1) or plain(x)
    want, long = kernels.user_rows(g, "lapinv", who), len(products)
    g.near = kernels.leading(g, *kernels.system(g, "lapinv"), k=8)
    products.clear()
    assert np.abs(kernels.user_rows(g, "lapinv", who) - want).max() < 1e-10 and len(products) < long
    asked = []
    monkeypatch.setattr(kernels, "WORKER_CELLS", 0)
    monkeypatch.setattr(kernels, "leading", lambda graph, *of, true=kernels.leading: asked.append(graph.n) or true(graph, *of))
    rows = spark.createDataFrame([(u, int(i), 1.0) for u in range(60) for i in g.r.own(u)], "user_id long, item_id long, rating double")
    got = {(r["user_id"], r["item_id"]): r["score"] for r in kernels.kernel_scores(rows, "lapinv").collect()}
    assert len(asked) == 1 and max(abs(got[u, i] - want[u, i]) for u, i in got) < 1e-10


@pytest.mark.parametrize("t", [1, 2])
def test_entropy_of_few_steps_goes_by_edges(monkeypatch, t):
    """No product takes a vector over all nodes for an item; the entries are those of the whole rows, whichever way an item's neighbours are found."""
    rng = np.random.default_rng(9)
    dense = rng.random((50, 40)) < 0.15
    dense[:, 3], dense[:, 4], dense[np.arange(50), np.arange(50) % 40] = 0, 1, 1
    n, m = dense.shape
    g = kernels.Graph(*np.nonzero(dense), None, n, m)
    z = kernels.averaged(g.backward, np.eye(n + m), t).T
    logs = np.log(np.maximum(z, 1e-12))
    want = (z @ logs.T + logs @ z.T)[:n, n:]
    monkeypatch.setattr(kernels.Graph, "backward", lambda *_: pytest.fail("a product over all nodes"))
    monkeypatch.setattr(kernels, "VECTOR_BYTES", 8 * 12 * (n + m) * 7)
    for followed in (0, 16, 1e9):
        monkeypatch.setattr(kernels, "FOLLOWED", followed)
        for users in (np.arange(n), np.array([7, 2, 49])):
            assert np.abs(kernels.user_rows(g, "entropy", users, t=t) - want[users]).max() < 1e-10


def test_entropy_takes_the_users_whose_scores_it_holds(spark, monkeypatch):
    rows = [(u, i, 1.0) for u in range(23) for i in range(9) if (u * i) % 4 != 1]
    ratings, asked = spark.createDataFrame(rows, "user_id long, item_id long, rating double"), []
    want = {(r["user_id"], r["item_id"]): r["score"] for r in kernels.kernel_scores(ratings, "entropy", t=2).collect()}
    monkeypatch.setattr(kernels, "WORKER_CELLS", 0)
    monkeypatch.setattr(kernels.Graph, "listed", lambda g: asked.append(g.m) or 5)
    got = {(r["user_id"], r["item_id"]): r["score"] for r in kernels.kernel_scores(ratings, "entropy", t=2).collect()}
    assert asked == [9] and got.keys() == want.keys() and max(abs(got[k] - want[k]) for k in want) < 1e-8
    assert kernels.kernel_scores(ratings, "entropy", t=3).count() == 23 * 9 and len(asked) == 1
