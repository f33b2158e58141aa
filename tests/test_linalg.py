import numpy as np
import pytest

from proxrec.operators import linalg
from proxrec.operators.model import local_operator


def problem(seed=0, n=60, m=25, d=0.4, kind="cosine"):
    rng = np.random.default_rng(seed)
    dense = rng.integers(1, 6, (n, m)) * (rng.random((n, m)) < 0.3)
    row, column = np.nonzero(dense)
    op, norms = local_operator(row, column, dense[row, column].astype(float), n, m, kind, d)
    return dense.astype(float), op, norms


@pytest.mark.parametrize("kind", ["cosine", "pearson", "jaccard"])
@pytest.mark.parametrize("d", [-1.0, 0.0, 0.4, 1.0])
def test_operator_equals_explicit_matrix(kind, d):
    r, op, norms = problem(kind=kind, d=d)
    if kind == "cosine":
        k = (r.T @ r) / np.outer(norms, norms)
    elif kind == "pearson":
        k = np.corrcoef(r.T)
    else:
        b = (r > 0).astype(float)
        both = b.T @ b
        k = both / (b.sum(0)[:, None] + b.sum(0)[None] - both)
    a = np.outer(norms**d, norms**d) * k
    x = np.random.default_rng(3).standard_normal((len(a), 2))
    assert np.allclose(op.apply(x), a @ x)


@pytest.mark.parametrize("solver", ["lanczos", "twice", "thick", "block", "filtered", "filter"])
def test_solvers_equal_dense(solver):
    _, op, _ = problem()
    want = linalg.dense_eigh(op.apply(np.eye(op.m)), 3)
    if solver == "thick":
        got = linalg.thick_restart_lanczos(op, 3)
    elif solver == "block":
        got = linalg.block_subspace(op, 3, oversample=6, passes=60)
    elif solver == "filtered":
        got = linalg.filtered_lanczos(op, 3, 1e-10)
    elif solver == "filter":
        inner = linalg.dense_eigh(op.apply(np.eye(op.m)), op.m).values
        got = linalg.lanczos(linalg.FilteredOperator(op, inner[-1], inner[6], 4), 3)
    else:
        got = linalg.lanczos(op, 3, reorth={"lanczos": "full"}.get(solver, solver))
    assert np.abs(got.vectors @ got.vectors.T - want.vectors @ want.vectors.T).max() < 1e-6
    if solver != "filter":
        assert np.allclose(got.values, want.values)


def test_residual_estimate_is_the_true_residual():
    _, op, _ = problem()
    got = linalg.lanczos(op, 2, max_steps=8, check_every=1, tol=1e-30, allow_partial=True)
    true = np.linalg.norm(op.apply(got.vectors) - got.vectors * got.values, axis=0)
    assert np.allclose(true, got.trace.residuals, atol=1e-8)


def test_all_factors_and_breakdown():
    _, op, _ = problem(m=6)
    got = linalg.lanczos(op, 10)
    assert np.allclose(got.vectors @ got.vectors.T, np.eye(6))
    identity = linalg.DenseOperator(np.diag([2.0, 2.0, 2.0, 1.0]))
    got = linalg.lanczos(identity, 3, check_every=1)
    assert np.allclose(got.vectors @ got.vectors.T, np.diag([1, 1, 1, 0]), atol=1e-8)


def test_without_reorthogonalisation_the_basis_degrades():
    """Three-term steps alone lose orthogonality once values converge, and then find copies of them; full steps do not."""
    spectrum = np.concatenate([[100.0, 90.0, 80.0], np.linspace(1, 0.1, 297)])
    op = linalg.DenseOperator(np.diag(spectrum))
    plain = linalg.lanczos(op, 6, max_steps=120, tol=0, reorth="none", allow_partial=True)
    full = linalg.lanczos(op, 6, max_steps=120, tol=0, allow_partial=True)
    off = lambda e: np.abs(e.vectors.T @ e.vectors - np.eye(6)).max()
    assert off(full) < 1e-10 and np.allclose(full.values[:3], [100, 90, 80]) and full.values[3] < 1.01
    assert off(plain) > 1e-2 and plain.values[1] > 99  # a ghost of the largest value


def flat(m=400):
    return linalg.DenseOperator(np.diag(np.concatenate([[2.0], 1 + np.linspace(0, 1e-3, m - 1)])))


def test_unfinished_solves_are_errors():
    for solve in (
        lambda **k: linalg.block_subspace(flat(), 20, oversample=2, passes=3, **k),
        lambda **k: linalg.thick_restart_lanczos(flat(), 20, width=24, restarts=2, **k),
        lambda **k: linalg.lanczos(flat(), 20, max_steps=30, **k),
    ):
        with pytest.raises(ArithmeticError):
            solve()
        assert max(solve(allow_partial=True).trace.residuals) > 1e-6
    done = linalg.lanczos(flat(120), 20)  # goes on until the basis spans the space
    assert max(done.trace.residuals) < 1e-7


def test_smaller_product_gives_the_same_factors():
    w = np.random.default_rng(2).standard_normal((12, 40))
    for a in (w, w.T):
        got, want = linalg.factor_eigh(a, 5), linalg.dense_eigh(a.T @ a, 5)
        assert np.allclose(got.values, want.values) and np.allclose(got.vectors @ got.vectors.T, want.vectors @ want.vectors.T)


def test_zero_norm_items_leave():
    from proxrec.operators.model import weights_of

    assert weights_of(np.array([0.0, 2.0]), -1.0).tolist() == [0.0, 0.25]


def test_factors_above_a_cut_are_all_found(spark):
    from proxrec.operators.gram import relational_subspace
    from proxrec.operators.model import ModelSpec, fit
    from proxrec.operators.ratings import item_stats

    dense = np.abs(np.random.default_rng(5).standard_normal((60, 6)) @ np.random.default_rng(6).standard_normal((6, 20)))
    rows = [(u, i, float(dense[u, i])) for u in range(60) for i in range(20)]
    ratings = spark.createDataFrame(rows, "user_id long, item_id long, rating double")
    g = np.linalg.norm(dense, axis=0) ** -0.6
    values, vectors = np.linalg.eigh(g[:, None] * (dense.T @ dense) * g)
    least = float((values[-6] + values[-7]) / 2)  # six above, where the search begins with three
    want = vectors[:, -6:] @ vectors[:, -6:].T
    for solver in ("dense", "lanczos", "block"):
        fitted = fit(ratings, ModelSpec("cosine", 0.4, 3, solver=solver, form="local", least=least))
        assert len(fitted.values) == 6 and np.abs(fitted.phi() - want).max() < 1e-6
    found, relation = relational_subspace(ratings, item_stats(ratings).selectExpr("item_id", "pow(norm, -0.6D) AS g"), 3, least=least)
    v = np.array([list(r)[1:] for r in relation.orderBy("item_id").collect()])
    assert len(found) == 6 and np.abs(v @ v.T - want).max() < 1e-3


def test_ratings_beyond_the_driver_stay_on_spark(spark, monkeypatch):
    from proxrec.operators import model

    draw = np.random.default_rng(8)
    rows = [(u, i, float(draw.integers(1, 6))) for u in range(80) for i in range(12) if draw.random() < (i + 2) / 16]
    ratings = spark.createDataFrame(rows, "user_id long, item_id long, rating double")
    want = {k: model.fit(ratings, model.ModelSpec(k, 0.4, 2, form="local")) for k in ("cosine", "pearson", "jaccard")}
    monkeypatch.setattr(model, "LOCAL_NNZ", 0)
    monkeypatch.setattr(model, "triplets", lambda _: (_ for _ in ()).throw(AssertionError("ratings on the driver")))
    for kind, one in want.items():
        for solver in ("dense", "lanczos", "filtered"):
            other = model.fit(ratings, model.ModelSpec(kind, 0.4, 2, form="local", solver=solver))
            assert other.items == one.items and np.allclose(other.values, one.values) and np.abs(other.phi() - one.phi()).max() < 1e-8
    assert model.choose_operator(10**6, 25, 10**8).form == "dense"


def test_block_solve_keeps_to_its_bytes(monkeypatch):
    from proxrec.operators import linalg

    m, f = 400, 5
    r = np.random.default_rng(3).standard_normal((900, m)) * np.linspace(3, 1, m)
    a = r.T @ r
    widest, plain = [0], linalg.np.hstack

    def watched(parts):
        out = plain(parts)
        widest[0] = max(widest[0], out.shape[1])
        return out

    monkeypatch.setattr(linalg, "BLOCK_BYTES", 8 * m * 8)
    monkeypatch.setattr(linalg, "BASIS_BYTES", 16 * m * 30)
    monkeypatch.setattr(linalg.np, "hstack", watched)
    found = linalg.block_subspace(linalg.DenseOperator(a), f, tol=1e-8)
    monkeypatch.undo()
    want = np.linalg.eigvalsh(a)[::-1][:f]
    assert np.allclose(found.values, want) and widest[0] <= 30 + 9 and max(found.trace.residuals) <= 1e-7 * want[0]

def test_relational_form_parts_close_values_at_the_cut(spark):
    from proxrec.operators.gram import relational_subspace

    # groups of two items of their own users: every group has one value, 1 % above that of the next
    rows = [(u, i, (100 * 1.005**group if u % 2 == i % 2 else 1.0)) for group in range(16) for u in (2 * group, 2 * group + 1) for i in (2 * group, 2 * group + 1)]
    ratings = spark.createDataFrame(rows, "user_id int, item_id int, rating double")
    r = np.zeros((32, 32))
    for u, i, x in rows:
        r[u, i] = x
    at, xi = np.linalg.eigh(r.T @ r)
    least = float(at[-9:-7].mean())
    v = xi[:, at > least]
    found, relation = relational_subspace(ratings, ratings.selectExpr("item_id", "1D AS g").distinct(), 3, rounds=40, least=least)
    got = relation.toPandas().sort_values("item_id").drop(columns="item_id").to_numpy()
    assert len(found) == v.shape[1] and np.abs(got @ got.T - v @ v.T).max() < 1e-8
