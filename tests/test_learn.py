import numpy as np
import pytest

from driftview.learn import closed_form, select
from driftview.learn.bulk import bulk_train, gradient
from driftview.learn.model import Model
from driftview.learn.multiclass import classify, classify_chain, largest_class, multiclass_certain, train_ovr
from driftview.learn.sgd import LOSSES, ScaledSgd, SgdTrainer
from driftview.operators.band import HolderPair, norm


def data(n=60, d=3, seed=1):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, d))
    return x, np.where(x @ np.arange(1, d + 1) + 0.3 >= 0, 1.0, -1.0)


@pytest.mark.parametrize("loss", ["hinge", "logistic", "squared"])
def test_losses_learn(loss):
    x, y = data(400)
    m = SgdTrainer(loss, 0.1, 1e-3).fit([(f, int(t)) for f, t in zip(x, y, strict=True)], 3, epochs=3)
    assert np.mean(np.sign(x @ m.w - m.b) == y) > 0.93


def test_sparse_and_scaled_steps_equal_dense_ones():
    x, y = data(50, 6)
    trainer = SgdTrainer("logistic", 0.5, 1e-2)
    dense = sparse = Model.zero(6)
    fast = ScaledSgd(trainer, Model.zero(6))
    fast.store()
    for f, t in zip(x, y, strict=True):
        pair = (np.arange(6), f)
        dense, sparse = trainer.step(dense, f, int(t)), trainer.step(sparse, pair, int(t))
        fast.step(*pair, int(t))
    assert np.allclose(dense.w, sparse.w) and dense.b == pytest.approx(sparse.b)
    assert np.allclose(fast.model().w, dense.w) and fast.distance() == pytest.approx(norm(dense.w, 2))


def test_closed_forms(spark):
    x, y = data()
    df = spark.createDataFrame([(*map(float, f), float(t), 2.0 if t > 0 else 1.0) for f, t in zip(x, y, strict=True)], "a double, b double, c double, y double, k double")
    a = np.column_stack([x, np.ones(len(x))])
    for l2, weight in ((0.0, None), (3.0, None), (0.0, "k")):
        k = np.where(y > 0, 2.0, 1.0) if weight else np.ones(len(y))
        ridge = np.diag([l2, l2, l2, 0.0])
        beta = np.linalg.solve((a * k[:, None]).T @ a + ridge, (a * k[:, None]).T @ y)
        m = closed_form.normal_equations(df, ["a", "b", "c"], "y", l2, weight)
        assert np.allclose(m.w, beta[:-1]) and m.b == pytest.approx(-beta[-1])


def test_leave_one_out_in_closed_form_equals_retraining():
    x, y = data(40)

    def train(p, q):
        b = np.column_stack([p, np.ones(len(p))])
        return closed_form.solve(b.T @ b, b.T @ q, 2.0)

    assert closed_form.loo_press(x, y, 2.0) == closed_form.loo_bruteforce(train, x, y)
    exact = [train(np.delete(x, k, 0), np.delete(y, k)).score(x[k]) for k in range(len(x))]
    assert np.allclose(closed_form.press(x, y, 2.0), exact)


def test_hinge_bound_is_an_upper_estimate():
    x, y = data(40)
    exact = closed_form.loo_bruteforce(lambda p, q: Model((w := closed_form.dual_hinge(p, q)[1])[:-1], -w[-1]), x, y)
    assert closed_form.loo_hinge_bound(x, y) >= exact


def test_method_choice(spark):
    x, y = data(30)
    batch = [(f, int(t)) for f, t in zip(x, y, strict=True)]
    rows = select.select_method(spark, batch, 3).collect()
    assert [r["rank"] for r in sorted(rows, key=lambda r: r["loo_error"])] == sorted(r["rank"] for r in rows)
    assert {r["method"] for r in rows} == set(select.METHODS)
    sparse = [((np.arange(3), f), t) for f, t in batch]
    assert dict(select.loo_errors(sparse, 3)) == pytest.approx(dict(select.loo_errors(batch, 3)))
    with pytest.raises(ValueError):
        select.get_method("forest")


def test_the_weighted_method_gives_both_classes_the_same_weight():
    assert select.balance(30, 10) == (40 / 60, 2.0) and select.balance(0, 5) == (1.0, 0.5)
    rng = np.random.default_rng(1)
    rows = [(rng.normal(1.0 if k % 8 == 0 else -1.0, 1.5, 2), 1 if k % 8 == 0 else -1) for k in range(800)]
    share = [np.mean([m.score(f) >= 0 for f, y in rows if y > 0]) for m in (select.method_for(n, 700, 100, eta0=0.02).fit(rows, 2) for n in ("ols", "weighted"))]
    assert share[1] > share[0] + 0.1


def test_leave_one_out_over_rows(spark):
    x, y = data(40)
    df = spark.createDataFrame([(k, *map(float, f), float(t)) for k, (f, t) in enumerate(zip(x, y, strict=True))], "id long, a double, b double, c double, y double")
    for l2 in (0.0, 2.0):
        got = [r["score"] for r in closed_form.press_rows(df, ["a", "b", "c"], "y", l2).orderBy("id").collect()]
        assert np.allclose(got, closed_form.press(x, y, l2))


@pytest.mark.parametrize("loss", ["hinge", "logistic", "squared"])
def test_whole_batch_steps(spark, loss):
    x, y = data(300)
    df = spark.createDataFrame([(f.tolist(), int(t)) for f, t in zip(x, y, strict=True)] + [(None, 1), ([1.0, 1.0, 1.0], None)], "f array<double>, label int")
    by_w, by_b, n = gradient(df.where("f is not null and label is not null"), Model(np.array([0.1, -0.2, 0.3]), 0.1), loss)
    z = x @ [0.1, -0.2, 0.3] - 0.1
    g = np.array([LOSSES[loss](t, s) for t, s in zip(y, z, strict=True)])
    assert n == 300 and np.allclose(by_w, (g[:, None] * x).mean(0)) and by_b == pytest.approx(-g.mean())
    m = bulk_train(df, 3, loss, rounds=8)
    assert np.mean(np.where(x @ m.w - m.b >= 0, 1, -1) == y) > 0.85
    assert bulk_train(df.limit(0), 3).round == 0


def test_classes_beyond_two(spark):
    rng = np.random.default_rng(3)
    centres = {"a": (3, 0), "b": (-3, 3), "c": (0, -4)}
    rows = [(k, (np.array(centres[c]) + rng.normal(0, 0.4, 2)).tolist(), c) for k, c in enumerate("abc" * 40)]
    df = spark.createDataFrame(rows, "id long, f array<double>, label string")
    stored = train_ovr([(np.array(f), c) for _, f, c in rows[:60]], "abc", SgdTrainer("hinge", 0.3, 1e-3), 2)
    models = train_ovr([(np.array(f), c) for _, f, c in rows], "abc", SgdTrainer("hinge", 0.3, 1e-3), 2)
    truth = {k: c for k, _, c in rows}
    got = {r["id"]: r["class"] for r in classify(df, models, "abc").collect()}
    assert np.mean([got[k] == truth[k] for k in truth]) > 0.95
    chain = {r["id"]: r["class"] for r in classify_chain(df, models, "abc").collect()}
    assert np.mean([chain[k] == truth[k] for k in truth]) > 0.9
    from driftview.learn.multiclass import scores

    largest = max(norm(np.array(f), 2) for _, f, _ in rows)
    sure = df.select("id", scores(df, stored).alias("scores")).select("id", multiclass_certain(stored, models, "abc", largest, HolderPair()).alias("c")).collect()
    assert all(r["c"] in (None, got[r["id"]]) for r in sure) and any(r["c"] for r in sure)
    assert largest_class(df) == "a"
