import numpy as np
import pytest

from tensorlane import kernels
from tensorlane.operators import featurizers as fz
from tensorlane.operators.base import UnknownSignature, lower
from tensorlane.pipeline import Builder, chain, diagnose, fold_linear, inject_selection, push_selection, rewrite
from tensorlane.trees import generate

NAMES = [f"x{k}" for k in range(5)]
X = {n: v for n, v in zip(NAMES, np.random.default_rng(4).normal(size=(5, 31)), strict=True)}
SCALE = ("sc.standard", {"mu": np.arange(5.0), "sd": np.arange(1.0, 6.0)})


def test_selection_reaches_the_columns():
    dag = chain(NAMES, SCALE, ("sel.columns", {"kept": [3, 1]}))
    less = push_selection(dag)
    assert less.live_columns() == ["x1", "x3"] and np.array_equal(less.run(X), dag.run(X))


def test_a_norm_blocks_the_selection():
    dag = chain(NAMES, SCALE, ("sc.normalize", {}), ("sel.columns", {"kept": [2]}))
    less = push_selection(dag)
    assert less.live_columns() == NAMES and np.array_equal(less.run(X), dag.run(X)) and any("stays above" in n for n in less.notes)


def test_products_absorb_the_selection():
    dag = chain(NAMES, ("poly.features", {"terms": fz.polynomial_terms(5)}), ("sel.columns", {"kept": [0, 2, 7]}))
    less = push_selection(dag)
    assert len(less.live_columns()) < 5 and np.array_equal(less.run(X), dag.run(X))


def test_branches_and_strings():
    b = Builder()
    numbers = b.then(b.pick(NAMES), "sc.standard", mu=np.zeros(5), sd=np.ones(5))
    words = b.strings("s", "cat.onehot", vocabulary=["a", "b", "c"])
    w = np.zeros((8, 1))
    w[[1, 6], 0] = 1.0, -2.0
    b.then([numbers, words], "lin.linear", w=w, b=np.zeros(1), mode="margin")
    dag = b.build()
    less = rewrite(dag, ("inject", "push"))
    data = {**X, "s": ["b", None, "zz"] + ["b"] * 28}
    assert set(less.live_columns()) == {"x1", "s"} and np.array_equal(less.run(data), dag.run(data))


def test_injection_for_trees_and_folding():
    f = generate(5, 3, 2, [[0.0], [], [0.5], [], []], 2)
    dag = chain(NAMES, ("trees.forest", {"spec": f}))
    less = rewrite(dag, ("inject", "push"))
    assert set(less.live_columns()) <= {"x0", "x2"} and np.array_equal(less.run(X), dag.run(X))
    w = np.random.default_rng(1).normal(size=(5, 2))
    dag = chain(NAMES, SCALE, ("dec.project", {"mu": np.ones(5), "w": w}), ("lin.linear", {"w": np.ones((2, 1)), "b": np.zeros(1)}))
    folded = fold_linear(dag)
    assert len(folded.nodes) == 2 and np.allclose(folded.run(X), dag.run(X), rtol=1e-9)


def test_model_of_its_bias_alone():
    dag = chain(NAMES, ("lin.linear", {"w": np.zeros((5, 1)), "b": np.ones(1)}))
    less = push_selection(inject_selection(dag))
    assert len(less.live_columns()) == 1 and np.array_equal(less.run(X), dag.run(X))


def test_idioms_agree_with_their_naive_forms():
    x, s = np.random.default_rng(0).normal(size=(9, 4)), np.random.default_rng(1).normal(size=(3, 4))
    assert np.allclose(kernels.squared_distances(x, s), kernels.squared_distances_naive(x, s, 200))
    assert np.array_equal(kernels.interactions_outer(x), kernels.interactions_pairwise(x))
    words = ["LARGE-X", "LARGE", None, "größer", ""]
    forms = [fz.OneHot(["LARGE", "größer"], form=f).vector(words) for f in ("broadcast", "fixed", "lookup")]
    assert all(np.array_equal(f, forms[0]) for f in forms) and forms[0].tolist() == [[0, 0], [1, 0], [0, 0], [0, 1], [0, 0]]


def test_numbers_stay_finite():
    assert kernels.sigmoid(np.array([-1e4, 0.0, 1e4])).tolist() == [0.0, 0.5, 1.0]
    assert np.isfinite(kernels.softmax(np.array([[1e4, 0.0]]))).all()
    assert fz.Normalize().vector(np.zeros((1, 3))).tolist() == [[0, 0, 0]]


def test_errors_and_diagnoses():
    with pytest.raises(UnknownSignature):
        lower("no.such")
    with pytest.raises(ValueError):
        fz.OneHot(["a"], unknown="error").vector(["b"])
    tiny = chain(NAMES, ("trees.forest", {"spec": generate(1, 1, 2, [[0.0]] * 5, 2)}))
    assert len(diagnose(tiny, density=0.01)) == 2
