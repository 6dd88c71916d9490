import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from tensorlane import trees
from tensorlane.trees import CompiledForest, ForestSpec, generate, gemm_tensors, ptt_tensors, tree, tt_leaves, tt_tensors


def hand_tree():
    """Four decisions, five leaves of three classes."""
    e = np.eye(3)
    return tree([(0, 2.0, 1, 2), (1, 1.0, 4, 5), (2, 4.0, 3, 8), (1, 3.0, 6, 7), (e[0],), (e[1],), (e[1],), (e[0],), (e[2],)], 3)


def walk(t, x, cmp="<"):
    k = 0
    while t.left[k] != k:
        v, b = x[t.feature[k]], t.threshold[k]
        k = t.left[k] if (v < b if cmp == "<" else v <= b) else t.right[k]
    return k


def test_hand_checked_tensors():
    g = gemm_tensors(ForestSpec((hand_tree(),)))
    assert g.feature[0].tolist() == [0, 1, 2, 1] and g.threshold[0].tolist() == [2, 1, 4, 3]
    # leaves in node order: under n1, under n3, right of n2
    assert g.ancestry[0].tolist() == [[1, 1, -1, -1, -1], [1, -1, 0, 0, 0], [0, 0, 1, 1, -1], [0, 0, 1, -1, 0]]
    assert g.lefts[0].tolist() == [2, 1, 2, 1, 0]
    p = ptt_tensors(ForestSpec((hand_tree(),)))
    assert p.value[0].argmax(1).tolist() == [0, 0, 1, 1, 1, 0, 2, 2]


@pytest.mark.parametrize("strategy", ["gemm", "tt", "ptt"])
def test_hand_rows(strategy):
    f = CompiledForest(ForestSpec((hand_tree(),), classifier=True), strategy)
    label, _ = f.predict(np.array([[3.0, 2, 1], [1, 5, 9], [2, 0, 4]]))
    assert label.tolist() == [1, 1, 2]
    at_most = CompiledForest(ForestSpec((hand_tree(),), classifier=True, cmp="<="), strategy)
    assert at_most.predict(np.array([[2.0, 0, 4]]))[0].tolist() == [0]


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 10**6), st.integers(0, 6), st.sampled_from(["bagged", "tall", "balanced"]), st.sampled_from(["<", "<="]))
def test_strategies_reach_the_walkers_leaf(seed, depth, shape, cmp):
    f = generate(seed, 4, depth, [[0.0, 0.5, 1.0]] * 3, 3, shape, cmp=cmp)
    x = np.random.default_rng(seed).choice([-1.0, 0.0, 0.25, 0.5, 1.0, 2.0], (23, 3))
    want = np.mean([[t.value[walk(t, r, cmp)] for r in x] for t in f.trees], 0)
    for s in ("gemm", "tt", "ptt"):
        assert np.array_equal(CompiledForest(f, s).raw(x), want)
    assert np.array_equal(CompiledForest(f, "ptt", layout="tree_major").raw(x), want)
    assert np.array_equal(CompiledForest(f, "tt", unroll=True).raw(x), want)
    t = tt_tensors(f)
    assert np.array_equal(tt_leaves(x, t, cmp), tt_leaves(x, t, cmp, extra=3))


def test_degenerate_trees_and_batches():
    root = tree([([0.25, 0.75],)], 2)
    for s in ("gemm", "tt", "ptt"):
        c = CompiledForest(ForestSpec((root,), classifier=True), s)
        assert c.predict(np.zeros((2, 1)))[0].tolist() == [1, 1]
        assert c.raw(np.zeros((0, 1))).shape == (0, 2)


def test_nan_goes_right_without_spoiling_other_decisions():
    x = np.array([[np.nan, 0.0, 9.0], [1.0, np.inf, 0.0]])
    outs = [CompiledForest(ForestSpec((hand_tree(),)), s).raw(x).argmax(1).tolist() for s in ("gemm", "tt", "ptt")]
    assert outs[0] == outs[1] == outs[2] == [2, 1]


def test_chunks_do_not_matter():
    f = generate(1, 8, 5, [[0.0, 0.5]] * 4, 2)
    x = np.random.default_rng(0).normal(size=(57, 4))
    g = gemm_tensors(f)
    assert np.array_equal(trees.gemm_sum(x, g, "<", budget=2000), trees.gemm_sum(x, g, "<"))


def test_choice_and_limits():
    assert [trees.choose_strategy(d) for d in (3, 4, 10, 11)] == ["gemm", "ptt", "ptt", "tt"]
    assert trees.choose_strategy(10, device="accelerator") == "gemm"
    with pytest.raises(trees.OverBudget):
        ptt_tensors(generate(2, 4, 12, [[0.0]], 2, "tall"), limit=1000)
    with pytest.raises(trees.UnsupportedSplit):
        tree([("red", 1, 1, 2)], 1)


def test_memory_follows_the_cost_model():
    f = generate(3, 1, 6, [[0.0, 1.0]] * 3, 2, "balanced")
    n = len(f.trees[0].left)
    assert tt_tensors(f).left.size == n and ptt_tensors(f).value.shape[1] == 2**6
    assert trees.cost_model("ptt", 3, n, 2, 6) == (64, 6)
