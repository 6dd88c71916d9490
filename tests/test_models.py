"""Front-ends, fits and mends against plain versions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tensorlane import baseline, fits, frontends, measure, queries_models, relops, trees
from tensorlane.pipeline import chain
from tensorlane.plans.scoring import compile_pipeline
from tensorlane.queries_models import QUERIES, exchange_forest, nested_dump, sectioned_dump

NAMES = ["a", "b", "c"]
GRID = [[0.25, 0.5, 0.75]] * 3


def frame(spark, x, **more):
    rows = [(k, *map(float, r)) for k, r in enumerate(x)]
    return spark.createDataFrame(rows, "id long, a double, b double, c double")


@pytest.mark.parametrize("cmp", ["<", "<="])
def test_dumps_give_back_the_forest(cmp):
    f = trees.generate(3, 5, 4, GRID, 1, "bagged", combine="sum", cmp=cmp)
    x = np.random.default_rng(1).integers(0, 5, (200, 3)) / 4
    want = trees.CompiledForest(f, "tt").raw(x)
    back = frontends.from_nested_dump(nested_dump(f, NAMES), NAMES) if cmp == "<" else frontends.from_sectioned_dump(sectioned_dump(f))
    for strategy in ("gemm", "tt", "ptt"):
        assert np.allclose(trees.CompiledForest(back, strategy).raw(x), want)


def test_specs_and_exchange_nodes():
    f = trees.generate(4, 3, 3, GRID, 1, "balanced", combine="sum")
    x = np.random.default_rng(2).integers(0, 5, (50, 3)) / 4
    columns = dict(zip(NAMES, x.T, strict=True))
    want = chain(NAMES, ("trees.forest", {"spec": f})).run(columns)
    spec = frontends.to_json([{"id": "a", "signature": "col.pick", "inputs": NAMES, "raw": True}, {"id": "b", "signature": "trees.forest", "inputs": ["a"], "params": {"spec": f}}])
    assert np.allclose(frontends.from_json(spec).run(columns), want)
    assert np.allclose(frontends.from_exchange(NAMES, [("TreeEnsembleRegressor", exchange_forest(f))]).run(columns), want)
    linear = frontends.from_exchange(NAMES, [("Scaler", {"offset": [1, 0, 0], "scale": [2, 1, 1]}), ("LinearRegressor", {"coefficients": [1, 2, 3], "intercepts": [0.5]})])
    assert np.allclose(linear.run(columns)[:, 0], (x[:, 0] - 1) * 2 + 2 * x[:, 1] + 3 * x[:, 2] + 0.5)
    with pytest.raises(frontends.UnknownStage):
        frontends.from_exchange(NAMES, [("Unheard", {})])
    with pytest.raises(trees.UnsupportedSplit):
        frontends.from_nested_dump('[{"nodeid": 0, "split": "a", "split_condition": ["x"], "yes": 1, "no": 2, "children": []}]', NAMES)


def test_isolation_leaves_hold_depth_and_mean_path():
    x = np.random.default_rng(3).normal(size=(300, 3))
    x[0] = 40.0
    f = trees.isolation(x, trees=40, psi=64, seed=2)
    for t in f.trees:
        shares, depth = {0: 64}, {0: 0}
        for k in range(len(t.left)):
            for child in {int(t.left[k]), int(t.right[k])} - {k}:
                depth[child] = depth[k] + 1
        leaves = np.flatnonzero(t.is_leaf)
        assert all(t.value[k, 0] >= depth[int(k)] for k in leaves) and max(depth.values()) <= 6 and shares
    scores = trees.CompiledForest(f, "tt").raw(x)[:, 0]
    assert scores.argmax() == 0 and scores[0] > 0.6 and np.median(scores) < 0.5


def test_rows_with_equal_keys_are_walked_apart(spark):
    f = trees.generate(5, 4, 3, GRID, 2, "bagged")
    df = frame(spark, [[0.1, 0.6, 0.3]] * 3 + [[0.9, 0.2, 0.8]]).withColumn("id", F.lit(1).cast("long"))
    out = [tuple(r) for r in baseline.relational_walk(df, f, NAMES, ["id"]).collect()]
    assert len(out) == 4 and all(p <= 1 for _, p, _ in out)


def test_relational_products_reach_the_leaf_right_of_all(spark):
    t = trees.tree([(0, 0.5, 1, 2), ([1.0],), (1, 0.5, 3, 4), ([2.0],), ([3.0],)], 1)
    out = baseline.relational_gemm(frame(spark, [[0, 0, 0], [1, 0, 0], [1, 1, 0]]), t, NAMES, "id")
    assert sorted((r["id"], r["p0"]) for r in out.collect()) == [(0, 1.0), (1, 2.0), (2, 3.0)]


def test_agreement_counts_rows_of_one_side_and_nulls(spark):
    a = spark.createDataFrame([(1, 1.0), (2, 2.0), (3, None), (4, None), (None, 5.0)], "k long, v double")
    b = spark.createDataFrame([(1, 1.0), (3, None), (4, 1.0), (5, 1.0), (None, 5.0)], "k long, v double")
    r = measure.allclose(a, b, ["k"], ["v"]).first()
    assert (r["rows"], r["mismatches"]) == (6, 3)


def test_single_precision_computes_in_single_precision(spark):
    dag = chain(NAMES, ("lin.linear", {"w": np.array([[1.0], [1e-9], [0.0]]), "b": np.array([0.0]), "mode": "regress"}))
    df = frame(spark, [[1.0, 1.0, 0.0]])
    wide, narrow = (compile_pipeline(dag, lane="vector", dtype=t).score(df, ["id"]).first()["prediction"] for t in ("float64", "float32"))
    assert wide == 1.000000001 and narrow == 1.0


def test_batch_rows_reach_the_choice_and_the_kernel(spark):
    f = trees.generate(6, 2, 8, GRID, 1, "balanced")
    small = compile_pipeline(chain(NAMES, ("trees.forest", {"spec": f})), lane="vector", batch_rows=1)
    large = compile_pipeline(chain(NAMES, ("trees.forest", {"spec": f})), lane="vector")
    assert small.dag.nodes[-1].op.chosen() == "gemm" and large.dag.nodes[-1].op.chosen() == "ptt"


def test_fits_against_numpy(spark):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(400, 3)) * [1, 5, 0.2] + [0, 3, 1]
    y = (x[:, 1] > 3).astype(int)
    df = frame(spark, x).join(spark.createDataFrame([(k, int(v)) for k, v in enumerate(y)], "id long, y int"), "id")
    p = fits.standard(df, NAMES)
    assert np.allclose(p["mu"], x.mean(0)) and np.allclose(p["sd"], x.std(0))
    n, s, m = fits.moments(df, NAMES)
    assert n == 400 and np.allclose(s, x.sum(0)) and np.allclose(m, x.T @ x)
    w = fits.pca(df, NAMES, 2)["w"]
    assert np.allclose(np.abs(w.T @ np.linalg.svd(x - x.mean(0))[2][:2].T), np.eye(2), atol=1e-9)
    assert fits.percentile(fits.anova_f(df, NAMES, "y"), 34)["kept"] == [1]
    assert fits.variance_threshold(df, NAMES, 0.5) == {"kept": [0, 1]}
    assert len(fits.kbins(df, NAMES, 4, "kmeans")["edges"][0]) == 3
    empty = df.limit(0)
    assert fits.standard(empty, NAMES)["sd"].tolist() == [1, 1, 1] and fits.moments(empty, NAMES)[0] == 0


def test_area_under_the_curve_by_ranges(spark):
    rng = np.random.default_rng(9)
    score, label = rng.integers(0, 60, 500) / 4.0, rng.integers(0, 2, 500)
    df = spark.createDataFrame([(float(a), int(b)) for a, b in zip(score, label, strict=True)], "s double, y int")
    pos, neg = score[label == 1], score[label == 0]
    want = ((pos[:, None] > neg).sum() + 0.5 * (pos[:, None] == neg).sum()) / (len(pos) * len(neg))
    assert abs(relops.auc_rank(df, "y", "s").first()["auc"] - want) < 1e-12


def tagged(spark):
    """A session that has made a member that can't be serialized."""
    session = spark.newSession()
    session._jsparkSession.addTag("tagged")
    return session


@pytest.mark.parametrize("name", ["mllib_random_forest", "mllib_logistic", "mllib_svc"])
def test_binary_models_leave_the_session_behind(spark, name):
    (row,) = QUERIES[name](tagged(spark), "/root/testdata/sf0.001").collect()
    assert row["rows"] == 6000 and row["mismatches"] == 0


def test_library_baseline_leaves_the_session_behind(spark):
    assert QUERIES["library_forest_baseline"](tagged(spark), "/root/testdata/sf0.001").filter("prediction IN (0, 1)").count() == 6000


def test_batch_sweep_spreads_a_table_of_one_file(spark, monkeypatch):
    """All rows go through each of the twelve runs, in more than one task."""
    seen = []

    def recorded(df):
        seen.append((df.rdd.getNumPartitions(), df.count()))
        return 1.0

    monkeypatch.setattr(queries_models, "_noop", recorded)
    assert QUERIES["w3_batch_sweep"](spark, "/root/testdata/sf0.001").count() == 12
    assert len(seen) == 12 and all(tasks > 1 and rows == 6000 for tasks, rows in seen)


def test_products_are_as_large_as_the_trees_of_a_tile():
    """Trees of unlike sizes give the cursors' sums to the bit, and padding takes no part."""
    small = trees.generate(1, 3, 1, [[0.5], [0.25]], 2, "balanced")
    large = trees.generate(2, 3, 5, [[0.5], [0.25, 0.75]], 2, "balanced")
    both = trees.ForestSpec((*small.trees, *large.trees))
    g = trees.gemm_tensors(both)
    assert g.sizes.tolist() == [[1, 2]] * 3 + [[31, 32]] * 3
    x = np.random.default_rng(3).uniform(size=(500, 2))
    x[0] = np.nan
    for budget in (1, 4096, trees.TILE):
        assert np.array_equal(trees.gemm_sum(x, g, both.cmp, budget=budget), trees.CompiledForest(both, "tt").leaf_values(x).sum(0))
