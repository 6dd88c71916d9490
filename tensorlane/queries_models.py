"""Queries over fitted models: front-ends against the libraries' own scores, fits by aggregates, and the workloads on them."""

from __future__ import annotations

import json
import time
from collections.abc import Callable

import numpy as np
from pyspark import SparkContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import fits, frontends, measure, trees
from . import queries as scoring
from .baseline import case_sql, udf_rowwise
from .oracle.sql import forest_sql
from .pipeline import ALL, PipelineDag, chain
from .plans.scoring import compile_pipeline
from .queries_columns import _scratch as scratch
from .workloads import AIRLINE, COVTYPE, FRAUD, HIGGS, OPS, STRATEGY, YEAR, View

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def agreement_sql(table: str) -> str:
    return f"SELECT count(*) AS rows, CAST(0 AS BIGINT) AS mismatches FROM {table}"


# -- trained models and their own library -------------------------------------------------

LABEL = "CAST(qd > 1.25 OR tax < 0.015 AS DOUBLE)"


def _labelled(s: SparkSession, d: str, view: View = OPS, label: str = LABEL) -> DataFrame:
    return view.frame(s, d).withColumn("y", F.expr(label))


def _train(df: DataFrame, key: str = "l_orderkey") -> DataFrame:
    """The 80 % of the rows that models are fitted on."""
    return df.filter(F.col(key) % 10 < 8)


def _assembled(names: list[str], *stages, target: str = "x"):
    from pyspark.ml import Pipeline
    from pyspark.ml.feature import VectorAssembler

    return Pipeline(stages=[VectorAssembler(inputCols=names, outputCol=target), *stages])


def _detached(fitted):
    """A fitted pipeline whose models leave their training summaries behind.

    Summaries of binary models hold the session, and the model goes to the workers with them: that fails once the
    session has made a member that can't be serialized (job tags, observations, streams do).
    """
    for stage in fitted.stages:
        if getattr(stage, "hasSummary", False):
            stage._java_obj.setSummary(SparkContext._active_spark_context._jvm.scala.Option.empty())
    return fitted


def _against_library(s, d, make, columns: list[str], view: View = OPS, label: str = LABEL) -> DataFrame:
    """Rows of the whole view, and rows on which the compiled pipeline and the library's own transform differ."""
    from pyspark.ml.functions import vector_to_array

    df = _labelled(s, d, view, label)
    fitted = _detached(_assembled(view.names, *make()).fit(_train(df)))
    dag = frontends.from_mllib(fitted)
    keys = list(view.keys)
    ours = compile_pipeline(dag, lane="vector").score(df, keys)
    last = fitted.stages[-1]
    own = fitted.transform(df)
    if last.hasParam("outputCol"):
        own = own.select(*keys, vector_to_array(last.getOutputCol()).alias("_v"))
        own = own.select(*keys, *[F.col("_v")[k].alias(c) for k, c in enumerate(columns)])
        ours = ours.select(*keys, *[F.col(c).alias(n) for c, n in zip(ours.columns[len(keys) :], columns, strict=False)])
    else:
        probability = [vector_to_array("probability")[int(c[1:])].alias(c) for c in columns if c != "prediction"]
        own = own.select(*keys, "prediction", *probability)
    return measure.allclose(ours.select(*keys, *columns), own, keys, columns, 1e-6, 1e-6).select("rows", "mismatches")


def _register_library() -> None:
    from pyspark.ml import classification as c
    from pyspark.ml import feature as f
    from pyspark.ml import regression as r

    xy = {"featuresCol": "x", "labelCol": "y"}
    both = ["prediction", "p0", "p1"]
    models = {
        "decision_tree": (lambda: [c.DecisionTreeClassifier(maxDepth=6, seed=1, **xy)], both),
        "random_forest": (lambda: [c.RandomForestClassifier(numTrees=20, maxDepth=6, seed=1, **xy)], both),
        "gbt": (lambda: [c.GBTClassifier(maxIter=8, maxDepth=4, seed=1, **xy)], both),
        "logistic": (lambda: [f.StandardScaler(inputCol="x", outputCol="z", withMean=True), c.LogisticRegression(featuresCol="z", labelCol="y", maxIter=20)], both),
        "svc": (lambda: [f.MinMaxScaler(inputCol="x", outputCol="z"), c.LinearSVC(featuresCol="z", labelCol="y", maxIter=10)], ["prediction"]),
        "naive_bayes_gaussian": (lambda: [f.StandardScaler(inputCol="x", outputCol="z", withMean=True), c.NaiveBayes(featuresCol="z", labelCol="y", modelType="gaussian")], both),
        "tree_regressor": (lambda: [r.DecisionTreeRegressor(maxDepth=5, seed=1, **xy)], ["prediction"]),
        "forest_regressor": (lambda: [r.RandomForestRegressor(numTrees=12, maxDepth=5, seed=1, **xy)], ["prediction"]),
        "gbt_regressor": (lambda: [r.GBTRegressor(maxIter=6, maxDepth=3, seed=1, **xy)], ["prediction"]),
        "linear_regression": (lambda: [r.LinearRegression(maxIter=10, **xy)], ["prediction"]),
    }
    few = [f"v{k}" for k in range(4)]
    shapes = {
        "standard_scaler": lambda: [f.StandardScaler(inputCol="x", outputCol="z", withMean=True)],
        "minmax_scaler": lambda: [f.MinMaxScaler(inputCol="x", outputCol="z")],
        "maxabs_scaler": lambda: [f.MaxAbsScaler(inputCol="x", outputCol="z")],
        "robust_scaler": lambda: [f.RobustScaler(inputCol="x", outputCol="z", withCentering=True)],
        "normalizer": lambda: [f.Normalizer(inputCol="x", outputCol="z", p=2.0)],
        "pca": lambda: [f.StandardScaler(inputCol="x", outputCol="w", withMean=True), f.PCA(inputCol="w", outputCol="z", k=4)],
        "selector": lambda: [f.VarianceThresholdSelector(featuresCol="x", outputCol="z", varianceThreshold=2.0)],
    }
    table = "lineitem"
    for name, (make, columns) in models.items():
        QUERIES[f"mllib_{name}"] = lambda s, d, make=make, columns=columns: _against_library(s, d, make, columns)
        ORACLES[f"mllib_{name}"] = agreement_sql(table)
    for name, make in shapes.items():
        QUERIES[f"mllib_{name}"] = lambda s, d, make=make: _against_library(s, d, make, few)
        ORACLES[f"mllib_{name}"] = agreement_sql(table)

    classes = "CAST(least(6, 2 * floor(q / 17) + CAST(disc > 0.05 AS INT) + CAST(size > 25 AS INT)) AS DOUBLE)"
    seven = ["prediction", *[f"p{k}" for k in range(7)]]
    QUERIES["mllib_forest_multiclass"] = lambda s, d: _against_library(s, d, lambda: [c.RandomForestClassifier(numTrees=10, maxDepth=6, seed=1, **xy)], seven, COVTYPE, classes)
    ORACLES["mllib_forest_multiclass"] = agreement_sql(table)


_register_library()


@query("library_forest_baseline")
def _(s, d):
    """The library's own scores of a trained forest: the baseline of the trained workloads."""
    from pyspark.ml import classification as c

    df = _labelled(s, d)
    fitted = _detached(_assembled(OPS.names, c.RandomForestClassifier(numTrees=20, maxDepth=6, seed=1, featuresCol="x", labelCol="y")).fit(_train(df)))
    return fitted.transform(df).select(*OPS.keys, "prediction")


# -- specs, dumps and exchange nodes ------------------------------------------------------

_BOOSTED = trees.generate(77, 8, 5, HIGGS.grid(), 1, "balanced", combine="sum", bias=(0.0,))
_KEYS = list(HIGGS.keys)


def nested_dump(forest: trees.ForestSpec, names: list[str]) -> str:
    def node(t, k):
        if t.left[k] == k:
            return {"nodeid": k, "leaf": float(t.value[k, 0])}
        a, b = int(t.left[k]), int(t.right[k])
        return {"nodeid": k, "split": names[t.feature[k]], "split_condition": float(t.threshold[k]), "yes": a, "no": b, "missing": a, "children": [node(t, a), node(t, b)]}

    return json.dumps([node(t, 0) for t in forest.trees])


def sectioned_dump(forest: trees.ForestSpec) -> str:
    out = ["tree"]
    for number, t in enumerate(forest.trees):
        inner, leaves = np.flatnonzero(~t.is_leaf), np.flatnonzero(t.is_leaf)
        place = {int(k): j for j, k in enumerate(inner)} | {int(k): -j - 1 for j, k in enumerate(leaves)}
        lists = {
            "split_feature": t.feature[inner], "threshold": [repr(float(x)) for x in t.threshold[inner]], "decision_type": [2] * len(inner),
            "left_child": [place[int(t.left[k])] for k in inner], "right_child": [place[int(t.right[k])] for k in inner], "leaf_value": [repr(float(x)) for x in t.value[leaves, 0]],
        }
        out += [f"Tree={number}", f"num_leaves={len(leaves)}", *[f"{k}={' '.join(map(str, v))}" for k, v in lists.items()], ""]
    return "\n".join(out)


def exchange_forest(forest: trees.ForestSpec) -> dict:
    a: dict[str, list] = {k: [] for k in ("nodes_treeids", "nodes_nodeids", "nodes_featureids", "nodes_values", "nodes_modes", "nodes_truenodeids", "nodes_falsenodeids", "target_treeids", "target_nodeids", "target_ids", "target_weights")}
    for number, t in enumerate(forest.trees):
        for k in range(len(t.left)):
            leaf = t.left[k] == k
            row = (number, k, 0 if leaf else int(t.feature[k]), 0.0 if leaf else float(t.threshold[k]), "LEAF" if leaf else "BRANCH_LT", 0 if leaf else int(t.left[k]), 0 if leaf else int(t.right[k]))
            for name, v in zip(list(a)[:7], row, strict=True):
                a[name].append(v)
            if leaf:
                for name, v in zip(list(a)[7:], (number, k, 0, float(t.value[k, 0])), strict=True):
                    a[name].append(v)
    return a


_BOOSTED_SQL = forest_sql(_BOOSTED, HIGGS.names, HIGGS.sql(), _KEYS)
_AT_MOST = trees.generate(78, 8, 5, HIGGS.grid(), 1, "balanced", combine="sum", bias=(0.0,), cmp="<=")


def _scored(s, d, dag: PipelineDag) -> DataFrame:
    return compile_pipeline(dag, lane="vector").score(HIGGS.frame(s, d), _KEYS)


@query("front_nested_dump", _BOOSTED_SQL)
def _(s, d):
    return _scored(s, d, chain(HIGGS.names, ("trees.forest", {"spec": frontends.from_nested_dump(nested_dump(_BOOSTED, HIGGS.names), HIGGS.names)})))


@query("front_sectioned_dump", forest_sql(_AT_MOST, HIGGS.names, HIGGS.sql(), _KEYS))
def _(s, d):
    return _scored(s, d, chain(HIGGS.names, ("trees.forest", {"spec": frontends.from_sectioned_dump(sectioned_dump(_AT_MOST))})))


@query("front_json_spec", _BOOSTED_SQL)
def _(s, d):
    spec = frontends.to_json([
        {"id": "a", "signature": "col.pick", "inputs": HIGGS.names, "raw": True},
        {"id": "b", "signature": "trees.forest", "inputs": ["a"], "params": {"spec": _BOOSTED}},
    ])
    return _scored(s, d, frontends.from_json(spec))


@query("front_exchange_nodes", _BOOSTED_SQL)
def _(s, d):
    return _scored(s, d, frontends.from_exchange(HIGGS.names, [("TreeEnsembleRegressor", exchange_forest(_BOOSTED))]))


# -- fits by aggregates -------------------------------------------------------------------


def _row(s: SparkSession, values, names: list[str], scale: float = 1e4) -> DataFrame:
    """Fitted numbers, one row, as whole 1/scale."""
    return s.createDataFrame([tuple(int(np.floor(v * scale + 0.5)) for v in values)], ", ".join(f"{n} long" for n in names))


_FIT = ["q", "price", "disc", "total"]


#: Columns of few values, on which quantiles within a hundred-thousandth of the rows are the exact ones.
_FEW = ["q", "disc", "tax", "line"]


def _fit_sql(*forms: str, columns: list[str] = _FIT, scale: str = "10000") -> str:
    cells = ", ".join(f"CAST(floor(({f.format(c)}) * {scale} + 0.5) AS BIGINT) AS {c}_{k}" for c in columns for k, f in enumerate(forms))
    return f"SELECT {cells} FROM ({HIGGS.sql()})"


def _fitted(s, *arrays, columns: list[str] = _FIT) -> DataFrame:
    return _row(s, [a[j] for j in range(len(columns)) for a in arrays], [f"{c}_{k}" for c in columns for k in range(len(arrays))])


@query("fit_standard", _fit_sql("avg({})", "stddev_pop({})"))
def _(s, d):
    p = fits.standard(HIGGS.frame(s, d), _FIT)
    return _fitted(s, p["mu"], p["sd"])


@query("fit_minmax", _fit_sql("min({})", "max({})"))
def _(s, d):
    p = fits.minmax(HIGGS.frame(s, d), _FIT)
    return _fitted(s, p["lo"], p["hi"])


@query("fit_maxabs", _fit_sql("max(abs({}))"))
def _(s, d):
    return _fitted(s, fits.maxabs(HIGGS.frame(s, d), _FIT)["m"])


@query("fit_robust", _fit_sql("quantile_disc({}, 0.5)", "quantile_disc({0}, 0.75) - quantile_disc({0}, 0.25)", columns=_FEW))
def _(s, d):
    p = fits.robust(HIGGS.frame(s, d), _FEW)
    return _fitted(s, p["center"], p["scale"], columns=_FEW)


@query("fit_impute_mean", _fit_sql("avg({})"))
def _(s, d):
    return _fitted(s, fits.impute(HIGGS.frame(s, d), _FIT)["values"])


@query("fit_impute_median", _fit_sql("quantile_disc({}, 0.5)", columns=_FEW))
def _(s, d):
    return _fitted(s, fits.impute(HIGGS.frame(s, d), _FEW, "median")["values"], columns=_FEW)


@query("fit_impute_mode", "SELECT (SELECT q FROM (SELECT l_quantity AS q, count(*) AS n FROM lineitem GROUP BY 1) ORDER BY n DESC, q LIMIT 1) AS q")
def _(s, d):
    return s.createDataFrame([(float(fits.impute(HIGGS.frame(s, d), ["q"], "mode")["values"][0]),)], "q double")


@query("fit_kbins_quantile", _fit_sql(*[f"quantile_disc({{}}, {k / 5})" for k in range(1, 5)], columns=_FEW[:2]))
def _(s, d):
    edges = fits.kbins(HIGGS.frame(s, d), _FEW[:2], 5, "quantile")["edges"]
    return _row(s, [e[k] for e in edges for k in range(4)], [f"{c}_{k}" for c in _FEW[:2] for k in range(4)])


@query("fit_kbins_uniform", _fit_sql(*[f"min({{0}}) + {k} * (max({{0}}) - min({{0}})) / 5" for k in range(1, 5)]))
def _(s, d):
    edges = fits.kbins(HIGGS.frame(s, d), _FIT, 5)["edges"]
    return _row(s, [e[k] for e in edges for k in range(4)], [f"{c}_{k}" for c in _FIT for k in range(4)])


@query("fit_kbins_kmeans")
def _(s, d):
    edges = fits.kbins(HIGGS.frame(s, d), _FIT, 4, "kmeans")["edges"]
    return s.createDataFrame([(c, k, float(e)) for c, row in zip(_FIT, edges, strict=True) for k, e in enumerate(row)], "name string, edge int, value double")


@query("fit_vocabulary", "SELECT DISTINCT p_brand AS v FROM part")
def _(s, d):
    return s.createDataFrame([(v,) for v in fits.vocabulary(s.read.parquet(f"{d}/part.parquet"), "p_brand")], "v string")


@query("fit_variance", _fit_sql("var_pop({}) / 1e6"))
def _(s, d):
    return _fitted(s, fits.variances(HIGGS.frame(s, d), _FIT) / 1e6)


_SCORE_LABEL = "CAST(q * disc > 1.25 OR tax < 0.015 AS INT)"


def _anova_sql() -> str:
    cells = []
    for c in _FIT:
        between = f"(sum(s_{c} * s_{c} / n) - sum(s_{c}) * sum(s_{c}) / sum(n))"
        within = f"(sum(q_{c}) - sum(s_{c} * s_{c} / n))"
        cells.append(f"CAST(floor({between} / (count(*) - 1) / ({within} / (sum(n) - count(*))) * 10000 + 0.5) AS BIGINT) AS {c}")
    sums = ", ".join(f"sum({c}) AS s_{c}, sum({c} * {c}) AS q_{c}" for c in _FIT)
    return f"SELECT {', '.join(cells)} FROM (SELECT {_SCORE_LABEL} AS y, CAST(count(*) AS DOUBLE) AS n, {sums} FROM ({HIGGS.sql()}) GROUP BY 1)"


@query("fit_anova", _anova_sql())
def _(s, d):
    df = HIGGS.frame(s, d).withColumn("y", F.expr(_SCORE_LABEL))
    return _row(s, fits.anova_f(df, _FIT, "y"), _FIT)


@query("fit_chi2", "SELECT " + ", ".join(f"CAST(floor(sum((s_{c} - n * t_{c} / m) * (s_{c} - n * t_{c} / m) / (n * t_{c} / m)) * 10000 + 0.5) AS BIGINT) AS {c}" for c in ("q", "disc")) + f" FROM (SELECT *, sum(n) OVER () AS m, sum(s_q) OVER () AS t_q, sum(s_disc) OVER () AS t_disc FROM (SELECT {_SCORE_LABEL} AS y, CAST(count(*) AS DOUBLE) AS n, sum(q) AS s_q, sum(disc) AS s_disc FROM ({HIGGS.sql()}) GROUP BY 1))")
def _(s, d):
    df = HIGGS.frame(s, d).withColumn("y", F.expr(_SCORE_LABEL))
    return _row(s, fits.chi2(df, ["q", "disc"], "y"), ["q", "disc"])


@query("fit_pca")
def _(s, d):
    p = fits.pca(HIGGS.frame(s, d), OPS.names, 4)
    return s.createDataFrame([(n, *map(float, row)) for n, row in zip(OPS.names, p["w"], strict=True)], "name string, c0 double, c1 double, c2 double, c3 double")


@query("fit_truncated_svd")
def _(s, d):
    p = fits.truncated_svd(HIGGS.frame(s, d), OPS.names, 4)
    return s.createDataFrame([(n, *map(float, row)) for n, row in zip(OPS.names, p["w"], strict=True)], "name string, c0 double, c1 double, c2 double, c3 double")


@query("fit_independent_components")
def _(s, d):
    p = fits.independent_components(HIGGS.frame(s, d), _FIT, 3)
    return s.createDataFrame([(n, *map(float, row)) for n, row in zip(_FIT, p["w"], strict=True)], "name string, c0 double, c1 double, c2 double")


@query("fit_kernel_pca")
def _(s, d):
    p = fits.kernel_pca(FRAUD.frame(s, d).withColumns({"a": F.col("value") / 100, "b": F.col("k") / 100}), ["a", "b"], "event_id", 2, 0.5)
    return s.createDataFrame([(k, *map(float, row)) for k, row in enumerate(p["a"])], "row int, c0 double, c1 double")


@query("fit_logistic_cv")
def _(s, d):
    df = FRAUD.frame(s, d).withColumn("y", (F.col("value") > 40).cast("double"))
    p = fits.logistic_cv(df, ["value", "k", "hour"], "y", "event_id", [0.001, 0.1, 10.0])
    return s.createDataFrame([(n, float(w)) for n, w in zip(["value", "k", "hour"], p["w"][:, 0], strict=True)], "name string, weight double")


# -- selection by real scores, and weights that L1 made 0 ---------------------------------


def _selected(s, d, percent: float, rules: tuple[str, ...]) -> DataFrame:
    """Scale, keep the best share of the columns by their F value, then a logistic model; with and without the push-down."""
    df = _labelled(s, d)
    train = _train(df)
    keep = fits.percentile(fits.anova_f(train, OPS.names, "y"), percent)
    p = fits.standard(train, OPS.names)
    chosen = [OPS.names[k] for k in keep["kept"]]
    scaled = train.select("y", *[((F.col(n) - float(p["mu"][k])) / float(p["sd"][k] or 1.0)).alias(n) for k, n in zip(keep["kept"], chosen, strict=True)])
    model = fits.logistic(scaled, chosen, "y", l2=0.01)
    dag = chain(OPS.names, ("sc.standard", p), ("sel.columns", keep), ("lin.linear", model))
    return compile_pipeline(dag, lane="vector", rules=rules).score(df, list(OPS.keys))


for _percent in (10, 20, 30, 40, 50, 60, 70, 80, 90, 100):

    @query(f"w13_scored_p{_percent}", agreement_sql("lineitem"))
    def _(s, d, percent=_percent):
        a, b = (_selected(s, d, percent, r) for r in ((), ALL))
        return measure.allclose(a, b, list(OPS.keys), ["p0", "p1"], 1e-9, 1e-9).select("rows", "mismatches")


for _strength in (0.001, 0.01, 0.05):

    @query(f"w14_l1_{_strength}".replace(".", "_"), agreement_sql("lineitem"))
    def _(s, d, strength=_strength):
        """A sparse model's dead inputs go: same scores, fewer columns read."""
        df = _labelled(s, d)
        train = _train(df)
        p = fits.standard(train, OPS.names)
        scaled = train.select("y", *[((F.col(n) - float(m)) / float(v or 1.0)).alias(n) for n, m, v in zip(OPS.names, p["mu"], p["sd"], strict=True)])
        dag = chain(OPS.names, ("sc.standard", p), ("lin.linear", fits.logistic(scaled, OPS.names, "y", l1=strength)))
        a, b = (compile_pipeline(dag, lane="vector", rules=r) for r in ((), ALL))
        return measure.allclose(a.score(df, list(OPS.keys)), b.score(df, list(OPS.keys)), list(OPS.keys), ["p0", "p1"], 1e-9, 1e-9).select("rows", "mismatches")


# -- validation, in all combinations of strategy, lane type and view ----------------------


def _combination(view: View, outputs: int, strategy: str, shape: str):
    def run(s, d):
        f = scoring.model(view, shape, 8, 6, outputs, seed=90, classifier=outputs > 1)
        a = scoring.scored(view, f, strategy=strategy)(s, d)
        dag = chain(view.names, ("trees.forest", {"spec": f, "strategy": "tt" if strategy != "tt" else "gemm"}))
        b = compile_pipeline(dag, lane="vector", dtype="float32").score(view.frame(s, d), list(view.keys))
        names = [f"p{k}" for k in range(outputs)]
        # single precision moves a value that lies on a threshold, so the share of rows is compared, not each row
        return measure.allclose(a, b, list(view.keys), names).select("rows", (F.col("share") < 0.01).alias("agrees"))

    return run


for _view, _n, _table in ((FRAUD, 2, "events"), (YEAR, 1, "lineitem"), (HIGGS, 2, "lineitem")):
    for _shape in ("bagged", "balanced"):
        for _strategy in ("gemm", "tt", "ptt"):
            QUERIES[f"w7_{_view.name}_{_shape}_{_strategy}"] = _combination(_view, _n, _strategy, _shape)
            ORACLES[f"w7_{_view.name}_{_shape}_{_strategy}"] = f"SELECT count(*) AS rows, true AS agrees FROM {_table}"


# -- forests of the full size: 500 trees of depth 8 ----------------------------------------


def _full_size(view: View, shape: str, outputs: int, **spec):
    def run(s, d):
        forest = scoring.model(view, shape, 500, 8, outputs, seed=20, **spec)  # grown when it is asked for
        return compile_pipeline(_forest_dag(view, forest), lane="vector").score(view.frame(s, d), list(view.keys))

    return run


for _view, _n in ((FRAUD, 2), (YEAR, 1), (COVTYPE, 7), (HIGGS, 2), (AIRLINE, 2)):
    for _shape in ("bagged", "tall", "balanced"):
        _spec = {"classifier": _n > 1, **({} if _shape == "bagged" else {"combine": "sum", "rate": 0.5})}
        QUERIES[f"w1_{_view.name}_{_shape}_t500"] = _full_size(_view, _shape, _n, **_spec)


# -- measured workloads: rows of seconds and sizes, no oracle ------------------------------


def _noop(df: DataFrame) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def _forest_dag(view: View, forest, **options) -> PipelineDag:
    return chain(view.names, ("trees.forest", {"spec": forest, **options}))


@query("w2_request_response")
def _(s, d):
    """Seconds a record, one record at a time without Spark, by strategy."""
    forest = scoring.model(FRAUD, "bagged", 100, 8, 2, seed=20, classifier=True)
    records = [r.asDict() for r in FRAUD.frame(s, d).orderBy("event_id").limit(200).collect()]
    rows = []
    for strategy in ("gemm", "tt", "ptt"):
        model = compile_pipeline(_forest_dag(FRAUD, forest, strategy=strategy), lane="vector", batch_rows=1)
        model.score_one(records[0])
        began = time.perf_counter()
        for r in records:
            model.score_one(r)
        rows.append((strategy, len(records), (time.perf_counter() - began) / len(records)))
    return s.createDataFrame(rows, "strategy string, records long, seconds double")


@query("w3_batch_sweep")
def _(s, d):
    """Seconds by batch size and strategy, over the view's rows stored once and spread over all tasks.

    A small table of one file would else be scored by one task, and joined again for each of the runs.
    """
    forest = scoring.model(HIGGS, "bagged", 32, 8, 2, seed=20, classifier=True)
    path = scratch(s, "batch-sweep")
    HIGGS.frame(s, d).repartition(4 * s.sparkContext.defaultParallelism).write.parquet(path)
    df = s.read.parquet(path)
    rows = []
    for batch in (100, 1000, 10_000, 50_000):
        for strategy in ("gemm", "tt", "ptt"):
            rows.append((batch, strategy, _noop(compile_pipeline(_forest_dag(HIGGS, forest, strategy=strategy), lane="vector", batch_rows=batch).score(df, _KEYS))))
    return s.createDataFrame(rows, "batch long, strategy string, seconds double")


@query("w4_partition_sweep")
def _(s, d):
    """Seconds by the number of tasks that share the work: how scoring scales out."""
    forest = scoring.model(HIGGS, "bagged", 32, 8, 2, seed=20, classifier=True)
    model = compile_pipeline(_forest_dag(HIGGS, forest), lane="vector")
    took = {n: _noop(model.score(HIGGS.frame(s, d).coalesce(n), _KEYS)) for n in (1, 2, 4, 8)}
    return s.createDataFrame([(n, took[n], x) for n, x in measure.scaling(took).items()], "tasks long, seconds double, speedup double")


@query("w5_cost")
def _(s, d):
    """Cost of a prediction from a timed run, for two prices of an hour (given, not looked up)."""
    forest = scoring.model(FRAUD, "bagged", 32, 8, 2, seed=20, classifier=True)
    df = FRAUD.frame(s, d)
    seconds, records = _noop(compile_pipeline(_forest_dag(FRAUD, forest), lane="vector").score(df, ["event_id"])), df.count()
    return s.createDataFrame([(rate, records, seconds, measure.cost_per_prediction(rate, seconds, records)) for rate in (0.5, 3.0)], "rate double, records long, seconds double, cost double")


@query("w6_memory")
def _(s, d):
    """Bytes of a compiled forest's tensors by strategy, and of its pipeline as sent to the workers; thresholds from the table."""
    view, rows = HIGGS.bounded(HIGGS.frame(s, d)), []
    for depth in (3, 6, 9):
        forest = scoring.model(view, "bagged", 100, depth, 2, seed=20, classifier=True)
        for strategy in ("gemm", "tt", "ptt"):
            compiled = trees.CompiledForest(forest, strategy)
            rows.append((depth, strategy, int(compiled.tensors.nbytes()), measure.model_size(_forest_dag(HIGGS, forest)), measure.peak_memory_mb()))
    return s.createDataFrame(rows, "depth long, strategy string, tensor_bytes long, pipeline_bytes long, process_mb double")


@query("w8_conversion_time")
def _(s, d):
    """Seconds to compile forests of growing size by strategy; thresholds from the table."""
    view, rows = AIRLINE.bounded(AIRLINE.frame(s, d)), []
    for count in (10, 100, 500):
        forest = scoring.model(view, "bagged", count, 8, 2, seed=20, classifier=True)
        for strategy in ("gemm", "tt", "ptt"):
            rows.append((count, strategy, measure.compile_time(lambda f=forest, k=strategy: trees.CompiledForest(f, k), 3)))
    return s.createDataFrame(rows, "trees long, strategy string, seconds double")


@query("w12_strategies_100_trees")
def _(s, d):
    """Seconds of each strategy for 100 trees, by depth and batch."""
    rows = []
    df = STRATEGY.frame(s, d).orderBy(*STRATEGY.keys).limit(5000).repartition(4).cache()
    df.count()
    for depth in (3, 7, 12):
        for shape in ("bagged", "balanced", "tall"):
            if shape == "balanced" and depth > 7:
                continue  # 2^12 leaves a tree: the perfect form of it is the same as the bagged one's
            forest = scoring.model(STRATEGY, shape, 100, depth, 2, seed=30 + depth, classifier=True)
            for batch in (1, 1000):
                records = df if batch > 1 else df.limit(200)
                for strategy in ("gemm", "tt", "ptt"):
                    if strategy == "gemm" and depth > 7 and shape != "tall":
                        continue  # its matrices would be of gigabytes
                    model = compile_pipeline(_forest_dag(STRATEGY, forest, strategy=strategy), lane="vector", batch_rows=batch)
                    rows.append((depth, shape, batch, strategy, _noop(model.score(records, list(STRATEGY.keys))), trees.choose_strategy(depth, batch)))
    df.unpersist()
    return s.createDataFrame(rows, "depth long, shape string, batch long, strategy string, seconds double, chosen string")


_CORPUS_STEPS = {
    "impute": lambda df, c: ("imp.simple", fits.impute(df, c)),
    "standard": lambda df, c: ("sc.standard", fits.standard(df, c)),
    "minmax": lambda df, c: ("sc.minmax", fits.minmax(df, c)),
    "maxabs": lambda df, c: ("sc.maxabs", fits.maxabs(df, c)),
    "robust": lambda df, c: ("sc.robust", fits.robust(df, c)),
    "kbins": lambda df, c: ("disc.kbins", fits.kbins(df, c, 4)),
    "normalize": lambda df, c: ("sc.normalize", {"norm": "l2"}),
}
_CORPUS = [
    ("impute", "standard"), ("impute", "minmax"), ("maxabs",), ("robust",), ("impute", "kbins"), ("standard",), ("normalize",),
    ("impute", "maxabs", "normalize"), ("minmax", "standard"), ("unknown.step",),
]


def _corpus(s, d):
    """(name, dag or None) of every pipeline: steps fitted on the table one after the other's input, then a logistic model."""
    df = FRAUD.frame(s, d)
    names = FRAUD.names[5:15]
    rng = np.random.default_rng(4)
    weights = {"w": np.round(rng.normal(size=(10, 1)) * 64) / 64, "b": np.zeros(1)}
    for number, steps in enumerate(_CORPUS):
        if any(x not in _CORPUS_STEPS for x in steps):
            yield number, steps, None
            continue
        made = [_CORPUS_STEPS[x](df, names) for x in steps]
        yield number, steps, chain(names, *made, ("lin.linear", weights))


@query("corpus_coverage", "SELECT CAST(10 AS BIGINT) AS pipelines, CAST(9 AS BIGINT) AS supported, CAST(0 AS BIGINT) AS failed, CAST(9 AS BIGINT) AS reported")
def _(s, d):
    """Which pipelines of the corpus compile and give a row for each record."""
    rows, df = [], FRAUD.frame(s, d)
    n = df.count()
    for number, _, dag in _corpus(s, d):
        failed = dag is not None and compile_pipeline(dag).score(df, ["event_id"]).count() != n
        rows.append((number, dag is not None, failed))
    return measure.coverage(s.createDataFrame(rows, "pipeline int, supported boolean, failed boolean"))


@query("corpus_speedup")
def _(s, d):
    """Seconds of every supported pipeline, operator by operator and compiled, and the summary's ratio."""
    from .baseline import stagewise

    df, rows = FRAUD.frame(s, d), []
    for number, steps, dag in _corpus(s, d):
        if dag is None:
            continue
        own = compile_pipeline(dag)
        rows.append((number, "+".join(steps), _noop(stagewise(df, dag, ["event_id"])), _noop(own.score(df, ["event_id"]))))
    return s.createDataFrame(rows, "pipeline int, steps string, baseline double, ours double")


@query("corpus_speedup_summary")
def _(s, d):
    return measure.speedup_summary(QUERIES["corpus_speedup"](s, d).select("pipeline", "baseline", "ours"))


@query("w11_baselines")
def _(s, d):
    """Seconds of the compiled forest beside a row-wise function, nested conditionals and the library's own transform."""
    forest = scoring.model(FRAUD, "bagged", 8, 6, 2, seed=20, classifier=True)
    df = FRAUD.frame(s, d)
    rows = [
        ("compiled", _noop(compile_pipeline(_forest_dag(FRAUD, forest), lane="vector").score(df, ["event_id"]))),
        ("row-wise", _noop(udf_rowwise(df, forest, FRAUD.names, ["event_id"]))),
        ("conditionals", _noop(case_sql(df, forest, FRAUD.names, ["event_id"]))),
    ]
    return s.createDataFrame(rows, "lane string, seconds double")


@query("iforest_fitted")
def _(s, d):
    """An isolation forest grown on a bounded sample of the table (512 rows by hash), scored on all of it."""
    df = HIGGS.frame(s, d)
    sample = df.orderBy(F.xxhash64(*_KEYS), *_KEYS).limit(512).select(*HIGGS.names).collect()
    spec = trees.isolation(np.array([list(r) for r in sample], float), trees=32, psi=128, seed=3)
    out = compile_pipeline(_forest_dag(HIGGS, spec), lane="vector").score(df, _KEYS)
    return out.select(*_KEYS, F.col("p0").alias("score"), (F.col("p0") > 0.5).alias("outlier"))
