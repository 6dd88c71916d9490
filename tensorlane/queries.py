"""Registered queries of the scoring methods, each with the SQL it is checked against."""

from __future__ import annotations

from collections.abc import Callable
from functools import cache

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import trees
from .operators.featurizers import polynomial_terms
from .oracle.sql import dot, first_largest, fixed, forest_sql, linear_scores, num, tree_case
from .pipeline import Builder, PipelineDag, chain
from .plans.scoring import compile_pipeline
from .sources import read_table
from .workloads import AIRLINE, BRANDS, COVTYPE, EPSILON, FRAUD, HIGGS, IRIS, LINE_KEYS, OPS, STRATEGY, TYPES, YEAR, View

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def whole(df: DataFrame, keep: list[str], names: list[str], scale: int = 10_000) -> DataFrame:
    """Outputs as whole 1/scale numbers, half up."""
    return df.select(*keep, *[F.floor(F.col(n) * scale + 0.5).cast("long").alias(n) for n in names])


def whole_sql(sql: str, keep: list[str], names: list[str], scale: int = 10_000) -> str:
    return f"SELECT {', '.join([*keep, *[f'{fixed(n, scale)} AS {n}' for n in names]])} FROM ({sql})"


# -- trees --------------------------------------------------------------------------------


@cache
def model(view: View, shape: str, count: int, depth: int, outputs: int, seed: int = 3, **spec) -> trees.ForestSpec:
    return trees.generate(seed, count, depth, view.grid(), outputs, shape, **dict(spec))


def scored(view: View, forest: trees.ForestSpec, **options) -> Query:
    lane = options.pop("lane", "vector")
    batch_rows = options.pop("batch_rows", None)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        dag = chain(view.names, ("trees.forest", {"spec": forest, **options}))
        compiled = compile_pipeline(dag, lane=lane, batch_rows=batch_rows)
        return compiled.score(view.frame(spark, sf_dir), list(view.keys))

    return run


def add_forest(name: str, view: View, forest: trees.ForestSpec, **options) -> None:
    sql = forest_sql(forest, view.names, view.sql(), list(view.keys))
    if forest.link != "identity" or forest.combine == "isolation":
        n = 2 if forest.link == "sigmoid" else forest.outputs
        names = ["prediction", *[f"p{k}" for k in range(n)]]
        query = scored(view, forest, **options)
        add(name, lambda s, d: whole(query(s, d), list(view.keys), names), whole_sql(sql, list(view.keys), names))
    else:
        add(name, scored(view, forest, **options), sql)


def register_trees() -> None:
    one = model(COVTYPE, "bagged", 1, 6, 7, seed=5, classifier=True)
    add_forest("tree_gemm", COVTYPE, one, strategy="gemm")
    add_forest("tree_tt", COVTYPE, one, strategy="tt")
    add_forest("tree_tt_unrolled", COVTYPE, one, strategy="tt", unroll=True)
    add_forest("tree_ptt", COVTYPE, one, strategy="ptt")
    value = model(YEAR, "bagged", 1, 6, 1, seed=6)
    multi = model(COVTYPE, "bagged", 8, 6, 7, classifier=True)
    binary = model(HIGGS, "bagged", 8, 6, 2, classifier=True)
    regress = model(YEAR, "bagged", 8, 6, 1)
    for s in ("gemm", "tt", "ptt"):
        add_forest(f"tree_regress_{s}", YEAR, value, strategy=s)
        add_forest(f"forest_{s}_multi", COVTYPE, multi, strategy=s)
        add_forest(f"forest_{s}_binary", HIGGS, binary, strategy=s)
        add_forest(f"forest_{s}_regress", YEAR, regress, strategy=s)
    add_forest("forest_ptt_tree_major", COVTYPE, multi, strategy="ptt", layout="tree_major")
    add_forest("forest_ptt_interleaved", COVTYPE, multi, strategy="ptt", layout="level_interleaved")
    add_forest("forest_auto", COVTYPE, multi)
    tall = model(HIGGS, "tall", 8, 12, 2, classifier=True)
    add_forest("forest_skinny_tt", HIGGS, tall, strategy="tt")
    mixed = trees.ForestSpec(tuple(t for d in range(1, 9) for t in model(HIGGS, "balanced" if d < 6 else "tall", 1, d, 2, seed=d).trees), classifier=True)
    for s in ("gemm", "tt", "ptt"):
        add_forest(f"forest_padded_mixed_depth_{s}", HIGGS, mixed, strategy=s)
    add_forest("forest_vote", COVTYPE, model(COVTYPE, "bagged", 8, 5, 7, seed=8, combine="vote", classifier=True), strategy="gemm")
    add_forest("forest_less_or_equal", HIGGS, model(HIGGS, "bagged", 8, 5, 2, seed=9, cmp="<=", classifier=True), strategy="ptt")
    add_forest("boost_binary", HIGGS, model(HIGGS, "tall", 8, 6, 1, seed=10, combine="sum", link="sigmoid", bias=(0.25,), rate=0.5, classifier=True), strategy="tt")
    add_forest("boost_regress", YEAR, model(YEAR, "balanced", 8, 4, 1, seed=11, combine="sum", bias=(32.0,), rate=0.5), strategy="ptt")
    add_forest("boost_multi", COVTYPE, model(COVTYPE, "balanced", 8, 3, 7, seed=12, combine="sum", link="softmax", rate=0.5, classifier=True), strategy="gemm")
    add_forest("extra_trees", HIGGS, model(HIGGS, "bagged", 16, 5, 2, seed=13, classifier=True), strategy="ptt")
    add_forest("hist_boost", FRAUD, model(FRAUD, "tall", 8, 7, 1, seed=14, combine="sum", link="sigmoid", rate=0.25, classifier=True), strategy="tt")
    # grown on rows drawn by rule between each feature's bounds, so that its SQL can be printed without a table
    rng = np.random.default_rng(15)
    rows = np.stack([rng.uniform(lo, hi if hi > lo else lo + 1, 512) for _, _, lo, hi in HIGGS.features], 1)
    alone = trees.isolation(np.round(rows * 1024) / 1024, trees=16, psi=64, seed=15)
    add_forest("iforest", HIGGS, alone, strategy="tt")
    add("iforest_label", lambda s, d: scored(HIGGS, alone, strategy="ptt")(s, d).groupBy(F.expr("CASE WHEN p0 > 0.5 THEN 1 ELSE 0 END AS outlier")).agg(F.count("*").alias("rows")),
        f"SELECT CASE WHEN p0 > 0.5 THEN 1 ELSE 0 END AS outlier, count(*) AS rows FROM ({forest_sql(alone, HIGGS.names, HIGGS.sql(), list(HIGGS.keys))}) GROUP BY 1")
    add_forest("forest_expr_lane", HIGGS, binary, lane="expression")
    add_forest("forest_batch_1000", HIGGS, binary, strategy="gemm", batch_rows=1000)
    keys = list(HIGGS.keys)

    def leaf_ids(spark, sf_dir):
        dag = chain(HIGGS.names, ("trees.forest", {"spec": numbered_leaves(binary), "strategy": "ptt"}))
        return compile_pipeline(dag, lane="vector").score(HIGGS.frame(spark, sf_dir), keys, ["first", "leaf"]).select(*keys, F.col("leaf").cast("long").alias("leaf"))

    t = binary.trees[0]
    add("tree_leaf_ids", leaf_ids, f"SELECT {', '.join(keys)}, CAST({tree_case(t, HIGGS.names, 0, '<', str)} AS BIGINT) AS leaf FROM ({HIGGS.sql()})")

    def agree(spark, sf_dir):
        """Rows on which the strategies, the batch sizes and the lanes differ: none."""
        outs = [scored(COVTYPE, multi, strategy=s)(spark, sf_dir) for s in ("gemm", "tt", "ptt")]
        first = outs[0]
        differ = first.exceptAll(outs[1]).unionByName(first.exceptAll(outs[2]))
        return first.agg(F.count("*").alias("rows")).crossJoin(differ.agg(F.count("*").alias("differ")))

    add("strategies_agree", agree, "SELECT count(*) AS rows, CAST(0 AS BIGINT) AS differ FROM lineitem")
    for kind, view, outputs, spec in (
        ("fraud", FRAUD, 2, {"classifier": True}), ("year", YEAR, 1, {}), ("covtype", COVTYPE, 7, {"classifier": True}),
        ("higgs", HIGGS, 2, {"classifier": True}), ("airline", AIRLINE, 2, {"classifier": True}), ("epsilon", EPSILON, 2, {"classifier": True}),
    ):
        for shape in ("bagged", "tall", "balanced"):
            boosted = shape != "bagged"
            extra = {**spec, **({"combine": "sum", "rate": 0.5} if boosted else {})}
            add_forest(f"w1_{kind}_{shape}", view, model(view, shape, 8, 8 if shape == "tall" else 6, outputs, seed=20, **extra))
    for depth in (3, 7, 12):
        add_forest(f"w12_depth{depth}", STRATEGY, model(STRATEGY, "bagged", 4, depth, 2, seed=30 + depth, classifier=True))
    add_forest("w16", STRATEGY, model(STRATEGY, "tall", 16, 10, 2, seed=41, classifier=True))

    def choices(spark: SparkSession, sf_dir: str) -> DataFrame:
        lines = read_table(spark, sf_dir, "lineitem", ["l_quantity", "l_linenumber", "l_returnflag"])
        grid = lines.selectExpr("CAST(l_quantity AS INT) % 16 + 1 AS depth", "CASE WHEN l_linenumber < 4 THEN 1 ELSE 1000 END AS batch", "CASE WHEN l_returnflag = 'R' THEN 'accelerator' ELSE 'cpu' END AS device")
        grid = grid.groupBy("depth", "batch", "device").agg(F.count("*").alias("rows"))
        return grid.withColumn("strategy", F.udf(trees.choose_strategy, "string")("depth", "batch", "device"))

    add("strategy_choice_grid", choices,
        "SELECT depth, batch, device, count(*) AS rows, CASE WHEN depth <= CASE device WHEN 'cpu' THEN 3 ELSE 10 END OR (batch <= 16 AND depth <= 10) THEN 'gemm' WHEN depth <= 10 THEN 'ptt' ELSE 'tt' END AS strategy "
        "FROM (SELECT CAST(l_quantity AS INT) % 16 + 1 AS depth, CASE WHEN l_linenumber < 4 THEN 1 ELSE 1000 END AS batch, CASE WHEN l_returnflag = 'R' THEN 'accelerator' ELSE 'cpu' END AS device FROM lineitem) t GROUP BY depth, batch, device")

    def costs(spark: SparkSession, sf_dir: str) -> DataFrame:
        shapes = read_table(spark, sf_dir, "lineitem", ["l_quantity", "l_linenumber"]).selectExpr("2 * CAST(l_quantity AS INT) + 1 AS nodes", "CAST(l_linenumber AS INT) + 5 AS depth").distinct()
        cost = F.udf(lambda strategy, nodes, depth: trees.cost_model(strategy, 28, nodes, 2, depth), "memory long, work long")
        each = shapes.withColumn("strategy", F.explode(F.array(*[F.lit(k) for k in ("gemm", "tt", "ptt")]))).withColumn("cost", cost("strategy", "nodes", "depth"))
        return each.select("strategy", "nodes", "depth", "cost.memory", "cost.work")

    add("strategy_cost_table", costs,
        "SELECT s AS strategy, nodes, depth, CAST(CASE s WHEN 'gemm' THEN 28 * nodes + nodes * nodes + 2 * nodes WHEN 'tt' THEN nodes ELSE 2 ** depth END AS BIGINT) AS memory, "
        "CAST(CASE s WHEN 'gemm' THEN 28 * nodes + nodes * nodes + 2 * nodes ELSE depth END AS BIGINT) AS work "
        "FROM (SELECT DISTINCT 2 * CAST(l_quantity AS INT) + 1 AS nodes, CAST(l_linenumber AS INT) + 5 AS depth FROM lineitem) t, (VALUES ('gemm'), ('tt'), ('ptt')) a(s)")


def numbered_leaves(forest: trees.ForestSpec) -> trees.ForestSpec:
    """The first tree, with each leaf's node number as its value."""
    t = forest.trees[0]
    return trees.ForestSpec((trees.TreeSpec(t.left, t.right, t.feature, t.threshold, np.arange(len(t.left), dtype=float)[:, None]),), cmp=forest.cmp)


# -- other operators ----------------------------------------------------------------------


def rule_weights(rows: int, columns: int, seed: int = 1, scale: float = 1.0) -> np.ndarray:
    """Small dyadic weights by rule."""
    k = np.arange(rows * columns).reshape(rows, columns)
    return ((k * 37 + seed * 11) % 33 - 16) / 64.0 * scale


OPS_CENTRE = np.array([(lo + hi) / 2 for _, _, lo, hi in OPS.features])
OPS_SPREAD = np.array([(hi - lo) / 2 for _, _, lo, hi in OPS.features])
SCALE = ("sc.standard", {"mu": OPS_CENTRE, "sd": OPS_SPREAD})
SCALED = [f"(({n} - {num(m)}) / {num(s)})" for n, m, s in zip(OPS.names, OPS_CENTRE, OPS_SPREAD, strict=True)]
IRIS_RAW = IRIS.names


def steps(view: View, *operators: tuple[str, dict], names: list[str], lane: str = "auto", rules: tuple[str, ...] = ("inject", "push", "fold")) -> Query:
    def run(spark, sf_dir):
        compiled = compile_pipeline(chain(view.names, *operators), lane=lane, rules=rules)
        return whole(compiled.score(view.frame(spark, sf_dir), list(view.keys), names), list(view.keys), names)

    return run


def add_steps(name: str, view: View, operators: list[tuple[str, dict]], outputs: list[str], lane: str = "auto", **more) -> None:
    """``outputs``: the SQL of each output over the view's columns."""
    names = ["prediction", *[f"p{k}" for k in range(len(outputs) - 1)]]
    sql = f"SELECT {', '.join(view.keys)}, {', '.join(f'{o} AS {n}' for o, n in zip(outputs, names, strict=True))} FROM ({view.sql()})"
    add(name, steps(view, *operators, names=names, lane=lane, **more), whole_sql(sql, list(view.keys), names))


def _sig(z: str) -> str:
    return f"(1 / (1 + exp(-{z})))"


def _softmax(zs: list[str]) -> list[str]:
    return [f"(1 / ({' + '.join(f'exp({o} - {z})' for o in zs)}))" for z in zs]


def register_models() -> None:
    w1, b1 = rule_weights(20, 1), np.array([0.25])
    w3, b3 = rule_weights(20, 3, 2), np.array([0.25, 0.0, -0.25])
    [z] = linear_scores(SCALED, w1, b1)
    zs = linear_scores(SCALED, w3, b3)
    label = f"CASE WHEN {z} > 0 THEN 1 ELSE 0 END"
    for name in ("lin_logistic_binary", "lin_logistic_cv", "lin_sgd_log"):
        add_steps(name, OPS, [SCALE, ("lin.linear", {"w": w1, "b": b1, "mode": "log" if "sgd" in name else "logistic"})], [label, f"1 - {_sig(z)}", _sig(z)])
    add_steps("lin_logistic_binary_vector", OPS, [SCALE, ("lin.linear", {"w": w1, "b": b1})], [label, f"1 - {_sig(z)}", _sig(z)], lane="vector")
    add_steps("lin_logistic_multi", OPS, [SCALE, ("lin.linear", {"w": w3, "b": b3, "mode": "softmax"})], [first_largest(zs), *_softmax(zs)])
    total = " + ".join(map(_sig, zs))
    add_steps("lin_logistic_ovr", OPS, [SCALE, ("lin.linear", {"w": w3, "b": b3, "mode": "ovr"})], [first_largest(zs), *[f"{_sig(v)} / ({total})" for v in zs]])
    for name in ("lin_svc", "lin_sgd_hinge"):
        add_steps(name, OPS, [SCALE, ("lin.linear", {"w": w1, "b": b1, "mode": "margin"})], [label, z])
    add_steps("lin_svc_multi", OPS, [SCALE, ("lin.linear", {"w": w3, "b": b3, "mode": "margin"})], [first_largest(zs), *zs])
    huber = f"((greatest(least({z}, 1), -1) + 1) / 2)"
    add_steps("lin_sgd_huber", OPS, [SCALE, ("lin.linear", {"w": w1, "b": b1, "mode": "huber"})], [label, f"1 - {huber}", huber])
    add_steps("lin_regress", OPS, [SCALE, ("lin.linear", {"w": w1, "b": b1, "mode": "regress"})], [z, z])
    # kernel machines: eight support rows by rule
    support, alpha = rule_weights(8, 20, 3), rule_weights(8, 1, 4, 2.0)
    dots = [dot(IRIS_RAW, s) for s in support]
    dist = [f"({' + '.join(f'({n} - {num(v)}) * ({n} - {num(v)})' for n, v in zip(IRIS_RAW, s, strict=True))})" for s in support]
    forms = {"rbf": [f"exp(-0.5::DOUBLE * {d})" for d in dist], "poly": [f"power(0.5::DOUBLE * {d} + 1, 3)" for d in dots], "linear": dots, "sigmoid": [_tanh(f"(0.5::DOUBLE * {d} + 1)") for d in dots]}
    for kernel, ks in forms.items():
        m = f"({' + '.join(f'{num(a)} * {k}' for a, k in zip(alpha[:, 0], ks, strict=True))} + {num(0.125)})"
        params = {"support": support, "alpha": alpha, "b": np.array([0.125]), "kernel": kernel, "gamma": 0.5, "coef0": 1.0, "degree": 3}
        add_steps(f"svm_svc_{kernel}", IRIS, [("svm.svc", params)], [f"CASE WHEN {m} > 0 THEN 1 ELSE 0 END", m])
        if kernel == "rbf":
            add_steps("svm_nusvc", IRIS, [("svm.nusvc", params)], [f"CASE WHEN {m} > 0 THEN 1 ELSE 0 END", m])
    alpha3 = rule_weights(8, 3, 5, 2.0)
    ms = [f"({' + '.join(f'{num(a)} * {k}' for a, k in zip(alpha3[:, j], forms['rbf'], strict=True))} + {num(0.0)})" for j in range(3)]
    wins = [f"(CASE WHEN {a} THEN 1 ELSE 0 END + CASE WHEN {b} THEN 1 ELSE 0 END)" for a, b in ((f"{ms[0]} > 0", f"{ms[1]} > 0"), (f"NOT {ms[0]} > 0", f"{ms[2]} > 0"), (f"NOT {ms[1]} > 0", f"NOT {ms[2]} > 0"))]
    add_steps("svm_svc_multi", IRIS, [("svm.svc", {"support": support, "alpha": alpha3, "b": np.zeros(3), "gamma": 0.5, "classes": 3})], [first_largest(wins), *ms])
    # perceptrons with one hidden layer of four
    h, hb, o, ob = rule_weights(20, 4, 6), np.array([0.1, 0.2, -0.1, 0.0]), rule_weights(4, 3, 7, 4.0), np.array([0.0, 0.125, -0.125])
    inner = linear_scores(IRIS_RAW, h, hb)
    acts = {"relu": lambda v: f"greatest({v}, 0)", "tanh": _tanh, "logistic": _sig, "identity": str}
    for act, f in acts.items():
        zs3 = linear_scores([f(v) for v in inner], o, ob)
        add_steps(f"mlp_{act}", IRIS, [("nn.mlp", {"weights": [h, o], "biases": [hb, ob], "act": act})], [first_largest(zs3), *_softmax(zs3)])
    # Bayes
    p = 0.1 + 0.8 * (np.arange(60).reshape(3, 20) * 7 % 11) / 11.0
    prior = np.array([0.25, 0.25, 0.5])
    bits = [f"(CASE WHEN {n} > 0 THEN 1.0::DOUBLE ELSE 0 END)" for n in IRIS_RAW]
    scores = [f"({dot(bits, np.log(q) - np.log1p(-q))} + {num(np.log1p(-q).sum() + np.log(c))})" for q, c in zip(p, prior, strict=True)]
    add_steps("nb_bernoulli", IRIS, [("nb.bernoulli", {"p": p, "prior": prior})], [first_largest(scores), *_softmax(scores)])
    share = p / p.sum(1, keepdims=True)
    scores = [f"({dot([f'abs({n})' for n in IRIS_RAW], np.log(q))} + {num(np.log(c))})" for q, c in zip(share, prior, strict=True)]
    positive = View("iris_abs", "embeddings", tuple((n, f"abs({e})", lo, hi) for n, e, lo, hi in IRIS.features), IRIS.keys)
    scores = [f"({dot(IRIS_RAW, np.log(q))} + {num(np.log(c))})" for q, c in zip(share, prior, strict=True)]
    add_steps("nb_multinomial", positive, [("nb.multinomial", {"p": share, "prior": prior})], [first_largest(scores), *_softmax(scores)])
    mu, var = rule_weights(3, 20, 8, 0.5), 0.01 + 0.03 * (np.arange(60).reshape(3, 20) % 5)
    scores = [f"({' + '.join(f'(-0.5::DOUBLE * (({n} - {num(m)}) * ({n} - {num(m)}) / {num(v)} + {num(np.log(2 * np.pi * v))}))' for n, m, v in zip(IRIS_RAW, a, b, strict=True))} + {num(np.log(c))})" for a, b, c in zip(mu, var, prior, strict=True)]
    add_steps("nb_gaussian", IRIS, [("nb.gaussian", {"mu": mu, "var": var, "prior": prior})], [first_largest(scores), *_softmax(scores)])


def _tanh(z: str) -> str:
    return f"(1 - 2 / (exp(2 * {z}) + 1))"


def register_featurizers() -> None:
    few = View("ops_few", "fact", OPS.features[:6], OPS.keys)
    names, gaps = few.names, View("ops_gaps", "fact", tuple((n, f"CASE WHEN (l_orderkey * 31 + l_linenumber * 7 + {k}) % 17 = 0 THEN NULL ELSE {e} END", lo, hi) for k, (n, e, lo, hi) in enumerate(OPS.features[:6])), OPS.keys)
    c, s = OPS_CENTRE[:6], OPS_SPREAD[:6]
    each = lambda f: [f(n, k) for k, n in enumerate(names)]
    affine = each(lambda n, k: f"(({n} - {num(c[k])}) / {num(s[k])})")
    for name, op in (("scale_standard", ("sc.standard", {"mu": c, "sd": s})), ("scale_robust", ("sc.robust", {"center": c, "scale": s}))):
        add_steps(name, few, [op], affine)
        add_steps(f"{name}_vector", few, [op], affine, lane="vector")
    add_steps("scale_maxabs", few, [("sc.maxabs", {"m": s})], each(lambda n, k: f"({n} / {num(s[k])})"))
    lo, hi = c - s, c + s
    plain = each(lambda n, k: f"(({n} - {num(lo[k])}) / {num(hi[k] - lo[k])})")
    add_steps("scale_minmax", few, [("sc.minmax", {"lo": lo, "hi": hi})], plain)
    add_steps("scale_minmax_clip", few, [("sc.minmax", {"lo": lo, "hi": hi, "clip": True})], [f"greatest(least({p}, 1), 0)" for p in plain])
    add_steps("scale_constant_column", few, [("sc.standard", {"mu": c, "sd": [0.0, *s[1:]]})], [f"({names[0]} - {num(c[0])})", *affine[1:]])
    add_steps("binarize", few, [("disc.binarize", {"threshold": 2.0})], each(lambda n, k: f"CASE WHEN {n} > 2 THEN 1 ELSE 0 END"))
    for norm, size in {"l1": " + ".join(f"abs({n})" for n in names), "l2": f"sqrt({' + '.join(f'{n} * {n}' for n in names)})", "max": f"greatest({', '.join(f'abs({n})' for n in names)})"}.items():
        add_steps(f"normalize_{norm}", few, [("sc.normalize", {"norm": norm})], each(lambda n, k, size=size: f"({n} / ({size}))"))
    for name, values in (("impute_mean", c), ("impute_median", np.round(c)), ("impute_mode", lo), ("impute_const", np.full(6, -1.0))):
        add_steps(name, gaps, [("imp.simple", {"values": values})], each(lambda n, k, v=values: f"coalesce({n}, {num(v[k])})"))
    add_steps("impute_mean_vector", gaps, [("imp.simple", {"values": c})], each(lambda n, k: f"coalesce({n}, {num(c[k])})"), lane="vector")
    add_steps("missing_indicator", gaps, [("imp.indicator", {})], each(lambda n, k: f"CASE WHEN {n} IS NULL THEN 1 ELSE 0 END"))
    edges = [[float(lo[k] + (hi[k] - lo[k]) * j / 4) for j in (1, 2, 3)] for k in range(6)]
    code = each(lambda n, k: f"({' + '.join(f'CASE WHEN {n} >= {num(e)} THEN 1 ELSE 0 END' for e in edges[k])})")
    add_steps("kbins_uniform", few, [("disc.kbins", {"edges": edges})], code)
    add_steps("kbins_onehot", few, [("disc.kbins", {"edges": edges, "encode": "onehot"})], [f"CASE WHEN {x} = {j} THEN 1 ELSE 0 END" for x in code for j in range(4)])
    for name, terms in (("poly_deg2", polynomial_terms(4)), ("poly_deg3", polynomial_terms(3, 3)), ("poly_interaction", polynomial_terms(4, 2, True, False))):
        short = View(name, "fact", OPS.features[2:6], OPS.keys)
        add_steps(name, short, [("poly.features", {"terms": terms})], [f"({' * '.join(['1.0::DOUBLE', *[short.names[k] for k in t]])})" for t in terms])
    short = View("interact", "fact", OPS.features[2:5], OPS.keys)
    a, b, d = short.names
    pairs = [f"{x} * {y}" for x, y in ((a, a), (b, b), (d, d), (a, b), (a, d), (b, d))]
    add_steps("interact_outer", short, [("poly.interact", {})], pairs, lane="vector")
    add_steps("interact_pairwise", short, [("poly.interact", {"naive": True})], pairs, lane="vector")
    add_steps("interact_expression", short, [("poly.interact", {})], pairs, lane="expression")
    w = rule_weights(20, 3, 9)
    centre = rule_weights(1, 20, 10)[0]
    comp = [f"({' + '.join(f'({n} - {num(m)}) * {num(v)}' for n, m, v in zip(IRIS_RAW, centre, w[:, j], strict=True))})" for j in range(3)]
    for name in ("pca", "ica"):
        add_steps(name, IRIS, [("dec.project", {"mu": centre, "w": w})], comp)
    add_steps("pca_whiten", IRIS, [("dec.project", {"mu": centre, "w": w, "scale": np.array([0.5, 0.25, 2.0])})], [f"({x} / {num(v)})" for x, v in zip(comp, (0.5, 0.25, 2.0), strict=True)])
    add_steps("tsvd", IRIS, [("dec.project", {"mu": np.zeros(20), "w": w})], [dot(IRIS_RAW, w[:, j]) for j in range(3)])
    support = rule_weights(4, 20, 11)
    ks = [f"exp(-0.5::DOUBLE * ({' + '.join(f'({n} - {num(v)}) * ({n} - {num(v)})' for n, v in zip(IRIS_RAW, r, strict=True))}))" for r in support]
    mean = np.array([0.5, 0.25, 0.125, 0.0])
    coef = rule_weights(4, 2, 12, 4.0)
    rowmean = f"(({' + '.join(ks)}) / 4)"
    add_steps("kpca", IRIS, [("dec.kpca", {"support": support, "gamma": 0.5, "column_mean": mean, "grand_mean": 0.25, "a": coef})],
              [f"({' + '.join(f'({k} - {rowmean} - {num(m)} + {num(0.25)}) * {num(v)}' for k, m, v in zip(ks, mean, coef[:, j], strict=True))})" for j in range(2)])
    for name, kept in (("sel_kbest", [0, 2]), ("sel_percentile", [1, 3, 5]), ("sel_variance", [0, 1, 4])):
        add_steps(name, few, [("sel.columns", {"kept": kept})], [names[k] for k in kept])


def register_categories() -> None:
    keys = list(LINE_KEYS)
    source = View("categories", "star", COVTYPE.features[:1], LINE_KEYS)

    def query(signature: str, column: str, params: dict, names: list[str], lane: str) -> Query:
        def run(spark, sf_dir):
            b = Builder()
            b.strings(column, signature, **params)
            frame = source.frame(spark, sf_dir, [column])
            return whole(compile_pipeline(b.build(), lane=lane).score(frame, keys, names), keys, names)

        return run

    def both(name: str, column: str, signature: str, params: dict, outputs: list[str], lane: str) -> None:
        names = ["prediction", *[f"p{k}" for k in range(len(outputs) - 1)]]
        sql = f"SELECT {', '.join(keys)}, {', '.join(f'{o} AS {n}' for o, n in zip(outputs, names, strict=True))} FROM ({source.sql([column])})"
        add(name, query(signature, column, params, names, lane), whole_sql(sql, keys, names))

    is_type = [f"CASE WHEN p_type = '{t}' THEN 1 ELSE 0 END" for t in TYPES]
    for form, lane in (("broadcast", "vector"), ("broadcast", "expression"), ("fixed", "vector"), ("fixed", "expression"), ("lookup", "vector"), ("lookup", "expression")):
        both(f"onehot_{form}_{lane}", "p_type", "cat.onehot", {"vocabulary": TYPES, "form": form}, is_type, lane)
    both("onehot_unknown", "p_type", "cat.onehot", {"vocabulary": TYPES[:3]}, is_type[:3], "expression")
    both("onehot_dropfirst", "p_type", "cat.onehot", {"vocabulary": TYPES[1:]}, is_type[1:], "expression")
    both("fixed_bytes_overlong", "p_type", "cat.onehot", {"vocabulary": ["LARG", "STAND", "PROMO"], "form": "fixed"}, ["0", "0", is_type[3]], "vector")
    place = " ".join(f"WHEN '{v}' THEN {k}" for k, v in enumerate(sorted(BRANDS)))
    both("label_encode", "p_brand", "cat.label", {"vocabulary": BRANDS}, [f"CASE p_brand {place} ELSE -1 END"], "expression")
    both("label_encode_vector", "p_brand", "cat.label", {"vocabulary": BRANDS}, [f"CASE p_brand {place} ELSE -1 END"], "vector")
    names = ["prediction", *[f"p{k}" for k in range(7)]]
    add("feature_hash", query("cat.hash", "p_brand", {"buckets": 8}, names, "vector"))


# -- rewrites -----------------------------------------------------------------------------


def on_off(name: str, view: View, dag: Callable[[], PipelineDag], outputs: list[str], on: tuple[str, ...]) -> None:
    names = ["prediction", *[f"p{k}" for k in range(len(outputs) - 1)]]
    sql = f"SELECT {', '.join(view.keys)}, {', '.join(f'{o} AS {n}' for o, n in zip(outputs, names, strict=True))} FROM ({view.sql()})"
    for suffix, rules in (("off", ()), ("on", on)):

        def run(spark, sf_dir, rules=rules):
            compiled = compile_pipeline(dag(), lane="vector", rules=rules)
            return whole(compiled.score(view.frame(spark, sf_dir), list(view.keys), names), list(view.keys), names)

        add(f"{name}_{suffix}", run, whole_sql(sql, list(view.keys), names))


def sparse_weights(share: float) -> np.ndarray:
    w = rule_weights(20, 1, 13)
    w[np.arange(20) >= max(1, round(20 * share))] = 0.0
    return w


def register_rewrites() -> None:
    kept = [0, 4, 9]
    scaled = [SCALED[k] for k in kept]
    on_off("pushdown_scaler", OPS, lambda: chain(OPS.names, SCALE, ("sel.columns", {"kept": kept})), scaled, ("push",))
    norm = f"sqrt({' + '.join(f'{x} * {x}' for x in SCALED)})"
    on_off("pushdown_blocked", OPS, lambda: chain(OPS.names, SCALE, ("sc.normalize", {}), ("sel.columns", {"kept": kept})), [f"({x} / {norm})" for x in scaled], ("push",))
    terms = polynomial_terms(20)
    chosen = [0, 1, 25, 60]
    on_off("pushdown_poly", OPS, lambda: chain(OPS.names, SCALE, ("poly.features", {"terms": terms}), ("sel.columns", {"kept": chosen})),
           [f"({' * '.join(['1.0::DOUBLE', *[SCALED[k] for k in terms[t]]])})" for t in chosen], ("push",))
    edges = [[float(m)] for m in OPS_CENTRE]
    on_off("pushdown_kbins", OPS, lambda: chain(OPS.names, ("disc.kbins", {"edges": edges, "encode": "onehot"}), ("sel.columns", {"kept": [1, 6, 7]})),
           [f"CASE WHEN {OPS.names[0]} >= {num(OPS_CENTRE[0])} THEN 1 ELSE 0 END", f"CASE WHEN {OPS.names[3]} >= {num(OPS_CENTRE[3])} THEN 0 ELSE 1 END", f"CASE WHEN {OPS.names[3]} >= {num(OPS_CENTRE[3])} THEN 1 ELSE 0 END"], ("push",))
    b = np.array([0.25])
    for share in (0.05, 0.2, 1.0):
        w = sparse_weights(share)
        [z] = linear_scores(SCALED, w, b)
        name = f"w14_s{round(share * 100):02d}" if share != 0.05 else "inject_linear"
        on_off(name, OPS, lambda w=w: chain(OPS.names, SCALE, ("lin.linear", {"w": w, "b": b})), [f"CASE WHEN {z} > 0 THEN 1 ELSE 0 END", f"1 - {_sig(z)}", _sig(z)], ("inject", "push"))
    small = model(HIGGS, "balanced", 4, 2, 2, seed=50, classifier=True)
    sql = forest_sql(small, HIGGS.names, HIGGS.sql(), list(HIGGS.keys))
    for suffix, rules in (("off", ()), ("on", ("inject", "push"))):
        add(f"inject_tree_{suffix}", lambda s, d, rules=rules: compile_pipeline(chain(HIGGS.names, ("trees.forest", {"spec": small})), lane="vector", rules=rules).score(HIGGS.frame(s, d), list(HIGGS.keys)), sql)
    w = rule_weights(20, 4, 14)
    head = rule_weights(4, 1, 15)
    [z] = linear_scores(SCALED, w @ head, b)
    on_off("fold_linear", OPS, lambda: chain(OPS.names, SCALE, ("dec.project", {"mu": np.zeros(20), "w": w}), ("lin.linear", {"w": head, "b": b, "mode": "margin"})), [f"CASE WHEN {z} > 0 THEN 1 ELSE 0 END", z], ("fold",))
    from .operators.models import Linear
    from .pipeline import stack_linear

    several = [Linear(rule_weights(20, 1, 16 + k), np.array([0.1 * k])) for k in range(3)]
    together = stack_linear(several)
    zs = [linear_scores(SCALED, m.w, m.b)[0] for m in several]
    add_steps("stack_batched_on", OPS, [SCALE, ("lin.linear", {"w": together.w, "b": together.b, "mode": "margin"})], [first_largest(zs), *zs])

    def apart(spark, sf_dir):
        out = OPS.frame(spark, sf_dir)
        keep = list(OPS.keys)
        for k, m in enumerate(several):
            keep_now = [*out.columns]
            out = compile_pipeline(chain(OPS.names, SCALE, ("lin.linear", {"w": m.w, "b": m.b, "mode": "margin"})), lane="expression").score(out, keep_now, [f"_l{k}", f"p{k}"]).drop(f"_l{k}")
        top = F.greatest("p0", "p1", "p2")
        label: Column = F.when(F.col("p0") == top, 0.0).when(F.col("p1") == top, 1.0).otherwise(2.0)
        return whole(out.withColumn("prediction", label), keep, ["prediction", "p0", "p1", "p2"])

    add("stack_batched_off", apart, ORACLES["stack_batched_on"])
    # a featurizer branch of strings and one of numbers with gaps, a percentile selection, a logistic model
    for percent in (10, 50, 90):
        add_mixed(percent)


def add_mixed(percent: int) -> None:
    view = View("mixed", "star", tuple((n, f"CASE WHEN (l_orderkey * 31 + l_linenumber * 7 + {k}) % 17 = 0 THEN NULL ELSE {e} END", lo, hi) for k, (n, e, lo, hi) in enumerate(YEAR.features[:16])), LINE_KEYS)
    centre = np.array([(lo + hi) / 2 for _, _, lo, hi in view.features])
    spread = np.array([max((hi - lo) / 2, 0.5) for _, _, lo, hi in view.features])
    total = 16 + len(BRANDS) + len(TYPES)
    kept = [k for k in range(total) if k * 37 % 100 < percent]
    w = rule_weights(len(kept), 1, 17)

    def dag() -> PipelineDag:
        b = Builder()
        numbers = b.then(b.then(b.pick(view.names), "imp.simple", values=centre), "sc.standard", mu=centre, sd=spread)
        brands = b.strings("p_brand", "cat.onehot", vocabulary=BRANDS)
        types = b.strings("p_type", "cat.onehot", vocabulary=TYPES)
        b.then(b.then([numbers, brands, types], "sel.columns", kept=kept), "lin.linear", w=w, b=np.array([0.125]))
        return b.build()

    every = [f"((coalesce({n}, {num(m)}) - {num(m)}) / {num(s)})" for n, m, s in zip(view.names, centre, spread, strict=True)]
    every += [f"(CASE WHEN p_brand = '{v}' THEN 1.0::DOUBLE ELSE 0 END)" for v in BRANDS] + [f"(CASE WHEN p_type = '{v}' THEN 1.0::DOUBLE ELSE 0 END)" for v in TYPES]
    [z] = linear_scores([every[k] for k in kept], w, np.array([0.125]))
    names = ["prediction", "p0", "p1"]
    sql = f"SELECT {', '.join(view.keys)}, CASE WHEN {z} > 0 THEN 1 ELSE 0 END AS prediction, 1 - {_sig(z)} AS p0, {_sig(z)} AS p1 FROM ({view.sql(['p_brand', 'p_type'])})"
    for suffix, rules in (("off", ()), ("on", ("inject", "push"))):

        def run(spark, sf_dir, rules=rules):
            compiled = compile_pipeline(dag(), lane="vector", rules=rules)
            return whole(compiled.score(view.frame(spark, sf_dir, ["p_brand", "p_type"]), list(view.keys), names), list(view.keys), names)

        add(f"w13_p{percent}_{suffix}", run, whole_sql(sql, list(view.keys), names))


register_trees()
register_models()
register_featurizers()
register_categories()
register_rewrites()
__all__ = ["ORACLES", "QUERIES"]
