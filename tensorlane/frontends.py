"""Front-ends: fitted models of other libraries, specs and dumps, as pipeline graphs.

An extractor turns one fitted stage into the signature and the parameters of an operator.
Extractors are registered by the stage's class name, so users may add their own.
"""

from __future__ import annotations

import json
from collections.abc import Callable

import numpy as np

from .operators.featurizers import Pick
from .pipeline import Builder, OpNode, PipelineDag
from .trees import ForestSpec, TreeSpec, UnsupportedSplit, tree

Steps = list[tuple[str, dict]]
EXTRACTORS: dict[str, Callable[[object], Steps]] = {}


class UnknownStage(KeyError):
    """No extractor is registered for a stage's class."""


def extractor(*class_names: str):
    def add(take):
        for name in class_names:
            EXTRACTORS[name] = take
        return take

    return add


def extract(stage) -> Steps:
    name = type(stage).__name__
    if name not in EXTRACTORS:
        raise UnknownStage(name)
    return EXTRACTORS[name](stage)


def supported(stages: list) -> bool:
    """Whether every stage of a pipeline has an extractor (or is an assembler)."""
    return all(type(s).__name__ in EXTRACTORS or type(s).__name__ == "VectorAssembler" for s in stages)


# -- Spark's own library ------------------------------------------------------------------


def _vector(v) -> np.ndarray:
    return np.asarray(v.toArray(), float)


def _jvm_tree(root, outputs: int, leaf: Callable[[object], list[float]]) -> TreeSpec:
    """A tree held by the JVM, node by node; its tests are value <= threshold."""
    nodes: list[tuple] = [()]
    waiting = [(0, root)]
    while waiting:
        k, node = waiting.pop()
        if node.subtreeDepth() == 0:
            nodes[k] = (leaf(node),)
            continue
        split = node.split()
        if split.getClass().getSimpleName() != "ContinuousSplit":
            raise UnsupportedSplit("categorical split")
        a = len(nodes)
        nodes += [(), ()]
        nodes[k] = (split.featureIndex(), split.threshold(), a, a + 1)
        waiting += [(a, node.leftChild()), (a + 1, node.rightChild())]
    return tree(nodes, outputs)


def _class_shares(classes: int):
    def take(node) -> list[float]:
        counts = np.array([float(x) for x in node.impurityStats().stats()])[:classes]
        return (counts / counts.sum()).tolist()

    return take


def _prediction(node) -> list[float]:
    return [node.prediction()]


def _forest(trees: list[TreeSpec], **spec) -> Steps:
    return [("trees.forest", {"spec": ForestSpec(tuple(trees), cmp="<=", **spec)})]


@extractor("DecisionTreeClassificationModel")
def _(m) -> Steps:
    return _forest([_jvm_tree(m._java_obj.rootNode(), m.numClasses, _class_shares(m.numClasses))], classifier=True)


@extractor("RandomForestClassificationModel")
def _(m) -> Steps:
    return _forest([_jvm_tree(t.rootNode(), m.numClasses, _class_shares(m.numClasses)) for t in m._java_obj.trees()], classifier=True)


@extractor("DecisionTreeRegressionModel")
def _(m) -> Steps:
    return _forest([_jvm_tree(m._java_obj.rootNode(), 1, _prediction)])


@extractor("RandomForestRegressionModel")
def _(m) -> Steps:
    return _forest([_jvm_tree(t.rootNode(), 1, _prediction) for t in m._java_obj.trees()])


def _weighted(m, factor: float) -> list[TreeSpec]:
    return [_jvm_tree(t.rootNode(), 1, lambda n, w=w: [n.prediction() * w * factor]) for t, w in zip(m._java_obj.trees(), m.treeWeights, strict=True)]


@extractor("GBTRegressionModel")
def _(m) -> Steps:
    return _forest(_weighted(m, 1.0), combine="sum")


@extractor("GBTClassificationModel")
def _(m) -> Steps:
    return _forest(_weighted(m, 2.0), combine="sum", link="sigmoid", classifier=True)  # the library's loss has twice the margin


@extractor("LogisticRegressionModel")
def _(m) -> Steps:
    w, b = np.asarray(m.coefficientMatrix.toArray(), float).T, _vector(m.interceptVector)
    return [("lin.linear", {"w": w, "b": b, "mode": "logistic" if w.shape[1] == 1 else "softmax"})]


@extractor("LinearSVCModel")
def _(m) -> Steps:
    return [("lin.linear", {"w": _vector(m.coefficients)[:, None], "b": np.array([m.intercept - m.getThreshold()]), "mode": "margin"})]


@extractor("LinearRegressionModel", "GeneralizedLinearRegressionModel")
def _(m) -> Steps:
    return [("lin.linear", {"w": _vector(m.coefficients)[:, None], "b": np.array([m.intercept]), "mode": "regress"})]


@extractor("NaiveBayesModel")
def _(m) -> Steps:
    theta, prior = np.asarray(m.theta.toArray(), float), np.exp(_vector(m.pi))
    if m.getModelType() == "gaussian":
        return [("nb.gaussian", {"mu": theta, "var": np.asarray(m.sigma.toArray(), float), "prior": prior})]
    if m.getModelType() == "bernoulli":
        return [("nb.bernoulli", {"p": np.exp(theta), "prior": prior})]
    return [("nb.multinomial", {"p": np.exp(theta), "prior": prior})]


@extractor("StandardScalerModel")
def _(m) -> Steps:
    mu, sd = _vector(m.mean), _vector(m.std)
    return [("sc.standard", {"mu": mu if m.getWithMean() else np.zeros(len(mu)), "sd": sd if m.getWithStd() else np.ones(len(sd))})]


@extractor("MinMaxScalerModel")
def _(m) -> Steps:
    return [("sc.minmax", {"lo": _vector(m.originalMin), "hi": _vector(m.originalMax), "to": (m.getMin(), m.getMax())})]


@extractor("MaxAbsScalerModel")
def _(m) -> Steps:
    return [("sc.maxabs", {"m": _vector(m.maxAbs)})]


@extractor("RobustScalerModel")
def _(m) -> Steps:
    center, scale = _vector(m.median), _vector(m.range)
    return [("sc.robust", {"center": center if m.getWithCentering() else np.zeros(len(center)), "scale": scale if m.getWithScaling() else np.ones(len(scale))})]


@extractor("PCAModel")
def _(m) -> Steps:
    w = np.asarray(m.pc.toArray(), float)
    return [("dec.project", {"mu": np.zeros(len(w)), "w": w})]  # the library projects without centring


@extractor("ChiSqSelectorModel", "UnivariateFeatureSelectorModel", "VarianceThresholdSelectorModel")
def _(m) -> Steps:
    return [("sel.columns", {"kept": sorted(int(k) for k in m.selectedFeatures)})]


@extractor("Normalizer")
def _(m) -> Steps:
    norms = {1.0: "l1", 2.0: "l2", float("inf"): "max"}
    return [("sc.normalize", {"norm": norms[m.getP()]})]


@extractor("Binarizer")
def _(m) -> Steps:
    return [("disc.binarize", {"threshold": m.getThreshold()})]


@extractor("Bucketizer")
def _(m) -> Steps:
    return [("disc.kbins", {"edges": [[float(x) for x in m.getSplits()[1:-1]]]})]


@extractor("ImputerModel")
def _(m) -> Steps:
    row = m.surrogateDF.first()
    return [("imp.simple", {"values": np.array([row[c] for c in m.getInputCols()], float)})]


def from_mllib(model) -> PipelineDag:
    """A fitted pipeline (or a single fitted stage over an assembled vector) of Spark's library as a graph.

    Vectors are followed by their column names; a column that no stage makes is a raw one.
    """
    stages = list(model.stages)
    b, made = Builder(), {}

    def node(names: list[str]) -> list[str]:
        out: list[str] = []
        for n in names:
            out.append(made[n] if n in made else b.pick([n]))
        return out

    for s in stages:
        kind = type(s).__name__
        if kind == "VectorAssembler":
            names = s.getInputCols()
            made[s.getOutputCol()] = b.pick(names) if not any(n in made for n in names) else b.then(node(names), "sel.columns", kept=_all(b, node(names)))
            continue
        steps = extract(s)
        if kind == "ImputerModel":
            at = b.pick(s.getInputCols())
            for signature, params in steps:
                at = b.then(at, signature, **params)
            for k, name in enumerate(s.getOutputCols()):
                made[name] = b.then(at, "sel.columns", kept=[k])
            continue
        get = s.getFeaturesCol if s.hasParam("featuresCol") and kind not in ("ChiSqSelectorModel",) and not kind.endswith("SelectorModel") else None
        source = get() if get else s.getFeaturesCol() if s.hasParam("featuresCol") else s.getInputCol()
        [at] = node([source])
        for signature, params in steps:
            at = b.then(at, signature, **params)
        made[s.getOutputCol() if s.hasParam("outputCol") else s.getPredictionCol()] = at
    return b.build()


def _all(b: Builder, nodes: list[str]) -> list[int]:
    widths = b.build().widths()
    return list(range(sum(widths[n] for n in nodes)))


# -- specs --------------------------------------------------------------------------------


def _plain(value):
    if isinstance(value, ForestSpec):
        trees = [{k: np.asarray(getattr(t, k)).tolist() for k in ("left", "right", "feature", "threshold", "value")} for t in value.trees]
        return {"forest": trees, **{k: getattr(value, k) for k in ("combine", "link", "bias", "rate", "cmp", "classifier", "psi")}}
    if isinstance(value, np.ndarray):
        return {"array": value.tolist()}
    return [_plain(v) for v in value] if isinstance(value, (list, tuple)) else value


def _rich(value):
    if isinstance(value, dict) and "forest" in value:
        rest = {k: tuple(v) if k == "bias" else v for k, v in value.items() if k != "forest"}
        return ForestSpec(tuple(TreeSpec(*(np.asarray(t[k], int if k in ("left", "right", "feature") else float) for k in ("left", "right", "feature", "threshold", "value"))) for t in value["forest"]), **rest)
    if isinstance(value, dict) and "array" in value:
        return np.asarray(value["array"])
    return [_rich(v) for v in value] if isinstance(value, list) else value


def to_json(nodes: list[dict]) -> str:
    """A spec: nodes with ``id``, ``signature``, ``inputs`` (ids, or raw columns where ``raw``) and ``params``."""
    return json.dumps([{**n, "params": {k: _plain(v) for k, v in n.get("params", {}).items()}} for n in nodes])


def from_json(text: str) -> PipelineDag:
    from .operators.base import lower

    nodes = []
    for n in json.loads(text):
        params = {k: _rich(v) for k, v in n.get("params", {}).items()}
        raw = bool(n.get("raw"))
        op = Pick(list(n["inputs"])) if n["signature"] == "col.pick" else lower(n["signature"], **params)
        nodes.append(OpNode(n["id"], n["signature"], tuple(n["inputs"]), op, raw))
    return PipelineDag(tuple(nodes))


# -- boosting dumps -----------------------------------------------------------------------


def from_nested_dump(text: str, columns: list[str], *, base: float = 0.0, link: str = "identity", outputs: int = 1) -> ForestSpec:
    """Boosted trees from a dump of nested JSON nodes (``split``, ``split_condition``, ``yes``, ``no``, ``children``, ``leaf``).

    ``yes`` holds where the value is less than the condition.  With several outputs tree number t adds to output
    t modulo ``outputs``.  ``base`` is a margin.  A split on a set of categories is rejected.
    """
    place = {c: k for k, c in enumerate(columns)}
    grown = []
    for number, root in enumerate(json.loads(text)):
        nodes: list[tuple] = [()]
        waiting = [(0, root)]
        while waiting:
            k, n = waiting.pop()
            if "leaf" in n:
                value = [0.0] * outputs
                value[number % outputs] = float(n["leaf"])
                nodes[k] = (value,)
                continue
            if isinstance(n.get("split_condition"), list) or "split_condition" not in n:
                raise UnsupportedSplit("categorical split")
            child = {c["nodeid"]: c for c in n["children"]}
            a = len(nodes)
            nodes += [(), ()]
            name = n["split"]
            feature = place[name] if name in place else int(str(name).lstrip("f"))
            nodes[k] = (feature, float(n["split_condition"]), a, a + 1)
            waiting += [(a, child[n["yes"]]), (a + 1, child[n["no"]])]
        grown.append(tree(nodes, outputs))
    return ForestSpec(tuple(grown), combine="sum", link=link, bias=(base,) * outputs, cmp="<", classifier=link != "identity")


def from_sectioned_dump(text: str, *, link: str = "identity", outputs: int = 1) -> ForestSpec:
    """Boosted trees from a text of ``Tree=k`` sections with key=value lists, where a negative child -j is leaf j - 1.

    The left child holds where the value is at most the threshold.  Bit 0 of a decision type marks a categorical split, which is rejected.
    """
    grown = []
    for number, section in enumerate(text.split("Tree=")[1:]):
        fields = dict(line.split("=", 1) for line in section.splitlines()[1:] if "=" in line)

        def numbers(name: str, kind=float, fields=fields) -> list:
            return [kind(x) for x in fields.get(name, "").split()]

        if any(d & 1 for d in numbers("decision_type", int)):
            raise UnsupportedSplit("categorical split")
        leaves = numbers("leaf_value")
        inner = len(numbers("split_feature", int))

        def value(v: float, number=number) -> tuple:
            out = [0.0] * outputs
            out[number % outputs] = v
            return (out,)

        def place(child: int, inner=inner) -> int:
            return child if child >= 0 else inner - child - 1

        rows = zip(numbers("split_feature", int), numbers("threshold"), numbers("left_child", int), numbers("right_child", int), strict=True)
        nodes = [(f, t, place(a), place(b)) for f, t, a, b in rows] + [value(v) for v in leaves]
        grown.append(tree(nodes, outputs))
    return ForestSpec(tuple(grown), combine="sum", link=link, bias=(0.0,) * outputs, cmp="<=", classifier=link != "identity")


# -- exchange nodes -----------------------------------------------------------------------


def _exchange_forest(a: dict) -> Steps:
    """Trees as parallel lists over all nodes; leaf weights come as (tree, node, output, weight)."""
    modes = {"BRANCH_LT": "<", "BRANCH_LEQ": "<="}
    used = {m for m in a["nodes_modes"] if m != "LEAF"}
    if len(used) > 1 or not used <= set(modes):
        raise UnsupportedSplit(", ".join(sorted(used)))
    kind = "class" if "class_weights" in a else "target"
    outputs = max(a[f"{kind}_ids"]) + 1
    grown = []
    for t in sorted(set(a["nodes_treeids"])):
        at = [k for k, x in enumerate(a["nodes_treeids"]) if x == t]
        where = {a["nodes_nodeids"][k]: j for j, k in enumerate(at)}
        weights = {n: [0.0] * outputs for n in where}
        for owner, n, j, w in zip(a[f"{kind}_treeids"], a[f"{kind}_nodeids"], a[f"{kind}_ids"], a[f"{kind}_weights"], strict=True):
            if owner == t:
                weights[n][j] += float(w)
        nodes = [
            (weights[a["nodes_nodeids"][k]],) if a["nodes_modes"][k] == "LEAF"
            else (a["nodes_featureids"][k], float(a["nodes_values"][k]), where[a["nodes_truenodeids"][k]], where[a["nodes_falsenodeids"][k]])
            for k in at
        ]
        grown.append(tree(nodes, outputs))
    links = {"NONE": "identity", "LOGISTIC": "sigmoid", "SOFTMAX": "softmax"}
    spec = {"combine": "sum", "link": links[a.get("post_transform", "NONE")], "bias": tuple(a.get("base_values", [0.0] * outputs)), "classifier": kind == "class"}
    return [("trees.forest", {"spec": ForestSpec(tuple(grown), cmp=modes[used.pop()] if used else "<", **spec)})]


def _exchange_linear(a: dict) -> Steps:
    n = len(a["intercepts"])
    w = np.asarray(a["coefficients"], float).reshape(n, -1).T
    mode = "regress" if not a.get("classifier") else "logistic" if n == 1 else "softmax"
    return [("lin.linear", {"w": w, "b": np.asarray(a["intercepts"], float), "mode": mode})]


EXCHANGE: dict[str, Callable[[dict], Steps]] = {
    "TreeEnsembleClassifier": _exchange_forest,
    "TreeEnsembleRegressor": _exchange_forest,
    "LinearClassifier": lambda a: _exchange_linear({**a, "classifier": True}),
    "LinearRegressor": _exchange_linear,
    "Scaler": lambda a: [("sc.affine", {"shift": np.asarray(a["offset"], float), "scale": 1.0 / np.asarray(a["scale"], float)})],
    "Normalizer": lambda a: [("sc.normalize", {"norm": a["norm"].lower()})],
    "Binarizer": lambda a: [("disc.binarize", {"threshold": a["threshold"]})],
    "Imputer": lambda a: [("imp.simple", {"values": np.asarray(a["imputed_value_floats"], float)})],
    "ArrayFeatureExtractor": lambda a: [("sel.columns", {"kept": list(a["indices"])})],
}


def from_exchange(columns: list[str], nodes: list[tuple[str, dict]]) -> PipelineDag:
    """A chain of exchange-format nodes (operator type, attributes) over raw columns."""
    b = Builder()
    at = b.pick(columns)
    for kind, attributes in nodes:
        if kind not in EXCHANGE:
            raise UnknownStage(kind)
        for signature, params in EXCHANGE[kind](attributes):
            at = b.then(at, signature, **params)
    return b.build()
