"""Models other than trees: linear, kernel, neural and Bayesian scorers.  Outputs: prediction, then one score a class."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..kernels import ACTIVATIONS, argmax, logsumexp, sigmoid, softmax, squared_distances
from ..trees import CompiledForest, ForestSpec, choose_strategy
from .base import NoExpression, Operator, array, converter


def _dot(xs: list[Column], w) -> Column:
    """A dot product as a balanced sum, which keeps the expression shallow."""
    parts = [x * F.lit(float(v)) for x, v in zip(xs, w, strict=True)] or [F.lit(0.0)]
    while len(parts) > 1:
        parts = [parts[k] + parts[k + 1] if k + 1 < len(parts) else parts[k] for k in range(0, len(parts), 2)]
    return parts[0]


def _first_largest(scores: list[Column]) -> Column:
    top = F.greatest(*scores)
    out = F.lit(float(len(scores) - 1))
    for k in range(len(scores) - 2, -1, -1):
        out = F.when(scores[k] == top, F.lit(float(k))).otherwise(out)
    return out


def _sigmoid(z: Column) -> Column:
    e = F.exp(-F.abs(z))
    return F.when(z >= 0, F.lit(1.0)).otherwise(e) / (F.lit(1.0) + e)


@converter("lin.linear")
@dataclass
class Linear(Operator):
    """w x + b and a link.  ``mode``: logistic, softmax, ovr (sigmoids over their sum), margin (sign or arg-max), log, huber, regress."""

    w: np.ndarray  #: inputs x columns
    b: np.ndarray
    mode: str = "logistic"
    threshold: float = 0.5

    def width(self, inputs):
        k = self.w.shape[1]
        return 2 if self.mode == "regress" else 3 if self.mode in ("logistic", "log", "huber") else 1 + k

    def vector(self, x):
        z = x @ self.w + array(self.b)
        if self.mode in ("logistic", "log", "huber"):
            p = sigmoid(z) if self.mode != "huber" else (np.clip(z, -1.0, 1.0) + 1.0) / 2.0
            return np.concatenate([(p > self.threshold).astype(float), 1.0 - p, p], 1)
        if self.mode == "regress":
            return np.concatenate([z, z], 1)
        if self.mode == "margin":
            label = (z > 0).astype(float) if z.shape[1] == 1 else argmax(z)[:, None].astype(float)
            return np.concatenate([label, z], 1)
        p = softmax(z) if self.mode == "softmax" else (s := sigmoid(z)) / s.sum(1, keepdims=True)
        return np.concatenate([argmax(p)[:, None].astype(float), p], 1)

    def expr(self, xs):
        z = [_dot(xs, self.w[:, j]) + F.lit(float(self.b[j])) for j in range(self.w.shape[1])]
        if self.mode in ("logistic", "log", "huber"):
            p = _sigmoid(z[0]) if self.mode != "huber" else (F.greatest(F.least(z[0], F.lit(1.0)), F.lit(-1.0)) + 1.0) / 2.0
            return [(p > F.lit(self.threshold)).cast("double"), F.lit(1.0) - p, p]
        if self.mode == "regress":
            return [z[0], z[0]]
        if self.mode == "margin":
            return [(z[0] > 0).cast("double") if len(z) == 1 else _first_largest(z), *z]
        if self.mode == "softmax":
            top = F.greatest(*z)
            e = [F.exp(v - top) for v in z]
        else:
            e = [_sigmoid(v) for v in z]
        total = sum(e[1:], e[0])
        p = [v / total for v in e]
        return [_first_largest(p), *p]

    def live(self) -> list[int]:
        """Inputs with a weight other than zero in some column."""
        return np.flatnonzero(np.any(self.w != 0, axis=1)).tolist()

    def reindexed(self, kept: list[int]) -> Linear:
        return Linear(self.w[kept], self.b, self.mode, self.threshold)


@converter("svm.svc")
@dataclass
class KernelMachine(Operator):
    """Kernel expansions; with more than one column, pairwise votes among the classes, ties to the lower.  NuSVC scores alike."""

    support: np.ndarray
    alpha: np.ndarray  #: support rows x columns
    b: np.ndarray
    kernel: str = "rbf"
    gamma: float = 1.0
    coef0: float = 0.0
    degree: int = 3
    classes: int = 2
    block: int = 4096

    def width(self, inputs):
        return 1 + self.alpha.shape[1]

    def _kernel(self, x, s):
        if self.kernel == "rbf":
            return np.exp(-self.gamma * squared_distances(x, s))
        dot = x @ s.T
        if self.kernel == "linear":
            return dot
        inner = self.gamma * dot + self.coef0
        return inner**self.degree if self.kernel == "poly" else np.tanh(inner)

    def vector(self, x):
        z = np.tile(array(self.b), (len(x), 1))
        for k in range(0, len(self.support), self.block):  # partial margins over blocks of support rows
            z = z + self._kernel(x, self.support[k : k + self.block]) @ self.alpha[k : k + self.block]
        if z.shape[1] == 1:
            return np.concatenate([(z > 0).astype(float), z], 1)
        votes, pair = np.zeros((len(x), self.classes)), 0
        for i in range(self.classes):
            for j in range(i + 1, self.classes):
                first = z[:, pair] > 0
                votes[:, i] += first
                votes[:, j] += ~first
                pair += 1
        return np.concatenate([argmax(votes)[:, None].astype(float), z], 1)


@converter("svm.nusvc")
def nusvc(**params) -> KernelMachine:
    return KernelMachine(**params)


@converter("nn.mlp")
@dataclass
class Perceptron(Operator):
    weights: list[np.ndarray]
    biases: list[np.ndarray]
    act: str = "relu"

    def width(self, inputs):
        return 1 + max(2, len(self.biases[-1]))

    def vector(self, x):
        for w, b in zip(self.weights[:-1], self.biases[:-1], strict=True):
            x = ACTIVATIONS[self.act](x @ w + b)
        z = x @ self.weights[-1] + self.biases[-1]
        p = softmax(z) if z.shape[1] > 1 else np.concatenate([1.0 - (q := sigmoid(z)), q], 1)
        return np.concatenate([argmax(p)[:, None].astype(float), p], 1)


@converter("nb.log_linear")
@dataclass
class LogLinearBayes(Operator):
    """Class scores linear in (binarised) inputs: multinomial and Bernoulli models with their constants folded."""

    w: np.ndarray
    b: np.ndarray
    binarize: float | None = None

    def width(self, inputs):
        return 1 + self.w.shape[1]

    def vector(self, x):
        if self.binarize is not None:
            x = (x > self.binarize).astype(float)
        z = x @ self.w + self.b
        p = np.exp(z - logsumexp(z))
        return np.concatenate([argmax(z)[:, None].astype(float), p], 1)


@converter("nb.bernoulli")
def bernoulli(p, prior, binarize=0.0) -> LogLinearBayes:
    """``p``: classes x inputs; log(1 - p) summed is a constant of the class."""
    p = array(p)
    return LogLinearBayes((np.log(p) - np.log1p(-p)).T, np.log1p(-p).sum(1) + np.log(array(prior)), binarize)


@converter("nb.multinomial")
def multinomial(p, prior) -> LogLinearBayes:
    return LogLinearBayes(np.log(array(p)).T, np.log(array(prior)))


@converter("nb.gaussian")
@dataclass
class GaussianBayes(Operator):
    """Quadratic scores expanded into products with x squared, x and 1, so no n x classes x inputs tensor is made."""

    mu: np.ndarray  #: classes x inputs
    var: np.ndarray
    prior: np.ndarray

    def width(self, inputs):
        return 1 + len(self.prior)

    def vector(self, x):
        mu, var = array(self.mu), array(self.var)
        constant = np.log(array(self.prior)) - 0.5 * (np.log(2 * np.pi * var) + mu * mu / var).sum(1)
        z = (x * x) @ (-0.5 / var).T + x @ (mu / var).T + constant
        p = np.exp(z - logsumexp(z))
        return np.concatenate([argmax(z)[:, None].astype(float), p], 1)


def _cursor_step(t, x: Column, cmp: str):
    """One move of a cursor (from 1) through a tree's literal arrays."""
    feature, threshold = F.lit((t.feature + 1).tolist()), F.lit(t.threshold.tolist())
    left, right = F.lit((t.left + 1).tolist()), F.lit((t.right + 1).tolist())

    def step(at, _):
        value, bound = F.element_at(x, F.element_at(feature, at)), F.element_at(threshold, at)
        test = (value < bound) if cmp == "<" else (value <= bound)
        return F.when(test, F.element_at(left, at)).otherwise(F.element_at(right, at)).cast("int")

    return step


@converter("trees.forest")
@dataclass
class Forest(Operator):
    """Any tree model; the strategy is chosen on its depth unless forced."""

    spec: ForestSpec
    strategy: str = "auto"
    layout: str = "level_interleaved"
    unroll: bool = False
    batch_rows: int = 10_000
    _compiled = None

    def width(self, inputs):
        return 1 + (2 if self.spec.link == "sigmoid" else self.spec.outputs)

    def chosen(self) -> str:
        return choose_strategy(self.spec.depth(), self.batch_rows) if self.strategy == "auto" else self.strategy

    def compiled(self) -> CompiledForest:
        if self._compiled is None:
            self._compiled = CompiledForest(self.spec, self.chosen(), self.layout, self.unroll)
        return self._compiled

    def vector(self, x):
        label, out = self.compiled().predict(x)
        return np.concatenate([label[:, None], out], 1)

    def expr(self, xs):
        """Level-by-level lookups in literal arrays; the cursor is a bound variable, so the expression does not multiply."""
        f = self.spec
        if f.link != "identity" or f.combine not in ("mean", "sum"):
            raise NoExpression("only mean and sum forests without link")
        outputs = []
        x = F.array(*xs)
        leaves = []
        for t in f.trees:
            depth = t.depth()
            leaves.append(F.aggregate(F.sequence(F.lit(1), F.lit(depth)), F.lit(1), _cursor_step(t, x, f.cmp)) if depth else F.lit(1))
        for j in range(f.outputs):
            parts = [F.element_at(F.lit(t.value[:, j].tolist()), at) for t, at in zip(f.trees, leaves, strict=True)]
            total = sum(parts[1:], parts[0])
            outputs.append(total / float(len(f.trees)) if f.combine == "mean" else total * f.rate + f.bias[min(j, len(f.bias) - 1)])
        return [_first_largest(outputs) if f.classifier else outputs[0], *outputs]

    def live(self) -> list[int]:
        return self.spec.features()

    def reindexed(self, kept: list[int]) -> Forest:
        return Forest(self.spec.renumbered(kept), self.strategy, self.layout, self.unroll, self.batch_rows)
