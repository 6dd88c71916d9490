"""Tree ensembles as tensors: three formulations with different redundancy.

``gemm`` evaluates every decision and finds the leaf by two matrix products; ``tt`` moves a
cursor through child tables a fixed number of times; ``ptt`` fills trees up to perfect ones
and moves by arithmetic.  All give the same leaf.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

import numpy as np

from .kernels import argmax, sigmoid, softmax

#: Bytes of a tile's arrays, which should stay in the processor's cache.
TILE = 512 << 10


class UnsupportedSplit(ValueError):
    """A categorical or missing-value split, which no formulation covers."""


class OverBudget(ValueError):
    """Perfect trees that would exceed the memory limit."""


@dataclass(frozen=True)
class TreeSpec:
    """Nodes as parallel arrays; node 0 is the root; a leaf has left == right == itself."""

    left: np.ndarray
    right: np.ndarray
    feature: np.ndarray
    threshold: np.ndarray
    value: np.ndarray  #: nodes x outputs

    @property
    def is_leaf(self) -> np.ndarray:
        return self.left == np.arange(len(self.left))

    def depth(self) -> int:
        level, now = 0, np.array([0])
        while not self.is_leaf[now].all():
            inner = now[~self.is_leaf[now]]
            now = np.concatenate([self.left[inner], self.right[inner]])
            level += 1
        return level


@dataclass(frozen=True)
class ForestSpec:
    trees: tuple[TreeSpec, ...]
    combine: str = "mean"  #: mean, sum, vote, isolation
    link: str = "identity"  #: identity, sigmoid, softmax
    bias: tuple[float, ...] = (0.0,)
    rate: float = 1.0
    cmp: str = "<"
    classifier: bool = False
    psi: int = 256  #: isolation forests: size of the training samples

    @property
    def outputs(self) -> int:
        return self.trees[0].value.shape[1]

    def depth(self) -> int:
        return max(t.depth() for t in self.trees)

    def features(self) -> list[int]:
        """Features that some decision reads."""
        used = {int(f) for t in self.trees for f in t.feature[~t.is_leaf]}
        return sorted(used)

    def renumbered(self, kept: list[int]) -> ForestSpec:
        place = {f: k for k, f in enumerate(kept)}
        return replace(self, trees=tuple(replace(t, feature=np.array([place.get(int(f), 0) for f in t.feature])) for t in self.trees))


def tree(nodes: list[tuple], outputs: int) -> TreeSpec:
    """A tree from (feature, threshold, left, right) decisions and (value, ...) leaves, in node order."""
    n = len(nodes)
    left, right, feature, threshold, value = np.arange(n), np.arange(n), np.zeros(n, int), np.zeros(n), np.zeros((n, outputs))
    for k, node in enumerate(nodes):
        if isinstance(node[0], str):
            raise UnsupportedSplit(node[0])
        if len(node) == 4:
            feature[k], threshold[k], left[k], right[k] = node
        else:
            value[k] = node[0]
    return TreeSpec(left, right, feature, threshold, value)


# -- tensors ------------------------------------------------------------------------------


@dataclass
class GemmTensors:
    feature: np.ndarray  #: trees x decisions; an index list in place of a projection matrix
    threshold: np.ndarray
    ancestry: np.ndarray  #: trees x decisions x leaves: 1 left, -1 right
    lefts: np.ndarray  #: trees x leaves; -1 for padding, which no score equals
    value: np.ndarray  #: trees x leaves x outputs
    sizes: np.ndarray  #: trees x 2: decisions and leaves without padding, one at least

    def nbytes(self) -> int:
        return sum(a.nbytes for a in (self.feature, self.threshold, self.ancestry, self.lefts, self.value, self.sizes))


def gemm_tensors(forest: ForestSpec) -> GemmTensors:
    most_d = max(1, max(int((~t.is_leaf).sum()) for t in forest.trees))
    most_l = max(int(t.is_leaf.sum()) for t in forest.trees)
    n = len(forest.trees)
    out = GemmTensors(np.zeros((n, most_d), int), np.full((n, most_d), -np.inf), np.zeros((n, most_d, most_l), np.float32), np.full((n, most_l), -1, np.float32), np.zeros((n, most_l, forest.outputs)), np.ones((n, 2), int))
    for k, t in enumerate(forest.trees):
        decision = {int(v): i for i, v in enumerate(np.flatnonzero(~t.is_leaf))}
        leaf = {int(v): i for i, v in enumerate(np.flatnonzero(t.is_leaf))}
        out.sizes[k] = max(1, len(decision)), len(leaf)
        for v, i in decision.items():
            out.feature[k, i], out.threshold[k, i] = t.feature[v], t.threshold[v]
        stack: list[tuple[int, list[tuple[int, int]]]] = [(0, [])]
        while stack:
            v, path = stack.pop()
            if v in leaf:
                for i, sign in path:
                    out.ancestry[k, i, leaf[v]] = sign
                out.lefts[k, leaf[v]] = sum(sign == 1 for _, sign in path)
                out.value[k, leaf[v]] = t.value[v]
            else:
                stack += [(int(t.left[v]), [*path, (decision[v], 1)]), (int(t.right[v]), [*path, (decision[v], -1)])]
    return out


@dataclass
class TraversalTensors:
    left: np.ndarray
    right: np.ndarray
    feature: np.ndarray
    threshold: np.ndarray
    value: np.ndarray
    depth: int

    def nbytes(self) -> int:
        return sum(a.nbytes for a in (self.left, self.right, self.feature, self.threshold, self.value))


def tt_tensors(forest: ForestSpec) -> TraversalTensors:
    """Tables padded to the largest tree; every leaf points to itself, so further steps change nothing."""
    n, most = len(forest.trees), max(len(t.left) for t in forest.trees)
    own = np.tile(np.arange(most), (n, 1))
    out = TraversalTensors(own.copy(), own.copy(), np.zeros((n, most), int), np.zeros((n, most)), np.zeros((n, most, forest.outputs)), forest.depth())
    for k, t in enumerate(forest.trees):
        m = len(t.left)
        out.left[k, :m], out.right[k, :m], out.feature[k, :m], out.threshold[k, :m], out.value[k, :m] = t.left, t.right, t.feature, t.threshold, t.value
    return out


@dataclass
class PerfectTensors:
    feature: np.ndarray  #: flat; place of (level, tree, slot) by the layout
    threshold: np.ndarray
    value: np.ndarray  #: trees x 2^depth x outputs
    depth: int
    layout: str

    def nbytes(self) -> int:
        return sum(a.nbytes for a in (self.feature, self.threshold, self.value))


def ptt_tensors(forest: ForestSpec, layout: str = "level_interleaved", limit: int = 512 << 20) -> PerfectTensors:
    n, depth = len(forest.trees), forest.depth()
    if n * 2**depth * (2 + forest.outputs) * 8 > limit:
        raise OverBudget(f"perfect trees of depth {depth} exceed {limit} bytes")
    feature, threshold, value = np.zeros((n, 2**depth), int), np.zeros((n, 2**depth)), np.zeros((n, 2**depth, forest.outputs))
    for k, t in enumerate(forest.trees):
        holds = np.zeros(1, int)  # which node of the tree stands in each slot of a level; leaves stay in both children
        for level in range(depth):
            at = slice(2**level, 2 ** (level + 1))
            feature[k, at], threshold[k, at] = t.feature[holds], t.threshold[holds]
            holds = np.stack([t.left[holds], t.right[holds]], 1).ravel()
        value[k] = t.value[holds]
    if layout == "level_interleaved":
        levels = [slice(2**i, 2 ** (i + 1)) for i in range(depth)]
        feature = np.concatenate([feature[:, s].ravel() for s in levels] or [np.zeros(0, int)])
        threshold = np.concatenate([threshold[:, s].ravel() for s in levels] or [np.zeros(0)])
    else:
        feature, threshold = feature.ravel(), threshold.ravel()
    return PerfectTensors(feature, threshold, value, depth, layout)


# -- leaf values of every tree for a batch ------------------------------------------------


def _test(x: np.ndarray, t: np.ndarray, cmp: str) -> np.ndarray:
    with np.errstate(invalid="ignore"):
        return x < t if cmp == "<" else x <= t


def gemm_sum(x: np.ndarray, g: GemmTensors, cmp: str, per_tree=None, budget: int = TILE) -> np.ndarray:
    """Sum over trees, in their order, of the reached leaves' values.

    Trees and rows go in tiles that stay in the processor's cache; a tile's products are as large as its largest tree.
    Exactly one leaf is reached, so a product with the leaves' numbers gives its number.
    """
    trees, decisions, leaves = g.ancestry.shape
    rows = max(1, min(len(x), budget // (4 * (leaves + decisions))))
    chunk = max(1, budget // (4 * (leaves + decisions) * rows))
    numbers = np.arange(leaves, dtype=np.float32)
    out = np.zeros((len(x), g.value.shape[2]))
    for a in range(0, len(x), rows):
        columns = np.ascontiguousarray(x[a : a + rows].T)
        for k in range(0, trees, chunk):
            s = slice(k, k + chunk)
            d, n = g.sizes[s].max(0)
            verdict = _test(columns[g.feature[s, :d]], g.threshold[s, :d, None], cmp).astype(np.float32)
            reached = (g.ancestry[s, :d, :n].transpose(0, 2, 1) @ verdict == g.lefts[s, :n, None]).astype(np.float32)
            at = (numbers[:n] @ reached).astype(int)
            values = g.value[np.arange(k, k + len(at))[:, None], at]
            for part in values if per_tree is None else per_tree(values):
                out[a : a + rows] += part
    return out


def tt_leaves(x: np.ndarray, t: TraversalTensors, cmp: str, extra: int = 0) -> np.ndarray:
    """Cursor (trees x rows) after the fixed number of steps."""
    rows = np.arange(len(x))
    base = (np.arange(len(t.left)) * t.left.shape[1])[:, None]
    left, right, feature, threshold = t.left.ravel(), t.right.ravel(), t.feature.ravel(), t.threshold.ravel()
    at = np.zeros((len(t.left), len(x)), int)
    for _ in range(t.depth + extra):
        k = base + at
        at = np.where(_test(x[rows, feature[k]], threshold[k], cmp), left[k], right[k])
    return at


def tt_unrolled(t: TraversalTensors, cmp: str):
    """A straight line of steps for one tree set, composed when it is made: no loop counter and no test for the end."""
    base = (np.arange(len(t.left)) * t.left.shape[1])[:, None]
    left, right, feature, threshold = t.left.ravel(), t.right.ravel(), t.feature.ravel(), t.threshold.ravel()

    def step(before):
        def move(x, rows, at):
            at = before(x, rows, at)
            k = base + at
            return np.where(_test(x[rows, feature[k]], threshold[k], cmp), left[k], right[k])

        return move

    walk = reduce(lambda f, _: step(f), range(t.depth), lambda x, rows, at: at)
    return lambda x: walk(x, np.arange(len(x)), np.zeros((len(t.left), len(x)), int))


def ptt_leaves(x: np.ndarray, p: PerfectTensors, cmp: str) -> np.ndarray:
    """Leaf slot (trees x rows): double the cursor and add one where the test fails."""
    n = len(p.value)
    rows, trees = np.arange(len(x)), np.arange(n)[:, None]
    at = np.ones((n, len(x)), int)
    for level in range(p.depth):
        if p.layout == "level_interleaved":
            k = n * (2**level - 1) + trees * 2**level + (at - 2**level)
        else:
            k = trees * 2**p.depth + at
        at = 2 * at + ~_test(x[rows, p.feature[k]], p.threshold[k], cmp)
    return at - 2**p.depth


# -- a compiled forest --------------------------------------------------------------------


def _votes(values: np.ndarray) -> np.ndarray:
    return np.eye(values.shape[-1])[values.argmax(-1)]


def average_path(n: float) -> float:
    """Mean depth of an unsuccessful search among n samples, by the harmonic number's expansion."""
    return 0.0 if n <= 1 else 1.0 if n == 2 else 2.0 * (np.log(n - 1.0) + 0.5772156649) - 2.0 * (n - 1.0) / n


@dataclass
class CompiledForest:
    """A forest lowered by one strategy; ``raw`` gives combined outputs, ``finish`` applies the link."""

    forest: ForestSpec
    strategy: str
    layout: str = "level_interleaved"
    unroll: bool = False
    tensors: object = field(init=False)

    def __post_init__(self) -> None:
        make = {"gemm": gemm_tensors, "tt": tt_tensors, "ptt": lambda f: ptt_tensors(f, self.layout)}
        self.tensors = make[self.strategy](self.forest)
        self._walk = tt_unrolled(self.tensors, self.forest.cmp) if self.unroll and self.strategy == "tt" else None

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_walk"}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self._walk = tt_unrolled(self.tensors, self.forest.cmp) if self.unroll and self.strategy == "tt" else None

    def leaf_values(self, x: np.ndarray) -> np.ndarray:
        """trees x rows x outputs."""
        t = self.tensors
        if self.strategy == "tt":
            at = self._walk(x) if self._walk else tt_leaves(x, t, self.forest.cmp)
        elif self.strategy == "ptt":
            at = ptt_leaves(x, t, self.forest.cmp)
        else:
            verdict = _test(x[:, t.feature].transpose(1, 0, 2), t.threshold[:, None, :], self.forest.cmp).astype(np.float32)
            at = (verdict @ t.ancestry == t.lefts[:, None, :]).argmax(-1)
        return t.value[np.arange(len(t.value))[:, None], at]

    def raw(self, x: np.ndarray) -> np.ndarray:
        f = self.forest
        per_tree = _votes if f.combine == "vote" else None
        if self.strategy == "gemm":
            total = gemm_sum(x, self.tensors, f.cmp, per_tree)
        else:
            rows = max(1, TILE // (8 * len(f.trees) * (f.outputs + 2)))
            parts = [self.leaf_values(x[k : k + rows]) for k in range(0, len(x), rows)]
            total = np.concatenate([(p if per_tree is None else per_tree(p)).sum(0) for p in parts]) if parts else np.zeros((0, f.outputs))
        if f.combine in ("mean", "vote", "isolation"):
            total = total / len(f.trees)
            return 2.0 ** (-total / average_path(f.psi)) if f.combine == "isolation" else total
        return np.asarray(f.bias) + f.rate * total

    def finish(self, raw: np.ndarray) -> np.ndarray:
        if self.forest.link == "sigmoid":
            p = sigmoid(raw)
            return np.concatenate([1.0 - p, p], 1)
        return softmax(raw) if self.forest.link == "softmax" else raw

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(prediction, outputs after the link)."""
        out = self.finish(self.raw(x))
        return (argmax(out).astype(float) if self.forest.classifier else out[:, 0]), out


# -- choosing a strategy ------------------------------------------------------------------


@dataclass(frozen=True)
class StrategyThresholds:
    """Depth limits of the heuristic; a small batch favours the products."""

    gemm_depth: int = 3
    gemm_depth_accelerator: int = 10
    perfect_depth: int = 10
    small_batch: int = 16


def choose_strategy(depth: int, batch_rows: int = 10_000, device: str = "cpu", thresholds: StrategyThresholds | None = None) -> str:
    """Products for shallow trees or small batches, perfect trees up to a depth, cursors beyond."""
    t = thresholds or StrategyThresholds()
    gemm = t.gemm_depth if device == "cpu" else t.gemm_depth_accelerator
    if depth <= gemm or (batch_rows <= t.small_batch and depth <= t.perfect_depth):
        return "gemm"
    return "ptt" if depth <= t.perfect_depth else "tt"


def cost_model(strategy: str, features: int, nodes: int, classes: int, depth: int) -> tuple[int, int]:
    """(memory, work for a row) of one tree, up to a constant: matrices hold products of sizes, tables the nodes, perfect trees 2^depth."""
    if strategy == "gemm":
        size = features * nodes + nodes * nodes + classes * nodes
        return size, size
    return (nodes, depth) if strategy == "tt" else (2**depth, depth)


def isolation(x: np.ndarray, trees: int = 100, psi: int = 256, seed: int = 1) -> ForestSpec:
    """An isolation forest grown on the rows of ``x``: random splits of random samples down to the mean depth of a search.

    A leaf's value is its depth and the mean path that its rows would still have; the score is 2^(-mean value / c(psi)).
    """
    rng = np.random.default_rng(seed)
    psi = min(psi, len(x))
    limit = int(np.ceil(np.log2(max(psi, 2))))
    grown = []
    for _ in range(trees):
        nodes: list[tuple] = [()]
        waiting = [(0, rng.choice(len(x), psi, replace=False), 0)]
        while waiting:
            k, rows, level = waiting.pop()
            part = x[rows]
            varied = np.flatnonzero(part.min(0) < part.max(0)) if len(rows) > 1 and level < limit else np.zeros(0, int)
            if not len(varied):
                nodes[k] = ([level + average_path(len(rows))],)
                continue
            f = int(varied[rng.integers(len(varied))])
            t = float(rng.uniform(part[:, f].min(), part[:, f].max()))
            go = part[:, f] < t
            if go.all() or not go.any():
                t = float(part[:, f].max())
                go = part[:, f] < t
            a = len(nodes)
            nodes += [(), ()]
            nodes[k] = (f, t, a, a + 1)
            waiting += [(a, rows[go], level + 1), (a + 1, rows[~go], level + 1)]
        grown.append(tree(nodes, 1))
    return ForestSpec(tuple(grown), combine="isolation", psi=psi)


# -- generated forests --------------------------------------------------------------------


def generate(seed: int, trees: int, max_depth: int, grid: list[list[float]], outputs: int, shape: str = "bagged", **spec) -> ForestSpec:
    """A forest by rule from a seed.  Thresholds come from ``grid`` (per feature), leaf values are whole 1024ths.

    ``bagged``: splits stop at random; ``balanced``: all branches reach the depth; ``tall``: one leaf splits at
    each level, so the tree is as deep as allowed and thin.  Not trained: the shape is the point.
    """
    rng = np.random.default_rng(seed)
    usable = [f for f, g in enumerate(grid) if g]
    grown = []
    for _ in range(trees):
        nodes: list[list] = [[]]
        open_leaves = [(0, 0)]
        while open_leaves:
            k, level = open_leaves.pop(0)
            if level < max_depth and (shape != "bagged" or level == 0 or rng.random() < 0.8):
                f = usable[rng.integers(len(usable))]
                a = len(nodes)
                nodes[k] = [f, grid[f][rng.integers(len(grid[f]))], a, a + 1]
                nodes += [[], []]
                deeper = [(a, level + 1), (a + 1, level + 1)]
                if shape == "tall":
                    keep = rng.integers(2)
                    open_leaves.append(deeper[keep])
                    nodes[deeper[1 - keep][0]] = [None]
                else:
                    open_leaves += deeper
            else:
                nodes[k] = [None]
        for node in nodes:
            if len(node) < 4:
                node[:] = [rng.integers(0, 1025, outputs) / 1024.0 if outputs > 1 else [int(rng.integers(-512, 513)) / 1024.0]]
        grown.append(tree([tuple(n) for n in nodes], outputs))
    return ForestSpec(tuple(grown), **spec)
