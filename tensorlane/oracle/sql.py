"""Models as nested conditionals and closed formulas in DuckDB SQL."""

from __future__ import annotations

import numpy as np


def num(v: float) -> str:
    return f"({float(v)!r})::DOUBLE"


def tree_case(tree, names: list[str], output: int, cmp: str = "<", leaf=None) -> str:
    """One tree as nested CASE; ``leaf`` maps a node to its text."""

    def walk(k: int) -> str:
        if tree.left[k] == k:
            return leaf(k) if leaf else num(tree.value[k, output])
        return f"CASE WHEN {names[tree.feature[k]]} {cmp} {num(tree.threshold[k])} THEN {walk(int(tree.left[k]))} ELSE {walk(int(tree.right[k]))} END"

    return walk(0)


def first_largest(scores: list[str]) -> str:
    top = f"greatest({', '.join(scores)})"
    cases = " ".join(f"WHEN {s} = {top} THEN {k}" for k, s in enumerate(scores))
    return f"(CASE {cases} END)::DOUBLE"


def forest_sql(forest, names: list[str], view: str, keys: list[str]) -> str:
    """prediction, p0, p1 ... of a forest over a view's SQL."""
    n = len(forest.trees)
    outs = range(forest.outputs)
    if forest.combine == "vote":
        parts = [[f"CASE WHEN {tree_case(t, names, 0, forest.cmp, lambda k, t=t: str(int(t.value[k].argmax())))} = {j} THEN 1 ELSE 0 END" for t in forest.trees] for j in outs]
        raw = [f"(({' + '.join(p)})::DOUBLE / {n})" for p in parts]
    else:
        sums = [f"({' + '.join(tree_case(t, names, j, forest.cmp) for t in forest.trees)})" for j in outs]
        if forest.combine == "mean":
            raw = [f"({s} / {n})" for s in sums]
        elif forest.combine == "isolation":
            from math import log

            c = 2.0 * (log(forest.psi - 1.0) + 0.5772156649) - 2.0 * (forest.psi - 1.0) / forest.psi
            raw = [f"power(2::DOUBLE, -({s} / {n}) / {num(c)})" for s in sums]
        else:
            raw = [f"({num(forest.bias[min(j, len(forest.bias) - 1)])} + {num(forest.rate)} * {s})" for j, s in zip(outs, sums, strict=True)]
    inner = ", ".join(f"{r} AS z{j}" for j, r in enumerate(raw))
    zs = [f"z{j}" for j in outs]
    return f"SELECT {', '.join(keys)}, {linked(forest.link, zs, forest.classifier)} FROM (SELECT {', '.join(keys)}, {inner} FROM ({view}))"


def linked(link: str, zs: list[str], classifier: bool) -> str:
    if link == "sigmoid":
        p = f"(1 / (1 + exp(-{zs[0]})))"
        ps = [f"(1 - {p})", p]
    elif link == "softmax":
        total = " + ".join(f"exp({z})" for z in zs)
        ps = [f"(exp({z}) / ({total}))" for z in zs]
    else:
        ps = zs
    label = first_largest(ps) if classifier else ps[0]
    return ", ".join([f"{label} AS prediction", *[f"{p} AS p{j}" for j, p in enumerate(ps)]])


def dot(names: list[str], w) -> str:
    parts = [f"{n} * {num(v)}" for n, v in zip(names, w, strict=True) if v != 0]
    return f"({' + '.join(parts)})" if parts else num(0)


def linear_scores(names: list[str], w: np.ndarray, b: np.ndarray) -> list[str]:
    return [f"({dot(names, w[:, j])} + {num(b[j])})" for j in range(w.shape[1])]


def fixed(expr: str, scale: int = 10_000) -> str:
    """A value as a whole number of 1/scale, half up, in SQL that both engines share."""
    return f"CAST(floor(({expr}) * {scale} + 0.5) AS BIGINT)"
