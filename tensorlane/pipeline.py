"""Pipelines as graphs of operators, and the passes over them.

A node takes the outputs of other nodes side by side, or raw columns of the table.  The
rewrites work on this graph, before Spark sees anything: the columns that no operator
needs any more are then left out of the projection, and so out of the Parquet scan.
"""

from __future__ import annotations

from dataclasses import dataclass, field, fields, replace

import numpy as np

from .operators import featurizers, models
from .operators.base import Operator, lower, precision
from .operators.featurizers import Project, Scale, Select
from .operators.models import Forest, Linear
from .trees import ForestSpec, TreeSpec

INPUT = "col.pick"


@dataclass(frozen=True)
class OpNode:
    op_id: str
    signature: str
    inputs: tuple[str, ...]  #: node ids, or raw columns of a leaf
    op: Operator
    leaf: bool = False


@dataclass(frozen=True)
class PipelineDag:
    """Nodes in topological order; the last one is the output."""

    nodes: tuple[OpNode, ...]
    notes: tuple[str, ...] = ()

    def widths(self) -> dict[str, int]:
        w: dict[str, int] = {}
        for n in self.nodes:
            w[n.op_id] = n.op.width(len(n.inputs) if n.leaf else sum(w[i] for i in n.inputs))
        return w

    def live_columns(self) -> list[str]:
        """Raw columns read, in order of first use."""
        return list(dict.fromkeys(c for n in self.nodes if n.leaf for c in n.inputs))

    def text_columns(self) -> set[str]:
        return {c for n in self.nodes if n.leaf and getattr(n.op, "strings", False) for c in n.inputs}

    def op_count(self) -> int:
        return sum(n.op.calls for n in self.nodes if not (n.leaf and n.signature == INPUT))

    def run(self, columns: dict[str, object], kind: type = np.float64) -> np.ndarray:
        """The output for a batch: raw columns as arrays (or lists of strings), computed in a floating type."""
        with precision(kind):
            return self._run(columns, kind)

    def _run(self, columns: dict[str, object], kind: type) -> np.ndarray:
        made: dict[str, np.ndarray] = {}
        for n in self.nodes:
            if n.leaf and getattr(n.op, "strings", False):
                x = columns[n.inputs[0]]
            else:
                source = columns if n.leaf else made
                parts = [np.asarray(source[i], kind) for i in n.inputs]
                x = np.stack(parts, 1) if n.leaf else parts[0] if len(parts) == 1 else np.concatenate(parts, 1)
            made[n.op_id] = np.asarray(n.op.vector(x), kind)
        return made[self.nodes[-1].op_id]

    def single(self) -> PipelineDag:
        """The pipeline with every parameter, thresholds and leaf values too, rounded to single precision."""
        return replace(self, nodes=tuple(replace(n, op=_single(n.op)) for n in self.nodes))

    def batched(self, rows: int | None) -> PipelineDag:
        """The pipeline with its forests told how many rows they get at once, which their strategy depends on."""
        return replace(self, nodes=tuple(replace(n, op=replace(n.op, batch_rows=rows)) if rows and isinstance(n.op, Forest) else n for n in self.nodes))

    def expressions(self, column) -> list:
        """The output as Spark columns; ``column(name)`` gives a raw one."""
        made: dict[str, list] = {}
        for n in self.nodes:
            xs = [column(c) for c in n.inputs] if n.leaf else [x for i in n.inputs for x in made[i]]
            made[n.op_id] = n.op.expr(xs)
        return made[self.nodes[-1].op_id]

    def explain(self) -> str:
        w = self.widths()
        rows = [f"{n.op_id}: {n.signature} <- {', '.join(n.inputs) if len(n.inputs) < 6 else f'{len(n.inputs)} columns'} -> {w[n.op_id]}" for n in self.nodes]
        return "\n".join([*rows, *self.notes])


def _single(value):
    if isinstance(value, np.ndarray):
        return value.astype(np.float32) if value.dtype == np.float64 else value
    if isinstance(value, (list, tuple)) and not isinstance(value, str):
        return type(value)(_single(v) for v in value)
    if isinstance(value, (Operator, ForestSpec, TreeSpec)):
        return replace(value, **{f.name: _single(getattr(value, f.name)) for f in fields(value) if f.init})
    return value


@dataclass
class Builder:
    """Collects nodes: ``pick`` and ``strings`` start branches, ``then`` continues them."""

    nodes: list[OpNode] = field(default_factory=list)

    def _add(self, signature: str, inputs: tuple[str, ...], op: Operator, leaf: bool) -> str:
        name = f"n{len(self.nodes)}"
        self.nodes.append(OpNode(name, signature, inputs, op, leaf))
        return name

    def pick(self, columns: list[str]) -> str:
        return self._add(INPUT, tuple(columns), featurizers.Pick(list(columns)), True)

    def strings(self, column: str, signature: str, **params) -> str:
        return self._add(signature, (column,), lower(signature, **params), True)

    def then(self, inputs: str | list[str], signature: str, **params) -> str:
        return self._add(signature, (inputs,) if isinstance(inputs, str) else tuple(inputs), lower(signature, **params), False)

    def build(self) -> PipelineDag:
        return PipelineDag(tuple(self.nodes))


def chain(columns: list[str], *steps: tuple[str, dict]) -> PipelineDag:
    """A straight pipeline: columns, then operators one after the other."""
    b = Builder()
    at = b.pick(columns)
    for signature, params in steps:
        at = b.then(at, signature, **params)
    return b.build()


# -- rewrites -----------------------------------------------------------------------------


def inject_selection(dag: PipelineDag) -> PipelineDag:
    """Put a selection before a final model that reads only some inputs, and renumber the model."""
    last = dag.nodes[-1]
    if not isinstance(last.op, (Linear, Forest)):
        return dag
    inputs = sum(dag.widths()[i] for i in last.inputs)
    live = last.op.live()
    if len(live) == inputs:
        return dag
    if not live:
        live = [0]  # a model of its bias alone still needs a row's shape
    select = OpNode(f"{last.op_id}s", "sel.columns", last.inputs, Select(live))
    return replace(dag, nodes=(*dag.nodes[:-1], select, replace(last, inputs=(select.op_id,), op=last.op.reindexed(live))))


def push_selection(dag: PipelineDag) -> PipelineDag:
    """Move every selection towards the inputs as far as the operators allow.

    Outputs that a selection drops are dropped by the operator below it, and so on down; a
    blocking operator keeps the selection above itself.  Nodes shared by consumers keep
    the union of what these need.
    """
    widths = dag.widths()
    needs: dict[str, set[int]] = {dag.nodes[-1].op_id: set(range(widths[dag.nodes[-1].op_id]))}
    plan: dict[str, tuple[Operator | None, list[int], list[int]]] = {}
    notes = list(dag.notes)
    for n in reversed(dag.nodes):  # which outputs are needed, from the end
        total = len(n.inputs) if n.leaf else sum(widths[i] for i in n.inputs)
        outputs = sorted(needs.get(n.op_id, ()))
        whole = len(outputs) == widths[n.op_id] and not isinstance(n.op, Select)
        smaller = None if whole else n.op.restrict(outputs, total)
        if smaller is None and not whole and outputs:
            notes.append(f"selection stays above {n.op_id} ({n.signature})")
        op, inputs = smaller if smaller else (n.op, list(range(total)))
        plan[n.op_id] = (op, inputs, outputs if smaller else list(range(widths[n.op_id])))
        if not n.leaf and outputs:
            at = 0
            for i in n.inputs:
                needs.setdefault(i, set()).update(k - at for k in inputs if at <= k < at + widths[i])
                at += widths[i]
    nodes, gives, alias = [], {}, {}
    for n in dag.nodes:
        if not needs.get(n.op_id):
            continue
        op, inputs, outputs = plan[n.op_id]
        gives[n.op_id] = outputs
        if n.leaf:
            names = n.inputs if getattr(op, "strings", False) else tuple(n.inputs[k] for k in inputs)
            nodes.append(replace(n, op=op, inputs=names))
            continue
        # where the nodes below give just the inputs in order, no gather is needed
        have, at = [], 0
        for i in n.inputs:
            have += [at + k for k in gives.get(i, [])]
            at += widths[i]
        sources = tuple(i for i in n.inputs if i in gives)
        gather = [have.index(k) for k in inputs]
        if gather != list(range(len(have))):
            pick = OpNode(f"{n.op_id}g", "sel.columns", sources, Select(gather))
            nodes.append(pick)
            sources = (pick.op_id,)
        if isinstance(op, Select) and op.kept == list(range(len(inputs))) and len(sources) == 1:
            alias[n.op_id] = sources[0]  # the selection has become the identity: consumers read its source
            continue
        nodes.append(replace(n, op=op, inputs=sources))
    nodes = [n if n.leaf else replace(n, inputs=tuple(alias.get(i, i) for i in n.inputs)) for n in nodes]
    return PipelineDag(tuple(nodes), tuple(dict.fromkeys(notes)))


def fold_linear(dag: PipelineDag) -> PipelineDag:
    """Scaler, projection and linear model in a row become one product and bias."""
    nodes = list(dag.nodes)
    used = [i for n in nodes if not n.leaf for i in n.inputs]
    k = len(nodes) - 1
    while k > 0:
        n = nodes[k]
        below = next((m for m in nodes[:k] if n.inputs == (m.op_id,)), None) if isinstance(n.op, Linear) else None
        if below is None or below.leaf or used.count(below.op_id) > 1 or not isinstance(below.op, (Scale, Project)):
            break
        if isinstance(below.op, Scale):
            w = n.op.w / featurizers.nonzero(below.op.scale)[:, None]
            b = n.op.b - np.asarray(below.op.shift, float) @ w
        else:
            p = below.op
            w = (p.w if p.scale is None else p.w / featurizers.nonzero(p.scale)) @ n.op.w
            b = n.op.b - np.asarray(p.mu, float) @ w
        nodes[k] = replace(n, inputs=below.inputs, op=Linear(w, b, n.op.mode, n.op.threshold))
        nodes.remove(below)
        k -= 1
    return replace(dag, nodes=tuple(nodes))


def stack_linear(models_: list[Linear]) -> Linear:
    """Linear models over one input as one product with their weights side by side (margins of all)."""
    return Linear(np.concatenate([m.w for m in models_], 1), np.concatenate([np.atleast_1d(m.b) for m in models_]), "margin")


RULES = {"inject": inject_selection, "push": push_selection, "fold": fold_linear}
ALL = ("inject", "push", "fold")


def rewrite(dag: PipelineDag, rules: tuple[str, ...] = ALL) -> PipelineDag:
    for r in rules:
        dag = RULES[r](dag)
    return dag


def diagnose(dag: PipelineDag, density: float | None = None) -> list[str]:
    """Warnings for pipelines that are too small or too sparse to gain from tensors."""
    found = []
    last = dag.nodes[-1].op
    if isinstance(last, Forest) and len(last.spec.trees) == 1 and last.spec.depth() <= 3:
        found.append("too small: one shallow tree is faster as a conditional expression")
    if density is not None and density < 0.05:
        found.append("too sparse: use the relational lane")
    return found


__all__ = ["ALL", "Builder", "OpNode", "PipelineDag", "chain", "diagnose", "fold_linear", "inject_selection", "models", "push_selection", "rewrite", "stack_linear"]
