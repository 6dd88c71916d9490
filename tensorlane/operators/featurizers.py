"""Featurizers: selection, imputation, scaling, discretising, normalising, interactions, encodings, projections."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from zlib import crc32

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..kernels import fixed_bytes, interactions_outer, interactions_pairwise, squared_distances
from .base import Operator, array, converter, nonzero


class PerColumn(Operator):
    """One output for each input; parameters are arrays by column."""

    per_column = ()

    def restrict(self, outputs, inputs):
        return replace(self, **{n: array(getattr(self, n))[outputs] for n in self.per_column}), list(outputs)


@converter("sel.columns")
@dataclass
class Select(Operator):
    """Keep some columns: the result of any selector."""

    kept: list[int]

    def width(self, inputs):
        return len(self.kept)

    def vector(self, x):
        return x[:, self.kept]

    def expr(self, xs):
        return [xs[k] for k in self.kept]

    def restrict(self, outputs, inputs):
        return Select(list(range(len(outputs)))), [self.kept[k] for k in outputs]


@converter("imp.simple")
@dataclass
class Impute(PerColumn):
    """Null or NaN becomes the column's statistic."""

    values: np.ndarray
    per_column = ("values",)

    def vector(self, x):
        return np.where(np.isnan(x), array(self.values), x)

    def expr(self, xs):
        return [F.when(x.isNull() | F.isnan(x), F.lit(float(v))).otherwise(x) for x, v in zip(xs, self.values, strict=True)]


@converter("imp.indicator")
@dataclass
class MissingIndicator(PerColumn):
    def vector(self, x):
        return np.isnan(x).astype(float)

    def expr(self, xs):
        return [(x.isNull() | F.isnan(x)).cast("double") for x in xs]


@converter("sc.affine")
@dataclass
class Scale(PerColumn):
    """(x - shift) / scale; standard, robust and max-abs scalers differ in how they are fitted."""

    shift: np.ndarray
    scale: np.ndarray
    per_column = ("shift", "scale")

    def vector(self, x):
        return (x - array(self.shift)) / nonzero(self.scale)

    def expr(self, xs):
        return [(x - F.lit(float(a))) / F.lit(float(b)) for x, a, b in zip(xs, self.shift, nonzero(self.scale), strict=True)]


@converter("sc.standard")
def standard(mu, sd) -> Scale:
    return Scale(mu, sd)


@converter("sc.robust")
def robust(center, scale) -> Scale:
    return Scale(center, scale)


@converter("sc.maxabs")
def maxabs(m) -> Scale:
    return Scale(np.zeros(len(m)), m)


@converter("sc.minmax")
@dataclass
class MinMax(PerColumn):
    lo: np.ndarray
    hi: np.ndarray
    to: tuple[float, float] = (0.0, 1.0)
    clip: bool = False
    per_column = ("lo", "hi")

    def vector(self, x):
        out = (x - array(self.lo)) / nonzero(array(self.hi) - array(self.lo)) * (self.to[1] - self.to[0]) + self.to[0]
        return np.clip(out, *self.to) if self.clip else out

    def expr(self, xs):
        out = []
        for x, lo, d in zip(xs, self.lo, nonzero(array(self.hi) - array(self.lo)), strict=True):
            y = (x - F.lit(float(lo))) / F.lit(float(d)) * F.lit(self.to[1] - self.to[0]) + F.lit(self.to[0])
            out.append(F.greatest(F.least(y, F.lit(self.to[1])), F.lit(self.to[0])) if self.clip else y)
        return out


@converter("disc.binarize")
@dataclass
class Binarize(PerColumn):
    threshold: float = 0.0

    def vector(self, x):
        return (x > self.threshold).astype(float)

    def expr(self, xs):
        return [(x > F.lit(float(self.threshold))).cast("double") for x in xs]


@converter("disc.kbins")
@dataclass
class KBins(Operator):
    """Count of inner edges at or below x; ordinal, or one column for each bin."""

    edges: list[list[float]]  #: by column: inner edges only
    encode: str = "ordinal"

    def width(self, inputs):
        return inputs if self.encode == "ordinal" else sum(len(e) + 1 for e in self.edges)

    def vector(self, x):
        codes = [np.searchsorted(array(e), x[:, k], "right") for k, e in enumerate(self.edges)]
        if self.encode == "ordinal":
            return np.stack(codes, 1).astype(float)
        return np.concatenate([(c[:, None] == np.arange(len(e) + 1)).astype(float) for c, e in zip(codes, self.edges, strict=True)], 1)

    def expr(self, xs):
        codes = [sum(((x >= F.lit(float(v))).cast("int") for v in e), F.lit(0)) for x, e in zip(xs, self.edges, strict=True)]
        if self.encode == "ordinal":
            return [c.cast("double") for c in codes]
        return [(c == k).cast("double") for c, e in zip(codes, self.edges, strict=True) for k in range(len(e) + 1)]

    def restrict(self, outputs, inputs):
        if self.encode == "ordinal":
            return KBins([self.edges[k] for k in outputs]), list(outputs)
        owner = [k for k, e in enumerate(self.edges) for _ in range(len(e) + 1)]
        inner = [j for e in self.edges for j in range(len(e) + 1)]
        need = sorted({owner[o] for o in outputs})
        picks = [(need.index(owner[o]), inner[o]) for o in outputs]
        return PickedBins([self.edges[k] for k in need], picks), need


@dataclass
class PickedBins(Operator):
    """Chosen (column, bin) indicators: what is left of one-hot bins under a selection."""

    edges: list[list[float]]
    picks: list[tuple[int, int]]

    def width(self, inputs):
        return len(self.picks)

    def vector(self, x):
        codes = [np.searchsorted(array(e), x[:, k], "right") for k, e in enumerate(self.edges)]
        return np.stack([(codes[c] == b).astype(float) for c, b in self.picks], 1)


@converter("sc.normalize")
@dataclass
class Normalize(Operator):
    """Rows over their norm; a zero row stays.  Every input counts, so selections stop here."""

    norm: str = "l2"

    def vector(self, x):
        size = {"l1": np.abs(x).sum(1), "l2": np.sqrt((x * x).sum(1)), "max": np.abs(x).max(1)}[self.norm]
        return x / nonzero(size)[:, None]

    def expr(self, xs):
        if self.norm == "max":
            size = F.greatest(*[F.abs(x) for x in xs]) if len(xs) > 1 else F.abs(xs[0])
        else:
            size = sum((F.abs(x) if self.norm == "l1" else x * x for x in xs[1:]), F.abs(xs[0]) if self.norm == "l1" else xs[0] * xs[0])
            size = size if self.norm == "l1" else F.sqrt(size)
        size = F.when(size == 0, F.lit(1.0)).otherwise(size)
        return [x / size for x in xs]


@converter("poly.features")
@dataclass
class Polynomial(Operator):
    """Products of up to ``degree`` inputs as lists of input numbers; (), (0,), (0, 0), (0, 1) ..."""

    terms: list[tuple[int, ...]]

    def width(self, inputs):
        return len(self.terms)

    def vector(self, x):
        done: dict[tuple[int, ...], np.ndarray] = {(): np.ones(len(x))}

        def product(t):
            if t not in done:
                done[t] = product(t[:-1]) * x[:, t[-1]]
            return done[t]

        return np.stack([product(t) for t in self.terms], 1)

    def expr(self, xs):
        out = []
        for t in self.terms:
            c = F.lit(1.0)
            for k in t:
                c = c * xs[k]
            out.append(c)
        return out

    def restrict(self, outputs, inputs):
        terms = [self.terms[o] for o in outputs]
        need = sorted({k for t in terms for k in t})
        return Polynomial([tuple(need.index(k) for k in t) for t in terms]), need


def polynomial_terms(d: int, degree: int = 2, interaction_only: bool = False, bias: bool = True) -> list[tuple[int, ...]]:
    from itertools import combinations, combinations_with_replacement

    pick = combinations if interaction_only else combinations_with_replacement
    return [t for k in range(0 if bias else 1, degree + 1) for t in pick(range(d), k)]


@converter("poly.interact")
@dataclass
class Interact(Operator):
    """Squares, then pair products; ``naive`` makes each by itself."""

    naive: bool = False

    def width(self, inputs):
        return inputs * (inputs + 1) // 2

    def vector(self, x):
        return interactions_pairwise(x) if self.naive else interactions_outer(x)

    def expr(self, xs):
        d = len(xs)
        return [x * x for x in xs] + [xs[i] * xs[j] for i in range(d) for j in range(i + 1, d)]


@converter("dec.project")
@dataclass
class Project(Operator):
    """(x - mu) W, over scale: PCA, truncated SVD and independent components once fitted."""

    mu: np.ndarray
    w: np.ndarray  #: inputs x outputs
    scale: np.ndarray | None = None

    def width(self, inputs):
        return self.w.shape[1]

    def vector(self, x):
        out = (x - array(self.mu)) @ self.w
        return out if self.scale is None else out / nonzero(self.scale)

    def expr(self, xs):
        out = []
        for j in range(self.w.shape[1]):
            c = F.lit(0.0)
            for x, m, v in zip(xs, self.mu, self.w[:, j], strict=True):
                c = c + (x - F.lit(float(m))) * F.lit(float(v))
            out.append(c if self.scale is None else c / F.lit(float(nonzero(self.scale)[j])))
        return out

    def restrict(self, outputs, inputs):
        return Project(self.mu, self.w[:, outputs], None if self.scale is None else array(self.scale)[outputs]), list(range(inputs))


@converter("dec.kpca")
@dataclass
class KernelProject(Operator):
    """Centred kernel values against support rows, times coefficients."""

    support: np.ndarray
    gamma: float
    column_mean: np.ndarray
    grand_mean: float
    a: np.ndarray

    def width(self, inputs):
        return self.a.shape[1]

    def vector(self, x):
        k = np.exp(-self.gamma * squared_distances(x, self.support))
        return (k - k.mean(1, keepdims=True) - self.column_mean + self.grand_mean) @ self.a


@converter("cat.onehot")
@dataclass
class OneHot(Operator):
    """One 0/1 column for each vocabulary entry of one string column; unknown and null give zeros (or an error)."""

    vocabulary: list[str]
    unknown: str = "zeros"
    form: str = "broadcast"  #: broadcast, fixed (bytes), lookup
    strings = True

    def width(self, inputs):
        return len(self.vocabulary)

    def vector(self, x):
        """``x``: a list of strings."""
        if self.form == "fixed":
            # one byte more than the longest entry, so that a longer string is never cut to an entry
            w = max(len(v.encode()) for v in self.vocabulary) + 1
            a, b = fixed_bytes(x, w), fixed_bytes(self.vocabulary, w)
            out = (a[:, None, :] == b[None]).all(-1).astype(float)
        elif self.form == "lookup":
            place = {v: k for k, v in enumerate(self.vocabulary)}
            out = np.zeros((len(x), len(self.vocabulary)))
            at = np.array([place.get(v, -1) for v in x], int)
            out[np.flatnonzero(at >= 0), at[at >= 0]] = 1.0
        else:
            out = (np.array(x, object)[:, None] == np.array(self.vocabulary, object)[None]).astype(float)
        if self.unknown == "error" and (out.sum(1) == 0).any():
            raise ValueError("a category is not in the vocabulary")
        return out

    def expr(self, xs):
        if self.form == "lookup":
            at = F.coalesce(F.array_position(F.lit(self.vocabulary), xs[0]), F.lit(0))
            return [(at == k + 1).cast("double") for k in range(len(self.vocabulary))]
        if self.form == "fixed":
            w = max(len(v.encode()) for v in self.vocabulary) + 1
            code = F.rpad(F.substring(F.encode(xs[0], "UTF-8"), 1, w), w, F.lit(b"\x00"))
            return [F.coalesce((code == F.lit(v.encode().ljust(w, b"\x00"))).cast("double"), F.lit(0.0)) for v in self.vocabulary]
        return [F.coalesce((xs[0] == F.lit(v)).cast("double"), F.lit(0.0)) for v in self.vocabulary]

    def restrict(self, outputs, inputs):
        # a dropped entry still is a known one: with fewer entries unknown strings must not fail
        return replace(self, vocabulary=[self.vocabulary[o] for o in outputs], unknown="zeros"), [0] if outputs else []


@converter("cat.label")
@dataclass
class LabelEncode(Operator):
    """Place in the sorted vocabulary, -1 for anything else."""

    vocabulary: list[str]
    strings = True

    def vector(self, x):
        place = {v: k for k, v in enumerate(sorted(self.vocabulary))}
        return np.array([[place.get(v, -1)] for v in x], float).reshape(-1, 1)

    def expr(self, xs):
        return [(F.coalesce(F.array_position(F.lit(sorted(self.vocabulary)), xs[0]), F.lit(0)) - 1).cast("double")]


@converter("cat.hash")
@dataclass
class HashFeatures(Operator):
    """Strings added with a sign into buckets by checksum."""

    buckets: int
    signed: bool = True
    strings = True

    def width(self, inputs):
        return self.buckets

    def vector(self, x):
        out = np.zeros((len(x), self.buckets))
        for k, v in enumerate(x):
            if v is not None:
                h = crc32(v.encode())
                out[k, h % self.buckets] += -1.0 if self.signed and h >> 31 else 1.0
        return out

    def expr(self, xs):
        h = F.crc32(F.encode(xs[0], "UTF-8"))
        sign = F.when(F.lit(self.signed) & (h >= 2**31), -1.0).otherwise(1.0)
        return [F.when(h % self.buckets == k, sign).otherwise(0.0) for k in range(self.buckets)]


@converter("col.pick")
@dataclass
class Pick(PerColumn):
    """Columns as they are."""

    names: list[str] = field(default_factory=list)

    def vector(self, x):
        return x

    def expr(self, xs):
        return list(xs)

    def restrict(self, outputs, inputs):
        return Pick([self.names[o] for o in outputs] if self.names else []), list(outputs)
