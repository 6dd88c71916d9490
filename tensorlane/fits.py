"""Fits by aggregates: parameters of featurizers and selectors from one or few passes over a table.

What reaches the driver is bounded by the number of columns (or of columns squared), never by the number of rows.
Nulls and NaN are left out column by column; a column without values gets the neutral parameter.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Accuracy of percentiles: rank error of at most rows / ACCURACY.
ACCURACY = 100_000
#: Most entries of a fitted vocabulary.
MOST_CATEGORIES = 100_000


class TooManyCategories(ValueError):
    pass


def _clean(c: str) -> Column:
    x = F.col(c).cast("double")
    return F.when(F.isnan(x), F.lit(None)).otherwise(x)


def _one_row(df: DataFrame, columns: list[str], make) -> np.ndarray:
    """Aggregates (possibly several a column) as an array, columns first; missing ones are NaN."""
    out = []
    for k in range(0, len(columns), 200):  # generated code stays small for very wide tables
        part = columns[k : k + 200]
        row = df.agg(*[F.array(*[x.cast("double") for x in make(_clean(c))]).alias(f"a{j}") for j, c in enumerate(part)]).first()
        out += [[np.nan if v is None else v for v in cell] for cell in row]
    return np.array(out, float)


# -- imputers, scalers, bins --------------------------------------------------------------


def impute(df: DataFrame, columns: list[str], how: str = "mean") -> dict:
    """``mean``, ``median`` or ``mode`` (the least of the most frequent values) of each column."""
    stat = {"mean": F.avg, "median": lambda c: F.percentile_approx(c, 0.5, ACCURACY)}
    if how == "mode":
        values = [_mode(df, c) for c in columns]
    else:
        values = _one_row(df, columns, lambda c: [stat[how](c)])[:, 0]
    return {"values": np.nan_to_num(np.asarray(values, float))}


def _mode(df: DataFrame, column: str) -> float:
    top = df.select(_clean(column).alias("v")).filter("v IS NOT NULL").groupBy("v").count().orderBy(F.desc("count"), "v").first()
    return top["v"] if top else 0.0


def standard(df: DataFrame, columns: list[str]) -> dict:
    a = _one_row(df, columns, lambda c: [F.avg(c), F.stddev_pop(c)])
    return {"mu": np.nan_to_num(a[:, 0]), "sd": np.nan_to_num(a[:, 1], nan=1.0)}


def minmax(df: DataFrame, columns: list[str]) -> dict:
    a = np.nan_to_num(_one_row(df, columns, lambda c: [F.min(c), F.max(c)]))
    return {"lo": a[:, 0], "hi": a[:, 1]}


def maxabs(df: DataFrame, columns: list[str]) -> dict:
    return {"m": np.nan_to_num(_one_row(df, columns, lambda c: [F.max(F.abs(c))])[:, 0], nan=1.0)}


def robust(df: DataFrame, columns: list[str], low: float = 0.25, high: float = 0.75) -> dict:
    a = np.nan_to_num(_one_row(df, columns, lambda c: [F.percentile_approx(c, q, ACCURACY) for q in (0.5, low, high)]))
    return {"center": a[:, 0], "scale": a[:, 2] - a[:, 1]}


def kbins(df: DataFrame, columns: list[str], bins: int = 5, how: str = "uniform", cells: int = 1024) -> dict:
    """Inner edges: ``uniform`` widths, ``quantile`` shares, or ``kmeans`` (midpoints of centres fitted on a histogram of ``cells``)."""
    ends = minmax(df, columns)
    if how == "uniform":
        return {"edges": [np.linspace(a, b, bins + 1)[1:-1].tolist() for a, b in zip(ends["lo"], ends["hi"], strict=True)]}
    if how == "quantile":
        a = _one_row(df, columns, lambda c: [F.percentile_approx(c, k / bins, ACCURACY) for k in range(1, bins)])
        return {"edges": [sorted(set(row[~np.isnan(row)].tolist())) for row in a]}
    cell = [F.least(F.greatest(F.floor((_clean(c) - F.lit(float(a))) / F.lit(float((b - a) or 1.0)) * cells), F.lit(0)), F.lit(cells - 1)).cast("int") for c, a, b in zip(columns, ends["lo"], ends["hi"], strict=True)]
    pairs = F.explode(F.array(*[F.struct(F.lit(k).alias("c"), x.alias("cell")) for k, x in enumerate(cell)]))
    counts = np.zeros((len(columns), cells))
    for r in df.select(pairs.alias("p")).filter("p.cell IS NOT NULL").groupBy("p.c", "p.cell").count().collect():  # columns x cells rows at most
        counts[r["c"], r["cell"]] = r["count"]
    edges = []
    for w, a, b in zip(counts, ends["lo"], ends["hi"], strict=True):
        x = a + (np.arange(cells) + 0.5) * (b - a) / cells
        edges.append(_lloyd(x, w, bins))
    return {"edges": edges}


def _lloyd(x: np.ndarray, w: np.ndarray, k: int) -> list[float]:
    """Edges between k centres of weighted points in order, from evenly spaced starts."""
    if not w.sum():
        return []
    centres = np.linspace(x[0], x[-1], k + 2)[1:-1]
    for _ in range(300):
        edges = (centres[1:] + centres[:-1]) / 2
        owner = np.searchsorted(edges, x, "right")
        mass, sums = np.bincount(owner, w, k), np.bincount(owner, w * x, k)
        new = np.where(mass > 0, sums / np.maximum(mass, 1e-300), centres)
        if np.array_equal(new, centres):
            break
        centres = new
    return ((centres[1:] + centres[:-1]) / 2).tolist()


def vocabulary(df: DataFrame, column: str, most: int = MOST_CATEGORIES) -> list[str]:
    """Distinct values in order; a column with more than ``most`` is refused."""
    found = [r[0] for r in df.select(F.col(column).cast("string").alias("v")).filter("v IS NOT NULL").distinct().orderBy("v").limit(most + 1).collect()]
    if len(found) > most:
        raise TooManyCategories(column)
    return found


# -- selectors ----------------------------------------------------------------------------


def variances(df: DataFrame, columns: list[str]) -> np.ndarray:
    return np.nan_to_num(_one_row(df, columns, lambda c: [F.var_pop(c)])[:, 0])


def variance_threshold(df: DataFrame, columns: list[str], least: float = 0.0) -> dict:
    return {"kept": np.flatnonzero(variances(df, columns) > least).tolist()}


def _class_sums(df: DataFrame, columns: list[str], label: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows (classes), sums and sums of squares (classes x columns)."""
    counts, sums, squares = {}, {}, {}
    for k in range(0, len(columns), 200):
        part = columns[k : k + 200]
        rows = df.groupBy(F.col(label).alias("y")).agg(F.count("*").alias("n"), F.array(*[F.sum(_clean(c)) for c in part]).alias("s"), F.array(*[F.sum(_clean(c) * _clean(c)) for c in part]).alias("q")).collect()
        for r in rows:
            counts[r["y"]] = r["n"]
            sums.setdefault(r["y"], []).extend(v or 0.0 for v in r["s"])
            squares.setdefault(r["y"], []).extend(v or 0.0 for v in r["q"])
    order = sorted(counts, key=lambda y: (y is None, y))
    return np.array([counts[y] for y in order], float), np.array([sums[y] for y in order]), np.array([squares[y] for y in order])


def anova_f(df: DataFrame, columns: list[str], label: str) -> np.ndarray:
    """F value of each column against the classes of the label (0 for a constant column)."""
    n, s, q = _class_sums(df, columns, label)
    total, between = s.sum(0), ((s**2) / n[:, None]).sum(0) - s.sum(0) ** 2 / n.sum()
    within = q.sum(0) - ((s**2) / n[:, None]).sum(0)
    scale = np.maximum(np.abs(q.sum(0) - total**2 / n.sum()), 1e-300)
    with np.errstate(all="ignore"):
        f = (between / max(len(n) - 1, 1)) / (within / max(n.sum() - len(n), 1))
    return np.where(between / scale < 1e-12, 0.0, np.where(within / scale < 1e-12, np.inf, f))


def chi2(df: DataFrame, columns: list[str], label: str) -> np.ndarray:
    """Chi-square value of each non-negative column, taken as counts, against the classes of the label."""
    n, s, _ = _class_sums(df, columns, label)
    expected = n[:, None] / n.sum() * s.sum(0)[None]
    with np.errstate(all="ignore"):
        return np.nan_to_num(((s - expected) ** 2 / expected).sum(0))


def best(scores: np.ndarray, k: int) -> dict:
    """The k highest scores, ties to the lower column, in column order."""
    order = np.lexsort((np.arange(len(scores)), -scores))
    return {"kept": sorted(order[:k].tolist())}


def percentile(scores: np.ndarray, percent: float) -> dict:
    """The best share of the columns: at least one."""
    return best(scores, max(1, int(len(scores) * percent / 100)))


# -- projections --------------------------------------------------------------------------


def moments(df: DataFrame, columns: list[str]) -> tuple[int, np.ndarray, np.ndarray]:
    """Rows, sums and sums of products of complete rows: a matrix a partition, added up by Spark entry by entry.

    Partial matrices are emitted as one row for each line, so no task holds more than one matrix.
    """
    d = len(columns)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((d + 1, d + 1))
        for b in batches:
            x = np.stack([c.to_numpy(zero_copy_only=False).astype(float) for c in b.columns], 1)
            x = x[~np.isnan(x).any(1)]
            x = np.concatenate([np.ones((len(x), 1)), x], 1)
            total += x.T @ x
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(d + 1)), pa.array(total.tolist(), pa.list_(pa.float64()))], ["line", "v"])

    lines = df.select(*[F.col(c).cast("double").alias(f"c{k}") for k, c in enumerate(columns)]).mapInArrow(partial, "line long, v array<double>")
    cells = lines.select("line", F.posexplode("v").alias("j", "v")).groupBy("line", "j").agg(F.sum("v").alias("v"))
    m = np.zeros((d + 1, d + 1))
    for r in cells.collect():  # columns squared
        m[r["line"], r["j"]] = r["v"]
    return int(m[0, 0]), m[0, 1:], m[1:, 1:]


def _signed(w: np.ndarray) -> np.ndarray:
    """Each column with its largest entry positive, so that a fit doesn't depend on the solver's signs."""
    return w * np.where(w[np.abs(w).argmax(0), np.arange(w.shape[1])] < 0, -1.0, 1.0)


def pca(df: DataFrame, columns: list[str], k: int, whiten: bool = False) -> dict:
    n, s, p = moments(df, columns)
    mu = s / max(n, 1)
    value, vector = np.linalg.eigh((p - n * np.outer(mu, mu)) / max(n - 1, 1))
    top = np.argsort(-value, kind="stable")[:k]
    return {"mu": mu, "w": _signed(vector[:, top]), "scale": np.sqrt(np.maximum(value[top], 0)) if whiten else None}


def truncated_svd(df: DataFrame, columns: list[str], k: int) -> dict:
    """Right singular vectors of the table itself, not centred."""
    _, _, p = moments(df, columns)
    value, vector = np.linalg.eigh(p)
    return {"mu": np.zeros(len(columns)), "w": _signed(vector[:, np.argsort(-value, kind="stable")[:k]])}


def independent_components(df: DataFrame, columns: list[str], k: int, rounds: int = 50, tolerance: float = 1e-6, seed: int = 1) -> dict:
    """Fixed-point iteration with the log-cosh contrast on whitened rows; every round is one aggregate over the table."""
    base = pca(df, columns, k, whiten=True)
    white = base["w"] / np.where(base["scale"] > 0, base["scale"], 1.0)
    mu, d = base["mu"], len(columns)
    q, _ = np.linalg.qr(np.random.default_rng(seed).normal(size=(k, k)))
    source = df.select(*[F.col(c).cast("double").alias(f"c{j}") for j, c in enumerate(columns)])
    for _ in range(rounds):

        def partial(batches: Iterator[pa.RecordBatch], q=q) -> Iterator[pa.RecordBatch]:
            total = np.zeros(k * k + k + 1)
            for b in batches:
                x = np.stack([c.to_numpy(zero_copy_only=False).astype(float) for c in b.columns], 1) if d else np.zeros((0, 0))
                z = (x[~np.isnan(x).any(1)] - mu) @ white
                g = np.tanh(z @ q)
                total += np.concatenate([(z.T @ g).ravel(), (1 - g * g).sum(0), [len(z)]])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], ["j", "v"])

        got = np.zeros(k * k + k + 1)
        for r in source.mapInArrow(partial, "j long, v double").groupBy("j").agg(F.sum("v").alias("v")).collect():
            got[r["j"]] = r["v"]
        n = max(got[-1], 1)
        new = got[: k * k].reshape(k, k) / n - q * (got[k * k : -1] / n)[None]
        u, _, v = np.linalg.svd(new)
        new = u @ v
        moved = float(np.abs(np.abs((new * q).sum(0)) - 1).max())
        q = new
        if moved < tolerance:
            break
    return {"mu": mu, "w": _signed(white @ q)}


def kernel_pca(df: DataFrame, columns: list[str], key: str, k: int, gamma: float, landmarks: int = 500) -> dict:
    """Components of the centred kernel matrix of ``landmarks`` rows, those with the least hash of ``key`` (a documented bound)."""
    rows = df.orderBy(F.xxhash64(key), key).limit(landmarks).select(*[F.col(c).cast("double") for c in columns]).collect()
    x = np.array([list(r) for r in rows], float).reshape(-1, len(columns))
    kernel = np.exp(-gamma * ((x[:, None, :] - x[None]) ** 2).sum(-1)) if len(x) else np.zeros((0, 0))
    column = kernel.mean(0) if len(x) else np.zeros(0)
    grand = float(column.mean()) if len(x) else 0.0
    value, vector = np.linalg.eigh(kernel - column[None] - column[:, None] + grand)
    top = np.argsort(-value, kind="stable")[:k]
    return {"support": x, "gamma": gamma, "column_mean": column, "grand_mean": grand, "a": _signed(vector[:, top]) / np.sqrt(np.maximum(value[top], 1e-12))}


# -- linear models ------------------------------------------------------------------------


def logistic(df: DataFrame, columns: list[str], label: str, l1: float = 0.0, l2: float = 0.0) -> dict:
    """Weights by Spark's own solver, on the raw columns; L1 gives weights that are exactly 0."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    both = l1 + l2
    data = VectorAssembler(inputCols=columns, outputCol="_x").transform(df).select("_x", F.col(label).cast("double").alias("_y"))
    m = LogisticRegression(featuresCol="_x", labelCol="_y", regParam=both, elasticNetParam=l1 / both if both else 0.0, maxIter=50).fit(data)
    return {"w": np.asarray(m.coefficientMatrix.toArray(), float).T, "b": np.asarray(m.interceptVector.toArray(), float), "mode": "logistic" if m.numClasses == 2 else "softmax"}


def logistic_cv(df: DataFrame, columns: list[str], label: str, key: str, strengths: list[float], folds: int = 3) -> dict:
    """Logistic regression whose L2 strength is the one of the least mean log loss over folds by a hash of ``key``."""
    fold = F.pmod(F.xxhash64(key), F.lit(folds))
    data = df.withColumn("_fold", fold)
    losses = []
    for c in strengths:
        total = 0.0
        for f in range(folds):
            m = logistic(data.filter(F.col("_fold") != f), columns, label, l2=c)
            z = sum((F.col(n) * float(w) for n, w in zip(columns, m["w"][:, 0], strict=True)), F.lit(float(m["b"][0])))
            y = F.col(label).cast("double")
            loss = F.log1p(F.exp(-F.abs(z))) + F.greatest(z, F.lit(0.0)) - z * y
            total += data.filter(F.col("_fold") == f).agg(F.avg(loss)).first()[0] or 0.0
        losses.append(total / folds)
    return {**logistic(df, columns, label, l2=strengths[int(np.argmin(losses))]), "mode": "logistic"}
