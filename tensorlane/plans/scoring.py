"""Scoring: the vector lane (Arrow batches and numpy) and the expression lane (built-in columns).  Neither shuffles."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.base import NoExpression
from ..pipeline import ALL, PipelineDag, rewrite


def _matrix_columns(batch: pa.RecordBatch, dag: PipelineDag) -> dict[str, object]:
    text = dag.text_columns()
    out: dict[str, object] = {}
    for name in dag.live_columns():
        c = batch.column(batch.schema.get_field_index(name))
        out[name] = c.to_pylist() if name in text else c.cast(pa.float64()).to_numpy(zero_copy_only=False)
    return out


def _gathered(batches: Iterator[pa.RecordBatch], least: int | None) -> Iterator[pa.RecordBatch]:
    held, rows = [], 0
    for b in batches:
        held.append(b)
        rows += b.num_rows
        if not least or rows >= least:
            yield from _one(held)
            held, rows = [], 0
    if held:
        yield from _one(held)


def _one(held: list[pa.RecordBatch]) -> list[pa.RecordBatch]:
    return held if len(held) == 1 else pa.Table.from_batches(held).combine_chunks().to_batches()


def vector_lane(df: DataFrame, dag: PipelineDag, keep: list[str], names: list[str], batch_rows: int | None = None, dtype: str = "float64") -> DataFrame:
    """Select live columns, then score whole Arrow batches; nulls reach the kernels as NaN.

    Batches of over ``batch_rows`` rows are cut, smaller ones (the session bounds Arrow batches) are gathered.
    """
    kind = np.float32 if dtype == "float32" else np.float64
    dag = dag.single() if dtype == "float32" else dag
    live = dag.live_columns()
    cols = [*keep, *[c for c in live if c not in keep]]
    shared = df.sparkSession.sparkContext.broadcast(dag)
    n_keep = len(keep)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for whole in _gathered(batches, batch_rows):
            step = batch_rows or max(1, whole.num_rows)
            for at in range(0, whole.num_rows, step):
                b = whole.slice(at, step)
                columns = _matrix_columns(b, model)
                with np.errstate(all="ignore"):
                    out = model.run(columns, kind).astype(np.float64, copy=False)
                yield pa.RecordBatch.from_arrays([*b.columns[:n_keep], *[pa.array(out[:, j]) for j in range(len(names))]], [*keep, *names])

    schema = T.StructType([*[df.schema[c] for c in keep], *[T.StructField(n, T.DoubleType()) for n in names]])
    return df.select(*cols).mapInArrow(score, schema)


def expression_lane(df: DataFrame, dag: PipelineDag, keep: list[str], names: list[str]) -> DataFrame:
    out = dag.expressions(lambda c: F.col(c).cast("double") if c not in dag.text_columns() else F.col(c))
    return df.select(*keep, *[c.alias(n) for c, n in zip(out, names, strict=False)])


@dataclass
class CompiledModel:
    """A pipeline ready to score; see :func:`compile_pipeline`."""

    dag: PipelineDag
    source: PipelineDag
    lane: str = "vector"
    batch_rows: int | None = None
    dtype: str = "float64"

    def names(self) -> list[str]:
        n = self.dag.widths()[self.dag.nodes[-1].op_id]
        return ["prediction", *[f"p{k}" for k in range(n - 1)]]

    def score(self, df: DataFrame, keep: list[str], names: list[str] | None = None) -> DataFrame:
        """``keep`` columns and the outputs; give all of the outputs' names, or a prefix of them."""
        every = self.names()
        wanted = names or every
        if self.lane == "expression":
            return expression_lane(df, self.dag, keep, wanted)
        made = [*wanted, *[f"_o{k}" for k in range(len(every) - len(wanted))]]
        out = vector_lane(df, self.dag, keep, made, self.batch_rows, self.dtype)
        return out.select(*keep, *wanted) if len(made) > len(wanted) else out

    def score_one(self, row: dict[str, object]) -> dict[str, float]:
        """One record without Spark."""
        text = self.dag.text_columns()
        columns = {c: [row[c]] if c in text else np.array([np.nan if row[c] is None else row[c]], float) for c in self.dag.live_columns()}
        return dict(zip(self.names(), self.dag.run(columns)[0].tolist(), strict=True))

    def udf(self):
        """A vectorised function of the live columns, in order, for use in SQL: the first output."""
        dag, live = self.dag, self.dag.live_columns()

        @F.pandas_udf(T.DoubleType())
        def first(*columns):
            import pandas as pd

            return pd.Series(dag.run(dict(zip(live, [c.to_numpy(float) for c in columns], strict=True)))[:, 0])

        return first

    def explain(self) -> str:
        return self.dag.explain()


def compile_pipeline(dag: PipelineDag, *, lane: str = "auto", rules: tuple[str, ...] = ALL, batch_rows: int | None = None, dtype: str = "float64") -> CompiledModel:
    """Rewrite a pipeline and choose its lane: built-in columns where all operators have them and few are needed."""
    smaller = rewrite(dag, rules).batched(batch_rows)
    if lane == "auto":
        lane = "vector"
        try:
            if sum(smaller.widths().values()) <= 64 and not any(n.signature == "trees.forest" for n in smaller.nodes):
                smaller.expressions(lambda c: F.col(c))
                lane = "expression"
        except NoExpression:
            pass
    return CompiledModel(smaller, dag, lane, batch_rows, dtype)


def register_scorer(spark, name: str, model: CompiledModel) -> None:
    """Make a model callable from SQL."""
    spark.udf.register(name, model.udf())


def decision(p: Column, threshold: float) -> Column:
    return (p > F.lit(threshold)).cast("double")
