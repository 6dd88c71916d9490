"""Baselines: imperative row-at-a-time scoring, nested conditionals, a relational walk, operator-by-operator pipelines."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .pipeline import PipelineDag
from .trees import ForestSpec


def udf_rowwise(df: DataFrame, forest: ForestSpec, names: list[str], keep: list[str]) -> DataFrame:
    """A plain Python function for each row walks nodes held as dictionaries: the slow path, for comparison."""
    nodes = [[{"leaf": bool(leaf), "l": int(a), "r": int(b), "f": int(f), "t": float(t), "v": v.tolist()} for leaf, a, b, f, t, v in zip(t.is_leaf, t.left, t.right, t.feature, t.threshold, t.value, strict=True)] for t in forest.trees]
    less, n_out = forest.cmp == "<", forest.outputs

    @F.udf("array<double>")
    def walk(*x):
        total = [0.0] * n_out
        for tree in nodes:
            node = tree[0]
            while not node["leaf"]:
                go = x[node["f"]] < node["t"] if less else x[node["f"]] <= node["t"]
                node = tree[node["l"] if go else node["r"]]
            total = [a + b for a, b in zip(total, node["v"], strict=True)]
        return [v / len(nodes) for v in total]

    return df.select(*keep, walk(*names).alias("out")).select(*keep, *[F.col("out")[k].alias(f"p{k}") for k in range(n_out)])


def case_column(tree, names: list[str], output: int, cmp: str = "<") -> Column:
    """One tree as nested conditionals."""

    def walk(k: int) -> Column:
        if tree.left[k] == k:
            return F.lit(float(tree.value[k, output]))
        x, t = F.col(names[tree.feature[k]]), F.lit(float(tree.threshold[k]))
        return F.when(x < t if cmp == "<" else x <= t, walk(int(tree.left[k]))).otherwise(walk(int(tree.right[k])))

    return walk(0)


def case_sql(df: DataFrame, forest: ForestSpec, names: list[str], keep: list[str], per_column: int = 4) -> DataFrame:
    """Nested conditionals, a few trees to a column so that generated methods stay small."""
    out = []
    for j in range(forest.outputs):
        parts = [case_column(t, names, j, forest.cmp) for t in forest.trees]
        for k in range(0, len(parts), per_column):
            df = df.withColumn(f"_c{j}_{k}", sum(parts[k + 1 : k + per_column], parts[k]))
        cols = [F.col(f"_c{j}_{k}") for k in range(0, len(parts), per_column)]
        out.append((sum(cols[1:], cols[0]) / float(len(forest.trees))).alias(f"p{j}"))
    return df.select(*keep, *out)


def node_table(spark, forest: ForestSpec) -> DataFrame:
    rows = [(t, k, bool(s.is_leaf[k]), int(s.feature[k]), float(s.threshold[k]), int(s.left[k]), int(s.right[k]), s.value[k].tolist()) for t, s in enumerate(forest.trees) for k in range(len(s.left))]
    return spark.createDataFrame(rows, "tree int, node int, leaf boolean, feature int, threshold double, l int, r int, value array<double>")


def relational_walk(df: DataFrame, forest: ForestSpec, names: list[str], keep: list[str]) -> DataFrame:
    """Every row's cursor of every tree moves by one join with the node table a level."""
    nodes = F.broadcast(node_table(df.sparkSession, forest))  # a model has a fixed size
    trees = F.explode(F.sequence(F.lit(0), F.lit(len(forest.trees) - 1)))
    # a number of its own keeps rows with equal keys apart
    at = df.select(*keep, F.monotonically_increasing_id().alias("_row"), F.array(*names).alias("x")).select("*", trees.alias("tree")).withColumn("node", F.lit(0))
    for _ in range(forest.depth()):
        test = F.element_at("x", F.col("feature") + 1) < F.col("threshold")
        if forest.cmp != "<":
            test = F.element_at("x", F.col("feature") + 1) <= F.col("threshold")
        at = at.join(nodes, ["tree", "node"]).select(*keep, "_row", "x", "tree", F.when(test, F.col("l")).otherwise(F.col("r")).alias("node"))
    reached = at.join(nodes, ["tree", "node"])
    return reached.groupBy("_row", *keep).agg(*[(F.sum(F.col("value")[j]) / len(forest.trees)).alias(f"p{j}") for j in range(forest.outputs)]).drop("_row")


def relational_gemm(df: DataFrame, tree, names: list[str], key: str) -> DataFrame:
    """The matrix formulation of one tree over coordinate tables: two joins and two sums; ``df`` has a unique key."""
    import numpy as np

    from .relops import coo_matmul, to_coo
    from .trees import ForestSpec, gemm_tensors

    spark = df.sparkSession
    g = gemm_tensors(ForestSpec((tree,)))
    n_d, n_l = g.ancestry.shape[1:]
    verdicts = df.select(key, *[(F.col(names[f]) < F.lit(float(t))).cast("double").alias(f"d{k}") for k, (f, t) in enumerate(zip(g.feature[0], g.threshold[0], strict=True))])
    s = to_coo(verdicts, key, [f"d{k}" for k in range(n_d)]).withColumnRenamed(key, "i")
    c = spark.createDataFrame([(int(i), int(j), float(g.ancestry[0, i, j])) for i, j in zip(*np.nonzero(g.ancestry[0]), strict=True)], "i int, j int, v double")
    score = coo_matmul(s, F.broadcast(c))
    leaves = spark.createDataFrame([(k, float(g.lefts[0, k]), g.value[0, k].tolist()) for k in range(n_l)], "j int, lefts double, value array<double>")
    reached = score.join(F.broadcast(leaves), "j").filter(F.col("v") == F.col("lefts")).select("i", "value")
    # only the leaf to the right of every decision has score 0: it is that of the rows that reach no other
    last = [g.value[0, k].tolist() for k in range(n_l) if g.lefts[0, k] == 0.0]
    every = df.select(F.col(key).alias("i")).join(reached, "i", "left").withColumn("value", F.coalesce("value", F.lit(last[0] if last else None).cast("array<double>")))
    return every.select(F.col("i").alias(key), *[F.col("value")[k].alias(f"p{k}") for k in range(g.value.shape[2])])


def stagewise(df: DataFrame, dag: PipelineDag, keep: list[str]) -> DataFrame:
    """One operator after the other, each adding columns; nothing is pushed or dropped."""
    made: dict[str, list[str]] = {}
    for n in dag.nodes:
        names = list(n.inputs) if n.leaf else [c for i in n.inputs for c in made[i]]
        out = n.op.expr([F.col(c) for c in names])
        made[n.op_id] = [f"{n.op_id}_{k}" for k in range(len(out))]
        df = df.withColumns(dict(zip(made[n.op_id], out, strict=True)))
    return df.select(*keep, *made[dag.nodes[-1].op_id])
