"""Relational operators around the methods: joins, aggregates, windows, order and sets.  All take and return DataFrames."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: A side is sent to every executor only below this many rows.
BROADCAST_ROWS = 200_000


def join_dim(df: DataFrame, dim: DataFrame, on: Column, most: int = BROADCAST_ROWS) -> DataFrame:
    """Equi-join to a dimension, sent to every executor only if it has few rows."""
    few = dim.limit(most + 1).count() <= most
    return df.join(F.broadcast(dim) if few else dim, on)


def join_fact(a: DataFrame, b: DataFrame, on: Column, algorithm: str = "merge") -> DataFrame:
    return a.join(b.hint(algorithm), on)


def join_theta(a: DataFrame, b: DataFrame, on: Column, most: int = BROADCAST_ROWS) -> DataFrame:
    """Join by any condition to a short list of rules; every row meets every rule, so a longer list is refused."""
    if b.limit(most + 1).count() > most:
        raise ValueError(f"the second table has over {most} rows: give the join a key, a range or time slots")
    return a.join(F.broadcast(b), on)


def where_score(scores: DataFrame, condition: Column) -> DataFrame:
    """Rows by their score or class; the condition stays above the scorer."""
    return scores.filter(condition)


def n_distinct(column: str, approx: float | None = None) -> Column:
    """Distinct values; with ``approx`` by a sketch of that relative standard deviation."""
    return F.count_distinct(column) if approx is None else F.approx_count_distinct(column, approx)


def agg_sets(df: DataFrame, sets: list[list[str]], aggs: list[Column]) -> DataFrame:
    """Aggregates over several groupings in one pass; columns that a grouping lacks are null."""
    names = list(dict.fromkeys(c for group in sets for c in group))
    return df.groupingSets([[F.col(c) for c in group] for group in sets], *names).agg(*aggs)


def arg_best(df: DataFrame, by: list[str], wanted: str, order: list[str], name: str) -> DataFrame:
    """The value of ``wanted`` in each group's greatest row by ``order``: no sort, one partial row a group."""
    return df.groupBy(*by).agg(F.max_by(wanted, F.struct(*order)).alias(name))


def most_common(df: DataFrame, by: list[str], column: str, name: str) -> DataFrame:
    """Each group's most frequent value, the smallest of ties."""
    counts = df.groupBy(*by, column).agg(F.count("*").alias("_n"))
    return counts.groupBy(*by).agg(F.max_by(column, F.struct("_n", (-F.col(column)).alias("_less"))).alias(name))


def sample_hash(df: DataFrame, key: str, share: float) -> DataFrame:
    """About that share of the keys, the same ones in every run and partitioning."""
    low = F.col(key).bitwiseXOR(F.shiftrightunsigned(key, 31)).bitwiseAND(F.lit((1 << 31) - 1))
    return df.filter(F.pmod(low * F.lit(2654435761), F.lit(1 << 32)) < F.lit(int(share * (1 << 32))))


def rolling(df: DataFrame, by: list[str], order: str, frame: tuple[int, int], aggs: dict[str, Column], kind: str = "range") -> DataFrame:
    """Aggregates over a frame of rows, or of values of ``order``, round each row."""
    w = Window.partitionBy(*by).orderBy(order)
    w = w.rangeBetween(*frame) if kind == "range" else w.rowsBetween(*frame)
    return df.withColumns({name: agg.over(w) for name, agg in aggs.items()})


def metrics_multi(df: DataFrame, label: str, predicted: str) -> DataFrame:
    """Precision, recall and support of each class (null where nothing is predicted or labelled so)."""
    pairs = df.groupBy(label, predicted).agg(F.count("*").alias("_n"))  # as many rows as pairs of classes
    same = F.sum(F.when(F.col(label) == F.col(predicted), F.col("_n")).otherwise(0))
    real = pairs.groupBy(F.col(label).alias("class")).agg(F.sum("_n").alias("support"), same.alias("tp"))
    given = pairs.groupBy(F.col(predicted).alias("class")).agg(F.sum("_n").alias("given"))
    out = real.join(given, "class", "full").withColumns({c: F.coalesce(c, F.lit(0).cast("long")) for c in ("support", "tp", "given")})
    return out.select("class", F.try_divide("tp", "given").alias("precision"), F.try_divide("tp", "support").alias("recall"), "support")


def metrics_regress(df: DataFrame, label: str, predicted: str) -> DataFrame:
    error = F.col(label) - F.col(predicted)
    sums = df.agg(F.avg(error * error).alias("mse"), F.avg(F.abs(error)).alias("mae"), F.var_pop(label).alias("spread"))
    return sums.select(F.sqrt("mse").alias("rmse"), "mae", (1 - F.try_divide("mse", "spread")).alias("r2"))


def join_range(df: DataFrame, value: str, edges: list[float]) -> DataFrame:
    """``bin``: how many edges (a short sorted list) lie at or below the value."""
    return df.withColumn("bin", reduce(lambda x, y: x + y, [(F.col(value) >= F.lit(float(e))).cast("int") for e in edges]))


def join_asof(left: DataFrame, right: DataFrame, by: str, at: str, value: str) -> DataFrame:
    """For each left row the right side's last ``value`` at or before it: one shuffle, a union and a window."""
    rows = left.select(by, at, *[c for c in left.columns if c not in (by, at)], F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    other = right.select(by, at, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in (by, at)], F.lit(0).alias("_side"), F.col(value).alias("_v"))
    order = Window.partitionBy(by).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = rows.unionByName(other).withColumn(f"last_{value}", F.last("_v", ignorenulls=True).over(order))
    return both.filter("_side = 1").drop("_side", "_v")


def join_interval(a: DataFrame, b: DataFrame, by: str, at_a: str, at_b: str, seconds: int) -> DataFrame:
    """Pairs with the same key and times at most so far apart; time buckets make it an equi-join, so one key does not meet all of itself."""
    def slot(c: str) -> Column:
        return F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / seconds)

    left = a.withColumn("_slot", slot(at_a))
    right = b.withColumn("_slot", F.explode(F.array(*[slot(at_b) + k for k in (-1, 0, 1)])))
    far = F.abs(F.unix_timestamp(F.col(at_a).cast("timestamp")) - F.unix_timestamp(F.col(at_b).cast("timestamp")))
    return left.join(right, [by, "_slot"]).filter(far <= seconds).drop("_slot")


def coo_matmul(a: DataFrame, b: DataFrame) -> DataFrame:
    """Product of two sparse matrices (i, j, v): join on the inner index, sum over it."""
    inner = a.select("i", F.col("j").alias("k"), F.col("v").alias("va")).join(b.select(F.col("i").alias("k"), "j", F.col("v").alias("vb")), "k")
    return inner.groupBy("i", "j").agg(F.sum(F.col("va") * F.col("vb")).alias("v"))


def to_coo(df: DataFrame, key: str, names: list[str]) -> DataFrame:
    """(key, j, v) of the entries other than zero."""
    pairs = F.explode(F.array(*[F.struct(F.lit(k).alias("j"), F.col(n).cast("double").alias("v")) for k, n in enumerate(names)]))
    return df.select(key, pairs.alias("e")).select(key, "e.j", "e.v").filter("v != 0")


def from_coo(coo: DataFrame, key: str, names: list[str]) -> DataFrame:
    return coo.groupBy(key).agg(*[F.coalesce(F.sum(F.when(F.col("j") == k, F.col("v"))), F.lit(0.0)).alias(n) for k, n in enumerate(names)])


def rank_by(df: DataFrame, by: list[str], order: list, kind: str, name: str = "rank") -> DataFrame:
    ways = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank, "percent_rank": F.percent_rank, "cume_dist": F.cume_dist, "ntile": lambda: F.ntile(4)}
    return df.withColumn(name, ways[kind]().over(Window.partitionBy(*by).orderBy(*order)))


def shift(df: DataFrame, by: list[str], order: list, column: str, k: int = 1) -> DataFrame:
    move = F.lag if k > 0 else F.lead
    return df.withColumn(f"shifted_{column}", move(column, abs(k)).over(Window.partitionBy(*by).orderBy(*order)))


def top_per(df: DataFrame, by: list[str], order: list, k: int) -> DataFrame:
    return rank_by(df, by, order, "row_number", "_r").filter(F.col("_r") <= k).drop("_r")


def split(df: DataFrame, key: str) -> DataFrame:
    """A fixed 80/20 split by the key, whatever the partitioning."""
    return df.withColumn("is_test", F.col(key) % 10 >= 8)


def metrics_binary(df: DataFrame, label: Column, predicted: Column) -> DataFrame:
    one = lambda c: F.sum(F.when(c, 1).otherwise(0))
    counts = df.agg(one((label == 1) & (predicted == 1)).alias("tp"), one((label == 0) & (predicted == 1)).alias("fp"), one((label == 1) & (predicted == 0)).alias("fn"), one((label == 0) & (predicted == 0)).alias("tn"))
    return counts.withColumns({
        "accuracy": (F.col("tp") + F.col("tn")) / (F.col("tp") + F.col("fp") + F.col("fn") + F.col("tn")),
        "precision": F.try_divide("tp", F.col("tp") + F.col("fp")), "recall": F.try_divide("tp", F.col("tp") + F.col("fn")),
    })


def auc_rank(df: DataFrame, label: str, score: str) -> DataFrame:
    """Area under the curve from average ranks; ties are grouped first.

    Scores are cut into ranges at approximate quantiles; a window runs inside each range, and the few ranges'
    counts give each one's first rank.
    """
    spark = df.sparkSession
    groups = df.groupBy(score).agg(F.count("*").alias("n"), F.sum(label).alias("pos"))
    parts = max(2, int(spark.conf.get("spark.sql.shuffle.partitions")))
    cuts = sorted(set(groups.agg(F.percentile_approx(score, [k / parts for k in range(1, parts)], 10_000)).first()[0] or []))
    part = F.size(F.filter(F.array(*[F.lit(float(c)) for c in cuts]).cast("array<double>"), lambda c: c < F.col(score))) if cuts else F.lit(0)
    groups = groups.withColumn("_part", part)
    starts = groups.groupBy("_part").agg(F.sum("n").alias("_n"))  # one row a range
    first = starts.withColumn("_first", F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_n")
    inside = F.coalesce(F.sum("n").over(Window.partitionBy("_part").orderBy(score).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = groups.withColumn("_inside", inside).join(F.broadcast(first), "_part").withColumn("rank", F.col("_first") + F.col("_inside") + (F.col("n") + 1) / 2)
    sums = ranked.agg(F.sum(F.col("rank") * F.col("pos")).alias("r"), F.sum("pos").alias("p"), F.sum("n").alias("n"))
    return sums.select(((F.col("r") - F.col("p") * (F.col("p") + 1) / 2) / (F.col("p") * (F.col("n") - F.col("p")))).alias("auc"))
