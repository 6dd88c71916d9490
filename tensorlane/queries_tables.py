"""Registered queries of the operators around the methods: baselines, measures, tables, streams."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import baseline, measure, relops, streaming
from . import functions as fx
from . import queries as scoring
from .oracle.sql import fixed, forest_sql
from .pipeline import chain, diagnose
from .plans.scoring import compile_pipeline, register_scorer
from .sources import read_table, stream_table
from .workloads import HIGGS, OPS, YEAR

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


_FOREST = scoring.model(HIGGS, "bagged", 8, 6, 2, classifier=True)
_KEYS = list(HIGGS.keys)
_PS = f"SELECT {', '.join(_KEYS)}, p0, p1 FROM ({forest_sql(_FOREST, HIGGS.names, HIGGS.sql(), _KEYS)})"


@query("forest_udf_rowwise", _PS)
def _(s, d):
    return baseline.udf_rowwise(HIGGS.frame(s, d), _FOREST, HIGGS.names, _KEYS)


@query("forest_case_baseline", _PS)
def _(s, d):
    return baseline.case_sql(HIGGS.frame(s, d), _FOREST, HIGGS.names, _KEYS)


@query("forest_relational_walk", _PS)
def _(s, d):
    return baseline.relational_walk(HIGGS.frame(s, d, ["l_shipdate"]), _FOREST, HIGGS.names, [*_KEYS, "l_shipdate"]).drop("l_shipdate")


_TREE = scoring.model(scoring.FRAUD, "balanced", 1, 3, 2, seed=60)


@query("forest_rel_lane", f"SELECT event_id, p0, p1 FROM ({forest_sql(_TREE, scoring.FRAUD.names, scoring.FRAUD.sql(), ['event_id'])})")
def _(s, d):
    return baseline.relational_gemm(scoring.FRAUD.frame(s, d), _TREE.trees[0], scoring.FRAUD.names, "event_id")


@query("pipeline_stagewise", scoring.ORACLES["lin_logistic_binary"])
def _(s, d):
    dag = chain(OPS.names, scoring.SCALE, ("lin.linear", {"w": scoring.rule_weights(20, 1), "b": [0.25]}))
    out = baseline.stagewise(OPS.frame(s, d), dag, list(OPS.keys))
    names = ["prediction", "p0", "p1"]
    return scoring.whole(out.toDF(*OPS.keys, *names), list(OPS.keys), names)


@query("sql_registered_scorer", f"SELECT {', '.join(_KEYS)}, prediction FROM ({forest_sql(_FOREST, HIGGS.names, HIGGS.sql(), _KEYS)})")
def _(s, d):
    model = compile_pipeline(chain(HIGGS.names, ("trees.forest", {"spec": _FOREST})), lane="vector")
    register_scorer(s, "score_forest", model)
    HIGGS.frame(s, d).createOrReplaceTempView("higgs_view")
    return s.sql(f"SELECT {', '.join(_KEYS)}, score_forest({', '.join(model.dag.live_columns())}) AS prediction FROM higgs_view")


@query("validate_allclose", "SELECT count(*) AS rows, CAST(0 AS BIGINT) AS mismatches, CAST(0 AS DOUBLE) AS share, CAST(0 AS DOUBLE) AS max_abs_diff FROM events")
def _(s, d):
    f = scoring.model(scoring.FRAUD, "bagged", 8, 5, 2, seed=61, classifier=True)
    a, b = (scoring.scored(scoring.FRAUD, f, strategy=k)(s, d) for k in ("gemm", "tt"))
    return measure.allclose(a, b, ["event_id"], ["p0", "p1"])


@query("cost_per_prediction", "SELECT l_orderkey, l_linenumber, CAST(floor(l_extendedprice / 10000 / 3600 * l_quantity / 100000 * 1e12 + 0.5) AS BIGINT) AS pico FROM lineitem")
def _(s, d):
    """Cost of one of 100,000 predictions, for the hourly rate and the seconds of each row."""
    cost = measure.cost_per_prediction(F.col("l_extendedprice") / 10000, F.col("l_quantity"), 100_000)
    lines = read_table(s, d, "lineitem", ["l_orderkey", "l_linenumber", "l_extendedprice", "l_quantity"])
    return lines.select("l_orderkey", "l_linenumber", F.floor(cost * 1e12 + 0.5).cast("long").alias("pico"))


@query(
    "speedup_summary",
    "SELECT count(*) AS pipelines, avg(CASE WHEN b > o THEN 1.0::DOUBLE ELSE 0 END) AS faster, min(b / o) AS least, median(b / o) AS median, max(b / o) AS greatest "
    "FROM (SELECT l_quantity AS b, 4.0::DOUBLE * l_linenumber AS o FROM lineitem) t",
)
def _(s, d):
    lines = read_table(s, d, "lineitem", ["l_orderkey", "l_quantity", "l_linenumber"])
    return measure.speedup_summary(lines.select(F.col("l_orderkey").alias("pipeline"), F.col("l_quantity").alias("baseline"), (F.col("l_linenumber") * F.lit(4.0)).alias("ours")))


@query(
    "coverage_summary",
    "SELECT count(*) AS pipelines, CAST(sum(CAST(s AS INT)) AS BIGINT) AS supported, CAST(sum(CAST(s AND f AS INT)) AS BIGINT) AS failed, CAST(sum(CAST(s AND NOT f AS INT)) AS BIGINT) AS reported "
    "FROM (SELECT event_type <> 'signup' AS s, value > 90 AS f FROM events) t",
)
def _(s, d):
    events = read_table(s, d, "events", ["event_id", "event_type", "value"])
    return measure.coverage(events.select(F.col("event_id").alias("pipeline"), (F.col("event_type") != "signup").alias("supported"), (F.col("value") > 90).alias("failed")))


@query("op_count_table", "SELECT CAST(l_quantity AS INT) AS d, count(*) AS rows, CAST(d * d + d + 1 AS BIGINT) AS pairwise, CAST(2 AS BIGINT) AS outer_calls FROM lineitem GROUP BY d")
def _(s, d):
    """Primitive calls of both idioms for each number of inputs that stands in the table."""
    from .kernels import CALLS_OUTER, calls_pairwise

    sizes = read_table(s, d, "lineitem", ["l_quantity"]).groupBy(F.col("l_quantity").cast("int").alias("d")).agg(F.count("*").alias("rows"))
    return sizes.select("d", "rows", calls_pairwise(F.col("d").cast("long")).alias("pairwise"), F.lit(CALLS_OUTER).cast("long").alias("outer_calls"))


_BRANDS = [f"b{k}" for k in range(25)]


def _density_sql(view, names: list[str]) -> str:
    return f"SELECT '{view.name}' AS view, avg(({' + '.join(f'CAST({n} <> 0 AS INT)' for n in names)}) / {len(names)}::DOUBLE) AS density FROM ({view.sql()})"


@query(
    "w18_diagnostics",
    f"WITH dense AS ({_density_sql(OPS, OPS.names)} UNION ALL {_density_sql(YEAR, _BRANDS)}) "
    "SELECT view, 'too small: one shallow tree is faster as a conditional expression' AS note FROM dense "
    "UNION ALL SELECT view, 'too sparse: use the relational lane' AS note FROM dense WHERE density < 0.05",
)
def _(s, d):
    """Notes on a shallow tree over dense columns and over one-hot ones, whose densities are measured on the table."""
    tiny, rows = scoring.model(OPS, "balanced", 1, 2, 2), []
    for view, names in ((OPS, OPS.names), (YEAR, _BRANDS)):
        filled = sum((F.col(n) != 0).cast("int") for n in names) / len(names)
        density = view.frame(s, d).agg(F.avg(filled)).first()[0]
        rows += [(view.name, note) for note in diagnose(chain(names, ("trees.forest", {"spec": tiny})), density)]
    return s.createDataFrame(rows, "view string, note string")


# -- tables -------------------------------------------------------------------------------


@query("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45")
def _(s, d):
    return read_table(s, d, "lineitem", ["l_orderkey", "l_quantity"]).filter(F.col("l_quantity") > 45)


@query("join_dim", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def _(s, d):
    return relops.join_dim(read_table(s, d, "nation"), read_table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")


@query("join_fact", "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus")
def _(s, d):
    return relops.join_fact(read_table(s, d, "lineitem"), read_table(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("join_outer", "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey")
def _(s, d):
    return read_table(s, d, "customer").join(read_table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", "o_orderkey")


for _kind, _not in (("semi", ""), ("anti", "NOT ")):
    QUERIES[f"join_{_kind}"] = lambda s, d, k=_kind: read_table(s, d, "customer").join(read_table(s, d, "orders").filter("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), f"left_{k}").select("c_custkey")
    ORACLES[f"join_{_kind}"] = f"SELECT c_custkey FROM customer WHERE {_not}EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)"


@query("join_range_bins", "SELECT (CASE WHEN l_quantity >= 10 THEN 1 ELSE 0 END + CASE WHEN l_quantity >= 25 THEN 1 ELSE 0 END + CASE WHEN l_quantity >= 40 THEN 1 ELSE 0 END)::INT AS bin, count(*) AS n FROM lineitem GROUP BY bin")
def _(s, d):
    return relops.join_range(read_table(s, d, "lineitem", ["l_quantity"]), "l_quantity", [10, 25, 40]).groupBy("bin").agg(F.count("*").alias("n"))


@query("join_asof", "SELECT a.event_id, b.value AS last_value FROM (SELECT * FROM events WHERE event_type = 'error') a ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') b ON a.user_id = b.user_id AND a.ts >= b.ts")
def _(s, d):
    e = read_table(s, d, "events")
    left, right = e.filter("event_type = 'error'").select("user_id", "ts", "event_id"), e.filter("event_type = 'view'").select("user_id", "ts", "value")
    return relops.join_asof(left, right, "user_id", "ts", "value").select("event_id", "last_value")


@query("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND abs(epoch(date_trunc('second', a.ts)) - epoch(date_trunc('second', b.ts))) <= 600 WHERE a.event_type = 'error' AND b.event_type = 'purchase'")
def _(s, d):
    e = read_table(s, d, "events")
    a = e.filter("event_type = 'error'").select("user_id", F.col("ts").alias("ta"), F.col("event_id").alias("a"))
    b = e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("tb"), F.col("event_id").alias("b"))
    return relops.join_interval(a, b, "user_id", "ta", "tb", 600).select("a", "b")


@query("coo_product", "SELECT a.i, b.j, sum(a.v * b.v) AS v FROM (SELECT l_orderkey % 50 AS i, l_linenumber::INT AS j, sum(l_quantity) AS v FROM lineitem GROUP BY ALL) a JOIN (VALUES (1, 0, 2.0::DOUBLE), (2, 1, 0.5), (3, 0, 1.0), (4, 1, 4.0)) b(i, j, v) ON a.j = b.i GROUP BY a.i, b.j")
def _(s, d):
    a = read_table(s, d, "lineitem").groupBy((F.col("l_orderkey") % 50).alias("i"), F.col("l_linenumber").cast("int").alias("j")).agg(F.sum("l_quantity").alias("v"))
    return relops.coo_matmul(a, s.createDataFrame([(1, 0, 2.0), (2, 1, 0.5), (3, 0, 1.0), (4, 1, 4.0)], "i int, j int, v double"))


@query("to_coo", "SELECT event_id, j, v FROM (SELECT event_id, 0 AS j, CAST(event_type = 'click' AS INT)::DOUBLE AS v FROM events UNION ALL SELECT event_id, 1, CAST(event_type = 'error' AS INT)::DOUBLE FROM events) WHERE v <> 0")
def _(s, d):
    return relops.to_coo(scoring.FRAUD.frame(s, d), "event_id", ["e0", "e1"])


@query("from_coo", "SELECT event_id, CAST(event_type = 'click' AS INT)::DOUBLE AS a, CAST(event_type = 'error' AS INT)::DOUBLE AS b FROM events WHERE event_type IN ('click', 'error')")
def _(s, d):
    return relops.from_coo(relops.to_coo(scoring.FRAUD.frame(s, d), "event_id", ["e0", "e1"]), "event_id", ["a", "b"])


@query("agg_moments", f"SELECT l_returnflag, count(*) AS n, {fixed('avg(l_quantity)')} AS mean, {fixed('var_pop(l_quantity)')} AS var, {fixed('corr(l_quantity, l_extendedprice)')} AS cor FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    out = read_table(s, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.avg("l_quantity").alias("mean"), F.var_pop("l_quantity").alias("var"), F.corr("l_quantity", "l_extendedprice").alias("cor"))
    return scoring.whole(out, ["l_returnflag", "n"], ["mean", "var", "cor"])


for _way in ("cube", "rollup"):
    QUERIES[f"agg_{_way}"] = lambda s, d, w=_way: getattr(read_table(s, d, "lineitem"), w)("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))
    ORACLES[f"agg_{_way}"] = f"SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY {_way}(l_returnflag, l_linestatus)"


@query("agg_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
def _(s, d):
    return read_table(s, d, "lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("agg_quantiles", "SELECT quantile_cont(l_quantity, 0.25) AS q1, quantile_cont(l_quantity, 0.5) AS q2, quantile_cont(l_quantity, 0.75) AS q3 FROM lineitem")
def _(s, d):
    return read_table(s, d, "lineitem").agg(*[F.percentile("l_quantity", p).alias(n) for n, p in (("q1", 0.25), ("q2", 0.5), ("q3", 0.75))])


@query("agg_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS f, count(*) FILTER (l_linestatus = 'O') AS o FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    out = read_table(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count()
    return out.select("l_returnflag", F.col("F").alias("f"), F.col("O").alias("o"))


@query("agg_filtered", "SELECT count(*) FILTER (l_quantity > 25) AS large, sum(CASE WHEN l_discount > 0.05 THEN 1 ELSE 0 END)::BIGINT AS cheap FROM lineitem")
def _(s, d):
    return read_table(s, d, "lineitem").agg(F.count(F.when(F.col("l_quantity") > 25, 1)).alias("large"), F.sum(F.when(F.col("l_discount") > 0.05, 1).otherwise(0)).alias("cheap"))


for _rank in ("row_number", "rank", "dense_rank"):
    QUERIES[f"win_{_rank}"] = lambda s, d, k=_rank: relops.rank_by(read_table(s, d, "events", ["event_id", "user_id"]), ["user_id"], [F.desc("event_id")], k).select("event_id", F.col("rank").cast("long").alias("rank"))
    ORACLES[f"win_{_rank}"] = f"SELECT event_id, {_rank}() OVER (PARTITION BY user_id ORDER BY event_id DESC) AS rank FROM events"


@query("win_lag", "SELECT event_id, lag(value) OVER (PARTITION BY user_id ORDER BY event_id) AS shifted_value FROM events")
def _(s, d):
    return relops.shift(read_table(s, d, "events"), ["user_id"], ["event_id"], "value").select("event_id", "shifted_value")


@query("win_rolling", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS top FROM events")
def _(s, d):
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(-4, 0)
    return read_table(s, d, "events").select("event_id", F.max("value").over(w).alias("top"))


@query("topk", "SELECT l_orderkey, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey LIMIT 20")
def _(s, d):
    return read_table(s, d, "lineitem").orderBy(F.desc("l_extendedprice"), "l_orderkey").limit(20).select("l_orderkey", "l_extendedprice")


@query("topk_group", "SELECT user_id, event_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) <= 3")
def _(s, d):
    return relops.top_per(read_table(s, d, "events"), ["user_id"], [F.desc("value"), "event_id"], 3).select("user_id", "event_id")


@query("split_80_20", "SELECT l_orderkey % 10 >= 8 AS is_test, count(*) AS n FROM lineitem GROUP BY is_test")
def _(s, d):
    return relops.split(read_table(s, d, "lineitem"), "l_orderkey").groupBy("is_test").agg(F.count("*").alias("n"))


for _set, _sql in (("union", "UNION ALL"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):
    QUERIES[f"set_{_set}"] = lambda s, d, k=_set: getattr(read_table(s, d, "customer").select(F.col("c_nationkey").alias("k")), {"union": "unionByName", "intersect": "intersect", "except": "subtract"}[k])(read_table(s, d, "supplier").filter("s_acctbal > 5000").select(F.col("s_nationkey").alias("k")))
    ORACLES[f"set_{_set}"] = f"SELECT c_nationkey AS k FROM customer {_sql} SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000"


@query("json_props", "SELECT event_id, CAST(regexp_extract(props, '[0-9]+', 0) AS INT) AS k FROM events")
def _(s, d):
    return read_table(s, d, "events").select("event_id", fx.json_field(F.col("props"), "$.k", "int").alias("k"))


@query("map_sparse", "SELECT event_id, CAST((event_type = 'click')::INT + (event_type = 'error')::INT AS INT) AS n FROM events")
def _(s, d):
    return scoring.FRAUD.frame(s, d).select("event_id", F.size(fx.sparse_map(["e0", "e1"])).alias("n"))


@query("array_vectors", f"SELECT vec_id, {fixed('sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)))')} AS norm, CAST(list_position(embedding, list_max(embedding)) - 1 AS BIGINT) AS top FROM embeddings")
def _(s, d):
    e = read_table(s, d, "embeddings")
    v = F.col("embedding").cast("array<double>")
    return scoring.whole(e.select("vec_id", fx.vec_norm(v).alias("norm"), fx.vec_argmax(F.col("embedding")).cast("long").alias("top")), ["vec_id", "top"], ["norm"])


@query("safe_operations", "SELECT event_id, CASE WHEN user_id % 3 = 0 THEN NULL ELSE value / (user_id % 3) END AS ratio, TRY_CAST(event_type AS INT) AS number FROM events")
def _(s, d):
    return read_table(s, d, "events").select("event_id", fx.safe_div(F.col("value"), F.col("user_id") % 3).alias("ratio"), fx.safe_cast(F.col("event_type"), "int").alias("number"))


@query("date_features", "SELECT o_orderkey, year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, month(o_orderdate)::INT AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS first FROM orders")
def _(s, d):
    f = fx.date_features(F.col("o_orderdate"))
    return read_table(s, d, "orders").select("o_orderkey", f["year"].alias("y"), f["quarter"].alias("q"), f["month"].alias("m"), f["month_start"].alias("first"))


@query("metrics_binary", "SELECT tp, fp, fn, tn, (tp + tn)::DOUBLE / (tp + fp + fn + tn) AS accuracy, tp::DOUBLE / (tp + fp) AS precision, tp::DOUBLE / (tp + fn) AS recall FROM (SELECT count(*) FILTER (a AND b) AS tp, count(*) FILTER (NOT a AND b) AS fp, count(*) FILTER (a AND NOT b) AS fn, count(*) FILTER (NOT a AND NOT b) AS tn FROM (SELECT l_quantity > 25 AS a, l_extendedprice > 40000 AS b FROM lineitem))")
def _(s, d):
    li = read_table(s, d, "lineitem")
    return relops.metrics_binary(li, (F.col("l_quantity") > 25).cast("int"), (F.col("l_extendedprice") > 40000).cast("int"))


@query("auc_rank", f"SELECT {fixed('(sum(r) FILTER (y = 1) - p * (p + 1) / 2) / (p * (n - p))', 10**8)} AS auc FROM (SELECT y, (rank() OVER (ORDER BY s) + (count(*) OVER (PARTITION BY s) - 1) / 2.0::DOUBLE) AS r, sum(y) OVER () AS p, count(*) OVER () AS n FROM (SELECT (l_extendedprice > 40000)::INT AS y, l_quantity AS s FROM lineitem)) GROUP BY p, n")
def _(s, d):
    li = read_table(s, d, "lineitem").select((F.col("l_extendedprice") > 40000).cast("int").alias("y"), F.col("l_quantity").alias("s"))
    return scoring.whole(relops.auc_rank(li, "y", "s"), [], ["auc"], 10**8)


@query("mismatch_by_segment_cube", "SELECT l_returnflag, l_linestatus, count(*) AS rows, CAST(0 AS BIGINT) AS mismatches FROM lineitem GROUP BY cube(l_returnflag, l_linestatus)")
def _(s, d):
    li = HIGGS.frame(s, d, ["l_returnflag", "l_linestatus"])
    dag = chain(HIGGS.names, ("trees.forest", {"spec": _FOREST, "strategy": "ptt"}))
    keep = ["l_returnflag", "l_linestatus", *HIGGS.names]
    a = compile_pipeline(dag, lane="vector", rules=()).score(li, keep, ["prediction", "p0", "p1"])
    other = sum((baseline.case_column(t, HIGGS.names, 0) for t in _FOREST.trees[1:]), baseline.case_column(_FOREST.trees[0], HIGGS.names, 0)) / float(len(_FOREST.trees))
    return a.withColumn("bad", (F.abs(F.col("p0") - other) > 1e-5).cast("long")).cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("rows"), F.sum("bad").alias("mismatches"))


# -- streams ------------------------------------------------------------------------------


@query("stream_score", f"SELECT event_id, prediction FROM ({forest_sql(_TREE, scoring.FRAUD.names, scoring.FRAUD.sql(), ['event_id'])})")
def _(s, d):
    rows = stream_table(s, d, "events").selectExpr("event_id", *scoring.FRAUD.columns("spark"))
    return streaming.replay(compile_pipeline(chain(scoring.FRAUD.names, ("trees.forest", {"spec": _TREE})), lane="vector").score(rows, ["event_id"], ["prediction"]))


def _windows(kind: str, size: str, slide: str | None = None):
    def run(s, d):
        rows = streaming.with_lateness(stream_table(s, d, "events"), "40 days")
        out = streaming.replay(streaming.score_windows(rows, kind, size, slide), "complete")
        utc = lambda c: F.unix_timestamp(F.col(c))
        return out.select(utc("start").alias("start"), utc("end").alias("end"), *(["user_id"] if kind == "session" else []), "n", F.col("cents").cast("long").alias("cents"))

    return run


QUERIES["stream_tumbling"] = _windows("tumbling", "1 hour")
QUERIES["stream_sliding"] = _windows("sliding", "2 hours", "1 hour")
QUERIES["stream_session"] = _windows("session", "30 minutes")

# event times count as UTC
_SUMS = "count(*) AS n, CAST(sum(floor(value * 100)) AS BIGINT) AS cents"
_HOUR = "CAST(epoch(date_trunc('hour', ts)) AS BIGINT)"
ORACLES["stream_tumbling"] = f'SELECT {_HOUR} AS start, {_HOUR} + 3600 AS "end", {_SUMS} FROM events GROUP BY ALL'
ORACLES["stream_sliding"] = f'SELECT h - 3600 * k AS start, h - 3600 * k + 7200 AS "end", {_SUMS} FROM (SELECT {_HOUR} AS h, value FROM events), (VALUES (0), (1)) t(k) GROUP BY ALL'
ORACLES["stream_session"] = f"""
WITH g AS (SELECT user_id, ts, value, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, value, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g)
SELECT CAST(floor(epoch(min(ts))) AS BIGINT) AS start, CAST(floor(epoch(max(ts) + INTERVAL 30 MINUTE)) AS BIGINT) AS "end", user_id, {_SUMS} FROM s GROUP BY user_id, k
"""


@query("stream_dedup", "SELECT count(*) AS n FROM events")
def _(s, d):
    twice = stream_table(s, d, "events").withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return streaming.replay(streaming.dedup(streaming.with_lateness(twice, "40 days"), "event_id").select("event_id")).agg(F.count("*").alias("n"))


@query("stream_stateful")
def _(s, d):
    return streaming.replay(streaming.stateful_counts(stream_table(s, d, "events")), "update")
