"""Registered queries of column helpers, remaining joins, aggregates, windows, sources and stream enrichment."""

from __future__ import annotations

import tempfile
import uuid
from pathlib import Path

from pyspark.sql import functions as F

from . import functions as fx
from . import queries as scoring
from . import relops, streaming
from .oracle.sql import fixed, forest_sql
from .pipeline import chain
from .plans.scoring import compile_pipeline
from .sources import load_model, read_file, read_table, save_model, stream_table, write_scores

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


_LINE = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
_LINE_SQL = ", ".join(_LINE)
_FRAUD = scoring.FRAUD
_TREE = scoring.model(_FRAUD, "balanced", 1, 3, 2, seed=60)
_TREE_SQL = forest_sql(_TREE, _FRAUD.names, _FRAUD.sql(), ["event_id"])


def _tree_dag():
    return chain(_FRAUD.names, ("trees.forest", {"spec": _TREE}))


def _scratch(s, label: str) -> str:
    return f"{streaming._shared(s)}/{label}-{uuid.uuid4().hex}"


# -- predicates and columns ---------------------------------------------------------------


@query(
    "where_predicates",
    "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 200000 "
    "AND (o_orderpriority LIKE '%H%' OR NULLIF(o_orderpriority, '5-LOW') IS NOT DISTINCT FROM NULL)",
)
def _(s, d):
    orders = read_table(s, d, "orders")
    urgent = F.col("o_orderpriority").like("%H%") | F.nullif(F.col("o_orderpriority"), F.lit("5-LOW")).eqNullSafe(F.lit(None))
    return orders.filter(F.col("o_orderstatus").isin("F", "O") & F.col("o_totalprice").between(1000, 200000) & urgent).select("o_orderkey", "o_orderpriority")


@query("where_score", f"SELECT event_id, {fixed('p1')} AS p1 FROM ({_TREE_SQL}) WHERE p1 >= 0.5")
def _(s, d):
    scores = compile_pipeline(_tree_dag(), lane="vector").score(_FRAUD.frame(s, d), ["event_id"], ["prediction", "p0", "p1"])
    return scoring.whole(relops.where_score(scores, F.col("p1") >= 0.5), ["event_id"], ["p1"])


@query(
    "choose_and_fill",
    "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS band, "
    "coalesce(nullif(p_size, 7), -1) AS size_or, coalesce(nullif(p_brand, 'none'), 'x') AS brand FROM part",
)
def _(s, d):
    band = fx.choose([(F.col("p_size") < 10, F.lit("small")), (F.col("p_size") < 30, F.lit("medium"))], F.lit("large"))
    size = fx.first_non_null(F.nullif(F.col("p_size"), F.lit(7)), F.lit(-1))
    return read_table(s, d, "part").select("p_partkey", band.alias("band"), size.alias("size_or"), F.nvl(F.nullif(F.col("p_brand"), F.lit("none")), F.lit("x")).alias("brand"))


@query(
    "text_columns",
    "SELECT p_partkey, regexp_extract(p_name, '([0-9]+)', 1) AS digits, regexp_replace(p_name, '[aeiou]', '_', 'g') AS masked, "
    "concat_ws('|', p_brand, p_type) AS joined, rpad(p_brand, 12, '.') AS padded, split_part(p_type, ' ', 1) AS head, "
    "CAST(levenshtein(p_brand, p_type) AS INTEGER) AS apart, lower(trim(p_name)) AS low FROM part",
)
def _(s, d):
    return read_table(s, d, "part").select(
        "p_partkey", F.regexp_extract("p_name", "([0-9]+)", 1).alias("digits"), F.regexp_replace("p_name", "[aeiou]", "_").alias("masked"),
        F.concat_ws("|", "p_brand", "p_type").alias("joined"), F.rpad("p_brand", 12, ".").alias("padded"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("head"),
        F.levenshtein("p_brand", "p_type").alias("apart"), F.lower(F.trim("p_name")).alias("low"),
    )


_MATH = {
    "root": "sqrt(l_extendedprice)", "log": "ln(1 + abs(l_quantity))", "grown": "exp(l_discount)", "squashed": "tanh(l_quantity / 50 - 0.5)",
    "square": "pow(l_quantity, 2)", "apart": "abs(l_discount - l_tax)", "side": "CAST(sign(l_discount - l_tax) AS DOUBLE)", "low": "CAST(floor(l_extendedprice) AS DOUBLE)",
}


@query(
    "math_columns",
    f"SELECT {_LINE_SQL}, {', '.join(f'{fixed(e)} AS {n}' for n, e in _MATH.items())}, CAST(((l_partkey - 50) % 7 + 7) % 7 AS BIGINT) AS left_over FROM lineitem",
)
def _(s, d):
    q, x = F.col("l_quantity"), F.col("l_discount") - F.col("l_tax")
    made = fx.math_features(q)
    li = read_table(s, d, "lineitem").select(
        *_LINE, F.sqrt("l_extendedprice").alias("root"), made["log1p"].alias("log"), F.exp("l_discount").alias("grown"), F.tanh(q / 50 - 0.5).alias("squashed"),
        made["square"].alias("square"), F.abs(x).alias("apart"), F.signum(x).alias("side"), F.floor("l_extendedprice").cast("double").alias("low"),
        F.pmod(F.col("l_partkey") - 50, F.lit(7)).cast("long").alias("left_over"),
    )
    return scoring.whole(li, [*_LINE, "left_over"], list(_MATH))


@query("decimal_sums", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,4))) * 10000 AS BIGINT) AS units FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return read_table(s, d, "lineitem").groupBy("l_returnflag").agg((F.sum(fx.money(F.col("l_extendedprice"))) * 10000).cast("long").alias("units"))


@query("bucket_columns", "SELECT count(*) AS rows, true AS in_range, true AS stable FROM orders")
def _(s, d):
    orders = read_table(s, d, "orders").select("o_custkey", fx.bucket(F.col("o_custkey"), 16).alias("b"))
    by_key = orders.groupBy("o_custkey").agg(F.count("*").alias("n"), F.min("b").alias("lo"), F.max("b").alias("hi"))
    return by_key.agg(F.sum("n").alias("rows"), F.min((F.col("lo") >= 0) & (F.col("hi") < 16)).alias("in_range"), F.min(F.col("lo") == F.col("hi")).alias("stable"))


_BEST = "SELECT * FROM (SELECT l_returnflag, l_orderkey, l_linenumber, l_partkey, row_number() OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice DESC, l_orderkey DESC, l_linenumber DESC, l_partkey DESC) AS r FROM lineitem) WHERE r = 1"


@query("pack_columns", f"SELECT l_returnflag, l_orderkey, l_linenumber, l_partkey FROM ({_BEST})")
def _(s, d):
    packed = fx.pack(["l_extendedprice", "l_orderkey", "l_linenumber", "l_partkey"])
    best = read_table(s, d, "lineitem").groupBy("l_returnflag").agg(F.max(packed).alias("p"))
    return best.select("l_returnflag", "p.l_orderkey", "p.l_linenumber", "p.l_partkey")


# -- joins, aggregates, windows -----------------------------------------------------------


@query("join_theta", "SELECT n_nationkey, count(*) AS rows FROM lineitem JOIN nation ON l_quantity > 2 * n_nationkey AND l_discount * 100 < n_nationkey GROUP BY n_nationkey")
def _(s, d):
    li, tests = read_table(s, d, "lineitem", ["l_quantity", "l_discount"]), read_table(s, d, "nation", ["n_nationkey"])
    on = (F.col("l_quantity") > 2 * F.col("n_nationkey")) & (F.col("l_discount") * 100 < F.col("n_nationkey"))
    return relops.join_theta(li, tests, on).groupBy("n_nationkey").agg(F.count("*").alias("rows"))


@query("agg_approx_distinct", "SELECT count(DISTINCT l_partkey) AS exact, true AS near FROM lineitem")
def _(s, d):
    li = read_table(s, d, "lineitem")
    both = li.agg(relops.n_distinct("l_partkey").alias("exact"), relops.n_distinct("l_partkey", approx=0.01).alias("guess"))
    return both.select("exact", (F.abs(F.col("guess") - F.col("exact")) <= 0.05 * F.col("exact")).alias("near"))


@query(
    "agg_grouping_sets",
    "SELECT l_returnflag, l_linestatus, l_linenumber, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM lineitem "
    "GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linenumber), ())",
)
def _(s, d):
    sets = [["l_returnflag", "l_linestatus"], ["l_linenumber"], []]
    return relops.agg_sets(read_table(s, d, "lineitem"), sets, [F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("quantity")])


@query("agg_arg_best", f"SELECT l_returnflag, l_orderkey AS best_order FROM ({_BEST})")
def _(s, d):
    return relops.arg_best(read_table(s, d, "lineitem"), ["l_returnflag"], "l_orderkey", ["l_extendedprice", "l_orderkey", "l_linenumber", "l_partkey"], "best_order")


@query(
    "agg_mode",
    "SELECT l_returnflag, l_linenumber AS mode FROM (SELECT l_returnflag, l_linenumber, row_number() OVER (PARTITION BY l_returnflag ORDER BY count(*) DESC, l_linenumber) AS r "
    "FROM lineitem GROUP BY l_returnflag, l_linenumber) WHERE r = 1",
)
def _(s, d):
    return relops.most_common(read_table(s, d, "lineitem"), ["l_returnflag"], "l_linenumber", "mode")


@query("agg_vocabulary", "SELECT n_regionkey, string_agg(n_name, '|' ORDER BY n_name) AS names FROM (SELECT DISTINCT n_regionkey, n_name FROM nation) GROUP BY n_regionkey")
def _(s, d):
    return read_table(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_set("n_name")), "|").alias("names"))


@query("sample_hash", "SELECT o_orderkey FROM orders WHERE (o_orderkey * 2654435761) % 4294967296 < CAST(floor(0.2 * 4294967296) AS BIGINT)")
def _(s, d):
    return relops.sample_hash(read_table(s, d, "orders"), "o_orderkey", 0.2).select("o_orderkey")


for _kind, _call in (("percent_rank", "percent_rank()"), ("cume_dist", "cume_dist()"), ("ntile", "ntile(4)")):
    def _ranked(s, d, kind=_kind):
        out = relops.rank_by(read_table(s, d, "events"), ["event_type", F.col("user_id") % 50], ["event_id"], kind, "r")
        return scoring.whole(out.withColumn("r", F.col("r").cast("double")), ["event_id"], ["r"], 1_000_000)

    QUERIES[f"win_{_kind}"] = _ranked
    ORACLES[f"win_{_kind}"] = f"SELECT event_id, {fixed('CAST(r AS DOUBLE)', 1_000_000)} AS r FROM (SELECT event_id, {_call} OVER (PARTITION BY event_type, user_id % 50 ORDER BY event_id) AS r FROM events)"


@query(
    "win_range_frame",
    "SELECT event_id, count(*) OVER w AS n, CAST(sum(floor(value * 100)) OVER w AS BIGINT) AS cents FROM (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS sec FROM events) "
    "WINDOW w AS (PARTITION BY user_id ORDER BY sec RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW)",
)
def _(s, d):
    events = read_table(s, d, "events").withColumn("at", F.unix_timestamp(F.col("ts").cast("timestamp")))
    sums = {"n": F.count("*"), "cents": F.sum(F.floor(F.col("value") * 100))}
    return relops.rolling(events, ["user_id"], "at", (-3600, 0), sums).select("event_id", "n", F.col("cents").cast("long").alias("cents"))


_CLASSES = "SELECT CAST(l_linenumber AS INTEGER) AS y, CAST(l_partkey % 7 + 1 AS INTEGER) AS p FROM lineitem"


@query(
    "metrics_multi",
    f"SELECT c AS class, {fixed('tp / pp')} AS precision, {fixed('tp / np')} AS recall, CAST(np AS BIGINT) AS support FROM "
    f"(SELECT c, count(*) FILTER (y = c AND p = c) * 1.0::DOUBLE AS tp, count(*) FILTER (p = c) * 1.0::DOUBLE AS pp, count(*) FILTER (y = c) * 1.0::DOUBLE AS np FROM ({_CLASSES}), range(1, 8) t(c) GROUP BY c)",
)
def _(s, d):
    li = read_table(s, d, "lineitem").select(F.col("l_linenumber").alias("y"), (F.col("l_partkey") % 7 + 1).cast("int").alias("p"))
    out = relops.metrics_multi(li, "y", "p").withColumn("class", F.col("class").cast("long"))
    return scoring.whole(out, ["class", "support"], ["precision", "recall"])


_ERRORS = "SELECT l_extendedprice / 1024 AS y, l_quantity * 1.5 AS p FROM lineitem"


@query(
    "metrics_regress",
    f"SELECT {fixed('sqrt(avg((y - p) * (y - p)))')} AS rmse, {fixed('avg(abs(y - p))')} AS mae, {fixed('1 - sum((y - p) * (y - p)) / (var_pop(y) * count(*))')} AS r2 FROM ({_ERRORS})",
)
def _(s, d):
    li = read_table(s, d, "lineitem").select((F.col("l_extendedprice") / 1024).alias("y"), (F.col("l_quantity") * 1.5).alias("p"))
    return scoring.whole(relops.metrics_regress(li, "y", "p"), [], ["rmse", "mae", "r2"])


# -- sources, sinks, models ---------------------------------------------------------------


@query("files_by_schema", "SELECT f AS fmt, n_nationkey, n_name FROM nation, (VALUES ('csv'), ('json'), ('orc')) t(f)")
def _(s, d):
    nation, out = read_table(s, d, "nation", ["n_nationkey", "n_name"]), None
    for fmt in ("csv", "json", "orc"):
        path = _scratch(s, f"files-{fmt}")
        nation.write.format(fmt).save(path)
        part = read_file(s, path, fmt, "n_nationkey int, n_name string").withColumn("fmt", F.lit(fmt))
        out = part if out is None else out.unionByName(part)
    return out.select("fmt", "n_nationkey", "n_name")


@query("sink_partitioned", "SELECT o_orderkey, o_orderstatus FROM orders")
def _(s, d):
    orders, path = read_table(s, d, "orders", ["o_orderkey", "o_orderstatus"]), _scratch(s, "scores")
    write_scores(orders, path, ["o_orderstatus"])
    write_scores(orders.filter("o_orderstatus = 'F'"), path, ["o_orderstatus"])  # a repeated part replaces itself
    return s.read.schema("o_orderkey long, o_orderstatus string").parquet(path)


@query("model_store", f"SELECT event_id, prediction FROM ({_TREE_SQL})")
def _(s, d):
    with tempfile.TemporaryDirectory() as folder:  # the driver alone writes and reads the model
        path = str(Path(folder) / "model")
        save_model(_tree_dag(), path)
        dag = load_model(path)
    return compile_pipeline(dag, lane="vector").score(_FRAUD.frame(s, d), ["event_id"], ["prediction"])


# -- streams ------------------------------------------------------------------------------


@query("stream_static_join", "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey")
def _(s, d):
    customers = read_table(s, d, "customer", ["c_custkey", "c_mktsegment"])
    rows = streaming.enrich(stream_table(s, d, "orders").select("o_orderkey", "o_custkey"), customers, F.col("o_custkey") == F.col("c_custkey"))
    return streaming.replay(rows.select("o_orderkey", "c_mktsegment"))


@query("stream_model_swap", f"SELECT event_id, prediction FROM ({_TREE_SQL})")
def _(s, d):
    path, model = _scratch(s, "swap"), compile_pipeline(_tree_dag(), lane="vector")
    rows = stream_table(s, d, "events").selectExpr("event_id", *_FRAUD.columns("spark"))
    streaming.sink_scores(rows, path, f"{path}-state", lambda: lambda batch: model.score(batch, ["event_id"], ["prediction"])).awaitTermination()
    return s.read.parquet(path).select("event_id", "prediction")
