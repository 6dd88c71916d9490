"""Feature views over the given tables, each a list of (name, SQL expression) and a rule for its thresholds.

The expressions are SQL that Spark and DuckDB read alike, but for the few names in ``DIALECT``.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .sources import read_table, star

# The categories of the tables.
BRANDS = [f"Brand#{k}" for k in range(1, 26)]
NATIONS = [f"NATION_{k}" for k in range(25)]
TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
REGIONS = ["AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST"]
STATUSES = ["F", "O", "P"]
EVENTS = ["click", "error", "purchase", "signup", "view"]

DIALECT = {
    "spark": {"WEEKDAY": "dayofweek({})", "DAYS": "datediff({1}, {0})", "K": "CAST(regexp_extract(props, '[0-9]+', 0) AS INT)", "AT": "element_at(embedding, {})", "IDIV": "({0} div {1})"},
    "duckdb": {"WEEKDAY": "(dayofweek({}) + 1)", "DAYS": "date_diff('day', {0}, {1})", "K": "CAST(regexp_extract(props, '[0-9]+', 0) AS INT)", "AT": "embedding[{}]", "IDIV": "({0} // {1})"},
}


class _Names:
    """``{WEEKDAY(x)}`` in a template becomes the dialect's expression."""

    def __init__(self, names: dict[str, str]):
        self.names = names

    def fill(self, text: str) -> str:
        import re

        def put(m):
            args = [a.strip() for a in (m[2] or "").split(";")]
            return self.names[m[1]].format(*args)

        return re.sub(r"\{([A-Z]+)(?::([^}]*))?\}", put, text)


@dataclass(frozen=True)
class View:
    name: str
    source: str  #: star, fact, events, embeddings
    features: tuple[tuple[str, str, float, float], ...]  #: name, expression, least and greatest threshold
    keys: tuple[str, ...]

    @property
    def names(self) -> list[str]:
        return [f[0] for f in self.features]

    def grid(self, steps: int = 16) -> list[list[float]]:
        """Thresholds of each feature: whole 1024ths, evenly spaced between its bounds."""
        return [[round((lo + (hi - lo) * k / steps) * 1024) / 1024 for k in range(1, steps)] if hi > lo else [lo] for _, _, lo, hi in self.features]

    def bounded(self, df: DataFrame) -> View:
        """The view with the least and greatest values of its table as the bounds of its thresholds."""
        found = df.agg(*[g(n).alias(f"{g.__name__}_{n}") for n in self.names for g in (F.min, F.max)]).first()
        return replace(self, features=tuple((n, e, found[f"min_{n}"], found[f"max_{n}"]) for n, e, _, _ in self.features))

    def columns(self, dialect: str, names: list[str] | None = None) -> list[str]:
        fill = _Names(DIALECT[dialect]).fill
        return [f"CAST({fill(e)} AS DOUBLE) + CAST(0 AS DOUBLE) AS {n}" for n, e, _, _ in self.features if names is None or n in names]

    def frame(self, spark: SparkSession, sf_dir: str, extra: list[str] = ()) -> DataFrame:
        return self._source(spark, sf_dir).selectExpr(*self.keys, *extra, *self.columns("spark"))

    def _source(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        if self.source == "star":
            return star(spark, sf_dir)
        if self.source == "fact":
            return read_table(spark, sf_dir, "lineitem").join(read_table(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
        return read_table(spark, sf_dir, self.source)

    def sql(self, extra: list[str] = ()) -> str:
        """The view for DuckDB."""
        return f"SELECT {', '.join([*self.keys, *extra, *self.columns('duckdb')])} FROM {SOURCES[self.source]}"


SOURCES = {
    "star": "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey",
    "fact": "lineitem JOIN orders ON l_orderkey = o_orderkey",
    "events": "events",
    "lineitem": "lineitem",
    "embeddings": "embeddings",
}
LINE_KEYS = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")


def _flags(column: str, values: list[str], prefix: str) -> list[tuple[str, str, float, float]]:
    return [(f"{prefix}{k}", f"CAST({column} = '{v}' AS INT)", 0.5, 0.5) for k, v in enumerate(values)]


def _calendar(column: str, prefix: str, parts: tuple[str, ...]) -> list[tuple[str, str, float, float]]:
    every = {"year": (f"year({column})", 1995, 2001), "month": (f"month({column})", 1, 12), "weekday": (f"{{WEEKDAY:{column}}}", 1, 7), "day": (f"day({column})", 1, 31)}
    return [(f"{prefix}_{p}", *every[p]) for p in parts]


_Q, _P, _D, _T = ("q", "l_quantity", 1, 50), ("price", "l_extendedprice", 1000, 90000), ("disc", "l_discount", 0, 0.1), ("tax", "l_tax", 0, 0.08)
_LAG = ("lag", "{DAYS:o_orderdate;l_shipdate}", -2000, 2000)
_YEAR_NUMBERS = [
    _Q, _D, _T, ("line", "l_linenumber", 1, 7), ("size", "p_size", 1, 50), ("retail", "p_retailprice", 900, 1000), ("total", "o_totalprice", 1000, 500000),
    *_calendar("o_orderdate", "o", ("year", "month", "weekday")), ("c_bal", "c_acctbal", -900, 9900), ("s_bal", "s_acctbal", -800, 9900),
    *_calendar("l_shipdate", "s", ("year", "month", "weekday")), _LAG,
]
_HIGGS = [
    _Q, _P, _D, _T, ("line", "l_linenumber", 1, 7), ("net", "l_extendedprice * (1 - l_discount)", 1000, 90000), ("gross", "l_extendedprice * (1 - l_discount) * (1 + l_tax)", 1000, 90000),
    ("unit", "l_extendedprice / l_quantity", 900, 2000), ("qd", "l_quantity * l_discount", 0, 4), ("qt", "l_quantity * l_tax", 0, 3),
    ("total", "o_totalprice", 1000, 500000), ("share", "l_extendedprice / o_totalprice", 0, 1), *_calendar("o_orderdate", "o", ("year", "month", "weekday", "day")), *_calendar("l_shipdate", "s", ("year", "month", "weekday", "day")),
    _LAG, ("p10", "l_partkey % 10", 0, 9), ("p100", "l_partkey % 100", 0, 99), ("u10", "l_suppkey % 10", 0, 9), ("u100", "l_suppkey % 100", 0, 99), ("c10", "o_custkey % 10", 0, 9), ("c100", "o_custkey % 100", 0, 99), ("k10", "l_orderkey % 10", 0, 9),
]
FRAUD = View("fraud", "events", tuple([
    *_flags("event_type", EVENTS, "e"), ("value", "value", 0, 100), ("root", "sqrt(value)", 0, 10), ("square", "value * value", 0, 10000), ("tens", "floor(value / 10)", 0, 10),
    ("k", "{K}", 0, 99), ("k2", "{K} % 2", 0.5, 0.5), ("k10", "{K} % 10", 0, 9), ("kv", "{K} * value", 0, 5000), ("vk", "value / ({K} + 1)", 0, 20),
    ("hour", "hour(ts)", 0, 23), ("minute", "minute(ts)", 0, 59), ("weekday", "{WEEKDAY:ts}", 1, 7), ("day", "day(ts)", 1, 31), ("weekend", "CAST({WEEKDAY:ts} IN (1, 7) AS INT)", 0.5, 0.5), ("clock", "hour(ts) * 60 + minute(ts)", 0, 1439),
    ("user", "user_id", 0, 100), ("u5", "user_id % 5", 0, 4), ("u10", "user_id % 10", 0, 9), ("u16", "user_id % 16", 0, 15), ("i7", "event_id % 7", 0, 6), ("i11", "event_id % 11", 0, 10), ("i13", "event_id % 13", 0, 12), ("i5", "event_id % 5", 0, 4),
]), ("event_id",))
YEAR = View("year", "star", tuple([*_YEAR_NUMBERS, *_flags("p_brand", BRANDS, "b"), *_flags("n_name", NATIONS, "n"), *_flags("p_type", TYPES, "t"), *_flags("o_orderpriority", PRIORITIES, "r"), *_flags("c_mktsegment", SEGMENTS, "m"), *_flags("r_name", REGIONS, "g"), *_flags("o_orderstatus", STATUSES, "z")]), LINE_KEYS)
COVTYPE = View("covtype", "star", tuple([
    _Q, _D, _T, ("line", "l_linenumber", 1, 7), ("size", "p_size", 1, 50), ("retail", "p_retailprice", 900, 1000), ("total", "o_totalprice", 1000, 500000), ("c_bal", "c_acctbal", -900, 9900), *_calendar("l_shipdate", "s", ("month",)), *_calendar("o_orderdate", "o", ("month",)),
    *_flags("p_brand", BRANDS, "b"), *_flags("p_type", TYPES, "t"), *_flags("c_mktsegment", SEGMENTS, "m"), *_flags("o_orderpriority", PRIORITIES, "r"), *_flags("o_orderstatus", STATUSES, "z"),
]), LINE_KEYS)
HIGGS = View("higgs", "fact", tuple(_HIGGS), LINE_KEYS)
AIRLINE = View("airline", "star", tuple([
    *_calendar("l_shipdate", "s", ("year", "month", "day", "weekday")), *_calendar("o_orderdate", "o", ("year", "month", "weekday")), ("s_nation", "s_nationkey", 0, 24), ("c_nation", "c_nationkey", 0, 24),
    ("u20", "l_suppkey % 20", 0, 19), ("apart", "abs(s_nationkey - c_nationkey)", 0, 24), _Q, ("line", "l_linenumber", 1, 7),
]), LINE_KEYS)
EPSILON = View("epsilon", "embeddings", tuple(
    (f"x{i}_{j}", f"CAST({{AT:{i + 1}}} AS DOUBLE) * CAST({{AT:{j + 1}}} AS DOUBLE)", *((0.0, 0.06) if i == j else (-0.03, 0.03)))
    for i, j in [*[(i, i) for i in range(64)], *[(i, j) for i in range(64) for j in range(i + 1, 64)]]
), ("vec_id",))
OPS = View("ops", "fact", tuple(_HIGGS[:20]), LINE_KEYS)
IRIS = View("iris", "embeddings", tuple((f"d{k}", f"{{AT:{k + 1}}}", -0.3, 0.3) for k in range(20)), ("vec_id",))
STRATEGY = View("strategy", "lineitem", tuple((f"f{j}", f"CAST((l_orderkey * {2 * j + 1} + l_partkey * {j + 3} + l_linenumber * {7 * j + 5}) % 1009 AS DOUBLE) / 1024", 0, 0.98) for j in range(200)), LINE_KEYS)
VIEWS = {v.name: v for v in (FRAUD, YEAR, COVTYPE, HIGGS, AIRLINE, EPSILON, OPS, IRIS, STRATEGY)}


