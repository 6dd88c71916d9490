"""Quality rules and robust multivariate outliers, with DataFrame functions only.

Every document gets counts from its whole text, and a vector of transformed statistics as
whole numbers.  For each language and source a minimum-covariance-determinant estimate is
found by concentration steps: from a start, keep the half of the rows nearest by
Mahalanobis distance, take their mean and covariance, and repeat.  Every group takes its first steps from
several starts (``STARTS``); the one whose covariance has the least determinant goes on until no group's
determinant falls any more.  The half is cut on a histogram of distances (so no group is ever gathered), sums are of
whole numbers (so the estimate does not depend on how rows are partitioned).  A last step takes all rows within a
quantile of the half's estimate.  A document is rejected where its squared distance from its
group's estimate is beyond the 0.999 point of chi-square, or a base rule fails.
"""

from __future__ import annotations

from functools import reduce
from operator import add

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

WINDOW = 8
#: Concentration steps from each start; then those of the best one, which end when determinants settle.
FIRST_STEPS = 2
#: More steps than this without settling are an error.
MOST_STEPS = 100
#: A group's estimate is settled when the logarithm of its determinant falls by less.
SETTLED = 1e-3
#: Quantile of each statistic that is a start's centre, and its spread in floors.
STARTS = ((0.5, 4.0), (0.5, 1.0), (0.25, 2.0), (0.75, 2.0))
#: Squared distance beyond which a vector is an outlier: the 0.999 point of chi-square with five degrees.
LIMIT = 20.515
#: Rows within this squared distance (the 0.975 point) of the half's estimate make the last one.
NEAR = 12.833
#: Histogram bins to a doubling of the distance.
BINS = 16
#: Sources of a language with fewer rows are pooled to one group.
LEAST_ROWS = 40
#: Estimates of at most so many groups (some 250 bytes each) are sent to all workers.
LOOKUP_GROUPS = 50_000
#: One over the shrinkage of a normal covariance in five dimensions when the nearest half, or those within ``NEAR``, are kept.
CONSISTENCY, NEAR_CONSISTENCY = 1.912, 1.056
#: Least standard deviation of each statistic, in its own units.  Most documents have no symbol and repeat nothing, so
#: there the floor rules: alone, symbols reject from 1.9 % of the characters, repeated lines from 3.3 % of the number
#: of words, repeated words (lines that repeat taken once) from 13 %, and words equal to the one before from 7.4 %.
FLOORS = {"s_word": 20.0, "s_symbol": 30.0, "s_line": 40.0, "s_repeat": 80.0, "s_echo": 60.0}

STATS = tuple(FLOORS)
_SPACE = "[\\x20\\x09-\\x0D]"
_WORD = "[^\\x20\\x09-\\x0D]"


def _pairs(column: str, gap: int) -> Column:
    """Hashes of each element with the one ``gap`` places on; shorter by ``gap``."""
    n = F.greatest(F.size(column) - gap, F.lit(0))
    return F.zip_with(F.slice(column, F.lit(1), n), F.slice(column, F.lit(1 + gap), n), lambda a, b: F.xxhash64(a, b))


def _with_repeats(out: DataFrame, name: str) -> DataFrame:
    """``out`` with the number of words of ``_words`` in repeated windows, in place of ``_words``.

    A window is hashed from its halves, those from theirs.  Only a text in which some half
    window occurs twice can have a repeated window, so only there the windows are sorted.
    """
    out = out.withColumn("_2", _pairs("_words", 1)).drop("_words")
    out = out.withColumn("_4", _pairs("_2", 2)).drop("_2")
    out = out.withColumn("_8", F.when(F.size(F.array_distinct("_4")) < F.size("_4"), _pairs("_4", 4))).drop("_4")
    # Sorted by (hash, place), equal windows are neighbours; the places of those with an equal
    # neighbour are put in order again, and each adds the words that the one before it has not.
    order = F.array_sort(F.transform("_8", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    out = out.withColumn("_order", F.when(F.size(F.array_distinct("_8")) < F.size("_8"), order)).drop("_8")
    shared = F.filter("_order", lambda x, k: ((k > 0) & (F.get("_order", k - 1)["h"] == x["h"])) | F.coalesce(F.get("_order", k + 1)["h"] == x["h"], F.lit(False)))
    out = out.withColumn("_places", F.array_sort(F.transform(shared, lambda x: x["i"]))).drop("_order")
    covered = F.aggregate(
        F.col("_places"), F.struct(F.lit(0).alias("n"), F.lit(-WINDOW).alias("last")),
        lambda a, i: F.struct((a["n"] + F.least(i - a["last"], F.lit(WINDOW))).alias("n"), i.alias("last")),
        lambda a: a["n"].cast("long"),
    )
    return out.withColumn(name, F.coalesce(covered, F.lit(0).cast("long"))).drop("_places")


def with_counts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (of ``WINDOW`` words: 8), n_prose_repeats
    (the same with every line taken once) and n_echo_words (equal to the word before)."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    lines = F.filter(F.split(text, "\\n"), lambda x: x.rlike(_WORD))
    out = docs.withColumn("n_symbols", F.regexp_count(text, F.lit("[#*$%&|<>]")).cast("long"))
    out = out.withColumn("_lines", lines)
    out = out.withColumn("_once", F.array_distinct("_lines"))
    out = out.withColumn("n_dup_lines", (F.size("_lines") - F.size("_once")).cast("long")).drop("_lines")
    out = out.withColumn("_once", F.when(F.col("n_dup_lines") > 0, F.array_join("_once", "\n")))
    out = out.withColumn("_words", F.array_remove(F.split(text, f"{_SPACE}+"), ""))
    n = F.greatest(F.size("_words") - 1, F.lit(0))
    echoes = F.filter(F.zip_with(F.slice("_words", F.lit(1), n), F.slice("_words", F.lit(2), n), lambda a, b: a == b), lambda same: same)
    out = out.withColumns({
        "n_words": F.size("_words").cast("long"), "word_chars": F.char_length(F.array_join("_words", "")).cast("long"), "n_echo_words": F.size(echoes).cast("long"),
    })
    out = _with_repeats(out, "n_repeat_words")
    # lines that repeat are often the heads and feet of pages: s_line counts those, so s_repeat leaves them out
    out = out.withColumn("_words", F.when(F.col("n_repeat_words") > 0, F.array_remove(F.split("_once", f"{_SPACE}+"), "")))
    out = _with_repeats(out, "n_prose_repeats")
    return out.withColumn("n_prose_repeats", F.when(F.col("_once").isNull(), F.col("n_repeat_words")).otherwise(F.col("n_prose_repeats"))).drop("_once")


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


def statistics() -> dict[str, Column]:
    """Transformed statistics in whole thousandths: mean word length, and shares of symbols, repeated lines, repeated and echoed words."""
    words, chars = F.greatest("n_words", F.lit(1).cast("long")), F.greatest("word_chars", F.lit(1).cast("long"))

    def root(share: Column) -> Column:
        return F.floor(F.sqrt(share) * 1000).cast("long")

    return {
        "s_word": F.floor(F.log(F.col("word_chars") / words + 1) * 1000).cast("long"),
        "s_symbol": root(F.col("n_symbols") / chars),
        "s_line": root(F.col("n_dup_lines") / words),
        "s_repeat": root(F.col("n_prose_repeats") / words),
        "s_echo": root(F.col("n_echo_words") / words),
    }


def _moments(keep: Column | None = None) -> list[Column]:
    """Sums of products of whole numbers: exact, whatever the order."""
    value = (lambda c: c) if keep is None else (lambda c: F.when(keep, c))
    first = [F.sum(value(F.col(a)).cast("decimal(20,0)")).cast("double").alias(f"m_{a}") for a in STATS]
    second = [
        F.sum(value(F.col(a) * F.col(b)).cast("decimal(28,0)")).cast("double").alias(f"m_{a}_{b}")
        for i, a in enumerate(STATS) for b in STATS[: i + 1]
    ]
    return [F.sum(value(F.lit(1))).alias("m"), *first, *second]


def _estimate(moments: DataFrame, keys: list[str], factor: float) -> DataFrame:
    """Centre and Cholesky factor of the covariance (scaled, with the floor added) from sums."""
    p = len(STATS)
    out = moments.withColumns({f"c{i}": F.col(f"m_{a}") / F.col("m") for i, a in enumerate(STATS)})
    cov = {}
    for i, a in enumerate(STATS):
        for j, b in enumerate(STATS[: i + 1]):
            cov[i, j] = (F.col(f"m_{a}_{b}") / F.col("m") - F.col(f"c{i}") * F.col(f"c{j}")) * factor + (FLOORS[a] ** 2 if i == j else 0.0)
    for j in range(p):
        out = out.withColumn(f"l{j}{j}", F.sqrt(F.greatest(cov[j, j] - reduce(add, [F.col(f"l{j}{k}") ** 2 for k in range(j)], F.lit(0.0)), F.lit(1.0))))
        out = out.withColumns({
            f"l{i}{j}": (cov[i, j] - reduce(add, [F.col(f"l{i}{k}") * F.col(f"l{j}{k}") for k in range(j)], F.lit(0.0))) / F.col(f"l{j}{j}")
            for i in range(j + 1, p)
        })
    return out.select(*keys, *[f"c{i}" for i in range(p)], *[f"l{i}{j}" for i in range(p) for j in range(i + 1)])


def _distance(df: DataFrame) -> DataFrame:
    """``d2``: the squared Mahalanobis distance, by forward substitution."""
    for i, a in enumerate(STATS):
        rest = F.col(a) - F.col(f"c{i}") - reduce(add, [F.col(f"l{i}{k}") * F.col(f"_z{k}") for k in range(i)], F.lit(0.0))
        df = df.withColumn(f"_z{i}", rest / F.col(f"l{i}{i}"))
    squares = reduce(add, [F.col(f"_z{i}") ** 2 for i in range(len(STATS))])
    return df.withColumn("d2", squares).drop(*[f"_z{i}" for i in range(len(STATS))])


def _half(binned: DataFrame, keys: list[str]) -> DataFrame:
    """For each group the smallest distance bin up to which at least half of its rows lie."""
    bins = binned.groupBy(*keys, "bin").count()
    one = bins.groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("bin", "count"))).alias("bins"), F.sum("count").alias("rows"))  # some hundreds of bins at most
    cut = F.aggregate(
        "bins", F.struct(F.lit(0).cast("long").alias("n"), F.lit(None).cast("int").alias("bin")),
        lambda a, x: F.struct((a["n"] + x["count"]).alias("n"), F.when(a["bin"].isNotNull(), a["bin"]).when(2 * (a["n"] + x["count"]) >= F.col("rows"), x["bin"]).alias("bin")),
        lambda a: a["bin"],
    )
    return one.select(*keys, cut.alias("cut"))


def _looked_up(groups: DataFrame):
    """How to join a table of one row a group: sent to all workers, so that a hot group isn't one task, where groups are few."""
    return F.broadcast if groups.count() <= LOOKUP_GROUPS else (lambda df: df)


def _determinant() -> Column:
    """Logarithm of the determinant of a covariance from its Cholesky factor."""
    return 2 * reduce(add, [F.log(F.col(f"l{i}{i}")) for i in range(len(STATS))])


def _concentrated(rows: DataFrame, now: DataFrame, keys: list[str], near_all, label: str) -> DataFrame:
    """One concentration step of every group's estimates (a row for each of its starts)."""
    each = [*keys, "start"]
    near = _distance(rows.join(near_all(now), keys))
    near = near.withColumn("bin", F.least(F.greatest(F.floor(F.log2(F.col("d2") + 1e-6) * BINS), F.lit(-320)), F.lit(640)).cast("int"))
    kept = near.join(near_all(_half(near, each)), each).filter(F.col("bin") <= F.col("cut"))
    return written(_estimate(kept.groupBy(*each).agg(*_moments()), each, CONSISTENCY).withColumn("logdet", _determinant()), label)


def estimates(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Reweighted minimum-covariance-determinant estimate of each group, by concentration steps over all its rows.

    Equal determinants go to the start that ``STARTS`` names first.
    """
    p = len(STATS)
    # the statistics are whole numbers in a narrow range, so the exact quantiles' table of counts stays small
    levels = sorted({q for q, _ in STARTS})
    groups = rows.groupBy(*keys).agg(F.count("*").alias("n"), *[F.percentile(F.col(a), F.array(*map(F.lit, levels))).alias(f"q{i}") for i, a in enumerate(STATS)])
    groups = written(groups.filter(F.col("n") >= LEAST_ROWS).drop("n"), "mcd-groups")
    near_all = _looked_up(groups)
    starts = F.array(*[F.struct(F.lit(k).alias("start"), F.lit(levels.index(q)).alias("level"), F.lit(spread).alias("spread")) for k, (q, spread) in enumerate(STARTS)])
    now = groups.withColumn("s", F.explode(starts)).select(
        *keys, "s.start", *[F.get(f"q{i}", F.col("s.level")).alias(f"c{i}") for i in range(p)],
        *[(F.col("s.spread") * FLOORS[a] if i == j else F.lit(0.0)).alias(f"l{i}{j}") for i, a in enumerate(STATS) for j in range(i + 1)],
    )
    for step in range(FIRST_STEPS):
        now = _concentrated(rows, now.drop("logdet"), keys, near_all, f"mcd-first-{step}")
    best = now.groupBy(*keys).agg(F.min(F.struct("logdet", "start"))["start"].alias("start"))
    now = written(now.join(best, [*keys, "start"]), "mcd-best")
    for step in range(MOST_STEPS + 1):
        if step == MOST_STEPS:
            raise RuntimeError(f"estimates not settled after {MOST_STEPS} steps")
        was, then = now.select(*keys, F.col("logdet").alias("was")), _concentrated(rows, now.drop("logdet"), keys, near_all, f"mcd-{step}")
        # a step on binned distances may raise a determinant by a hair: the lower one stays
        lower = now.join(then.select(*keys, F.col("logdet").alias("then")), keys).filter(F.col("then") >= F.col("logdet")).drop("then")
        falls = then.join(was, keys).filter(F.col("logdet") < F.col("was"))
        moving = not falls.filter(F.col("was") - F.col("logdet") >= SETTLED).isEmpty()
        now = written(falls.drop("was").unionByName(lower), f"mcd-lower-{step}")
        if not moving:
            break
    near = _distance(rows.join(near_all(now.drop("start", "logdet")), keys)).filter(F.col("d2") <= NEAR)
    return written(_estimate(near.groupBy(*keys).agg(*_moments()), keys, NEAR_CONSISTENCY), "mcd-near")


def judge(docs: DataFrame, *, text_col: str = "text", id_col: str = "doc_id", lang_col: str = "lang", source_col: str = "source", limit: float = LIMIT, whole: bool = False) -> DataFrame:
    """Per document: id, counts, ``base_failed``, ``distance`` (null: no estimate) and ``kept``.

    Null texts have no words (and fail); a null language or source is a value of its own.  Sources of
    fewer than ``LEAST_ROWS`` rows that pass the base rules are pooled within their language; a
    pool that is still smaller is judged by the base rules alone.  Repeated rows are judged
    one by one, and an empty table gives no rows.  Other columns are not read.

    With ``whole``, a column ``row`` more: all columns of ``docs``, as a struct.  It is written with the counts, so
    verdicts need no join with the documents.
    """
    missing = F.lit("\x00")
    rows = docs.select(
        F.col(id_col).alias("id"), F.coalesce(F.col(lang_col).cast("string"), missing).alias("g_lang"),
        F.coalesce(F.col(source_col).cast("string"), missing).alias("g_source"), F.col(text_col).alias("text"),
        *([F.struct("*").alias("row")] if whole else []),
    )
    rows = with_counts(rows).drop("text")
    rows = written(rows.withColumns({**statistics(), "base_failed": base_failed()}), "quality-counts")
    keys = ["g_lang", "g_pool"]
    sizes = rows.filter(~F.col("base_failed")).groupBy("g_lang", "g_source").agg((F.count("*") < LEAST_ROWS).alias("few"))
    sizes = written(sizes, "quality-sizes")
    rows = rows.join(_looked_up(sizes)(sizes), ["g_lang", "g_source"], "left").withColumn("g_pool", F.when(F.col("few"), F.lit("\x01")).otherwise(F.col("g_source"))).drop("few")
    fit = rows.filter(~F.col("base_failed"))
    found = estimates(fit, keys)
    judged = _distance(rows.join(_looked_up(found)(found), keys, "left"))
    return judged.select(
        F.col("id").alias(id_col), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed",
        (~F.col("base_failed") & ~F.coalesce(F.col("d2") > limit, F.lit(False))).alias("kept"), F.col("d2").alias("distance"),
        *(["row"] if whole else []),
    )
