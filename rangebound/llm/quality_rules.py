"""Quality rules: base counts of each text, then robust multivariate outliers.

Within each language and source, a minimum-covariance-determinant estimate of centre and scatter
is made of transformed statistics, and a text far from the centre in Mahalanobis distance is
rejected. Everything is DataFrame expressions and aggregates; the statistics are whole numbers (thousandths), so
sums, and with them all estimates, do not depend on the order of rows.

Concentration starts at coordinate-wise medians and median deviations, and again at the moments of the half nearest to
those; each step keeps the share `h` of a group nearest to the centre and re-estimates from those. The start
that ends with the least determinant counts. Distances are ranked on a fine
fixed grid, so a group of any size is a bounded histogram, never a sorted list. The last step
reweights. A group of fewer than `least` texts takes its language's estimates.

Defined results: null and empty texts have no words and fail the base rules; null languages and
sources are groups of their own; if a language has fewer than `least` texts too, only the base
rules count; repeated rows count each and are judged alike; other columns of the input are kept as they are, but those
named as a result, which takes their place.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import free_of, materialise, table

SPACE = " \t\n\x0b\x0c\r"
WORD_GAP = r"[\x20\x09-\x0D]+"
WINDOW = 8


@dataclass(frozen=True)
class McdConfig:
    """h: share of a group that concentration keeps; steps: concentration steps; tail: chance of
    rejecting a text of the fitted shape; least: least size of a group; floors: smallest spread of
    each statistic in thousandths, so that a constant statistic doesn't reject the first other value. In a group that
    repeats no lines, two thirds of them repeated are too many by themselves; repeated words beyond 30 percent are the base rule's."""

    h: float = 0.75
    steps: int = 4
    tail: float = 1e-3
    least: int = 50
    floors: tuple[int, ...] = (800, 400, 500, 440, 600)


BASE = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words", "base_failed")
FEATURES = ("f_length", "f_word", "f_symbol", "f_lines", "f_repeat")


def base_counts(docs: DataFrame, text: str = "text") -> DataFrame:
    """All columns of docs, with n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words."""
    t = F.coalesce(F.col(text), F.lit(""))
    a = docs.withColumn("_t", t).withColumn("_b", F.btrim("_t", F.lit(SPACE)))
    a = a.withColumn("_w", F.when(F.col("_b") == "", F.array().cast("array<string>")).otherwise(F.split("_b", WORD_GAP)))
    a = a.withColumn("_l", F.filter(F.split("_t", "\n"), lambda x: F.btrim(x, F.lit(SPACE)) != ""))
    a = a.withColumn("n_words", F.size("_w").cast("long"))
    a = a.withColumn("_h", F.when(F.col("n_words") < WINDOW, F.array().cast("array<bigint>")).otherwise(F.transform(F.sequence(F.lit(1), F.size("_w") - (WINDOW - 1)), lambda i: F.xxhash64(F.slice("_w", i, WINDOW)))))
    a = a.select(
        *docs.columns,
        "n_words",
        F.length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        (F.length("_t") - F.length(F.regexp_replace("_t", r"[#*$%&|<>]+", ""))).cast("long").alias("n_symbols"),
        F.size("_l").cast("long").alias("n_lines"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        "_h",
    )
    # Only texts with a repeated window sort theirs.
    a = a.withColumn("_p", F.when(F.size(F.array_distinct("_h")) < F.size("_h"), F.sort_array(F.transform("_h", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    n = F.size("_p")

    def twin(x: Column, k: Column) -> Column:
        return ((k > 0) & (F.get("_p", k - 1)["h"] == x["h"])) | ((k < n - 1) & (F.get("_p", k + 1)["h"] == x["h"]))

    a = a.withColumn("_i", F.sort_array(F.transform(F.filter("_p", twin), lambda x: x["i"])))
    start = F.struct(F.lit(-WINDOW).alias("last"), F.lit(0).alias("n"))
    covered = F.aggregate("_i", start, lambda acc, i: F.struct(i.alias("last"), (acc["n"] + F.least(F.lit(WINDOW), i - acc["last"])).alias("n")), lambda acc: acc["n"])
    return a.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long")).drop("_h", "_p", "_i")


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


def statistics() -> dict[str, Column]:
    """The transformed statistic vector, in thousandths."""
    w, c, n = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.col("word_chars"), F.lit(1)), F.greatest(F.col("n_lines"), F.lit(1))
    raw = (F.log1p(w), c / w, F.log1p(100 * F.col("n_symbols") / c), F.log1p(10 * F.col("n_dup_lines") / n), F.log1p(10 * F.col("n_repeat_words") / w))
    return {k: F.round(1000 * x).cast("long") for k, x in zip(FEATURES, raw, strict=True)}


def chi2_cdf(x: float, d: int) -> float:
    """By the series of the incomplete gamma function."""
    a, y = d / 2, x / 2
    if y <= 0:
        return 0.0
    term = total = 1 / a
    k = a
    while term > total * 1e-16:
        k += 1
        term *= y / k
        total += term
    return min(1.0, total * math.exp(a * math.log(y) - y - math.lgamma(a)))


def chi2_quantile(p: float, d: int) -> float:
    lo, hi = 0.0, 1000.0
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if chi2_cdf(mid, d) < p else (lo, mid)
    return hi


def distance() -> Column:
    """Squared Mahalanobis distance from columns m_i (centre) and l_i_j (Cholesky factor): forward
    substitution, written out."""
    z: list[Column] = []
    for i, x in enumerate(FEATURES):
        rest = F.col(x) - F.col(f"m_{i}")
        for j in range(i):
            rest = rest - F.col(f"l_{i}_{j}") * z[j]
        z.append(rest / F.col(f"l_{i}_{i}"))
    total = z[0] * z[0]
    for x in z[1:]:
        total = total + x * x
    return total


def estimates(rows: DataFrame, cfg: McdConfig, scale: float = 1.0) -> DataFrame:
    """By group: size, centre and Cholesky factor of scale x covariance, its variances raised to the squared floors."""
    d = len(FEATURES)
    sums = [F.sum(x).alias(f"s_{i}") for i, x in enumerate(FEATURES)]
    prods = [F.sum(F.col(FEATURES[i]) * F.col(FEATURES[j])).alias(f"p_{i}_{j}") for i in range(d) for j in range(i + 1)]
    got = rows.groupBy("g").agg(F.count(F.lit(1)).alias("n"), *sums, *prods)
    spread = lambda i, j: scale * (F.col(f"p_{i}_{j}") / F.col("n") - F.col(f"s_{i}") / F.col("n") * (F.col(f"s_{j}") / F.col("n")))
    got = got.select("g", "n", *[(F.col(f"s_{i}") / F.col("n")).alias(f"m_{i}") for i in range(d)], *[(F.greatest(spread(i, j), F.lit(float(cfg.floors[i] ** 2))) if i == j else spread(i, j)).alias(f"c_{i}_{j}") for i in range(d) for j in range(i + 1)])
    return cholesky(got)


def cholesky(got: DataFrame) -> DataFrame:
    d = len(FEATURES)
    for i in range(d):
        for j in range(i + 1):
            rest = F.col(f"c_{i}_{j}")
            for k in range(j):
                rest = rest - F.col(f"l_{i}_{k}") * F.col(f"l_{j}_{k}")
            got = got.withColumn(f"l_{i}_{j}", F.sqrt(F.greatest(rest, F.lit(1.0))) if i == j else rest / F.col(f"l_{j}_{j}"))
    return got.drop(*[f"c_{i}_{j}" for i in range(d) for j in range(i + 1)])


def quantile_bins(rows: DataFrame, keys: list[str], bin_: str, share: float) -> DataFrame:
    """By keys: the least bin at or below which the share of rows lies. One row for each key and
    bin is sorted, not the rows."""
    n = rows.groupBy(*keys, bin_).agg(F.count(F.lit(1)).alias("c"))
    w = W.partitionBy(*keys)
    run = F.sum("c").over(w.orderBy(bin_).rowsBetween(W.unboundedPreceding, 0))
    return n.select(*keys, bin_, (run >= F.ceil(F.sum("c").over(w) * share)).alias("in")).where("in").groupBy(*keys).agg(F.min(bin_).alias("cut"))


def start(rows: DataFrame, cfg: McdConfig) -> DataFrame:
    """Medians, and a diagonal scatter of median deviations, on a grid of half a tenth of each floor."""
    d = len(FEATURES)
    grid = [max(1, f // 20) for f in cfg.floors]
    entries = F.array(*[F.struct(F.lit(i).alias("i"), F.floor(F.col(x) / grid[i]).alias("b")) for i, x in enumerate(FEATURES)])
    long = rows.select("g", F.explode(entries).alias("e")).select("g", "e.i", "e.b")
    cells = materialise(long.groupBy("g", "i", "b").agg(F.count(F.lit(1)).alias("c")))
    w = W.partitionBy("g", "i")

    def middle(cells: DataFrame, bin_: str) -> DataFrame:
        run = F.sum("c").over(w.orderBy(bin_).rowsBetween(W.unboundedPreceding, 0))
        return cells.select("g", "i", bin_, (2 * run >= F.sum("c").over(w)).alias("in")).where("in").groupBy("g", "i").agg(F.min(bin_).alias("mid"))

    mids = middle(cells, "b")
    away = cells.join(mids, ["g", "i"]).groupBy("g", "i", F.abs(F.col("b") - F.col("mid")).alias("a")).agg(F.sum("c").alias("c"))
    mad = middle(away, "a").withColumnRenamed("mid", "mad")
    at = F.create_map(*[F.lit(x) for i in range(d) for x in (i, grid[i])])
    floor = F.create_map(*[F.lit(x) for i in range(d) for x in (i, cfg.floors[i])])
    both = mids.join(mad, ["g", "i"]).select("g", "i", ((F.col("mid") + 0.5) * at[F.col("i")]).alias("m"), F.greatest(1.4826 * F.col("mad") * at[F.col("i")], floor[F.col("i")]).alias("s"))
    pick = lambda i, c: F.max(F.when(F.col("i") == i, F.col(c)))
    got = both.groupBy("g").agg(*[pick(i, "m").alias(f"m_{i}") for i in range(d)], *[pick(i, "s").alias(f"l_{i}_{i}") for i in range(d)])
    return got.withColumns({f"l_{i}_{j}": F.lit(0.0) for i in range(d) for j in range(i)})


def nearest(rows: DataFrame, params: DataFrame, share: float) -> DataFrame:
    """Each group's share of rows nearest to its centre."""
    placed = rows.join(params, "g").select("g", *FEATURES, F.floor(F.log1p(distance()) * 200).alias("bin"))
    return placed.join(materialise(quantile_bins(placed, ["g"], "bin", share)), "g").where("bin <= cut")


def fit(rows: DataFrame, cfg: McdConfig) -> DataFrame:
    """rows: g and the statistics. Estimates by group: n, m_i, l_i_j. Concentration runs from each start, and a group takes
    the estimate of least determinant. A group has one row, so Spark broadcasts the estimates only while they are small."""
    d = len(FEATURES)
    cut = chi2_quantile(cfg.h, d)
    grow = cfg.h / chi2_cdf(cut, d + 2)
    half = 0.5 / chi2_cdf(chi2_quantile(0.5, d), d + 2)
    first = materialise(start(rows, cfg))
    found = None
    for i, begin in enumerate((first, estimates(nearest(rows, first, 0.5), cfg, half))):
        params = first if i == 0 else materialise(begin)
        for _ in range(cfg.steps):
            params = materialise(estimates(nearest(rows, params, cfg.h), cfg, grow))
        names = [c for c in params.columns if c != "g"]
        spread = sum((F.log(F.col(f"l_{j}_{j}")) for j in range(d)), F.lit(0.0))
        one = params.select("g", F.round(spread, 9).alias("spread"), F.lit(i).alias("from"), F.struct(*names).alias("p"))
        found = one if found is None else found.unionByName(one)
    params = materialise(found.groupBy("g").agg(F.min_by("p", F.struct("spread", "from")).alias("p")).select("g", "p.*"))
    q = 0.975
    limit = chi2_quantile(q, d)
    inner = rows.join(params, "g").where(distance() <= limit).select("g", *FEATURES)
    sizes = rows.groupBy("g").agg(F.count(F.lit(1)).alias("size"))
    return materialise(estimates(inner, cfg, q / chi2_cdf(limit, d + 2)).drop("n").join(sizes, "g"))


def judge(docs: DataFrame, cfg: McdConfig = McdConfig(), text: str = "text", carry: tuple[str, ...] = ()) -> DataFrame:
    """The columns of docs (those in `carry`, if given), the base counts, base_failed, distance
    (null: not judged) and kept. docs has lang and source. What is carried is written once to the shared folder."""
    carry = carry or tuple(free_of(docs, [*BASE, "distance", "kept"]).columns)
    # What is carried travels as one column, so that no name of it meets one of ours.
    slim = docs.select(F.struct(*carry).alias("row"), F.col(text).alias("text"), "lang", "source")
    counted = base_counts(slim).withColumns({"base_failed": base_failed()} | statistics())
    counted = materialise(counted.select("row", "lang", "source", *BASE, *FEATURES))
    own = F.concat_ws("\x1f", F.lit("s"), F.coalesce(F.concat(F.lit("="), F.col("lang")), F.lit("-")), F.coalesce(F.concat(F.lit("="), F.col("source")), F.lit("-")))
    wide = F.concat_ws("\x1f", F.lit("l"), F.coalesce(F.concat(F.lit("="), F.col("lang")), F.lit("-")))
    rows = counted.where(~F.col("base_failed")).select(F.explode(F.array(own, wide)).alias("g"), *FEATURES)
    params = fit(rows, cfg).where(F.col("size") >= cfg.least)
    limit = chi2_quantile(1 - cfg.tail, len(FEATURES))
    names = [c for c in params.columns if c not in ("g", "size")]
    two = counted.withColumns({"_own": own, "_wide": wide})
    for side, key in (("a", "_own"), ("b", "_wide")):
        two = two.join(params.select(F.col("g").alias(key), *[F.col(c).alias(f"{side}_{c}") for c in names]), key, "left")
    two = two.withColumns({c: F.coalesce(f"a_{c}", f"b_{c}") for c in names}).withColumn("distance", distance())
    kept = ~F.col("base_failed") & (F.coalesce("distance", F.lit(0.0)) <= limit)
    return two.select("row.*", *BASE, "distance", kept.alias("kept"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    got = judge(docs, carry=("doc_id", "lang", "source"))
    return got.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "distance")
