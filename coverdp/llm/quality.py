"""Quality rules with DataFrame functions only: text statistics, then robust outliers for each language and source."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coverdp.runtime import materialise

P = 5
#: No group's spread counts as less than this, in the units of FEATURES.
FLOOR = (0.6, 0.35, 0.12, 0.12, 0.2)
#: In place of a language or a source: all of them.
ANY = "\1"


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source, n_words, word_chars, n_symbols, n_dup_lines, n_lines, n_repeat_words of whole texts; null text: none."""
    white = r"[\x20\x09-\x0D]+"
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    blanks = " \t\n\x0b\x0c\r"
    base = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.col("lang").cast("string").alias("lang"),
        F.col("source").cast("string").alias("source"),
        F.length(F.translate(text, blanks, "")).cast("long").alias("word_chars"),
        (F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        F.filter(F.split(text, "\n"), lambda x: F.length(F.translate(x, blanks, "")) > 0).alias("lines"),
        F.transform(F.filter(F.split(text, white), lambda x: x != ""), lambda x: F.xxhash64(x)).alias("w"),
    )
    sized = base.withColumn("n_words", F.size("w").cast("long")).withColumn("n_lines", F.size("lines").cast("long")).withColumn("n_dup_lines", (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long"))
    windows = F.when(
        F.col("n_words") >= 3,
        F.array_sort(F.transform(F.sequence(F.lit(0), F.size("w") - 3), lambda i: F.struct(F.xxhash64(F.get("w", i), F.get("w", i + 1), F.get("w", i + 2)).alias("h"), i.alias("at")))),
    )
    sorted_ = sized.withColumn("s", windows)
    again = sorted_.withColumn("again", F.filter("s", lambda x, i: (x["h"] == F.get("s", i - 1)["h"]) | (x["h"] == F.get("s", i + 1)["h"])))
    start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(-3).alias("last"))
    covered = F.aggregate(
        F.array_sort(F.transform("again", lambda x: x["at"])),
        start,
        lambda acc, at: F.struct((acc["n"] + F.least(F.lit(3), at - acc["last"])).cast("long").alias("n"), at.alias("last")),
        lambda acc: acc["n"],
    )
    return again.select("doc_id", "lang", "source", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_lines", F.coalesce(covered, F.lit(0).cast("long")).alias("n_repeat_words"))


def _features(n: Column) -> list[Column]:
    some = F.greatest(n, F.lit(1)).cast("double")
    return [F.log1p(n.cast("double")), F.col("word_chars") / some, F.sqrt(F.col("n_symbols") / some), F.sqrt(F.col("n_repeat_words") / some), F.sqrt(F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1)).cast("double"))]


def _chi2(x: float, p: int) -> float:
    """The chi-square distribution function."""
    y, half = x / 2, (p % 2) / 2
    return (math.erf(math.sqrt(y)) if half else 1.0) - math.exp(-y) * sum(y ** (i + half) / math.gamma(i + half + 1) for i in range(p // 2))


def _quantile(q: float, p: int) -> float:
    lo, hi = 0.0, 1e3
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if _chi2(mid, p) < q else (lo, mid)
    return lo


def _moments(x: list[Column], weight: Column | None = None) -> list[Column]:
    """Sums for a mean and a covariance, as partial aggregates."""
    return [F.avg(v).alias(f"m{i}") for i, v in enumerate(x)] + [F.covar_pop(x[i], x[j]).alias(f"c{i}{j}") for i in range(P) for j in range(i + 1)]


def _factor(groups: DataFrame, scale: float, det: str = "det") -> DataFrame:
    """The Cholesky factor of scale * covariance with floored spreads, as columns l{i}{j}, and its determinant."""
    out = groups
    for i in range(P):
        for j in range(i + 1):
            v = F.coalesce(F.col(f"c{i}{j}"), F.lit(0.0)) * scale + (FLOOR[i] ** 2 * 0.25 if i == j else 0.0)
            v = v - sum((F.col(f"l{i}{k}") * F.col(f"l{j}{k}") for k in range(j)), F.lit(0.0))
            out = out.withColumn(f"l{i}{j}", F.sqrt(F.greatest(v, F.lit(FLOOR[i] ** 2 * 0.05))) if i == j else v / F.col(f"l{j}{j}"))
    out = out.withColumn(det, sum((2 * F.log(f"l{i}{i}") for i in range(P)), F.lit(0.0)))
    return out.drop(*(f"c{i}{j}" for i in range(P) for j in range(i + 1)))


def _distance(rows: DataFrame) -> DataFrame:
    """Adds d, the squared Mahalanobis distance, by forward substitution with the group's factor."""
    out = rows
    for i in range(P):
        z = F.col(f"x{i}") - F.col(f"m{i}") - sum((F.col(f"l{i}{j}") * F.col(f"z{j}") for j in range(i)), F.lit(0.0))
        out = out.withColumn(f"z{i}", z / F.col(f"l{i}{i}"))
    return out.withColumn("d", sum((F.col(f"z{i}") * F.col(f"z{i}") for i in range(P)), F.lit(0.0)))


def quality_rules(docs: DataFrame, keep: float = 0.75, cutoff: float = 0.99995, steps: int = 4, least: int = 40, least_words: int = 50, most_repeat: int = 50) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, distance, kept for each row of docs(doc_id, text, lang, source).

    base_failed: fewer than least_words words, or over most_repeat per cent of them in repeated three-word windows.
    The others get minimum-covariance-determinant estimates for each (lang, source), null being a group of its own:
    from two starts (medians with mean deviations; the same with the largest coordinate as distance) `steps`
    concentration steps on the share `keep` of least distance; the start of the lesser determinant stays; one
    reweighted step follows. Rows beyond the `cutoff` quantile of chi-square are not kept. Groups under `least` such
    rows are judged by the estimate of their whole language, languages under `least` by that of all rows; only where
    all rows together are fewer, there is nothing to judge by: a null distance, and nothing is rejected.
    """
    key = ["g_lang", "g_source"]
    stats = statistics(docs).withColumn("base_failed", (F.col("n_words") < least_words) | (100 * F.col("n_repeat_words") > most_repeat * F.col("n_words")))
    rows = stats.withColumns({f"x{i}": x for i, x in enumerate(_features(F.col("n_words")))})
    rows = materialise(rows.withColumns({"o_lang": F.coalesce("lang", F.lit("\0")), "o_source": F.coalesce("source", F.lit("\0"))}))
    x = [F.col(f"x{i}") for i in range(P)]
    xs = [f"x{i}" for i in range(P)]
    sizes = rows.groupBy("o_lang", "o_source").agg(F.sum((~F.col("base_failed")).cast("long")).alias("n"))
    of_lang = sizes.groupBy("o_lang").agg(F.sum("n").alias("n_lang"))
    enough, whole = F.col("n") >= least, F.col("n_lang") >= least
    pools = materialise(sizes.join(of_lang, "o_lang").select("o_lang", "o_source", F.when(whole | enough, F.col("o_lang")).otherwise(ANY).alias("g_lang"), F.when(enough, F.col("o_source")).otherwise(ANY).alias("g_source")))
    rows = rows.join(pools, ["o_lang", "o_source"])
    used = pools.select(*key).distinct()
    member = F.struct(F.col("o_lang").alias("g_lang"), F.col("o_source").alias("g_source"))
    language, everyone = (F.struct(v.alias("g_lang"), F.lit(ANY).alias("g_source")) for v in (F.col("o_lang"), F.lit(ANY)))
    good = rows.where("not base_failed").select(F.explode(F.array(member, language, everyone)).alias("g"), *xs).select("g.*", *xs)
    good = materialise(good.join(used, key, "left_semi").select(*key, *xs))
    centre = good.groupBy(*key).agg(F.count("*").alias("size"), *(F.percentile_approx(v, 0.5, 1000).alias(f"m{i}") for i, v in enumerate(x))).where(F.col("size") >= least)
    spread = good.join(centre, key).groupBy(*key).agg(F.first("size").alias("size"), *(F.first(f"m{i}").alias(f"m{i}") for i in range(P)), *(F.greatest(F.percentile_approx(F.abs(x[i] - F.col(f"m{i}")), 0.5, 1000) * 1.4826, F.lit(FLOOR[i] / 2)).alias(f"s{i}") for i in range(P)))
    spread = materialise(spread)
    scaled = [(F.col(f"x{i}") - F.col(f"m{i}")) / F.col(f"s{i}") for i in range(P)]
    first = good.join(spread, key).select(*key, "size", *xs, F.explode(F.array(F.struct(F.lit(0).alias("start"), sum((v * v for v in scaled), F.lit(0.0)).alias("d")), F.struct(F.lit(1).alias("start"), F.greatest(*(F.abs(v) for v in scaled)).alias("d")))).alias("e")).select(*key, "size", *xs, "e.start", "e.d")
    estimates = None
    for _ in range(steps):
        near = first if estimates is None else _distance(good.join(estimates, key))
        limit = materialise(near.groupBy(*key, "start").agg(F.percentile_approx("d", keep, 10000).alias("limit")))
        inside = near.join(limit, [*key, "start"]).where("d <= limit")
        estimates = materialise(_factor(inside.groupBy(*key, "start").agg(*_moments(x)), 1.0))
    best = estimates.groupBy(*key).agg(F.min(F.struct("det", "start")).alias("b")).select(*key, "b.start")
    inner = _quantile(keep, P)
    consistent = keep / _chi2(inner, P + 2)
    final = _rescaled(estimates.join(best, [*key, "start"]), consistent)
    reweighted = _distance(good.join(final, key)).where(F.col("d") <= _quantile(0.975, P))
    final = materialise(_factor(reweighted.groupBy(*key).agg(*_moments(x)), 0.975 / _chi2(_quantile(0.975, P), P + 2)).drop("det"))
    judged = _distance(rows.join(final, key, "left"))
    bad = F.coalesce(F.col("d") > _quantile(cutoff, P), F.lit(False))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", F.when(~F.col("base_failed"), F.col("d")).alias("distance"), (~F.col("base_failed") & ~bad).alias("kept"))


def _rescaled(estimates: DataFrame, by: float) -> DataFrame:
    return estimates.withColumns({f"l{i}{j}": F.col(f"l{i}{j}") * math.sqrt(by) for i in range(P) for j in range(i + 1)}).drop("det", "start")
