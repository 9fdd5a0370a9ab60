"""Quality rules: robust multivariate outliers. Each text gives a vector of transformed statistics; for each language and
source the minimum-covariance-determinant estimate of centre and scatter is found by concentration steps, and texts
whose squared Mahalanobis distance is beyond a chi-square quantile are rejected, beside two fixed base rules.

A concentration step is one aggregation: rows are binned by the logarithm of their distance, each bin holds its count,
sums and cross products, and the bins that make up the share `cover` of a group give the next estimate. The steps run from
two starts, medians with quartile distances and the plain mean with the whole scatter; each keeps the estimate of the least
determinant that it has met, and the better start counts. Steps end when no determinant falls any more, or after
`most_steps`. Two last steps re-estimate from all rows within the 97.5 % quantile. All of it is SQL; a group's rows never
meet in one task. The limit is the chi-square quantile that one good text in 1 / `beyond` passes, if texts are normal.

Defined results: a null or wordless text has no words and fails the base rules; a null language or source is a group of
its own; groups of fewer than `least_rows` texts that pass the base rules are pooled, by language and then altogether,
and a pool that is still smaller rejects nothing; a statistic that varies less than its floor in `FLOORS` counts with the
floor, one that varies more with its own variance; repeated rows
count each time; on an empty table the result is empty.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from proxcore.llm.common import keep

BLANK = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
#: Statistics of the vector and the least standard deviation each counts with.
FLOORS = {"log_words": 0.6, "log_word_chars": 0.08, "symbol_share": 0.35, "dup_line_share": 0.12, "repeat_share": 0.08}
FEATURES = list(FLOORS)
P = len(FEATURES)
BASE = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]


def _let(value: Column, body) -> Column:  # noqa: ANN001
    """Works out a value once for a body that uses it in lambdas."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _repeats(words: Column) -> Column:
    """Words in 5-word windows that are found twice or more."""

    def of(windows: Column) -> Column:
        placed = F.sort_array(F.transform(windows, lambda h, k: F.struct(h.alias("h"), k.alias("k"))))
        same = lambda s, j, d: F.coalesce(F.get(s, j + d)["h"] == F.get(s, j)["h"], F.lit(False))
        twice = _let(placed, lambda s: F.sort_array(F.filter(F.transform(s, lambda x, j: F.when((j > 0) & same(s, j, -1) | same(s, j, 1), x["k"])), lambda k: k.isNotNull())))
        covered = _let(twice, lambda at: F.aggregate(at, F.struct(F.lit(0).alias("n"), F.lit(0).alias("end")), lambda s, k: F.struct((s["n"] + k + 5 - F.greatest(s["end"], k)).alias("n"), (k + 5).alias("end")), lambda s: s["n"]))
        return F.when(F.size(F.array_distinct(windows)) == F.size(windows), F.lit(0)).otherwise(covered)

    hashed = F.transform(words, lambda w: F.xxhash64(w))
    windows = _let(hashed, lambda h: F.slice(F.transform(h, lambda x, k: F.xxhash64(x, *[F.get(h, k + d) for d in range(1, 5)])), 1, F.size(h) - 4))
    return F.when(F.size(words) < 6, F.lit(0)).otherwise(_let(windows, of))


def base_statistics(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (bigint) and base_failed; columns of these names are replaced."""
    content = F.coalesce(F.col(text), F.lit(""))
    lines = F.filter(F.split(content, "\n"), lambda x: F.translate(x, BLANK, "") != "")
    words = F.array_remove(F.split(content, r"[\x20\x09-\x0D]+"), "")
    out = docs.drop(*(c for c in [*BASE, "base_failed"] if c != text)).withColumn("__stats", _let(words, lambda w: F.struct(F.size(w).cast("bigint").alias("n_words"), _repeats(w).cast("bigint").alias("n_repeat_words"))))
    out = out.withColumns({
        "n_words": F.col("__stats.n_words"),
        "word_chars": F.length(F.translate(content, BLANK, "")).cast("bigint"),
        "n_symbols": (F.length(content) - F.length(F.translate(content, SYMBOLS, ""))).cast("bigint"),
        "n_dup_lines": _let(lines, lambda x: (F.size(x) - F.size(F.array_distinct(x))).cast("bigint")),
        "n_repeat_words": F.col("__stats.n_repeat_words"),
    }).drop("__stats")
    return out.withColumn("base_failed", (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words")))


def _vector() -> list[Column]:
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    return [
        F.log(n), F.log(F.greatest(F.col("word_chars"), F.lit(1)) / n), F.log1p(100.0 * F.col("n_symbols") / n),
        F.sqrt(F.col("n_dup_lines") * 12.0 / n), F.sqrt(F.col("n_repeat_words") / n),
    ]


def chi_square_below(x: float, p: int) -> float:
    """The chi-square distribution function, by the series of the incomplete gamma function."""
    a, x = p / 2, x / 2
    term = total = 1 / a
    k = a
    while term > total * 1e-16:
        k += 1
        term *= x / k
        total += term
    return min(1.0, total * math.exp(-x + a * math.log(x) - math.lgamma(a))) if x > 0 else 0.0


def chi_square_quantile(q: float, p: int) -> float:
    low, high = 0.0, 1000.0
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if chi_square_below(mid, p) < q else (low, mid)
    return high


def _with_distance(df: DataFrame, out: str) -> DataFrame:
    """df with its squared distance, from the joined columns centre and root, the lower triangle of the scatter's Cholesky factor by
    rows. Each coordinate is a column of its own: written out in one another they double at each row, and so does the driver's plan."""
    z = []
    for i in range(P):
        at = i * (i + 1) // 2
        less = "".join(f" - get(root, {at + j}) * __z{j}" for j in range(i))
        z.append(f"({_off(i)}{less}) / get(root, {at + i}) AS __z{i}")  # on aliases to the left
    total = " + ".join(f"__z{i} * __z{i}" for i in range(P))
    return df.selectExpr("*", *z, f"{total} AS {out}").drop(*(f"__z{i}" for i in range(P)))


def _off(i: int) -> str:
    return f"(get(x, {i}) - get(centre, {i}))"


def _pairs() -> list[tuple[int, int]]:
    return [(i, j) for i in range(P) for j in range(i + 1)]


def _factor(groups: DataFrame, cov: dict[tuple[int, int], str], *also: str) -> DataFrame:
    """grp, centre, root, log_det from a table with grp, centre; cov gives the scatter's lower triangle as SQL. Other columns stay if named."""
    given = [f"greatest({cov[i, j]}, {FLOORS[FEATURES[i]] ** 2}D) AS c{i}_{j}" if i == j else f"{cov[i, j]} AS c{i}_{j}" for i, j in _pairs()]
    steps = []
    for i, j in _pairs():
        rest = f"c{i}_{j}" + "".join(f" - l{i}_{k} * l{j}_{k}" for k in range(j))
        steps.append(f"sqrt(greatest({rest}, 1e-9D)) AS l{i}_{j}" if i == j else f"({rest}) / l{j}_{j} AS l{i}_{j}")  # on aliases to the left
    root = ", ".join(f"l{i}_{j}" for i, j in _pairs())
    log_det = " + ".join(f"2 * ln(l{i}_{i})" for i in range(P))
    return groups.selectExpr("grp", "centre", *also, *given).selectExpr("grp", "centre", *also, *steps, f"array({root}) AS root", f"{log_det} AS log_det").select("grp", "centre", "root", "log_det", *also)


def _plain_start(rows: DataFrame) -> DataFrame:
    """Means and the scatter of all rows."""
    centre = ", ".join(f"avg(get(x, {i}))" for i in range(P))
    groups = rows.groupBy("grp").agg(F.expr(f"array({centre}) AS centre"), *[F.expr(f"covar_pop(get(x, {i}), get(x, {j})) AS v{i}_{j}") for i, j in _pairs()])
    return _factor(groups, {(i, j): f"v{i}_{j}" for i, j in _pairs()})


def _robust_start(rows: DataFrame) -> DataFrame:
    """Medians and squared quartile distances."""
    q = [F.expr(f"percentile_approx(get(x, {i}), array(0.25, 0.5, 0.75), 1000) AS q{i}") for i in range(P)]
    groups = rows.groupBy("grp").agg(*q).selectExpr("*", f"array({', '.join(f'get(q{i}, 1)' for i in range(P))}) AS centre")
    return _factor(groups, {(i, j): f"power((get(q{i}, 2) - get(q{i}, 0)) / 1.349D, 2)" if i == j else "0D" for i, j in _pairs()})


def _step(rows: DataFrame, state: DataFrame, cover: float | None, within: float, scale: float) -> DataFrame:
    """The next estimate, from the nearest rows: the share cover, or if it is None those within a squared distance; and before, the
    log_det of this one. The rows bring a group's last centre along, so that a step joins the small table once."""
    near = _with_distance(rows.join(state.select("grp", "centre", "root", F.col("log_det").alias("before")), "grp"), "d")
    last = [F.any_value("centre").alias("was"), F.any_value("before").alias("before")]
    sums_of = {f"s{i}": _off(i) for i in range(P)} | {f"s{i}_{j}": f"{_off(i)} * {_off(j)}" for i, j in _pairs()}
    moments = [F.expr(f"sum({x}) AS {name}") for name, x in sums_of.items()]
    if cover is None:
        sums = near.where(F.col("d") <= within).groupBy("grp").agg(F.count("*").alias("n"), *last, *moments)
    else:
        bins = near.groupBy("grp", F.floor(F.log(F.col("d") + 1e-6) * 24).alias("bin")).agg(F.count("*").alias("n"), *last, *moments)
        own = Window.partitionBy("grp")
        nearer = F.sum("n").over(own.orderBy("bin")) - F.col("n")
        kept = bins.select("*", nearer.alias("nearer"), F.sum("n").over(own).alias("all")).where(F.col("nearer") < F.ceil(cover * F.col("all")))
        sums = kept.groupBy("grp").agg(F.sum("n").alias("n"), F.any_value("was").alias("was"), F.any_value("before").alias("before"), *[F.expr(f"sum({name}) AS {name}") for name in sums_of])
    sums = sums.selectExpr("*", f"array({', '.join(f'get(was, {i}) + s{i} / n' for i in range(P))}) AS centre")
    return _factor(sums, {(i, j): f"{scale!r}D * (s{i}_{j} / n - s{i} * s{j} / (CAST(n AS DOUBLE) * n))" for i, j in _pairs()}, "before")


def _concentrated(rows: DataFrame, cover: float, scale: float, most_steps: int) -> DataFrame:
    """grp, centre, root, log_det: of all estimates that the steps from both starts meet, a group's one of the least determinant.
    Each start's own estimate isn't among them, for it doesn't come from the share `cover` of the rows."""
    two = rows.select(F.explode(F.array(F.lit("0"), F.lit("1"))).alias("k"), "grp", "x").select(F.concat("k", "grp").alias("grp"), "x")
    named = lambda k, s: s.withColumn("grp", F.concat(F.lit(k), F.col("grp")))
    state = keep(named("0", _robust_start(rows)).unionByName(named("1", _plain_start(rows))))
    met: list[DataFrame] = []
    for _ in range(most_steps):
        fresh = keep(_step(two, state, cover, 0.0, scale))
        met.append(fresh)
        fell = fresh.where(F.col("log_det") < F.col("before") - 1e-3).limit(1).count()
        state = fresh
        if not fell and len(met) > 1:
            break
    best = reduce(DataFrame.unionByName, met)  # a row for each group, start and step
    own = best.select(F.substr("grp", F.lit(2)).alias("grp"), F.struct("log_det", F.substr("grp", F.lit(1), F.lit(1)).alias("k"), "centre", "root").alias("s"))
    return keep(own.groupBy("grp").agg(F.min("s").alias("s")).select("grp", "s.centre", "s.root", "s.log_det"))


def _grouped(stats: DataFrame, lang: str, source: str, least_rows: int) -> DataFrame:
    """Rows with grp, language and source or the pool of small groups, and whether it has enough rows."""
    name = F.to_json(F.struct(F.col(lang).alias("l"), F.col(source).alias("s")))
    tongue = F.to_json(F.struct(F.col(lang).alias("l")))
    rows = stats.withColumn("__own", name)
    sizes = rows.groupBy(F.col("__own").alias("__of"), tongue.alias("__lang")).agg(F.count_if(~F.col("base_failed")).alias("n"))
    small = F.sum(F.when(F.col("n") < least_rows, F.col("n")).otherwise(0)).over(Window.partitionBy("__lang"))
    chosen = sizes.select("__of", F.when(F.col("n") >= least_rows, F.col("__of")).when(small >= least_rows, F.concat(F.lit("language "), "__lang")).otherwise("all").alias("grp"), "n")
    chosen = chosen.withColumn("enough", F.sum("n").over(Window.partitionBy("grp")) >= least_rows).drop("n")
    return rows.join(chosen, F.col("__own") == F.col("__of")).drop("__own", "__of")


def score(docs: DataFrame, *, text: str = "text", lang: str = "lang", source: str = "source", cover: float = 0.75, least_rows: int = 60, most_steps: int = 6, beyond: float = 1e-9, columns: list[str] | None = None) -> DataFrame:
    """The given columns of docs (all by default) with the base statistics, base_failed, distance (squared; null without an
    estimate) and kept. The statistics are worked out once and kept in the shared folder."""
    wanted = columns or docs.columns
    stats = base_statistics(docs, text).select(*wanted, *[c for c in [*BASE, "base_failed"] if c not in wanted], *{c for c in (lang, source) if c not in wanted}) if columns else base_statistics(docs, text)
    stats = keep(stats)
    rows = keep(_grouped(stats.select(lang, source, *BASE, "base_failed"), lang, source, least_rows).where(F.col("enough") & ~F.col("base_failed")).select("grp", F.array(*_vector()).alias("x")))
    scale = cover / chi_square_below(chi_square_quantile(cover, P), P + 2)
    state = _concentrated(rows, cover, scale, most_steps)
    again = 0.975 / chi_square_below(chi_square_quantile(0.975, P), P + 2)
    for _ in range(2):
        state = keep(_step(rows, state, None, chi_square_quantile(0.975, P), again))
    judged = _grouped(stats, lang, source, least_rows).withColumn("x", F.array(*_vector())).join(state.select(F.col("grp").alias("__grp"), "centre", "root"), F.col("grp") == F.col("__grp"), "left")
    limit = chi_square_quantile(1 - beyond, P)
    out = _with_distance(judged, "distance").withColumn("kept", ~F.col("base_failed") & (F.coalesce(F.col("distance"), F.lit(0.0)) <= limit))
    return out.select(*wanted, *[c for c in [*BASE, "base_failed"] if c not in wanted], "distance", "kept")


def drop_low_quality(docs: DataFrame, **how: object) -> DataFrame:
    """The kept rows, with the columns of docs."""
    clash = [c for c in docs.columns if c in (*BASE, "base_failed", "distance", "kept", "grp", "enough", "x", "centre", "root")]
    plain = docs.withColumnsRenamed({c: f"__own_{c}" for c in clash})
    return score(plain, **how).where("kept").select(*plain.columns).withColumnsRenamed({f"__own_{c}": c for c in clash})
