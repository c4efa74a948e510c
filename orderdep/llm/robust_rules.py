"""Quality rules: base counts of every text, then robust multivariate outliers for each language and source.

Only DataFrame functions run here.  Documents that pass the base rules become vectors of transformed statistics.  The
minimum covariance determinant of a group is looked for from three starts that share the group's medians and median
deviations and differ in the correlations: none, those of tanh scores, those of spatial signs.  A concentration step takes
the ``SUBSET`` share of documents closest to an estimate and gives their mean and covariance.  After ``FIRST_STEPS`` steps
the start with the least determinant goes on alone until the determinant falls no more (at most ``MOST_STEPS`` steps).  A
document whose squared Mahalanobis distance is over the cutoff is rejected.

Scatter may be singular (most groups have no symbols and no repeated lines in their closest documents): each
statistic's variance, given those before it, is at least one unit squared, the unit being the resolution to which documents are told
apart at all.  Determinants are those of the scatter with this floor.

Every group has an estimate of its own, at any size, which is then mixed with that of its language: with weight
n / (n + ``PRIOR_ROWS``) for a group of n documents.

Distances and medians are selected by fixed bins and a step is one aggregate: counts, sums and products by group, start and
bin of the distance, of which the bins up to the share are added up.  So a group costs a few hundred rows behind the
partial aggregate, however many documents it has, and any partitioning gives the same result (but for the last digits of sums).

Nulls: a null text has no words and fails the base rules; null lang or source are values of their own.  Repeated rows
count as often as they stand there.  Empty table: empty result.  Own columns have a prefix, so other columns may have any name.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, own, stored

MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
SUBSET = 0.75
PRIOR_ROWS = 50
FIRST_STEPS, MOST_STEPS = 2, 20
#: A determinant that falls by less than this share has converged.
LEAST_FALL = 1e-6
#: Groups (some 200 bytes each) whose estimates may be broadcast.
MOST_SENT = 50_000
#: Share of normal documents whose squared distance lies under the cutoff.
TAIL = 0.9999
#: One unit of each statistic after its transformation: the resolution to which documents are told apart.
UNITS = {"log_words": 0.25, "word_length": 0.25, "symbols": 0.1, "dup_lines": 0.1, "repeats": 0.1}
DIMS = len(UNITS)
_Z, _M, _L, _Y = own("z"), own("m"), own("l"), own("y")  # statistic, centre, factor and residual columns
_BIN = 32  # bins a unit for medians
_D_BIN = 64  # bins of the logarithm of squared distances
_STARTS = {"none": "none", "tanh": "t", "signs": "u"}  # name and column prefix of their sums


def chi2_cdf(x: float, k: int) -> float:
    """Chi-square distribution by the series of the lower incomplete gamma function."""
    a, term, total = k / 2, 1 / (k / 2), 1 / (k / 2)
    for n in range(1, 500):
        term *= (x / 2) / (a + n)
        total += term
    return total * math.exp(-x / 2 + a * math.log(x / 2) - math.lgamma(a))


def chi2_quantile(p: float, k: int) -> float:
    low, high = 1e-9, 1000.0
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if chi2_cdf(mid, k) < p else (low, mid)
    return low


#: The covariance of the closest share understates that of normal data by this factor.
CONSISTENCY = SUBSET / chi2_cdf(chi2_quantile(SUBSET, DIMS), DIMS + 2)
#: Squared distance beyond which a document is rejected.
CUTOFF = chi2_quantile(TAIL, DIMS)
_MEDIAN_FACTOR = 1.4826  # median absolute deviation to standard deviation of normal data


def base_counts(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with own() columns n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (long) and base_failed."""
    columns = docs.columns
    t = F.coalesce(F.col(text).cast("string"), F.lit(""))
    space = "[ \\t-\\r]+"
    d = docs.withColumns({
        own("words"): F.filter(F.split(t, space), lambda w: w != ""),
        own("word_chars"): F.length(F.regexp_replace(t, space, "")).cast("long"),
        own("n_symbols"): F.length(F.regexp_replace(t, "[^#*$%&|<>]+", "")).cast("long"),
        own("lines"): F.filter(F.split(t, "\n"), lambda x: x.rlike("[^ \\t-\\r]")),
    })
    words = F.col(own("words"))
    windows = F.transform(F.sequence(F.lit(0), F.size(words) - 3), lambda i: F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)))
    d = d.withColumns({own("windows"): F.when(F.size(words) >= 3, windows).otherwise(F.array().cast("array<bigint>"))})
    w = F.col(own("windows"))
    # only texts with some window twice are sorted
    pairs = F.array_sort(F.transform(w, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
    d = d.withColumn(own("pairs"), F.when(F.size(F.array_distinct(w)) < F.size(w), pairs))
    e = F.col(own("pairs"))
    twice = F.filter(e, lambda x, k: ((k > 0) & (F.get(e, k - 1)["h"] == x["h"])) | F.coalesce(F.get(e, k + 1)["h"] == x["h"], F.lit(False)))
    d = d.withColumn(own("at"), F.array_sort(F.transform(twice, lambda x: x["i"])))
    at = F.col(own("at"))
    covered = F.aggregate(F.transform(at, lambda p, k: F.least(F.coalesce(F.get(at, k + 1) - p, F.lit(3)), F.lit(3))), F.lit(0).cast("long"), lambda s, n: s + n)
    d = d.select(
        *columns,
        F.size(words).cast("long").alias(own("n_words")), own("word_chars"), own("n_symbols"),
        (F.size(own("lines")) - F.size(F.array_distinct(own("lines")))).cast("long").alias(own("n_dup_lines")),
        F.size(own("lines")).cast("long").alias(own("n_lines")),
        F.coalesce(covered, F.lit(0)).cast("long").alias(own("n_repeat_words")),
    )
    n, r = F.col(own("n_words")), F.col(own("n_repeat_words"))
    return d.withColumn(own("base_failed"), (n < MIN_WORDS) | (100 * r > MAX_REPEAT_PERCENT * n))


def vectors() -> dict[str, Column]:
    """The transformed statistics, in units."""
    n = F.col(own("n_words")).cast("double")
    raw = {
        "log_words": F.log(n),
        "word_length": F.col(own("word_chars")) / n,
        "symbols": F.sqrt(F.col(own("n_symbols")) / n),
        "dup_lines": F.col(own("n_dup_lines")) / F.greatest(F.col(own("n_lines")).cast("double"), F.lit(1.0)),
        "repeats": F.col(own("n_repeat_words")) / n,
    }
    return {f"{_Z}{k}": raw[name] / unit for k, (name, unit) in enumerate(UNITS.items())}


Z = [f"{_Z}{k}" for k in range(DIMS)]
CELLS = [(i, j) for i in range(DIMS) for j in range(i + 1)]


def _joined(points: DataFrame, estimates: DataFrame, few: bool) -> DataFrame:
    """Estimates are some rows a group; they are sent to all tasks if their groups have been counted as few."""
    return points.join(F.broadcast(estimates) if few else estimates, "g")


def _weighted_middle(pairs: Column) -> Column:
    """The value v at which half of the count c of array<struct<v, c>> in order is reached."""
    zero = F.struct(F.lit(0).cast("long").alias("run"), F.lit(None).cast("double").alias("v"))
    total = F.aggregate(pairs, F.lit(0).cast("long"), lambda n, x: n + x["c"])

    def more(s: Column, x: Column) -> Column:
        return F.struct((s["run"] + x["c"]).alias("run"), F.when(2 * s["run"] < total, x["v"]).otherwise(s["v"]).alias("v"))

    return F.aggregate(pairs, zero, more)["v"]


def middles(points: DataFrame) -> DataFrame:
    """(g, m0.., s0..): medians, and median absolute deviations of one unit at least, from one table of bin counts."""
    long = points.select("g", F.posexplode(F.array(*Z)).alias("dim", "z")).withColumn("bin", F.floor(F.col("z") * _BIN).cast("long"))
    counts = long.groupBy("g", "dim", "bin").agg(F.count("*").alias("c"))
    each = counts.groupBy("g", "dim").agg(F.array_sort(F.collect_list(F.struct(((F.col("bin") + 0.5) / _BIN).alias("v"), "c"))).alias("bins"))
    each = each.withColumn("m", _weighted_middle(F.col("bins")))
    off = F.array_sort(F.transform("bins", lambda x: F.struct(F.abs(x["v"] - F.col("m")).alias("v"), x["c"].alias("c"))))
    each = each.withColumn("s", F.greatest(_weighted_middle(off) * _MEDIAN_FACTOR, F.lit(1.0)))
    return each.groupBy("g").agg(*[F.max(F.when(F.col("dim") == k, F.col(c))).alias(f"{name}{k}") for c, name in (("m", _M), ("s", "s")) for k in range(DIMS)])


def _names(kind: str) -> list[str]:
    """Columns of centres, of scatters (c) or of their factors."""
    return [f"{kind}{k}" for k in range(DIMS)] if kind in (_M, _Z, "s", "a", "u", "t") else [f"{kind}{i}{j}" for i, j in CELLS]


def starts(points: DataFrame, centres: DataFrame, few: bool) -> DataFrame:
    """(g, start, m0.., c00..): the centre of a group with three scatters."""
    length = " + ".join(f"pow({u}, 2)" for u in _names("u"))
    scaled = _joined(points, centres, few).selectExpr("g", *[f"({_Z}{k} - {_M}{k}) / s{k} AS u{k}" for k in range(DIMS)])
    scores = scaled.selectExpr("g", *[f"tanh({u}) AS t{k}" for k, u in enumerate(_names("u"))], f"sqrt({length}) AS r", *_names("u"))
    scores = scores.selectExpr("g", *_names("t"), *[f"if(r > 0, {u} / r, 0D) AS {u}" for u in _names("u")])
    sums = scores.groupBy("g").agg(*[F.expr(x) for i, j in CELLS for x in (f"covar_pop(t{i}, t{j}) AS t{i}{j}", f"avg(u{i} * u{j}) AS u{i}{j}")])

    def scatter(kind: str) -> str:
        def cell(i: int, j: int) -> str:
            part = "1D" if i == j else "0D" if kind == "none" else f"coalesce(try_divide({kind}{i}{j}, sqrt({kind}{i}{i} * {kind}{j}{j})), 0D)"
            return f"'c{i}{j}', {part} * s{i} * s{j}"

        return ", ".join(cell(i, j) for i, j in CELLS)

    kinds = ", ".join(f"named_struct('start', '{name}', {scatter(kind)})" for name, kind in _STARTS.items())
    return centres.join(sums, "g").selectExpr("g", *_names(_M), f"inline(array({kinds}))")


def distance() -> list[str]:
    """Squared Mahalanobis distance by forward substitution in the triangular factor: SQL, each using those before it."""
    steps = []
    for i in range(DIMS):
        rest = "".join(f" - {_L}{i}{j} * {_Y}{j}" for j in range(i))
        steps.append(f"({_Z}{i} - {_M}{i}{rest}) / {_L}{i}{i} AS {_Y}{i}")
    return steps


D2 = " + ".join(f"{_Y}{k} * {_Y}{k}" for k in range(DIMS))


def factored(scatter: DataFrame) -> DataFrame:
    """Adds l00.., the triangular factor of c00.. with a floor of one unit, and logdet."""
    steps = []
    for j in range(DIMS):
        square = "".join(f" - {_L}{j}{k} * {_L}{j}{k}" for k in range(j))
        steps.append(f"sqrt(greatest(c{j}{j}{square}, 1D)) AS {_L}{j}{j}")
        for i in range(j + 1, DIMS):
            rest = "".join(f" - {_L}{i}{k} * {_L}{j}{k}" for k in range(j))
            steps.append(f"(c{i}{j}{rest}) / {_L}{j}{j} AS {_L}{i}{j}")
    logdet = " + ".join(f"2 * ln({_L}{j}{j})" for j in range(DIMS))
    return scatter.selectExpr("*", *steps, f"{logdet} AS logdet")


def concentrate(points: DataFrame, estimates: DataFrame, few: bool) -> DataFrame:
    """One step: mean and covariance of the share of each group that is closest under each of its estimates."""
    measured = _joined(points, estimates.select("g", "start", *_names(_M), *_names(_L)), few).selectExpr("g", "start", *Z, *distance())
    binned = measured.selectExpr("g", "start", *Z, f"CAST(floor(ln(1 + {D2}) * {_D_BIN}) AS BIGINT) AS bin")
    parts = {"n": "1L", **{f"a{k}": z for k, z in enumerate(Z)}, **{f"p{i}{j}": f"{Z[i]} * {Z[j]}" for i, j in CELLS}}
    sums = binned.groupBy("g", "start", "bin").agg(*[F.expr(f"sum({what}) AS {name}") for name, what in parts.items()])
    near = sums.selectExpr("*", "sum(n) OVER (PARTITION BY g, start ORDER BY bin) - n AS before", f"ceil(sum(n) OVER (PARTITION BY g, start) * {SUBSET}D) AS need").where("before < need")
    total = near.groupBy("g", "start").agg(*[F.expr(f"sum({name}) AS {name}") for name in parts])
    cells = [f"(p{i}{j} / n - {_M}{i} * {_M}{j}) * {CONSISTENCY!r}D AS c{i}{j}" for i, j in CELLS]
    return total.selectExpr("g", "start", *[f"a{k} / n AS {_M}{k}" for k in range(DIMS)], *cells)


def _least(estimates: DataFrame, keys: list[str]) -> DataFrame:
    """The row with the least determinant for each key, the first start by name of equals."""
    rest = [c for c in estimates.columns if c not in keys]
    best = estimates.groupBy(*keys).agg(F.min(F.struct("logdet", "start", *[c for c in rest if c not in ("logdet", "start")])).alias("e"))
    return best.select(*keys, *[f"e.{c}" for c in rest])


def estimate(points: DataFrame, few: bool, most_steps: int = MOST_STEPS) -> DataFrame:
    """points (g, z0..) -> (g, start, m0.., c00.., l00.., logdet) with the least determinant that is found."""
    centres = stored(middles(points), "mcd-middles")
    now = stored(factored(starts(points, centres, few)), "mcd-starts")
    for step in range(most_steps):
        after = factored(concentrate(points, now, few))
        if step < FIRST_STEPS:
            after = _least(after, ["g"]) if step == FIRST_STEPS - 1 else after
            falls = None
        else:  # a step that does not fall is not taken
            was = now.select("g", F.col("logdet").alias("was"))
            after = after.join(was, "g").selectExpr("*", f"logdet < was + {math.log1p(-LEAST_FALL)!r}D AS falls").drop("was")
            after = _least(after.unionByName(now.selectExpr("*", "false AS falls")), ["g"])
            falls = "falls"
        after = stored(after, "mcd-estimate")
        discard(now)
        now = after.drop("falls") if falls else after
        if falls and after.where("falls").isEmpty():
            break
    return now


def judged(docs: DataFrame, *, text: str = "text", lang: str = "lang", source: str = "source", cutoff: float = CUTOFF, with_text: bool = True) -> DataFrame:
    """docs (its own columns, text only if asked for) with own() counts, own('base_failed'), own('distance') double and
    own('kept').  The counts are taken once and written to the shared folder.
    """

    def named(*parts: Column) -> Column:
        return F.concat_ws("\u0001", *[F.coalesce(p.cast("string"), F.lit("\u0002")) for p in parts])

    columns = [c for c in docs.columns if with_text or c != text]
    counted = base_counts(docs, text).withColumns({own("lang"): named(F.lit("l"), F.col(lang)), own("group"): named(F.lit("g"), F.col(lang), F.col(source))})
    d = stored(counted if with_text else counted.drop(text), "quality-counts")
    both = F.explode(F.array(own("group"), own("lang"))).alias("g")
    points = stored(d.where(~F.col(own("base_failed"))).select(both, *[c.alias(k) for k, c in vectors().items()]), "mcd-points")
    sizes = stored(points.groupBy("g").agg(F.count("*").alias("n")), "mcd-sizes")
    few = sizes.limit(MOST_SENT + 1).count() <= MOST_SENT
    found = estimate(points, few).join(sizes, "g")
    use = stored(mixed(d.select(own("group"), own("lang")).distinct(), found), "mcd-use")
    use = F.broadcast(use) if few else use
    out = d.join(use, own("group"), "left").withColumns({k: F.when(~F.col(own("base_failed")), c) for k, c in vectors().items()})
    out = out.selectExpr("*", *distance()).withColumn(own("distance"), F.expr(D2))
    kept = ~F.col(own("base_failed")) & F.coalesce(F.col(own("distance")) <= cutoff, F.lit(True))
    return out.select(*columns, *[own(n) for n in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "distance")], kept.alias(own("kept")))


def mixed(groups: DataFrame, found: DataFrame) -> DataFrame:
    """(own group, own lang), estimates by g with n -> (own group, m0.., l00..): each group's mixed with its language's."""
    names = _names(_M) + _names("c")
    mine = found.selectExpr(f"g AS {own('group')}", f"n / (n + {PRIOR_ROWS}) AS w", *[f"{c} AS g_{c}" for c in names])
    wide = found.selectExpr(f"g AS {own('lang')}", *[f"{c} AS l_{c}" for c in names])
    centres = [f"w * g_{m} + (1 - w) * l_{m} AS {m}" for m in _names(_M)]
    apart = [f"(g_{m} - l_{m})" for m in _names(_M)]
    cells = [f"w * g_c{i}{j} + (1 - w) * l_c{i}{j} + w * (1 - w) * {apart[i]} * {apart[j]} AS c{i}{j}" for i, j in CELLS]
    both = groups.join(mine, own("group")).join(wide, own("lang")).selectExpr(own("group"), *centres, *cells)
    return factored(both).select(own("group"), *_names(_M), *_names(_L))


def keep(docs: DataFrame, **parameters) -> DataFrame:
    """The documents that are kept, with their own columns."""
    return judged(docs, **parameters).where(own("kept")).select(*docs.columns)
