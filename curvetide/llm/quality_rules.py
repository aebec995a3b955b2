"""Quality rules: word statistics, base rules, and robust multivariate outliers.

All in DataFrame functions.  A document's statistics come from its own row alone (array
functions), so texts are never shuffled.  Per language and source a minimum-covariance-
determinant estimate is found: of several deterministic starts (medians with median
deviations, all rows, the half of the rows that is nearest to the medians) each goes through
concentration steps (mean and covariance of the share ``NEAR`` of the rows that is nearest)
until its determinant falls no more, and the least determinant wins.  The covariance is made
consistent for normal data and regularised by least spreads ``FLOOR``, as most statistics
are 0 in most rows.  A document is rejected if the squared Mahalanobis distance of its
transformed statistics is beyond the chi-squared quantile of tail ``TAIL``.  Groups below
``MIN_GROUP`` rows are judged with the other small groups of their language, and those of
small languages all together.

The steps don't run over rows but over cells of a fixed grid (one ``FLOOR`` wide, over a
bounded range): counts, sums and products of the rows of a cell, which add up before the
shuffle.  Moments of whole cells are exact; a cell is in or out as one.  So a hot source is a
bounded number of cells, and costs no more than any other.

Edge cases: null text has no words and fails the base rules; null lang or source is a
group of its own; with fewer than ``MIN_GROUP`` rows in all, only the base rules hold;
repeated rows are judged each; null ids are kept as they are; other columns aren't read by
``judge`` and stay as they are in ``keep_good``.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import common as C

SYMBOLS = "#*$%&|<>"
BLANKS = " \t\n\x0b\f\r"
MIN_GROUP = 40
STEPS = 40  # at most; the determinant converges long before
NEAR = 0.75  # of a group's rows that an estimate rests on
TAIL = 1e-7  # of the chi-squared distribution that is rejected
#: Least standard deviations: a statistic that is nearly always 0 has no spread of its own.
FLOOR = (0.35, 0.03, 0.05, 0.1, 0.07)
LIMITS = ((0, 20), (-3, 10), (0, 3), (0, 1), (0, 1))  # of the grid; beyond lies its last cell
_X = [f"x{i}" for i in range(len(FLOOR))]


# ------------------------------------------------------------------ statistics
def _repeated_words(h: Column, n: Column) -> Column:
    """Words in windows of five that occur twice or more; h: hashes of the words."""
    at = lambda i, j: F.get(h, i + j)
    window = F.transform(F.sequence(F.lit(0), n - 5), lambda i: F.xxhash64(*[at(i, j) for j in range(5)]))
    return F.when(n >= 5, window)


STATS = ["n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words"]


def statistics(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` with the columns STATS (all long) in place of the text; columns
    of ``docs`` with these names are replaced."""
    C.need(docs, "doc_id", "text")
    text = F.coalesce("text", F.lit(""))
    words = F.filter(F.split(text, C.GAP), lambda w: w != "")
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(C.WORD))
    out = docs.withColumn("_h", F.transform(words, lambda w: F.xxhash64(w)))
    out = out.withColumn("_lines", F.transform(lines, lambda x: F.xxhash64(x)))
    out = out.withColumns({
        "n_words": F.size("_h").cast("long"),
        "word_chars": F.length(F.translate(text, BLANKS, "")).cast("long"),
        "n_symbols": (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long"),
        "n_lines": F.size("_lines").cast("long"),
        "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
    })
    out = out.drop("_lines", "text").withColumn("_g", _repeated_words(F.col("_h"), F.col("n_words").cast("int"))).drop("_h")
    many = F.size(F.array_distinct("_g")) < F.size("_g")
    out = out.withColumn("_s", F.when(many, F.sort_array(F.transform("_g", lambda x, i: F.struct(x.alias("h"), i.alias("i")))))).drop("_g")
    same = lambda x, i, j: F.get("_s", i + j)["h"] == x["h"]
    hit = F.transform("_s", lambda x, i: F.when(F.coalesce((i > 0) & same(x, i, -1), F.lit(False)) | F.coalesce(same(x, i, 1), F.lit(False)), x["i"]))
    out = out.withColumn("_p", F.sort_array(F.filter(hit, lambda p: p.isNotNull()))).drop("_s")
    cover = F.transform("_p", lambda p, i: F.least(F.lit(5), F.coalesce(F.get("_p", i + 1) - p, F.lit(5))))
    return out.withColumn("n_repeat_words", F.coalesce(F.aggregate(cover, F.lit(0), lambda a, b: a + b), F.lit(0)).cast("long")).drop("_p")


def transformed() -> list[Column]:
    """The statistic vector: length, shrunken word length, shares of symbols, repeated words
    and repeated lines."""
    n, chars = F.col("n_words"), F.col("word_chars")
    return [
        F.log(n + 1.0),
        F.log((chars + 200.0) / (n + 40.0)),
        F.sqrt(F.col("n_symbols") / F.greatest(chars, F.lit(1))),
        F.sqrt(F.col("n_repeat_words") / F.greatest(n, F.lit(1))),
        F.col("n_dup_lines") / (F.col("n_lines") + 2.0),
    ]


# ------------------------------------------------------------------ chi-squared
def chi2_tail(x: float, df: int) -> float:
    """The share beyond x of the chi-squared distribution."""
    value, k = (math.erfc(math.sqrt(x / 2)), 1) if df % 2 else (math.exp(-x / 2), 2)
    while k < df:
        value += (x / 2) ** (k / 2) * math.exp(-x / 2) / math.gamma(k / 2 + 1)
        k += 2
    return value


def chi2_quantile(tail: float, df: int) -> float:
    low, high = 0.0, 2000.0
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if chi2_tail(mid, df) > tail else (low, mid)
    return low


_P = len(FLOOR)
CUT = chi2_quantile(TAIL, _P)
#: Makes the covariance of the nearest rows consistent for normal data.
CONSISTENT = NEAR / (1 - chi2_tail(chi2_quantile(1 - NEAR, _P), _P + 2))


# ------------------------------------------------------------------ robust estimates
_PAIRS = [(i, j) for i in range(_P) for j in range(i, _P)]


def cells(rows: DataFrame) -> DataFrame:
    """(grp, n, s_i, q_ij) of the grid cells of rows (grp, x0..)."""
    at = []
    for i, ((low, high), width) in enumerate(zip(LIMITS, FLOOR)):
        at.append(F.floor((F.least(F.greatest(F.col(_X[i]), F.lit(float(low))), F.lit(float(high))) - low) / width).alias(f"cell{i}"))
    agg = [F.count(F.lit(1)).alias("n")] + [F.sum(x).alias(f"s{i}") for i, x in enumerate(_X)]
    agg += [F.sum(F.col(_X[i]) * F.col(_X[j])).alias(f"q{i}{j}") for i, j in _PAIRS]
    return rows.groupBy("grp", *at).agg(*agg).withColumns({f"a{i}": F.col(f"s{i}") / F.col("n") for i in range(_P)})


def _factored(par: DataFrame) -> DataFrame:
    """Adds the entries l_ij of the Cholesky factor of the regularised covariance c_ij, and
    the logarithm of its determinant."""
    for i in range(_P):
        for j in range(i + 1):
            rest = reduce(lambda a, k: a - F.col(f"l{i}{k}") * F.col(f"l{j}{k}"), range(j), F.col(f"c{j}{i}"))
            par = par.withColumn(f"l{i}{j}", F.sqrt(F.greatest(rest, F.lit(1e-12))) if i == j else rest / F.col(f"l{j}{j}"))
    return par.withColumn("det", 2 * reduce(lambda a, b: a + b, [F.ln(F.col(f"l{i}{i}")) for i in range(_P)])).drop(*[f"c{i}{j}" for i, j in _PAIRS])


def _squared_distance(rows: DataFrame, names: list[str]) -> DataFrame:
    """Adds d2, the squared Mahalanobis distance of the columns ``names``."""
    for i, name in enumerate(names):
        rest = reduce(lambda a, j: a - F.col(f"l{i}{j}") * F.col(f"z{j}"), range(i), F.col(name) - F.col(f"m{i}"))
        rows = rows.withColumn(f"z{i}", rest / F.col(f"l{i}{i}"))
    return rows.withColumn("d2", reduce(lambda a, b: a + b, [F.col(f"z{i}") * F.col(f"z{i}") for i in range(_P)])).drop(*[f"z{i}" for i in range(_P)])


def _moments(chosen: DataFrame, *by: str) -> DataFrame:
    """Means and consistent, regularised covariance of cells, factored."""
    total = chosen.groupBy(*by).agg(F.sum("n").alias("n"), *[F.sum(f"s{i}").alias(f"s{i}") for i in range(_P)], *[F.sum(f"q{i}{j}").alias(f"q{i}{j}") for i, j in _PAIRS])
    mean = {f"m{i}": F.col(f"s{i}") / F.col("n") for i in range(_P)}
    cov = {f"c{i}{j}": CONSISTENT * F.greatest(F.lit(0.0 if i == j else -1e300), F.col(f"q{i}{j}") / F.col("n") - F.col(f"m{i}") * F.col(f"m{j}")) + (FLOOR[i] ** 2 if i == j else 0.0) for i, j in _PAIRS}
    return _factored(total.withColumns(mean).withColumns(cov)).drop("n", *[f"s{i}" for i in range(_P)], *[f"q{i}{j}" for i, j in _PAIRS])


def _nearest(near: DataFrame, share: float, *by: str) -> DataFrame:
    """The cells nearest by d2 that hold the share of the rows of each group.  A group has a
    bounded number of cells."""
    order = W.partitionBy(*by).orderBy("d2", *[f"a{i}" for i in range(_P)])
    seen, every = F.sum("n").over(order.rowsBetween(W.unboundedPreceding, -1)), F.sum("n").over(W.partitionBy(*by))
    return near.withColumns({"_seen": F.coalesce(seen, F.lit(0)), "_all": every}).where(F.col("_seen") < F.ceil(share * F.col("_all"))).drop("_seen", "_all")


def _starts(grid: DataFrame) -> DataFrame:
    """(grp, start, m_i, l_ij, det) of the deterministic starts."""
    half = lambda x: F.expr(f"percentile({x}, 0.5, n)")
    mid = grid.groupBy("grp").agg(*[half(f"a{i}").alias(f"m{i}") for i in range(_P)])
    off = grid.join(mid, "grp").withColumns({f"o{i}": F.abs(F.col(f"a{i}") - F.col(f"m{i}")) for i in range(_P)})
    dev = off.groupBy("grp").agg(*[F.first(f"m{i}").alias(f"m{i}") for i in range(_P)], *[half(f"o{i}").alias(f"v{i}") for i in range(_P)])
    cov = {f"c{i}{j}": (F.pow(1.4826 * F.col(f"v{i}"), 2) + FLOOR[i] ** 2 if i == j else F.lit(0.0)) for i, j in _PAIRS}
    medians = C.materialize(_factored(dev.withColumns(cov)).drop(*[f"v{i}" for i in range(_P)]), "mcd-medians")
    inner = _nearest(_squared_distance(grid.join(medians, "grp"), [f"a{i}" for i in range(_P)]), 0.5, "grp")
    found = [medians, _moments(grid, "grp"), _moments(inner, "grp")]
    out = [f.withColumn("start", F.lit(k)) for k, f in enumerate(found)]
    return out[0].unionByName(out[1]).unionByName(out[2])


def fit(rows: DataFrame) -> DataFrame:
    """Per group (grp) of rows (grp, x0..): robust centre m_i, factor l_ij, scale, and
    whether the group is large enough to be judged."""
    grid = C.materialize(cells(rows), "mcd-cells")
    par = C.materialize(_starts(grid), "mcd-start")
    par = par.withColumn("was", F.lit(float("inf")))
    for step in range(STEPS):
        near = _squared_distance(grid.join(par.drop("det", "was"), "grp"), [f"a{i}" for i in range(_P)])
        new = _moments(_nearest(near, NEAR, "grp", "start"), "grp", "start")
        # a start's own determinant isn't that of a share of the rows: it doesn't count
        before = par.select("grp", "start", (F.lit(float("inf")) if step == 0 else F.col("det")).alias("was"))
        par = C.materialize(new.join(before, ["grp", "start"]), f"mcd-step{step}")
        if par.where("was - det > 1e-9").isEmpty():
            break
    best = W.partitionBy("grp").orderBy("det", "start")
    par = par.withColumn("_r", F.row_number().over(best)).where("_r = 1").drop("_r", "was", "start")
    last = _squared_distance(grid.join(par, "grp"), [f"a{i}" for i in range(_P)]).groupBy("grp").agg(F.expr("percentile(d2, 0.5, n)").alias("mid"), (F.sum("n") >= MIN_GROUP).alias("enough"))
    last = last.select("grp", "enough", F.greatest(F.col("mid") / chi2_quantile(0.5, _P), F.lit(1.0)).alias("scale"))
    return C.materialize(par.join(last, "grp"), "mcd-best")


_TAGS = ["_lang", "_source"]


def _prepared(docs: DataFrame) -> DataFrame:
    """Statistics, base rules, transformed vector, and group tags without null."""
    rows = statistics(docs)
    rows = rows.withColumn("base_failed", (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words")))
    tag = lambda c: F.coalesce(F.concat(F.lit("v"), F.col(c)), F.lit("n"))
    return rows.withColumns({"_lang": tag("lang"), "_source": tag("source")}).withColumns(dict(zip(_X, transformed())))


def estimates(rows: DataFrame) -> DataFrame:
    """The fitted group of each (language, source), from prepared rows."""
    good = rows.where("NOT base_failed")
    size = good.groupBy(*_TAGS).count().withColumn("own", F.col("count") >= MIN_GROUP)
    size = C.materialize(size, "rules-size")
    lang = size.where("NOT own").groupBy("_lang").agg((F.sum("count") >= MIN_GROUP).alias("by_lang"))
    grp = F.when(F.col("own"), F.concat_ws("\x01", F.lit("s"), *_TAGS)).when(F.col("by_lang"), F.concat_ws("\x01", F.lit("l"), "_lang")).otherwise(F.lit("all"))
    size = C.materialize(size.join(lang, "_lang", "left").select(*_TAGS, grp.alias("grp")), "rules-groups")
    grouped = C.materialize(good.join(size, _TAGS).select("grp", *_X), "rules-grouped")
    return C.materialize(size.join(fit(grouped), "grp"), "rules-fitted")


def _judged(rows: DataFrame, fitted: DataFrame) -> DataFrame:
    """Adds d2 and kept to prepared rows.  ``fitted`` has a row for each language and
    source; Spark broadcasts it where its size allows, else the join is by these keys."""
    out = _squared_distance(rows.join(fitted.drop("det"), _TAGS, "left"), _X).withColumn("d2", F.col("d2") / F.col("scale"))
    fine = F.coalesce((F.col("d2") <= CUT) | ~F.col("enough"), F.lit(True))
    return out.withColumn("kept", ~F.col("base_failed") & fine)


def judge(docs: DataFrame) -> DataFrame:
    """(doc_id, lang, source, STATS, base_failed, d2, kept) of each row (doc_id, text, lang,
    source)."""
    C.need(docs, "doc_id", "text", "lang", "source")
    with C.Scratch(docs.sparkSession) as tables:
        rows = C.materialize(_prepared(docs.select("doc_id", "text", "lang", "source")), "rules-stats")
        return tables.keep(_judged(rows, estimates(rows)).select("doc_id", "lang", "source", *STATS, "base_failed", "d2", "kept"), "rules-judged")


def keep_good(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that the rules keep.  Rows and statistics are written once, so
    that no text is shuffled and no statistic computed twice."""
    C.need(docs, "doc_id", "text", "lang", "source")
    inner = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_doc"), "doc_id", "text", "lang", "source")
    rows = C.materialize(_prepared(inner), "rules-rows")
    with C.Scratch(docs.sparkSession) as tables:
        fitted = tables.keep(estimates(rows.drop("_doc")), "rules-estimates")
    return _judged(rows, fitted).where("kept").select("_doc.*")


def op8_quality_rules(spark, sf_dir: str) -> DataFrame:
    out = judge(C.read_table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "d2")
