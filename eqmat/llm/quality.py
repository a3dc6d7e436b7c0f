"""Quality rules with robust multivariate outliers, in DataFrame functions only.

Each text gives word and line counts; fixed rules reject the plainly unfit. The others become vectors of four
transformed statistics, held as whole numbers so that sums are exact in any order. Per language and source (groups
with few rows are pooled by language, then all together) the minimum covariance determinant estimate is sought from three
deterministic starts: median absolute deviations, spatial signs and squashed scores. From each, concentration steps
keep the ``SHARE`` of rows with the smallest distances and take their mean and covariance, until the determinant falls
no more; of the starts of a group the least determinant wins. Distances count by buckets of 1/256 octave, and the
bucket in which the share is reached counts by the part that is still wanted, so ties weigh alike. The covariance
carries fixed floors on its diagonal, also in the determinant. One scan per step sums moments by group, start and
bucket for all starts; only these sums are put in order, so no group is ever gathered. A vector whose squared
Mahalanobis distance passes a chi-square quantile is rejected.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from eqmat.storage import keyed, saved

WORD = r"[^\\x20\\x09-\\x0D]+"
DIMS = ("x1", "x2", "x3", "x4")
UNIT = 1000  # the whole-number step of a statistic
FLOORS = (120.0, 60.0, 60.0, 150.0)  # spread that is always allowed for, in units, per statistic
SHARE, MOST_STEPS, LEAST_GROUP = 0.75, 100, 40
SALTS = 32  # parts of a group in joins
STARTS = ("spread", "signs", "squashed")
FALL = 1e-3  # a determinant falls if its logarithm falls by more
CONSISTENCY = 1.486  # 0.75 / P(chi2 with 6 degrees <= 0.75 quantile of chi2 with 4 degrees)
CUTOFF = 18.467  # 0.999 quantile of chi2 with 4 degrees
BUCKETS_PER_OCTAVE = 256


def text_statistics(docs: DataFrame, keep_bits: int = 63) -> DataFrame:
    """doc_id, lang, source and the counts of each whole text; a null text has no words and no lines. ``keep_bits``: how
    many bits of a window's hash are looked at, which changes the work but not the counts."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("t"))
    rows = rows.select(
        "doc_id",
        "lang",
        "source",
        F.expr(f"regexp_extract_all(t, '{WORD}', 0)").alias("w"),
        F.expr("regexp_count(t, '[#*$%&|<>]')").cast("long").alias("n_symbols"),
        F.expr(r"regexp_count(t, '\\p{Lu}')").cast("long").alias("n_upper"),
        F.expr(f"filter(split(t, '\\n', -1), x -> x rlike '{WORD}')").alias("lines"),
    )
    # A window of three words is a hash whose low bits give way to its place; equal windows meet when these are sorted.
    rows = rows.select(
        "doc_id", "lang", "source", "n_symbols", "n_upper", "w",
        F.expr("cast(size(w) as bigint)").alias("n_words"),
        F.expr("cast(length(array_join(w, '')) as bigint)").alias("word_chars"),
        F.expr("cast(size(lines) - size(array_distinct(lines)) as bigint)").alias("n_dup_lines"),
        F.lit((1 << keep_bits) - 1).alias("kept_bits"),
        F.expr("shiftleft(1L, length(bin(size(w)))) - 1").alias("low"),
    )
    rows = rows.withColumn("high", F.expr("kept_bits & ~low"))
    rows = rows.withColumn("s", F.expr("case when size(w) >= 3 then sort_array(transform(sequence(0, size(w) - 3), i -> (xxhash64(w[i], w[i + 1], w[i + 2]) & high) | cast(i as bigint))) else cast(array() as array<bigint>) end"))
    near = "(x & high) = (s[%s] & high)"
    rows = rows.withColumn("twice", F.expr(f"filter(s, (x, k) -> (k > 0 and {near % 'greatest(k - 1, 0)'}) or (k < size(s) - 1 and {near % 'least(k + 1, size(s) - 1)'}))"))
    # Neighbours with one hash are held against each other word by word; if any differ, the text's windows are sorted by
    # their words instead. So the count is exact whatever the hash does.
    place = "cast({} & low as int)"
    differ = " or ".join(f"w[{place.format('x')} + {d}] <> w[{place.format('s[k - 1]')} + {d}]" for d in range(3))
    rows = rows.withColumn("clash", F.expr(f"exists(filter(s, (x, k) -> k > 0 and {near % 'greatest(k - 1, 0)'} and ({differ})), x -> true)"))
    windows = "sort_array(transform(sequence(0, size(w) - 3), i -> struct(w[i] as a, w[i + 1] as b, w[i + 2] as c, i as i)))"
    equal = lambda k: "(" + " and ".join(f"x.{c} = y[{k}].{c}" for c in "abc") + ")"
    slow = f"transform(array({windows}), y -> transform(filter(y, (x, k) -> (k > 0 and {equal('greatest(k - 1, 0)')}) or (k < size(y) - 1 and {equal('least(k + 1, size(y) - 1)')})), x -> x.i))[0]"
    places = F.expr(f"case when clash then {slow} else transform(twice, x -> {place.format('x')}) end")
    rows = rows.withColumn("places", places).drop("s", "twice", "w")
    covered = F.expr("cast(size(array_distinct(flatten(transform(places, x -> array(x, x + 1, x + 2))))) as bigint)")
    return rows.select("doc_id", "lang", "source", "n_words", "word_chars", "n_symbols", "n_upper", "n_dup_lines", covered.alias("n_repeat_words"))


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def vectors(stats: DataFrame) -> DataFrame:
    """Add x1..x4 in whole units: log of the mean word length, and roots of the shares of symbols, of upper-case letters
    and of repeated words."""
    n, c = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.col("word_chars"), F.lit(1))
    value = (F.log(c / n), F.sqrt(F.col("n_symbols") / c), F.sqrt(F.col("n_upper") / c), F.sqrt(F.col("n_repeat_words") / n))
    return stats.withColumns({d: F.round(UNIT * v).cast("long") for d, v in zip(DIMS, value, strict=True)})


def grouped(rows: DataFrame) -> DataFrame:
    """Add g1, g2: language and source where they have LEAST_GROUP rows, else language with all its small sources, else
    what is left together. Null values are values like others."""
    own = rows.where(~F.col("base_failed")).groupBy("lang", "source").agg(F.count("*").alias("n"))
    own = own.withColumn("big", F.col("n") >= LEAST_GROUP)
    pooled = own.where(~F.col("big")).groupBy(F.col("lang").alias("pl")).agg(F.sum("n").alias("pn"))
    key = F.when(F.col("big"), F.concat_ws("\x1f", F.lit("s"), F.coalesce("lang", F.lit("\x00")), F.coalesce("source", F.lit("\x00")))).when(F.col("pn") >= LEAST_GROUP, F.concat_ws("\x1f", F.lit("l"), F.coalesce("lang", F.lit("\x00")))).otherwise(F.lit("a"))
    named = own.join(pooled, F.col("lang").eqNullSafe(F.col("pl")), "left").select(F.col("lang").alias("gl"), F.col("source").alias("gs"), key.alias("grp"))
    return rows.join(named, F.col("lang").eqNullSafe(F.col("gl")) & F.col("source").eqNullSafe(F.col("gs")), "left").drop("gl", "gs")


_PAIRS = [(i, j) for i in range(4) for j in range(i + 1)]
_MEANS, _CELLS = [f"m{i + 1}" for i in range(4)], [f"c{i + 1}{j + 1}" for i, j in _PAIRS]


def _salted(estimate: DataFrame) -> DataFrame:
    """A row of each group for each salt: joined by group and salt, a large group is spread over many tasks, also where
    sums by group follow the join."""
    return estimate.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))


def _salt() -> Column:
    return F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int")


def _median(values: DataFrame, column: str) -> DataFrame:
    """Median of column for grp, dim over values counted by n: few rows, one for each value."""
    w = Window.partitionBy("grp", "dim")
    run = w.orderBy(column).rowsBetween(Window.unboundedPreceding, 0)
    return values.select("*", F.sum("n").over(run).alias("upto"), F.sum("n").over(w).alias("all")).where(2 * F.col("upto") >= F.col("all")).groupBy("grp", "dim").agg(F.min(column).alias("median"))


def _starts(rows: DataFrame) -> DataFrame:
    """grp, start and a first factor for each: around the medians, the diagonal of median absolute deviations, and the
    covariances of scores after they were brought to length one (signs) or squashed by tanh. Scores enter the sums as
    whole numbers."""
    long = rows.select("grp", F.explode(F.array(*[F.struct(F.lit(i + 1).alias("dim"), F.col(d).alias("x")) for i, d in enumerate(DIMS)])).alias("e")).select("grp", "e.dim", "e.x").groupBy("grp", "dim", "x").agg(F.count("*").alias("n"))
    long = saved(long, "values")
    mid = _median(long, "x")
    apart = saved(long.join(mid, ["grp", "dim"]).groupBy("grp", "dim", F.abs(F.col("x") - F.col("median")).alias("d")).agg(F.sum("n").alias("n")), "apart")
    both = mid.join(_median(apart, "d").withColumnRenamed("median", "mad"), ["grp", "dim"])
    pick = [F.expr(f"cast(max(case when dim = {i + 1} then {c} end) as double) as {n}{i + 1}") for c, n in (("median", "m"), ("mad", "s")) for i in range(4)]
    wide = saved(both.groupBy("grp").agg(*pick), "spread")
    spread = [f"sqrt(pow(1.4826 * s{i + 1}, 2) + {FLOORS[i] ** 2}D)" for i in range(4)]
    scored = rows.join(_salted(wide), ["grp", "salt"]).selectExpr("grp", *[f"({d} - m{i + 1}) / {spread[i]} as z{i + 1}" for i, d in enumerate(DIMS)], "greatest(sqrt(z1 * z1 + z2 * z2 + z3 * z3 + z4 * z4), 1e-6D) as z")
    whole = [f"cast(round({UNIT} * {v}) as bigint) as {name}{i}" for i in range(1, 5) for name, v in (("a", f"z{i} / z"), ("b", f"tanh(z{i})"))]
    sums = [F.expr(f"sum({name}{i + 1} * {name}{j + 1}) as {name}{i + 1}{j + 1}") for name in "ab" for i, j in _PAIRS]
    base = saved(scored.selectExpr("grp", *whole).groupBy("grp").agg(F.count("*").alias("n"), *sums), "scores").join(wide, "grp")

    def cell(start: str, i: int, j: int) -> str:
        if start == "spread":
            return f"pow(1.4826 * s{i + 1}, 2)" if i == j else "0D"
        return f"{'a' if start == 'signs' else 'b'}{i + 1}{j + 1} / (n * {UNIT * UNIT}D) * {spread[i]} * {spread[j]}"

    firsts = [base.selectExpr("grp", f"'{start}' as start", *_MEANS, *[f"{cell(start, i, j)} as c{i + 1}{j + 1}" for i, j in _PAIRS]) for start in STARTS]
    return _factor(reduce(DataFrame.unionByName, firsts))


def _factor(estimate: DataFrame) -> DataFrame:
    """Cholesky factor l11..l44 of the covariance c11..c44 with the floors added to its diagonal, and logdet, the
    logarithm of its determinant."""
    cells = []
    for i, j in _PAIRS:
        rest = f"c{i + 1}{j + 1}" + (f" + {FLOORS[i] ** 2}D" if i == j else "") + "".join(f" - l{i + 1}{k + 1} * l{j + 1}{k + 1}" for k in range(j))
        cells.append(f"sqrt(greatest({rest}, 1D)) as l{i + 1}{j + 1}" if i == j else f"({rest}) / l{j + 1}{j + 1} as l{i + 1}{j + 1}")
    return estimate.selectExpr("grp", "start", *_MEANS, *_CELLS, *cells, "2 * (ln(l11) + ln(l22) + ln(l33) + ln(l44)) as logdet")


def _distance(rows: DataFrame, estimate: DataFrame, *also: str) -> DataFrame:
    """Add d2, the squared Mahalanobis distance, by forward substitution, for each estimate of the group."""
    steps = [f"({DIMS[i]} - m{i + 1}" + "".join(f" - l{i + 1}{k + 1} * y{k + 1}" for k in range(i)) + f") / l{i + 1}{i + 1} as y{i + 1}" for i in range(4)]
    out = rows.join(_salted(estimate), ["grp", "salt"], "left").selectExpr(*rows.columns, *also, *steps, "y1 * y1 + y2 * y2 + y3 * y3 + y4 * y4 as d2")
    return out.drop("y1", "y2", "y3", "y4")


def _concentrate(rows: DataFrame, estimate: DataFrame) -> DataFrame:
    """Mean and covariance of the SHARE of a group's rows with the smallest distances, for each start."""
    sums = [f"sum({d}) as t{i + 1}" for i, d in enumerate(DIMS)] + [f"sum({DIMS[i]} * {DIMS[j]}) as q{i + 1}{j + 1}" for i, j in _PAIRS]
    moments = [f"t{i + 1}" for i in range(4)] + [f"q{i + 1}{j + 1}" for i, j in _PAIRS]
    # Written before they are put in order, so that rows are dealt by bucket too and a large group is not gathered.
    bucket = F.expr(f"floor({BUCKETS_PER_OCTAVE} * log2(1 + d2)) as bucket")
    by = saved(_distance(rows, estimate, "start").groupBy("grp", "start", bucket).agg(F.count("*").alias("n"), *map(F.expr, sums)), "sums")
    before = "coalesce(sum(n) over (partition by grp, start order by bucket rows between unbounded preceding and 1 preceding), 0) as before"
    near = by.selectExpr("*", before, f"ceil({SHARE} * sum(n) over (partition by grp, start)) as wanted").where("before < wanted")
    near = near.selectExpr("grp", "start", "least(1D, (wanted - before) / n) as part", "n", *moments)
    total = near.groupBy("grp", "start").agg(*[F.expr(f"sum(part * {c}) as {c}") for c in ("n", *moments)])
    return _factor(total.selectExpr("grp", "start", *[f"t{i + 1} / n as m{i + 1}" for i in range(4)], *[f"q{i + 1}{j + 1} / n - t{i + 1} / n * t{j + 1} / n as c{i + 1}{j + 1}" for i, j in _PAIRS]))


def least_determinants(rows: DataFrame) -> DataFrame:
    """rows(grp, x1..x4) -> for each grp the estimate (m, c, l, logdet) and the start of the least determinant that any
    start comes to. Concentration goes on for those starts whose determinant still falls, by more than FALL in its
    logarithm and MOST_STEPS times at most. Equal determinants: the first start by name."""
    rows = rows if "salt" in rows.columns else saved(rows.withColumn("salt", _salt()), "vectors")
    open_ = saved(_concentrate(rows, saved(_starts(rows), "start")), "estimate")
    seen = [open_]
    for _ in range(MOST_STEPS):
        was = open_.select("grp", "start", F.col("logdet").alias("was"))
        open_ = saved(_concentrate(rows, open_).join(was, ["grp", "start"]).where(F.col("logdet") < F.col("was") - FALL).drop("was"), "estimate")
        if open_.isEmpty():
            break
        seen.append(open_)
    every = reduce(DataFrame.unionByName, seen)
    fields = [c for c in every.columns if c != "grp"]
    return saved(every.groupBy("grp").agg(F.min_by(F.struct(*fields), F.struct("logdet", "start")).alias("e")).select("grp", "e.*"), "estimate")


def assess(docs: DataFrame) -> DataFrame:
    """docs(doc_id, text, lang, source) -> doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
    base_failed, d2, kept.

    An empty or null text fails the base rules; where a document fails them d2 is null. Null languages and sources
    form groups of their own, repeated rows count as often as they come, and an empty table gives no rows.
    """
    stats = saved(vectors(text_statistics(docs)).withColumns({"base_failed": base_failed(), "salt": _salt()}), "statistics")
    rows = grouped(stats)
    ok = saved(rows.where(~F.col("base_failed")).select("grp", "salt", *DIMS), "vectors")
    least = least_determinants(ok)
    estimate = saved(_factor(least.selectExpr("grp", "start", *_MEANS, *[f"{CONSISTENCY}D * {c} as {c}" for c in _CELLS])), "estimate")
    judged = _distance(rows, estimate)
    d2 = F.when(~F.col("base_failed"), F.col("d2"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", d2.alias("d2"), F.coalesce(~F.col("base_failed") & (F.col("d2") <= CUTOFF), F.lit(False)).alias("kept"))


def keep_sound(docs: DataFrame) -> DataFrame:
    """The rows of docs that assess() keeps, with their columns. Each row has a verdict of its own, whatever its id."""
    rows, key = keyed(docs, "keyed")
    kept = assess(rows.select(F.col(key).alias("doc_id"), "text", "lang", "source")).where("kept").select(F.col("doc_id").alias(key))
    return rows.join(kept, key, "left_semi").select(*docs.columns)
