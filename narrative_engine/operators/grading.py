"""Grades of narratives: accuracy, completeness, fluency, conciseness, total, guard.

Every grade is a column expression over the row; broadcasts are a row per style.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from narrative_engine.operators.bulk_reading import measured
from narrative_engine.operators.claims import Reading, claims
from narrative_engine.operators.columns import uniform
from narrative_engine.settings import BANDS, DEFAULT_EXEMPLARS, DRAWS, LONGEST_SHARE, NEED_EQUAL, TOLERANCE, WEIGHTS

CLAUSE_END = r"[.;!?](?:\s|$)|, while |, but "
NUMBER = r"[0-9]+(?:\.[0-9]+)?"
STYLE_STEP = 9  # style distance that costs a point of fluency


@dataclass(frozen=True)
class AccuracyPolicy:
    """Which mistakes count, and how many levels the grade has.

    ``yes_no`` asks one question of the whole text, which most features answer; ``stepwise`` goes
    through the features one by one and keeps the steps (:func:`accuracy_steps`).
    """

    levels: int = 2
    allow_omission: bool = True
    check_direction: bool = True
    check_values: bool = True
    invented_is_error: bool = True
    yes_no: bool = False
    stepwise: bool = True
    tolerance: float = TOLERANCE

    @classmethod
    def plain(cls) -> AccuracyPolicy:
        return cls(allow_omission=False, check_direction=False, invented_is_error=False, stepwise=False)

    @classmethod
    def asked_yes_no(cls) -> AccuracyPolicy:
        return cls(yes_no=True, stepwise=False)


@dataclass(frozen=True)
class CompletenessPolicy:
    require_contrib: bool = False
    per_feature: bool = True


def word_count(text: Column) -> Column:
    return F.size(F.regexp_extract_all(text, F.lit(r"[^ \t\n\r]+"), F.lit(0)))


def _feature_wrong(c: Column, policy: AccuracyPolicy) -> Column:
    return (c["wrong"] if policy.check_values else F.lit(False)) | (c["direction"] < 0 if policy.check_direction else F.lit(False))


def accuracy(read: Column, policy: AccuracyPolicy = AccuracyPolicy()) -> Column:
    """1 when nothing said is wrong (or 2, 1, 0 on three levels: accurate, misleading, inaccurate), from :func:`claims`."""
    found = read["found"]
    if policy.yes_no:
        wrong = F.size(F.filter(found, lambda c: _feature_wrong(c, policy)))
        return F.when(2 * wrong > F.size(found), 0).otherwise(1)
    bad = F.exists(found, lambda c: _feature_wrong(c, policy))
    if policy.invented_is_error:
        bad = bad | read["invented"]
    missing = F.lit(False) if policy.allow_omission else F.exists(found, lambda c: ~c["mentioned"] | ~c["value"])
    if policy.levels == 3:
        vague = F.exists(found, lambda c: c["mentioned"] & (~c["value"] | (c["direction"] == 0)))
        return F.when(bad, 0).when(vague, 1).otherwise(2)
    return F.when(bad | missing, 0).otherwise(1)


def accuracy_steps(read: Column, policy: AccuracyPolicy = AccuracyPolicy()) -> Column:
    """What a stepwise judge writes down: a line for each feature, and one for what is invented."""
    line = lambda c: F.concat(c["feature"], F.lit(": value "), c["value_state"], F.lit(", contribution "), c["contrib_state"], F.lit(", direction "), F.when(c["direction"] > 0, "right").when(c["direction"] < 0, "wrong").otherwise("untold"))
    return F.concat(F.transform(read["found"], line), F.when(read["invented"], F.array(F.lit("something is invented"))).otherwise(F.array().cast("array<string>")))


def _full(c: Column, policy: CompletenessPolicy) -> Column:
    return c["value"] & (c["direction"] != 0) & (c["contribution"] if policy.require_contrib else F.lit(True))


def completeness(read: Column, policy: CompletenessPolicy = CompletenessPolicy()) -> Column:
    """0 when a feature is missing, 2 when every value and direction is there, else 1."""
    found = read["found"]
    full = F.forall(found, lambda c: _full(c, policy))
    if not policy.per_feature:  # the plain question misses absent features when some value is there
        some = F.forall(F.filter(found, lambda c: c["mentioned"]), lambda c: _full(c, policy))
        return F.when(~F.exists(found, lambda c: c["mentioned"]), 0).when(some, 2).otherwise(1)
    return F.when(F.exists(found, lambda c: ~c["mentioned"]), 0).when(full, 2).otherwise(1)


def checklist(read: Column, policy: CompletenessPolicy = CompletenessPolicy()) -> Column:
    """The per-feature list that the judge goes through: (feature, listed, value, direction, done)."""
    return F.transform(read["found"], lambda c: F.struct(c["feature"].alias("feature"), c["mentioned"].alias("listed"), c["value"].alias("value"), (c["direction"] != 0).alias("direction"), _full(c, policy).alias("done")))


def conciseness(words: Column, features: Column, longest: Column) -> Column:
    """4 up to ``features * longest`` words, 0 from twice that on, falling in between."""
    room = features * longest
    return F.when((room <= 0) | (words >= 2 * room), F.lit(0.0)).when(words <= room, F.lit(4.0)).otherwise(4.0 * (2.0 - words / room))


def masked(text: Column, expl: Column) -> Column:
    """``text`` without its topic: features, values and numbers replaced (the first three features)."""
    out = text
    for k in range(3):
        x = F.get(expl, F.lit(k))
        out = F.replace(F.replace(out, F.coalesce(x["value"], F.lit("\x03")), F.lit("y")), F.coalesce(x["feature"], F.lit("\x03")), F.lit("x"))
    return F.regexp_replace(out, NUMBER, "0")


#: Words that carry no topic.
FUNCTION_WORDS = ("the", "a", "its", "their", "is", "and", "which", "by", "of", "being", "this", "that")
TRIGRAM_BUCKETS = 16


def _surface(text: Column, n: Column) -> list[Column]:
    times = lambda s: ((F.length(text) - F.length(F.replace(text, F.lit(s), F.lit("")))) / F.lit(len(s))).cast("int")
    rate = lambda s: F.floor(times(s) * 100 / n).cast("int")
    return [
        rate(","), rate("("), rate(";"), rate("about"), rate("We ") + rate("our "), rate("!"), rate("0"), rate("which"), rate("feature"),
        F.floor(n / F.greatest(F.size(F.split(text, CLAUSE_END)) - 1, F.lit(1))).cast("int"),
        F.floor((F.length(text) - n) * 2 / n).cast("int"),
    ]


def _function(text: Column, n: Column) -> list[Column]:
    padded = F.concat(F.lit(" "), F.regexp_replace(F.regexp_replace(F.lower(text), "[^a-z ]", " "), " +", "  "), F.lit(" "))
    return [F.floor((F.length(padded) - F.length(F.replace(padded, F.lit(f" {w} "), F.lit("")))) / (len(w) + 2) * 100 / n).cast("int") for w in FUNCTION_WORDS]


def _trigrams(text: Column, n: Column) -> list[Column]:
    low = F.lower(text)
    grams = F.transform(F.sequence(F.lit(1), F.greatest(F.length(text) - 2, F.lit(1))), lambda i: F.conv(F.substring(F.md5(low.substr(i, F.lit(3)).cast("binary")), 1, 1), 16, 10).cast("int"))
    return [F.floor(F.size(F.filter(grams, lambda g: g == b)) * 100 / F.size(grams)).cast("int") for b in range(TRIGRAM_BUCKETS)]


#: Terms of a style vector, each switchable.
TERMS: dict[str, tuple[Callable[[Column, Column], list[Column]], int]] = {"surface": (_surface, 11), "function": (_function, len(FUNCTION_WORDS)), "trigrams": (_trigrams, TRIGRAM_BUCKETS)}


def style_vector(text: Column, terms: tuple[str, ...] = ("surface",)) -> Column:
    """Whole-number measures of style, so that no order of summing can change a grade."""
    n = F.greatest(word_count(text), F.lit(1))
    return F.array(*[m for t in terms for m in TERMS[t][0](text, n)])


def centroid(vectors: DataFrame, by: str = "style", terms: tuple[str, ...] = ("surface",)) -> DataFrame:
    """Mean style vector of each group, in whole numbers."""
    size = sum(TERMS[t][1] for t in terms)
    sums = vectors.groupBy(by).agg(F.count(F.lit(1)).alias("n"), *[F.sum(F.get("v", F.lit(i))).alias(f"s{i}") for i in range(size)])
    return sums.select(by, F.array(*[F.floor(F.col(f"s{i}") / F.col("n")).cast("int") for i in range(size)]).alias("centre"))


@dataclass(frozen=True)
class FluencyPolicy:
    """``k`` exemplars of the style (or as many as there are), its topic masked; ``pooled`` takes all styles' exemplars for one generic centre."""

    k: int = DEFAULT_EXEMPLARS
    mask_topic: bool = True
    pooled: bool = False
    terms: tuple[str, ...] = ("surface",)


def style_references(exemplars: DataFrame, policy: FluencyPolicy = FluencyPolicy()) -> DataFrame:
    """style -> centre, from exemplars (style, place, text, expl): the first ``k`` by place."""
    text = masked(F.col("text"), F.col("expl")) if policy.mask_topic else F.col("text")
    rows = exemplars.withColumn("_k", F.row_number().over(Window.partitionBy("style").orderBy("place"))).where(F.col("_k") <= policy.k).withColumn("v", style_vector(text, policy.terms))
    if not policy.pooled:
        return centroid(rows, "style", policy.terms)
    whole = centroid(rows.withColumn("all", F.lit(1)), "all", policy.terms).drop("all")
    return rows.select("style").distinct().crossJoin(F.broadcast(whole))


def style_distance(v: Column, centre: Column) -> Column:
    return F.aggregate(F.zip_with(v, centre, lambda a, b: F.abs(a - b)), F.lit(0), lambda s, x: s + x)


def fluency(v: Column, centre: Column) -> Column:
    """0 to 4, a point less for every ``STYLE_STEP`` of distance."""
    return F.greatest(F.lit(0), 4 - F.floor(style_distance(v, centre) / STYLE_STEP)).cast("int")


def derive_longest(df: DataFrame, share: float = LONGEST_SHARE, rule: str = "ratio") -> DataFrame:
    """style -> words per feature that are still concise: a share of the longest exemplar's.

    By ``ratio`` the longest is the largest number of words per feature; by ``clause`` the longest
    single clause of any exemplar.
    """
    if rule == "clause":
        per = F.array_max(F.transform(F.split("text", CLAUSE_END), lambda c: word_count(c).cast("double")))
    else:
        per = word_count(F.col("text")) / F.size("expl")
    return df.groupBy("style").agg((F.max(per) * share).alias("longest"))


def draws(value: Column, key: Column, p: float = 0.0, k: int = DRAWS, top: int = 1) -> Column:
    """``k`` draws of a judge that errs with probability ``p``, seeded by ``key``; no row is multiplied."""
    return F.transform(F.sequence(F.lit(1), F.lit(k)), lambda i: F.when(uniform(key, i.cast("string")) < p, F.lit(top) - value).otherwise(value).cast("double"))


def mean_draw(d: Column) -> Column:
    return F.aggregate(d, F.lit(0.0), lambda a, x: a + x) / F.size(d)


def consistency_alert(d: Column, need: int = NEED_EQUAL) -> Column:
    """Whether fewer than ``need`` draws agree."""
    return F.array_max(F.transform(F.array_distinct(d), lambda v: F.size(F.filter(d, lambda x: x == v)))) < need


def total_grade(a: Column, c: Column, f: Column, s: Column, weights: dict[str, float] = WEIGHTS) -> Column:
    return F.lit(weights["a"]) * a + F.lit(weights["f"]) * f + F.lit(weights["c"]) * c + F.lit(weights["s"]) * s


@dataclass(frozen=True)
class Metric:
    """One more metric: ``fn`` makes its grade from a row of (style, expl, text, ...)."""

    fn: Callable[[DataFrame], Column]
    weight: float


@dataclass(frozen=True)
class Judge:
    """Draws of each judged grade, and how often a draw errs (a hosted judge's part; 0 for the rules)."""

    draws: int = DRAWS
    error: float = 0.0


def graded(
    df: DataFrame, styles: DataFrame, accuracy_policy: AccuracyPolicy = AccuracyPolicy(), completeness_policy: CompletenessPolicy = CompletenessPolicy(),
    weights: dict[str, float] = WEIGHTS, reading: Reading = Reading(), judge: Judge = Judge(), key: tuple[str, ...] = (), metrics: dict[str, Metric] | None = None,
    fluency_policy: FluencyPolicy = FluencyPolicy(), bulk: bool = False,
) -> DataFrame:
    """``df`` (style, expl, text) with a, c, f, s, alert and total; ``styles`` has centre and longest of each style.

    Accuracy, completeness and fluency are the mean of the judge's draws, seeded by the ``key``
    columns; ``alert`` tells that fewer than four of five agree in one of them.  ``bulk`` reads the
    texts in batches, outside the JVM, with the same results: for millions of narratives.
    """
    reading = reading if reading.tolerance == accuracy_policy.tolerance else Reading(accuracy_policy.tolerance, reading.up, reading.down, reading.aliases, reading.others)
    rows = df.join(F.broadcast(styles.select("style", "centre", "longest")), "style")
    if bulk:
        if fluency_policy.terms != ("surface",):
            raise ValueError("in bulk only the surface terms of style are measured")
        rows = measured(df, reading, fluency_policy.mask_topic).join(F.broadcast(styles.select("style", "centre", "longest")), "style")
    else:
        shown = masked(F.col("text"), F.col("expl")) if fluency_policy.mask_topic else F.col("text")
        rows = rows.withColumn("claims", claims(F.col("text"), F.col("expl"), reading)).withColumn("_v", style_vector(shown, fluency_policy.terms)).withColumn("n_words", word_count(F.col("text")))
    rows = rows.select(
        "*", accuracy(F.col("claims"), accuracy_policy).alias("a"), completeness(F.col("claims"), completeness_policy).alias("c"), fluency(F.col("_v"), F.col("centre")).alias("f"),
        conciseness(F.col("n_words"), F.size("expl"), F.col("longest")).alias("s"),
    )
    if judge.error > 0.0:
        seed = lambda m: F.concat_ws("|", F.lit(m), *[F.col(c).cast("string") for c in key])
        tops = {"a": accuracy_policy.levels - 1, "c": 2, "f": 4}
        rows = rows.withColumns({f"_{m}": draws(F.col(m), seed(m), judge.error, judge.draws, top) for m, top in tops.items()})
        alert = consistency_alert(F.col("_a")) | consistency_alert(F.col("_c")) | consistency_alert(F.col("_f"))
        rows = rows.withColumns({"alert": alert, **{m: mean_draw(F.col(f"_{m}")) for m in tops}}).drop("_a", "_c", "_f")
    else:  # equal draws: their mean is the grade, and none disagrees
        rows = rows.withColumn("alert", F.lit(False))
    total = total_grade(F.col("a"), F.col("c"), F.col("f"), F.col("s"), weights)
    for name, m in (metrics or {}).items():
        rows = rows.withColumn(name, m.fn(rows))
        total = total + F.lit(m.weight) * F.col(name)
    return rows.withColumn("total", total).drop("_v", "centre", "longest")


def bar_view(expl: Column, width: int = 20) -> Column:
    """The default view: a signed bar per feature, the longest ``width`` marks."""
    most = F.abs(F.get(expl, F.lit(0))["contribution"])
    bar = lambda x: F.repeat(F.when(x["contribution"] < 0, "-").otherwise("+"), F.when(most > 0, F.floor(F.abs(x["contribution"]) / most * width + 0.5)).otherwise(0).cast("int"))
    return F.array_join(F.transform(expl, lambda x: F.concat(F.rpad(x["feature"], 18, " "), bar(x))), "\n")


def guarded(df: DataFrame, least: float = 12.0, per_metric: dict[str, float] | None = None) -> DataFrame:
    """``shown``: the narrative, or the bar view where the total (or a metric) is under its threshold."""
    ok = F.col("total") >= least
    for name, floor in (per_metric or {}).items():
        ok = ok & (F.col(name) >= floor)
    return df.withColumn("rejected", ~ok).withColumn("shown", F.when(ok, F.col("text")).otherwise(bar_view(F.col("expl"))))


def banded(grade: Column) -> Column:
    """high above 3.5, low under 3, on the 0-4 scale."""
    (_, _, low), _, (_, high, _) = BANDS
    return F.when(grade > high, "high").when(grade < low, "low").otherwise("middle")


def unigram_alignment(pairs: DataFrame, recall_weight: float = 9.0, penalty: float = 0.5, power: int = 3) -> DataFrame:
    """(id, n_match, n_chunks, score) of (id, text, reference): exact-match unigram alignment.

    The j-th occurrence of a word is matched with its j-th occurrence in the reference.  Precision and
    recall meet in a harmonic mean that weighs recall ``recall_weight`` times; matches that lie in
    many separate chunks cost up to ``penalty``.  Needs a reference for every text.
    """
    def places(col: str, at: str) -> DataFrame:
        words = F.regexp_extract_all(F.lower(F.col(col)), F.lit("[a-z0-9]+"), F.lit(0))
        rows = pairs.select("id", F.posexplode(words).alias(at, "w"))
        return rows.withColumn("j", F.row_number().over(Window.partitionBy("id", "w").orderBy(at)))

    one, two = places("text", "i"), places("reference", "k")
    both = one.join(two, ["id", "w", "j"])
    order = Window.partitionBy("id").orderBy("i")
    fresh = F.coalesce((F.col("i") == F.lag("i").over(order) + 1) & (F.col("k") == F.lag("k").over(order) + 1), F.lit(False))
    matched = both.withColumn("fresh", (~fresh).cast("int")).groupBy("id").agg(F.count("*").alias("n_match"), F.sum("fresh").alias("n_chunks"))
    size = lambda rows, name: rows.groupBy("id").agg(F.count("*").alias(name))
    rows = pairs.select("id").join(size(one, "n_text"), "id", "left").join(size(two, "n_reference"), "id", "left").join(matched, "id", "left").na.fill(0)
    p, r = F.col("n_match") / F.col("n_text"), F.col("n_match") / F.col("n_reference")
    mean = (1 + recall_weight) * p * r / (r + recall_weight * p)
    kept = F.lit(1.0) - F.lit(penalty) * F.pow(F.col("n_chunks") / F.col("n_match"), F.lit(float(power)))
    return rows.select("id", "n_match", "n_chunks", F.when(F.col("n_match") == 0, F.lit(0.0)).otherwise(mean * kept).alias("score"))
