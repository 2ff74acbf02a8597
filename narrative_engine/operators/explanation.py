"""Explanations: the strongest contributions of a row, as an array and as text; other kinds beside them."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from narrative_engine.settings import FORMATS

TOP = 3


def number_text(x: Column) -> Column:
    """Two decimals, without thousands marks."""
    return F.format_string("%.2f", x)


def top_contributions(df: DataFrame, n: int = TOP, col: str = "attr") -> DataFrame:
    """``expl``: the ``n`` largest of ``col`` by absolute contribution, ties by feature; in the row, no shuffle."""
    keyed = F.transform(col, lambda x: F.struct((-F.abs(x["contribution"])).alias("k"), x["feature"].alias("f"), x.alias("x")))
    return df.withColumn("expl", F.transform(F.slice(F.array_sort(keyed), 1, n), lambda s: s["x"]))


def top_contributions_long(df: DataFrame, n: int = TOP) -> DataFrame:
    """The same over rows (row_id, feature, value, contribution); the rank limit is applied before the shuffle too."""
    order = Window.partitionBy("row_id").orderBy(F.abs("contribution").desc(), "feature")
    return df.withColumn("place", F.row_number().over(order)).where(F.col("place") <= n)


def serialize_explanation(expl: Column | str = "expl", extras: Column | None = None) -> Column:
    """``(feature, value, contribution), ...``; ``extras`` (map feature -> text) adds a fourth field."""
    expl = F.col(expl) if isinstance(expl, str) else expl
    more = (lambda x: F.coalesce(F.concat(F.lit(", "), extras[x["feature"]]), F.lit(""))) if extras is not None else (lambda x: F.lit(""))
    return F.array_join(F.transform(expl, lambda x: F.concat(F.lit("("), x["feature"], F.lit(", "), x["value"], F.lit(", "), number_text(x["contribution"]), more(x), F.lit(")"))), ", ")


def parse_explanation(text: Column | str) -> Column:
    """Triples of a parenthesised list, or one bare triple, back as an array; a feature may hold commas."""
    text = F.col(text) if isinstance(text, str) else text
    whole = F.when(text.startswith("("), text).otherwise(F.concat(F.lit("("), text, F.lit(")")))
    body = F.regexp_extract_all(whole, F.lit(r"\(((?:[^()]|\([^()]*\))*)\)"), F.lit(1))
    part = lambda x, k: F.trim(F.regexp_extract(x, r"^(.*),([^,]*),([^,]*)$", k))
    return F.transform(body, lambda x: F.struct(part(x, 1).alias("feature"), part(x, 2).alias("value"), part(x, 2).try_cast("double").alias("value_num"), part(x, 3).try_cast("double").alias("contribution")))


def direction(contribution: Column) -> Column:
    return F.signum(contribution).cast("int")


#: z-scores between which a value counts as usual.
USUAL = 0.5


def feature_statistics(frame: DataFrame, numeric: tuple[str, ...], percentiles: bool = False) -> DataFrame:
    """One row of maps from feature to mean and spread (and p10, p50, p90), in one pass of exact decimal sums."""
    wide = lambda c: F.col(c).cast("decimal(18,4)")
    n = F.count(F.lit(1)).cast("double")
    name = lambda c: F.lit(c.replace("_", " "))
    mean = lambda c: F.sum(wide(c)).cast("double") / n
    spread = lambda c: F.sqrt(F.greatest(F.lit(0.0), F.sum((wide(c) * wide(c)).cast("decimal(34,6)")).cast("double") / n - mean(c) * mean(c)))
    out = [F.map_from_arrays(F.array(*map(name, numeric)), F.array(*map(mean, numeric))).alias("means"), F.map_from_arrays(F.array(*map(name, numeric)), F.array(*map(spread, numeric))).alias("spreads")]
    if percentiles:
        out.append(F.map_from_arrays(F.array(*map(name, numeric)), F.array(*[F.percentile_approx(F.col(c).cast("double"), F.array(*map(F.lit, (0.1, 0.5, 0.9))), 10_000) for c in numeric])).alias("percentiles"))
    return frame.agg(*out)


def z_band(x: Column, means: Column, spreads: Column) -> Column:
    """How a value stands to the usual one: smaller, usual or larger; null where nothing is known."""
    m, s = means[x["feature"]], spreads[x["feature"]]
    z = F.when(s > 0, (x["value_num"] - m) / s)
    return F.when(z.isNull(), F.lit(None).cast("string")).when(z > USUAL, "larger than usual").when(z < -USUAL, "smaller than usual").otherwise("as usual")


def with_feature_statistics(df: DataFrame, statistics: DataFrame) -> DataFrame:
    """``extras``: map feature -> its usual value and how this row's stands to it, for :func:`serialize_explanation`; one broadcast row."""
    rows = df.crossJoin(F.broadcast(statistics))
    known = F.filter("expl", lambda x: x["value_num"].isNotNull() & F.col("means")[x["feature"]].isNotNull())
    text = lambda x: F.concat(F.lit("usually "), number_text(F.floor(F.col("means")[x["feature"]] * 100 + 0.5) / 100), F.coalesce(F.concat(F.lit(", "), z_band(x, F.col("means"), F.col("spreads"))), F.lit("")))
    return rows.withColumn("extras", F.map_from_entries(F.transform(known, lambda x: F.struct(x["feature"], text(x)))))


def compared(expl: Column, means: Column) -> Column:
    """"larger" or "smaller than usual" of each feature that has a mean."""
    word = lambda x: F.when(x["value_num"] >= means[x["feature"]].cast("double"), "larger than usual").otherwise("smaller than usual")
    return F.transform(expl, lambda x: F.struct(x["feature"].alias("feature"), F.when(x["value_num"].isNull() | means[x["feature"]].isNull(), F.lit(None)).otherwise(word(x)).alias("band")))


@dataclass(frozen=True)
class ExplanationKind:
    """A kind of explanation: what its text means, how it is written and read, and what each part of it asks of a narrative."""

    name: str
    describe: str
    serialize: Callable[[Column], Column]
    parse: Callable[[Column], Column]
    #: (expl, lower-case text) -> array of booleans, one per part: does the text tell it?
    told: Callable[[Column, Column], Column]


def _listed(expl: Column, *fields: str) -> Column:
    return F.array_join(F.transform(expl, lambda x: F.concat(F.lit("("), F.concat_ws(", ", *[x[f] for f in fields]), F.lit(")"))), ", ")


def _pairs(text: Column, first: str, second: str) -> Column:
    body = F.regexp_extract_all(text, F.lit(r"\(([^()]*)\)"), F.lit(1))
    return F.transform(body, lambda x: F.struct(F.trim(F.regexp_extract(x, r"^(.*),([^,]*)$", 1)).alias(first), F.trim(F.regexp_extract(x, r"^(.*),([^,]*)$", 2)).alias(second)))


def _both_told(first: str, second: str) -> Callable[[Column, Column], Column]:
    return lambda expl, low: F.transform(expl, lambda x: F.contains(low, F.lower(x[first])) & F.contains(low, F.lower(x[second])))


EXPLANATION_KINDS: dict[str, ExplanationKind] = {}


def register_kind(kind: ExplanationKind) -> ExplanationKind:
    EXPLANATION_KINDS[kind.name] = kind
    return kind


for _name in ("contributions", "contributions_with_statistics"):
    register_kind(ExplanationKind(_name, FORMATS[_name], lambda e: serialize_explanation(e), lambda t: parse_explanation(t), lambda e, low: F.transform(e, lambda x: F.contains(low, F.lower(x["feature"])))))
register_kind(ExplanationKind("rules", FORMATS["rules"], lambda e: _listed(e, "condition", "outcome"), lambda t: _pairs(t, "condition", "outcome"), _both_told("condition", "outcome")))
register_kind(ExplanationKind("examples", FORMATS["examples"], lambda e: _listed(e, "case", "outcome"), lambda t: _pairs(t, "case", "outcome"), _both_told("case", "outcome")))


def kind_completeness(kind: str, expl: Column, text: Column) -> Column:
    """2 when every part is told, 1 when some are, else 0: the rubric of kinds without contributions."""
    told = EXPLANATION_KINDS[kind].told(expl, F.lower(text))
    n = F.size(F.filter(told, lambda t: t))
    return F.when(n == F.size(expl), 2).when(n > 0, 1).otherwise(0)


def pick_diverse(df: DataFrame, k: int = 5) -> DataFrame:
    """``k`` explanations of different kinds: one per (features, signs) signature first, the commonest signatures first."""
    sign = F.array_join(F.transform("expl", lambda x: F.concat(x["feature"], F.when(x["contribution"] < 0, "-").otherwise("+"))), "|")
    rows = df.withColumn("signature", sign)
    n = rows.groupBy("signature").agg(F.count("*").alias("n"), F.min("row_id").alias("row_id"))
    best = n.orderBy(F.desc("n"), "signature").limit(k).select("row_id", "signature", "n")
    return best
