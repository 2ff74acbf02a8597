"""Signed additive contributions of features to one prediction."""

from __future__ import annotations

import itertools
import math
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from narrative_engine.shipping import ship


def half_up(x: Column, digits: int = 2) -> Column:
    """Rounding by the same floating-point steps that SQL engines share."""
    k = float(10**digits)
    return F.floor(x * F.lit(k) + F.lit(0.5)).cast("double") / F.lit(k)


def value_text(x: Column) -> Column:
    """A decimal without trailing zeros."""
    return F.rtrim(F.rtrim(x.cast("decimal(18,4)").cast("string"), F.lit("0")), F.lit("."))


def fit_numeric(df: DataFrame, numeric: Sequence[str], target: str = "target") -> DataFrame:
    """One row (feature, n, slope, mean) per numeric feature, in one aggregate pass over exact sums."""
    wide = lambda c: F.col(c).cast("decimal(18,4)")
    y = wide(target)
    sums = [
        F.struct(
            F.lit(c).alias("feature"), F.count(F.lit(1)).cast("double").alias("n"), F.sum(wide(c)).cast("double").alias("sx"), F.sum(y).cast("double").alias("sy"),
            F.sum((wide(c) * y).cast("decimal(34,6)")).cast("double").alias("sxy"), F.sum((wide(c) * wide(c)).cast("decimal(34,6)")).cast("double").alias("sxx"),
        ).alias(f"c{i}")
        for i, c in enumerate(numeric)
    ]
    card = df.agg(*sums).select(F.explode(F.array(*[F.col(f"c{i}") for i in range(len(numeric))])).alias("c")).select("c.*")
    down = F.col("n") * F.col("sxx") - F.col("sx") * F.col("sx")
    slope = F.when(down == 0, F.lit(0.0)).otherwise((F.col("n") * F.col("sxy") - F.col("sx") * F.col("sy")) / down)
    return card.select("feature", "n", slope.alias("slope"), (F.col("sx") / F.col("n")).alias("mean"))


def fit_categorical(df: DataFrame, categorical: Sequence[str], target: str = "target") -> DataFrame:
    """Rows (feature, level, n, effect): a level's mean less the overall one, by grouping sets in one pass."""
    sets = [[c] for c in categorical] + [[]]
    by = df.groupingSets([[F.col(c) for c in s] for s in sets], *[F.col(c) for c in categorical])
    which = F.grouping_id(*[F.col(c) for c in categorical])
    rows = by.agg(which.alias("g"), F.count(F.lit(1)).cast("double").alias("n"), F.sum(F.col(target).cast("decimal(18,4)")).cast("double").alias("sy"))
    k = len(categorical)
    full = (1 << k) - 1
    feature = F.coalesce(*[F.when(F.col("g") == full - (1 << (k - 1 - i)), F.lit(c)) for i, c in enumerate(categorical)])
    level = F.coalesce(*[F.when(F.col("g") == full - (1 << (k - 1 - i)), F.coalesce(F.col(c), F.lit("none"))) for i, c in enumerate(categorical)])
    rows = rows.select("g", "n", "sy", feature.alias("feature"), level.alias("level"))
    whole = rows.where(F.col("g") == full).select((F.col("sy") / F.col("n")).alias("mean"))
    return rows.where(F.col("g") != full).crossJoin(F.broadcast(whole)).select("feature", "level", "n", (F.col("sy") / F.col("n") - F.col("mean")).alias("effect"))


def attribute_additive(df: DataFrame, numeric: Sequence[str], categorical: Sequence[str], numbers: DataFrame | None, levels: DataFrame | None) -> DataFrame:
    """``df`` with ``attr``: (feature, value, value_num, contribution, direction) of every feature, in the row.

    The cards have one row per feature or level and are broadcast as one row of maps: no shuffle.
    """
    kind = "struct<slope:double,mean:double>"
    cards = None
    if numeric:
        cards = numbers.agg(F.map_from_entries(F.collect_list(F.struct("feature", F.struct("slope", "mean").cast(kind)))).alias("_n"))
    if categorical:
        more = levels.agg(F.map_from_entries(F.collect_list(F.struct(F.concat_ws("=", "feature", "level"), "effect"))).alias("_c"))
        cards = more if cards is None else cards.crossJoin(more)
    out = df.crossJoin(F.broadcast(cards))
    parts = []
    for c in numeric:
        x = F.col(c).cast("double")
        contribution = half_up(F.col("_n")[c]["slope"] * (x - F.col("_n")[c]["mean"]))
        parts.append((c, value_text(F.col(c)), x, contribution))
    for c in categorical:
        level = F.coalesce(F.col(c), F.lit("none"))
        parts.append((c, level, F.lit(None).cast("double"), half_up(F.coalesce(F.col("_c")[F.concat(F.lit(c + "="), level)], F.lit(0.0)))))
    attr = F.array(*[
        F.struct(F.lit(c.replace("_", " ")).alias("feature"), v.alias("value"), x.alias("value_num"), w.alias("contribution"), F.signum(w).cast("int").alias("direction"))
        for c, v, x, w in parts
    ])
    return out.withColumn("attr", attr).drop("_n", "_c")


def check_additivity(df: DataFrame, base: str, prediction: str, tolerance: float = 1e-6) -> DataFrame:
    """Rows whose contributions and base don't add up to the prediction."""
    total = F.aggregate("attr", F.lit(0.0), lambda a, x: a + x["contribution"])
    return df.where(F.abs(F.col(base) + total - F.col(prediction)) > tolerance)


def fit_linear(df: DataFrame, numeric: Sequence[str], target: str = "target") -> tuple[np.ndarray, float, np.ndarray]:
    """Coefficients, intercept and feature means of least squares, from one aggregate of the normal equations."""
    x = [F.col(c).cast("double") for c in numeric] + [F.lit(1.0)]
    y, k = F.col(target).cast("double"), len(x)
    got = df.agg(*[F.sum(x[i] * x[j]).alias(f"a{i}_{j}") for i in range(k) for j in range(i, k)], *[F.sum(x[i] * y).alias(f"b{i}") for i in range(k)]).first()
    a = np.array([[got[f"a{min(i, j)}_{max(i, j)}"] for j in range(k)] for i in range(k)])
    w = np.linalg.lstsq(a, np.array([got[f"b{i}"] for i in range(k)]), rcond=None)[0]
    return w[:-1], float(w[-1]), a[-1, :-1] / a[-1, -1]


def fit_logistic(df: DataFrame, numeric: Sequence[str], target: str = "target") -> tuple[np.ndarray, float, np.ndarray]:
    """The same of a logistic model; its contributions are on the margin."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    rows = VectorAssembler(inputCols=list(numeric), outputCol="x").transform(df.select(*[F.col(c).cast("double").alias(c) for c in numeric], F.col(target).cast("double").alias("y")))
    model = LogisticRegression(featuresCol="x", labelCol="y", maxIter=50, regParam=1e-4).fit(rows)
    means = df.agg(*[F.avg(F.col(c).cast("double")) for c in numeric]).first()
    return np.array(model.coefficients), float(model.intercept), np.array(list(means))


def attribute_linear(df: DataFrame, numeric: Sequence[str], weights: np.ndarray, intercept: float, means: np.ndarray) -> DataFrame:
    """Exact contributions of a linear score when features are independent: weight x (value - mean)."""
    attr = F.array(*[
        F.struct(F.lit(c).alias("feature"), F.col(c).cast("string").alias("value"), F.col(c).cast("double").alias("value_num"), (F.lit(float(w)) * (F.col(c).cast("double") - F.lit(float(m)))).alias("contribution"))
        for c, w, m in zip(numeric, weights, means)
    ])
    score = sum((F.lit(float(w)) * F.col(c).cast("double") for c, w in zip(numeric, weights)), F.lit(intercept))
    return df.withColumn("attr", attr).withColumn("base", F.lit(float(intercept + weights @ means))).withColumn("prediction", score)


MOST_FEATURES = 12


def _per_row(df: DataFrame, numeric: Sequence[str], fn: Callable[[np.ndarray], np.ndarray]) -> DataFrame:
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.stack([b.column(1 + i).to_numpy(zero_copy_only=False) for i in range(len(numeric))], axis=1) if len(b) else np.empty((0, len(numeric)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(list(fn(x)), pa.list_(pa.float64()))], names=["row_id", "contributions"])

    return df.select("row_id", *[F.col(c).cast("double") for c in numeric]).mapInArrow(run, "row_id string, contributions array<double>")


def attribute_coalition(df: DataFrame, numeric: Sequence[str], score: Callable[[np.ndarray], np.ndarray], background: np.ndarray) -> DataFrame:
    """Exact averages over all coalitions of at most 12 features; absent ones come from ``background``'s rows."""
    d = len(numeric)
    if d > MOST_FEATURES:
        raise ValueError(f"exact coalitions take at most {MOST_FEATURES} features; sample instead")
    subsets = [np.array(s, dtype=bool) for s in itertools.product((False, True), repeat=d)]
    code = {tuple(s): k for k, s in enumerate(subsets)}
    weight = [math.factorial(k) * math.factorial(d - k - 1) / math.factorial(d) for k in range(d)]

    def fn(x: np.ndarray) -> np.ndarray:
        value = np.stack([np.mean([score(np.where(s, x, b)) for b in background], axis=0) for s in subsets], axis=1) if len(x) else np.empty((0, len(subsets)))
        out = np.zeros((len(x), d))
        for s in subsets:
            for i in np.flatnonzero(~s):
                more = s.copy()
                more[i] = True
                out[:, i] += weight[int(s.sum())] * (value[:, code[tuple(more)]] - value[:, code[tuple(s)]])
        return out

    return _per_row(df, numeric, fn)


def attribute_sampled(df: DataFrame, numeric: Sequence[str], score: Callable[[np.ndarray], np.ndarray], background: np.ndarray, m: int = 64, seed: int = 42) -> DataFrame:
    """The same, estimated from ``m`` random orders of the features."""
    d = len(numeric)

    def fn(x: np.ndarray) -> np.ndarray:
        rng, out = np.random.default_rng(seed), np.zeros((len(x), d))
        for _ in range(m):
            now = np.tile(background[rng.integers(len(background))], (len(x), 1))
            before = score(now)
            for i in rng.permutation(d):
                now[:, i] = x[:, i]
                after = score(now)
                out[:, i] += after - before
                before = after
        return out / m

    return _per_row(df, numeric, fn)
