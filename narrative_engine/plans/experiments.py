"""The experiment workloads: explained domains, exemplar styles, the technique grid, validation, reports."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from narrative_engine.operators import attribution as at
from narrative_engine.operators import explanation as ex
from narrative_engine.operators import grading as gr
from narrative_engine.operators import writing as wr
from narrative_engine.settings import CATEGORIES, GATE, PUBLISHED_CONFUSION, PUBLISHED_SETS, PUBLISHED_TECHNIQUES, SET_ASIDE, STYLES, TECHNIQUES, WEIGHTS
from narrative_engine.staging import spread_out, staged
from narrative_engine.sources.tables import CATEGORICAL, LABEL_RULES, NUMERIC, features

BOOT = 5
#: Assumed prices of a million tokens in and out, and characters a token.
PRICE_IN, PRICE_OUT, CHARS = 2.5, 10.0, 4


def effects(frame: DataFrame, domain: str) -> DataFrame:
    """(feature, level, slope_or_effect, mean): the fitted card of a domain, rounded for reading."""
    out = None
    frame = staged(frame)  # both fits read it
    if NUMERIC[domain]:
        card = at.fit_numeric(frame, NUMERIC[domain])
        out = card.select("feature", F.lit(None).cast("string").alias("level"), at.half_up(F.col("slope"), 3).alias("effect"), at.half_up(F.col("mean"), 3).alias("mean"))
    if CATEGORICAL[domain]:
        levels = at.fit_categorical(frame, CATEGORICAL[domain]).select("feature", "level", at.half_up(F.col("effect"), 3).alias("effect"), F.lit(None).cast("double").alias("mean"))
        out = levels if out is None else out.unionByName(levels)
    return out


def explained(frame: DataFrame, domain: str, n: int = ex.TOP) -> DataFrame:
    """``frame`` with every feature's contribution and its top ``n``.

    The frame is a row per case, far smaller than the tables it sums up; it is written once, and
    fitting and scoring read that.
    """
    frame = staged(frame)
    numbers = at.fit_numeric(frame, NUMERIC[domain]) if NUMERIC[domain] else None
    levels = at.fit_categorical(frame, CATEGORICAL[domain]) if CATEGORICAL[domain] else None
    return ex.top_contributions(at.attribute_additive(frame, NUMERIC[domain], CATEGORICAL[domain], numbers, levels), n)


def explanations(spark: SparkSession, sf_dir: str, domain: str) -> DataFrame:
    rows = explained(features(spark, sf_dir, domain), domain)
    return rows.select("row_id", ex.serialize_explanation("expl").alias("expl_text"), F.size("expl").alias("n_features"))


#: Rounds of bootstrapping; round r follows 1, 2 or 3 hand-written exemplars, drawn anew for it.
ROUNDS = 12


class Study:
    """Everything the grid needs: entries, hand-written narratives, styles with their exemplars, centre and length, bootstrapped pool."""

    def __init__(self, spark: SparkSession, sf_dir: str, gate: dict[str, float] = GATE, wanted: int = BOOT, rounds: int = ROUNDS) -> None:
        self.spark, self.gate, self.wanted = spark, gate, wanted
        domains = {d for d, _, _ in STYLES.values()}
        self.explained = {d: explained(features(spark, sf_dir, d), d) for d in sorted(domains)}
        self.entries = staged(wr.entries(spark, self.explained))
        self.techniques = wr.technique_frame(spark)
        self.hand = staged(wr.authored(self.entries))
        bare = wr.style_frame(self.hand)
        self.refs = staged(gr.style_references(self.hand).join(gr.derive_longest(self.hand), "style"))
        self.candidates = staged(self.bootstrapped(bare, rounds))
        self.accepted = self.candidates.where(" AND ".join(f"{k} >= {v}" for k, v in gate.items()))
        pool = self.pool().groupBy("style").agg(F.array_sort(F.collect_list(F.struct("b", "one"))).alias("p"))
        pool = pool.select("style", F.transform("p", lambda x: x["one"]).alias("boot"))
        self.styles = bare.join(pool, "style", "left").withColumn("boot", F.coalesce("boot", F.array().cast(f"array<{wr.EX}>"))).join(self.refs, "style")
        self.styles = staged(self.styles)

    def bootstrapped(self, styles: DataFrame, rounds: int) -> DataFrame:
        """Graded candidates: every set-aside entry in every round, written after exemplars drawn for that round.

        Rounds differ in their seed only, so all are one job; a pool is then filled in their order.
        """
        rows = self.entries.where(f"place > 5 AND place <= {SET_ASIDE}").join(F.broadcast(styles.drop("domain")), "style")
        rows = rows.withColumn("round", F.explode(F.sequence(F.lit(1), F.lit(rounds))))
        keyed = F.transform("hand", lambda x: F.struct(F.md5(F.concat_ws("|", F.col("style"), F.col("row_id"), F.lit("boot"), F.col("round").cast("string"), x["ex"]).cast("binary")).alias("k"), x.alias("x")))
        some = F.transform(F.slice(F.array_sort(keyed), 1, F.least(1 + (F.col("round") - 1) % 3, F.size("hand"))), lambda s: s["x"])
        rows = rows.withColumn("drawn", some).drop("hand").withColumn("text", wr.realized(F.col("expl"), F.col("drawn")))
        return gr.graded(rows, self.refs)

    def pool(self) -> DataFrame:
        """style, b, round and the exemplar of the first ``wanted`` accepted narratives of a style, by round; equal texts count once.

        A narrative's slots are those it was written with, so it is an exemplar of its own: another
        entry, and the clauses of all the exemplars it followed.
        """
        key = F.md5(F.concat_ws("|", F.lit("boot"), "style", F.col("round").cast("string"), F.col("place").cast("string")).cast("binary"))
        once = Window.partitionBy("style", "text").orderBy("round", key)
        rows = self.accepted.withColumn("same", F.row_number().over(once)).where("same = 1")
        rows = rows.withColumn("b", F.row_number().over(Window.partitionBy("style").orderBy("round", key))).where(F.col("b") <= self.wanted)
        first = F.get("drawn", F.lit(0))
        clauses = wr.followed(F.col("drawn"), wr.told_features(F.col("expl"), first["omits"]))
        one = F.struct(
            F.col("b").cast("string").alias("ex"), ex.serialize_explanation("expl").alias("expl_text"), "text", first["lead"].alias("lead"), first["joiner"].alias("joiner"), first["tail"].alias("tail"),
            first["omits"].alias("omits"), clauses.alias("clauses"),
        )
        return rows.select("style", "b", "round", "place", "row_id", one.cast(wr.EX).alias("one"))

    def short_styles(self) -> DataFrame:
        """Styles whose pool has fewer than wanted: style, candidates, accepted, in_pool, rounds_used."""
        got = self.pool().groupBy("style").agg(F.count("*").alias("in_pool"), F.max("round").alias("rounds_used"))
        ok = self.accepted.groupBy("style").agg(F.count("*").alias("accepted"))
        rows = self.candidates.groupBy("style").agg(F.count("*").alias("candidates")).join(ok, "style", "left").join(got, "style", "left")
        return rows.na.fill(0).withColumn("reached", F.col("in_pool") >= self.wanted)

    def prompts(self, rows: DataFrame | None = None) -> DataFrame:
        """Evaluated entries x techniques with their exemplars and text; both sides beyond the entries are a few fixed rows."""
        rows = self.entries.where(f"place > {SET_ASIDE}") if rows is None else rows
        wide = rows.join(F.broadcast(self.styles.drop("domain", "centre", "longest")), "style").crossJoin(F.broadcast(self.techniques))
        return wr.write(wr.sample_exemplars(wide))

    def grid(self, rows: DataFrame | None = None, **policies) -> DataFrame:
        return gr.graded(staged(self.prompts(rows)), self.refs, key=("style", "row_id", "technique"), **policies)

    def whole_grid(self, rows: DataFrame | None = None) -> DataFrame:
        """The grid over every row of every domain but the set-aside ones, each in all styles of its domain: its different narratives, and their number by technique.

        A narrative and its grades depend on the style, the explanation and the parts of the exemplars that
        it follows, so each different one is written and read once.  ``n`` rows have it in its technique.
        """
        if rows is None:
            aside = self.entries.where(f"place <= {SET_ASIDE}").select("style", "row_id")
            rows = wr.entries(self.spark, self.explained, whole=True).join(F.broadcast(aside), ["style", "row_id"], "left_anti")
        pools = wr.pool_parts(self.styles)
        rows = wr.drawn_places(rows.join(F.broadcast(pools.drop("firsts", "clauses")), "style"))
        settings = [F.struct(F.lit(t).alias("technique"), wr.used_parts(h, b).alias("used"), F.lit(base).alias("base")) for t, base, h, b in TECHNIQUES]
        rows = rows.select("style", "expl", F.inline(F.array(*settings)))
        bare = F.when(F.size("used") == 0, F.col("base")).alias("base")  # a base prompt shows in prose without exemplars only
        counted = rows.groupBy("style", "expl", "used", bare).agg(*[F.count(F.when(F.col("technique") == t[0], 1)).alias(f"n_{t[0]}") for t in TECHNIQUES])
        told = spread_out(counted).join(F.broadcast(pools.select("style", "firsts", "clauses")), "style").withColumn("exemplars", wr.of_parts(F.col("used"))).drop("firsts", "clauses")
        read = gr.graded(wr.write(told).drop("exemplars", "base", "used"), self.refs, bulk=True).drop("claims")
        times = F.array(*[F.struct(F.lit(t).alias("technique"), F.lit(base).alias("base"), F.lit(h).alias("h"), F.lit(b).alias("b"), F.col(f"n_{t}").alias("n")) for t, base, h, b in TECHNIQUES])
        return read.select("style", "expl", "text", "a", "c", "f", "s", "n_words", "total", F.inline(times)).where("n > 0")


def weighted(df: DataFrame, n: Column | None = None) -> list[Column]:
    """Means on the 0-4 scale and of the total, in whole ten-thousandths, so that no order of summing shows; a row counts ``n`` times."""
    n = F.lit(1) if n is None else n
    unit = lambda c, w: F.floor(F.sum(F.floor(F.col(c) * w * 10000 + 0.5) * n) / F.sum(n) + 0.5) / 10000
    return [*[unit(c, WEIGHTS[c]).alias(name) for c, name in (("a", "accuracy"), ("c", "completeness"), ("f", "fluency"), ("s", "conciseness"))], unit("total", 1.0).alias("total")]


def technique_scores(grid: DataFrame, n: str | None = None) -> DataFrame:
    """Means by technique; ``n`` names a column that tells how often a row counts."""
    if n is None:
        return grid.groupBy("technique", "base", "h", "b").agg(F.count("*").alias("n"), *weighted(grid))
    return grid.withColumnRenamed(n, "_n").groupBy("technique", "base", "h", "b").agg(F.sum("_n").alias("n"), *weighted(grid, F.col("_n")))


def score_tables(grid: DataFrame) -> DataFrame:
    """Means by technique, by style and by both, in one pass of grouping sets."""
    rows = grid.groupingSets([[F.col("technique")], [F.col("style")], [F.col("technique"), F.col("style")]], "technique", "style")
    return rows.agg(F.count("*").alias("n"), *weighted(grid))


METRICS = (("a", "accuracy"), ("c", "completeness"), ("f", "fluency"), ("s", "conciseness"), ("total", "total"))


def _units(c: str) -> Column:
    """A weighted grade in whole ten-thousandths; sums of them don't depend on their order."""
    return F.floor(F.col(c) * WEIGHTS.get(c, 1.0) * 10000 + 0.5).cast("bigint")


def _deviation(n: Column, s: Column, q: Column, sample: bool) -> Column:
    """Standard deviation from the exact count, sum and sum of squares."""
    left = n * q - s * s
    down = n * (n - 1) if sample else n * n
    return F.when(down > 0, F.sqrt(F.greatest(left, F.lit(0)).cast("double") / down.cast("double")) / 10000.0)


def spread(grid: DataFrame, by: str = "technique", across: str = "style") -> DataFrame:
    """Spread of every metric by ``by``: over narratives, and over the means of the ``across`` groups (population and sample)."""
    sums = [f for c, n in METRICS for f in (F.sum(_units(c)).alias(f"s_{n}"), F.sum((_units(c) * _units(c)).cast("decimal(38,0)")).alias(f"q_{n}"))]
    inner = grid.groupBy(by).agg(F.count("*").alias("n"), *sums)
    dec = lambda c: F.col(c).cast("decimal(38,0)")
    over = [at.half_up(_deviation(dec("n"), dec(f"s_{n}"), dec(f"q_{n}"), False), 4).alias(f"{n}_over_narratives") for _, n in METRICS]
    mean = lambda n: F.floor(F.col(f"s_{n}") / F.col("n") + 0.5).cast("bigint")
    groups = grid.groupBy(by, across).agg(F.count("*").alias("n"), *[F.sum(_units(c)).alias(f"s_{n}") for c, n in METRICS]).select(by, across, *[mean(n).alias(n) for _, n in METRICS])
    outer = groups.groupBy(by).agg(F.count("*").alias("g"), *[f for _, n in METRICS for f in (F.sum(n).alias(f"s_{n}"), F.sum((F.col(n) * F.col(n)).cast("decimal(38,0)")).alias(f"q_{n}"))])
    far = [at.half_up(_deviation(dec("g"), dec(f"s_{n}"), dec(f"q_{n}"), k), 4).alias(f"{n}_{name}") for _, n in METRICS for k, name in ((False, "across"), (True, "across_sample"))]
    return outer.select(by, *far).join(inner.select(by, "n", *over), by)


def best_techniques(scores: DataFrame) -> DataFrame:
    """(metric, technique, score, band) of the best technique of each metric."""
    long = scores.unpivot(["technique"], ["accuracy", "completeness", "fluency", "conciseness", "total"], "metric", "score")
    ranked = long.withColumn("r", F.row_number().over(Window.partitionBy("metric").orderBy(F.desc("score"), "technique"))).where("r = 1")
    return ranked.select("metric", "technique", "score", gr.banded(F.when(F.col("metric") == "total", F.col("score") / 4).otherwise(F.col("score"))).alias("band"))


NAMES = tuple(n for _, n in METRICS)


def heatmap(scores: DataFrame) -> DataFrame:
    """Every metric by H (rows) and B (columns) of the first base prompt."""
    long = scores.where("base = 'plain'").unpivot(["h", "b"], list(NAMES), "metric", "score")
    return long.groupBy("metric", "h").pivot("b", [0, 1, 3, 5]).agg(F.first("score")).select("metric", "h", *[F.col(str(b)).alias(f"b{b}") for b in (0, 1, 3, 5)])


def exemplar_correlations(scores: DataFrame) -> DataFrame:
    """Correlation of each metric with the number of hand-written and of bootstrapped exemplars, over the few-shot techniques."""
    long = scores.where("base = 'plain' AND h > 0").unpivot(["h", "b"], list(NAMES), "metric", "score").withColumn("u", F.floor(F.col("score") * 10000 + 0.5).cast("bigint"))
    by = lambda x: pearson(F.count("*"), F.sum(x), F.sum("u"), F.sum(F.col(x) * F.col(x)), F.sum(F.col("u") * F.col("u")), F.sum(F.col(x) * F.col("u")))
    return long.groupBy("metric").agg(at.half_up(by("h"), 3).alias("with_h"), at.half_up(by("b"), 3).alias("with_b"))


def pearson(n: Column, sx: Column, sy: Column, sxx: Column, syy: Column, sxy: Column) -> Column:
    """Correlation from exact whole-number sums; null where one side never changes."""
    d = lambda c: c.cast("double")
    vx, vy = d(n * sxx - sx * sx), d(n * syy - sy * sy)
    return F.when((vx > 0) & (vy > 0), d(n * sxy - sx * sy) / F.sqrt(vx) / F.sqrt(vy))


def select_base_prompt(scores: DataFrame) -> DataFrame:
    """The base prompt with the fewest words among those that are accurate and complete."""
    from narrative_engine.settings import BASE_PROMPTS

    words = F.create_map(*[F.lit(v) for k, p in BASE_PROMPTS.items() for v in (k, len(p.split()))])
    rows = scores.where("h = 0 AND b = 0").withColumn("words", words[F.col("base")])
    return rows.withColumn("chosen", F.row_number().over(Window.orderBy((F.col("accuracy") + F.col("completeness") >= 7.5).desc(), "words")) == 1).select("base", "words", "accuracy", "completeness", "chosen")


def weight_sensitivity(scores: DataFrame) -> DataFrame:
    """Rank of every technique under several weight vectors (accuracy, completeness, fluency, conciseness)."""
    vectors = {"equal": (1, 1, 1, 1), "correctness": (3, 3, 1, 1), "style": (1, 1, 3, 3), "accuracy": (5, 1, 1, 1), "short": (1, 1, 1, 5)}
    out = None
    for name, w in vectors.items():
        t = sum(F.col(c) * x for c, x in zip(("accuracy", "completeness", "fluency", "conciseness"), w)) / sum(w)
        rows = scores.select(F.lit(name).alias("weights"), "technique", at.half_up(t, 4).alias("score"))
        out = rows if out is None else out.unionByName(rows)
    return out.withColumn("place", F.rank().over(Window.partitionBy("weights").orderBy(F.desc("score"))).cast("bigint"))


def prompt_costs(prompts: DataFrame) -> DataFrame:
    """Estimated tokens and money of each technique's prompts, and how many calls a cache of equal prompts leaves."""
    rows = wr.build_prompt(prompts).select("technique", F.ceil(F.length("prompt") / CHARS).alias("t_in"), F.ceil(F.length("text") / CHARS).alias("t_out"), F.sha2("prompt", 256).alias("h"))
    cost = (F.sum("t_in") * PRICE_IN + F.sum("t_out") * PRICE_OUT) / 1e6
    return rows.groupBy("technique").agg(
        F.count("*").alias("n"), F.min("t_in").alias("tokens_min"), F.max("t_in").alias("tokens_max"), at.half_up(F.avg("t_in"), 1).alias("tokens_mean"),
        at.half_up(cost, 6).alias("usd"), F.countDistinct("h").alias("different_prompts"),
    )


class BudgetGuard:
    """Stops before the calls when their estimate exceeds the budget."""

    def __init__(self, usd: float) -> None:
        self.usd = usd

    def check(self, costs: DataFrame) -> float:
        total = float(costs.agg(F.coalesce(F.sum("usd"), F.lit(0.0))).first()[0])
        if total > self.usd:
            raise RuntimeError(f"estimated {total:.2f} USD; the budget is {self.usd:.2f}")
        return total


# --- validation of the grader ---------------------------------------------------------------------


def validation_set(entries: DataFrame, metric: str) -> DataFrame:
    """Pairs of known truth: explanations in md5 order, each narrated with the edits of its category."""
    cases, at_ = [], 0
    for m, category, grade, n in CATEGORIES:
        if m == metric:
            cases.append((category, grade, at_, at_ + n))
            at_ += n
    order = F.md5(F.concat(F.lit(metric + "|"), "style", F.lit("|"), "row_id").cast("binary"))
    rows = entries.where(F.size("expl") >= 2).orderBy(order, "style", "row_id").limit(at_).withColumn("pair_id", F.row_number().over(Window.orderBy(order, "style", "row_id")) - 1)
    hit = lambda lo, hi: (F.col("pair_id") >= lo) & (F.col("pair_id") < hi)
    category, grade = F.lit(None).cast("string"), F.lit(None).cast("int")
    for name, g, lo, hi in cases:
        category, grade = F.when(hit(lo, hi), name).otherwise(category), F.when(hit(lo, hi), g).otherwise(grade)
    rows = rows.withColumn("category", category).withColumn("human", grade)
    c = F.col("category")
    size = lambda x: F.abs(x["contribution"])
    way = lambda x, flip: F.when((x["contribution"] < 0) != flip, "lowers the output").otherwise("raises the output")

    def sentence(x: Column, i: Column) -> Column:
        first = i == 0
        odd = F.pmod(F.col("pair_id"), F.lit(2)) == 1
        amount = F.when(c == "approximate values", wr.about(size(x))).when((c == "value error") & first, wr.coarse(size(x))).otherwise(ex.number_text(size(x)))
        flip = (c == "direction error") & first
        with_value = ~((c == "value or direction missing") & first & odd) & ~((c == "some values") & ~first)
        with_way = ~((c == "value or direction missing") & first & ~odd)
        with_amount = c.isin("all values", "approximate values", "value error", "everything") | ((c == "some values") & first)
        return F.concat(
            F.lit("The "), x["feature"], F.when(with_value, F.concat(F.lit(" is "), x["value"], F.lit(" and"))).otherwise(F.lit("")),
            F.when(with_way, F.concat(F.lit(" "), way(x, flip))).otherwise(F.lit(" counts")), F.when(with_amount, F.concat(F.lit(" by "), amount)).otherwise(F.lit("")), F.lit("."),
        )

    told = F.when(c == "feature missing", F.slice("expl", 1, F.size("expl") - 1)).otherwise(F.col("expl"))
    return rows.withColumn("text", F.array_join(F.transform(told, sentence), " "))


def graded_pairs(pairs: DataFrame, metric: str, policy=None, error: float = 0.0) -> DataFrame:
    """``pairs`` with the grader's grade; with ``error``, that of a judge whose draws err so often, rounded."""
    policy = policy or (gr.AccuracyPolicy() if metric == "accuracy" else gr.CompletenessPolicy())
    fn = gr.accuracy if metric == "accuracy" else gr.completeness
    rows = pairs.withColumn("claims", gr.claims(F.col("text"), F.col("expl"))).withColumn("grader", fn(F.col("claims"), policy))
    if error:
        top = policy.levels - 1 if metric == "accuracy" else 2
        drawn = gr.mean_draw(gr.draws(F.col("grader"), F.concat_ws("|", F.lit(metric), "style", "row_id"), error, top=top))
        rows = rows.withColumn("grader", F.floor(drawn + 0.5).cast("int"))
    return rows


def grader_correlation(pairs: DataFrame) -> DataFrame:
    """(metric, n, pearson, spearman) of ``pairs`` (metric, human, grader): plain, and of the ranks (mean rank of ties)."""
    rank = lambda c: 2 * F.rank().over(Window.partitionBy("metric").orderBy(c)) + F.count("*").over(Window.partitionBy("metric", c))  # noqa: E731  twice the mean rank plus one
    rows = pairs.select("metric", F.col("human").cast("bigint").alias("x"), F.col("grader").cast("bigint").alias("y"), rank("human").cast("bigint").alias("rx"), rank("grader").cast("bigint").alias("ry"))
    both = lambda x, y: pearson(F.count("*"), F.sum(x), F.sum(y), F.sum(F.col(x) * F.col(x)), F.sum(F.col(y) * F.col(y)), F.sum(F.col(x) * F.col(y)))
    return rows.groupBy("metric").agg(F.count("*").alias("n"), at.half_up(both("x", "y"), 4).alias("pearson"), at.half_up(both("rx", "ry"), 4).alias("spearman"))


def per_class(counts: DataFrame) -> DataFrame:
    """Precision and recall of the grader by class, from (metric, human, grader, n)."""
    hit = counts.where("human = grader").select("metric", F.col("human").alias("class"), F.col("n").alias("hit"))
    said = counts.groupBy("metric", F.col("grader").alias("class")).agg(F.sum("n").alias("said"))
    meant = counts.groupBy("metric", F.col("human").alias("class")).agg(F.sum("n").alias("meant"))
    rows = meant.join(said, ["metric", "class"], "left").join(hit, ["metric", "class"], "left").na.fill(0)
    share = lambda a, b: F.when(F.col(b) > 0, at.half_up(F.col(a) / F.col(b), 4))
    return rows.select("metric", "class", share("hit", "said").alias("precision"), share("hit", "meant").alias("recall"))


def agreement_by_category(df: DataFrame) -> DataFrame:
    return df.groupBy("category").agg(F.count("*").alias("n"), F.sum((F.col("human") == F.col("grader")).cast("int")).alias("agreed"))


def confusion(df: DataFrame, levels: int) -> DataFrame:
    return df.groupBy("human").pivot("grader", list(range(levels))).count().na.fill(0).select("human", *[F.col(str(k)).alias(f"grader_{k}") for k in range(levels)])


def agreement(counts: DataFrame) -> DataFrame:
    """Share of agreement and its chance-corrected form from (metric, human, grader, n)."""
    by = lambda c: counts.groupBy("metric", c).agg(F.sum("n").alias(f"n_{c}"))
    total = counts.groupBy("metric").agg(F.sum("n").alias("all"), F.sum(F.when(F.col("human") == F.col("grader"), F.col("n")).otherwise(0)).alias("same"))
    chance = by("human").join(by("grader"), "metric").where("human = grader").groupBy("metric").agg(F.sum(F.col("n_human") * F.col("n_grader")).alias("x"))
    rows = total.join(chance, "metric")
    share, luck = F.col("same") / F.col("all"), F.col("x") / (F.col("all") * F.col("all"))
    return rows.select("metric", F.col("all").alias("n"), at.half_up(share, 4).alias("agreement"), at.half_up((share - luck) / (1 - luck), 4).alias("kappa"))


def published_confusion(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(PUBLISHED_CONFUSION, "metric string, human int, grader int, n int")


def published_totals(spark: SparkSession) -> DataFrame:
    """Printed and recomputed totals of the published tables."""
    rows = [(f"technique {t[0]}", *t[1:]) for t in PUBLISHED_TECHNIQUES] + list(PUBLISHED_SETS)
    return totals(spark.createDataFrame(rows, "name string, accuracy double, completeness double, fluency double, conciseness double, printed double"), "accuracy", "completeness", "fluency", "conciseness")


def document_totals(documents: DataFrame) -> DataFrame:
    """Printed lengths of documents against the sum of their letters, digits, blanks and the rest."""
    left = lambda cut: F.length(F.regexp_replace("text", cut, "")).cast("double")
    parts = {"letters": "[^A-Za-z]+", "digits": "[^0-9]+", "blanks": "[^ ]+", "rest": "[A-Za-z0-9 ]+"}
    rows = documents.select(F.col("doc_id").cast("string").alias("name"), *[left(cut).alias(p) for p, cut in parts.items()], F.col("n_chars").cast("double").alias("printed"))
    return totals(rows, *parts)


def label_confusion(labels: DataFrame, documents: DataFrame) -> DataFrame:
    """(metric, human, grader, n): labels against what plain rules of the text say."""
    rule = {m: F.when(F.expr(r.replace("regexp_matches(", "regexp_like(")), 1).otherwise(0) for m, r in LABEL_RULES.items()}
    each = F.array(*[F.struct(F.lit(m).alias("metric"), F.col(m).alias("human"), r.alias("grader")) for m, r in rule.items()])
    return labels.join(documents.select("doc_id", "text"), "doc_id").select(F.inline(each)).groupBy("metric", "human", "grader").agg(F.count("*").alias("n"))


def totals(df: DataFrame, *parts: str) -> DataFrame:
    total = sum((F.col(p) for p in parts[1:]), F.col(parts[0]))
    return df.select("name", at.half_up(total, 3).alias("recomputed"), "printed", (F.abs(total - F.col("printed")) <= 0.0015).alias("agrees"))


#: The policies that revision goes through, in the order of the questions' growth.
ACCURACY_POLICIES = {
    "plain question": gr.AccuracyPolicy.plain(), "yes or no": gr.AccuracyPolicy.asked_yes_no(),
    "two points": gr.AccuracyPolicy(allow_omission=False, check_direction=False, stepwise=False), "omission is fine": gr.AccuracyPolicy(check_direction=False, stepwise=False),
    "directions count": gr.AccuracyPolicy(stepwise=False), "step by step": gr.AccuracyPolicy(), "three points": gr.AccuracyPolicy(levels=3),
    "no tolerance": gr.AccuracyPolicy(tolerance=0.0),
}
COMPLETENESS_POLICIES = {"plain question": gr.CompletenessPolicy(per_feature=False), "checklist": gr.CompletenessPolicy(), "contributions required": gr.CompletenessPolicy(require_contrib=True)}


def revise_policy(pairs: DataFrame, metric: str = "accuracy", target: float = 0.95) -> DataFrame:
    """Agreement of every policy on the same pairs, in one scan; the first that reaches ``target`` is chosen, else the best."""
    known = ACCURACY_POLICIES if metric == "accuracy" else COMPLETENESS_POLICIES
    fn = gr.accuracy if metric == "accuracy" else gr.completeness
    told = []
    for k, (name, policy) in enumerate(known.items()):
        read = gr.claims(F.col("text"), F.col("expl"), gr.Reading(getattr(policy, "tolerance", gr.TOLERANCE)))
        g = fn(read, policy)
        g = F.when(g > 0, 1).otherwise(0) if getattr(policy, "levels", 2) == 3 else g  # misleading counts as accurate
        told.append(F.struct(F.lit(k).alias("place"), F.lit(name).alias("policy"), (g == F.col("human")).cast("int").alias("ok")))
    rows = pairs.select(F.inline(F.array(*told))).groupBy("place", "policy").agg(F.count("*").alias("n"), F.sum("ok").alias("agreed"))
    rows = rows.withColumn("reached", F.col("agreed") >= target * F.col("n"))
    order = Window.orderBy(F.desc("reached"), F.when(F.col("reached"), 0).otherwise(-F.col("agreed")), "place")  # a row per policy
    return rows.withColumn("chosen", F.row_number().over(order) == 1)


#: Draws of the exemplars for each number of them.
GAP_DRAWS = 5


def style_gap(vectors: DataFrame, sizes: tuple[int, ...] = (1, 2, 3, 4), terms: tuple[str, ...] = ("surface",), draws: int = GAP_DRAWS) -> DataFrame:
    """Own and hardest other fluency by number of exemplars: ``vectors`` has style, k (from 1) and v.

    For each number and draw, exemplars are taken by chance (md5 of the draw), and the rest of a style
    is judged against every style's centre (a few broadcast rows).
    """
    key = F.md5(F.concat_ws("|", F.col("n").cast("string"), F.col("draw").cast("string"), "style", F.col("k").cast("string")).cast("binary"))
    cases = F.explode(F.array(*[F.struct(F.lit(n).alias("n"), F.lit(d).alias("draw")) for n in sizes for d in range(1, draws + 1)]))
    rows = vectors.withColumn("_c", cases).select("style", "k", "v", "_c.*").withColumn("place", F.row_number().over(Window.partitionBy("n", "draw", "style").orderBy(key, "k")))
    picked = rows.where("place <= n").withColumn("_g", F.concat_ws("|", F.col("n").cast("string"), F.col("draw").cast("string"), "style"))
    centre = gr.centroid(picked, "_g", terms).select(F.split("_g", r"\|").alias("p"), "centre").select(F.col("p")[0].cast("int").alias("n"), F.col("p")[1].cast("int").alias("draw"), F.col("p")[2].alias("against"), "centre")
    judged = rows.where("place > n").join(F.broadcast(centre), ["n", "draw"]).withColumn("f", gr.fluency(F.col("v"), F.col("centre")))
    own = judged.where("style = against").groupBy("n", "draw", "style").agg(F.sum("f").alias("own"), F.count("*").alias("m"))
    other = judged.where("style <> against").groupBy("n", "draw", "style", "against").agg(F.sum("f").alias("o")).groupBy("n", "draw", "style").agg(F.max("o").alias("other"))
    unit = lambda c: F.floor(F.col(c) * 10000 / F.col("m") + 0.5).cast("bigint")
    gaps = own.join(other, ["n", "draw", "style"]).select("n", unit("own").alias("own"), unit("other").alias("other")).withColumn("gap", F.col("own") - F.col("other"))
    mean = lambda c: (F.floor(F.sum(c) / F.count("*") + 0.5) / 10000).alias(c)
    return gaps.groupBy("n").agg(mean("own"), mean("other"), mean("gap"), (F.min("gap") / 10000).alias("worst"))


def enough_exemplars(gaps: DataFrame, least: float = 0.05) -> DataFrame:
    """``gaps`` with what one step more brings, and the number from which no further step brings ``least``."""
    order = Window.orderBy("n")  # a row per number of exemplars
    rows = gaps.withColumn("gain", at.half_up(F.col("gap") - F.lag("gap").over(order), 4))
    last = F.max(F.when(F.col("gain") >= least, F.col("n"))).over(Window.partitionBy())
    return rows.withColumn("enough", F.col("n") == F.coalesce(last, F.min("n").over(Window.partitionBy())))


def evaluated_count() -> int:
    return sum(n - SET_ASIDE for _, n, _ in STYLES.values()) * len(TECHNIQUES)
