"""The user's side: samples of a style in, narratives keyed by row out; and the steps of a new application."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.ml import Transformer
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.operators import explanation as ex
from narrative_engine.operators import grading as gr
from narrative_engine.operators import samples as sp
from narrative_engine.operators import writing as wr
from narrative_engine.operators.claims import Reading
from narrative_engine.settings import DEFAULT_EXEMPLARS, WEIGHTS

EXPL = "array<struct<feature:string,value:string,value_num:double,contribution:double>>"


def exemplar_column(found: list[sp.Exemplar]) -> Column:
    clause = lambda c: F.struct(F.lit(c.slots).alias("c"), F.lit(c.up).alias("up"), F.lit(c.down).alias("down"))
    one = lambda e: F.struct(
        F.lit(e.ex).alias("ex"), F.lit(e.expl_text).alias("expl_text"), F.lit(e.text).alias("text"), F.lit(e.lead).alias("lead"), F.lit(e.joiner).alias("joiner"), F.lit(e.tail).alias("tail"),
        F.lit(e.omits).alias("omits"), F.array(*map(clause, e.clauses)).alias("clauses"),
    )
    return F.array(*map(one, found))


class NarrativePipeline(Transformer):
    """Turns explanations into narratives in the style of a few samples.

    ``samples``: pairs of an explanation as text, ``(feature, value, contribution), ...`` or one bare
    triple, and the narrative a user wrote for it.  Each row draws up to ``exemplars`` of them.
    """

    def __init__(self, num_features: int = 3, context: str = "", samples: list[tuple[str, str]] = (), weights: dict[str, float] = WEIGHTS, exemplars: int = DEFAULT_EXEMPLARS, base: str = "plain", reading: Reading = Reading()) -> None:
        super().__init__()
        self.num_features, self.context, self.weights, self.exemplars, self.base, self.reading = num_features, context, weights, exemplars, base, reading
        self.samples = list(samples)
        self.derived = [sp.derived(str(k + 1), expl, text) for k, (expl, text) in enumerate(self.samples)]

    def _transform(self, df: DataFrame) -> DataFrame:
        """``df`` (row_id and ``attr``, or ``expl``) with ``expl`` and ``text``."""
        rows = ex.top_contributions(df, self.num_features) if "attr" in df.columns else df
        if not self.derived:
            return rows.withColumn("text", wr.zero_shot(F.col("expl"), self.base))
        keyed = F.transform(exemplar_column(self.derived), lambda x: F.struct(F.md5(F.concat(F.col("row_id"), F.lit("|"), x["ex"]).cast("binary")).alias("k"), x.alias("x")))
        mine = F.transform(F.slice(F.array_sort(keyed), 1, min(self.exemplars, len(self.derived))), lambda s: s["x"])
        return rows.withColumn("exemplars", mine).withColumn("text", wr.realized(F.col("expl"), F.col("exemplars")))

    def prompts(self, df: DataFrame) -> DataFrame:
        """What a hosted model would get: the samples as pairs, the explanation, its format and the context."""
        rows = self.transform(df)
        rows = rows if "exemplars" in rows.columns else rows.withColumn("exemplars", F.array().cast(f"array<{wr.EX}>"))
        prompt = wr.build_prompt(rows.withColumn("base", F.lit(self.base)).withColumn("domain", F.lit("")))
        return prompt.withColumn("prompt", F.replace(F.col("prompt"), F.lit("Context: "), F.lit(f"Context: {self.context}")))

    def to_mapping(self, df: DataFrame) -> DataFrame:
        """(row_id, narrative)."""
        return self.transform(df).select("row_id", F.col("text").alias("narrative"))

    def references(self, spark: SparkSession) -> DataFrame:
        """Centre and concise length of the samples themselves."""
        rows = spark.createDataFrame([("own", k + 1, e, t) for k, (e, t) in enumerate(self.samples)], "style string, place int, e string, text string")
        rows = rows.withColumn("expl", ex.parse_explanation("e"))
        return gr.style_references(rows, gr.FluencyPolicy(k=self.exemplars)).join(gr.derive_longest(rows), "style")

    def graded(self, df: DataFrame) -> DataFrame:
        rows = self.transform(df).withColumn("style", F.lit("own"))
        return gr.graded(rows, self.references(df.sparkSession), weights=self.weights, reading=self.reading)

    def guarded(self, df: DataFrame, least: float, per_metric: dict[str, float] | None = None) -> DataFrame:
        return gr.guarded(self.graded(df), least, per_metric)


class NewApplication:
    """The steps for a new model: seeds, samples, weights, narratives, guard."""

    def __init__(self, explained: DataFrame, context: str, num_features: int = 3) -> None:
        self.explained, self.context, self.num_features = explained, context, num_features
        self.pipeline: NarrativePipeline | None = None

    def seeds(self, k: int = DEFAULT_EXEMPLARS) -> DataFrame:
        """Explanations of ``k`` different kinds, for the user to narrate."""
        return ex.pick_diverse(self.explained, k)

    def seed_texts(self, k: int = DEFAULT_EXEMPLARS) -> list[tuple[str, str]]:
        """(row_id, explanation as text) of the seeds: a handful of rows, for the user to read."""
        rows = self.seeds(k).join(self.explained.select("row_id", "expl"), "row_id").select("row_id", ex.serialize_explanation("expl").alias("t"), "n", "signature")
        return [(r["row_id"], r["t"]) for r in rows.orderBy(F.desc("n"), "signature").collect()]

    def narrated(self, author: Callable[[str], str] | dict[str, str], weights: dict[str, float] = WEIGHTS, k: int = DEFAULT_EXEMPLARS) -> NarrativePipeline:
        """The pipeline that the user's narratives (by explanation text) make."""
        write = author if callable(author) else author.__getitem__
        pairs = [(t, write(t)) for _, t in self.seed_texts(k)]
        self.pipeline = NarrativePipeline(self.num_features, self.context, pairs, weights)
        return self.pipeline

    def shown(self, least: float | None = None) -> DataFrame:
        """row_id and what stakeholders see; with ``least``, narratives under it are withheld."""
        if self.pipeline is None:
            raise ValueError("narrate the seeds first")
        if least is None:
            return self.pipeline.to_mapping(self.explained).withColumnRenamed("narrative", "shown")
        return self.pipeline.guarded(self.explained, least).select("row_id", "shown", "rejected")
