"""The function surface: SQL functions that Catalyst inlines, an Arrow function, an aggregate and a table function."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.plans import experiments as xp
from narrative_engine.plans import twins
from narrative_engine.shipping import ship
from narrative_engine.sources.tables import table

#: name -> (parameters, type, body)
SQL_FUNCTIONS = {
    "word_count": ("t STRING", "INT", "size(regexp_extract_all(t, '[^ \\\\t\\\\n\\\\r]+', 0))"),
    "conciseness_grade": (
        "words DOUBLE, features DOUBLE, longest DOUBLE", "DOUBLE",
        "CASE WHEN features * longest <= 0 OR words >= 2 * features * longest THEN 0D WHEN words <= features * longest THEN 4D ELSE 4D * (2D - words / (features * longest)) END",
    ),
    "total_grade": ("a DOUBLE, c DOUBLE, f DOUBLE, s DOUBLE", "DOUBLE", "4D * a + 2D * c + f + s"),
}


def register(spark: SparkSession) -> None:
    for name, (parameters, kind, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {kind} RETURN {body}")


def udf_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark)
    table(spark, sf_dir, "documents").createOrReplaceTempView("documents")
    return spark.sql("SELECT doc_id, word_count(text) AS n_words, floor(conciseness_grade(word_count(text), 3, 60) * 1000 + 0.5) / 1000 AS s, floor(total_grade(1, 2, 4, conciseness_grade(word_count(text), 3, 60)) * 1000 + 0.5) / 1000 AS total FROM documents")


def _longest_word(text: pd.Series) -> pd.Series:
    return text.map(lambda t: max((len(w) for w in re.split("[ \t\n\r]+", t)), default=0))


def udf_arrow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A vectorised Python function, to show the surface; built-in functions do the same in the JVM."""
    ship(spark)
    longest = F.pandas_udf(_longest_word, "bigint")
    return table(spark, sf_dir, "conversations").select("conv_id", "turn", longest("text").alias("longest"))


def _consistency(n: pd.Series) -> float:
    return float(n.max()) / float(n.sum())


def udaf_consistency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of the commonest value; values are counted first, so the aggregate gets a row per different value and never a language's rows."""
    ship(spark)
    rows = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id").groupBy("lang", "quality").agg(F.count("*").alias("n"))
    return rows.groupBy("lang").agg(F.pandas_udf(_consistency, "double")("n").alias("share")).select("lang", (F.floor(F.col("share") * 1000 + 0.5) / 1000).alias("share"))


class Tuples:
    """Rows of a serialised explanation."""

    def eval(self, text: str):
        for m in re.finditer(r"\(([^()]*), ([^(),]*), (-?[0-9.]+)\)", text or ""):
            yield m[1], m[2], float(m[3])


def udtf_claims(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table function, to show the surface; ``parse_explanation`` does the same in the JVM."""
    ship(spark)
    spark.udtf.register("tuples", F.udtf(Tuples, returnType="feature string, value string, contribution double"))
    xp.explanations(spark, sf_dir, "spend").createOrReplaceTempView("spend_explanations")
    return spark.sql("SELECT row_id, t.feature, t.contribution FROM spend_explanations, LATERAL tuples(expl_text) t")


QUERIES = {"udf_sql": udf_sql, "udf_arrow": udf_arrow, "udaf_consistency": udaf_consistency, "udtf_claims": udtf_claims}
_S = "CASE WHEN n >= 360 THEN 0.0::DOUBLE WHEN n <= 180 THEN 4.0::DOUBLE ELSE 4.0::DOUBLE * (2.0::DOUBLE - n / 180.0::DOUBLE) END"
ORACLES = {
    "udf_sql": f"WITH w AS (SELECT doc_id, len(regexp_extract_all(text, '[^ \\t\\n\\r]+'))::INT AS n FROM documents) SELECT doc_id, n AS n_words, floor({_S} * 1000 + 0.5) / 1000 AS s, floor((12.0::DOUBLE + {_S}) * 1000 + 0.5) / 1000 AS total FROM w",
    "udf_arrow": "SELECT conv_id, turn, coalesce(list_max(list_transform(string_split_regex(text, '[ \\t\\n\\r]+'), lambda x: length(x))), 0)::BIGINT AS longest FROM conversations",
    "udaf_consistency": "WITH c AS (SELECT lang, quality, count(*) AS n FROM documents d JOIN labels l ON l.doc_id = d.doc_id GROUP BY lang, quality) SELECT lang, floor(max(n)::DOUBLE / sum(n)::DOUBLE * 1000 + 0.5) / 1000 AS share FROM c GROUP BY lang",
    "udtf_claims": f"WITH {twins.top_ctes('spend')}\nSELECT row_id, feature, contribution FROM top",
}
