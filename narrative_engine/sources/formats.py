"""Formats around the engine: exemplars and prompts as JSON, CSV and text, partitioned results, and a data source of the authored styles."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from narrative_engine.fixtures import CLAUSES
from narrative_engine.operators.attribution import half_up
from narrative_engine.operators.writing import filled
from narrative_engine.plans.twins import filled as filled_sql
from narrative_engine.plans.twins import quoted
from narrative_engine.shipping import ship
from narrative_engine.sources.tables import table
from narrative_engine.staging import kept_until_exit, shared_dir


def folder(spark: SparkSession, kind: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{kind}-{uuid.uuid4().hex}"


def through(df: DataFrame, kind: str, **options: str) -> DataFrame:
    """``df`` written in a format and read back with its schema."""
    spark, path = df.sparkSession, folder(df.sparkSession, kind)
    df.write.format(kind).options(**options).save(path)
    return spark.read.format(kind).schema(df.schema).options(**options).load(kept_until_exit(spark, path))


def source_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return through(table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text"), "json")


def source_csv(spark: SparkSession, sf_dir: str) -> DataFrame:
    return through(table(spark, sf_dir, "customer").select("c_custkey", "c_name", "c_mktsegment"), "csv", header="true")


def source_orc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return through(table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_size"), "orc")


def source_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines of benchmark items; a text file holds one string a line."""
    lines = table(spark, sf_dir, "benchmark").select(F.concat_ws("\t", F.col("item_id").cast("string"), F.regexp_replace("text", "\\s+", " ")).alias("value"))
    parts = F.split("value", "\t")
    return through(lines, "text").select(parts[0].alias("item"), F.length(parts[1]).alias("n"))


def sink_partitioned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders written by status and read for one of them: the others' folders are never opened."""
    path = folder(spark, "parts")
    table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(kept_until_exit(spark, path)).where("o_orderstatus = 'F'").select("o_orderkey", "o_custkey")


def prompt_log(prompts: DataFrame, path: str) -> None:
    """Prompts as JSON lines, each different one once, by hash."""
    prompts.select(F.sha2("prompt", 256).alias("prompt_hash"), "prompt").dropDuplicates(["prompt_hash"]).write.mode("append").json(path)


class _Styles(DataSourceReader):
    def __init__(self, options: dict[str, str]) -> None:
        self.options = options

    def partitions(self) -> list[InputPartition]:
        from narrative_engine.fixtures import CLAUSES

        return [InputPartition(s) for s in sorted(CLAUSES) if self.options.get("domain", "") in ("", s.rpartition("_")[0])]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        from narrative_engine.fixtures import CLAUSES

        for k, (slots, flaw) in enumerate(CLAUSES[partition.value]):
            yield partition.value, k + 1, slots, flaw


class StyleSource(DataSource):
    """``spark.read.format("narrative_fixture").option("domain", ...)``: the authored slot texts, a partition per style."""

    @classmethod
    def name(cls) -> str:
        return "narrative_fixture"

    def schema(self) -> str:
        return "style string, place int, slots string, flaw string"

    def reader(self, schema) -> DataSourceReader:
        return _Styles(dict(self.options))


def source_fixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The source's slot texts of orders, each told of the orders whose key picks its place: orders and characters of their clauses."""
    ship(spark)
    spark.dataSource.register(StyleSource)
    styles = spark.read.format("narrative_fixture").option("domain", "basket").load()
    orders = table(spark, sf_dir, "orders")
    mean = orders.agg((F.sum(F.col("o_totalprice").cast("decimal(18,4)")).cast("double") / F.count("o_totalprice")).alias("mean"))
    x = F.struct(F.lit("priority").alias("feature"), F.col("o_orderpriority").alias("value"), half_up(F.col("o_totalprice") - F.col("mean")).alias("contribution"))
    rows = orders.crossJoin(F.broadcast(mean)).select((F.col("o_orderkey") % len(CLAUSES["basket_a"]) + 1).cast("int").alias("place"), x.alias("x"))
    clause = F.struct(F.col("slots").alias("c"), F.lit("raises").alias("up"), F.lit("lowers").alias("down"))
    told = rows.join(F.broadcast(styles), "place").withColumn("n_chars", F.length(filled(F.col("x"), clause)))
    return told.groupBy("style", "place", "slots", "flaw").agg(F.count("*").alias("n"), F.sum("n_chars").alias("n_chars"))


def _fixture_sql() -> str:
    styles = ", ".join(f"({quoted(s)}, {k + 1}, {quoted(c)}, {quoted(flaw)})" for s, own in CLAUSES.items() if s.startswith("basket_") for k, (c, flaw) in enumerate(own))
    return f"""WITH st(style, place, slots, flaw) AS (VALUES {styles}),
m AS (SELECT sum(CAST(o_totalprice AS DECIMAL(18,4)))::DOUBLE / count(o_totalprice) AS mean FROM orders),
o AS (SELECT o_orderkey % {len(CLAUSES['basket_a'])} + 1 AS place, 'priority' AS feature, o_orderpriority AS value, floor((o_totalprice - mean) * 100.0::DOUBLE + 0.5) / 100.0::DOUBLE AS contribution FROM orders, m)
SELECT style, st.place, slots, flaw, count(*) AS n, CAST(sum(length({filled_sql('slots', "'raises'", "'lowers'")})) AS BIGINT) AS n_chars FROM o JOIN st ON st.place = o.place GROUP BY style, st.place, slots, flaw"""


QUERIES = {"source_json": source_json, "source_csv": source_csv, "source_orc": source_orc, "source_text": source_text, "sink_partitioned": sink_partitioned, "source_fixture": source_fixture}
ORACLES = {
    "source_json": "SELECT conv_id, turn, role, text FROM conversations",
    "source_csv": "SELECT c_custkey, c_name, c_mktsegment FROM customer",
    "source_orc": "SELECT p_partkey, p_name, p_size FROM part",
    "source_text": "SELECT CAST(item_id AS VARCHAR) AS item, CAST(length(regexp_replace(text, '\\s+', ' ', 'g')) AS INT) AS n FROM benchmark",
    "sink_partitioned": "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus = 'F'",
    "source_fixture": _fixture_sql(),
}
