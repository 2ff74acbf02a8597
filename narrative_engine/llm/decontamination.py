"""Benchmark decontamination as a prefix-filtered set join, in built-in functions only.

A document is hit where it contains an item's window: 13 consecutive words of the item, or the
whole item when it is shorter.  Containment is asked for in full, so one word of a window is a
necessary prefix: the rarest over all documents.  Documents meet windows on that word alone;
the word's offset then fixes where the window would have to start and end (position and length
bounds), and what passes is compared word for word.

Windows are broadcast only while the benchmark stays under ``BROADCAST_WINDOWS``; documents are then
never shuffled.  Beyond it their words meet the windows by a shuffle of places and hashes alone, and
the texts are moved once, to be compared where a window may start.

Defined results: null texts have no words; items without words are never found; repeated rows
each give their own equal row; an empty benchmark leaves every document clean, and an empty
table gives no rows.  Only ``doc_id``, ``text``, ``item_id`` are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.llm.common import let, lower_ascii, staged, table

ITEM_WINDOW = 13
BROADCAST_WINDOWS = 200_000
BROADCAST_HITS = 200_000
#: All characters that are no word characters (a fixed value of the contract).
BETWEEN = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def raw_words(text: Column) -> Column:
    """Lowered words; an empty string may stand first and last, which no window holds.

    No lambda, and an outer generator (an inner one infers a filter that splits the text again): an operator that has one leaves whole-stage code, and the rows between it and the
    generator would each be given a copy of the array.
    """
    return F.split(lower_ascii(F.coalesce(text, F.lit(""))), BETWEEN)


def count_words(raw: Column) -> Column:
    edge = lambda i: F.when(F.element_at(raw, i) == "", 1).otherwise(0)
    return F.when(F.size(raw) == 1, 1 - edge(1)).otherwise(F.size(raw) - edge(1) - edge(-1)).cast("long")


def windows(benchmark: DataFrame) -> DataFrame:
    """Each different window once: its words and the items that hold it."""
    words = F.filter(raw_words(F.col("text")), lambda w: w != "")
    cut = lambda w: F.transform(
        F.sequence(F.lit(0), F.greatest(F.size(w) - ITEM_WINDOW, F.lit(0))), lambda i: F.slice(w, i + 1, ITEM_WINDOW)
    )
    items = benchmark.where(F.col("item_id").isNotNull()).select(F.col("item_id").cast("string").alias("item_id"), words.alias("words")).where(F.size("words") > 0)
    return (
        items.select("item_id", F.explode(let(F.col("words"), cut)).alias("window"))
        .groupBy("window")
        .agg(F.collect_set("item_id").alias("items"))
    )


def occurrences(docs: DataFrame, *carry: Column) -> DataFrame:
    """One row per word: ``at`` is its place in the document's words; ``carry`` may name ``raw``, the words."""
    rows = docs.select("doc_id", F.xxhash64("text").alias("text_key"), raw_words(F.col("text")).alias("raw"))
    rows = rows.select("doc_id", "text_key", *carry, F.posexplode_outer("raw").alias("at", "word"))
    return rows.withColumn("word_key", F.xxhash64("word")).drop("word")


def prefixed(found: DataFrame, docs: DataFrame, small: bool) -> DataFrame:
    """Windows with the key and the offset of their rarest word, counted over all documents."""
    hint = F.broadcast if small else (lambda x: x)
    asked = found.select(F.explode("window").alias("word")).select(F.xxhash64("word").alias("word_key")).distinct()
    seen = occurrences(docs).select("word_key").join(hint(asked), "word_key").groupBy("word_key").agg(F.count("*").alias("n"))
    places = found.select("*", F.posexplode("window").alias("offset", "word")).withColumn("word_key", F.xxhash64("word"))
    rarest = (
        places.join(seen, "word_key")
        .groupBy("window")
        .agg(F.min(F.struct("n", "word_key", "offset")).alias("first"), F.count("*").alias("known"), F.first("items").alias("items"))
        .where(F.col("known") == F.size("window"))  # a word that no document has rules its windows out
    )
    told = F.array_join("window", " ").alias("window")  # words hold no blank
    return rarest.select(told, F.size("window").alias("n"), "items", F.col("first.word_key").alias("word_key"), F.col("first.offset").alias("offset"))


def starts_at(raw: Column, start: Column, n: Column, window: Column) -> Column:
    fits = (start >= 0) & (start + n <= F.size(raw))
    return fits & (F.array_join(F.slice(raw, F.when(fits, start + 1).otherwise(1), n), " ") == window)


def hits(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Verified occurrences: document, first word, length, items."""
    few = docs.sparkSession.sparkContext.defaultParallelism  # files of tables that are as large as the benchmark
    found = staged(windows(benchmark), few)
    small = found.count() <= BROADCAST_WINDOWS
    keyed = staged(prefixed(found, docs, small), few)
    start = F.col("at") - F.col("offset")
    if small:
        met = occurrences(docs, F.col("raw")).join(F.broadcast(keyed), "word_key").where(starts_at(F.col("raw"), start, F.col("n"), F.col("window")))
        return met.select("doc_id", "text_key", start.alias("start"), "n", "items")
    met = occurrences(docs, F.size("raw").alias("all")).join(keyed, "word_key").where((start >= 0) & (start + F.col("n") <= F.col("all")))
    asked = met.groupBy("doc_id", "text_key").agg(F.collect_set(F.struct(start.alias("start"), "n", "window", "items")).alias("asked"))
    asked = staged(asked.select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key"), "asked"))
    texts = docs.select("doc_id", F.xxhash64("text").alias("text_key"), "text").join(asked, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_key") == F.col("_key")))
    true = let(raw_words(F.col("text")), lambda raw: F.filter("asked", lambda x: starts_at(raw, x["start"], x["n"], x["window"])))
    return texts.select("doc_id", "text_key", F.inline(true)).select("doc_id", "text_key", "start", "n", "items")


def covered(spans: Column) -> Column:
    """Places in the union of (start, n) spans."""
    zero = F.struct(F.lit(0).alias("end"), F.lit(0).alias("sum"))
    def step(acc: Column, x: Column) -> Column:
        end = x["start"] + x["n"]
        more = F.greatest(F.lit(0), end - F.greatest(acc["end"], x["start"]))
        return F.struct(F.greatest(acc["end"], end).alias("end"), (acc["sum"] + more).alias("sum"))

    return F.aggregate(F.sort_array(spans), zero, step, lambda acc: acc["sum"]).cast("long")


def contamination(docs: DataFrame, benchmark: DataFrame, *keep: str) -> DataFrame:
    """One row per document with its hit words, items and verdict."""
    per_doc = (
        hits(docs, benchmark)
        .groupBy("doc_id", "text_key")
        .agg(F.collect_set(F.struct("start", "n")).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("found"))
        .select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key"), covered(F.col("spans")).alias("n_hit"), "found")
    )
    per_doc = staged(per_doc, docs.sparkSession.sparkContext.defaultParallelism)
    per_doc = F.broadcast(per_doc) if per_doc.count() <= BROADCAST_HITS else per_doc
    rows = docs.select("doc_id", *keep, F.xxhash64("text").alias("text_key"), raw_words(F.col("text")).alias("raw"))
    rows = rows.select("doc_id", *keep, "text_key", count_words(F.col("raw")).alias("n_words"))
    joined = rows.join(per_doc, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_key") == F.col("_key")), "left")
    n_hit, items = F.coalesce("n_hit", F.lit(0)).cast("long"), F.coalesce("found", F.array().cast("array<string>"))
    return joined.select(
        "doc_id", *keep, "n_words", n_hit.alias("n_hit"), F.size(items).cast("long").alias("n_items"),
        F.sha2(F.array_join(items, ","), 256).alias("items_sha256"),
        ((n_hit > 0) & (20 * n_hit >= F.col("n_words"))).alias("contaminated"), items.alias("items"),
    )


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("items")


ORACLE = r"""
WITH d AS (
  SELECT row_number() OVER () AS k, doc_id,
         regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents),
b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark),
v AS (
  SELECT DISTINCT item_id, least(len(w), 13) AS n, array_to_string(w[i:i+12], ' ') AS g
  FROM (SELECT *, unnest(range(1, greatest(len(w) - 12, 1) + 1)) AS i FROM b WHERE len(w) > 0)),
p AS (
  SELECT k, n, i, array_to_string(w[i:i+n-1], ' ') AS g
  FROM (SELECT k, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d, (SELECT DISTINCT n FROM v) WHERE len(w) >= n)),
h AS (SELECT p.k, p.i, p.n, v.item_id FROM p JOIN v ON p.n = v.n AND p.g = v.g),
c AS (SELECT k, count(DISTINCT i + o) AS n_hit FROM h, range(13) AS t(o) WHERE o < n GROUP BY k),
s AS (SELECT k, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS items
      FROM (SELECT DISTINCT k, item_id::VARCHAR AS item_id FROM h) GROUP BY k)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(items, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN c USING (k) LEFT JOIN s USING (k)
"""
