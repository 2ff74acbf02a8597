"""Tables and the feature frames of the five domains.

The frames are SQL that Spark and DuckDB both accept.  Every numeric feature is DECIMAL(18,4), every
categorical one a string, the target DECIMAL(18,4): sums of decimals don't depend on their order, so
fitted effects are the same whatever the partitions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    for name in names or NAMES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def query(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    """``sql`` over the tables it names."""
    views(spark, sf_dir, *[n for n in NAMES if n in sql])
    return spark.sql(sql)


_D = "CAST({} AS DECIMAL(18,4))"


def _dec(expr: str, name: str) -> str:
    return f'CAST({expr} AS DECIMAL(18,4)) AS {name}'


INSULTS = "idiot|stupid|moron|loser|clown|scum|trash|worthless|pathetic|disgusting"

#: Plain rules that stand for a grader of the labels, in SQL that both engines accept.
LABEL_RULES = {
    "toxic": f"regexp_matches(lower(text), '(^|[^a-z])({INSULTS})([^a-z]|$)')",
    "quality": "length(text) >= 200 AND length(text) - length(replace(text, '|', '')) <= 5 AND length(text) - length(replace(text, '!', '')) <= 5",
}

FEATURES = {
    # lines are summed per order before anything is joined
    "basket": f"""
WITH l AS (
  SELECT l_orderkey, count(*) AS n, sum(CAST(l_quantity AS DECIMAL(12,2))) AS q, sum(CAST(l_discount AS DECIMAL(12,4))) AS d, sum(CAST(l_tax AS DECIMAL(12,4))) AS t,
         count(DISTINCT l_partkey) AS p, count(DISTINCT l_suppkey) AS s, sum(CAST(l_extendedprice AS DECIMAL(12,2))) AS v, min(CAST(l_shipdate AS DATE)) AS shipped
  FROM lineitem GROUP BY l_orderkey)
SELECT CAST(l_orderkey AS STRING) AS row_id, {_dec("n", "line_count")}, {_dec("q", "quantity")},
  {_dec("floor(CAST(d AS DOUBLE) / n * 10000 + 0.5) / 10000", "mean_discount")}, {_dec("floor(CAST(t AS DOUBLE) / n * 10000 + 0.5) / 10000", "mean_tax")},
  {_dec("p", "parts")}, {_dec("s", "suppliers")}, {_dec("datediff('day', CAST(o_orderdate AS DATE), shipped)", "ship_lag")}, {_dec("c_acctbal", "balance")},
  o_orderpriority AS priority, o_orderstatus AS status, c_mktsegment AS segment, r_name AS region, {_dec("v", "target")}
FROM l JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey
""",
    "toxic": f"""
SELECT CAST(d.doc_id AS STRING) AS row_id, lang AS language, source,
  CASE WHEN n_chars < 800 THEN 'short' WHEN n_chars < 3000 THEN 'medium' ELSE 'long' END AS length,
  CASE WHEN length(text) - length(replace(text, '!', '')) > 5 THEN 'loud' ELSE 'calm' END AS punctuation,
  CASE WHEN 2 * length(regexp_replace(text, '[^A-Z]', '', 'g')) > n_chars THEN 'shouting' ELSE 'normal' END AS letter_case,
  CASE WHEN length(text) - length(replace(text, '|', '')) > 5 THEN 'table' ELSE 'prose' END AS repetition,
  CASE WHEN regexp_like(lower(text), '(^|[^a-z])({INSULTS})([^a-z]|$)') THEN 'yes' ELSE 'no' END AS insult_word,
  CASE WHEN text LIKE '%http%' THEN 'yes' ELSE 'no' END AS web_link, {_dec("toxic", "target")}
FROM documents d JOIN labels l ON l.doc_id = d.doc_id
""",
    "junk": f"""
WITH m AS (
  SELECT d.doc_id, quality, length(text) AS n, size(regexp_extract_all(text, '[^ \\t\\n\\r]+', 0)) AS w, length(text) - length(replace(text, '\n', '')) + 1 AS k,
    length(regexp_replace(text, '[^A-Z]', '', 'g')) AS u, length(regexp_replace(text, '[^0-9]', '', 'g')) AS g, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS s,
    length(text) - length(replace(text, '!', '')) AS e, length(regexp_replace(text, '[ \\t\\n\\r]', '', 'g')) AS c,
    length(regexp_replace(text, '[A-Za-zÀ-ÿ]', '', 'g')) AS x, repeated_lines(text) AS r
  FROM documents d JOIN labels l ON l.doc_id = d.doc_id)
SELECT CAST(doc_id AS STRING) AS row_id, {_dec("n", "characters")}, {_dec("w", "word_count")}, {_dec("k", "line_count")},
  {_dec("floor(CAST(c AS DOUBLE) / greatest(w, 1) * 1000 + 0.5) / 1000", "word_length")}, {_dec("floor(CAST(u AS DOUBLE) / greatest(n, 1) * 1000 + 0.5) / 1000", "upper_share")},
  {_dec("floor(CAST(g AS DOUBLE) / greatest(n, 1) * 1000 + 0.5) / 1000", "digit_share")}, {_dec("floor(CAST(s AS DOUBLE) / greatest(n, 1) * 1000 + 0.5) / 1000", "symbol_share")},
  {_dec("e", "exclamations")}, {_dec("floor(CAST(x AS DOUBLE) / greatest(n, 1) * 1000 + 0.5) / 1000", "nonletter_share")}, {_dec("r", "repeated_lines")}, {_dec("1 - quality", "target")}
FROM m
""",
    "spend": f"""
WITH o AS (
  SELECT o_custkey, count(*) AS n, count(DISTINCT date_trunc('month', o_orderdate)) AS m, count(DISTINCT o_orderpriority) AS p, sum(CAST(o_totalprice AS DECIMAL(12,2))) AS v,
         max(CASE WHEN o_orderpriority LIKE '1%' THEN 1 ELSE 0 END) AS urgent, max(CASE WHEN o_orderstatus = 'O' THEN 1 ELSE 0 END) AS open
  FROM orders GROUP BY o_custkey),
a AS (SELECT CAST(avg(CAST(v AS DOUBLE)) AS DECIMAL(18,2)) AS mean FROM o)
SELECT CAST(c_custkey AS STRING) AS row_id, {_dec("n", "order_count")}, {_dec("m", "active_months")}, {_dec("p", "priorities")}, c_mktsegment AS market_segment, n_name AS home_nation,
  r_name AS home_region, CASE WHEN c_acctbal > 0 THEN 'yes' ELSE 'no' END AS positive_balance, CASE WHEN urgent = 1 THEN 'yes' ELSE 'no' END AS urgent_order,
  CASE WHEN open = 1 THEN 'yes' ELSE 'no' END AS open_order, {_dec("CASE WHEN v >= mean THEN 1 ELSE 0 END", "target")}
FROM o CROSS JOIN a JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey
""",
    "activity": f"""
SELECT concat(CAST(user_id AS STRING), '@', CAST(CAST(ts AS DATE) AS STRING)) AS row_id,
  {_dec("sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END)", "clicks")}, {_dec("sum(CASE WHEN event_type = 'view' THEN 1 ELSE 0 END)", "views")},
  {_dec("sum(CASE WHEN event_type = 'error' THEN 1 ELSE 0 END)", "errors")}, {_dec("sum(CASE WHEN event_type = 'signup' THEN 1 ELSE 0 END)", "signups")},
  {_dec("sum(CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END)", "purchases")}, {_dec("count(DISTINCT props)", "distinct_props")},
  {_dec("sum(CAST(floor(value * 10000 + 0.5) / 10000 AS DECIMAL(18,4)))", "target")}
FROM events GROUP BY user_id, CAST(ts AS DATE)
""",
}

#: Features of each frame, numeric and categorical, in the frame's order.
NUMERIC = {
    "basket": ("line_count", "quantity", "mean_discount", "mean_tax", "parts", "suppliers", "ship_lag", "balance"),
    "toxic": (),
    "junk": ("characters", "word_count", "line_count", "word_length", "upper_share", "digit_share", "symbol_share", "exclamations", "nonletter_share", "repeated_lines"),
    "spend": ("order_count", "active_months", "priorities"),
    "activity": ("clicks", "views", "errors", "signups", "purchases", "distinct_props"),
}
CATEGORICAL = {
    "basket": ("priority", "status", "segment", "region"),
    "toxic": ("language", "source", "length", "punctuation", "letter_case", "repetition", "insult_word", "web_link"),
    "junk": (),
    "spend": ("market_segment", "home_nation", "home_region", "positive_balance", "urgent_order", "open_order"),
    "activity": (),
}


def spark_sql(sql: str) -> str:
    """The few spellings in which Spark differs; the distinct parts of an order are a set of a few, which costs no expanded rows."""
    for c in ("l_partkey", "l_suppkey"):
        sql = sql.replace(f"count(DISTINCT {c})", f"size(collect_set({c}))")
    return (
        sql.replace(", '', 'g')", ", '')").replace("datediff('day', ", "datediff(DAY, ").replace("[^ \\t\\n\\r]", "[^ \\\\t\\\\n\\\\r]").replace("[ \\t\\n\\r]", "[ \\\\t\\\\n\\\\r]")
        .replace("repeated_lines(text)", "size(split(text, '\\n')) - size(array_distinct(split(text, '\\n')))")
    )


def duck_sql(sql: str) -> str:
    return sql.replace("AS STRING", "AS VARCHAR").replace("size(regexp_extract_all(text, '[^ \\t\\n\\r]+', 0))", "len(regexp_extract_all(text, '[^ \\t\\n\\r]+'))").replace("regexp_like(", "regexp_matches(").replace("repeated_lines(text)", "len(string_split(text, chr(10))) - len(list_distinct(string_split(text, chr(10))))")


def features(spark: SparkSession, sf_dir: str, domain: str) -> DataFrame:
    return query(spark, sf_dir, spark_sql(FEATURES[domain]))


def features_sql(domain: str) -> str:
    return duck_sql(FEATURES[domain])
