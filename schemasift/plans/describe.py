"""Metadata: observed descriptions, missing ones, generated meanings, cost ledger, table grouping."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import ABBREVIATIONS, bare_name, bare_name_sql, expanded, expanded_sql, word_pieces, word_pieces_sql
from ..registry import query
from ..sources import fixtures as fx
from ..sources.catalog import cte, from_parquet


def observed(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(t, c, d) for (t, c), d in fx.OBSERVED.items()], "table_name string, column_name string, descr string")


def needs_meaning(columns: DataFrame, known: DataFrame) -> DataFrame:
    """(table_name, column_name, missing, abbreviated)."""
    short = F.exists(F.split(bare_name("column_name"), "_"), lambda w: w.isin(list(ABBREVIATIONS)))
    return columns.join(known, ["table_name", "column_name"], "left").select("table_name", "column_name", F.col("descr").isNull().alias("missing"), short.alias("abbreviated"))


def column_meaning(table: Column, column: Column, dtype: Column) -> Column:
    return F.concat(F.lit("The "), expanded(column), F.lit(" of a row of "), table, F.lit(" ("), dtype, F.lit(")."))


def describe_columns(columns: DataFrame) -> DataFrame:
    """One sentence per column, by template."""
    return columns.select("table_name", "column_name", column_meaning(F.col("table_name"), F.col("column_name"), F.col("dtype")).alias("descr"))


def describe_tables(columns: DataFrame) -> DataFrame:
    """One sentence per table from its columns."""
    words = F.transform(F.array_sort(F.collect_list(F.struct("ordinal", expanded("column_name").alias("w")))), lambda s: s["w"])  # a table's columns
    return columns.groupBy("table_name").agg(words.alias("w")).select("table_name", F.concat(F.lit("Rows of "), "table_name", F.lit(" with "), F.array_join("w", ", "), F.lit(".")).alias("descr"))


def replayed(columns: DataFrame, replies: DataFrame) -> DataFrame:
    """Recorded meanings where there is one, the template's elsewhere."""
    made = describe_columns(columns).withColumnRenamed("descr", "made")
    return made.join(replies, ["table_name", "column_name"], "left").select("table_name", "column_name", F.coalesce("descr", "made").alias("descr"))


def attach(columns: DataFrame, known: DataFrame) -> DataFrame:
    """Observed descriptions unchanged, generated ones elsewhere, with where they come from."""
    made = describe_columns(columns).withColumnRenamed("descr", "made")
    both = columns.select("table_name", "column_name").join(F.broadcast(known), ["table_name", "column_name"], "left").join(made, ["table_name", "column_name"])
    return both.select("table_name", "column_name", F.coalesce("descr", "made").alias("descr"), F.when(F.col("descr").isNotNull(), "observed").otherwise("generated").alias("descr_src"))


def ledger(calls: DataFrame, price_per_million: float = 0.4) -> DataFrame:
    """(n_calls, tokens, price)."""
    return calls.agg(F.count(F.lit(1)).alias("n_calls"), F.sum("tokens").alias("tokens"), (F.sum("tokens") * price_per_million / 1e6).alias("price"))


def group_tables(columns: DataFrame) -> DataFrame:
    """(db_id, table_name, group_id, representative): tables of one structure."""
    shape = F.md5(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("column_name", "dtype"))), lambda s: F.concat_ws(":", s["column_name"], s["dtype"])), ","))
    shapes = columns.groupBy("db_id", "table_name").agg(shape.alias("group_id"))
    first = shapes.groupBy("db_id", "group_id").agg(F.min("table_name").alias("representative"))
    return shapes.join(first, ["db_id", "group_id"]).select("db_id", "table_name", "group_id", "representative")


def expand_groups(selection: DataFrame, groups: DataFrame) -> DataFrame:
    """(qid, table_name, column_name) for every member of the selected representatives' groups."""
    chosen = selection.withColumnRenamed("table_name", "representative")
    return chosen.join(groups.select("table_name", "representative"), "representative").select("qid", "table_name", "column_name")


# --- registered queries --------------------------------------------------------------------------------------------------------
_OBSERVED = "obs AS (SELECT * FROM (VALUES " + ", ".join(f"('{t}', '{c}', '{d}')" for (t, c), d in fx.OBSERVED.items()) + ") v(table_name, column_name, descr))"
_MEANING = f"'The ' || {expanded_sql('column_name')} || ' of a row of ' || table_name || ' (' || dtype || ').'"


@query("meta_merge", f"WITH {cte('cols')}, {_OBSERVED} SELECT table_name, column_name, coalesce(descr, {_MEANING}) AS descr, CASE WHEN descr IS NULL THEN 'generated' ELSE 'observed' END AS descr_src FROM cols LEFT JOIN obs USING (table_name, column_name)")
def _merge(spark: SparkSession, sf: str) -> DataFrame:
    return attach(from_parquet(spark, sf).columns, observed(spark))


@query("meta_missing", f"WITH {cte('cols')}, {_OBSERVED} SELECT table_name, column_name, descr IS NULL AS missing, list_has_any(string_split({bare_name_sql('column_name')}, '_'), [{', '.join(repr(k) for k in ABBREVIATIONS)}]) AS abbreviated FROM cols LEFT JOIN obs USING (table_name, column_name)")
def _missing(spark: SparkSession, sf: str) -> DataFrame:
    return needs_meaning(from_parquet(spark, sf).columns, observed(spark))


@query("meta_columns", f"WITH {cte('cols')} SELECT table_name, column_name, {_MEANING} AS descr FROM cols")
def _columns(spark: SparkSession, sf: str) -> DataFrame:
    return describe_columns(from_parquet(spark, sf).columns)


@query("meta_tables", f"WITH {cte('cols')} SELECT table_name, 'Rows of ' || table_name || ' with ' || string_agg({expanded_sql('column_name')}, ', ' ORDER BY ordinal) || '.' AS descr FROM cols GROUP BY table_name")
def _tables(spark: SparkSession, sf: str) -> DataFrame:
    return describe_tables(from_parquet(spark, sf).columns)


@query("meta_replay", f"WITH {cte('cols')}, {_OBSERVED} SELECT table_name, column_name, coalesce(descr, {_MEANING}) AS descr FROM cols LEFT JOIN obs USING (table_name, column_name)")
def _replay(spark: SparkSession, sf: str) -> DataFrame:
    return replayed(from_parquet(spark, sf).columns, observed(spark))


@query("enrich_cost", f"SELECT count(*) AS n_calls, CAST(sum(t) AS BIGINT) AS tokens, CAST(sum(t) AS BIGINT) * 0.4 / 1e6 AS price FROM (SELECT {word_pieces_sql('text')} AS t FROM conversations WHERE role = 'assistant')")
def _cost(spark: SparkSession, sf: str) -> DataFrame:
    """What the recorded replies cost: a call for each turn of an assistant."""
    return ledger(spark.read.parquet(f"{sf}/conversations.parquet").where("role = 'assistant'").select(word_pieces(F.col("text")).alias("tokens")))


@query("table_groups", f"WITH {cte('cols')}, dated AS (SELECT table_name || '_' || d AS table_name, column_name, dtype FROM cols, (SELECT * FROM (VALUES ('20240101'), ('20240102'), ('20240103')) v(d)) WHERE table_name = 'events'), every AS (SELECT table_name, column_name, dtype FROM cols UNION ALL SELECT * FROM dated), shapes AS (SELECT table_name, md5(string_agg(column_name || ':' || dtype, ',' ORDER BY column_name, dtype)) AS group_id FROM every GROUP BY table_name) SELECT 'all14' AS db_id, table_name, group_id, min(table_name) OVER (PARTITION BY group_id) AS representative FROM shapes")
def _groups(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf).columns
    days = F.explode(F.array(*(F.lit(d) for d in ("20240101", "20240102", "20240103"))))
    dated = c.where("table_name = 'events'").withColumn("d", days).withColumn("table_name", F.concat_ws("_", "table_name", "d")).drop("d")
    return group_tables(c.unionByName(dated))
