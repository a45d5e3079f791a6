"""Column contexts, prompts and the features of question-column pairs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import bare_name, expanded, expanded_sql, grams, grams_sql, tokens, tokens_sql, word_pieces, word_pieces_sql
from ..registry import query
from ..sources.catalog import cte, from_parquet, questions
from ..sources.fixtures import TABLES
from .describe import _MEANING, _OBSERVED, attach, describe_tables, observed
from .profile import value_facts, value_facts_sql
from .valueindex import SAMPLES_SQL, _open, bm25, samples, top_values

NUMERIC, MAX_TOKENS = ["int", "bigint", "double", "float", "smallint", "decimal"], 4096
FEATURES = ["name_share", "name_prefix", "name_grams", "table_prefix", "table_grams", "descr_share", "value_score", "number_cue", "date_cue", "pk", "fk", "name_exact"]
#: Words that ask for numbers, and for dates. Fixed values.
NUMBER_CUES, DATE_CUES = ["average", "total", "sum", "number", "many", "count", "price", "revenue", "expensive", "negative", "quantity"], ["day", "date", "after", "before", "when", "year", "month", "1998"]
#: Weights of the untrained encoder, in the features' order, and its bias. Fixed values.
HAND, BIAS = [1.2, 1.6, 0.8, 0.7, 0.6, 0.4, 2.2, 0.2, 0.6, 0.1, 0.0, 1.0], -3.0


def build(asked: DataFrame, columns: DataFrame, meta: DataFrame, tables: DataFrame, found: DataFrame, facts: DataFrame) -> DataFrame:
    """(qid, col_id, context): the eight named parts. Parts without the question are joined once per column."""
    columns = columns.join(facts, ["table_name", "column_name"], "left")
    still = columns.join(meta.select("table_name", "column_name", "descr"), ["table_name", "column_name"], "left").join(tables.withColumnRenamed("descr", "table_descr"), "table_name", "left")
    pairs = asked.select("qid").crossJoin(F.broadcast(still)).join(found, ["qid", "col_id"], "left")
    parts = F.struct(
        F.col("table_name").alias("table"), F.col("column_name").alias("column"), "table_descr", F.col("descr").alias("column_descr"), "dtype",
        F.coalesce("samples", F.array().cast("array<string>")).alias("samples"), F.coalesce("may_be_null", F.lit(False)).alias("may_be_null"), "value_descr",
    )
    return pairs.select("qid", "col_id", parts.alias("context"))


def as_text(c: Column) -> Column:
    """A context as one line of text."""
    return F.concat(
        F.lit("column "), c["table"], F.lit("."), c["column"], F.lit(" of type "), c["dtype"], F.lit("; "), F.coalesce(c["column_descr"], F.lit("")), F.lit(" "), F.coalesce(c["table_descr"], F.lit("")),
        F.lit(" Values: "), F.array_join(c["samples"], ", "), F.when(c["may_be_null"], F.lit("; may be missing")).otherwise(F.lit("")), F.coalesce(F.concat(F.lit("; "), c["value_descr"]), F.lit("")),
    )


def truncated(text: Column, limit: int = MAX_TOKENS) -> Column:
    return F.array_join(F.slice(F.split(text, " "), 1, limit), " ")


def prompt(question: Column, context: Column) -> Column:
    """Our wording of the yes-or-no question about one column; the reply is opened with an empty thought."""
    return F.concat(
        F.lit("[system] You decide whether a database column is of use for a question. Reply yes or no.\n[user] Question: "), truncated(question), F.lit("\nColumn: "), truncated(as_text(context)),
        F.lit("\nIs this column of use in a statement that answers the question?\n[reply] (no thought)\n"),
    )


def _either_prefix(t: Column, w: Column) -> Column:
    return (F.length(t) >= 4) & (F.length(w) >= 3) & (F.startswith(t, w) | F.startswith(w, t))


def pair_features(asked: DataFrame, columns: DataFrame, meta: DataFrame, best: DataFrame) -> DataFrame:
    """(qid, col_id, one column per feature): what is only the question's or only the column's is formed once, before the pairs."""
    q = asked.select("qid", F.array_distinct(tokens("text")).alias("qt"), grams(F.lower("text")).alias("qg"))
    c = columns.join(meta.select("table_name", "column_name", "descr"), ["table_name", "column_name"], "left").select(
        "col_id", "table_name", "dtype", "is_pk", "is_fk", bare_name("column_name").alias("bare"), F.array_distinct(tokens(expanded("column_name"))).alias("cw"), grams(expanded("column_name")).alias("cg"), grams(F.col("table_name")).alias("tg"), F.array_distinct(tokens("descr")).alias("dw")
    )
    value = best.groupBy("qid", "col_id").agg(F.max("score").alias("bm"))
    p = q.crossJoin(F.broadcast(c)).join(value, ["qid", "col_id"], "left")
    share = lambda part, whole: F.coalesce(F.size(F.array_intersect(part, whole)) / F.nullif(F.size(whole), F.lit(0)), F.lit(0.0))
    flag = lambda x: x.cast("double")
    near = F.size(F.filter("cw", lambda w: F.exists("qt", lambda t: _either_prefix(t, w)))) / F.nullif(F.size("cw"), F.lit(0))
    return p.select(
        "qid", "col_id", share(F.col("qt"), F.col("cw")).alias("name_share"), F.coalesce(near, F.lit(0.0)).alias("name_prefix"), share(F.col("qg"), F.col("cg")).alias("name_grams"),
        flag(F.exists("qt", lambda t: _either_prefix(t, F.col("table_name")))).alias("table_prefix"), share(F.col("qg"), F.col("tg")).alias("table_grams"), share(F.col("qt"), F.col("dw")).alias("descr_share"),
        F.coalesce(F.col("bm") / 10, F.lit(0.0)).alias("value_score"), flag(F.arrays_overlap("qt", F.array(*map(F.lit, NUMBER_CUES))) & F.col("dtype").isin(NUMERIC)).alias("number_cue"),
        flag(F.arrays_overlap("qt", F.array(*map(F.lit, DATE_CUES))) & F.col("dtype").startswith("timestamp")).alias("date_cue"), flag(F.col("is_pk")).alias("pk"), flag(F.col("is_fk")).alias("fk"), flag(F.array_contains("qt", F.col("bare"))).alias("name_exact"),
    )


def linear(weights: list[float] = HAND, bias: float = BIAS) -> Column:
    total = F.lit(bias)
    for name, w in zip(FEATURES, weights, strict=True):
        total = total + F.col(name) * w
    return total


def features_of(spark: SparkSession, sf: str) -> DataFrame:
    asked, columns, index = _open(spark, sf)
    return pair_features(asked, columns, attach(columns, observed(spark)), top_values(bm25(asked, index.values, index.postings)))


# --- registered queries --------------------------------------------------------------------------------------------------------
_DESCRIBED = f"{_OBSERVED}, meta AS (SELECT table_name, column_name, coalesce(descr, {_MEANING}) AS descr FROM cols LEFT JOIN obs USING (table_name, column_name))"
_LIST = lambda xs: "[" + ", ".join(f"'{x}'" for x in xs) + "]"
_SHARE = lambda part, whole: f"coalesce(len(list_intersect({part}, {whole})) / nullif(CAST(len({whole}) AS DOUBLE), 0), 0.0)"
_NEAR = lambda t, w: f"(length({t}) >= 4 AND length({w}) >= 3 AND (starts_with({t}, {w}) OR starts_with({w}, {t})))"
FEATURES_SQL = f"""{SAMPLES_SQL}, {_DESCRIBED},
fq AS (SELECT qid, list_distinct({tokens_sql('text')}) AS qt, {grams_sql('lower(text)')} AS qg FROM questions),
fc AS (SELECT col_id, c.table_name, dtype, is_pk, is_fk, regexp_replace(lower(c.column_name), '^[a-z]_', '') AS bare, list_distinct({tokens_sql(expanded_sql('c.column_name'))}) AS cw, {grams_sql(expanded_sql('c.column_name'))} AS cg, {grams_sql('c.table_name')} AS tg, list_distinct({tokens_sql('m.descr')}) AS dw FROM cols c JOIN meta m USING (table_name, column_name)),
fv AS (SELECT qid, col_id, max(score) AS bm FROM best GROUP BY qid, col_id),
feats AS (SELECT qid, col_id, {_SHARE('qt', 'cw')} AS name_share, coalesce(len(list_filter(cw, lambda w: len(list_filter(qt, lambda t: {_NEAR('t', 'w')})) > 0)) / nullif(CAST(len(cw) AS DOUBLE), 0), 0.0) AS name_prefix,
 {_SHARE('qg', 'cg')} AS name_grams, CAST(len(list_filter(qt, lambda t: {_NEAR('t', 'table_name')})) > 0 AS INT)::DOUBLE AS table_prefix, {_SHARE('qg', 'tg')} AS table_grams, {_SHARE('qt', 'dw')} AS descr_share, coalesce(bm / 10, 0.0) AS value_score,
 CAST(list_has_any(qt, {_LIST(NUMBER_CUES)}) AND dtype IN ({_LIST(NUMERIC)[1:-1]}) AS INT)::DOUBLE AS number_cue, CAST(list_has_any(qt, {_LIST(DATE_CUES)}) AND starts_with(dtype, 'timestamp') AS INT)::DOUBLE AS date_cue,
 CAST(is_pk AS INT)::DOUBLE AS pk, CAST(is_fk AS INT)::DOUBLE AS fk, CAST(list_contains(qt, bare) AS INT)::DOUBLE AS name_exact FROM fq CROSS JOIN fc LEFT JOIN fv USING (qid, col_id))"""
LOGIT_SQL = " + ".join([str(BIAS), *(f"{n} * {w}" for n, w in zip(FEATURES, HAND, strict=True))])
_ROUNDED = ", ".join(f"round({f}, 6) AS {f}" for f in FEATURES)


@query("pair_features", f"WITH {FEATURES_SQL} SELECT qid, col_id, {_ROUNDED} FROM feats")
def _features(spark: SparkSession, sf: str) -> DataFrame:
    return features_of(spark, sf).select("qid", "col_id", *(F.round(f, 6).alias(f) for f in FEATURES))


@query("yes_logit", f"WITH {FEATURES_SQL} SELECT qid, col_id, round({LOGIT_SQL}, 6) AS score FROM feats")
def _logit(spark: SparkSession, sf: str) -> DataFrame:
    return features_of(spark, sf).select("qid", "col_id", F.round(linear(), 6).alias("score"))


@query("graph_rerank_l0", f"WITH {FEATURES_SQL} SELECT qid, col_id, round({LOGIT_SQL} - {BIAS}, 6) AS score FROM feats")
def _l0(spark: SparkSession, sf: str) -> DataFrame:
    """No graph layer: a linear score of the first vectors, without looking at an edge."""
    return features_of(spark, sf).select("qid", "col_id", F.round(linear(bias=0.0), 6).alias("score"))


_TABLE_DESCR = f"td AS (SELECT table_name, 'Rows of ' || table_name || ' with ' || string_agg({expanded_sql('column_name')}, ', ' ORDER BY ordinal) || '.' AS table_descr FROM cols GROUP BY table_name)"
_CONTEXT_SQL = f"""{SAMPLES_SQL}, {_DESCRIBED}, {_TABLE_DESCR}, cf AS ({value_facts_sql(TABLES)}), ctx AS (SELECT qid, col_id, 'column ' || c.table_name || '.' || c.column_name || ' of type ' || dtype || '; ' || m.descr || ' ' || table_descr || ' Values: ' || array_to_string(samples, ', ') || CASE WHEN may_be_null THEN '; may be missing' ELSE '' END || coalesce('; ' || value_descr, '') AS context FROM samples JOIN cols c USING (col_id) JOIN meta m USING (table_name, column_name) JOIN td USING (table_name) LEFT JOIN cf USING (table_name, column_name))"""


def contexts(spark: SparkSession, sf: str) -> DataFrame:
    asked, columns, index = _open(spark, sf)
    found = samples(asked, columns, top_values(bm25(asked, index.values, index.postings)), index.examples)
    return build(asked, columns, attach(columns, observed(spark)), describe_tables(columns), found, value_facts(spark, sf, TABLES))


@query("column_context", f"WITH {_CONTEXT_SQL} SELECT qid, col_id, context FROM ctx")
def _context(spark: SparkSession, sf: str) -> DataFrame:
    return contexts(spark, sf).select("qid", "col_id", as_text(F.col("context")).alias("context"))


@query("truncate_ctx", f"WITH {_CONTEXT_SQL} SELECT qid, col_id, array_to_string(string_split(context, ' ')[1:8], ' ') AS context FROM ctx")
def _truncate(spark: SparkSession, sf: str) -> DataFrame:
    return contexts(spark, sf).select("qid", "col_id", truncated(as_text(F.col("context")), 8).alias("context"))


@query("context_tokens", f"WITH {_CONTEXT_SQL} SELECT qid, CAST(sum({word_pieces_sql('context')}) AS BIGINT) AS tokens FROM ctx GROUP BY qid")
def _tokens(spark: SparkSession, sf: str) -> DataFrame:
    return contexts(spark, sf).groupBy("qid").agg(F.sum(word_pieces(as_text(F.col("context")))).alias("tokens"))


@query("prompt_text")
def _prompt(spark: SparkSession, sf: str) -> DataFrame:
    return contexts(spark, sf).join(questions(spark), "qid").select("qid", "col_id", prompt(F.col("text"), F.col("context")).alias("prompt"))
