"""Baselines on the in-repo encoder's features, capacity and cost models."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import expanded, tokens, tokens_sql, word_pieces, word_pieces_sql
from ..functions.vectors import sigmoid
from ..registry import query
from ..sources.catalog import TURNS_SQL, from_parquet, turns
from .context import FEATURES_SQL, LOGIT_SQL, _CONTEXT_SQL, as_text, contexts, features_of, linear

#: Functional comparison by code: scope, names, meanings, values, types, connectivity, architecture, relations, columns. Fixed values.
FUNCTIONAL = [
    ("FULL", "multi", True, "long", True, True, True, "decoder", "graph", 23067), ("PRUNE1", "single", True, "no", True, True, False, "encoder", "attention", 90), ("REL", "multi", True, "no", False, False, False, "encoder", "attention", 159),
    ("TC", "multi", True, "short", False, False, False, "encoder", "attention", 117), ("SKEL", "multi", True, "short", False, False, True, "encoder", "attention", 117),
]


def single_table(features: DataFrame, columns: DataFrame, max_cols: int = 90) -> DataFrame:
    """Each table by itself: names and values only, scores normalised inside the table; tables wider than the window are cut."""
    raw = features.join(F.broadcast(columns.select("col_id", "table_name", "ordinal")), "col_id").where(F.col("ordinal") <= max_cols)
    s = F.col("name_share") * 1.2 + F.col("name_prefix") * 1.6 + F.col("value_score") * 2.2 + F.col("number_cue") * 0.2
    by = Window.partitionBy("qid", "table_name")
    return raw.withColumn("e", F.exp(s)).select("qid", "col_id", (F.col("e") / F.sum("e").over(by)).alias("score"))


def table_column(scores: DataFrame, columns: DataFrame, tables: int, per_table: int) -> DataFrame:
    """Columns of the best tables (a table is as good as its best column), the best of each."""
    named = scores.join(F.broadcast(columns.select("col_id", "table_name")), "col_id")
    best = named.groupBy("qid", "table_name").agg(F.max("score").alias("t"))
    kept = best.withColumn("tr", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("t"), "table_name"))).where(F.col("tr") <= tables)
    inner = named.join(kept, ["qid", "table_name"])
    return inner.withColumn("cr", F.row_number().over(Window.partitionBy("qid", "table_name").orderBy(F.desc("score"), "col_id"))).where(F.col("cr") <= per_table).select("qid", "col_id", "score")


def chunks(sized: DataFrame, budget: int) -> DataFrame:
    """(qid, col_id, chunk): columns in order, by tokens before them over the budget of one window."""
    before = F.sum("tokens").over(Window.partitionBy("qid").orderBy("col_id").rowsBetween(Window.unboundedPreceding, 0)) - F.col("tokens")
    return sized.select("qid", "col_id", F.floor(before / budget).alias("chunk"))


def chunk_calls(chunked: DataFrame) -> DataFrame:
    return chunked.groupBy("qid").agg((F.max("chunk") + 1).alias("n_calls"))


def biencoder(asked: DataFrame, columns: DataFrame) -> DataFrame:
    """Cosine of tf-idf vectors of question and column (with its descr) that never saw each other; sums over shared words only. A
    question without a word that tells columns apart has no rows. The columns' side is broadcast, the questions' may be any size."""
    docs = columns.select("col_id", F.explode(tokens(F.concat_ws(" ", "table_name", expanded("column_name"), "descr"))).alias("token"))
    tf = docs.groupBy("col_id", "token").agg(F.count(F.lit(1)).alias("tf"))
    n = columns.count()
    idf = tf.groupBy("token").agg(F.log((n + 1.0) / (F.count(F.lit(1)) + 1.0)).alias("idf"))
    c = tf.join(idf, "token").withColumn("w", F.col("tf") * F.col("idf"))
    q = asked.select("qid", F.explode(tokens("text")).alias("token")).groupBy("qid", "token").agg(F.count(F.lit(1)).alias("qtf")).join(idf, "token").withColumn("v", F.col("qtf") * F.col("idf"))
    cn, qn = c.groupBy("col_id").agg(F.sqrt(F.sum(F.col("w") ** 2)).alias("cn")), q.groupBy("qid").agg(F.sqrt(F.sum(F.col("v") ** 2)).alias("qn")).where("qn > 0")
    dots = q.select("token", "qid", "v").join(F.broadcast(c.select("token", "col_id", "w")), "token").groupBy("qid", "col_id").agg(F.sum(F.col("w") * F.col("v")).alias("dot"))
    return dots.join(cn, "col_id").join(qn, "qid").select("qid", "col_id", (F.col("dot") / (F.col("cn") * F.col("qn"))).alias("score"))


#: Pairs of features that the cross-encoder weighs together. Fixed values.
PAIRS = [("name_prefix", "table_prefix", 1.5), ("value_score", "name_grams", 2.0), ("descr_share", "name_share", 1.0), ("number_cue", "table_grams", -0.8)]


def cross(features: DataFrame) -> DataFrame:
    """Question and column are read together: evidence counts by itself and, other than in ``reranker``, in pairs."""
    joint = linear()
    for a, b, w in PAIRS:
        joint = joint + F.col(a) * F.col(b) * w
    return features.select("qid", "col_id", sigmoid(joint).alias("score"))


def reranker(features: DataFrame) -> DataFrame:
    return features.select("qid", "col_id", linear().alias("score"))


# --- registered queries --------------------------------------------------------------------------------------------------------
_JOINT = " + ".join([LOGIT_SQL, *(f"{a} * {b} * {w}" for a, b, w in PAIRS)])
_S = "name_share * 1.2 + name_prefix * 1.6 + value_score * 2.2 + number_cue * 0.2"


def _r(df: DataFrame) -> DataFrame:
    return df.select("qid", "col_id", F.round("score", 6).alias("score"))


@query("base_single_table", f"WITH {FEATURES_SQL} SELECT qid, col_id, round(exp({_S}) / sum(exp({_S})) OVER (PARTITION BY qid, table_name), 6) AS score FROM feats JOIN cols USING (col_id) WHERE ordinal <= 90")
def _single(spark: SparkSession, sf: str) -> DataFrame:
    return _r(single_table(features_of(spark, sf), from_parquet(spark, sf).columns))


def _tc_sql(kt: int, kc: int) -> str:
    return f"WITH {FEATURES_SQL}, s AS (SELECT qid, col_id, table_name, round({LOGIT_SQL}, 9) AS score FROM feats JOIN cols USING (col_id)), t AS (SELECT qid, table_name FROM s GROUP BY qid, table_name QUALIFY row_number() OVER (PARTITION BY qid ORDER BY max(score) DESC, table_name) <= {kt}) SELECT qid, col_id, round(score, 6) AS score FROM s JOIN t USING (qid, table_name) QUALIFY row_number() OVER (PARTITION BY qid, table_name ORDER BY score DESC, col_id) <= {kc}"


def _tc(spark: SparkSession, sf: str, kt: int, kc: int) -> DataFrame:
    scores = features_of(spark, sf).select("qid", "col_id", F.round(linear(), 9).alias("score"))
    return _r(table_column(scores, from_parquet(spark, sf).columns, kt, kc))


query("base_tables6_cols10", _tc_sql(6, 10))(lambda spark, sf: _tc(spark, sf, 6, 10))
query("base_tables40_cols80", _tc_sql(40, 80))(lambda spark, sf: _tc(spark, sf, 40, 80))


@query("chunk_assign", f"WITH {_CONTEXT_SQL}, sized AS (SELECT qid, col_id, {word_pieces_sql('context')} AS tokens FROM ctx) SELECT qid, col_id, CAST(floor((sum(tokens) OVER (PARTITION BY qid ORDER BY col_id ROWS UNBOUNDED PRECEDING) - tokens) / 512.0) AS BIGINT) AS chunk FROM sized")
def _chunk(spark: SparkSession, sf: str) -> DataFrame:
    return chunks(contexts(spark, sf).select("qid", "col_id", word_pieces(as_text(F.col("context"))).alias("tokens")), 512)


@query("functional_table", "SELECT * FROM (VALUES " + ", ".join(str(r).replace("True", "TRUE").replace("False", "FALSE") for r in FUNCTIONAL) + ") v(method, scope, names, meanings, \"values\", types, connectivity, architecture, relations, max_cols)")
def _functional(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame(FUNCTIONAL, "method string, scope string, names boolean, meanings string, values boolean, types boolean, connectivity boolean, architecture string, relations string, max_cols int")


_BI = f"""WITH cols AS (SELECT item_id AS col_id, text FROM benchmark), questions AS {TURNS_SQL}, d AS (SELECT col_id, unnest({tokens_sql("'benchmark text ' || text")}) AS token FROM cols), tf AS (SELECT col_id, token, count(*) AS tf FROM d GROUP BY ALL),
idf AS (SELECT token, ln(((SELECT count(*) FROM cols) + 1.0) / (count(*) + 1.0)) AS idf FROM tf GROUP BY token), c AS (SELECT col_id, token, tf * idf AS w FROM tf JOIN idf USING (token)),
q AS (SELECT qid, token, count(*) * any_value(idf) AS v FROM (SELECT qid, unnest({tokens_sql('text')}) AS token FROM questions) JOIN idf USING (token) GROUP BY qid, token),
cn AS (SELECT col_id, sqrt(sum(w * w)) AS cn FROM c GROUP BY col_id), qn AS (SELECT qid, sqrt(sum(v * v)) AS qn FROM q GROUP BY qid HAVING sum(v * v) > 0)
SELECT qid, col_id, round(sum(w * v) / (any_value(cn) * any_value(qn)), 6) AS score FROM c JOIN q USING (token) JOIN cn USING (col_id) JOIN qn USING (qid) GROUP BY qid, col_id"""


@query("base_biencoder", _BI)
def _bi(spark: SparkSession, sf: str) -> DataFrame:
    """Users' turns against the texts of ``benchmark``, each described by itself."""
    c = spark.read.parquet(f"{sf}/benchmark.parquet").select(F.col("item_id").alias("col_id"), F.lit("benchmark").alias("table_name"), F.lit("text").alias("column_name"), F.col("text").alias("descr"))
    return _r(biencoder(turns(spark, sf), c))


@query("base_cross", f"WITH {FEATURES_SQL} SELECT qid, col_id, round(1.0 / (1.0 + exp(-({_JOINT}))), 6) AS score FROM feats")
def _cross(spark: SparkSession, sf: str) -> DataFrame:
    return _r(cross(features_of(spark, sf)))


@query("base_reranker", f"WITH {FEATURES_SQL} SELECT qid, col_id, round({LOGIT_SQL}, 6) AS score FROM feats")
def _reranker(spark: SparkSession, sf: str) -> DataFrame:
    return _r(reranker(features_of(spark, sf)))


@query("prompt_cost", "SELECT tokens, round(tokens * 10.0 / 1e6, 6) AS price FROM (VALUES (340000), (20000000)) v(tokens)")
def _price(spark: SparkSession, sf: str) -> DataFrame:
    """Tokens of one request to a commercial model at 10 a million."""
    return spark.createDataFrame([(340000,), (20000000,)], "tokens int").withColumn("price", F.round(F.col("tokens") * 10.0 / 1e6, 6))


@query("max_cols", f"WITH {_CONTEXT_SQL}, t AS (SELECT avg({word_pieces_sql('context')}) AS per FROM ctx) SELECT window_tokens, CAST(floor((window_tokens - 64) / per) AS BIGINT) AS max_cols FROM t, (SELECT * FROM (VALUES (512), (4096), (32768)) v(window_tokens))")
def _max_cols(spark: SparkSession, sf: str) -> DataFrame:
    per = contexts(spark, sf).agg(F.avg(word_pieces(as_text(F.col("context")))).alias("per"))
    return per.crossJoin(spark.createDataFrame([(512,), (4096,), (32768,)], "window_tokens int")).select("window_tokens", F.floor((F.col("window_tokens") - 64) / F.col("per")).alias("max_cols"))


@query("prompt_reduction", f"WITH {FEATURES_SQL}, {_CONTEXT_SQL.split('td AS', 1)[1].join(['td AS', ''])}, sc AS (SELECT qid, col_id, row_number() OVER (PARTITION BY qid ORDER BY round({LOGIT_SQL}, 9) DESC, col_id) AS rank FROM feats), t AS (SELECT qid, {word_pieces_sql('context')} AS tokens, rank FROM ctx JOIN sc USING (qid, col_id)), s AS (SELECT sum(tokens) AS a, sum(tokens) FILTER (WHERE rank <= 20) AS b FROM t) SELECT style, CAST(a + extra AS BIGINT) AS prompt_full, CAST(b + extra AS BIGINT) AS prompt_kept, round(1 - (b + extra) / CAST(a + extra AS DOUBLE), 6) AS reduction FROM s, (SELECT * FROM (VALUES ('compact', 24 * 60), ('verbose', 24 * 1800)) v(style, extra))")
def _reduction(spark: SparkSession, sf: str) -> DataFrame:
    """Prompt tokens with all columns and with the best 20, for a compact prompt and one with long examples in front."""
    rank = F.row_number().over(Window.partitionBy("qid").orderBy(F.desc(F.round(linear(), 9)), "col_id"))
    order = features_of(spark, sf).select("qid", "col_id", rank.alias("rank"))
    sized = contexts(spark, sf).select("qid", "col_id", word_pieces(as_text(F.col("context"))).alias("tokens")).join(order, ["qid", "col_id"])
    s = sized.agg(F.sum("tokens").alias("a"), F.sum(F.when(F.col("rank") <= 20, F.col("tokens"))).alias("b"))
    both = s.crossJoin(spark.createDataFrame([("compact", 24 * 60), ("verbose", 24 * 1800)], "style string, extra int"))
    full, kept = F.col("a") + F.col("extra"), F.col("b") + F.col("extra")
    return both.select("style", full.alias("prompt_full"), kept.alias("prompt_kept"), F.round(1 - kept / full, 6).alias("reduction"))
