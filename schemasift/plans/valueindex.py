"""The value index: distinct cell values of enumerable columns as a sparse inverted file, BM25, and the samples of a column."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import STOP, tokens, tokens_sql
from ..registry import query
from ..sources.catalog import cte, from_parquet, questions

#: Indexed columns of the given tables: short strings that are no free text, urls or nested text. Fixed values.
INDEXED = [
    ("customer", "c_mktsegment"), ("customer", "c_name"), ("documents", "lang"), ("events", "event_type"), ("lineitem", "l_linestatus"), ("lineitem", "l_returnflag"), ("nation", "n_name"), ("orders", "o_orderpriority"),
    ("orders", "o_orderstatus"), ("part", "p_brand"), ("part", "p_name"), ("part", "p_type"), ("region", "r_name"), ("conversations", "role"), ("supplier", "s_name"),
]
K1, B, TOP = 1.2, 0.75, 2


def distinct_values(spark: SparkSession, sf: str, columns: DataFrame, indexed: list[tuple[str, str]]) -> DataFrame:
    """(col_id, value, len): one pruned scan per column; only distinct values leave it."""
    out = []
    for t, c in indexed:
        cells = spark.read.parquet(f"{sf}/{t}.parquet").select(F.col(c).cast("string").alias("value")).where("value IS NOT NULL").distinct()
        out.append(cells.select(F.lit(t).alias("table_name"), F.lit(c).alias("column_name"), "value"))
    ids = columns.select("table_name", "column_name", "col_id")
    return reduce(DataFrame.union, out).join(F.broadcast(ids), ["table_name", "column_name"]).select("col_id", "value", F.size(tokens("value")).cast("long").alias("len"))


def postings(values: DataFrame) -> DataFrame:
    """(token, col_id, value, tf, len)."""
    each = values.select("col_id", "value", "len", F.explode(tokens("value")).alias("token"))
    return each.groupBy("token", "col_id", "value", "len").agg(F.count(F.lit(1)).alias("tf"))


def token_stats(post: DataFrame) -> DataFrame:
    return post.groupBy("token").agg(F.count(F.lit(1)).alias("df"))


def bm25(asked: DataFrame, values: DataFrame, post: DataFrame, scope: str = "database", min_token: int = 1, stop: list[str] | None = None, fold_plurals: bool = False) -> DataFrame:
    """(qid, col_id, value, score) of every value that shares a token with the question. Statistics are those of the database, or of
    the value's column."""
    by = [] if scope == "database" else ["col_id"]
    n = values.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.avg("len").alias("avg"))
    df = post.groupBy("token", *by).agg(F.count(F.lit(1)).alias("df"))
    words = asked.select("qid", F.explode(F.array_distinct(tokens("text"))).alias("token")).where(F.length("token") >= min_token)
    if stop:
        words = words.where(~F.col("token").isin(stop))
    if fold_plurals:
        words = words.union(words.where("token LIKE '%s' AND length(token) > 3").select("qid", F.expr("substr(token, 1, length(token) - 1)").alias("token"))).distinct()
    hit = post.join(F.broadcast(words), "token").join(df, ["token", *by])  # questions are the small, stated side
    hit = hit.join(F.broadcast(n), by) if by else hit.crossJoin(F.broadcast(n))
    idf = F.log(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    part = idf * F.col("tf") * (K1 + 1) / (F.col("tf") + K1 * (1 - B + B * F.col("len") / F.col("avg")))
    return hit.groupBy("qid", "col_id", "value").agg(F.sum(part).alias("score"))


def top_values(scores: DataFrame, k: int = TOP) -> DataFrame:
    """(qid, col_id, value, score, rank) of the k best values; ranks are cut before the shuffle by the window's group limit."""
    order = Window.partitionBy("qid", "col_id").orderBy(F.desc(F.round("score", 9)), "value")
    return scores.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def representatives(spark: SparkSession, sf: str, columns: DataFrame, indexed: list[tuple[str, str]]) -> DataFrame:
    """(col_id, example): the most frequent value, the smallest of those."""
    out = []
    for t, c in indexed:
        counts = spark.read.parquet(f"{sf}/{t}.parquet").groupBy(F.col(c).cast("string").alias("v")).agg(F.count(F.lit(1)).alias("n")).where("v IS NOT NULL")
        out.append(counts.agg(F.min_by("v", F.struct(-F.col("n"), F.col("v"))).alias("example")).select(F.lit(t).alias("table_name"), F.lit(c).alias("column_name"), "example"))
    return reduce(DataFrame.union, out).join(columns.select("table_name", "column_name", "col_id"), ["table_name", "column_name"]).select("col_id", "example")


def samples(asked: DataFrame, columns: DataFrame, best: DataFrame, examples: DataFrame) -> DataFrame:
    """(qid, col_id, samples): the best values, or the representative where none shares a token."""
    found = best.groupBy("qid", "col_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "value"))), lambda s: s["value"]).alias("found"))  # TOP values at most
    pairs = asked.select("qid").crossJoin(F.broadcast(columns.select("col_id")))
    joined = pairs.join(found, ["qid", "col_id"], "left").join(examples, "col_id", "left")
    return joined.select("qid", "col_id", F.coalesce("found", F.when(F.col("example").isNotNull(), F.array("example")), F.array().cast("array<string>")).alias("samples"))


class Index:
    """A database's index, built once; ``save`` and ``load`` keep it partitioned by token bucket."""

    def __init__(self, spark: SparkSession, sf: str, columns: DataFrame, indexed: list[tuple[str, str]] = INDEXED):
        self.values = distinct_values(spark, sf, columns, indexed)
        self.postings = postings(self.values)
        self.examples = representatives(spark, sf, columns, indexed)

    def save(self, path: str, buckets: int = 16) -> None:
        self.values.write.mode("overwrite").parquet(f"{path}/values")
        self.postings.withColumn("bucket", F.pmod(F.xxhash64("token"), F.lit(buckets))).repartition("bucket").sortWithinPartitions("bucket", "token").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/postings")
        self.examples.write.mode("overwrite").parquet(f"{path}/examples")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Index:
        out = Index.__new__(Index)
        out.values, out.postings, out.examples = (spark.read.parquet(f"{path}/{n}") for n in ("values", "postings", "examples"))
        return out


# --- registered queries --------------------------------------------------------------------------------------------------------
_VALUES = " UNION ALL ".join(f"SELECT DISTINCT '{t}' AS table_name, '{c}' AS column_name, {c} AS value FROM {t} WHERE {c} IS NOT NULL" for t, c in INDEXED)
INDEX_SQL = f"""{cte('cols', 'questions')},
vals AS (SELECT col_id, value, CAST(len({tokens_sql('value')}) AS BIGINT) AS len FROM ({_VALUES}) JOIN cols USING (table_name, column_name)),
post AS (SELECT token, col_id, value, len, count(*) AS tf FROM (SELECT *, unnest({tokens_sql('value')}) AS token FROM vals) GROUP BY token, col_id, value, len),
qt AS (SELECT DISTINCT qid, unnest({tokens_sql('text')}) AS token FROM questions)"""


def _bm25_sql(by: str = "", words: str = "qt") -> str:
    on, g = (f", {by}", f"GROUP BY {by}") if by else ("", "")
    return f"""n AS (SELECT {by + ', ' if by else ''}count(*) AS n, avg(len) AS avg FROM vals {g}), df AS (SELECT token{on}, count(*) AS df FROM post GROUP BY token{on}),
bm AS (SELECT qid, col_id, value, sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * {K1 + 1} / (tf + {K1} * ({1 - B} + {B} * len / avg))) AS score
       FROM post JOIN {words} USING (token) JOIN df USING (token{on}) {'JOIN n USING (' + by + ')' if by else ', n'} GROUP BY qid, col_id, value)"""


BM25_SQL = f"{INDEX_SQL}, {_bm25_sql()}, best AS (SELECT *, row_number() OVER (PARTITION BY qid, col_id ORDER BY round(score, 9) DESC, value) AS rank FROM bm QUALIFY rank <= {TOP})"
_EXAMPLES = " UNION ALL ".join(f"(SELECT '{t}' AS table_name, '{c}' AS column_name, {c} AS example FROM {t} WHERE {c} IS NOT NULL GROUP BY {c} ORDER BY count(*) DESC, {c} LIMIT 1)" for t, c in INDEXED)
SAMPLES_SQL = f"""{BM25_SQL}, ex AS (SELECT col_id, example FROM ({_EXAMPLES}) JOIN cols USING (table_name, column_name)),
found AS (SELECT qid, col_id, list(value ORDER BY rank) AS found FROM best GROUP BY qid, col_id),
samples AS (SELECT qid, c.col_id, coalesce(found, CASE WHEN example IS NOT NULL THEN [example] END, CAST([] AS VARCHAR[])) AS samples FROM questions q CROSS JOIN cols c LEFT JOIN found USING (qid, col_id) LEFT JOIN ex USING (col_id))"""


def _open(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame, Index]:
    c = from_parquet(spark, sf).columns
    return questions(spark), c, Index(spark, sf, c)


@query("vindex_df", f"WITH {INDEX_SQL} SELECT token, count(*) AS df FROM post GROUP BY token")
def _df(spark: SparkSession, sf: str) -> DataFrame:
    return token_stats(_open(spark, sf)[2].postings)


@query("vindex_postings", f"WITH {INDEX_SQL} SELECT token, col_id, value, len, tf FROM post")
def _postings(spark: SparkSession, sf: str) -> DataFrame:
    return _open(spark, sf)[2].postings


@query("bm25_scores", f"WITH {INDEX_SQL}, {_bm25_sql()} SELECT qid, col_id, value, round(score, 6) AS score FROM bm")
def _scores(spark: SparkSession, sf: str) -> DataFrame:
    q, _, i = _open(spark, sf)
    return bm25(q, i.values, i.postings).withColumn("score", F.round("score", 6))


@query("bm25_column_scope", f"WITH {INDEX_SQL}, {_bm25_sql('col_id')} SELECT qid, col_id, value, round(score, 6) AS score FROM bm")
def _column_scope(spark: SparkSession, sf: str) -> DataFrame:
    q, _, i = _open(spark, sf)
    return bm25(q, i.values, i.postings, scope="column").withColumn("score", F.round("score", 6))


@query("bm25_stopwords", f"WITH {INDEX_SQL}, qs AS (SELECT * FROM qt WHERE token NOT IN ({', '.join(repr(w) for w in STOP)}) UNION SELECT qid, substr(token, 1, length(token) - 1) FROM qt WHERE token NOT IN ({', '.join(repr(w) for w in STOP)}) AND token LIKE '%s' AND length(token) > 3), {_bm25_sql('', 'qs')} SELECT qid, col_id, value, round(score, 6) AS score FROM bm")
def _stop(spark: SparkSession, sf: str) -> DataFrame:
    q, _, i = _open(spark, sf)
    return bm25(q, i.values, i.postings, stop=STOP, fold_plurals=True).withColumn("score", F.round("score", 6))


@query("bm25_top2", f"WITH {BM25_SQL} SELECT qid, col_id, value, round(score, 6) AS score, rank FROM best")
def _top(spark: SparkSession, sf: str) -> DataFrame:
    q, _, i = _open(spark, sf)
    return top_values(bm25(q, i.values, i.postings)).withColumn("score", F.round("score", 6))


@query("samples_fallback", f"WITH {SAMPLES_SQL} SELECT qid, col_id, samples FROM samples")
def _samples(spark: SparkSession, sf: str) -> DataFrame:
    q, c, i = _open(spark, sf)
    return samples(q, c, top_values(bm25(q, i.values, i.postings)), i.examples)


@query("samples_provided", f"WITH {cte('cols')} SELECT c.col_id, [example] AS samples FROM ({_EXAMPLES}) JOIN cols c USING (table_name, column_name)")
def _provided(spark: SparkSession, sf: str) -> DataFrame:
    """No index: the samples that come with the catalog are used as they are."""
    return representatives(spark, sf, from_parquet(spark, sf).columns, INDEXED).select("col_id", F.array("example").alias("samples"))
