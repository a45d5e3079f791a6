"""Supervision: gold columns read from Catalyst's pruned scans, alternatives checked by results, negatives, losses.

The plan reader needs a classic session (it goes through the JVM plan); nothing else in the library does.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import digest, digest_sql
from ..registry import query
from ..sources import fixtures as fx
from ..sources.catalog import cte
from .spanner import TOY_SQL, toy_scores

#: Rewritten statements: some give the gold result, some must be rejected. Fixed values.
ALTERNATIVES = [
    ("q24", 1, "SELECT DISTINCT s_name FROM supplier JOIN lineitem ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey WHERE p_name = 'red widget'"),
    ("q03", 1, "SELECT r_name, COUNT(n_regionkey) AS n FROM region JOIN nation ON n_regionkey = r_regionkey GROUP BY r_name"),
    ("q04", 1, "SELECT COUNT(n_nationkey) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE n_name = 'NATION_7'"),
    ("q13", 1, "SELECT COUNT(DISTINCT l_suppkey) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING'"),
    ("q01", 1, "SELECT o_orderstatus, COUNT(DISTINCT o_custkey) AS n FROM orders GROUP BY o_orderstatus"),
    ("q02", 1, "SELECT c_name FROM customer WHERE c_mktsegment = 'MACHINERY' AND c_acctbal > 0"),
]


def with_views(spark: SparkSession, sf: str) -> SparkSession:
    """A session of its own in which the tables are views."""
    own = spark.newSession()
    for t in fx.TABLES:
        own.read.parquet(f"{sf}/{t}.parquet").createOrReplaceTempView(t)
    return own


def scanned_columns(df: DataFrame) -> set[tuple[str, str]]:
    """(table, column) of every column that the physical scans read, after Catalyst's pruning. No job runs."""
    if not hasattr(df, "_jdf"):
        raise RuntimeError("gold columns are read from a classic session's plan")
    leaves, out = df._jdf.queryExecution().sparkPlan().collectLeaves(), set()
    for i in range(leaves.size()):
        leaf = leaves.apply(i)
        if leaf.getClass().getSimpleName() == "FileSourceScanExec":
            table = leaf.relation().location().rootPaths().head().getName().removesuffix(".parquet")
            out |= {(table, c) for c in leaf.requiredSchema().fieldNames()}
    return out


def gold_columns(spark: SparkSession, sf: str, statements: list[tuple[str, str]]) -> DataFrame:
    own = with_views(spark, sf)
    rows = [(q, t, c) for q, sql in statements for t, c in sorted(scanned_columns(own.sql(sql)))]
    return spark.createDataFrame(rows, "qid string, table_name string, column_name string")


def execution_equal(spark: SparkSession, sf: str, pairs: list[tuple[str, int, str, str]]) -> DataFrame:
    """(qid, variant, equal): whether each statement gives the other's rows, as bags, compared where the data is."""
    own, rows = with_views(spark, sf), []
    for q, n, a, b in pairs:
        try:
            x, y = own.sql(a), own.sql(b)
            same = len(x.columns) == len(y.columns) and x.exceptAll(y).isEmpty() and y.exceptAll(x).isEmpty()
        except Exception as e:  # a statement that can't be analyzed or run is no alternative
            if "Spark" not in type(e).__module__ and "pyspark" not in type(e).__module__:
                raise
            same = False
        rows.append((q, n, same))
    return spark.createDataFrame(rows, "qid string, variant int, equal boolean")


def augment(spark: SparkSession, sf: str) -> DataFrame:
    """Gold columns, with those of alternatives that give the same rows."""
    sql = {q: s for q, _, s in fx.QUESTIONS}
    fine = {(r["qid"], r["variant"]) for r in execution_equal(spark, sf, [(q, n, s, sql[q]) for q, n, s in ALTERNATIVES]).collect() if r["equal"]}
    every = [(q, s) for q, _, s in fx.QUESTIONS] + [(q, s) for q, n, s in ALTERNATIVES if (q, n) in fine]
    return gold_columns(spark, sf, every).distinct()


def misaligned(spark: SparkSession, sf: str, statements: list[tuple[str, str]]) -> DataFrame:
    """(qid, reason) of statements that can't be analyzed or read no column."""
    own, rows = with_views(spark, sf), []
    for q, s in statements:
        try:
            if not scanned_columns(own.sql(s)):
                rows.append((q, "no columns"))
        except Exception as e:
            if "pyspark" not in type(e).__module__:
                raise
            rows.append((q, "not analyzed"))
    return spark.createDataFrame(rows, "qid string, reason string")


def negatives(scores: DataFrame, n: int = 7, seed: str = "neg") -> DataFrame:
    """(qid, pos, neg): n others for each gold column, by a digest, so that reruns and other engines draw the same."""
    p, o = scores.where("y = 1").select("qid", F.col("col_id").alias("pos")), scores.where("y = 0").select(F.col("qid").alias("q"), F.col("col_id").alias("neg"))
    pairs = p.join(o, F.col("qid") == F.col("q")).withColumn("d", digest(seed, F.col("qid"), F.col("pos").cast("string"), F.col("neg").cast("string")))
    return pairs.withColumn("r", F.row_number().over(Window.partitionBy("qid", "pos").orderBy("d", "neg"))).where(F.col("r") <= n).select("qid", "pos", "neg")


def grouped_scores(scores: DataFrame, drawn: DataFrame) -> DataFrame:
    """(qid, pos, fp, fn) for each drawn negative."""
    s = scores.select("qid", F.col("col_id").alias("pos"), F.col("score").alias("fp"))
    t = scores.select("qid", F.col("col_id").alias("neg"), F.col("score").alias("fn"))
    return drawn.join(s, ["qid", "pos"]).join(t, ["qid", "neg"])


def infonce(grouped: DataFrame) -> DataFrame:
    """(qid, pos, loss): minus the log of the gold column's softmax share among its group."""
    top = F.greatest(F.max("fn"), F.max("fp"))
    return grouped.groupBy("qid", "pos").agg(F.max("fp").alias("fp"), top.alias("m"), F.collect_list("fn").alias("fn")).select("qid", "pos", (F.log(F.exp(F.col("fp") - F.col("m")) + F.aggregate("fn", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("m")))) + F.col("m") - F.col("fp")).alias("loss"))


def margin(grouped: DataFrame, gamma: float = 1.0) -> DataFrame:
    return grouped.groupBy("qid").agg(F.sum(F.greatest(F.lit(0.0), gamma - F.col("fp") + F.col("fn"))).alias("loss"))


# --- registered queries --------------------------------------------------------------------------------------------------------
_DRAWN = f"drawn AS (SELECT a.qid, a.col_id AS pos, b.col_id AS neg, a.score AS fp, b.score AS fn FROM toy a JOIN toy b ON a.qid = b.qid AND a.y = 1 AND b.y = 0 QUALIFY row_number() OVER (PARTITION BY a.qid, a.col_id ORDER BY {digest_sql(repr('neg'), 'a.qid', 'CAST(a.col_id AS VARCHAR)', 'CAST(b.col_id AS VARCHAR)')}, b.col_id) <= 7)"


@query("gold_columns", f"WITH {cte('goldlist')} SELECT * FROM goldlist")
def _gold(spark: SparkSession, sf: str) -> DataFrame:
    return gold_columns(spark, sf, [(q, s) for q, _, s in fx.QUESTIONS])


@query("labels_neg", f"WITH {TOY_SQL} SELECT qid, col_id FROM toy WHERE y = 0")
def _neg(spark: SparkSession, sf: str) -> DataFrame:
    s, g, _ = toy_scores(spark, sf)
    return s.select("qid", "col_id").join(g, ["qid", "col_id"], "left_anti")


def _equal_sql() -> str:
    sql = {q: s for q, _, s in fx.QUESTIONS}
    return " UNION ALL ".join(f"SELECT '{q}' AS qid, {n} AS variant, NOT EXISTS (({a}) EXCEPT ALL ({sql[q]})) AND NOT EXISTS (({sql[q]}) EXCEPT ALL ({a})) AS equal" for q, n, a in ALTERNATIVES)


@query("augment_exec_equal", _equal_sql())
def _equal(spark: SparkSession, sf: str) -> DataFrame:
    sql = {q: s for q, _, s in fx.QUESTIONS}
    return execution_equal(spark, sf, [(q, n, s, sql[q]) for q, n, s in ALTERNATIVES])


@query("augment_gold")
def _augment(spark: SparkSession, sf: str) -> DataFrame:
    return augment(spark, sf)


@query("misaligned")
def _misaligned(spark: SparkSession, sf: str) -> DataFrame:
    return misaligned(spark, sf, [("bad1", "SELECT nothing_here FROM orders"), ("bad2", "SELECT 1 AS one"), *((q, s) for q, _, s in fx.QUESTIONS)])


@query("instances", f"WITH {TOY_SQL} SELECT qid, list(col_id ORDER BY col_id) FILTER (WHERE y = 1) AS positives, list(col_id ORDER BY col_id) FILTER (WHERE y = 0) AS negatives FROM toy GROUP BY qid")
def _instances(spark: SparkSession, sf: str) -> DataFrame:
    only = lambda v: F.array_sort(F.collect_list(F.when(F.col("y") == v, F.col("col_id"))))  # noqa: E731  a schema's columns
    return toy_scores(spark, sf)[0].groupBy("qid").agg(only(1).alias("positives"), only(0).alias("negatives"))


@query("neg_sample7", f"WITH {TOY_SQL}, {_DRAWN} SELECT qid, pos, neg FROM drawn")
def _seven(spark: SparkSession, sf: str) -> DataFrame:
    return negatives(toy_scores(spark, sf)[0])


@query("loss_infonce", f"WITH {TOY_SQL}, {_DRAWN} SELECT qid, pos, round(ln(exp(any_value(fp)) + sum(exp(fn))) - any_value(fp), 6) AS loss FROM drawn GROUP BY qid, pos")
def _infonce(spark: SparkSession, sf: str) -> DataFrame:
    s = toy_scores(spark, sf)[0]
    return infonce(grouped_scores(s, negatives(s))).withColumn("loss", F.round("loss", 6))


@query("loss_margin", f"WITH {TOY_SQL}, {_DRAWN} SELECT qid, round(sum(greatest(0.0, 1.0 - fp + fn)), 6) AS loss FROM drawn GROUP BY qid")
def _margin(spark: SparkSession, sf: str) -> DataFrame:
    s = toy_scores(spark, sf)[0]
    return margin(grouped_scores(s, negatives(s))).withColumn("loss", F.round("loss", 6))
