"""Accuracy measures over (qid, col_id, score, y), each from aggregates or one windowed sweep."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..registry import query
from .spanner import TOY_SQL, ranked, toy_scores


def roc_auc(scores: DataFrame, by: list[str] = ()) -> DataFrame:
    """Share of gold and other columns' pairs that are in order, ties a half: from sums per distinct score, so no pair is formed."""
    by = list(by)
    per = scores.groupBy(*by, "score").agg(F.sum("y").alias("p"), F.sum(1 - F.col("y")).alias("n"))
    below = F.coalesce(F.sum("n").over(Window.partitionBy(*by).orderBy("score").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    won = per.withColumn("won", F.col("p") * (below + F.col("n") / 2))
    return won.groupBy(*by).agg((F.sum("won") / F.nullif(F.sum("p") * F.sum("n"), F.lit(0))).alias("roc_auc"))


def sweep(scores: DataFrame, by: list[str] = ()) -> DataFrame:
    """(by, score, tp, kept, gold): what a threshold at each distinct score keeps. Counts per score come before the window."""
    per = scores.groupBy(*by, "score").agg(F.sum("y").alias("p"), F.count(F.lit(1)).alias("n"))
    down = Window.partitionBy(*by).orderBy(F.desc("score")).rowsBetween(Window.unboundedPreceding, 0)
    return per.select(*by, "score", "p", F.sum("p").over(down).alias("tp"), F.sum("n").over(down).alias("kept"), F.sum("p").over(Window.partitionBy(*by)).alias("gold"))


def pr_auc(scores: DataFrame, by: list[str] = ()) -> DataFrame:
    """Average precision by steps, tied scores as one step."""
    return sweep(scores, by).groupBy(*by).agg((F.sum(F.col("p") * F.col("tp") / F.col("kept")) / F.max("gold")).alias("pr_auc"))


def precision_at_recall(scores: DataFrame, targets: list[float], by: list[str] = ()) -> DataFrame:
    """(target, score, recall, precision) at the highest threshold that reaches each recall; the recall got is always told."""
    wanted = scores.sparkSession.createDataFrame([(t,) for t in targets], "target double")
    reached = sweep(scores, by).crossJoin(F.broadcast(wanted)).where(F.col("tp") / F.col("gold") >= F.col("target"))
    best = reached.groupBy(*by, "target").agg(F.max_by(F.struct("score", "tp", "kept", "gold"), "score").alias("b"))
    return best.select(*by, "target", "b.score", (F.col("b.tp") / F.col("b.gold")).alias("recall"), (F.col("b.tp") / F.col("b.kept")).alias("precision"))


def precision_recall_at(scores: DataFrame, tau: float) -> DataFrame:
    kept = F.col("score") >= tau
    return scores.agg((F.sum(F.when(kept, F.col("y")).otherwise(0)) / F.sum("y")).alias("recall"), F.try_divide(F.sum(F.when(kept, F.col("y")).otherwise(0)), F.count_if(kept)).alias("precision"))


def topk_curve(scores: DataFrame, ks: list[int]) -> DataFrame:
    """(k, recall, precision), means over questions: one ranking, then counts per question and k."""
    wanted = scores.sparkSession.createDataFrame([(k,) for k in ks], "k int")
    hits = ranked(scores).where(F.col("rank") <= max(ks)).crossJoin(F.broadcast(wanted)).where(F.col("rank") <= F.col("k")).groupBy("qid", "k").agg(F.sum("y").alias("hit"), F.count(F.lit(1)).alias("kept"))
    gold = scores.groupBy("qid").agg(F.sum("y").alias("gold")).where("gold > 0")
    return hits.join(gold, "qid").groupBy("k").agg(F.avg(F.col("hit") / F.col("gold")).alias("recall"), F.avg(F.col("hit") / F.col("kept")).alias("precision"))


def threshold_curve(scores: DataFrame, taus: list[float]) -> DataFrame:
    """(tau, precision, recall, f1), macro means; a question that keeps nothing has precision 0."""
    wanted = scores.sparkSession.createDataFrame([(t,) for t in taus], "tau double")
    kept = F.col("score") >= F.col("tau")
    per = scores.crossJoin(F.broadcast(wanted)).groupBy("qid", "tau").agg(F.sum(F.when(kept, F.col("y")).otherwise(0)).alias("tp"), F.count_if(kept).alias("kept"), F.sum("y").alias("gold")).where("gold > 0")
    p, r = F.coalesce(F.try_divide("tp", "kept"), F.lit(0.0)), F.col("tp") / F.col("gold")
    rows = per.select("tau", p.alias("p"), r.alias("r")).withColumn("f", F.coalesce(F.try_divide(2 * F.col("p") * F.col("r"), F.col("p") + F.col("r")), F.lit(0.0)))
    return rows.groupBy("tau").agg(F.avg("p").alias("precision"), F.avg("r").alias("recall"), F.avg("f").alias("f1"))


def score_hist(scores: DataFrame, bins: int, lo: float, hi: float) -> DataFrame:
    """(y, bin, n)."""
    return scores.groupBy("y", F.width_bucket("score", F.lit(lo), F.lit(hi), F.lit(bins)).alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def latency_report(timings: DataFrame) -> DataFrame:
    """(db_id, n_tables, n_columns, median_ms, n); timings: (db_id, n_tables, n_columns, ms)."""
    return timings.groupBy("db_id", "n_tables", "n_columns").agg(F.percentile("ms", F.lit(0.5)).alias("median_ms"), F.count(F.lit(1)).alias("n"))


# --- registered queries --------------------------------------------------------------------------------------------------------
_SWEEP = "per AS (SELECT score, sum(y) AS p, count(*) AS n FROM toy GROUP BY score), sw AS (SELECT score, p, sum(p) OVER w AS tp, sum(n) OVER w AS kept, sum(p) OVER () AS gold FROM per WINDOW w AS (ORDER BY score DESC ROWS UNBOUNDED PRECEDING))"
_AUC = lambda by: f"SELECT {by + ', ' if by else ''}round(sum(CASE WHEN a.score > b.score THEN 1.0 WHEN a.score = b.score THEN 0.5 ELSE 0.0 END)::DOUBLE / count(*), 6) AS roc_auc FROM toy a JOIN toy b ON a.y = 1 AND b.y = 0 {'AND a.qid = b.qid GROUP BY a.qid' if by else ''}"


def _r(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in cols})


@query("roc_auc", f"WITH {TOY_SQL} {_AUC('')}")
def _roc(spark: SparkSession, sf: str) -> DataFrame:
    return _r(roc_auc(toy_scores(spark, sf)[0]), "roc_auc")


@query("roc_auc_by_question", f"WITH {TOY_SQL} {_AUC('a.qid AS qid')}")
def _roc_q(spark: SparkSession, sf: str) -> DataFrame:
    return _r(roc_auc(toy_scores(spark, sf)[0], ["qid"]), "roc_auc")


@query("roc_auc_macro", f"WITH {TOY_SQL}, q AS (SELECT a.qid, sum(CASE WHEN a.score > b.score THEN 1.0 WHEN a.score = b.score THEN 0.5 ELSE 0.0 END)::DOUBLE / count(*) AS v FROM toy a JOIN toy b ON a.y = 1 AND b.y = 0 AND a.qid = b.qid GROUP BY a.qid) SELECT round(avg(v), 6) AS roc_auc FROM q")
def _roc_macro(spark: SparkSession, sf: str) -> DataFrame:
    return roc_auc(toy_scores(spark, sf)[0], ["qid"]).agg(F.round(F.avg("roc_auc"), 6).alias("roc_auc"))


@query("pr_auc", f"WITH {TOY_SQL}, {_SWEEP} SELECT round(sum(p * tp / kept::DOUBLE) / max(gold), 6) AS pr_auc FROM sw")
def _pr(spark: SparkSession, sf: str) -> DataFrame:
    return _r(pr_auc(toy_scores(spark, sf)[0]), "pr_auc")


@query("prec_at_recall", f"WITH {TOY_SQL}, {_SWEEP} SELECT target, round(score, 6) AS score, round(tp / gold::DOUBLE, 6) AS recall, round(tp / kept::DOUBLE, 6) AS precision FROM sw, (SELECT * FROM (VALUES (0.998::DOUBLE), (0.992::DOUBLE), (0.991::DOUBLE), (0.9::DOUBLE)) v(target)) WHERE tp / gold::DOUBLE >= target QUALIFY row_number() OVER (PARTITION BY target ORDER BY score DESC) = 1")
def _par(spark: SparkSession, sf: str) -> DataFrame:
    return _r(precision_at_recall(toy_scores(spark, sf)[0], [0.998, 0.992, 0.991, 0.9]), "score", "recall", "precision")


@query("prec_recall_at", f"WITH {TOY_SQL} SELECT round(sum(y) FILTER (WHERE score >= 0.75) / sum(y)::DOUBLE, 6) AS recall, round(sum(y) FILTER (WHERE score >= 0.75) / (count(*) FILTER (WHERE score >= 0.75))::DOUBLE, 6) AS precision FROM toy")
def _pra(spark: SparkSession, sf: str) -> DataFrame:
    return _r(precision_recall_at(toy_scores(spark, sf)[0], 0.75), "recall", "precision")


@query("topk_curve", f"WITH {TOY_SQL}, g AS (SELECT qid, sum(y) AS gold FROM toy GROUP BY qid), h AS (SELECT qid, k, sum(y) AS hit, count(*) AS kept FROM rk, (SELECT unnest(range(2, 21)) AS k) WHERE rank <= k GROUP BY qid, k) SELECT CAST(k AS INT) AS k, round(avg(hit / gold::DOUBLE), 6) AS recall, round(avg(hit / kept::DOUBLE), 6) AS precision FROM h JOIN g USING (qid) GROUP BY k")
def _topk(spark: SparkSession, sf: str) -> DataFrame:
    return _r(topk_curve(toy_scores(spark, sf)[0], list(range(2, 21))), "recall", "precision")


@query("threshold_curve", f"WITH {TOY_SQL}, t AS (SELECT unnest(range(0, 16)) / 10.0::DOUBLE AS tau), per AS (SELECT qid, tau, sum(y) FILTER (WHERE score >= tau) AS tp, count(*) FILTER (WHERE score >= tau) AS kept, sum(y) AS gold FROM toy, t GROUP BY qid, tau), pr AS (SELECT tau, coalesce(tp / nullif(kept, 0)::DOUBLE, 0.0) AS p, coalesce(tp, 0) / gold::DOUBLE AS r FROM per) SELECT tau, round(avg(p), 6) AS precision, round(avg(r), 6) AS recall, round(avg(coalesce(2 * p * r / nullif(p + r, 0), 0)), 6) AS f1 FROM pr GROUP BY tau")
def _tau(spark: SparkSession, sf: str) -> DataFrame:
    return _r(threshold_curve(toy_scores(spark, sf)[0], [k / 10 for k in range(16)]), "precision", "recall", "f1")


@query("score_hist", f"WITH {TOY_SQL} SELECT y, CAST(CASE WHEN score < 0 THEN 0 WHEN score >= 1.5 THEN 51 ELSE floor(score / 1.5 * 50) + 1 END AS BIGINT) AS bin, count(*) AS n FROM toy GROUP BY 1, 2")
def _hist(spark: SparkSession, sf: str) -> DataFrame:
    return score_hist(toy_scores(spark, sf)[0], 50, 0.0, 1.5)
