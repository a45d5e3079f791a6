"""Workloads over replicated catalogs: the latency ladder, grouping of dated tables, key recovery, metadata."""

from __future__ import annotations

import time
from typing import NamedTuple

import numpy as np
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..registry import query
from ..sources import fixtures as fx
from ..sources.catalog import Catalog, from_parquet, questions, replicated
from . import depgraph, describe, encoder, metrics, relgraph, spanner
from .context import pair_features
from .profile import width_stats

#: Tables and columns of the ladder: the given tables, then widths of published databases. Fixed values.
LADDER = [(14, 63), (26, 352), (66, 457), (21, 6066), (78, 14433), (381, 23067)]


class Prepared(NamedTuple):
    """What is made once per database and kept for all questions."""

    columns: DataFrame
    forward: DataFrame
    nodes: DataFrame
    meta: DataFrame
    edges: Broadcast
    schema: Broadcast

    def drop(self) -> None:
        for df in (self.columns, self.forward, self.nodes, self.meta):
            df.unpersist()
        self.edges.destroy(), self.schema.destroy()


def prepare(c: Catalog) -> Prepared:
    columns = c.columns.cache()
    forward = depgraph.build(c._replace(columns=columns)).cache()
    nodes = depgraph.components(columns, forward).cache()
    meta = describe.describe_columns(columns).cache()
    nodes.count(), meta.count()
    return Prepared(columns, forward, nodes, meta, relgraph.held_edges(depgraph.with_reverse(forward), nodes), spanner.held_schema(columns, forward, nodes))


def timings(spark: SparkSession, sf: str, asked: DataFrame, points: list[tuple[int, int]] = LADDER, repeats: int = 3) -> DataFrame:
    """(db_id, n_tables, n_columns, n_questions, ms) of questions through features, encoder, graph and spanner together; the
    catalog, its graph and components are built before, once per database."""
    weights, e, n = relgraph.seeded([encoder.SIZES["L"][0]] * 3), encoder.fresh(), asked.count()
    none = spark.createDataFrame([], "qid string, col_id long, score double")
    out = []
    for tables, columns in points:
        p = prepare(from_parquet(spark, sf) if columns == 63 else replicated(spark, sf, tables, columns))
        for _ in range(repeats):
            began = time.perf_counter()
            vectors = encoder.encode_pairs(pair_features(asked, p.columns, p.meta, none), e)
            scores = relgraph.rerank(vectors.select("qid", "col_id", "h"), p.edges, p.nodes, weights)
            spanner.span(spanner.top_k(scores, 10), p.columns, p.forward, p.nodes, held=p.schema).write.format("noop").mode("overwrite").save()
            out.append((f"wide_{tables}_{columns}", tables, columns, n, (time.perf_counter() - began) * 1000))
        p.drop()
    return spark.createDataFrame(out, "db_id string, n_tables int, n_columns int, n_questions long, ms double")


@query("w03_latency")
def w03_latency(spark: SparkSession, sf: str) -> DataFrame:
    """The median time of one question on every rung of the ladder."""
    return metrics.latency_report(timings(spark, sf, questions(spark).where("qid = 'q08'")))


@query("w03_throughput")
def w03_throughput(spark: SparkSession, sf: str) -> DataFrame:
    """(db_id, n_tables, n_columns, columns_per_s): pairs of a question and a column per second if all questions come at once."""
    t = timings(spark, sf, questions(spark), repeats=2)
    return t.groupBy("db_id", "n_tables", "n_columns").agg((F.max(F.col("n_columns") * F.col("n_questions") / F.col("ms")) * 1000).alias("columns_per_s"))


@query("w11_grouping")
def w11_grouping(spark: SparkSession, sf: str) -> DataFrame:
    """Columns before and after merging thirty dated copies of one table."""
    c = from_parquet(spark, sf).columns
    days = F.explode(F.array(*(F.lit(f"202401{d:02d}") for d in range(1, 31))))
    every = c.unionByName(c.where("table_name = 'events'").withColumn("d", days).withColumn("table_name", F.concat_ws("_", "table_name", "d")).drop("d"))
    groups = describe.group_tables(every)
    kept = every.join(groups.where("table_name = representative").select("db_id", "table_name"), ["db_id", "table_name"], "left_semi")
    return every.agg(F.count(F.lit(1)).alias("n_before")).crossJoin(kept.agg(F.count(F.lit(1)).alias("n_after")))


@query("w12_widths")
def w12_widths(spark: SparkSession, sf: str) -> DataFrame:
    wide = [replicated(spark, sf, t, n).columns for t, n in LADDER[1:4]]
    every = from_parquet(spark, sf).columns
    for w in wide:
        every = every.union(w)
    return width_stats(every)


@query("w10_obfuscated")
def w10_obfuscated(spark: SparkSession, sf: str) -> DataFrame:
    """Names without vowels, without descriptions, and what the template makes of them."""
    c = from_parquet(spark, sf).columns.withColumn("column_name", F.regexp_replace("column_name", "(?<=[a-z])[aeiou]", ""))
    return describe.describe_columns(c)


def gradient_gap(seed: int = 0) -> float:
    """The largest gap between the graph layers' gradient and central differences, on a small graph."""
    rng = np.random.default_rng(seed)
    h, src, dst, rel = rng.normal(size=(5, 3)), np.array([0, 1, 2, 3, 4, 1]), np.array([1, 2, 0, 0, 0, 3]), np.array([0, 1, 2, 0, 0, 1])
    w = relgraph.seeded([3, 3, 3], seed, 3)
    target = rng.normal(size=(5, 3))
    value = lambda: float((relgraph.forward(h, src, dst, rel, w) * target).sum())
    tape: list = []
    relgraph.forward(h, src, dst, rel, w, tape)
    _, grads = relgraph.backward(target, src, dst, w, tape)
    worst = 0.0
    for layer, grad in zip(w.layers, grads, strict=True):
        for p, g in zip(layer, grad, strict=True):
            for at in np.ndindex(*p.shape):
                keep = p[at]
                p[at] = keep + 1e-6
                up = value()
                p[at] = keep - 1e-6
                worst = max(worst, abs((up - value()) / 2e-6 - g[at]))
                p[at] = keep
    return worst


assert set(fx.GOLD) == {q for q, _, _ in fx.QUESTIONS}
