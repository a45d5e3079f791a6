"""The whole filter: enrich once per database, score, rerank over the graph, span, and give the sub-schema."""

from __future__ import annotations

from functools import reduce
from typing import NamedTuple

import numpy as np
import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..registry import query
from ..sources import fixtures as fx
from ..sources.catalog import Catalog, cte, from_parquet, gold, questions
from . import baselines, depgraph, encoder, keys, metrics, relgraph, spanner
from .context import BIAS, FEATURES, FEATURES_SQL, HAND, LOGIT_SQL, features_of, linear
from .depgraph import EDGES_SQL
from .gold import with_views
from .describe import _MEANING, _OBSERVED, attach, describe_columns, observed


class Model(NamedTuple):
    encoder: encoder.Encoder
    graph: relgraph.Weights


class Enriched(NamedTuple):
    catalog: Catalog
    edges: DataFrame
    nodes: DataFrame
    meta: DataFrame


def enrich(spark: SparkSession, sf: str, db: str = "all14", scope: str = "both", save: str | None = None, recover: bool = False) -> Enriched:
    """Once per database: the graph with reversed edges, components and meanings; ``save`` writes them for later questions. ``recover``
    takes keys from the data where none is declared."""
    c = from_parquet(spark, sf, db)
    if recover:
        c = keys.recovered(spark, sf, c)
    forward = depgraph.build(c, scope)
    edges, nodes, meta = depgraph.with_reverse(forward), depgraph.components(c.columns, forward), attach(c.columns, observed(spark))
    if save:
        for name, df in (("columns", c.columns), ("edges", edges), ("nodes", nodes), ("meta", meta)):
            df.write.mode("overwrite").parquet(f"{save}/{db}/{name}")
        edges, nodes, meta = (spark.read.parquet(f"{save}/{db}/{n}") for n in ("edges", "nodes", "meta"))
    return Enriched(c, edges, nodes, meta)


def table_of(features: DataFrame, wanted: DataFrame) -> pd.DataFrame:
    """Features with labels on the driver: questions times a schema's columns."""
    return features.join(wanted.withColumn("y", F.lit(1)), ["qid", "col_id"], "left").fillna({"y": 0}).orderBy("qid", "col_id").toPandas()


def groups_of(rows: pd.DataFrame, keep: set[str] | None = None) -> encoder.Groups:
    return [(g[FEATURES].to_numpy(np.float64), g["y"].to_numpy()) for q, g in rows.groupby("qid") if keep is None or q in keep]


def split() -> tuple[set[str], set[str]]:
    """Every third question is for testing."""
    qs = [q for q, _, _ in fx.QUESTIONS]
    return {q for i, q in enumerate(qs) if i % 3}, {q for i, q in enumerate(qs) if i % 3 == 0}


def edge_arrays(rows: pd.DataFrame, edges: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    ids, e = np.sort(rows["col_id"].unique()), edges.select("src", "dst", "rel").toPandas()
    return np.searchsorted(ids, e["src"]), np.searchsorted(ids, e["dst"]), e["rel"].to_numpy()


def train(rows: pd.DataFrame, edges: DataFrame, keep: set[str], size: str = "L", depth: int = 2, seed: int = 0) -> Model:
    groups = groups_of(rows, keep)
    e, _ = encoder.train_encoder(groups, size, seed)
    return Model(e, encoder.train_graph(groups, e, *edge_arrays(rows, edges), depth=depth, seed=seed)[0])


def filter_schema(spark: SparkSession, sf: str, k: int = 10, model: Model | None = None, spanning: str | None = "greedy") -> DataFrame:
    """(qid, tables, columns, fks) of every question."""
    made = enrich(spark, sf)
    features = features_of(spark, sf)
    if model is None:
        model = train(table_of(features, gold(spark, made.catalog)), made.edges, split()[0])
    vectors = encoder.encode_pairs(features, model.encoder)
    scores = relgraph.rerank(vectors.select("qid", "col_id", "h"), made.edges, made.nodes, model.graph)
    chosen = spanner.top_k(scores, k)
    if spanning:
        own = depgraph.build(made.catalog, "own", link_keys=True)
        chosen = spanner.span(chosen, made.catalog.columns, own, made.nodes, spanning)
    return spanner.derive_subschema(chosen, made.catalog.columns, made.catalog.fk)


def all_scores(rows: pd.DataFrame, edges: DataFrame, columns: pd.DataFrame, seed: int = 0) -> pd.DataFrame:
    """(method, qid, col_id, score, y): every method's scores of all questions, trained on the learning questions only."""
    learn, _ = split()
    x, out = rows[FEATURES].to_numpy(np.float64), []
    put = lambda name, s: out.append(rows[["qid", "col_id", "y"]].assign(method=name, score=s))
    sigmoid = lambda z: 1 / (1 + np.exp(-z))
    table = rows["col_id"].map(columns.set_index("col_id")["table_name"])
    at = {f: rows[f] for f in FEATURES}
    raw = np.exp(1.2 * at["name_share"] + 1.6 * at["name_prefix"] + 2.2 * at["value_score"])
    put("PRUNE1", raw / raw.groupby([rows["qid"], table]).transform("sum"))
    small = encoder.train_encoder(groups_of(rows, learn), "S", seed)[0].logit(x)
    top = pd.Series(small).groupby([rows["qid"], table]).transform("max")
    put("TC-S", sigmoid(small) * sigmoid(top))
    put("TC-L+ch", sigmoid((mid := encoder.train_encoder(groups_of(rows, learn), "M", seed)[0].logit(x))) * sigmoid(pd.Series(mid).groupby([rows["qid"], table]).transform("max")))
    put("BI-A", at["name_grams"] + at["descr_share"])
    put("BI-B", at["name_share"] + at["table_grams"])
    put("CE-A", sigmoid(x @ np.array(HAND) + BIAS))
    put("CE-B", sigmoid(x[:, :7] @ np.array(HAND[:7]) + BIAS))
    for size, name in (("S", "0.6"), ("M", "4"), ("L", "8")):
        model = train(rows, edges, learn, size, seed=seed)
        put(f"LR-{name}", model.encoder.logit(x))
        s, d, r = edge_arrays(rows, edges)
        put(f"FULL-{name}", np.concatenate([relgraph.forward(model.encoder.vectors(g[FEATURES].to_numpy(np.float64)), s, d, r, model.graph) @ model.graph.w for _, g in rows.groupby("qid")]))
    return pd.concat(out)


def _scored(spark: SparkSession, sf: str) -> tuple[DataFrame, Enriched]:
    made = enrich(spark, sf)
    rows = table_of(features_of(spark, sf), gold(spark, made.catalog))
    every = all_scores(rows, made.edges, made.catalog.columns.toPandas())
    return spark.createDataFrame(every[["method", "qid", "col_id", "score", "y"]], "method string, qid string, col_id long, score double, y int"), made


# --- registered queries and workloads -----------------------------------------------------------------------------------------
@query("filter_schema")
def _filter(spark: SparkSession, sf: str) -> DataFrame:
    return filter_schema(spark, sf)


@query("enrich_catalog", f"WITH {cte('cols', 'fk').replace('cols AS', 'listed AS', 1)}, {keys.RECOVERED_SQL}, {EDGES_SQL}, {_OBSERVED}, m AS (SELECT table_name, column_name, CASE WHEN descr IS NULL THEN 'generated' ELSE 'observed' END AS descr_src FROM cols LEFT JOIN obs USING (table_name, column_name)), d AS (SELECT c.col_id, count(e.rel) AS degree FROM cols c LEFT JOIN (SELECT src AS v, rel FROM edges UNION ALL SELECT dst, rel FROM edges) e ON e.v = c.col_id GROUP BY c.col_id) SELECT col_id, table_name, column_name, is_pk, is_fk, degree, descr_src FROM cols JOIN d USING (col_id) JOIN m USING (table_name, column_name)")
def _enrich(spark: SparkSession, sf: str) -> DataFrame:
    made = enrich(spark, sf, scope="own", recover=True)
    degree = made.edges.groupBy(F.col("src").alias("col_id")).agg(F.count(F.lit(1)).alias("degree"))
    every = made.catalog.columns.join(degree, "col_id", "left").join(made.meta, ["table_name", "column_name"])
    return every.select("col_id", "table_name", "column_name", "is_pk", "is_fk", F.coalesce("degree", F.lit(0)).alias("degree"), "descr_src")


@query("encode_pairs")
def _encode(spark: SparkSession, sf: str) -> DataFrame:
    return encoder.encode_pairs(features_of(spark, sf), encoder.fresh())


@query("graph_rerank")
def _rerank(spark: SparkSession, sf: str) -> DataFrame:
    made = enrich(spark, sf)
    d, _ = encoder.SIZES["L"]
    return relgraph.rerank(encoder.encode_pairs(features_of(spark, sf), encoder.fresh()).select("qid", "col_id", "h"), made.edges, made.nodes, relgraph.seeded([d, d, d]))


@query("w01_main")
def w01_main(spark: SparkSession, sf: str) -> DataFrame:
    """(method, roc_auc, pr_auc, recall, precision) over the test questions, at recall 0.99 or more."""
    scored, _ = _scored(spark, sf)
    test = scored.where(F.col("qid").isin(sorted(split()[1])))
    p = metrics.precision_at_recall(test, [0.99], ["method"]).select("method", "recall", "precision")
    return metrics.roc_auc(test, ["method"]).join(metrics.pr_auc(test, ["method"]), "method").join(p, "method")


@query("ablation_topk")
def ablation_topk(spark: SparkSession, sf: str) -> DataFrame:
    """(config, k, recall, precision) for k of 2 to 20: all stages, without the spanner, without the graph."""
    scored, made = _scored(spark, sf)
    scored = scored.where(F.col("qid").isin(sorted(split()[1])))
    full, plain = scored.where("method = 'FULL-0.6'"), scored.where("method = 'LR-0.6'")
    ks = list(range(2, 21))
    by_k = spanner.ranked(full).crossJoin(spark.createDataFrame([(k,) for k in ks], "k int")).where("rank <= k").select(F.concat_ws("#", "qid", F.col("k").cast("string")).alias("qid"), "col_id")
    spanned = spanner.span(by_k, made.catalog.columns, depgraph.build(made.catalog, "own", link_keys=True), made.nodes)
    parts = F.split("qid", "#")
    wanted = gold(spark, made.catalog)
    n = wanted.groupBy("qid").agg(F.count(F.lit(1)).alias("gold"))
    hits = spanned.select(parts[0].alias("qid"), parts[1].cast("int").alias("k"), "col_id").join(wanted.withColumn("y", F.lit(1)), ["qid", "col_id"], "left").groupBy("qid", "k").agg(F.sum(F.coalesce("y", F.lit(0))).alias("hit"), F.count(F.lit(1)).alias("kept")).join(n, "qid")
    with_tree = hits.groupBy("k").agg(F.avg(F.col("hit") / F.col("gold")).alias("recall"), F.avg(F.col("hit") / F.col("kept")).alias("precision"))
    out = [(with_tree, "full"), (metrics.topk_curve(full.drop("method"), ks), "no_spanner"), (metrics.topk_curve(plain.drop("method"), ks), "no_graph")]
    return reduce(DataFrame.unionByName, (df.withColumn("config", F.lit(c)) for df, c in out))


@query("w05_thresholds")
def w05_thresholds(spark: SparkSession, sf: str) -> DataFrame:
    """(tau, precision, recall, f1) of the full method's scores scaled to 0..1."""
    scored, _ = _scored(spark, sf)
    s = scored.where("method = 'FULL-8'").withColumn("score", 1 / (1 + F.exp(-F.col("score"))))
    return metrics.threshold_curve(s, [k / 100 for k in range(101)])


@query("w06_distributions")
def w06_distributions(spark: SparkSession, sf: str) -> DataFrame:
    scored, _ = _scored(spark, sf)
    return metrics.score_hist(scored.where("method = 'FULL-8'").withColumn("score", 1 / (1 + F.exp(-F.col("score")))), 50, 0.0, 1.0)


def sensitivity(spark: SparkSession, sf: str, depths: list[int] = (0, 1, 2, 3, 4), sizes: list[str] = ("S", "M", "L")) -> DataFrame:
    """(depth, size, roc_auc, pr_auc) over the test questions."""
    made = enrich(spark, sf)
    rows = table_of(features_of(spark, sf), gold(spark, made.catalog))
    learn, test = split()
    s, d, r = edge_arrays(rows, made.edges)
    out = []
    for size in sizes:
        for depth in depths:
            m = train(rows, made.edges, learn, size, depth)
            for q, g in rows.groupby("qid"):
                if q in test:
                    out += [(depth, size, q, int(c), float(v), int(y)) for c, v, y in zip(g["col_id"], relgraph.forward(m.encoder.vectors(g[FEATURES].to_numpy(np.float64)), s, d, r, m.graph) @ m.graph.w, g["y"], strict=True)]
    scored = spark.createDataFrame(out, "depth int, size string, qid string, col_id long, score double, y int")
    by = ["depth", "size"]
    return metrics.roc_auc(scored, by).join(metrics.pr_auc(scored, by), by)


@query("w04_sensitivity")
def w04_sensitivity(spark: SparkSession, sf: str) -> DataFrame:
    """The whole grid of depths and widths."""
    return sensitivity(spark, sf)


@query("graph_variants")
def graph_variants(spark: SparkSession, sf: str) -> DataFrame:
    """(scope, reverse, link_keys, roc_auc, pr_auc) of the test questions for each form of the dependency graph."""
    c = from_parquet(spark, sf)
    rows, (learn, test), out = table_of(features_of(spark, sf), gold(spark, c)), split(), []
    for scope, reverse, link in [("own", True, False), ("referenced", True, False), ("both", True, False), ("both", False, False), ("both", True, True)]:
        forward = depgraph.build(c, scope, link)
        edges = depgraph.with_reverse(forward) if reverse else forward
        m, (s, d, r) = train(rows, edges, learn, "S"), edge_arrays(rows, edges)
        for q, g in rows.groupby("qid"):
            if q in test:
                out += [(scope, reverse, link, q, int(i), float(v), int(y)) for i, v, y in zip(g["col_id"], relgraph.forward(m.encoder.vectors(g[FEATURES].to_numpy(np.float64)), s, d, r, m.graph) @ m.graph.w, g["y"], strict=True)]
    scored = spark.createDataFrame(out, "scope string, reverse boolean, link_keys boolean, qid string, col_id long, score double, y int")
    by = ["scope", "reverse", "link_keys"]
    return metrics.roc_auc(scored, by).join(metrics.pr_auc(scored, by), by)


def runs_on(spark: SparkSession, sf: str, kept: dict[str, set[str]]) -> DataFrame:
    """(qid, answerable): whether the gold statement, run on views that have the kept columns only, gives the rows that it gives on
    the whole tables. It measures what the kept columns allow, not what a language model would write."""
    rows = []
    whole = with_views(spark, sf)
    for q, _, sql in fx.QUESTIONS:
        own, by = spark.newSession(), {}
        for name in kept.get(q, ()):
            table, column = name.split(".", 1)
            by.setdefault(table, []).append(column)
        for table, names in by.items():
            own.read.parquet(f"{sf}/{table}.parquet").select(*sorted(names)).createOrReplaceTempView(table)
        try:
            x, y = own.sql(sql), whole.sql(sql)
            # as both read the same files, the views' statement can be compared in the session of the whole tables
            same = x.columns == y.columns and _bag(x) == _bag(y)
        except AnalysisException:  # a column or table that the statement names isn't there
            same = False
        rows.append((q, same))
    return spark.createDataFrame(rows, "qid string, answerable boolean")


def _bag(df: DataFrame) -> tuple[int, object]:
    """A row count and an order-free digest of all rows, computed where the data is."""
    return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64(*(F.col(f"`{c}`") for c in df.columns)).cast("decimal(38,0)"))).first())


@query("exec_on_subschema")
def exec_on_subschema(spark: SparkSession, sf: str) -> DataFrame:
    """Gold statements on the sub-schemas of the trained filter."""
    return runs_on(spark, sf, {r["qid"]: set(r["columns"]) for r in filter_schema(spark, sf, k=16).collect()})


_GOLD_ROWS = ", ".join(f"('{q}', '{c}')" for q in fx.GOLD for c in fx.GOLD[q].split())


@query("exec_on_ranked", f"WITH {FEATURES_SQL}, r AS (SELECT qid, table_name || '.' || column_name AS name FROM feats JOIN cols USING (col_id) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY round({LOGIT_SQL}, 9) DESC, col_id) <= 16), g AS (SELECT * FROM (VALUES {_GOLD_ROWS}) v(qid, name)) SELECT g.qid, count(*) = count(r.name) AS answerable FROM g LEFT JOIN r ON g.qid = r.qid AND g.name = r.name GROUP BY g.qid")
def exec_on_ranked(spark: SparkSession, sf: str) -> DataFrame:
    """Gold statements on the best 16 columns of the untrained encoder. Its SQL tells by inclusion what is found here by running."""
    order = Window.partitionBy("qid").orderBy(F.desc(F.round(linear(), 9)), "col_id")
    best = features_of(spark, sf).select("qid", "col_id", F.row_number().over(order).alias("rank")).where("rank <= 16").join(from_parquet(spark, sf).columns, "col_id")
    kept: dict[str, set[str]] = {}
    for r in best.select("qid", F.concat_ws(".", "table_name", "column_name").alias("name")).collect():  # 16 a question
        kept.setdefault(r["qid"], set()).add(r["name"])
    return runs_on(spark, sf, kept)
