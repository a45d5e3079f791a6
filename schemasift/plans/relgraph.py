"""Relation-typed attention message passing over the column graph: vectorised inside a group, and as joins and aggregates."""

from __future__ import annotations

from functools import reduce
from typing import NamedTuple

import numpy as np
import pandas as pd
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..registry import query
from ..sources.catalog import from_parquet
from .depgraph import ALL_SQL, build, with_reverse

RELATIONS = 6


class Layer(NamedTuple):
    own: np.ndarray  # (d, d')
    message: np.ndarray  # (relations, d, d')
    ask: np.ndarray  # (relations, d, k)
    answer: np.ndarray  # (relations, d, k)


class Weights(NamedTuple):
    layers: list[Layer]
    w: np.ndarray
    b: float


def seeded(widths: list[int], seed: int = 1, relations: int = RELATIONS) -> Weights:
    """Weights for vectors of widths[0], through layers of the other widths."""
    rng = np.random.default_rng(seed)
    layers = [Layer(np.eye(d, e) + rng.normal(0, 0.02, (d, e)), rng.normal(0, 0.1 / np.sqrt(d), (relations, d, e)), *(rng.normal(0, 1 / np.sqrt(d), (relations, d, d)) for _ in range(2))) for d, e in zip(widths, widths[1:], strict=False)]
    return Weights(layers, rng.normal(0, 1 / np.sqrt(widths[-1]), widths[-1]), 0.0)


def softmax_by(score: np.ndarray, group: np.ndarray, n: int) -> np.ndarray:
    top = np.full(n, -np.inf)
    np.maximum.at(top, group, score)
    e = np.exp(score - top[group])
    return e / np.bincount(group, e, n)[group]


def attention(h: np.ndarray, src: np.ndarray, dst: np.ndarray, layer: Layer, r: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(weights of edges, what their ends ask, what their beginnings answer) within one relation."""
    ask, answer = h[dst] @ layer.ask[r], h[src] @ layer.answer[r]
    return softmax_by((ask * answer).sum(1) / np.sqrt(ask.shape[1]), dst, len(h)), ask, answer


def forward(h: np.ndarray, src: np.ndarray, dst: np.ndarray, rel: np.ndarray, weights: Weights, tape: list | None = None) -> np.ndarray:
    """The last layer's vectors. tape gets what ``backward`` needs."""
    for layer in weights.layers:
        out, seen = h @ layer.own, []
        for r in range(len(layer.message)):
            e = np.flatnonzero(rel == r)
            if e.size:
                share, ask, answer = attention(h, src[e], dst[e], layer, r)
                value = h[src[e]] @ layer.message[r]
                np.add.at(out, dst[e], share[:, None] * value)
                seen.append((r, e, share, ask, answer, value))
        if tape is not None:
            tape.append((h, seen))
        h = out
    return h


def backward(grad: np.ndarray, src: np.ndarray, dst: np.ndarray, weights: Weights, tape: list) -> tuple[np.ndarray, list[Layer]]:
    """Gradients of the first vectors and of the layers, from that of the last vectors."""
    out = []
    for layer, (h, seen) in zip(reversed(weights.layers), reversed(tape), strict=True):
        dh, d = grad @ layer.own.T, Layer(h.T @ grad, *(np.zeros_like(x) for x in layer[1:]))
        for r, e, share, ask, answer, value in seen:
            s, t = src[e], dst[e]
            g = grad[t]
            to_share, to_value = (g * value).sum(1), share[:, None] * g
            d.message[r][:] = h[s].T @ to_value
            np.add.at(dh, s, to_value @ layer.message[r].T)
            mean = np.bincount(t, share * to_share, len(h))
            to_score = (share * (to_share - mean[t]) / np.sqrt(ask.shape[1]))[:, None]
            d.ask[r][:], d.answer[r][:] = h[t].T @ (to_score * answer), h[s].T @ (to_score * ask)
            np.add.at(dh, t, to_score * answer @ layer.ask[r].T)
            np.add.at(dh, s, to_score * ask @ layer.answer[r].T)
        out.append(d)
        grad = dh
    return grad, out[::-1]


def held_edges(edges: DataFrame, nodes: DataFrame) -> Broadcast:
    """Each component's edges, once per database: a schema's edges are bounded by its columns, so every task may hold them."""
    rows = edges.join(nodes.withColumnRenamed("col_id", "src"), "src").select("comp", "src", "dst", "rel").toPandas()
    return edges.sparkSession.sparkContext.broadcast({c: g[["src", "dst", "rel"]].to_numpy() for c, g in rows.groupby("comp")})


def rerank(vectors: DataFrame, edges: DataFrame | Broadcast, nodes: DataFrame, weights: Weights) -> DataFrame:
    """(qid, col_id, score). vectors: (qid, col_id, h); edges: a table or what ``held_edges`` made of it; nodes: (col_id, comp).
    Questions and graph components are groups of their own: messages never cross components, so all layers run inside one
    group after a single shuffle."""
    spark = vectors.sparkSession
    listed = held_edges(edges, nodes) if isinstance(edges, DataFrame) else edges
    plain = ([[np.asarray(x) for x in layer] for layer in weights.layers], weights.w, weights.b)
    shared = spark.sparkContext.broadcast(plain)

    def run(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        layers, w, b = shared.value
        g = g.sort_values("col_id")
        ids = g["col_id"].to_numpy()
        e = listed.value.get(key[1], np.zeros((0, 3), np.int64))
        h = forward(np.stack(g["h"].to_numpy()).astype(np.float64), np.searchsorted(ids, e[:, 0]), np.searchsorted(ids, e[:, 1]), e[:, 2], Weights([Layer(*x) for x in layers], w, b))
        return pd.DataFrame({"qid": key[0], "col_id": ids, "score": h @ w + b})

    return vectors.join(F.broadcast(nodes.select("col_id", "comp")), "col_id").groupBy("qid", "comp").applyInPandas(run, "qid string, col_id long, score double")


def as_rows(spark: SparkSession, layer: Layer, dims: int) -> DataFrame:
    """(name, rel, i, j, w) of a layer's weights."""
    data = [("own", -1, i, j, float(layer.own[i, j])) for i in range(dims) for j in range(dims)]
    data += [(n, r, i, j, float(x[r, i, j])) for n, x in (("message", layer.message), ("ask", layer.ask), ("answer", layer.answer)) for r in range(len(x)) for i in range(dims) for j in range(dims)]
    return spark.createDataFrame(data, "name string, rel int, i int, j int, w double")


def relational_attention(h: DataFrame, edges: DataFrame, weights: DataFrame, dims: int) -> DataFrame:
    """(src, dst, rel, alpha); h: (col_id, i, x)."""
    ask = h.join(weights.where("name = 'ask'"), "i").groupBy(F.col("col_id").alias("dst"), "rel", "j").agg(F.sum(F.col("x") * F.col("w")).alias("a"))
    answer = h.join(weights.where("name = 'answer'"), "i").groupBy(F.col("col_id").alias("src"), "rel", "j").agg(F.sum(F.col("x") * F.col("w")).alias("b"))
    score = edges.join(ask, ["dst", "rel"]).join(answer, ["src", "rel", "j"]).groupBy("src", "dst", "rel").agg((F.sum(F.col("a") * F.col("b")) / float(np.sqrt(dims))).alias("s"))
    by = Window.partitionBy("dst", "rel")
    return score.withColumn("e", F.exp(F.col("s") - F.max("s").over(by))).select("src", "dst", "rel", (F.col("e") / F.sum("e").over(by)).alias("alpha"))


def relational_layer(h: DataFrame, edges: DataFrame, weights: DataFrame, dims: int) -> DataFrame:
    """(col_id, i, x) after one layer, by joins and aggregates only."""
    alpha = relational_attention(h, edges, weights, dims)
    value = h.join(weights.where("name = 'message'"), "i").groupBy(F.col("col_id").alias("src"), "rel", "j").agg(F.sum(F.col("x") * F.col("w")).alias("v"))
    sent = alpha.join(value, ["src", "rel"]).select(F.col("dst").alias("col_id"), "j", (F.col("alpha") * F.col("v")).alias("y"))
    own = h.join(weights.where("name = 'own'"), "i").select("col_id", "j", (F.col("x") * F.col("w")).alias("y"))
    return own.union(sent).groupBy("col_id", F.col("j").alias("i")).agg(F.sum("y").alias("x"))


# --- registered queries --------------------------------------------------------------------------------------------------------
_D = 3


def _sample_layer() -> Layer:
    at = lambda k, *shape: np.round(np.sin(np.arange(int(np.prod(shape))) * 1.7 + k), 4).reshape(shape)
    return Layer(at(1, _D, _D), at(2, RELATIONS, _D, _D), at(3, RELATIONS, _D, _D), at(4, RELATIONS, _D, _D))


def _weights_sql() -> str:
    layer = _sample_layer()
    rows = [("own", -1, i, j, layer.own[i, j]) for i in range(_D) for j in range(_D)]
    rows += [(n, r, i, j, x[r, i, j]) for n, x in (("message", layer.message), ("ask", layer.ask), ("answer", layer.answer)) for r in range(RELATIONS) for i in range(_D) for j in range(_D)]
    return "wt AS (SELECT * FROM (VALUES " + ", ".join(f"('{n}', {r}, {i}, {j}, CAST({w} AS DOUBLE))" for n, r, i, j, w in rows) + ") v(name, rel, i, j, w))"


def _layer_sql(both: bool) -> str:
    e = "SELECT src, dst, rel FROM edges UNION ALL SELECT dst, src, rel + 3 FROM edges" if both else "SELECT src, dst, rel FROM edges"
    return f"""{ALL_SQL}, {_weights_sql()}, e AS ({e}), h AS (SELECT col_id, i, CAST(col_id * (i + 1) % 7 AS DOUBLE) / 7 AS x FROM cols, (SELECT unnest(range({_D})) AS i)),
ask AS (SELECT col_id AS dst, rel, j, sum(x * w) AS a FROM h JOIN wt USING (i) WHERE name = 'ask' GROUP BY ALL), ans AS (SELECT col_id AS src, rel, j, sum(x * w) AS b FROM h JOIN wt USING (i) WHERE name = 'answer' GROUP BY ALL),
sc AS (SELECT src, dst, rel, sum(a * b) / sqrt({_D}) AS s FROM e JOIN ask USING (dst, rel) JOIN ans USING (src, rel, j) GROUP BY ALL),
ex AS (SELECT *, exp(s - max(s) OVER (PARTITION BY dst, rel)) AS x FROM sc), alpha AS (SELECT src, dst, rel, x / sum(x) OVER (PARTITION BY dst, rel) AS alpha FROM ex),
val AS (SELECT col_id AS src, rel, j, sum(x * w) AS v FROM h JOIN wt USING (i) WHERE name = 'message' GROUP BY ALL),
y AS (SELECT dst AS col_id, j, alpha * v AS y FROM alpha JOIN val USING (src, rel) UNION ALL SELECT col_id, j, x * w FROM h JOIN wt USING (i) WHERE name = 'own')"""


def _sample(spark: SparkSession, sf: str, both: bool) -> tuple[DataFrame, DataFrame, DataFrame]:
    c = from_parquet(spark, sf)
    edges = with_reverse(build(c)) if both else build(c)
    h = c.columns.select("col_id", F.explode(F.array(*(F.struct(F.lit(i).alias("i"), ((F.col("col_id") * (i + 1) % 7).cast("double") / 7).alias("x")) for i in range(_D)))).alias("s")).select("col_id", "s.i", "s.x")
    return h, edges.select("src", "dst", "rel"), as_rows(spark, _sample_layer(), _D)


_IN_NATIONS = f"""{_weights_sql()}, n AS (SELECT c_custkey * 3 + 1 AS src, c_nationkey * 3 AS dst, 0 AS rel, c_acctbal / 10000 AS balance, c_nationkey / 25.0::DOUBLE AS place FROM customer UNION ALL SELECT s_suppkey * 3 + 2, s_nationkey * 3, 1, s_acctbal / 10000, s_nationkey / 25.0::DOUBLE FROM supplier),
h AS (SELECT src AS col_id, unnest([0, 1, 2]) AS i, unnest([balance, place, 1.0::DOUBLE]) AS x FROM n UNION ALL SELECT n_nationkey * 3, unnest([0, 1, 2]), unnest([n_regionkey / 5.0::DOUBLE, n_nationkey / 25.0::DOUBLE, 1.0::DOUBLE]) FROM nation),
ask AS (SELECT col_id AS dst, rel, j, sum(x * w) AS a FROM h JOIN wt USING (i) WHERE name = 'ask' GROUP BY ALL), ans AS (SELECT col_id AS src, rel, j, sum(x * w) AS b FROM h JOIN wt USING (i) WHERE name = 'answer' GROUP BY ALL),
sc AS (SELECT src, dst, rel, sum(a * b) / sqrt({_D}) AS s FROM n JOIN ask USING (dst, rel) JOIN ans USING (src, rel, j) GROUP BY ALL),
ex AS (SELECT *, exp(s - max(s) OVER (PARTITION BY dst, rel)) AS x FROM sc)"""


@query("edge_softmax", f"WITH {_IN_NATIONS} SELECT src, dst, rel, round(x / sum(x) OVER (PARTITION BY dst, rel), 6) AS alpha FROM ex")
def _softmax(spark: SparkSession, sf: str) -> DataFrame:
    """Attention of nations to their customers (relation 0) and suppliers (1); features are balance, place and a constant."""
    t = lambda n: spark.read.parquet(f"{sf}/{n}.parquet")
    ends = t("customer").selectExpr("c_custkey * 3 + 1 AS src", "c_nationkey * 3 AS dst", "0 AS rel", "c_acctbal / 10000 AS balance", "c_nationkey / 25D AS place")
    ends = ends.union(t("supplier").selectExpr("s_suppkey * 3 + 2", "s_nationkey * 3", "1", "s_acctbal / 10000", "s_nationkey / 25D"))
    nations = t("nation").selectExpr("n_nationkey * 3L AS col_id", "array(n_regionkey / 5D, n_nationkey / 25D, 1D) AS x")
    h = ends.selectExpr("src AS col_id", "array(balance, place, 1D) AS x").union(nations).select("col_id", F.posexplode("x").alias("i", "x"))
    used = F.broadcast(as_rows(spark, _sample_layer(), _D).where("rel IN (0, 1)"))
    return relational_attention(h, ends.select("src", "dst", "rel"), used, _D).withColumn("alpha", F.round("alpha", 6))


@query("graph_layer_join", f"WITH {_layer_sql(True)} SELECT col_id, j AS i, round(sum(y), 6) AS x FROM y GROUP BY col_id, j")
def _layer(spark: SparkSession, sf: str) -> DataFrame:
    return relational_layer(*_sample(spark, sf, True), _D).withColumn("x", F.round("x", 6))


@query("graph_layer_fwd", f"WITH {_layer_sql(False)} SELECT col_id, j AS i, round(sum(y), 6) AS x FROM y GROUP BY col_id, j")
def _layer_fwd(spark: SparkSession, sf: str) -> DataFrame:
    return relational_layer(*_sample(spark, sf, False), _D).withColumn("x", F.round("x", 6))


@query("graph_layer_numpy", f"WITH {_layer_sql(True)} SELECT col_id, j AS i, round(sum(y), 6) AS x FROM y GROUP BY col_id, j")
def _layer_numpy(spark: SparkSession, sf: str) -> DataFrame:
    """The same layer through the grouped form: a unit vector for each place reads it out."""
    c = from_parquet(spark, sf)
    from .depgraph import components

    edges = with_reverse(build(c))
    nodes = components(c.columns, build(c))
    h = c.columns.select(F.lit("q").alias("qid"), "col_id", F.array(*((F.col("col_id") * (i + 1) % 7).cast("double") / 7 for i in range(_D))).alias("h"))
    out = [rerank(h, edges, nodes, Weights([_sample_layer()], np.eye(_D)[i], 0.0)).select("col_id", F.lit(i).alias("i"), F.round("score", 6).alias("x")) for i in range(_D)]
    return reduce(DataFrame.union, out)
