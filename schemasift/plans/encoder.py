"""The question-aware encoder: features through one tanh layer to a vector, and its yes-logit; trained by a group-wise softmax loss, the
graph layers by a margin loss over frozen vectors.

The labelled set is questions times a schema's columns; it is bounded by the questions and held on the driver. ``partial_gradients``
gives the same step from distributed rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import relgraph
from .context import FEATURES

#: Vector width and features by size. Fixed values.
SIZES = {"S": (16, 8), "M": (32, 10), "L": (64, 12)}
LEARNING_RATE, EPOCHS, GRAPH_RATE, GRAPH_EPOCHS, NEGATIVES, GAMMA = 0.02, 60, 5e-5, 40, 7, 1.0


class Encoder(NamedTuple):
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray

    def vectors(self, x: np.ndarray) -> np.ndarray:
        return np.tanh(x[:, : self.w1.shape[0]] @ self.w1 + self.b1)

    def logit(self, x: np.ndarray) -> np.ndarray:
        return self.vectors(x) @ self.w2


def fresh(size: str = "L", seed: int = 0) -> Encoder:
    d, f = SIZES[size]
    rng = np.random.default_rng(seed)
    return Encoder(rng.normal(0, 1 / np.sqrt(f), (f, d)), np.zeros(d), rng.normal(0, 1 / np.sqrt(d), d))


def low_rank(matrix: np.ndarray, rank: int, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Factors of an update to a frozen matrix; it starts at zero."""
    rng = np.random.default_rng(seed)
    return rng.normal(0, 0.1, (matrix.shape[0], rank)), np.zeros((rank, matrix.shape[1]))


def group_loss(score: np.ndarray, pos: int, others: np.ndarray) -> tuple[float, np.ndarray]:
    """(loss, gradient by score) of one gold column among its group."""
    at = np.concatenate(([pos], others))
    z = score[at] - score[at].max()
    p = np.exp(z) / np.exp(z).sum()
    g = np.zeros_like(score)
    np.add.at(g, at, p)
    g[pos] -= 1
    return float(-np.log(p[0])), g


def encoder_gradient(e: Encoder, x: np.ndarray, dscore: np.ndarray) -> Encoder:
    h = e.vectors(x)
    back = dscore[:, None] * e.w2 * (1 - h * h)
    return Encoder(x[:, : e.w1.shape[0]].T @ back, back.sum(0), h.T @ dscore)


def draws(y: np.ndarray, rng: np.random.Generator, n: int = NEGATIVES) -> list[tuple[int, np.ndarray]]:
    others = np.flatnonzero(y == 0)
    return [(int(p), rng.choice(others, min(n, len(others)), replace=False)) for p in np.flatnonzero(y == 1)]


class Adam:
    def __init__(self, like: list[np.ndarray], rate: float):
        self.m, self.v, self.t, self.rate = [np.zeros_like(x) for x in like], [np.zeros_like(x) for x in like], 0, rate

    def step(self, params: list[np.ndarray], grads: list[np.ndarray]) -> None:
        self.t += 1
        for p, g, m, v in zip(params, grads, self.m, self.v, strict=True):
            m *= 0.9
            m += 0.1 * g
            v *= 0.999
            v += 0.001 * g * g
            p -= self.rate * (m / (1 - 0.9**self.t)) / (np.sqrt(v / (1 - 0.999**self.t)) + 1e-8)


Groups = list[tuple[np.ndarray, np.ndarray]]  # per question: features, labels


def train_encoder(groups: Groups, size: str = "L", seed: int = 0, epochs: int = EPOCHS, batch: int = 8) -> tuple[Encoder, list[float]]:
    e, rng, losses = fresh(size, seed), np.random.default_rng(seed), []
    params = list(e)
    adam = Adam(params, LEARNING_RATE)
    for _ in range(epochs):
        total, n = 0.0, 0
        order = rng.permutation(len(groups))
        for i in range(0, len(order), batch):
            grads = [np.zeros_like(p) for p in params]
            for k in order[i : i + batch]:
                x, y = groups[k]
                score, d = Encoder(*params).logit(x), np.zeros(len(y))
                for pos, others in draws(y, rng):
                    loss, g = group_loss(score, pos, others)
                    total, n, d = total + loss, n + 1, d + g
                for a, b in zip(grads, encoder_gradient(Encoder(*params), x, d), strict=True):
                    a += b / max(1, len(order[i : i + batch]))
            adam.step(params, grads)
        losses.append(total / max(1, n))
    return Encoder(*params), losses


def train_graph(groups: Groups, encoder: Encoder, src: np.ndarray, dst: np.ndarray, rel: np.ndarray, depth: int = 2, width: int | None = None, seed: int = 0, epochs: int = GRAPH_EPOCHS, gamma: float = GAMMA, relations: int = relgraph.RELATIONS, rate: float = GRAPH_RATE) -> tuple[relgraph.Weights, list[float]]:
    """Graph layers over frozen vectors; all columns of a question are one graph. Layers as wide as the vectors start as the
    identity without messages, so training starts at the encoder's own scores."""
    d = encoder.w1.shape[1]
    start = relgraph.seeded([d, *([width or d] * depth)], seed + 1, relations)
    w = encoder.w2.copy() if (width or d) == d or not depth else start.w.copy()
    if (width or d) == d:
        for layer in start.layers:
            layer.own[:], layer.message[:] = np.eye(d), 0.0
    params = [x for layer in start.layers for x in layer] + [w]
    adam, rng, losses = Adam(params, rate), np.random.default_rng(seed), []
    rebuild = lambda: relgraph.Weights([relgraph.Layer(*params[4 * i : 4 * i + 4]) for i in range(depth)], params[-1], 0.0)
    for _ in range(epochs):
        total, n = 0.0, 0
        for k in rng.permutation(len(groups)):
            x, y = groups[k]
            weights, tape = rebuild(), []
            last = relgraph.forward(encoder.vectors(x), src, dst, rel, weights, tape)
            score, d_score, chosen = last @ weights.w, np.zeros(len(y)), draws(y, rng)
            for pos, others in chosen:
                bad = others[gamma - score[pos] + score[others] > 0]
                total, n = total + float((gamma - score[pos] + score[bad]).sum()), n + 1
                d_score[pos] -= len(bad)
                d_score[bad] += 1
            d_score /= max(1, len(chosen))
            _, grads = relgraph.backward(d_score[:, None] * weights.w, src, dst, weights, tape)
            adam.step(params, [g for layer in grads for g in layer] + [last.T @ d_score])
        losses.append(total / max(1, n))
    return rebuild(), losses


def encode_pairs(features: DataFrame, encoder: Encoder) -> DataFrame:
    """(qid, col_id, h, logit) in Arrow batches."""
    shared = features.sparkSession.sparkContext.broadcast(tuple(encoder))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        w1, b1, w2 = shared.value
        for b in batches:
            h = np.tanh(b[FEATURES].to_numpy(np.float64)[:, : w1.shape[0]] @ w1 + b1)
            yield pd.DataFrame({"qid": b["qid"], "col_id": b["col_id"], "h": list(h), "logit": h @ w2})

    return features.mapInPandas(run, "qid string, col_id long, h array<double>, logit double")


def partial_gradients(rows: DataFrame, encoder: Encoder) -> Encoder:
    """The encoder's gradient from distributed rows (features, dscore): each task sends one sum."""
    shared = rows.sparkSession.sparkContext.broadcast(tuple(encoder))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        w1, b1, w2 = shared.value
        total = np.zeros(w1.size + b1.size + w2.size)
        for b in batches:
            x, d = b[FEATURES].to_numpy(np.float64)[:, : w1.shape[0]], b["dscore"].to_numpy(np.float64)
            h = np.tanh(x @ w1 + b1)
            back = d[:, None] * w2 * (1 - h * h)
            total += np.concatenate([(x.T @ back).ravel(), back.sum(0), h.T @ d])
        yield pd.DataFrame({"at": np.arange(len(total)), "g": total})

    g = rows.mapInPandas(run, "at int, g double").groupBy("at").agg(F.sum("g").alias("g")).orderBy("at").toPandas()["g"].to_numpy()
    n, m = encoder.w1.size, encoder.b1.size
    return Encoder(g[:n].reshape(encoder.w1.shape), g[n : n + m], g[n + m :])
