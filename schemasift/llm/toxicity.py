"""Toxicity scores: gradient-boosted trees over dense features of whole texts, with isotonic calibration.

Features are densities of a lexicon (words and word beginnings whose presence speaks for the label), their nearness to words of
the second person, capitals, punctuation, and obfuscation (letters mixed with digits or signs, stretched letters, lexicon words
behind such spelling). Lexicon, trees and calibration are fit on at most ``MAX_ROWS`` labelled documents, those with
the smallest digests of their ids: lexicon and trees on four folds in five of them, calibration on the fifth fold's scores.
Held-out documents never enter. Scoring covers every document and all of its text.

Cases: null and empty texts have all features 0 and get a score all the same; documents without a label, or with a null one, teach
nothing; a document labelled twice counts as toxic if either says so; without both classes every score is the share of
toxic rows learned (0 if none); an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .boosting import Isotonic, Trees
from .common import by_row, drop_durable, durable, held_out, slices
from .hashing import mix, wide

U = np.uint64

#: Labelled documents that the classifier is fit on at most, terms tried, and terms kept.
MAX_ROWS, MAX_TRIED, MAX_TERMS = 40_000, 200_000, 20_000
LEAST_SEEN, LEAST_WEIGHT, PREFIXES = 5, 1.8, (4, 6)
#: Words of the second person. Fixed values.
SECOND_PERSON = "you your yours yourself u ur du dich dir dein deine deiner ihr euch sie tu te toi ton ta tes vous votre vos tú ti tuyo usted ustedes vosotros vuestro".split()
NAMES = ["weight_share", "hit_share", "hits", "top_weight", "near_second_share", "near_second", "second_share", "capital_share", "bang_share", "sign_share", "odd_share", "odd_hits", "stretched_share", "single_share", "words"]
_B = np.arange(256)
_LETTER = (_B >= 128) | ((_B | 32) >= 97) & ((_B | 32) <= 122)
_DIGIT = (_B >= 48) & (_B <= 57)
#: Signs and digits read as letters inside words. Fixed values.
_MASKED = np.isin(_B, np.frombuffer(b"0134578@$", np.uint8))
_PLAIN = np.frombuffer(bytes(range(256)).translate(bytes.maketrans(b"0134578@$", b"oieastbas")), np.uint8)
_LOWER = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], np.uint8)


def codes(eight: np.ndarray, start: np.ndarray, size: np.ndarray) -> list[np.ndarray]:
    """A number for the word (by its first and last eight bytes and its length) and for each of its beginnings, 0 where
    the word is too short to have one. eight: ``wide`` of lower-case bytes."""
    first = eight[start]
    part = np.minimum(size, 8).astype(np.uint64)
    inside = np.where(part == 8, U(0xFFFFFFFFFFFFFFFF), (U(1) << (U(8) * (part % U(8)))) - U(1))
    last = np.where(size > 8, eight[start + np.maximum(size - 8, 0)], U(0))
    word = np.where((size > 2) & (size <= 40), mix((first & inside) ^ mix(last, 2), 1) ^ size.astype(np.uint64), U(0))
    return [word, *(np.where(size > n, mix(first & U((1 << 8 * n) - 1), 10 + n), U(0)) for n in PREFIXES)]


def words_of(data: np.ndarray, at: np.ndarray, more: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, first byte, bytes) of every run of letters and digits (and of bytes in ``more``)."""
    inner = (_LETTER | _DIGIT if more is None else _LETTER | _DIGIT | more)[data]
    edge = np.zeros(len(data) + 1, bool)
    edge[at] = True
    start = np.flatnonzero(inner & (~np.concatenate(([False], inner[:-1])) | edge[:-1]))
    end = np.flatnonzero(inner & (~np.concatenate((inner[1:], [False])) | edge[1:])) + 1
    return np.searchsorted(at, start, side="right") - 1, start, end - start


class Lookup:
    """Weights of term numbers: a table of bits first, then a binary search for what passes."""

    def __init__(self, weights: dict[int, float]):
        self.keys = np.array(sorted(weights), np.uint64)
        self.values = np.array([weights[int(k)] for k in self.keys], np.float64)
        self.table = np.zeros(1 << 20, bool)
        self.table[(self.keys >> U(44)).astype(np.int64)] = True

    def __call__(self, numbers: np.ndarray) -> np.ndarray:
        out = np.zeros(len(numbers))
        maybe = np.flatnonzero(self.table[(numbers >> U(44)).astype(np.int64)])
        if maybe.size and len(self.keys):
            k = np.minimum(np.searchsorted(self.keys, numbers[maybe]), len(self.keys) - 1)
            out[maybe] = np.where((self.keys[k] == numbers[maybe]) & (numbers[maybe] > 0), self.values[k], 0.0)
        return out


def second_person() -> Lookup:
    text = [w.encode() for w in SECOND_PERSON]
    at = np.concatenate(([0], np.cumsum([len(w) for w in text])))
    data = np.frombuffer(b"".join(text), np.uint8)
    return Lookup({int(short(wide(data), at[i : i + 1], np.array([len(w)]))[0]): 1.0 for i, w in enumerate(text)})


def short(eight: np.ndarray, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """A number for words of up to eight bytes, 0 for longer ones."""
    part = np.minimum(size, 8).astype(np.uint64)
    inside = np.where(part == 8, U(0xFFFFFFFFFFFFFFFF), (U(1) << (U(8) * (part % U(8)))) - U(1))
    return np.where(size <= 8, mix(eight[start] & inside, 20), U(0))


def features(data: np.ndarray, at: np.ndarray, lexicon: Lookup, second: Lookup) -> np.ndarray:
    """The features of each text."""
    texts, out = len(at) - 1, np.zeros((len(at) - 1, len(NAMES)))
    if not len(data):
        return out
    low = _LOWER[data]
    eight = wide(low)
    text, start, size = words_of(data, at)
    n = np.bincount(text, minlength=texts)
    per = np.maximum(n, 1)
    add = lambda v: np.bincount(text, v, texts)
    weight = np.maximum.reduce([lexicon(c) for c in codes(eight, start, size)]) if len(start) else np.zeros(0)
    hit, said = weight > 0, second(short(eight, start, size)) > 0
    total, edge = np.concatenate(([0], np.cumsum(said))), np.concatenate(([0], np.cumsum(n)))
    k = np.flatnonzero(hit)
    close = np.zeros(len(start), bool)
    close[k] = total[np.minimum(k + 4, edge[text[k] + 1])] > total[np.maximum(k - 3, edge[text[k]])]
    upper = np.concatenate(([0], np.cumsum((data >= 65) & (data <= 90))))
    loud = (upper[start + size] - upper[start] == size) & (size > 1)
    letter, chars = _LETTER[data], np.maximum(np.diff(at), 1)
    count = lambda flag: by_row(flag, at)
    signs = ~letter & ~_DIGIT[data] & (data > 32)
    beside = np.concatenate(([False], letter[:-1])) & np.concatenate((letter[1:], [False]))
    odd = (signs | _DIGIT[data]) & beside & (data != 39) & (data != 45)
    stretched = np.zeros(len(data), bool)
    if len(data) > 2:
        stretched[2:] = letter[2:] & (low[2:] == low[1:-1]) & (low[2:] == low[:-2]) & (data[2:] < 128)
    hidden = np.zeros(texts)
    masked = np.concatenate(([0], np.cumsum(_MASKED[data])))
    if masked[-1]:
        own, a, s = words_of(data, at, _MASKED)
        letters = np.concatenate(([0], np.cumsum(letter)))
        some = np.flatnonzero((masked[a + s] > masked[a]) & (letters[a + s] > letters[a]))
        if some.size:
            read = wide(_PLAIN[low])
            found = np.maximum.reduce([lexicon(c) for c in codes(read, a[some], s[some])]) > 0
            hidden = np.bincount(own[some], found, texts)
    top = np.zeros(texts)
    np.maximum.at(top, text[k], weight[k])
    hits, near = add(hit), add(close)
    out[:] = np.stack([add(weight) / per, hits / per, np.log1p(hits), top, near / per, near > 0, add(said) / per, add(loud) / per, count((data == 33) | (data == 63)) / chars, count(signs) / chars, count(odd) / chars, hidden, count(stretched) / chars, add(size == 1) / per, np.log1p(n)], 1)
    return out


def _counts(df: DataFrame, only: set[int] | None) -> DataFrame:
    """(term, n): in how many texts each term is; only: the terms to count, all if None."""
    shared = df.sparkSession.sparkContext.broadcast(None if only is None else np.array(sorted(only), np.int64).view(np.uint64))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = None if shared.value is None else Lookup(dict.fromkeys(map(int, shared.value), 1.0))
        for batch in batches:
            for _, _, data, at in slices(batch.column(0)):
                if not len(data):
                    continue
                text, start, size = words_of(data, at)
                term = np.concatenate(codes(wide(_LOWER[data]), start, size))
                own = np.tile(text, 1 + len(PREFIXES))
                keep = term > 0 if wanted is None else wanted(term) > 0
                term, own = term[keep], own[keep]
                _, first = np.unique(mix(own.astype(np.uint64), 30) ^ term, return_index=True)
                found, n = np.unique(term[first], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(found.view(np.int64)), pa.array(n.astype(np.int64))], ["term", "n"])

    return df.select("text").mapInArrow(run, "term long, n long").groupBy("term").agg(F.sum("n").alias("n"))


def lexicon(train: DataFrame) -> dict[int, float]:
    """Numbers of terms and the log of how much likelier they are in toxic texts."""
    sizes = {r["toxic"]: r["n"] for r in train.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    tried = {r["term"]: r["n"] for r in _counts(train.where("toxic = 1"), None).where(F.col("n") >= LEAST_SEEN).orderBy(F.desc("n"), "term").limit(MAX_TRIED).collect()}
    other = {r["term"]: r["n"] for r in _counts(train.where("toxic = 0"), set(tried)).collect()}
    weight = {t: float(np.log((n + 0.5) / (sizes.get(1, 0) + 1)) - np.log((other.get(t, 0) + 0.5) / (sizes.get(0, 0) + 1))) for t, n in tried.items()}
    best = sorted((t for t, w in weight.items() if w >= LEAST_WEIGHT), key=lambda t: (-weight[t] * np.log1p(tried[t]), t))
    return {t % (1 << 64): weight[t] for t in best[:MAX_TERMS]}


def fit(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", rows: int = MAX_ROWS) -> dict:
    """The model: lexicon, trees and calibration, or a constant."""
    said = labels.where("toxic IN (0, 1)").groupBy(F.col("doc_id").alias("k")).agg(F.max("toxic").alias("toxic")).where(F.col("k").isNotNull() & ~held_out("k"))
    sample = said.withColumn("fold", F.crc32(F.col("k").cast("string")) % 5).orderBy(F.xxhash64("k"), "k").limit(rows)
    train = durable(docs.select(F.col(key).alias("k"), F.col(text).alias("text")).join(F.broadcast(sample), "k"), "toxicity-train")
    fitted = train.where("fold <> 1")
    words = lexicon(fitted)
    known = train.sparkSession.sparkContext.broadcast(words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lookup, second = Lookup(known.value), second_person()
        for b in batches:
            x = np.concatenate([features(data, at, lookup, second) for _, _, data, at in slices(b.column(0))] or [np.zeros((0, len(NAMES)))])
            yield pa.RecordBatch.from_arrays([b.column(1), b.column(2), pa.array(list(x), pa.list_(pa.float64()))], ["toxic", "fold", "x"])

    seen = train.select("text", F.col("toxic").cast("int"), F.col("fold").cast("int")).mapInArrow(run, "toxic int, fold int, x array<double>").toPandas()
    drop_durable(train)
    y, fold = seen["toxic"].to_numpy(np.float64), seen["fold"].to_numpy()
    if not len(y) or y.min() == y.max() or len({*y[fold != 1]}) < 2:
        return {"constant": float(y.mean()) if len(y) else 0.0}
    x = np.stack(seen["x"].to_list())
    order = np.lexsort((*x.T, y))  # rows come in any order; the fit must not depend on it
    x, y, fold = x[order], y[order], fold[order]
    trees = Trees().fit(x[fold != 1], y[fold != 1])
    check = fold == 1 if len({*y[fold == 1]}) == 2 else fold != 1
    return {"words": words, "trees": trees, "line": Isotonic().fit(trees.margin(x[check]), y[check])}


def score(docs: DataFrame, model: dict, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, held_out, score, predicted) of every row."""
    shared, kind = docs.sparkSession.sparkContext.broadcast(cloudpickle.dumps(model)), dict(docs.dtypes)[key]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = pickle.loads(shared.value)
        lookup, second = Lookup(model.get("words", {})), second_person()
        for b in batches:
            if "constant" in model:
                p = np.full(b.num_rows, model["constant"])
            else:
                x = [features(data, at, lookup, second) for _, _, data, at in slices(b.column(2))]
                p = model["line"].probability(model["trees"].margin(np.concatenate(x))) if x else np.zeros(0)
            made = pa.array(p, pa.float64())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), made, pc.cast(pc.greater_equal(made, 0.5), pa.int32())], [key, "held_out", "score", "predicted"])

    return docs.select(F.col(key), held_out(key).alias("held_out"), F.col(text)).mapInArrow(run, f"`{key}` {kind}, held_out boolean, score double, predicted int")
