"""Language identification with hyperdimensional profiles.

Every letter has a vector of +1 and -1, drawn from its code point. The vector of a three-letter piece is the product of its
letters' vectors, permuted (rotated) by their place in it; a text's profile is the sum over its pieces, a language's prototype
the sum over all texts that it is learned from, and a text is compared with the prototypes by cosine. The sums are whole
numbers, so a task adds up one vector for each language and Spark adds those: any order gives the same prototypes.

Cases: null texts and texts without a letter are ``und`` with score 0; ties go to the language that sorts first; documents
without a language teach nothing; if nothing can be learned, every text is ``und``; long texts are read whole; an
empty table gives an empty result; repeated rows are judged alike; other columns are not read, and passed on where asked for.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_row, held_out, slices
from .hashing import mix

WIDTH = 512
#: Text bytes that are counted at once, and languages whose sums a task holds before it hands them on.
AT_ONCE, HELD = 1 << 20, 1024
PLACE = 21  # bits of a code point


@cache
def letter_table() -> np.ndarray:
    """By code point: its lower-case letter, or 0 outside letters."""
    out = np.zeros(0x110000, np.int32)
    for c in range(0x110000):
        if (x := chr(c)).isalpha():
            out[c] = ord(x.lower()[0])
    return out


def letter_vectors(points: np.ndarray) -> np.ndarray:
    """(letters, WIDTH) of +1 and -1; 0 stands for no letter and has a vector too."""
    words = mix(points.astype(np.uint64)[:, None] * np.uint64(WIDTH) + np.arange(WIDTH // 64, dtype=np.uint64), 7)
    return np.unpackbits(words.view(np.uint8).reshape(len(points), -1), axis=1).view(np.int8) * np.int8(2) - np.int8(1)


def code(pieces: np.ndarray) -> np.ndarray:
    """The vectors of pieces, bound by product after rotations by 2, 1 and 0 places."""
    out = np.ones((len(pieces), WIDTH), np.int8)
    for turn in range(3):
        point, own = np.unique((pieces >> (PLACE * turn)) & ((1 << PLACE) - 1), return_inverse=True)
        out *= np.roll(letter_vectors(point), turn, 1)[own]
    return out.astype(np.float32)


def pieces_of(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct pieces; which of them stands at each letter: the letter and its neighbours, 0 for none; letters of each text)."""
    chars = np.frombuffer(data.tobytes().decode("utf-8").encode("utf-32-le"), np.uint32)
    ends = by_row((data & 0xC0) != 0x80, at)
    offsets = np.concatenate(([0], np.cumsum(ends)))
    letter = letter_table()[chars]
    before, after = np.zeros_like(letter), np.zeros_like(letter)
    before[1:], after[:-1] = letter[:-1], letter[1:]
    before[offsets[:-1][ends > 0]] = 0
    after[offsets[1:][ends > 0] - 1] = 0
    here = np.flatnonzero(letter)
    points = np.flatnonzero(np.bincount(letter, minlength=1))
    if not len(here):
        return np.zeros(0, np.int64), here, by_row(letter > 0, offsets)
    local = np.zeros(int(points[-1]) + 1, np.int64)
    local[points] = np.arange(len(points))
    points = np.concatenate(([0], points)) if points[0] else points
    local += int(points[0] == 0 and local[points[1]] == 0)
    local[0] = 0
    wide = len(points)
    number = (local[before[here]] * wide + local[letter[here]]) * wide + local[after[here]]
    if wide**3 <= 1 << 22:
        seen = np.flatnonzero(np.bincount(number, minlength=1))
        rank = np.zeros(int(seen[-1]) + 1, np.int64)
        rank[seen] = np.arange(len(seen))
        which = rank[number]
    else:
        seen, which = np.unique(number, return_inverse=True)
    a, b, c = points[seen // wide**2], points[seen // wide % wide], points[seen % wide]
    return (a << 2 * PLACE) | (b << PLACE) | c, which, by_row(letter > 0, offsets)


def profiles(piece: np.ndarray, which: np.ndarray, row: np.ndarray, rows: int) -> np.ndarray:
    """(rows, WIDTH): the sums of the vectors of each row's pieces; exact, as no sum passes 2 to the 24th."""
    if not len(piece):
        return np.zeros((rows, WIDTH), np.float32)
    out = np.zeros((rows, WIDTH), np.float32)
    for lo in range(0, len(piece), 8192):
        some = slice(None) if len(piece) <= 8192 else (which >= lo) & (which < lo + 8192)
        n = min(8192, len(piece) - lo)
        count = np.bincount(row[some] * n + which[some] - lo, minlength=rows * n).reshape(rows, n)
        out += count.astype(np.float32) @ code(piece[lo : lo + n])
    return out


def sums(df: DataFrame, lang: str = "lang", text: str = "text") -> DataFrame:
    """(lang, place, n): the summed vector of every language, over all rows that name one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}

        def out() -> Iterator[pa.RecordBatch]:
            for name, v in total.items():
                yield pa.RecordBatch.from_arrays([pa.array([name] * WIDTH, pa.string()), pa.array(np.arange(WIDTH, dtype=np.int32)), pa.array(v)], ["lang", "place", "n"])
            total.clear()

        for batch in batches:
            names = batch.column(0).to_pylist()
            for lo, hi, data, at in slices(batch.column(1), AT_ONCE):
                own = list(dict.fromkeys(names[lo:hi]))
                number = {name: k for k, name in enumerate(own)}
                piece, which, n = pieces_of(data, at)
                for k in range(0, len(own), 256):
                    row = np.repeat(np.array([number[x] - k for x in names[lo:hi]]), n)
                    some = (row >= 0) & (row < 256)
                    for name, v in zip(own[k : k + 256], profiles(piece, which[some], row[some], min(256, len(own) - k)), strict=True):
                        total[name] = total.get(name, 0) + v.astype(np.int64)
            if len(total) > HELD:
                yield from out()
        yield from out()

    parted = df.where(F.col(lang).isNotNull()).select(lang, text).mapInArrow(run, "lang string, place int, n long")
    return parted.groupBy("lang", "place").agg(F.sum("n").alias("n"))


def prototypes(summed: DataFrame) -> tuple[list[str], np.ndarray]:
    """Languages in order, and their unit prototypes: one vector of each language reaches the driver, 4 KB."""
    found: dict[str, np.ndarray] = {}
    for r in summed.collect():
        found.setdefault(r["lang"], np.zeros(WIDTH))[r["place"]] = r["n"]
    names = sorted(x for x in found if found[x].any())
    out = np.stack([found[x] for x in names]) if names else np.zeros((0, WIDTH))
    return names, out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-12)


def predict(df: DataFrame, names: list[str], protos: np.ndarray, text: str = "text", keep: tuple[str, ...] = ("doc_id",), prefix: str = "") -> DataFrame:
    """The columns of ``keep``, lang_pred, score and letters (how many letters it has) of every row; prefix: of the three new names."""
    shared = df.sparkSession.sparkContext.broadcast((names, protos.astype(np.float32)))
    made = [f"{prefix}{c}" for c in ("lang_pred", "score", "letters")]
    at_text = keep.index(text) if text in keep else len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, protos = shared.value
        for batch in batches:
            for lo, hi, data, at in slices(batch.column(at_text), AT_ONCE):
                piece, which, n = pieces_of(data, at)
                said, score = ["und"] * len(n), [0.0] * len(n)
                row = np.repeat(np.arange(hi - lo), n)
                for k in range(0, hi - lo, 512) if names else ():
                    some = slice(*np.searchsorted(row, [k, k + 512]))
                    profile = profiles(piece, which[some], row[some] - k, min(512, hi - lo - k))
                    got = profile @ protos.T / np.maximum(np.linalg.norm(profile, axis=1, keepdims=True), 1e-9)
                    best = got.argmax(1)
                    said[k : k + 512] = [names[b] if m else "und" for b, m in zip(best, n[k : k + 512], strict=True)]
                    score[k : k + 512] = [float(min(1.0, max(0.0, got[i, b]))) if n[k + i] else 0.0 for i, b in enumerate(best)]
                own = batch.slice(lo, hi - lo)
                yield pa.RecordBatch.from_arrays([*(own.column(i) for i in range(len(keep))), pa.array(said, pa.string()), pa.array(score, pa.float64()), pa.array(n, pa.int64())], [*(f"k{i}" for i in range(len(keep))), *made])

    schema = df.select(*keep).schema
    for i, field in enumerate(schema.fields):
        field.name = f"k{i}"
    schema.names = [f.name for f in schema.fields]
    for c, kind in zip(made, ("string", "double", "long"), strict=True):
        schema.add(c, kind)
    out = df.select(*(F.col(c).alias(f"k{i}") for i, c in enumerate(keep)), *([] if text in keep else [F.col(text).alias("t")])).mapInArrow(run, schema)
    return out.select(*(F.col(f"k{i}").alias(c) for i, c in enumerate(keep)), *made)


def identify(df: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """(key, held_out, lang_pred, score): learned from the rows that aren't held out."""
    names, protos = prototypes(sums(df.where(~held_out(key)), lang, text))
    named = df.select(F.col(key), F.col(text), held_out(key).alias("held_out"))
    return predict(named, names, protos, text, (key, "held_out")).drop("letters")
