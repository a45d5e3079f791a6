"""License scans by an exact set-similarity join of text blocks with notice templates.

A block (a line, a run of words a little longer than the template that crosses line breaks but no line without words, or
the whole text for the phrase templates) meets a template when it holds at least a threshold of the
template's distinct words. Words stand in the order of their frequency over all documents, rarest first; a block that
shares none of a template's prefix (the words that it can't all miss) is out by the prefix filter, one with too few words by
the length filter, and the walk through the template's words ends by the positional filter once too few are left. None of
these drops a block that meets the threshold. Phrases are then confirmed as consecutive words.

Cases: a null text counts as empty: no words, no labels, score 0; repeated rows are scanned alike; a text of any length is
read whole; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator, Sequence

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

#: Phrases whose words stand consecutively, and their labels. Fixed values.
PHRASES = [("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl")]
#: Notices in common use, and labels; a block with this share of a notice's words has the label.
NOTICES = [
    ("released under the mit license", "mit"),
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "mit"),
    ("licensed under the apache license version 2 0", "apache"),
    ("this work is licensed under the gnu general public license version 3", "gpl"),
    ("licensed under cc by nc 4 0", "cc-by-nc"),
    ("this work is licensed under a creative commons attribution 4 0 international license", "cc-by"),
    ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "bsd"),
    ("this source code form is subject to the terms of the mozilla public license v 2 0", "mpl"),
    ("all rights reserved", "reserved"),
]
TENTHS = 8  # of a notice's distinct words
#: Upper to lower case, and every byte outside words to a blank; bytes from 0x80 on belong to words.
WORDS = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


class Template:
    def __init__(self, words: str, label: str, order: dict[bytes, int], tenths: int = TENTHS):
        self.label = label
        self.sorted = sorted(set(words.encode().split()), key=lambda w: (order.get(w, 0), w))
        self.needed = -(-len(self.sorted) * tenths // 10)
        self.window = len(words.split()) + len(words.split()) // 5
        self.prefix = self.sorted[: len(self.sorted) - self.needed + 1]

    def overlap(self, block: set[bytes]) -> int:
        """Shared words, or 0 where the threshold is out of reach."""
        if len(block) < self.needed or block.isdisjoint(self.prefix):
            return 0
        got = 0
        for k, word in enumerate(self.sorted):
            got += word in block
            if got + len(self.sorted) - k - 1 < self.needed:
                return 0
        return got


def word_counts(df: DataFrame, words: Sequence[str], text: str = "text") -> dict[bytes, int]:
    """How often each of a few given words occurs over all texts."""
    wanted = {w.encode() for w in words}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: Counter[bytes] = Counter()
        for batch in batches:
            for _, _, data, _ in slices(batch.column(0)):
                # of a slice's texts together: a line break stands between texts, so no words join
                total.update(w for w in data.tobytes().translate(WORDS).split() if w in wanted)
        yield pa.RecordBatch.from_arrays([pa.array([w.decode() for w in total], pa.string()), pa.array(list(total.values()), pa.int64())], ["word", "n"])

    parted = df.select(F.concat(F.coalesce(F.col(text), F.lit("")), F.lit("\n")).alias("t")).mapInArrow(run, "word string, n long")
    return {r["word"].encode(): r["n"] for r in parted.groupBy("word").agg(F.sum("n").alias("n")).collect()}


def scan(df: DataFrame, key: str = "doc_id", text: str = "text", phrases: Sequence[tuple[str, str]] = PHRASES, notices: Sequence[tuple[str, str]] = NOTICES, tenths: int = TENTHS) -> DataFrame:
    """(key, n_words, matches) of every row; a match has its label, kind, line, first word, words of the block and share."""
    order = word_counts(df, sorted({w for s, _ in [*phrases, *notices] for w in s.split()}), text)
    whole = [(Template(s, label, order, 10), s.encode().split()) for s, label in phrases]
    parts = [Template(s, label, order, tenths) for s, label in notices]
    prefixes = {w for t in [*parts, *(t for t, _ in whole)] for w in t.prefix}
    kind = dict(df.dtypes)[key]
    match = pa.list_(pa.struct([("label", pa.string()), ("base", pa.bool_()), ("line", pa.int32()), ("first_word", pa.int64()), ("n", pa.int32()), ("share", pa.float64())]))

    def wrapped(lines: list[tuple[int, int, list[bytes]]]) -> list[dict]:
        """The best run of words of each template that no single line of the paragraph meets."""
        if len(lines) < 2:
            return []
        found, block = [], {w for _, _, here in lines for w in here}
        if block.isdisjoint(prefixes):
            return []
        for t in parts:
            if not t.overlap(block) or any(t.overlap(set(here)) for _, _, here in lines):
                continue
            own = set(t.sorted)
            at = [(begin + k, w) for _, begin, here in lines for k, w in enumerate(here) if w in own]
            held: Counter[bytes] = Counter()
            best, place, lo = 0, 0, 0
            for end, w in at:
                held[w] += 1
                while at[lo][0] <= end - t.window:
                    held[at[lo][1]] -= 1
                    if not held[at[lo][1]]:
                        del held[at[lo][1]]
                    lo += 1
                if len(held) > best:
                    best, place = len(held), at[lo][0]
            if best >= t.needed:
                line = max(number for number, begin, _ in lines if begin <= place)
                found.append({"label": t.label, "base": False, "line": line, "first_word": place, "n": t.window, "share": best / len(t.sorted)})
        return found

    def matches(raw: bytes, words: list[bytes]) -> list[dict]:
        found, every = [], set(words)
        for template, phrase in whole:
            if template.overlap(every):
                found += [{"label": template.label, "base": True, "line": None, "first_word": at, "n": len(phrase), "share": 1.0} for at, w in enumerate(words) if w == phrase[0] and words[at : at + len(phrase)] == phrase]
        first = 0
        paragraph: list[tuple[int, int, list[bytes]]] = []
        for number, line in enumerate(raw.split(b"\n")):
            here = line.split()
            if here:
                paragraph.append((number, first, here))
            else:
                found += wrapped(paragraph)
                paragraph = []
            block = set(here)
            if not block.isdisjoint(prefixes):
                for t in parts:
                    if got := t.overlap(block):
                        found.append({"label": t.label, "base": False, "line": number, "first_word": first, "n": len(here), "share": got / len(t.sorted)})
            first += len(here)
        return found + wrapped(paragraph)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep = bytes(10 if b == 10 else WORDS[b] for b in range(256))
        for batch in batches:
            n, found = [], []
            for lo, hi, data, at in slices(batch.column(1)):
                text_ = data.tobytes().translate(keep)
                for i in range(hi - lo):
                    words = (raw := text_[at[i] : at[i + 1]]).split()
                    n.append(len(words))
                    found.append(matches(raw, words) if not prefixes.isdisjoint(words) else [])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(found, match)], [key, "n_words", "matches"])

    return df.select(F.col(key), F.col(text)).mapInArrow(run, f"`{key}` {kind}, n_words long, matches array<struct<label:string,base:boolean,line:int,first_word:long,n:int,share:double>>")


def summary(found: DataFrame, key: str = "doc_id") -> DataFrame:
    base = F.filter("matches", lambda m: m["base"])
    starts = F.transform(base, lambda m: m["first_word"])
    joined = lambda ms: F.array_join(F.array_sort(F.array_distinct(F.transform(ms, lambda m: m["label"]))), ",")
    return found.select(
        key, "n_words", F.size(base).cast("long").alias("n_base"), F.array_min(starts).alias("first_word"), F.array_max(starts).alias("last_word"),
        joined(base).alias("base_labels"), joined(F.col("matches")).alias("labels"), F.coalesce(F.array_max(F.transform("matches", lambda m: m["share"])), F.lit(0.0)).alias("score"),
    )


def oracle_sql() -> str:
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    word = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
    templates = ", ".join(f"('{s}', '{label}')" for s, label in NOTICES)
    places = " OR ".join("(" + " AND ".join(f"{'w' if not k else f'w{k}'} = '{x}'" for k, x in enumerate(s.split())) + ")" for s, _ in PHRASES)
    which = " ".join(f"WHEN {' AND '.join(f"{'w' if not k else f'w{k}'} = '{x}'" for k, x in enumerate(s.split()))} THEN '{label}'" for s, label in PHRASES)
    return f"""
WITH docs AS (SELECT doc_id, translate(coalesce(text, ''), '{upper}', '{lower}') AS t FROM documents),
listed AS (SELECT doc_id, t, regexp_extract_all(t, '{word}') AS ws FROM docs),
words AS (SELECT doc_id, unnest(ws) AS w, generate_subscripts(ws, 1) - 1 AS pos FROM listed),
ahead AS (SELECT *, lead(w, 1) OVER d AS w1, lead(w, 2) OVER d AS w2 FROM words WINDOW d AS (PARTITION BY doc_id ORDER BY pos)),
places AS (SELECT doc_id, pos, CASE {which} END AS label FROM ahead WHERE {places}),
base AS (SELECT doc_id, count(*) AS n_base, min(pos) AS first_word, max(pos) AS last_word, list(label) AS ls FROM places GROUP BY doc_id),
notices AS (SELECT list_distinct(string_split(s, ' ')) AS tw, label FROM (VALUES {templates}) v(s, label)),
lines AS (SELECT doc_id, list_distinct(regexp_extract_all(unnest(string_split(t, chr(10))), '{word}')) AS lw FROM docs),
met AS (
  SELECT doc_id, label, len(list_intersect(lw, tw)) / CAST(len(tw) AS DOUBLE) AS share FROM lines, notices
  WHERE len(list_intersect(lw, tw)) >= (len(tw) * {TENTHS} + 9) // 10),
own AS (SELECT doc_id, list(label) AS ls, max(share) AS share FROM met GROUP BY doc_id)
SELECT l.doc_id, len(ws) AS n_words, coalesce(n_base, 0) AS n_base, first_word, last_word,
       coalesce(array_to_string(list_sort(list_distinct(b.ls)), ','), '') AS base_labels,
       coalesce(array_to_string(list_sort(list_distinct(list_concat(coalesce(b.ls, []), coalesce(o.ls, [])))), ','), '') AS labels,
       CASE WHEN n_base > 0 THEN 1.0::DOUBLE ELSE coalesce(o.share, 0.0::DOUBLE) END AS score
FROM listed l LEFT JOIN base b USING (doc_id) LEFT JOIN own o USING (doc_id)"""
