"""Removal of long substrings that an earlier document has, by column-wise multi-document construction.

Every window of ``WIDTH`` bytes belongs to the least hash of its grams (of ``GRAM`` bytes); windows side by side with one least
gram form a piece. Equal windows have equal least grams, so all their copies are in pieces of one key. Keys that
only one document has are done; of equal pieces only that of the smallest document goes on (the others are covered
whole). Those that are left, different pieces of one key that agree around the gram as a shared window must (``alike``), form small collections whose Burrows-Wheeler transform and common
prefixes are built column by column; suffixes with a common prefix of ``WIDTH`` or more are one window, and each of its copies
in any but the smallest document is removed.

Keys and pieces travel in packed blocks by key, answers by document; texts are dealt once, and texts whose pieces need a
collection are kept until its answer is there. A window is judged on the input, never on what is left.

Cases: null texts count as empty (no bytes); texts shorter than the width lose nothing; rows of one id and text keep what they have
alike, as neither id is smaller; null ids come after all others, in the order of their texts' hashes; long texts are read
whole; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .columnbwt import seen_before
from .common import drop_durable, durable, release, slices
from .hashing import mix, wide

U = np.uint64
WIDTH, GRAM = 50, 20
#: Windows in a piece at most, pieces that a partition of keys gets on average, text bytes of a partition of documents,
#: pieces of one collection (the pieces of a key stay together), and bytes before a gram that one digest of ``alike`` stands for.
PIECE, PART_PIECES, PART_BYTES, COLLECTION, STEP = WIDTH - GRAM + 1, 2_000_000, 24 << 20, 1_500, 10
#: Bytes of texts that are cut into pieces at once. Like ``COLLECTION`` it keeps arrays below the size that ``common.lean`` gives
#: back to the system when they are freed: fresh pages for every step cost more than the steps.
BLOCK = 64 << 10
ODD = 0xD1342543DE82EF95
_POWERS = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _powers(n: int) -> list[np.ndarray]:
    if len(_POWERS[0]) < n:
        for k, base in enumerate((ODD, pow(ODD, -1, 1 << 64))):
            _POWERS[k] = np.concatenate(([U(1)], np.cumprod(np.full(n, U(base)), dtype=np.uint64)))
    return _POWERS


def _grams(eight: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the GRAM bytes from each of n places on."""
    tail = np.concatenate((eight[GRAM - 8 :], np.zeros(GRAM - 8, np.uint64)))[:n]
    return mix(eight[:n] ^ mix(eight[8 : n + 8], 2) ^ mix(tail, 5), 1)


def pieces(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, first window, windows, key, hash of all bytes) of every piece, block by block so that arrays stay small."""
    got, lo = [], 0
    while lo < len(offsets) - 1 or not got:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + BLOCK, side="right")) - 1)
        text, first, *rest = _pieces(data[offsets[lo] : offsets[min(hi, len(offsets) - 1)]], offsets[lo : hi + 1] - offsets[lo])
        got.append((text + lo, first + offsets[lo], *rest))
        lo = hi
    return tuple(np.concatenate(x) for x in zip(*got, strict=True))


def _pieces(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    n, lengths = len(data), np.diff(offsets)
    none = np.zeros(0, np.int64)
    if n < WIDTH or not (lengths >= WIDTH).any():
        return none, none, none, none.astype(np.uint64), none.astype(np.uint64)
    eight = wide(data)
    least = _grams(eight, n)
    step = 1
    while 2 * step <= PIECE:
        least = np.minimum(least[:-step], least[step:])
        step *= 2
    least = np.minimum(least[: step - PIECE], least[PIECE - step :])
    have = np.maximum(lengths - WIDTH + 1, 0)
    text = np.repeat(np.arange(len(lengths)), have)
    window = np.arange(len(text)) - np.repeat(np.cumsum(have) - have, have) + offsets[text]
    key = least[window]
    new = np.concatenate(([True], (key[1:] != key[:-1]) | (text[1:] != text[:-1])))
    begin = np.flatnonzero(new)
    run = np.arange(len(text)) - np.repeat(begin, np.diff(np.concatenate((begin, [len(text)]))))
    begin = np.flatnonzero(run % PIECE == 0)
    count = np.diff(np.concatenate((begin, [len(text)])))
    first = window[begin]
    power, inverse = _powers(n + 16)
    total = np.concatenate(([U(0)], np.cumsum(mix(eight[:n], 3) * power[:n], dtype=np.uint64)))
    whole = mix((total[first + count + WIDTH - 8] - total[first]) * inverse[first] + count.astype(np.uint64), 4)
    return text[begin], first, count, key[begin], whole


def _join(column: pa.Array, kind: str) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), kind)


def _of(ids: np.ndarray, whole: np.ndarray) -> np.ndarray:
    return mix(ids.view(np.uint64), 6) ^ whole


def judge_pieces(key: np.ndarray, whole: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(entries whose every window is an earlier document's, entries whose windows a collection must tell)."""
    order = np.lexsort((ids, whole, key))
    key, whole, ids = key[order], whole[order], ids[order]
    new_key = np.concatenate(([True], key[1:] != key[:-1]))
    new = new_key | np.concatenate(([True], whole[1:] != whole[:-1]))
    first = np.flatnonzero(new)
    late = ids > np.repeat(ids[first], np.diff(np.concatenate((first, [len(key)]))))
    at = np.flatnonzero(new_key)
    size = np.diff(np.concatenate((at, [len(key)])))
    several = (np.minimum.reduceat(ids, at) < np.maximum.reduceat(ids, at)) & (np.add.reduceat(new.astype(np.int64), at) > 1)
    return order[late], order[np.repeat(several, size) & ~late]


def alike(key: np.ndarray, data: np.ndarray, at: np.ndarray, owner: np.ndarray) -> np.ndarray:
    """Whether a piece may share a window with one of another owner and the same key.

    A window has the least gram and WIDTH - GRAM bytes around it. With l of them before the gram, both pieces agree on the
    last STEP * (l // STEP) bytes before it and on as many after it as any l of that step leaves; so pieces that agree with
    no other owner's in any of the steps share no window. Equal bytes have equal digests: nothing is lost.
    """
    n, room = len(data), WIDTH - GRAM
    eight = wide(data)
    hit = np.flatnonzero(_grams(eight, n) == np.repeat(key, np.diff(at)))
    piece = np.searchsorted(at, hit, side="right") - 1
    power, inverse = _powers(n + 1)
    total = np.concatenate(([U(0)], np.cumsum(mix(data.astype(np.uint64), 3) * power[:n], dtype=np.uint64)))
    out = np.zeros(len(key), bool)
    for left in range(0, room + 1, STEP):
        a, b = hit - left, hit + GRAM + max(0, room - left - STEP + 1)
        inside = (a >= at[piece]) & (b <= at[piece + 1])
        a, b, own = a[inside], b[inside], piece[inside]
        if not len(own):
            continue
        digest = mix((total[b] - total[a]) * inverse[a] ^ key[own], 4)
        order = np.argsort(digest, kind="stable")
        digest, own = digest[order], own[order]
        begin = np.flatnonzero(np.concatenate(([True], digest[1:] != digest[:-1])))
        several = np.minimum.reduceat(owner[own], begin) < np.maximum.reduceat(owner[own], begin)
        out[own[np.repeat(several, np.diff(np.concatenate((begin, [len(own)]))))]] = True
    return out


def spans(first: np.ndarray, count: np.ndarray) -> list[tuple[int, int]]:
    """The maximal byte ranges that windows [first, first + count) cover."""
    out: list[tuple[int, int]] = []
    for a, c in sorted(zip(first.tolist(), count.tolist(), strict=True)):
        b = a + c - 1 + WIDTH
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def without(text: bytes, cut: list[tuple[int, int]]) -> tuple[int, int, int, str]:
    """(n_bytes, n_removed, n_spans, kept_sha256)."""
    kept, at = hashlib.sha256(), 0
    for a, b in cut:
        kept.update(text[at:a])
        at = b
    kept.update(text[at:])
    return len(text), sum(b - a for a, b in cut), len(cut), kept.hexdigest()


def collections(key: np.ndarray) -> Iterator[np.ndarray]:
    """Numbers of pieces in collections of about ``COLLECTION``, keys whole."""
    order = np.argsort(key, kind="stable")
    ends = np.flatnonzero(np.concatenate((key[order][1:] != key[order][:-1], [True]))) + 1
    lo = 0
    while lo < len(order):
        k = int(np.searchsorted(ends, lo + COLLECTION, side="right"))
        hi = int(ends[k - 1]) if k and ends[k - 1] > lo else int(ends[np.searchsorted(ends, lo, side="right")])
        yield order[lo:hi]
        lo = hi


def remove(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_bytes, n_removed, n_spans, kept_sha256) of every row."""
    spark, kind = df.sparkSession, dict(df.dtypes)[key]
    plain = F.coalesce(F.col(text), F.lit(""))
    late_id = F.lit(1 << 62) + F.pmod(F.xxhash64(plain), F.lit(1 << 60))
    docs = df.select(F.col(key).alias("id"), F.coalesce(F.col(key).cast("long"), late_id).alias("uid"), plain.alias("text"))
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    least_parts = spark.sparkContext.defaultParallelism
    parts, places = max(least_parts, total // 18 // PART_PIECES + 1), max(least_parts, total // PART_BYTES + 1)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(i, 4096) for b in batches for i in range(0, b.num_rows, 4096)):
            ids, got = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64), []
            for lo, _, data, at in slices(batch.column(1)):
                own, _, _, key_, whole = pieces(data, at)
                got.append((own + lo, key_, whole))
            own, key_, whole = (np.concatenate(x) for x in zip(*got, strict=True)) if got else (np.zeros(0, np.int64),) * 3
            if not len(own):
                continue
            part = (key_ % U(parts)).astype(np.int64)
            order = np.argsort(part, kind="stable")
            cut = np.searchsorted(part[order], np.arange(parts + 1))
            rows = []
            for p in np.flatnonzero(np.diff(cut)):
                at = order[cut[p] : cut[p + 1]]
                who, n = np.unique(own[at], return_counts=True)
                rows.append((int(p), (key_[at] >> U(32)).astype(np.uint32).tobytes(), whole[at].tobytes(), ids[who].tobytes(), n.astype(np.uint32).tobytes()))
            cols = list(zip(*rows, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], ["part", "key", "whole", "ids", "n"])

    def answer(ids: np.ndarray, *columns: np.ndarray) -> Iterator[tuple]:
        """Rows for the partitions of documents: place, ids, rows of each id, columns in that order."""
        place = (mix(ids.view(np.uint64), 8) % U(places)).astype(np.int64)
        order = np.lexsort((ids, place))
        cut = np.searchsorted(place[order], np.arange(places + 1))
        for p in np.flatnonzero(np.diff(cut)):
            at = order[cut[p] : cut[p + 1]]
            who, n = np.unique(ids[at], return_counts=True)
            yield (int(p), who.tobytes(), n.astype(np.uint32).tobytes(), *(c[at].tobytes() for c in columns))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [[], [], []]
        for b in batches:
            got[0].append(_join(b.column(1), np.uint32)), got[1].append(_join(b.column(2), np.uint64))
            got[2].append(np.repeat(_join(b.column(3), np.int64), _join(b.column(4), np.uint32)))
        if not got[0]:
            return
        key_, whole, ids = (np.concatenate(x) for x in got)
        covered, open_ = judge_pieces(key_, whole, ids)
        at = np.concatenate((covered, open_))
        told = np.concatenate((np.ones(len(covered), np.uint8), np.zeros(len(open_), np.uint8)))
        for row in answer(ids[at], whole[at], told):
            yield pa.RecordBatch.from_arrays([pa.array([row[0]], pa.int32()), *(pa.array([c], pa.binary()) for c in row[1:])], ["place", "ids", "n", "whole", "told"])

    packed = docs.select("uid", "text").mapInArrow(scan, "part int, key binary, whole binary, ids binary, n binary")
    told = durable(packed.repartition(parts, "part").mapInArrow(compare, "place int, ids binary, n binary, whole binary, told binary"), "substrings-told")
    release(spark)

    result = "n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    names = ["id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "place", "uids", "named", "sizes", "texts", "spans", "first", "count", "part", "key", "strings", "lengths", "owner", "start"]

    def table_of(**cols) -> pa.RecordBatch:
        kinds = [*[pa.int64()] * 4, pa.string(), pa.int32(), *[pa.binary()] * 7, pa.int32(), *[pa.binary()] * 5]
        n = len(next(iter(cols.values())))
        return pa.RecordBatch.from_arrays([pa.array(cols.get(c, [None] * n), k) for c, k in zip(names, kinds, strict=True)], names)

    def packed_texts(place: int, uid: np.ndarray, named: np.ndarray, texts: list[bytes]) -> dict:
        """Texts of one partition of documents as one row."""
        sizes, raw = np.array([len(t) for t in texts], np.int32), b"".join(texts)
        return {"place": place, "uids": uid.tobytes(), "named": named.tobytes(), "sizes": sizes.tobytes(), "texts": pa.compress(raw, codec="zstd", asbytes=True)}

    def unpacked(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(uid, named, bytes, offsets)."""
        at = np.concatenate(([0], np.cumsum(np.frombuffer(row["sizes"], np.int32), dtype=np.int64)))
        raw = pa.decompress(row["texts"], decompressed_size=int(at[-1]), codec="zstd", asbytes=True) if at[-1] else b""
        return np.frombuffer(row["uids"], np.int64), np.frombuffer(row["named"], bool), np.frombuffer(raw, np.uint8), at

    def dealt_texts(batches: Iterator[pa.RecordBatch], columns: int) -> tuple[list[np.ndarray], list[dict]]:
        """Answers of a partition (ids repeated, then the columns), and the rows with texts."""
        ids, rest, texts = [], [[] for _ in range(columns)], []
        for b in batches:
            is_text = np.array(b.column("texts").is_valid().to_numpy(zero_copy_only=False))
            some = b.filter(pa.array(~is_text))
            if some.num_rows:
                ids.append(np.repeat(_join(some.column("ids"), np.int64), _join(some.column("n"), np.uint32)))
                for k in range(columns):
                    rest[k].append(_join(some.column(f"c{k}"), np.uint8))
            texts += b.filter(pa.array(is_text)).to_pylist()
        return [np.concatenate(ids) if ids else np.zeros(0, np.int64), *(np.concatenate(r) if r else np.zeros(0, np.uint8) for r in rest)], texts

    def pack_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (b.slice(i, 2048) for b in batches for i in range(0, b.num_rows, 2048)):
            uid, named = b.column(1).to_numpy(zero_copy_only=False).astype(np.int64), np.array(b.column(0).is_valid().to_numpy(zero_copy_only=False))
            place = (mix(uid.view(np.uint64), 8) % U(places)).astype(np.int64)
            texts, rows = [t.encode() for t in b.column(2).to_pylist()], []
            for p in np.unique(place):
                own = np.flatnonzero(place == p)
                rows.append(packed_texts(int(p), uid[own], named[own], [texts[i] for i in own]))
            yield pa.RecordBatch.from_pylist(rows, pa.schema([("place", pa.int32()), *((c, pa.binary()) for c in ("uids", "named", "sizes", "texts"))]))

    def pieces_in(data: np.ndarray, at: np.ndarray) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        lo = 0
        while lo < len(at) - 1:
            hi = max(lo + 1, int(np.searchsorted(at, at[lo] + (2 << 20), side="right")) - 1)
            yield lo, hi, data[at[lo] : at[hi]], at[lo : hi + 1] - at[lo]
            lo = hi

    def apply_told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (ids, whole, told_), texts = dealt_texts(batches, 2)
        known = _of(ids, whole.view(np.uint64))
        order = np.argsort(known)
        known, told_ = known[order], told_[order]
        for row in texts:
            uid, named, every, ends = unpacked(row)
            done, kept, sent = [], [], []
            for lo, hi, data, at in pieces_in(every, ends):
                own, first, count, key_, all_ = pieces(data, at)
                mine = _of(uid[lo:hi][own], all_) if len(own) else np.zeros(0, np.uint64)
                k = np.minimum(np.searchsorted(known, mine), max(0, len(known) - 1))
                hit = known[k] == mine if len(known) else np.zeros(len(mine), bool)
                cover, ask = hit & (told_[k] == 1) if len(known) else hit, hit & (told_[k] == 0) if len(known) else hit
                raw = data.tobytes()
                asked = np.bincount(own[ask], minlength=hi - lo)
                ranges = np.searchsorted(own[cover], np.arange(hi - lo + 1))
                f, c = first[cover] - at[own[cover]], count[cover]
                for i in range(hi - lo):
                    r = slice(ranges[i], ranges[i + 1])
                    if asked[i]:
                        kept.append((lo + i, raw[at[i] : at[i + 1]], f[r].astype(np.int32), c[r].astype(np.int32)))
                    else:
                        done.append((int(uid[lo + i]) if named[lo + i] else None, *without(raw[at[i] : at[i + 1]], spans(f[r], c[r]))))
                if ask.any():
                    size = count[ask] + WIDTH - 1
                    part = (key_[ask] % U(parts)).astype(np.int64)
                    where = first[ask]
                    for p in np.unique(part):
                        some = np.flatnonzero(part == p)
                        idx = np.repeat(where[some], size[some]) + np.arange(int(size[some].sum())) - np.repeat(np.cumsum(size[some]) - size[some], size[some])
                        sent.append((int(p), key_[ask][some].tobytes(), data[idx].tobytes(), size[some].astype(np.uint8).tobytes(), uid[lo:hi][own[ask][some]].tobytes(), (where[some] - at[own[ask][some]]).astype(np.int32).tobytes()))
            if done:
                x = list(zip(*done, strict=True))
                yield table_of(id=x[0], n_bytes=x[1], n_removed=x[2], n_spans=x[3], kept_sha256=x[4])
            if kept:
                which, raws, f, c = zip(*kept, strict=True)
                which = np.array(which)
                out = packed_texts(row["place"], uid[which], named[which], list(raws)) | {"spans": np.array([len(x) for x in f], np.int32).tobytes(), "first": np.concatenate(f).tobytes(), "count": np.concatenate(c).tobytes()}
                yield table_of(**{k: [v] for k, v in out.items()})
            if sent:
                x = list(zip(*sent, strict=True))
                yield table_of(part=x[0], key=x[1], strings=x[2], lengths=x[3], owner=x[4], start=x[5])

    def dealt(texts: DataFrame, answers: DataFrame, columns: tuple[str, ...]) -> DataFrame:
        """Texts and answers in one table, dealt to the partitions of documents."""
        told_ = answers.select("place", "ids", "n", *(F.col(c).alias(f"c{k}") for k, c in enumerate(columns)))
        return texts.unionByName(told_, allowMissingColumns=True).repartition(places, "place")

    texts = docs.mapInArrow(pack_texts, "place int, uids binary, named binary, sizes binary, texts binary")
    schema = "id long, " + result + ", place int, " + ", ".join(f"{c} binary" for c in names[6:13]) + ", part int, " + ", ".join(f"{c} binary" for c in names[14:])
    half = durable(dealt(texts, told, ("whole", "told")).mapInArrow(apply_told, schema), "substrings-half")
    drop_durable(told)
    release(spark)

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [[], [], [], [], []]
        for b in batches:
            for k, t in enumerate((np.uint64, np.uint8, np.uint8, np.int64, np.int32)):
                got[k].append(_join(b.column(k + 1), t))
        if not got[0]:
            return
        key_, data, size, owner, start = (np.concatenate(x) for x in got)
        at = np.concatenate(([0], np.cumsum(size, dtype=np.int64)))

        def strings(some: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            n = size[some].astype(np.int64)
            off = np.concatenate(([0], np.cumsum(n)))
            return data[np.repeat(at[some] - off[:-1], n) + np.arange(int(off[-1]))], off

        left = np.concatenate([some[alike(key_[some], *strings(some), owner[some])] for some in collections(key_)])
        for some in (left[part] for part in collections(key_[left])):
            string, where = seen_before(*strings(some), owner[some], WIDTH)
            if not len(string):
                continue
            order = np.lexsort((where, string))
            string, where = string[order], where[order]
            new = np.concatenate(([True], (string[1:] != string[:-1]) | (where[1:] != where[:-1] + 1)))
            first = np.flatnonzero(new)
            count = np.diff(np.concatenate((first, [len(string)]))).astype(np.int32)
            own = some[string[first]]
            for row in answer(owner[own], start[own] + where[first].astype(np.int32), count):
                yield pa.RecordBatch.from_arrays([pa.array([row[0]], pa.int32()), *(pa.array([c], pa.binary()) for c in row[1:])], ["place", "ids", "n", "first", "count"])

    sent = half.where("part IS NOT NULL").select("part", "key", "strings", "lengths", "owner", "start")
    late = durable(sent.repartition(parts, "part").mapInArrow(build, "place int, ids binary, n binary, first binary, count binary"), "substrings-late")
    release(spark)

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (ids, first, count), texts = dealt_texts(batches, 2)
        first, count = first.view(np.int32), count.view(np.int32)
        order = np.argsort(ids, kind="stable")
        ids, first, count = ids[order], first[order], count[order]
        for row in texts:
            uid, named, every, at = unpacked(row)
            n = np.concatenate(([0], np.cumsum(np.frombuffer(row["spans"], np.int32))))
            f0, c0, raw = np.frombuffer(row["first"], np.int32), np.frombuffer(row["count"], np.int32), every.tobytes()
            lo, hi = np.searchsorted(ids, uid, side="left"), np.searchsorted(ids, uid, side="right")
            rows = [without(raw[at[i] : at[i + 1]], spans(np.concatenate((f0[n[i] : n[i + 1]], first[lo[i] : hi[i]])), np.concatenate((c0[n[i] : n[i + 1]], count[lo[i] : hi[i]])))) for i in range(len(uid))]
            x = list(zip(*rows, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array([int(u) if k else None for u, k in zip(uid, named, strict=True)], pa.int64()), *(pa.array(v, pa.int64()) for v in x[:3]), pa.array(x[3], pa.string())], names[:5])

    waiting = half.where("uids IS NOT NULL").select("place", "uids", "named", "sizes", "texts", "spans", "first", "count")
    last = dealt(waiting, late, ("first", "count")).mapInArrow(finish, f"id long, {result}")
    every = half.where("n_bytes IS NOT NULL").select(*names[:5]).union(last)
    return every.select(F.col("id").cast(kind).alias(key), *names[1:5])
