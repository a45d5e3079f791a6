"""Mixing sources to target weights with Pareto order sampling.

Each source's target is its weight's share of all sizes, at most three times its own size, the excess shared again by weight.
A document's expected copies grow with the binary digits of its size: rate x digits, at most three, where a source's rate makes
the expected words its target. It gets the whole part of them as certain copies; the rest is its inclusion probability. One
more copy goes to the documents of least rank: random odds over inclusion odds. The sample's size is fixed in words: it is the
head of that order that fits into what the certain copies leave of the target, and a closing document: the next in the order that
brings the source within a hundredth of its target, or, where none does, the one that comes nearest.

The random numbers are digests of the ids (of the texts, for rows without an id), so reruns agree. The place at which a source's
order is cut is found level by level: 16,384 steps of the rank; in one of them the points, which are rank, text's digest and one
of 4,096 parts of rows that are equal in both; at one of them the rows. Every level is a sum by its values in what the level before
left, so no task holds a whole source or a whole group of equal rows. Sources are the stated classes of the mix; tables with rows by source are broadcast
only where their measured size allows it.

Cases: a null text has size 0; null is a source of its own, after all others; repeated rows and rows without an id each
have a rank of their own; an empty table gives an empty result; a source without words has target 0; other columns are not
read, and passed on where asked for.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import PLACE, durable, numbered, small

WORD = r"[^\x20\x09-\x0D]+"
STEPS = 1 << 14
LIMIT = 3
#: Share of a target within which a source is full.
NEAR = 0.01


def targets(sizes: DataFrame) -> DataFrame:
    """(source, source_size, weight, target); sizes: (source, source_size). One row per source, so one task is enough."""
    order = Window.orderBy(F.col("source").asc_nulls_last())
    weighed = sizes.withColumn("weight", (F.pmod(F.row_number().over(order) - 1, F.lit(3)) + 1).cast("double"))
    full = (F.col("source_size") * LIMIT).cast("double")
    by_need = Window.orderBy(full / F.col("weight"), F.col("source").asc_nulls_last())
    before, after = by_need.rowsBetween(Window.unboundedPreceding, -1), by_need.rowsBetween(0, Window.unboundedFollowing)
    level = (F.sum("source_size").over(Window.partitionBy()) - F.coalesce(F.sum(full).over(before), F.lit(0.0))) / F.sum("weight").over(after)
    levelled = weighed.withColumn("level", level).withColumn("free", full / F.col("weight") >= F.col("level"))
    common = F.first(F.when(F.col("free"), F.col("level")), ignorenulls=True).over(by_need.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return levelled.withColumn("common", common).select("source", "source_size", "weight", F.when(F.col("free"), F.col("common") * F.col("weight")).otherwise(full).alias("target"))


def plan_of(classes: DataFrame) -> DataFrame:
    """(s, d, source_size, target, certain, inclusion, left) of each class; classes: (source, digits, words)."""
    aims = targets(classes.groupBy("source").agg(F.sum("words").alias("source_size"))).withColumnRenamed("source", "s")
    largest = Window.partitionBy("s").orderBy(F.desc("digits"))
    held = F.coalesce(F.sum("words").over(largest.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    weighted = F.sum(F.col("words") * F.col("digits")).over(largest.rowsBetween(0, Window.unboundedFollowing))
    rated = classes.join(aims, F.col("source").eqNullSafe(F.col("s"))).withColumn("held", held).withColumn("weighted", weighted)
    rated = rated.withColumn("rate", F.when(F.col("weighted") > 0, (F.col("target") - float(LIMIT) * F.col("held")) / F.col("weighted")))
    rate = F.first(F.when(F.col("rate") * F.col("digits") <= LIMIT, F.col("rate")), ignorenulls=True).over(largest.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    expected = F.when(F.col("source_size") == 0, F.lit(0.0)).otherwise(F.least(F.lit(float(LIMIT)), F.coalesce(F.col("common") * F.col("digits"), F.lit(float(LIMIT)))))
    planned = rated.withColumn("common", rate).withColumn("expected", expected).withColumn("certain", F.floor("expected"))
    left = F.col("target") - F.sum(F.col("certain") * F.col("words")).over(Window.partitionBy("s"))
    return planned.select("s", F.col("digits").alias("d"), "source_size", "target", "certain", (F.col("expected") - F.col("certain")).alias("inclusion"), left.alias("left"))


def cuts(ranked: DataFrame) -> DataFrame:
    """(s, the first row that doesn't fit: point, place; the words that are missing before it) of each source whose order is cut."""
    rows, cut = ranked.where("inclusion > 0 AND left > 0").withColumn("start", F.lit(0).cast("long")), None
    for level, before in (("step", None), ("point", "step"), ("place", "point")):
        own = rows
        if before:
            own = rows.drop("start").join(small(cut, 400), F.col("s").eqNullSafe(F.col("s0")) & (F.col(before) == F.col(f"{before}0")))
        kept = [f"{before}0"] if before == "point" else []
        sums = own.groupBy("s", "left", "start", *kept, level).agg(F.sum("size").alias("words"))
        sums = sums.withColumn("upto", F.col("start") + F.sum("words").over(Window.partitionBy("s").orderBy(level)))
        found = F.struct(*kept, F.col(level).alias(f"{level}0"), "left", (F.col("upto") - F.col("words")).alias("start"))
        first = sums.where("upto > left").groupBy("s").agg(F.min_by(found, level).alias("f"))
        cut = durable(first.select(F.col("s").alias("s0"), *(f"f.{c}" for c in (*kept, f"{level}0", "start")), F.col("f.left").alias("left0")), "mix-cut")
    return cut.select("s0", F.struct(F.col("point0").alias("point"), F.col("place0").alias("place")).alias("last"), (F.col("left0") - F.col("start")).alias("missing"))


def closing(headed: DataFrame) -> DataFrame:
    """(s, row) of the document that closes each source whose head leaves too much missing."""
    off = F.abs(F.col("size") - F.col("missing"))
    beyond = F.greatest(off - NEAR * F.col("target"), F.lit(0.0))
    open_ = headed.where("inclusion > 0 AND last IS NOT NULL AND NOT head").where((F.col("missing") > NEAR * F.col("target")) & (off < F.col("missing")))
    return open_.groupBy(F.col("s").alias("s1")).agg(F.min_by("row", F.struct(beyond, F.col("row"))).alias("closes"))


def mix(df: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", seed: str = "mix", keep: Sequence[str] = ()) -> DataFrame:
    """(key, size, source_size, target, taken, copies) of every row, and its columns ``keep``."""
    digest = F.md5(F.coalesce(F.col(text), F.lit("")))
    named = F.coalesce(F.col(key).cast("string"), F.concat(F.lit("~"), digest))
    u = (F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), named)), 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)
    size = F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")
    base = df.select(F.col(key).alias("k"), F.col(source).alias("source"), size.alias("size"), u.alias("u"), digest.alias("digest"), *(F.col(c).alias(f"keep{i}") for i, c in enumerate(keep)))
    base = durable(base.withColumn("digits", F.length(F.bin("size"))), "mix-base")
    classes = durable(base.groupBy("source", "digits").agg(F.sum("size").alias("words")), "mix-classes")  # some 20 rows a source
    plan = small(durable(plan_of(classes), "mix-plan"), 100)
    spot = F.xxhash64(*PLACE)
    q = (F.col("u") / (1 - F.col("u"))) / (F.col("inclusion") / (1 - F.col("inclusion")))
    ranked = numbered(base).join(plan, F.col("source").eqNullSafe(F.col("s")) & (F.col("digits") == F.col("d"))).withColumn("q", F.when(F.col("inclusion") > 0, q))
    ranked = ranked.withColumns({"step": F.floor(F.col("q") / (1 + F.col("q")) * STEPS), "point": F.struct("q", "digest", F.pmod(spot, F.lit(4096)).alias("sub")), "place": F.struct(spot.alias("spot"), *PLACE)})
    cut = small(durable(cuts(ranked), "mix-cuts"), 400)
    headed = ranked.join(cut, F.col("s").eqNullSafe(F.col("s0")), "left").withColumn("row", F.struct("point", "place"))
    headed = headed.withColumn("head", (F.col("inclusion") > 0) & (F.col("left") > 0) & (F.col("last").isNull() | (F.col("row") < F.col("last"))))
    last = small(durable(closing(headed), "mix-closing"), 400)
    chosen = F.col("head") | F.coalesce(F.col("row") == F.col("closes"), F.lit(False))
    done = headed.join(last, F.col("s").eqNullSafe(F.col("s1")), "left").withColumn("copies", (F.col("certain") + chosen.cast("int")).cast("int"))
    return done.select(F.col("k").alias(key), "size", "source_size", "target", (F.col("copies") * F.col("size")).cast("long").alias("taken"), "copies", *(F.col(f"keep{i}").alias(c) for i, c in enumerate(keep)))


def oracle_sql(table: str = "documents", seed: str = "mix") -> str:
    return f"""
WITH base AS (
  SELECT doc_id AS k, source, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0) AS size, md5(coalesce(text, '')) AS digest,
         (CAST(CAST('0x' || substr(md5('{seed}|' || coalesce(CAST(doc_id AS VARCHAR), '~' || md5(coalesce(text, '')))), 1, 13) AS BIGINT) AS DOUBLE) + 0.5) / 4503599627370496.0 AS u
  FROM {table}),
classes AS (SELECT source, length(bin(CAST(size AS BIGINT))) AS digits, CAST(sum(size) AS BIGINT) AS words FROM base GROUP BY ALL),
sizes AS (SELECT source, CAST(sum(words) AS BIGINT) AS source_size FROM classes GROUP BY source),
weighed AS (SELECT *, CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS DOUBLE) AS weight FROM sizes),
levelled AS (
  SELECT *, 3.0 * source_size / weight AS need,
         (sum(CAST(source_size AS DOUBLE)) OVER () - coalesce(sum(3.0 * source_size) OVER (ORDER BY 3.0 * source_size / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0))
         / sum(weight) OVER (ORDER BY 3.0 * source_size / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM weighed),
common AS (SELECT arg_min(level, need) FILTER (WHERE need >= level) AS common FROM levelled),
aims AS (SELECT source AS s, source_size, CASE WHEN need >= level THEN common * weight ELSE 3.0 * source_size END AS target FROM levelled, common),
held AS (
  SELECT c.*, a.*, coalesce(sum(words) OVER (PARTITION BY s ORDER BY digits DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS held,
         sum(words * digits) OVER (PARTITION BY s ORDER BY digits DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS weighted
  FROM classes c JOIN aims a ON c.source IS NOT DISTINCT FROM a.s),
rated AS (SELECT *, CASE WHEN weighted > 0 THEN (target - 3.0::DOUBLE * CAST(held AS DOUBLE)) / CAST(weighted AS DOUBLE) END AS rate FROM held),
rates AS (SELECT s AS rs, arg_max(rate, digits) AS one FROM rated WHERE rate * digits <= 3 GROUP BY s),
expected AS (
  SELECT r.*, CASE WHEN source_size = 0 THEN 0.0::DOUBLE ELSE least(3.0::DOUBLE, coalesce(one * digits, 3.0::DOUBLE)) END AS expected
  FROM rated r LEFT JOIN rates ON r.s IS NOT DISTINCT FROM rs),
planned AS (
  SELECT s, digits AS d, source_size, target, CAST(floor(expected) AS BIGINT) AS certain, expected - floor(expected) AS inclusion,
         target - CAST(sum(floor(expected) * words) OVER (PARTITION BY s) AS DOUBLE) AS rest FROM expected),
ranked AS (
  SELECT b.*, p.*, CASE WHEN inclusion > 0 THEN (u / (1 - u)) / (inclusion / (1 - inclusion)) END AS q
  FROM base b JOIN planned p ON b.source IS NOT DISTINCT FROM p.s AND length(bin(CAST(b.size AS BIGINT))) = p.d),
running AS (SELECT *, sum(CASE WHEN q IS NOT NULL THEN size ELSE 0 END) OVER (PARTITION BY s ORDER BY q NULLS LAST, digest, k ROWS UNBOUNDED PRECEDING) AS upto FROM ranked),
headed AS (SELECT *, q IS NOT NULL AND rest > 0 AND upto <= rest AS head FROM running),
short AS (SELECT s AS hs, max(rest) - sum(CASE WHEN head THEN size ELSE 0 END) AS missing FROM headed GROUP BY s),
closing AS (
  SELECT s AS cs, k AS ck FROM headed JOIN short ON s IS NOT DISTINCT FROM hs
  WHERE q IS NOT NULL AND rest > 0 AND NOT head AND missing > {NEAR}::DOUBLE * target AND abs(size - missing) < missing
  QUALIFY row_number() OVER (PARTITION BY s ORDER BY greatest(abs(size - missing) - {NEAR}::DOUBLE * target, 0.0::DOUBLE), q, digest, k) = 1),
chosen AS (SELECT h.*, head OR ck IS NOT NULL AS chosen FROM headed h LEFT JOIN closing ON s IS NOT DISTINCT FROM cs AND k = ck)
SELECT k AS doc_id, size, source_size, target, CAST((certain + CASE WHEN chosen THEN 1 ELSE 0 END) * size AS BIGINT) AS taken,
       CAST(certain + CASE WHEN chosen THEN 1 ELSE 0 END AS INTEGER) AS copies
FROM chosen"""
