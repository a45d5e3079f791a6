"""The corpus pipeline: language, near copies, benchmark leaks, source mix, shards; each stage reads what the one before wrote.

Every stage takes (spark, docs, sf_dir) and works on all rows of docs; all but the last return the columns of docs. Decisions
are made for rows, not for ids: rows with equal ids and other texts, or without an id, are judged by themselves.

Cases: a table from which no language can be learned loses only texts without letters; rows without an id are never taken for
near copies, but leave if they leak; repeated rows are one group of near copies, and each of them has its own rank in the mix; an
empty table stays empty; null texts have no letter and leave first.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from schemasift.llm import decontamination, langid, mixing, sharding, simhash
from schemasift.llm.common import PLACE, durable, held_out, numbered, small, table

#: A text of so many letters whose cosine with every language is lower is in none of them.
TELLING, UNLIKE = 64, 0.1


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any letter go, and those with enough letters that are unlike every language that was learned."""
    names, protos = langid.prototypes(langid.sums(docs.where(~held_out("doc_id"))))
    said = langid.predict(docs, names, protos, keep=tuple(docs.columns), prefix="__")
    known = F.lit(not names) | (F.col("__letters") < TELLING) | (F.col("__score") >= UNLIKE)
    return said.where((F.col("__letters") > 0) & known).select(*docs.columns)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group linked by an exact Jaccard of 0.8 of their five-word shingles, the document with the smallest id stays."""
    return simhash.keep_one(docs, 0.8, 5)


def leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage go."""
    return decontamination.clean(docs, table(spark, sf_dir, "benchmark"))


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    placed = numbered(docs)
    taken = durable(mixing.mix(placed, keep=PLACE).where("copies <> 1").select(*(F.col(c).alias(f"m{c}") for c in PLACE), "copies"), "pipeline-mix")
    same = (F.col(PLACE[0]) == F.col(f"m{PLACE[0]}")) & (F.col(PLACE[1]) == F.col(f"m{PLACE[1]}"))
    times = placed.join(small(taken.withColumnRenamed("copies", "__copies"), 256), same, "left").withColumn("__copies", F.coalesce("__copies", F.lit(1)))
    return times.where("__copies > 0").withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__copies")))).select(*docs.columns)


def shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sharding.shard(docs)


STAGES = [("language", language), ("near_copies", near_copies), ("leaks", leaks), ("source_mix", source_mix), ("shards", shards)]
#: Language and near copies have no SQL form; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = durable(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
