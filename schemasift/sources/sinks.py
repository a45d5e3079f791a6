"""Sinks, small file sources, a directory data source, SQL-callable functions."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader

from ..functions.text import word_pieces
from ..registry import query
from . import fixtures as fx
from .catalog import questions, scanned


def scratch(spark: SparkSession, name: str) -> str:
    """A folder that all executors share, for tables that live as long as a job."""
    top = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not top:
        if not re.fullmatch(r"local(\[[^\[]*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir names no folder that the executors share")
        top = "file://" + tempfile.mkdtemp(prefix="schemasift-")
        spark.sparkContext.setCheckpointDir(top)
    return f"{top.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def write_partitioned(df: DataFrame, path: str, by: str) -> None:
    """Idempotent: a rerun replaces only the partitions that it has."""
    df.repartition(by).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(by).parquet(path)


def write_bucketed(df: DataFrame, table: str, by: str, buckets: int = 8) -> None:
    """A table whose later joins and groups on the key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).format("parquet").saveAsTable(table)


class CatalogReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def read(self, partition) -> Iterator[tuple]:
        import os

        import pyarrow.dataset as ds

        top = self.path.removeprefix("file://")
        for name in sorted(os.listdir(top)):
            if name.endswith(".parquet"):
                for i, f in enumerate(ds.dataset(f"{top}/{name}").schema):
                    yield name.removesuffix(".parquet"), f.name, i + 1, str(f.type)


class DirectoryCatalog(DataSource):
    """A folder of parquet tables as rows of (table_name, column_name, ordinal, dtype)."""

    @classmethod
    def name(cls) -> str:
        return "directory_catalog"

    def schema(self) -> str:
        return "table_name string, column_name string, ordinal int, dtype string"

    def reader(self, schema) -> CatalogReader:
        return CatalogReader(self.options["path"])


@query("source_catalog")
def _source(spark: SparkSession, sf: str) -> DataFrame:
    spark.dataSource.register(DirectoryCatalog)
    return spark.read.format("directory_catalog").option("path", sf).load()


@query("catalog_scan", "SELECT table_name, column_name, ordinal, dtype FROM (VALUES " + ", ".join(f"('{t}', '{x.split(':')[0]}', {i + 1}, '{x.split(':')[1]}')" for t, cs in fx.COLUMNS.items() for i, x in enumerate(cs.split())) + ") v(table_name, column_name, ordinal, dtype)")
def _scan(spark: SparkSession, sf: str) -> DataFrame:
    return scanned(spark, sf)


@query("scan_footer_stats", " UNION ALL ".join(f"SELECT '{t}' AS table_name, count(*) AS n_rows FROM {t}" for t in ("region", "nation", "part", "labels")))
def _footers(spark: SparkSession, sf: str) -> DataFrame:
    """Row counts from file footers: a count needs no column, so no data page is read."""
    from functools import reduce

    return reduce(DataFrame.union, (spark.read.parquet(f"{sf}/{t}.parquet").agg(F.count(F.lit(1)).alias("n_rows")).select(F.lit(t).alias("table_name"), "n_rows") for t in ("region", "nation", "part", "labels")))


@query("scan_json", "SELECT n_nationkey, n_name FROM nation")
def _json(spark: SparkSession, sf: str) -> DataFrame:
    at = scratch(spark, "json")
    spark.read.parquet(f"{sf}/nation.parquet").write.json(at)
    return spark.read.schema("n_nationkey int, n_name string, _corrupt_record string").json(at).where("_corrupt_record IS NULL").select("n_nationkey", "n_name")


@query("scan_csv", "SELECT r_regionkey, r_name FROM region")
def _csv(spark: SparkSession, sf: str) -> DataFrame:
    at = scratch(spark, "csv")
    spark.read.parquet(f"{sf}/region.parquet").select("r_regionkey", "r_name").write.option("header", True).csv(at)
    return spark.read.schema("r_regionkey int, r_name string").option("header", True).csv(at)


@query("sink_partitioned", "SELECT o_orderkey, o_orderstatus FROM orders")
def _partitioned(spark: SparkSession, sf: str) -> DataFrame:
    at = scratch(spark, "partitioned")
    write_partitioned(spark.read.parquet(f"{sf}/orders.parquet").select("o_orderkey", "o_orderstatus"), at, "o_orderstatus")
    return spark.read.parquet(at).select("o_orderkey", "o_orderstatus")


@query("sink_bucketed", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1")
def _bucketed(spark: SparkSession, sf: str) -> DataFrame:
    name = f"schemasift_{uuid.uuid4().hex[:12]}"
    write_bucketed(spark.read.parquet(f"{sf}/orders.parquet").select("o_custkey", "o_orderkey"), name, "o_custkey")
    return spark.table(name).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))


@query("sql_function_bm25", "SELECT tf, round(ln(1 + (100 - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * 2 / 3.0)), 6) AS s FROM (VALUES (1, 1), (2, 5), (3, 50)) v(tf, df)")
def _function(spark: SparkSession, sf: str) -> DataFrame:
    """A SQL function that the analyzer inlines."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bm25_term(tf DOUBLE, df DOUBLE, n DOUBLE, len DOUBLE, avg DOUBLE) RETURNS DOUBLE RETURN ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * len / avg))")
    return spark.sql("SELECT tf, round(bm25_term(tf, df, 100, 2, 3), 6) AS s FROM VALUES (1, 1), (2, 5), (3, 50) v(tf, df)")


@query("udtf_context_lines", "SELECT 'orders' AS table_name, column_name FROM (VALUES " + ", ".join(f"('{x.split(':')[0]}')" for x in fx.COLUMNS["orders"].split()) + ") v(column_name)")
def _udtf(spark: SparkSession, sf: str) -> DataFrame:
    """A table function that SQL can call: the columns of a sub-schema's text."""
    from pyspark.sql.functions import udtf

    class Lines:
        def eval(self, text: str):  # noqa: ANN202
            for part in text.split(","):
                table, column = part.split(".")
                yield table, column

    spark.udtf.register("context_lines", udtf(Lines, returnType="table_name string, column_name string"))
    listed = ",".join(f"orders.{x.split(':')[0]}" for x in fx.COLUMNS["orders"].split())
    return spark.sql(f"SELECT * FROM context_lines('{listed}')")


@query("explode_subschema", "SELECT * FROM (VALUES " + ", ".join(f"('{q}', '{c.split('.')[0]}', '{c.split('.')[1]}')" for q in fx.GOLD for c in fx.GOLD[q].split()) + ") v(qid, table_name, column_name)")
def _explode(spark: SparkSession, sf: str) -> DataFrame:
    """A table function beside a lateral join: one row for each column of each question's sub-schema."""
    from pyspark.sql.functions import udtf

    class Columns:
        def eval(self, names: str):  # noqa: ANN202
            for name in (names or "").split():
                yield tuple(name.split(".", 1))

    spark.udtf.register("explode_subschema", udtf(Columns, returnType="table_name string, column_name string"))
    held = spark.createDataFrame(list(fx.GOLD.items()), "qid string, names string")
    return spark.sql("SELECT qid, s.table_name, s.column_name FROM {held}, LATERAL explode_subschema(names) s", held=held)


@query("udaf_auc_check")
def _udaf(spark: SparkSession, sf: str) -> DataFrame:
    """A grouped pandas aggregate, beside which the native measure is checked."""
    from ..plans.spanner import toy_scores

    def auc(score: pd.Series, y: pd.Series) -> float:
        r, p = score.rank(), int(y.sum())
        return float((r[y == 1].sum() - p * (p + 1) / 2) / (p * (len(y) - p)))

    f = F.pandas_udf(auc, "double")
    return toy_scores(spark, sf)[0].groupBy("qid").agg(f("score", "y").alias("roc_auc"))


@query("question_tokens")
def _question_tokens(spark: SparkSession, sf: str) -> DataFrame:
    return questions(spark).select("qid", word_pieces(F.col("text")).alias("tokens"))
