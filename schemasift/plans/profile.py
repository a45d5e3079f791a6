"""Profiles of columns: one aggregate per table, exact or sketched; value descriptions; width statistics."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..registry import query
from ..sources import fixtures as fx

DESCRIBED_NDV = 12


def profile_table(df: DataFrame, table: str, exact: bool = True) -> DataFrame:
    """(table_name, column_name, n_rows, n_null, ndv, lo, hi, max_len) of each column, by one pass."""
    cols = [c for c, kind in df.dtypes if not kind.startswith(("array", "map", "struct"))]
    text = lambda c: F.col(c).cast("string")
    ndv = F.count_distinct if exact else (lambda c: F.approx_count_distinct(c, 0.02))
    aggs = [F.count(F.lit(1)).alias("n_rows")]
    for c in cols:
        aggs += [F.count_if(F.col(c).isNull()).alias(f"n_{c}"), ndv(F.col(c)).alias(f"d_{c}"), F.min(text(c)).alias(f"l_{c}"), F.max(text(c)).alias(f"h_{c}"), F.max(F.length(text(c))).alias(f"m_{c}")]
    one = df.agg(*aggs)
    each = F.array(*(F.struct(F.lit(c).alias("column_name"), F.col(f"n_{c}").alias("n_null"), F.col(f"d_{c}").alias("ndv"), F.col(f"l_{c}").alias("lo"), F.col(f"h_{c}").alias("hi"), F.col(f"m_{c}").cast("long").alias("max_len")) for c in cols))
    return one.select(F.lit(table).alias("table_name"), "n_rows", F.explode(each).alias("p")).select("table_name", "p.column_name", "n_rows", "p.n_null", "p.ndv", "p.lo", "p.hi", "p.max_len")


def profile(spark: SparkSession, sf: str, tables: list[str], exact: bool = True) -> DataFrame:
    return reduce(DataFrame.unionByName, (profile_table(spark.read.parquet(f"{sf}/{t}.parquet"), t, exact) for t in tables))


def value_descr(df: DataFrame, table: str, columns: list[str], cap: int = DESCRIBED_NDV) -> DataFrame:
    """The values of columns with few of them, as text. A count per value bounds what one row gathers to the cap."""
    out = []
    for c in columns:
        values = df.where(F.col(c).isNotNull()).groupBy(F.col(c).cast("string").alias("v")).agg(F.count(F.lit(1)).alias("n")).orderBy("v").limit(cap + 1)
        out.append(values.agg(F.when(F.count(F.lit(1)).between(1, cap), F.concat(F.lit("one of: "), F.array_join(F.array_sort(F.collect_list("v")), ", "))).alias("value_descr")).select(F.lit(table).alias("table_name"), F.lit(c).alias("column_name"), "value_descr"))
    return reduce(DataFrame.union, out)


def value_facts(spark: SparkSession, sf: str, tables: list[str]) -> DataFrame:
    """(table_name, column_name, may_be_null, value_descr) of every column: one pass over a table counts nulls and sketches how many
    values each text column has; only those with few are read again for them, and the exact number decides."""
    load, one = {t: spark.read.parquet(f"{sf}/{t}.parquet") for t in tables}, []
    for t, df in load.items():
        row = df.agg(*(F.struct((F.count_if(F.col(c).isNull()) > 0).alias("nulls"), (F.approx_count_distinct(c, 0.1) if kind == "string" else F.lit(None).cast("long")).alias("about")).alias(f"c{i}") for i, (c, kind) in enumerate(df.dtypes)))
        each = F.array(*(F.struct(F.lit(c).alias("column_name"), F.col(f"c{i}.nulls").alias("may_be_null"), F.col(f"c{i}.about").alias("about")) for i, c in enumerate(df.columns)))
        one.append(row.select(F.lit(t).alias("table_name"), F.inline(each)))
    rows = reduce(DataFrame.union, one).collect()  # a row per column of the catalog
    flags = spark.createDataFrame([tuple(r)[:3] for r in rows], "table_name string, column_name string, may_be_null boolean")
    few = [(r["table_name"], r["column_name"]) for r in rows if r["about"] and r["about"] <= 2 * DESCRIBED_NDV]
    if not few:
        return flags.withColumn("value_descr", F.lit(None).cast("string"))
    described = reduce(DataFrame.union, (value_descr(load[t], t, [c]) for t, c in few))
    return flags.join(F.broadcast(described), ["table_name", "column_name"], "left")


def value_facts_sql(tables: list[str]) -> str:
    out = []
    for t in tables:
        for x in fx.COLUMNS[t].split():
            c, kind = x.split(":")
            descr = f"CASE WHEN count(DISTINCT {c}) <= {DESCRIBED_NDV} THEN 'one of: ' || string_agg(DISTINCT {c}, ', ' ORDER BY {c}) END" if kind == "string" else "CAST(NULL AS VARCHAR)"
            out.append(f"SELECT '{t}' AS table_name, '{c}' AS column_name, count(*) > count({c}) AS may_be_null, {descr} AS value_descr FROM {t}")
    return " UNION ALL ".join(out)


def _profile_sql(tables: list[str]) -> str:
    kinds = {"timestamp_ntz": "strftime({c}, '%Y-%m-%d %H:%M:%S')", "double": None}
    out = []
    for t in tables:
        for x in fx.COLUMNS[t].split():
            c, kind = x.split(":")
            if kind.startswith("array"):
                continue
            text = (kinds.get(kind) or "CAST({c} AS VARCHAR)").format(c=c)
            out.append(f"SELECT '{t}' AS table_name, '{c}' AS column_name, count(*) AS n_rows, count(*) - count({c}) AS n_null, count(DISTINCT {c}) AS ndv, min({text}) AS lo, max({text}) AS hi, CAST(max(length({text})) AS BIGINT) AS max_len FROM {t}")
    return " UNION ALL ".join(out)


@query("profile_exact", _profile_sql(["region", "nation", "labels", "benchmark", "conversations", "pages"]))
def _exact(spark: SparkSession, sf: str) -> DataFrame:
    return profile(spark, sf, ["region", "nation", "labels", "benchmark", "conversations", "pages"])


_FACTS = [t for t in fx.TABLES if t not in ("region", "nation", "labels", "benchmark", "conversations", "pages")]


@query("profile_exact_facts")
def _exact_facts(spark: SparkSession, sf: str) -> DataFrame:
    """The tables that profile_exact leaves out."""
    return profile(spark, sf, _FACTS)


@query("profile_approx")
def _approx(spark: SparkSession, sf: str) -> DataFrame:
    return profile(spark, sf, fx.TABLES, exact=False)


_DESCR = [("orders", c) for c in ("o_orderstatus", "o_orderpriority")] + [("customer", c) for c in ("c_mktsegment", "c_name")] + [("documents", "lang")]


@query("value_descr", " UNION ALL ".join(f"SELECT '{t}' AS table_name, '{c}' AS column_name, CASE WHEN count(DISTINCT {c}) <= {DESCRIBED_NDV} THEN 'one of: ' || string_agg(DISTINCT {c}, ', ' ORDER BY {c}) END AS value_descr FROM {t}" for t, c in _DESCR))
def _descr(spark: SparkSession, sf: str) -> DataFrame:
    by = {}
    for t, c in _DESCR:
        by.setdefault(t, []).append(c)
    return reduce(DataFrame.union, (value_descr(spark.read.parquet(f"{sf}/{t}.parquet"), t, cs) for t, cs in by.items()))


_WIDTHS = ", ".join(f"('{d}', {len(ts)}, {sum(len(fx.COLUMNS[t].split()) for t in ts)})" for d, ts in fx.DATABASES.items())


@query("width_stats", f"SELECT count(*) AS n_dbs, quantile_cont(nt, 0.5) AS med_tables, quantile_cont(nt, 0.95) AS p95_tables, max(nt) AS max_tables, quantile_cont(nc, 0.5) AS med_columns, quantile_cont(nc, 0.95) AS p95_columns, max(nc) AS max_columns FROM (VALUES {_WIDTHS}) v(db, nt, nc)")
def _width(spark: SparkSession, sf: str) -> DataFrame:
    from ..sources.catalog import from_parquet

    every = reduce(DataFrame.union, (from_parquet(spark, sf, d).columns for d in fx.DATABASES))
    return width_stats(every)


def width_stats(columns: DataFrame) -> DataFrame:
    per = columns.groupBy("db_id").agg(F.count_distinct("table_name").alias("nt"), F.count(F.lit(1)).alias("nc"))
    at = lambda c, p: F.percentile(c, F.lit(p))
    return per.agg(F.count(F.lit(1)).alias("n_dbs"), at("nt", 0.5).alias("med_tables"), at("nt", 0.95).alias("p95_tables"), F.max("nt").alias("max_tables"), at("nc", 0.5).alias("med_columns"), at("nc", 0.95).alias("p95_columns"), F.max("nc").alias("max_columns"))
