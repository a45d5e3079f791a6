"""Catalogs as rows: tables, columns and keys of a logical database, read from file footers, by ``scanned`` from all rows."""

from __future__ import annotations

from functools import reduce
from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import fixtures as fx

COLUMN_ROWS = "db_id string, col_id long, table_name string, column_name string, ordinal int, dtype string, is_pk boolean, is_fk boolean"
FK_ROWS = "db_id string, fk_id long, src_table string, src_cols array<string>, dst_table string, dst_cols array<string>, origin string"
PK_ROWS = "db_id string, table_name string, columns array<string>, origin string"


class Catalog(NamedTuple):
    columns: DataFrame
    pk: DataFrame
    fk: DataFrame


def leaves(schema: T.StructType, prefix: str = "") -> list[tuple[str, str]]:
    """(dotted name, type) of every leaf; arrays and maps are leaves."""
    out = []
    for f in schema.fields:
        if isinstance(f.dataType, T.StructType):
            out += leaves(f.dataType, f"{prefix}{f.name}.")
        else:
            out.append((prefix + f.name, f.dataType.simpleString()))
    return out


def rows(spark: SparkSession, listing: dict[str, list[tuple[str, str]]], pk: dict[str, list[str]], fk: list[tuple[str, str, str, str]], db: str) -> Catalog:
    own = {(s, c) for s, c, _, _ in fk}
    cols, n = [], 0
    for t in sorted(listing):
        for i, (c, kind) in enumerate(listing[t]):
            n += 1
            cols.append((db, n, t, c, i + 1, kind, c in pk.get(t, []), (t, c) in own))
    pks = [(db, t, k, "declared") for t, k in sorted(pk.items()) if t in listing]
    fks = [(db, i + 1, s, [c], d, [e], "declared") for i, (s, c, d, e) in enumerate(x for x in fk if x[0] in listing and x[2] in listing)]
    return Catalog(spark.createDataFrame(cols, COLUMN_ROWS), spark.createDataFrame(pks, PK_ROWS), spark.createDataFrame(fks, FK_ROWS))


def from_parquet(spark: SparkSession, sf_dir: str, db: str = "all14") -> Catalog:
    """The catalog of one logical database; only footers are read."""
    return rows(spark, {t: leaves(spark.read.parquet(f"{sf_dir}/{t}.parquet").schema) for t in fx.DATABASES[db]}, fx.PRIMARY_KEYS, fx.FOREIGN_KEYS, db)


def _paths(schema: T.StructType, above: tuple[str, ...] = ()) -> list[str]:
    """The quoted path of every leaf, in the order of ``leaves``."""
    out = []
    for f in schema.fields:
        here = (*above, "`" + f.name.replace("`", "``") + "`")
        out += _paths(f.dataType, here) if isinstance(f.dataType, T.StructType) else [".".join(here)]
    return out


def scanned(spark: SparkSession, sf_dir: str, db: str = "all14") -> DataFrame:
    """(table_name, column_name, ordinal, dtype) of the columns that Spark reads in every row of their table: one aggregate per table
    decodes all of its leaves, so a file that doesn't hold what the footer says fails here. Tables without rows are listed too."""
    out = []
    for t in fx.DATABASES[db]:
        df = spark.read.parquet(f"{sf_dir}/{t}.parquet")
        seen = [(F.count(F.col(p)) + F.count_if(F.col(p).isNull())).alias(f"c{i}") for i, p in enumerate(_paths(df.schema))]
        each = F.array(*(F.struct(F.lit(c).alias("column_name"), F.lit(i + 1).alias("ordinal"), F.lit(kind).alias("dtype"), F.col(f"c{i}").alias("seen")) for i, (c, kind) in enumerate(leaves(df.schema))))
        out.append(df.agg(F.count(F.lit(1)).alias("n"), *seen).select(F.lit(t).alias("table_name"), "n", F.inline(each)).where("seen = n"))
    return reduce(DataFrame.unionByName, out).select("table_name", "column_name", "ordinal", "dtype")


def campus(spark: SparkSession, sf_dir: str) -> Catalog:
    """The worked example's catalog: four of the given tables in one chain of keys."""
    return rows(spark, {t: leaves(spark.read.parquet(f"{sf_dir}/{t}.parquet").schema) for t in fx.CAMPUS}, fx.PRIMARY_KEYS, [x for x in fx.FOREIGN_KEYS if {x[0], x[2]} <= set(fx.CAMPUS)], "campus")


def replicated(spark: SparkSession, sf_dir: str, tables: int, columns: int, db: str | None = None) -> Catalog:
    """A wide catalog: replicas of the given tables with their keys, filled up with noise columns to a given width."""
    base = {t: leaves(spark.read.parquet(f"{sf_dir}/{t}.parquet").schema) for t in fx.TABLES}
    order = fx.DATABASES["retail7"] + [t for t in fx.TABLES if t not in fx.DATABASES["retail7"]]
    listing, pk, fk = {}, {}, []
    for i in range(tables):
        t, r = order[i % len(order)], i // len(order)
        listing[f"{t}_{r}"] = list(base[t])
        pk[f"{t}_{r}"] = fx.PRIMARY_KEYS.get(t, [])
        fk += [(f"{s}_{r}", c, f"{d}_{r}", e) for s, c, d, e in fx.FOREIGN_KEYS if s == t]
    fk = [x for x in fk if x[0] in listing and x[2] in listing]
    words = ["rate", "share", "count", "median", "index", "score", "flag", "code", "total", "ratio"]
    names, k = sorted(listing), 0
    while sum(map(len, listing.values())) < columns:
        listing[names[k % len(names)]].append((f"{words[k % len(words)]}_{k}", "double"))
        k += 1
    return rows(spark, listing, pk, fk, db or f"wide_{tables}_{columns}")


def questions(spark: SparkSession, db: str = "all14") -> DataFrame:
    tables = set(fx.DATABASES.get(db, fx.TABLES))
    data = [(q, db, text, None) for q, text, _ in fx.QUESTIONS if {c.split(".")[0] for c in fx.GOLD[q].split()} <= tables]
    return spark.createDataFrame(data, "qid string, db_id string, text string, evidence string")


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(qid, text) of the users' turns of ``conversations``, asked of the catalog as questions."""
    return spark.read.parquet(f"{sf_dir}/conversations.parquet").where("role = 'user'").selectExpr("concat_ws('-', conv_id, turn) AS qid", "text")


TURNS_SQL = "(SELECT concat_ws('-', conv_id, turn) AS qid, text FROM conversations WHERE role = 'user')"


def gold(spark: SparkSession, catalog: Catalog) -> DataFrame:
    """(qid, col_id) of the columns that gold statements need, by the fixture list."""
    listed = spark.createDataFrame([(q, *c.split(".")) for q, cs in fx.GOLD.items() for c in cs.split()], "qid string, table_name string, column_name string")
    return listed.join(catalog.columns, ["table_name", "column_name"]).select("qid", "col_id")


# --- the SQL side: the same rows as literals -------------------------------------------------------------------------------
def _values(data: list[tuple], names: str) -> str:
    show = lambda v: "NULL" if v is None else str(v).upper() if isinstance(v, bool) else str(v) if isinstance(v, (int, float)) else "'" + str(v).replace("'", "''") + "'"
    return f"(SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(show, r)) + ')' for r in data)}) v({names}))"


def cte(*names: str) -> str:
    """WITH parts for the SQL side: cols, pk, fk, questions, gold."""
    own, cols, n = {(s, c) for s, c, _, _ in fx.FOREIGN_KEYS}, [], 0
    for t in sorted(fx.COLUMNS):
        for i, x in enumerate(fx.COLUMNS[t].split()):
            n += 1
            c, kind = x.split(":")
            cols.append((n, t, c, i + 1, kind, c in fx.PRIMARY_KEYS.get(t, []), (t, c) in own))
    parts = {
        "cols": _values(cols, "col_id, table_name, column_name, ordinal, dtype, is_pk, is_fk"),
        "pk": _values([(t, c) for t, k in fx.PRIMARY_KEYS.items() for c in k], "table_name, column_name"),
        "fk": _values([(i + 1, *x) for i, x in enumerate(fx.FOREIGN_KEYS)], "fk_id, src_table, src_col, dst_table, dst_col"),
        "questions": _values([(q, t) for q, t, _ in fx.QUESTIONS], "qid, text"),
        "goldlist": _values([(q, *c.split(".")) for q, cs in fx.GOLD.items() for c in cs.split()], "qid, table_name, column_name"),
        "gold": "(SELECT g.qid, c.col_id FROM goldlist g JOIN cols c USING (table_name, column_name))",
    }
    return ", ".join(f"{n} AS {parts[n]}" for n in names)
