"""Key recovery: naming rules, data evidence, recorded replies, merging with declared keys, quality."""

from __future__ import annotations

from functools import reduce
from math import prod

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import bare_name, bare_name_sql
from ..registry import query
from ..sources import fixtures as fx
from ..sources.catalog import FK_ROWS, PK_ROWS, Catalog, cte, from_parquet

#: Names of counters inside a key. Fixed values.
COUNTERS = ["turn", "linenumber", "seq", "no", "number", "line", "position"]


def key_like(name: Column) -> Column:
    return bare_name(name).rlike("(^|_)[a-z]*(id|key)$") & F.col("dtype").isin("int", "bigint", "string")


def stem(name: Column) -> Column:
    """What a key name is about: its bare name without the id or key at its end."""
    return F.regexp_replace(bare_name(name), "_?(id|key)$", "")


def uniqueness(spark: SparkSession, sf: str, columns: list[tuple[str, tuple[str, ...]]]) -> DataFrame:
    """(table_name, columns, is_unique): one aggregate per table tests all of its candidates."""
    by: dict[str, list[tuple[str, ...]]] = {}
    for t, cs in columns:
        by.setdefault(t, []).append(cs)
    out = []
    for t, sets in sorted(by.items()):
        df = spark.read.parquet(f"{sf}/{t}.parquet")
        one = df.agg(F.count(F.lit(1)).alias("n"), *(F.count_distinct(*(F.col(c) for c in cs)).alias(f"d{i}") for i, cs in enumerate(sets)))
        each = F.array(*(F.struct(F.array(*(F.lit(c) for c in cs)).alias("columns"), (F.col(f"d{i}") == F.col("n")).alias("is_unique")) for i, cs in enumerate(sets)))
        out.append(one.select(F.lit(t).alias("table_name"), F.explode(each).alias("u")).select("table_name", "u.columns", "u.is_unique"))
    return reduce(DataFrame.union, out)


def pk_candidates(columns: DataFrame) -> list[tuple[str, tuple[str, ...]]]:
    """Single key-like columns, and pairs of one with a counter; as many as the schema has keys."""
    one = columns.where(key_like(F.col("column_name"))).select("table_name", "column_name", "ordinal")
    two = columns.where(bare_name(F.col("column_name")).isin(COUNTERS)).select("table_name", F.col("column_name").alias("counter"))
    rows = one.join(two, "table_name", "left").orderBy("table_name", "ordinal").collect()  # catalog rows
    out = dict.fromkeys((r["table_name"], (r["column_name"],)) for r in rows)
    return [*out, *((r["table_name"], (r["column_name"], r["counter"])) for r in rows if r["counter"])]


def predict_pk(spark: SparkSession, sf: str, columns: DataFrame) -> DataFrame:
    """(table_name, columns): the first unique single candidate in column order, else the first unique pair."""
    fine = uniqueness(spark, sf, pk_candidates(columns)).where("is_unique")
    order = columns.select("table_name", F.col("column_name").alias("first_col"), "ordinal")
    ranked = fine.withColumn("first_col", F.element_at("columns", 1)).join(order, ["table_name", "first_col"])
    return ranked.groupBy("table_name").agg(F.min_by("columns", F.struct(F.size("columns"), F.col("ordinal"))).alias("columns"))


def fk_candidates(columns: DataFrame, pk: DataFrame) -> DataFrame:
    """Key-like columns and single-column primary keys of other tables with one stem, that the other table's name begins with; an
    equi-join on the stem, never all pairs."""
    single = pk.where(F.size("columns") == 1).select(F.col("table_name").alias("dst_table"), F.element_at("columns", 1).alias("dst_col"))
    to = single.withColumn("stem", stem(F.col("dst_col"))).where(F.expr("startswith(dst_table, stem)"))
    of = columns.where(key_like(F.col("column_name"))).select(F.col("table_name").alias("src_table"), F.col("column_name").alias("src_col"), stem(F.col("column_name")).alias("stem"))
    return of.join(to, "stem").where("src_table <> dst_table").select("src_table", "src_col", "dst_table", "dst_col")


def included(spark: SparkSession, sf: str, links: list[tuple[str, str, str, str]]) -> DataFrame:
    """(src_table, src_col, dst_table, dst_col, n_missing): distinct source values that the other column lacks."""
    out = []
    for s, c, d, e in links:
        a = spark.read.parquet(f"{sf}/{s}.parquet").select(F.col(c).cast("string").alias("v")).where("v IS NOT NULL").distinct()
        b = spark.read.parquet(f"{sf}/{d}.parquet").select(F.col(e).cast("string").alias("v"))
        out.append(a.join(b, "v", "left_anti").agg(F.count(F.lit(1)).alias("n_missing")).select(F.lit(s).alias("src_table"), F.lit(c).alias("src_col"), F.lit(d).alias("dst_table"), F.lit(e).alias("dst_col"), "n_missing"))
    return reduce(DataFrame.union, out)


def predict_fk(spark: SparkSession, sf: str, columns: DataFrame, pk: DataFrame) -> DataFrame:
    found = [tuple(r) for r in fk_candidates(columns, pk).orderBy("src_table", "src_col", "dst_table").collect()]  # as many as the schema's links
    return included(spark, sf, found).where("n_missing = 0").drop("n_missing")


def merge(declared: DataFrame, predicted: DataFrame, on: list[str]) -> DataFrame:
    """Declared keys, and predicted ones where none is declared."""
    return declared.withColumn("origin", F.lit("declared")).unionByName(predicted.join(declared, on, "left_anti").withColumn("origin", F.lit("predicted")))


def open_candidates(spark: SparkSession, sf: str, columns: DataFrame) -> list[tuple[str, tuple[str, ...]]]:
    """The candidates that one pass over each table doesn't refute: a table without rows is no evidence, a null is none of a key, and
    whole numbers in a room smaller than the number of rows must repeat. What is left needs an exact test."""
    by: dict[str, list[tuple[str, ...]]] = {}
    for t, cs in pk_candidates(columns):
        by.setdefault(t, []).append(cs)
    out = []
    for t, sets in sorted(by.items()):
        df = spark.read.parquet(f"{sf}/{t}.parquet")
        names, kinds = sorted({c for cs in sets for c in cs}), dict(df.dtypes)
        whole = [c for c in names if kinds[c] in ("tinyint", "smallint", "int", "bigint")]
        r = df.agg(F.count(F.lit(1)).alias("n"), *(F.count(c).alias(f"f_{c}") for c in names), *(f(c).alias(f"{k}_{c}") for c in whole for f, k in ((F.min, "lo"), (F.max, "hi")))).first()
        for cs in sets:
            full = r["n"] > 0 and all(r[f"f_{c}"] == r["n"] for c in cs)
            if full and not (set(cs) <= set(whole) and prod(r[f"hi_{c}"] - r[f"lo_{c}"] + 1 for c in cs) < r["n"]):
                out.append((t, cs))
    return out


def recovered_pk(spark: SparkSession, sf: str, columns: DataFrame) -> list[tuple[str, tuple[str, ...]]]:
    """The first unique single candidate in column order of each table, else the first unique pair; as predict_pk, with fewer exact
    tests."""
    out: dict[str, tuple[str, ...]] = {}
    for t, cs in sorted(open_candidates(spark, sf, columns), key=lambda x: len(x[1])):
        if t not in out and uniqueness(spark, sf, [(t, cs)]).first()["is_unique"]:
            out[t] = cs
    return sorted(out.items())


def recovered(spark: SparkSession, sf: str, c: Catalog) -> Catalog:
    """The catalog with keys from the data where none is declared: primary keys of tables without one, and foreign keys of key-like
    columns that are part of none. Declared keys stay as they are."""
    none = c.columns.join(c.pk.select("table_name").distinct(), "table_name", "left_anti")
    db, n = c.columns.first()["db_id"], c.fk.count()
    pks = [(db, t, list(cs), "predicted") for t, cs in recovered_pk(spark, sf, none)]
    pk = c.pk.unionByName(spark.createDataFrame(pks, PK_ROWS))
    links = fk_candidates(c.columns, pk).join(c.fk.select("src_table", F.explode("src_cols").alias("src_col")), ["src_table", "src_col"], "left_anti")
    asked = [tuple(r) for r in links.select("src_table", "src_col", "dst_table", "dst_col").orderBy("src_table", "src_col", "dst_table").collect()]  # as many as the schema's links
    found = [r for r in included(spark, sf, asked).collect() if not r["n_missing"]] if asked else []
    fks = [(db, n + i + 1, r["src_table"], [r["src_col"]], r["dst_table"], [r["dst_col"]], "predicted") for i, r in enumerate(found)]
    flag = lambda keys: reduce(Column.__or__, ((F.col("table_name") == t) & F.col("column_name").isin(list(cs)) for t, cs in keys), F.lit(False))
    columns = c.columns.withColumns({"is_pk": F.col("is_pk") | flag((t, cs) for _, t, cs, _ in pks), "is_fk": F.col("is_fk") | flag((x[2], x[3]) for x in fks)})
    return Catalog(columns, pk, c.fk.unionByName(spark.createDataFrame(fks, FK_ROWS)))


def keys_from_json(replies: DataFrame) -> DataFrame:
    """(reply_id, table_name, column_name) from recorded replies; broken ones give nothing."""
    parsed = replies.select("reply_id", F.from_json("body", "primary_keys array<struct<table:string,columns:array<string>>>", {"mode": "PERMISSIVE"}).alias("j"))
    return parsed.select("reply_id", F.explode("j.primary_keys").alias("k")).select("reply_id", F.col("k.table").alias("table_name"), F.explode("k.columns").alias("column_name"))


def quality(predicted: DataFrame, truth: DataFrame, on: list[str]) -> DataFrame:
    both = predicted.select(*on).distinct().withColumn("p", F.lit(1)).join(truth.select(*on).distinct().withColumn("t", F.lit(1)), on, "full")
    sums = both.agg(F.count_if(F.expr("p = 1 AND t = 1")).alias("tp"), F.count_if(F.col("t").isNull()).alias("fp"), F.count_if(F.col("p").isNull()).alias("fn"))
    return sums.select("tp", "fp", "fn", F.try_divide("tp", F.col("tp") + F.col("fp")).alias("precision"), F.try_divide("tp", F.col("tp") + F.col("fn")).alias("recall"))


# --- registered queries --------------------------------------------------------------------------------------------------------
_LIKE = [(t, x.split(":")[0]) for t in sorted(fx.COLUMNS) for x in fx.COLUMNS[t].split() if x.split(":")[0].endswith(("id", "key")) and x.split(":")[1] in ("int", "bigint", "string")]
_PAIRS = [(t, c, x.split(":")[0]) for t, c in _LIKE for x in fx.COLUMNS[t].split() if x.split(":")[0].removeprefix("l_") in COUNTERS]
_UNIQUE = " UNION ALL ".join([f"SELECT '{t}' AS table_name, ['{c}'] AS columns, count(DISTINCT {c}) = count(*) AS is_unique FROM {t}" for t, c in _LIKE] + [f"SELECT '{t}', ['{c}', '{d}'], (SELECT count(*) FROM (SELECT DISTINCT {c}, {d} FROM {t})) = (SELECT count(*) FROM {t})" for t, c, d in _PAIRS])
_PK = f"pkp AS (SELECT table_name, arg_min(u.columns, len(u.columns) * 1000 + ordinal) AS columns FROM (SELECT *, columns[1] AS column_name FROM ({_UNIQUE})) u JOIN cols USING (table_name, column_name) WHERE is_unique GROUP BY table_name)"
_STEM = lambda c: f"regexp_replace({bare_name_sql(c)}, '_?(id|key)$', '')"
_INC = lambda s, c, d, e: f"SELECT '{s}' AS src_table, '{c}' AS src_col, '{d}' AS dst_table, '{e}' AS dst_col, (SELECT count(DISTINCT {c}) FROM {s} WHERE {c} NOT IN (SELECT {e} FROM {d})) AS n_missing"
_LINKS = [(s, c, d, e) for s, c in _LIKE for d, k in fx.PRIMARY_KEYS.items() for e in k[:1] if s != d and (d, e) in _LIKE]


#: The columns with the flags of recovered primary keys; no further foreign key can be named in the given tables.
_OPEN = [(t, i, cs) for t in fx.COLUMNS if t not in fx.PRIMARY_KEYS for i, cs in enumerate([(c,) for u, c in _LIKE if u == t] + [(c, d) for u, c, d in _PAIRS if u == t])]
RECOVERED_SQL = "found AS (SELECT table_name, arg_min(columns, i) AS columns FROM (" + " UNION ALL ".join(f"SELECT '{t}' AS table_name, {i} AS i, {list(cs)} AS columns, count(*) > 0 AND count(*) = count(DISTINCT CASE WHEN {' AND '.join(f'{c} IS NOT NULL' for c in cs)} THEN [{', '.join(cs)}] END) AS fits FROM {t}" for t, i, cs in _OPEN) + ") WHERE fits GROUP BY table_name), cols AS (SELECT l.* REPLACE (l.is_pk OR coalesce(list_contains(columns, column_name), FALSE) AS is_pk) FROM listed l LEFT JOIN found USING (table_name))"


@query("ucc_unary", _UNIQUE)
def _ucc(spark: SparkSession, sf: str) -> DataFrame:
    return uniqueness(spark, sf, pk_candidates(from_parquet(spark, sf).columns))


@query("pk_predict", f"WITH {cte('cols')}, {_PK} SELECT table_name, columns FROM pkp")
def _pk(spark: SparkSession, sf: str) -> DataFrame:
    return predict_pk(spark, sf, from_parquet(spark, sf).columns)


_FKP = f"fkp AS (SELECT i.* FROM ({' UNION ALL '.join(_INC(*x) for x in _LINKS)}) i JOIN pkp ON dst_table = table_name AND columns = [dst_col] WHERE {_STEM('src_col')} = {_STEM('dst_col')} AND starts_with(dst_table, {_STEM('dst_col')}) AND n_missing = 0)"


@query("fk_predict", f"WITH {cte('cols')}, {_PK}, {_FKP} SELECT src_table, src_col, dst_table, dst_col FROM fkp")
def _fk(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    return predict_fk(spark, sf, c.columns, predict_pk(spark, sf, c.columns))


_IND = [("events", "user_id", "customer", "c_custkey"), *fx.FOREIGN_KEYS, ("orders", "o_orderkey", "customer", "c_custkey"), ("documents", "doc_id", "labels", "doc_id")]


@query("ind_unary", " UNION ALL ".join(_INC(*x) for x in _IND))
def _ind(spark: SparkSession, sf: str) -> DataFrame:
    return included(spark, sf, _IND)


_REPLIES = [("r1", '{"primary_keys": [{"table": "courses", "columns": ["cid"]}, {"table": "conversations", "columns": ["conv_id", "turn"]}]}'), ("r2", "not json"), ("r3", '{"primary_keys": []}')]


@query("keys_from_json", "SELECT * FROM (VALUES ('r1', 'courses', 'cid'), ('r1', 'conversations', 'conv_id'), ('r1', 'conversations', 'turn')) v(reply_id, table_name, column_name)")
def _json(spark: SparkSession, sf: str) -> DataFrame:
    return keys_from_json(spark.createDataFrame(_REPLIES, "reply_id string, body string"))


@query("key_quality", f"WITH {cte('cols', 'fk')}, {_PK}, {_FKP}, b AS (SELECT p.src_table AS p, f.src_table AS t FROM fkp p FULL JOIN fk f USING (src_table, src_col, dst_table, dst_col)), s AS (SELECT count(*) FILTER (WHERE p IS NOT NULL AND t IS NOT NULL) AS tp, count(*) FILTER (WHERE t IS NULL) AS fp, count(*) FILTER (WHERE p IS NULL) AS fn FROM b) SELECT *, tp / CAST(tp + fp AS DOUBLE) AS precision, tp / CAST(tp + fn AS DOUBLE) AS recall FROM s")
def _quality(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    truth = spark.createDataFrame(fx.FOREIGN_KEYS, "src_table string, src_col string, dst_table string, dst_col string")
    return quality(predict_fk(spark, sf, c.columns, predict_pk(spark, sf, c.columns)), truth, truth.columns)


@query("keys_merged", f"WITH {cte('cols', 'pk')}, {_PK}, d AS (SELECT table_name, list(column_name ORDER BY column_name) AS columns FROM pk WHERE table_name <> 'orders' GROUP BY table_name) SELECT table_name, columns, 'declared' AS origin FROM d UNION ALL SELECT p.table_name, p.columns, 'predicted' FROM pkp p ANTI JOIN d ON d.table_name = p.table_name")
def _merged(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    return merge(c.pk.where("table_name <> 'orders'").select("table_name", "columns"), predict_pk(spark, sf, c.columns), ["table_name"])
