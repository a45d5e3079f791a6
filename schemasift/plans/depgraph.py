"""The column dependency graph: foreign-key, column-to-foreign-key and column-to-primary-key edges, reversed edges, components."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..registry import query
from ..sources.catalog import Catalog, cte, from_parquet

FK, COL_FK, COL_PK = 0, 1, 2
#: Relations that are preferred where costs are equal: foreign keys, then primary keys, then columns to foreign keys.
TIE = {FK: 0, COL_PK: 1, COL_FK: 2}


def graph_nodes(columns: DataFrame) -> DataFrame:
    return columns.select("db_id", "col_id", "table_name", "column_name")


def fk_edges(columns: DataFrame, fk: DataFrame) -> DataFrame:
    """One edge for each pair of columns of a key."""
    pairs = fk.select("db_id", "src_table", "dst_table", F.explode(F.arrays_zip("src_cols", "dst_cols")).alias("p"))
    s = columns.select("db_id", F.col("table_name").alias("src_table"), F.col("column_name").alias("sc"), F.col("col_id").alias("src"))
    d = columns.select("db_id", F.col("table_name").alias("dst_table"), F.col("column_name").alias("dc"), F.col("col_id").alias("dst"))
    found = pairs.withColumns({"sc": F.col("p.src_cols"), "dc": F.col("p.dst_cols")}).join(s, ["db_id", "src_table", "sc"]).join(d, ["db_id", "dst_table", "dc"])
    return found.select("db_id", "src", "dst", F.lit(FK).alias("rel"))


def col_fk_edges(columns: DataFrame, fk: DataFrame, scope: str = "own") -> DataFrame:
    """Non-key columns to the foreign keys of their table (own), to the columns that those refer to (referenced), or both."""
    if scope == "both":
        return col_fk_edges(columns, fk, "own").union(col_fk_edges(columns, fk, "referenced")).distinct()
    plain = columns.where("NOT is_pk AND NOT is_fk").select("db_id", F.col("table_name").alias("t"), F.col("col_id").alias("src"))
    links = fk_edges(columns, fk).select(F.col("db_id").alias("db"), F.col("src").alias("key_col"), F.col("dst").alias("other"))
    keyed = links.join(columns.select(F.col("col_id").alias("key_col"), F.col("db_id").alias("db"), F.col("table_name").alias("t")), ["db", "key_col"])
    end = "key_col" if scope == "own" else "other"
    return plain.join(keyed.withColumnRenamed("db", "db_id"), ["db_id", "t"]).select("db_id", "src", F.col(end).alias("dst"), F.lit(COL_FK).alias("rel")).distinct()


def col_pk_edges(columns: DataFrame) -> DataFrame:
    keys = columns.where("is_pk").select("db_id", "table_name", F.col("col_id").alias("dst"))
    return columns.where("NOT is_pk").select("db_id", "table_name", F.col("col_id").alias("src")).join(keys, ["db_id", "table_name"]).select("db_id", "src", "dst", F.lit(COL_PK).alias("rel"))


def key_links(columns: DataFrame) -> DataFrame:
    """Keys of a table without a primary key, side by side (an option that the method itself doesn't have)."""
    without = columns.groupBy("db_id", "table_name").agg(F.max("is_pk").alias("has")).where("NOT has").select("db_id", "table_name")
    keys = columns.where("is_fk").join(without, ["db_id", "table_name"]).select("db_id", "table_name", "col_id")
    other = keys.select("db_id", "table_name", F.col("col_id").alias("dst"))
    return keys.withColumnRenamed("col_id", "src").join(other, ["db_id", "table_name"]).where("src < dst").select("db_id", "src", "dst", F.lit(COL_PK).alias("rel"))


def build(catalog: Catalog, scope: str = "own", link_keys: bool = False) -> DataFrame:
    edges = fk_edges(catalog.columns, catalog.fk).union(col_fk_edges(catalog.columns, catalog.fk, scope)).union(col_pk_edges(catalog.columns))
    return edges.union(key_links(catalog.columns)) if link_keys else edges


def with_reverse(edges: DataFrame) -> DataFrame:
    """Both directions; a reversed edge's relation is three more."""
    return edges.withColumn("reverse", F.lit(False)).unionByName(edges.select("db_id", F.col("dst").alias("src"), F.col("src").alias("dst"), (F.col("rel") + 3).alias("rel"), F.lit(True).alias("reverse")))


def union_find(nodes: list[int], pairs: list[tuple[int, int]]) -> dict[int, int]:
    """The least node of each node's component."""
    root = {n: n for n in nodes}

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def components(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(db_id, col_id, comp); a database's catalog is one group, whose size is that of its schema, not of its data."""

    def run(key: tuple, n: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        found = union_find(n["col_id"].tolist(), list(zip(e["src"], e["dst"], strict=True)))
        return pd.DataFrame({"db_id": [key[0]] * len(found), "col_id": list(found), "comp": list(found.values())})

    left, right = nodes.select("db_id", "col_id").groupBy("db_id"), edges.select("db_id", "src", "dst").groupBy("db_id")
    return left.cogroup(right).applyInPandas(run, "db_id string, col_id long, comp long")


def stats(edges: DataFrame) -> DataFrame:
    return edges.groupBy("db_id", "rel").agg(F.count(F.lit(1)).alias("n_edges"), F.count_distinct("src").alias("n_src"), F.count_distinct("dst").alias("n_dst"))


# --- registered queries --------------------------------------------------------------------------------------------------------
_FKE = "fke AS (SELECT s.col_id AS src, d.col_id AS dst, s.table_name AS t FROM fk JOIN cols s ON s.table_name = src_table AND s.column_name = src_col JOIN cols d ON d.table_name = dst_table AND d.column_name = dst_col)"
_OWN = "SELECT c.col_id AS src, f.src AS dst, 1 AS rel FROM cols c JOIN fke f ON f.t = c.table_name WHERE NOT c.is_pk AND NOT c.is_fk"
_REF = "SELECT DISTINCT c.col_id AS src, f.dst AS dst, 1 AS rel FROM cols c JOIN fke f ON f.t = c.table_name WHERE NOT c.is_pk AND NOT c.is_fk"
_PKE = "SELECT c.col_id AS src, k.col_id AS dst, 2 AS rel FROM cols c JOIN cols k ON k.table_name = c.table_name AND k.is_pk WHERE NOT c.is_pk"
EDGES_SQL = f"{_FKE}, edges AS (SELECT src, dst, 0 AS rel FROM fke UNION ALL {_OWN} UNION ALL {_PKE})"
ALL_SQL = f"{cte('cols', 'fk')}, {EDGES_SQL}"


@query("fd_nodes", f"WITH {cte('cols')} SELECT 'all14' AS db_id, col_id, table_name, column_name FROM cols")
def _nodes(spark: SparkSession, sf: str) -> DataFrame:
    return graph_nodes(from_parquet(spark, sf).columns)


@query("fd_edges_fk", f"WITH {cte('cols', 'fk')}, {_FKE} SELECT 'all14' AS db_id, src, dst, 0 AS rel FROM fke")
def _fk(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    return fk_edges(c.columns, c.fk)


@query("fd_edges_colfk", f"WITH {cte('cols', 'fk')}, {_FKE} SELECT 'all14' AS db_id, * FROM ({_OWN})")
def _colfk(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    return col_fk_edges(c.columns, c.fk)


@query("fd_edges_colfk_ref", f"WITH {cte('cols', 'fk')}, {_FKE} SELECT 'all14' AS db_id, * FROM ({_REF})")
def _colfk_ref(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    return col_fk_edges(c.columns, c.fk, "referenced")


@query("fd_edges_colfk_both", f"WITH {cte('cols', 'fk')}, {_FKE} SELECT 'all14' AS db_id, * FROM ({_OWN} UNION {_REF})")
def _colfk_both(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    return col_fk_edges(c.columns, c.fk, "both")


@query("fd_edges_colpk", f"WITH {cte('cols')} SELECT 'all14' AS db_id, * FROM ({_PKE})")
def _colpk(spark: SparkSession, sf: str) -> DataFrame:
    return col_pk_edges(from_parquet(spark, sf).columns)


@query("fd_edges_bidir", f"WITH {ALL_SQL} SELECT 'all14' AS db_id, src, dst, rel, FALSE AS reverse FROM edges UNION ALL SELECT 'all14', dst, src, rel + 3, TRUE FROM edges")
def _bidir(spark: SparkSession, sf: str) -> DataFrame:
    return with_reverse(build(from_parquet(spark, sf)))


@query("fd_edges_linkkeys", f"WITH {cte('cols')}, none AS (SELECT table_name FROM cols GROUP BY table_name HAVING NOT bool_or(is_pk)), k AS (SELECT c.* FROM cols c JOIN none USING (table_name) WHERE is_fk) SELECT 'all14' AS db_id, a.col_id AS src, b.col_id AS dst, 2 AS rel FROM k a JOIN k b ON a.table_name = b.table_name AND a.col_id < b.col_id")
def _link_keys(spark: SparkSession, sf: str) -> DataFrame:
    return key_links(from_parquet(spark, sf).columns)


@query("fd_components", f"""WITH RECURSIVE {ALL_SQL}, both_ways AS (SELECT src, dst FROM edges UNION SELECT dst, src FROM edges),
reach AS (SELECT col_id AS a, col_id AS b FROM cols UNION SELECT r.a, e.dst FROM reach r JOIN both_ways e ON e.src = r.b)
SELECT 'all14' AS db_id, a AS col_id, min(b) AS comp FROM reach GROUP BY a""")
def _components(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    return components(c.columns, build(c))


@query("fd_stats", f"WITH {ALL_SQL} SELECT 'all14' AS db_id, rel, count(*) AS n_edges, count(DISTINCT src) AS n_src, count(DISTINCT dst) AS n_dst FROM edges GROUP BY rel")
def _stats(spark: SparkSession, sf: str) -> DataFrame:
    return stats(build(from_parquet(spark, sf)))


@query("graph_degree", f"WITH {ALL_SQL}, e AS (SELECT src, dst FROM edges UNION ALL SELECT dst, src FROM edges) SELECT src AS col_id, count(*) AS degree FROM e GROUP BY src")
def _degree(spark: SparkSession, sf: str) -> DataFrame:
    return with_reverse(build(from_parquet(spark, sf))).groupBy(F.col("src").alias("col_id")).agg(F.count(F.lit(1)).alias("degree"))


@query("graph_khop", f"WITH {ALL_SQL}, e AS (SELECT src, dst FROM edges UNION SELECT dst, src FROM edges), h1 AS (SELECT dst AS v FROM e JOIN cols c ON c.col_id = e.src WHERE c.column_name = 'o_orderpriority'), h2 AS (SELECT v FROM h1 UNION SELECT e.dst FROM h1 JOIN e ON e.src = h1.v) SELECT v AS col_id FROM h2")
def _khop(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    e = with_reverse(build(c)).select("src", "dst").distinct()
    one = e.join(c.columns.where("column_name = 'o_orderpriority'").select(F.col("col_id").alias("src")), "src").select(F.col("dst").alias("v"))
    return one.union(one.join(e, F.col("v") == F.col("src")).select("dst")).distinct().select(F.col("v").alias("col_id"))


@query("graph_reach", f"WITH RECURSIVE {ALL_SQL}, e AS (SELECT src, dst FROM edges UNION SELECT dst, src FROM edges), r AS (SELECT col_id AS v FROM cols WHERE column_name = 'r_name' UNION SELECT e.dst FROM r JOIN e ON e.src = r.v) SELECT v AS col_id FROM r")
def _reach(spark: SparkSession, sf: str) -> DataFrame:
    c = from_parquet(spark, sf)
    """Reachable nodes are those of the same component, so no step-by-step search is needed."""
    return spark.sql(
        "SELECT b.col_id FROM {comps} a JOIN {comps} b ON a.comp = b.comp JOIN {cols} c ON c.col_id = a.col_id WHERE c.column_name = 'r_name'",
        comps=components(c.columns, build(c)),
        cols=c.columns,
    )
