"""Selection of columns and the connectivity spanner: 0/1-cost Steiner trees over the column graph, greedy, by Voronoi regions, exact."""

from __future__ import annotations

import heapq
from functools import reduce

import pandas as pd
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import digest, digest_sql, expanded, expanded_sql, tokens, tokens_sql
from ..registry import query
from ..sources import fixtures as fx
from ..sources.catalog import TURNS_SQL, cte, from_parquet, gold, questions, turns
from .depgraph import EDGES_SQL, TIE, build, components, union_find

Edge = tuple[int, int, int]  # src, dst, relation


# --- selection -------------------------------------------------------------------------------------------------------------------
def ranked(scores: DataFrame) -> DataFrame:
    return scores.withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("score"), "col_id")))


def top_k(scores: DataFrame, k: int) -> DataFrame:
    return ranked(scores).where(F.col("rank") <= k)


def top_pct(scores: DataFrame, p: float) -> DataFrame:
    n = F.count(F.lit(1)).over(Window.partitionBy("qid"))
    return ranked(scores).withColumn("n", n).where(F.col("rank") <= F.ceil(F.lit(p) * F.col("n"))).drop("n")


def by_threshold(scores: DataFrame, tau: float) -> DataFrame:
    return ranked(scores).where(F.col("score") >= tau)


# --- spanners ----------------------------------------------------------------------------------------------------------------------
def cost_of(edge: Edge, terminals: set[int], table: dict[int, str], keys: set[int]) -> int:
    """0 where the edge joins a terminal with a key of its own table, else 1."""
    a, b, _ = edge
    return int(not (table[a] == table[b] and (a in terminals and b in keys or b in terminals and a in keys)))


class _Sets:
    def __init__(self):
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        self.up.setdefault(x, x)
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.find(a), self.find(b)
        self.up[max(a, b)] = min(a, b)
        return a != b


def _pruned(tree: list[Edge], terminals: set[int]) -> list[Edge]:
    """The tree without branches that end in no terminal."""
    tree = list(tree)
    while True:
        degree: dict[int, int] = {}
        for a, b, _ in tree:
            degree[a], degree[b] = degree.get(a, 0) + 1, degree.get(b, 0) + 1
        kept = [e for e in tree if all(degree[v] > 1 or v in terminals for v in e[:2])]
        if len(kept) == len(tree):
            return tree
        tree = kept


def span_greedy(terminals: set[int], edges: list[Edge], table: dict[int, str], keys: set[int]) -> list[Edge]:
    """Cheapest edges first (two cost classes, then the relations' order, then ends), until all terminals that can be joined are;
    what serves no terminal is cut off."""
    reach = _Sets()
    for a, b, _ in edges:
        reach.join(a, b)
    open_ = {reach.find(t) for t in terminals}
    use = [e for e in edges if reach.find(e[0]) in open_]
    sets, tree, apart = _Sets(), [], dict.fromkeys(terminals, True)
    groups = len(terminals)
    goal = len(open_)
    for e in sorted(use, key=lambda e: (cost_of(e, terminals, table, keys), TIE[e[2] % 3], e[0], e[1])):
        if groups == goal:
            break
        a, b = sets.find(e[0]), sets.find(e[1])
        if a != b:
            held = [apart.pop(v, False) for v in (a, b)]
            sets.join(a, b)
            apart[sets.find(a)] = any(held)
            groups -= all(held)
            tree.append(e)
    return _pruned(tree, terminals)


def _adjacent(edges: list[Edge], terminals: set[int], table: dict[int, str], keys: set[int]) -> dict[int, list[tuple[int, int, Edge]]]:
    out: dict[int, list[tuple[int, int, Edge]]] = {}
    for e in sorted(edges, key=lambda e: (TIE[e[2] % 3], e[0], e[1])):
        c = cost_of(e, terminals, table, keys)
        out.setdefault(e[0], []).append((e[1], c, e))
        out.setdefault(e[1], []).append((e[0], c, e))
    return out


def span_voronoi(terminals: set[int], edges: list[Edge], table: dict[int, str], keys: set[int]) -> list[Edge]:
    """Twice the best cost at most: each node goes to its nearest terminal, regions are joined by their cheapest bridges, and the
    paths of those bridges make the tree."""
    near, dist, come = {}, {}, {}
    heap = [(0, i, t, t, None) for i, t in enumerate(sorted(terminals))]
    heapq.heapify(heap)
    adjacent, n = _adjacent(edges, terminals, table, keys), len(terminals)
    while heap:
        d, _, v, t, e = heapq.heappop(heap)
        if v in near:
            continue
        near[v], dist[v], come[v] = t, d, e
        for u, c, edge in adjacent.get(v, []):
            if u not in near:
                n += 1
                heapq.heappush(heap, (d + c, n, u, t, (v, edge)))
    bridges = sorted((dist[a] + cost_of(e, terminals, table, keys) + dist[b], TIE[e[2] % 3], e) for e in edges for a, b in [e[:2]] if a in near and b in near and near[a] != near[b])
    sets, kept = _Sets(), set()
    for _, _, e in bridges:
        if sets.join(near[e[0]], near[e[1]]):
            kept.add(e)
            for v in e[:2]:
                while come[v]:
                    v, edge = come[v]
                    kept.add(edge)
    grown, tree = _Sets(), []
    for e in sorted(kept, key=lambda e: (cost_of(e, terminals, table, keys), e)):
        if grown.join(e[0], e[1]):
            tree.append(e)
    return _pruned(tree, terminals)


def span_exact(terminals: set[int], edges: list[Edge], table: dict[int, str], keys: set[int]) -> int | None:
    """The least cost of a tree over the terminals, by dynamic programming over their subsets; None where they aren't connected."""
    order = sorted(terminals)
    adjacent = _adjacent(edges, terminals, table, keys)
    nodes = sorted({*adjacent, *terminals})
    full, inf = (1 << len(order)) - 1, float("inf")
    best = {m: dict.fromkeys(nodes, inf) for m in range(1, full + 1)}
    for i, t in enumerate(order):
        best[1 << i][t] = 0
    for m in range(1, full + 1):
        row, s = best[m], (m - 1) & m
        while s:
            for v in nodes:
                row[v] = min(row[v], best[s][v] + best[m ^ s][v])
            s = (s - 1) & m
        heap = [(d, v) for v, d in row.items() if d < inf]
        heapq.heapify(heap)
        while heap:
            d, v = heapq.heappop(heap)
            if d == row[v]:
                for u, c, _ in adjacent.get(v, []):
                    if d + c < row[u]:
                        row[u] = d + c
                        heapq.heappush(heap, (d + c, u))
    least = min(best[full].values(), default=inf)
    return None if least == inf else int(least)


SPANNERS = {"greedy": span_greedy, "voronoi": span_voronoi}
SPAN_ROWS = "qid string, col_id long, role string, cost int, connected boolean"


def held_schema(columns: DataFrame, edges: DataFrame, nodes: DataFrame) -> Broadcast:
    """(edges by component, table of each column, key columns), once per database; all are part of its schema, so every task may
    hold them."""
    listed = edges.join(nodes.withColumnRenamed("col_id", "src"), "src").select("comp", "src", "dst", "rel").toPandas()
    by = {int(c): list(zip(g["src"].tolist(), g["dst"].tolist(), g["rel"].tolist(), strict=True)) for c, g in listed.groupby("comp")}
    about = columns.select("col_id", "table_name", (F.col("is_pk") | F.col("is_fk")).alias("k")).collect()  # the schema's columns
    return edges.sparkSession.sparkContext.broadcast((by, {r["col_id"]: r["table_name"] for r in about}, {r["col_id"] for r in about if r["k"]}))


def span(terminals: DataFrame, columns: DataFrame, edges: DataFrame, nodes: DataFrame, method: str = "greedy", held: Broadcast | None = None) -> DataFrame:
    """(qid, col_id, role, cost, connected) of R and the auxiliary columns. Groups are a question and a graph component;
    ``held`` is what ``held_schema`` made, if many calls share it. ``connected`` tells whether the question's terminals are in
    one component."""
    shared = held or held_schema(columns, edges, nodes)
    spanned = SPANNERS[method]

    def run(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        by_comp, table, keys = shared.value
        r = set(g["col_id"].tolist())
        tree = spanned(r, by_comp.get(key[1], []), table, keys)
        cost = sum(cost_of(e, r, table, keys) for e in tree)
        aux = sorted({v for e in tree for v in e[:2]} - r)
        return pd.DataFrame({"qid": key[0], "col_id": [*sorted(r), *aux], "role": ["terminal"] * len(r) + ["auxiliary"] * len(aux), "cost": cost, "connected": bool(g["n_comps"].iloc[0] == 1)})

    t = terminals.select("qid", "col_id").join(F.broadcast(nodes.select("col_id", "comp")), "col_id")
    n = t.groupBy("qid").agg(F.count_distinct("comp").alias("n_comps"))
    return t.join(n, "qid").groupBy("qid", "comp").applyInPandas(run, SPAN_ROWS)


def derive_subschema(selection: DataFrame, columns: DataFrame, fk: DataFrame) -> DataFrame:
    """(qid, tables, columns, fks): tables of the kept columns, and the foreign keys of which both ends are kept."""
    named = selection.select("qid", "col_id").distinct().join(F.broadcast(columns.select("col_id", F.concat_ws(".", "table_name", "column_name").alias("name"), "table_name")), "col_id")
    lists = named.groupBy("qid").agg(F.array_sort(F.collect_set("table_name")).alias("tables"), F.array_sort(F.collect_set("name")).alias("columns"))  # at most the schema
    keys = fk.select(F.explode(F.arrays_zip("src_cols", "dst_cols")).alias("p"), "src_table", "dst_table").select(F.concat_ws(".", "src_table", "p.src_cols").alias("s"), F.concat_ws(".", "dst_table", "p.dst_cols").alias("d"))
    return lists.crossJoin(F.broadcast(keys.agg(F.collect_list(F.struct("s", "d")).alias("every")))).select(
        "qid", "tables", "columns", F.array_sort(F.transform(F.filter("every", lambda k: F.array_contains("columns", k["s"]) & F.array_contains("columns", k["d"])), lambda k: F.concat(k["s"], F.lit(" -> "), k["d"]))).alias("fks")
    )


def sufficiency(selection: DataFrame, wanted: DataFrame) -> DataFrame:
    """(qid, n_gold, n_missing, sufficient)."""
    kept = selection.select("qid", "col_id", F.lit(1).alias("kept")).distinct()
    return wanted.join(kept, ["qid", "col_id"], "left").groupBy("qid").agg(F.count(F.lit(1)).alias("n_gold"), F.count_if(F.col("kept").isNull()).alias("n_missing")).withColumn("sufficient", F.col("n_missing") == 0)


def join_keys_present(selection: DataFrame, columns: DataFrame, fk: DataFrame) -> DataFrame:
    """(qid, n_tables, n_fks, joinable): whether the kept foreign keys join all kept tables into as few parts as they can."""
    sub = derive_subschema(selection, columns, fk)
    return sub.select("qid", F.size("tables").alias("n_tables"), F.size("fks").alias("n_fks"), (F.size("fks") >= F.size("tables") - 1).alias("joinable"))


# --- registered queries --------------------------------------------------------------------------------------------------------
def toy_scores(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame, object]:
    """Scores in 41 steps that lean to the gold columns, with ties; the gold list; the catalog."""
    c = from_parquet(spark, sf)
    g = gold(spark, c)
    pairs = questions(spark).select("qid").crossJoin(c.columns.select("col_id")).join(g.withColumn("y", F.lit(1)), ["qid", "col_id"], "left")
    score = (digest(F.col("qid"), F.col("col_id").cast("string")) % 41) / 41 + F.when(F.col("y") == 1, 0.5).otherwise(0.0)
    return pairs.select("qid", "col_id", score.alias("score"), F.coalesce("y", F.lit(0)).alias("y")), g, c


TOY_SQL = f"{cte('cols', 'questions', 'goldlist', 'gold')}, toy AS (SELECT q.qid, c.col_id, ({digest_sql('q.qid', 'CAST(c.col_id AS VARCHAR)')} % 41)::DOUBLE / 41 + CASE WHEN g.qid IS NULL THEN 0.0 ELSE 0.5 END::DOUBLE AS score, CASE WHEN g.qid IS NULL THEN 0 ELSE 1 END AS y FROM questions q CROSS JOIN cols c LEFT JOIN gold g ON g.qid = q.qid AND g.col_id = c.col_id), rk AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, col_id) AS rank, count(*) OVER (PARTITION BY qid) AS n FROM toy)"
_OUT = "qid, col_id, round(score, 6) AS score, rank"


def _out(df: DataFrame) -> DataFrame:
    return df.select("qid", "col_id", F.round("score", 6).alias("score"), "rank")


@query("select_topk", f"WITH {TOY_SQL} SELECT {_OUT} FROM rk WHERE rank <= 8")
def _topk(spark: SparkSession, sf: str) -> DataFrame:
    return _out(top_k(toy_scores(spark, sf)[0], 8))


@query("select_toppct", f"WITH {TOY_SQL} SELECT {_OUT} FROM rk WHERE rank <= ceil(0.15 * n)")
def _toppct(spark: SparkSession, sf: str) -> DataFrame:
    return _out(top_pct(toy_scores(spark, sf)[0], 0.15))


@query("select_threshold", f"WITH {TOY_SQL} SELECT {_OUT} FROM rk WHERE score >= 0.75")
def _threshold(spark: SparkSession, sf: str) -> DataFrame:
    return _out(by_threshold(toy_scores(spark, sf)[0], 0.75))


@query("steiner_costs", f"WITH {TOY_SQL}, {cte('fk')}, {EDGES_SQL}, r AS (SELECT qid, col_id FROM rk WHERE rank <= 4) SELECT q.qid, e.src, e.dst, e.rel, CASE WHEN a.table_name = b.table_name AND ((ra.qid IS NOT NULL AND (b.is_pk OR b.is_fk)) OR (rb.qid IS NOT NULL AND (a.is_pk OR a.is_fk))) THEN 0 ELSE 1 END AS cost FROM questions q CROSS JOIN edges e JOIN cols a ON a.col_id = e.src JOIN cols b ON b.col_id = e.dst LEFT JOIN r ra ON ra.qid = q.qid AND ra.col_id = e.src LEFT JOIN r rb ON rb.qid = q.qid AND rb.col_id = e.dst")
def _costs(spark: SparkSession, sf: str) -> DataFrame:
    s, _, c = toy_scores(spark, sf)
    return edge_costs(build(c), top_k(s, 4), c.columns, questions(spark))


def edge_costs(edges: DataFrame, terminals: DataFrame, columns: DataFrame, asked: DataFrame) -> DataFrame:
    """(qid, src, dst, rel, cost)."""
    about = columns.select("col_id", "table_name", (F.col("is_pk") | F.col("is_fk")).alias("k"))
    end = lambda n: about.select(F.col("col_id").alias(n), F.col("table_name").alias(f"t_{n}"), F.col("k").alias(f"k_{n}"))
    r = terminals.select("qid", "col_id").distinct()
    each = asked.select("qid").crossJoin(F.broadcast(edges.join(end("src"), "src").join(end("dst"), "dst")))
    each = each.join(r.select("qid", F.col("col_id").alias("src"), F.lit(True).alias("r_src")), ["qid", "src"], "left").join(r.select("qid", F.col("col_id").alias("dst"), F.lit(True).alias("r_dst")), ["qid", "dst"], "left")
    free = (F.col("t_src") == F.col("t_dst")) & ((F.col("r_src").isNotNull() & F.col("k_dst")) | (F.col("r_dst").isNotNull() & F.col("k_src")))
    return each.select("qid", "src", "dst", "rel", F.when(free, 0).otherwise(1).alias("cost"))


def _spanned(spark: SparkSession, sf: str, k: int, method: str) -> tuple[DataFrame, DataFrame, object]:
    s, g, c = toy_scores(spark, sf)
    e = build(c)
    return span(top_k(s, k), c.columns, e, components(c.columns, e), method), g, c


@query("steiner_greedy")
def _greedy(spark: SparkSession, sf: str) -> DataFrame:
    return _spanned(spark, sf, 4, "greedy")[0]


@query("steiner_voronoi")
def _voronoi(spark: SparkSession, sf: str) -> DataFrame:
    return _spanned(spark, sf, 4, "voronoi")[0]


@query("steiner_roles")
def _roles(spark: SparkSession, sf: str) -> DataFrame:
    return _spanned(spark, sf, 4, "greedy")[0].groupBy("qid", "role").agg(F.count(F.lit(1)).alias("n"))


@query("span_stats")
def _span_stats(spark: SparkSession, sf: str) -> DataFrame:
    one, two = (_spanned(spark, sf, 4, m)[0].groupBy("qid").agg(F.count(F.lit(1)).alias("size"), F.count_if(F.col("role") == "auxiliary").alias("aux"), F.max("cost").alias("cost")).withColumn("method", F.lit(m)) for m in SPANNERS)
    return one.union(two)


_SEL = "sel AS (SELECT qid, col_id FROM rk WHERE rank <= 12)"


_NAMED = f"WITH {cte('cols')}, questions AS {TURNS_SQL}, sh AS (SELECT qid, col_id, len(list_intersect({tokens_sql('text')}, {tokens_sql(expanded_sql('column_name'))})) + ({digest_sql('qid', 'CAST(col_id AS VARCHAR)')} % 41)::DOUBLE / 41 AS score FROM questions CROSS JOIN cols), rk AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, col_id) AS rank FROM sh)"


@query("derive_subschema", f"{_NAMED}, {_SEL}, fk AS (SELECT * FROM (VALUES {', '.join(str(x) for x in fx.FOREIGN_KEYS)}) v(st, sc, dt, dc)), l AS (SELECT qid, list_sort(list_distinct(list(table_name))) AS tables, list_sort(list(table_name || '.' || column_name)) AS columns FROM sel JOIN cols USING (col_id) GROUP BY qid) SELECT qid, tables, columns, coalesce((SELECT list(st || '.' || sc || ' -> ' || dt || '.' || dc ORDER BY st || '.' || sc || ' -> ' || dt || '.' || dc) FROM fk WHERE list_contains(columns, st || '.' || sc) AND list_contains(columns, dt || '.' || dc)), []) AS fks FROM l")
def _derive(spark: SparkSession, sf: str) -> DataFrame:
    """The sub-schemas of the users' turns, by the words that they share with names of columns and, for turns that share none, a digest."""
    c = from_parquet(spark, sf)
    named = c.columns.select("col_id", tokens(expanded("column_name")).alias("name"))
    asked = turns(spark, sf).select("qid", tokens("text").alias("words")).crossJoin(F.broadcast(named))
    scores = asked.select("qid", "col_id", (F.size(F.array_intersect("words", "name")) + (digest(F.col("qid"), F.col("col_id").cast("string")) % 41) / 41).alias("score"))
    return derive_subschema(top_k(scores, 12), c.columns, c.fk)


@query("sufficiency", f"WITH {TOY_SQL}, {_SEL} SELECT g.qid, count(*) AS n_gold, count(*) FILTER (WHERE s.qid IS NULL) AS n_missing, count(*) FILTER (WHERE s.qid IS NULL) = 0 AS sufficient FROM gold g LEFT JOIN sel s ON s.qid = g.qid AND s.col_id = g.col_id GROUP BY g.qid")
def _sufficient(spark: SparkSession, sf: str) -> DataFrame:
    s, g, _ = toy_scores(spark, sf)
    return sufficiency(top_k(s, 12), g)


@query("join_keys_present", f"WITH {TOY_SQL}, {_SEL}, fk AS (SELECT * FROM (VALUES {', '.join(str(x) for x in fx.FOREIGN_KEYS)}) v(st, sc, dt, dc)), l AS (SELECT qid, count(DISTINCT table_name) AS nt, list(table_name || '.' || column_name) AS columns FROM sel JOIN cols USING (col_id) GROUP BY qid), m AS (SELECT qid, nt, (SELECT count(*) FROM fk WHERE list_contains(columns, st || '.' || sc) AND list_contains(columns, dt || '.' || dc)) AS nf FROM l) SELECT qid, CAST(nt AS INT) AS n_tables, CAST(nf AS INT) AS n_fks, nf >= nt - 1 AS joinable FROM m")
def _joinable(spark: SparkSession, sf: str) -> DataFrame:
    s, _, c = toy_scores(spark, sf)
    return join_keys_present(top_k(s, 12), c.columns, c.fk)


def selection_connected(selection: DataFrame, edges: DataFrame) -> DataFrame:
    """(qid, n_parts, connected): the parts that the selected columns form among themselves."""

    def run(key: tuple, n: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        if not len(n):
            return pd.DataFrame({"qid": [], "n_parts": [], "connected": []})
        parts = len(set(union_find(n["col_id"].tolist(), list(zip(e["src"], e["dst"], strict=True))).values()))
        return pd.DataFrame({"qid": [key[0]], "n_parts": [parts], "connected": [parts == 1]})

    s = selection.select("qid", "col_id").distinct()
    ends = s.groupBy(F.col("qid").alias("q")).agg(F.collect_set("col_id").alias("kept"))  # at most the schema
    inner = ends.crossJoin(F.broadcast(edges.select("src", "dst"))).where(F.array_contains("kept", F.col("src")) & F.array_contains("kept", F.col("dst"))).select("q", "src", "dst")
    return s.groupBy("qid").cogroup(inner.groupBy("q")).applyInPandas(run, "qid string, n_parts long, connected boolean")


@query("selection_connected", f"""WITH RECURSIVE {TOY_SQL}, {_SEL}, {cte('fk')}, {EDGES_SQL},
inn AS (SELECT a.qid, e.src, e.dst FROM (SELECT src, dst FROM edges UNION SELECT dst, src FROM edges) e JOIN sel a ON a.col_id = e.src JOIN sel b ON b.col_id = e.dst AND b.qid = a.qid),
reach AS (SELECT qid, col_id AS a, col_id AS b FROM sel UNION SELECT r.qid, r.a, i.dst FROM reach r JOIN inn i ON i.qid = r.qid AND i.src = r.b),
lab AS (SELECT qid, a, min(b) AS m FROM reach GROUP BY qid, a) SELECT qid, count(DISTINCT m) AS n_parts, count(DISTINCT m) = 1 AS connected FROM lab GROUP BY qid""")
def _connected(spark: SparkSession, sf: str) -> DataFrame:
    s, _, c = toy_scores(spark, sf)
    return selection_connected(top_k(s, 12), build(c))


def holders(spark: SparkSession, sf: str, values: DataFrame, columns: DataFrame) -> DataFrame:
    """(value, col_id) of the text columns that hold a value as it stands; each is read once, the values are broadcast."""
    out = []
    for r in columns.where("dtype = 'string'").orderBy("col_id").collect():  # the schema's columns
        held = spark.read.parquet(f"{sf}/{r['table_name']}.parquet").select(F.col(f"`{r['column_name']}`").alias("value"))
        out.append(held.join(F.broadcast(values), "value", "left_semi").select("value", F.lit(r["col_id"]).cast("long").alias("col_id")))
    return reduce(DataFrame.union, out).distinct()


_TEXTS = " UNION ALL ".join(f"SELECT qid, '{t}' AS t, '{x.split(':')[0]}' AS c FROM names SEMI JOIN {t} ON {x.split(':')[0]} = qid" for t in fx.CAMPUS for x in fx.COLUMNS[t].split() if x.endswith(":string"))
_CHAIN = ", ".join(str((i, *next((f"{s}.{c}", f"{d}.{e}") for s, c, d, e in fx.FOREIGN_KEYS if {s, d} == set(fx.CAMPUS[i : i + 2])))) for i in range(len(fx.CAMPUS) - 1))


@query(
    "campus_example",
    f"""WITH names AS (SELECT DISTINCT n_name AS qid FROM nation WHERE n_name IS NOT NULL), term AS ({_TEXTS} UNION ALL SELECT qid, 'supplier', 's_suppkey' FROM names),
reach AS (SELECT qid, min(i) AS lo, max(i) AS hi FROM term JOIN (VALUES {', '.join(str((t, i)) for i, t in enumerate(fx.CAMPUS))}) p(t, i) USING (t) GROUP BY qid), chain AS (SELECT * FROM (VALUES {_CHAIN}) v(i, s, d)),
kept AS (SELECT qid, t || '.' || c AS name FROM term UNION SELECT qid, unnest([s, d]) FROM reach JOIN chain ON i >= lo AND i < hi), l AS (SELECT qid, list_sort(list_distinct(list(split_part(name, '.', 1)))) AS tables, list_sort(list(name)) AS columns FROM kept GROUP BY qid)
SELECT qid, tables, columns, coalesce((SELECT list(s || ' -> ' || d ORDER BY s || ' -> ' || d) FROM chain WHERE list_contains(columns, s) AND list_contains(columns, d)), []) AS fks FROM l""",
)
def _campus(spark: SparkSession, sf: str) -> DataFrame:
    """The sub-schemas of the worked example, how many suppliers a nation has, asked for each nation by its name: the supplier's id and
    the columns in which the name is found are the terminals."""
    from ..sources.catalog import campus

    c = campus(spark, sf)
    e = build(c, link_keys=True)
    asked = spark.read.parquet(f"{sf}/nation.parquet").where("n_name IS NOT NULL").select(F.col("n_name").alias("value")).distinct()
    counted = c.columns.where("table_name = 'supplier' AND column_name = 's_suppkey'").select("col_id")
    r = holders(spark, sf, asked, c.columns).union(asked.crossJoin(F.broadcast(counted))).withColumnRenamed("value", "qid")
    return derive_subschema(span(r, c.columns, e, components(c.columns, e)), c.columns, c.fk)
