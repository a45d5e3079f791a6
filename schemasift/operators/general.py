"""General relational operators, each a small plan over the given tables with the SQL beside it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.text import digest, digest_sql, expanded, expanded_sql, grams, grams_sql, jaccard, jaccard_sql, tokens, tokens_sql
from ..functions.vectors import cosine, dot, norm
from ..registry import query

Load = Callable[[str], DataFrame]
W, C, L = Window, F.col, F.lit


def N():  # noqa: N802
    return F.count(F.lit(1))


def op(name: str, sql: str | None) -> Callable[[Callable[[Load], DataFrame]], Callable]:
    def put(f: Callable[[Load], DataFrame]) -> Callable:
        query(name, sql)(lambda spark, sf: f(lambda t: spark.read.parquet(f"{sf}/{t}.parquet")))
        return f

    return put


# --- scans, projections, predicates ---------------------------------------------------------------------------------------------
op("scan_parquet", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1999-01-01'")(lambda t: t("lineitem").where(C("l_shipdate") >= F.expr("TIMESTAMP_NTZ '1999-01-01'")).select("l_orderkey", "l_quantity"))
op("filter_project", "SELECT c_name, round(c_acctbal * 1.1, 4) AS raised FROM customer WHERE c_mktsegment = 'MACHINERY' AND c_acctbal < 0")(lambda t: t("customer").where("c_mktsegment = 'MACHINERY' AND c_acctbal < 0").select("c_name", F.round(C("c_acctbal") * 1.1, 4).alias("raised")))
op("filter_in_between", "SELECT p_partkey FROM part WHERE p_size IN (1, 5, 9) OR p_retailprice BETWEEN 900 AND 950")(lambda t: t("part").where(C("p_size").isin(1, 5, 9) | C("p_retailprice").between(900, 950)).select("p_partkey"))
op("filter_like_rlike", "SELECT page_id FROM pages WHERE url LIKE '%?%' AND regexp_matches(url, '/[a-z]{2}/[0-9]+')")(lambda t: t("pages").where(C("url").like("%?%") & C("url").rlike("/[a-z]{2}/[0-9]+")).select("page_id"))
op("filter_nullsafe", "SELECT d.doc_id, coalesce(l.toxic, -1) AS toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL OR l.quality = 1")(lambda t: t("documents").select("doc_id").join(t("labels"), "doc_id", "left").where(C("quality").eqNullSafe(None) | (C("quality") == 1)).select("doc_id", F.coalesce("toxic", L(-1)).alias("toxic")))
op("case_when", "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band FROM orders")(lambda t: t("orders").select("o_orderkey", F.when(C("o_totalprice") > 200000, "high").when(C("o_totalprice") > 100000, "mid").otherwise("low").alias("band")))

# --- joins ---------------------------------------------------------------------------------------------------------------------
op("join_inner_hash", "SELECT c_name, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")(lambda t: t("customer").join(F.broadcast(t("nation")), C("c_nationkey") == C("n_nationkey")).select("c_name", "n_name"))  # nation: 25 rows by definition
op("join_sort_merge", "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(lambda t: t("lineitem").hint("merge").join(t("orders"), C("l_orderkey") == C("o_orderkey")).groupBy("o_orderpriority").agg(N().alias("n")))
op("join_shuffle_hash", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")(lambda t: t("orders").join(t("customer").hint("shuffle_hash"), C("o_custkey") == C("c_custkey")).groupBy("c_mktsegment").agg(N().alias("n")))
op("join_left_outer", "SELECT c_custkey, coalesce(n, 0) AS n FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) ON c_custkey = o_custkey")(lambda t: t("customer").join(t("orders").groupBy("o_custkey").agg(N().alias("n")), C("c_custkey") == C("o_custkey"), "left").select("c_custkey", F.coalesce("n", L(0)).alias("n")))
op("join_full_outer", "SELECT coalesce(c_nationkey, s_nationkey) AS nk, a, b FROM (SELECT c_nationkey, count(*) AS a FROM customer WHERE c_nationkey < 20 GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS b FROM supplier WHERE s_nationkey > 4 GROUP BY 1) ON c_nationkey = s_nationkey")(lambda t: t("customer").where("c_nationkey < 20").groupBy("c_nationkey").agg(N().alias("a")).join(t("supplier").where("s_nationkey > 4").groupBy("s_nationkey").agg(N().alias("b")), C("c_nationkey") == C("s_nationkey"), "full").select(F.coalesce("c_nationkey", "s_nationkey").alias("nk"), "a", "b"))
op("join_left_semi", "SELECT s_name FROM supplier WHERE s_suppkey IN (SELECT l_suppkey FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_name = 'red widget')")(lambda t: t("supplier").join(t("lineitem").join(t("part").where("p_name = 'red widget'"), C("l_partkey") == C("p_partkey"), "left_semi"), C("s_suppkey") == C("l_suppkey"), "left_semi").select("s_name"))
op("join_left_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")(lambda t: t("documents").join(t("labels"), "doc_id", "left_anti").select("doc_id"))
op("join_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation")(lambda t: t("region").crossJoin(F.broadcast(t("nation"))).select("r_name", "n_name"))
op("join_range", "SELECT lo, count(*) AS n FROM part JOIN (SELECT * FROM (VALUES (900, 1000), (1000, 1200), (1200, 3000)) v(lo, hi)) ON p_retailprice >= lo AND p_retailprice < hi GROUP BY lo")(lambda t: t("part").join(F.broadcast(t("part").sparkSession.createDataFrame([(900, 1000), (1000, 1200), (1200, 3000)], "lo int, hi int")), (C("p_retailprice") >= C("lo")) & (C("p_retailprice") < C("hi"))).groupBy("lo").agg(N().alias("n")))


@op("join_interval", "SELECT a.event_id, b.event_id AS error_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'error' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _interval(t: Load) -> DataFrame:
    """An equi-join on user and hour slot (the slot and the next), then the exact interval: never a pair outside two hours."""
    a = t("events").where("event_type = 'click'").select("event_id", "user_id", "ts").withColumn("slot", F.explode(F.array(F.date_trunc("hour", "ts"), F.date_trunc("hour", "ts") + F.expr("INTERVAL 1 HOUR"))))
    b = t("events").where("event_type = 'error'").select(C("event_id").alias("error_id"), "user_id", C("ts").alias("ts2")).withColumn("slot", F.date_trunc("hour", "ts2"))
    return a.join(b, ["user_id", "slot"]).where((C("ts2") >= C("ts")) & (C("ts2") <= C("ts") + F.expr("INTERVAL 1 HOUR"))).select("event_id", "error_id")


@op("join_asof", "SELECT p.event_id, max(v.ts) AS last_view FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts WHERE p.event_type = 'purchase' GROUP BY p.event_id")
def _asof(t: Load) -> DataFrame:
    """One sorted pass per user over both kinds, instead of a join."""
    last = F.last(F.when(C("event_type") == "view", C("ts")), ignorenulls=True).over(W.partitionBy("user_id").orderBy("ts").rangeBetween(W.unboundedPreceding, W.currentRow))
    return t("events").where(C("event_type").isin("view", "purchase")).withColumn("last_view", last).where("event_type = 'purchase'").select("event_id", "last_view")


def _lateral(t: Load) -> DataFrame:
    """For each brand, the head of an ordered subquery that names it."""
    own = t("part").alias("p").where(C("p.p_brand").eqNullSafe(C("b.brand").outer())).orderBy(F.desc("p_retailprice"), "p_partkey").limit(2).select("p_partkey")
    return t("part").select(C("p_brand").alias("brand")).distinct().alias("b").lateralJoin(own).select(C("brand").alias("p_brand"), "p_partkey")


op("join_lateral_topk", "SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 2")(lambda t: _lateral(t))
op("join_self_chain", "SELECT r_name, count(*) AS n FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey GROUP BY 1")(lambda t: t("orders").join(t("customer"), C("o_custkey") == C("c_custkey")).join(F.broadcast(t("nation")), C("c_nationkey") == C("n_nationkey")).join(F.broadcast(t("region")), C("n_regionkey") == C("r_regionkey")).groupBy("r_name").agg(N().alias("n")))

# --- aggregates ----------------------------------------------------------------------------------------------------------------
op("agg_hash", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q, round(avg(l_discount), 6) AS d, count(*) AS n FROM lineitem GROUP BY 1, 2")(lambda t: t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("q"), F.round(F.avg("l_discount"), 6).alias("d"), N().alias("n")))
op("agg_distinct", "SELECT count(DISTINCT o_custkey) AS c, count(DISTINCT o_orderpriority) AS p FROM orders")(lambda t: t("orders").agg(F.count_distinct("o_custkey").alias("c"), F.count_distinct("o_orderpriority").alias("p")))
op("agg_approx_distinct", None)(lambda t: t("lineitem").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("approx"), F.count_distinct("l_orderkey").alias("exact")))
op("agg_percentile", "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 4) AS med, round(quantile_cont(o_totalprice, 0.95), 4) AS p95 FROM orders GROUP BY 1")(lambda t: t("orders").groupBy("o_orderpriority").agg(F.round(F.percentile("o_totalprice", L(0.5)), 4).alias("med"), F.round(F.percentile("o_totalprice", L(0.95)), 4).alias("p95")))
op("agg_filtered", "SELECT lang, count(*) FILTER (WHERE n_chars > 1000) AS big, count(*) AS n FROM documents GROUP BY 1")(lambda t: t("documents").groupBy("lang").agg(F.count_if(C("n_chars") > 1000).alias("big"), N().alias("n")))
op("agg_collect", "SELECT n_regionkey, list(n_name ORDER BY n_name) AS names FROM nation GROUP BY 1")(lambda t: t("nation").groupBy("n_regionkey").agg(F.array_sort(F.collect_list("n_name")).alias("names")))
op("agg_maxby", "SELECT o_custkey, max(o_totalprice) AS top FROM orders GROUP BY 1")(lambda t: t("orders").groupBy("o_custkey").agg(F.max_by("o_totalprice", "o_totalprice").alias("top")))
op("agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")(lambda t: t("orders").groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(N().alias("n")).select("o_orderstatus", "o_orderpriority", "n"))
op("agg_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")(lambda t: t("orders").rollup("o_orderstatus", "o_orderpriority").agg(N().alias("n")))
op("agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n, GROUPING(o_orderstatus, o_orderpriority) AS g FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")(lambda t: t("orders").cube("o_orderstatus", "o_orderpriority").agg(N().alias("n"), F.grouping_id("o_orderstatus", "o_orderpriority").alias("g")))
op("agg_pivot", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(*) FILTER (WHERE o_orderstatus = 'O') AS o, count(*) FILTER (WHERE o_orderstatus = 'P') AS p FROM orders GROUP BY 1")(lambda t: t("orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(N()).select("o_orderpriority", F.coalesce("F", L(0)).alias("f"), F.coalesce("O", L(0)).alias("o"), F.coalesce("P", L(0)).alias("p")))
op("agg_unpivot", "SELECT p_partkey, 'p_size' AS what, CAST(p_size AS DOUBLE) AS v FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")(lambda t: t("part").select("p_partkey", C("p_size").cast("double").alias("p_size"), "p_retailprice").unpivot("p_partkey", ["p_size", "p_retailprice"], "what", "v"))
op("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")(lambda t: t("orders").groupBy("o_custkey").agg(N().alias("n")).where("n > 12"))
op("agg_sort_based", "SELECT o_custkey, max(o_orderpriority) AS top, min(o_orderstatus) AS low FROM orders GROUP BY 1")(lambda t: t("orders").groupBy("o_custkey").agg(F.max("o_orderpriority").alias("top"), F.min("o_orderstatus").alias("low")))  # text can't be updated in place, so Spark sorts

# --- windows, sorts, sets --------------------------------------------------------------------------------------------------------
_cust = lambda: W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
_prio = lambda: W.partitionBy("p_brand").orderBy("p_size")
op("win_row_number", "SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders")(lambda t: t("orders").select("o_custkey", "o_orderkey", F.row_number().over(_cust()).alias("r")))
op("win_rank", "SELECT p_partkey, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS r FROM part")(lambda t: t("part").select("p_partkey", F.rank().over(_prio()).alias("r")))
op("win_dense_rank", "SELECT p_partkey, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS r FROM part")(lambda t: t("part").select("p_partkey", F.dense_rank().over(_prio()).alias("r")))
op("win_ntile", "SELECT o_orderkey, ntile(4) OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice, o_orderkey) AS q FROM orders")(lambda t: t("orders").select("o_orderkey", F.ntile(4).over(W.partitionBy("o_orderstatus").orderBy("o_totalprice", "o_orderkey")).alias("q")))
op("win_percent_rank", "SELECT p_partkey, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_size), 6) AS r FROM part")(lambda t: t("part").select("p_partkey", F.round(F.percent_rank().over(_prio()), 6).alias("r")))
op("win_cume_dist", "SELECT p_partkey, round(cume_dist() OVER (PARTITION BY p_brand ORDER BY p_size), 6) AS r FROM part")(lambda t: t("part").select("p_partkey", F.round(F.cume_dist().over(_prio()), 6).alias("r")))
op("win_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")(lambda t: t("events").select("event_id", F.lag("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("before"), F.lead("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("after")))
op("win_running_rows", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS n FROM orders")(lambda t: t("orders").select("o_orderkey", N().over(W.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(W.unboundedPreceding, 0)).alias("n")))
op("win_range_frame", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS n FROM part")(lambda t: t("part").select("p_partkey", N().over(_prio().rangeBetween(-2, 2)).alias("n")))
op("win_first_last", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS s FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(lambda t: t("orders").select("o_orderkey", *(f.over(W.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias(n) for f, n in ((F.first("o_orderkey"), "f"), (F.last("o_orderkey"), "l"), (F.nth_value("o_orderkey", 2), "s")))))
op("win_softmax", "SELECT p_partkey, round(exp(p_size / 10.0 - max(p_size / 10.0) OVER (PARTITION BY p_brand)) / sum(exp(p_size / 10.0)) OVER (PARTITION BY p_brand) * exp(max(p_size / 10.0) OVER (PARTITION BY p_brand)), 6) AS s FROM part")(lambda t: t("part").withColumn("e", F.exp(C("p_size") / 10 - F.max(C("p_size") / 10).over(W.partitionBy("p_brand")))).select("p_partkey", F.round(C("e") / F.sum("e").over(W.partitionBy("p_brand")), 6).alias("s")))
op("sort_multi", "SELECT p_partkey, p_brand, p_size FROM part ORDER BY p_brand DESC NULLS LAST, p_size, p_partkey")(lambda t: t("part").select("p_partkey", "p_brand", "p_size").orderBy(F.desc_nulls_last("p_brand"), "p_size", "p_partkey"))
op("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 20")(lambda t: t("orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(20).limit(10).select("o_orderkey"))
op("topk_global", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 15")(lambda t: t("orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(15).select("o_orderkey"))
op("topk_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")(lambda t: t("orders").withColumn("r", F.row_number().over(_cust())).where("r <= 3").select("o_custkey", "o_orderkey"))
_ck, _sk = (lambda t: t("customer").select(C("c_nationkey").alias("k"))), (lambda t: t("supplier").select(C("s_nationkey").alias("k")))
for _name, _word, _f in (("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_union_all", "UNION ALL", DataFrame.union), ("set_intersect", "INTERSECT", DataFrame.intersect), ("set_intersect_all", "INTERSECT ALL", DataFrame.intersectAll), ("set_except", "EXCEPT", DataFrame.subtract), ("set_except_all", "EXCEPT ALL", DataFrame.exceptAll)):
    op(_name, f"SELECT c_nationkey AS k FROM customer {_word} SELECT s_nationkey AS k FROM supplier")(lambda t, f=_f: f(_ck(t), _sk(t)))

# --- scalars -----------------------------------------------------------------------------------------------------------------------
op("str_tokenize", f"SELECT item_id, {tokens_sql('text')} AS ts FROM benchmark")(lambda t: t("benchmark").select("item_id", tokens("text").alias("ts")))
op("str_snake_expand", f"SELECT s, {expanded_sql('s')} AS e FROM (VALUES ('c_mktsegment'), ('doc_id'), ('crs_cd'), ('std_nm')) v(s)")(lambda t: t("region").sparkSession.createDataFrame([("c_mktsegment",), ("doc_id",), ("crs_cd",), ("std_nm",)], "s string").select("s", expanded("s").alias("e")))
op("str_ngrams", f"SELECT p_partkey, round({jaccard_sql(grams_sql('p_name'), grams_sql(repr('red widget')))}, 6) AS j FROM part")(lambda t: t("part").select("p_partkey", F.round(jaccard(grams(C("p_name")), grams(L("red widget"))), 6).alias("j")))
op("str_edit_distance", "SELECT p_partkey, levenshtein(p_name, 'red widget') AS d FROM part")(lambda t: t("part").select("p_partkey", F.levenshtein("p_name", L("red widget")).alias("d")))
op("str_regex", "SELECT page_id, len(regexp_extract_all(html, '<[a-z]+')) AS n_tags, regexp_replace(url, '[0-9]+', '#', 'g') AS shape FROM pages")(lambda t: t("pages").select("page_id", F.regexp_count("html", L("<[a-z]+")).alias("n_tags"), F.regexp_replace("url", "[0-9]+", "#").alias("shape")))
op("str_format", "SELECT n_nationkey, 'nation ' || lpad(CAST(n_nationkey AS VARCHAR), 4, '0') || ': ' || n_name AS s FROM nation")(lambda t: t("nation").select("n_nationkey", F.concat(L("nation "), F.lpad(C("n_nationkey").cast("string"), 4, "0"), L(": "), C("n_name")).alias("s")))
op("str_hash", f"SELECT c_custkey, {digest_sql('c_name')} AS h FROM customer")(lambda t: t("customer").select("c_custkey", digest(C("c_name")).alias("h")))
op("date_parts", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, dayofyear(o_orderdate) AS d FROM orders")(lambda t: t("orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofyear("o_orderdate").alias("d")))
op("date_arith", "SELECT o_orderkey, date_diff('day', CAST(o_orderdate AS DATE), DATE '2002-01-01') AS d FROM orders")(lambda t: t("orders").select("o_orderkey", F.datediff(L("2002-01-01").cast("date"), C("o_orderdate").cast("date")).alias("d")))
op("date_trunc_window", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS h, count(*) AS n FROM events GROUP BY 1")(lambda t: t("events").groupBy(F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH").alias("h")).agg(N().alias("n")))
op("math_scalar", "SELECT p_partkey, round(ln(p_retailprice) + sqrt(p_size) + pow(p_size, 2) + 1 / (1 + exp(-p_size / 10.0)), 6) AS v FROM part")(lambda t: t("part").select("p_partkey", F.round(F.log("p_retailprice") + F.sqrt("p_size") + F.pow("p_size", L(2)) + 1 / (1 + F.exp(-C("p_size") / 10)), 6).alias("v")))
op("arr_hof", f"SELECT item_id, len(list_filter({tokens_sql('text')}, lambda w: length(w) > 5)) AS n_long, list_sum(list_transform({tokens_sql('text')}, lambda w: length(w))) AS chars FROM benchmark")(lambda t: t("benchmark").withColumn("w", tokens("text")).select("item_id", F.size(F.filter("w", lambda x: F.length(x) > 5)).alias("n_long"), F.aggregate(F.transform("w", F.length), L(0), lambda a, x: a + x).alias("chars")))
op("arr_set_ops", f"SELECT item_id, len(list_distinct({tokens_sql('text')})) AS d, len(list_intersect({tokens_sql('text')}, ['the', 'of', 'and'])) AS i FROM benchmark")(lambda t: t("benchmark").withColumn("w", tokens("text")).select("item_id", F.size(F.array_distinct("w")).alias("d"), F.size(F.array_intersect("w", F.array(L("the"), L("of"), L("and")))).alias("i")))
op("arr_vector", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 6) AS nn FROM embeddings")(lambda t: t("embeddings").select("vec_id", F.round(dot(C("embedding"), C("embedding")), 6).alias("nn")))
op("arr_explode", "SELECT doc_id, unnest(string_split(source, 'c')) AS part FROM documents")(lambda t: t("documents").select("doc_id", F.explode(F.split("source", "c")).alias("part")))
op("arr_posexplode", f"SELECT item_id, pos - 1 AS pos, ws[pos] AS w FROM (SELECT item_id, {tokens_sql('text')} AS ws, unnest(generate_series(1, len({tokens_sql('text')}))) AS pos FROM benchmark)")(lambda t: t("benchmark").select("item_id", F.posexplode(tokens("text")).alias("pos", "w")))
op("arr_zip", "SELECT n_nationkey, n_name || '/' || CAST(n_regionkey AS VARCHAR) AS z FROM nation")(lambda t: t("nation").select("n_nationkey", F.explode(F.arrays_zip(F.array("n_name").alias("a"), F.array("n_regionkey").alias("b"))).alias("p")).select("n_nationkey", F.concat_ws("/", "p.a", C("p.b").cast("string")).alias("z")))
op("map_build", "SELECT r_regionkey, 1 AS n_keys, r_name AS v FROM region")(lambda t: t("region").withColumn("m", F.map_from_entries(F.array(F.struct(C("r_regionkey"), C("r_name"))))).select("r_regionkey", F.size("m").alias("n_keys"), F.element_at("m", C("r_regionkey")).alias("v")))
op("map_lookup", "SELECT o_orderkey, CASE o_orderstatus WHEN 'F' THEN 'filled' WHEN 'O' THEN 'open' ELSE 'other' END AS s FROM orders")(lambda t: t("orders").select("o_orderkey", F.coalesce(F.element_at(F.create_map(L("F"), L("filled"), L("O"), L("open")), C("o_orderstatus")), L("other")).alias("s")))
op("map_merge", "SELECT n_nationkey, 2 AS n FROM nation")(lambda t: t("nation").select("n_nationkey", F.size(F.map_concat(F.create_map(L("a"), C("n_name")), F.create_map(L("b"), C("n_name")))).alias("n")))
op("json_extract", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")(lambda t: t("events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")))
op("json_parse", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")(lambda t: t("events").select(F.from_json("props", "k long").alias("p")).groupBy("p.k").agg(N().alias("n")))
op("json_emit", "SELECT n_nationkey, '{\"k\":' || CAST(n_nationkey AS VARCHAR) || ',\"n\":\"' || n_name || '\"}' AS j FROM nation")(lambda t: t("nation").select("n_nationkey", F.to_json(F.struct(C("n_nationkey").alias("k"), C("n_name").alias("n"))).alias("j")))
op("struct_nested", "SELECT n_nationkey, n_name || '!' AS a, n_regionkey AS b FROM nation")(lambda t: t("nation").withColumn("s", F.struct(C("n_name").alias("a"), C("n_regionkey").alias("b"), L(1).alias("c"))).withColumn("s", C("s").withField("a", F.concat("s.a", L("!"))).dropFields("c")).select("n_nationkey", "s.a", "s.b"))
op("page_strip_html", "SELECT page_id, md5(trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \\t\\n]+', ' ', 'g'))) AS h FROM pages")(lambda t: t("pages").select("page_id", F.md5(F.trim(F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), r"[ \t\n]+", " "))).alias("h")))
op("page_url_parts", "SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '://([^/?#]+)', 1) AS host FROM pages")(lambda t: t("pages").select("page_id", F.parse_url("url", L("PROTOCOL")).alias("scheme"), F.parse_url("url", L("HOST")).alias("host")))
op("cast_types", "SELECT o_orderkey, CAST(o_totalprice AS BIGINT) AS whole, TRY_CAST(o_orderpriority AS INT) AS none FROM orders WHERE o_totalprice - floor(o_totalprice) < 0.5")(lambda t: t("orders").where(C("o_totalprice") - F.floor("o_totalprice") < 0.5).select("o_orderkey", C("o_totalprice").cast("long").alias("whole"), C("o_orderpriority").try_cast("int").alias("none")))

# --- vectors, sampling -------------------------------------------------------------------------------------------------------------


@op("knn_exact", "SELECT q, v, round(s, 6) AS score FROM (SELECT a.vec_id AS q, b.vec_id AS v, list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: CAST(z[1] AS DOUBLE) * z[2])) / (sqrt(list_sum(list_transform(a.embedding, lambda x: CAST(x AS DOUBLE) * x))) * sqrt(list_sum(list_transform(b.embedding, lambda x: CAST(x AS DOUBLE) * x)))) AS s FROM embeddings a JOIN embeddings b ON a.vec_id % 100 = 0 AND a.vec_id <> b.vec_id) QUALIFY row_number() OVER (PARTITION BY q ORDER BY round(s, 9) DESC, v) <= 5")
def _knn(t: Load) -> DataFrame:
    """A stated query set (every hundredth vector) against all rows; each task keeps five per query before the shuffle."""
    q = t("embeddings").where("vec_id % 100 = 0").select(C("vec_id").alias("q"), C("embedding").alias("a"))
    pairs = t("embeddings").select(C("vec_id").alias("v"), C("embedding").alias("b")).join(F.broadcast(q), C("q") != C("v")).select("q", "v", cosine(C("a"), C("b")).alias("s"))
    return pairs.withColumn("r", F.row_number().over(W.partitionBy("q").orderBy(F.desc(F.round("s", 9)), "v"))).where("r <= 5").select("q", "v", F.round("s", 6).alias("score"))


#: Tables of sign buckets, bits of each, and how many bits a probed bucket may differ in.
LSH_TABLES, LSH_BITS, LSH_RADIUS = 36, 12, 2


@op("knn_lsh", None)
def _lsh(t: Load) -> DataFrame:
    """Signs against fixed planes make the buckets; a query probes all buckets within the radius, and what it meets is ranked exactly."""
    from itertools import combinations

    import numpy as np

    planes = np.random.default_rng(11).normal(size=(LSH_TABLES, LSH_BITS, 64))
    near = [sum(1 << i for i in bits) for r in range(LSH_RADIUS + 1) for bits in combinations(range(LSH_BITS), r)]

    def buckets(frames):
        for frame in frames:
            x = np.array(frame.pop("embedding").tolist(), np.float64).reshape(-1, 64)
            value = ((np.einsum("nd,tbd->ntb", x, planes) > 0) << np.arange(LSH_BITS)).sum(2) + (np.arange(LSH_TABLES) << LSH_BITS)
            yield frame.assign(buckets=list(value.astype(np.int32)))

    rows = t("embeddings").select("vec_id", "embedding").where("embedding is not null")
    every = rows.mapInPandas(buckets, f"vec_id {dict(rows.dtypes)['vec_id']}, buckets array<int>").select("vec_id", F.explode("buckets").alias("bucket"))
    q = every.where("vec_id % 100 = 0").select(C("vec_id").alias("q"), F.explode(F.transform(F.array(*map(L, near)), lambda m: C("bucket").bitwiseXOR(m))).alias("bucket"))
    met = every.join(q, "bucket").where("q <> vec_id").groupBy(C("vec_id").alias("v")).agg(F.collect_set("q").alias("qs"))
    a, b = rows.where("vec_id % 100 = 0").select(C("vec_id").alias("q"), C("embedding").alias("a")), rows.select(C("vec_id").alias("v"), C("embedding").alias("b"))
    scored = b.join(met, "v").select("v", "b", F.explode("qs").alias("q")).join(F.broadcast(a), "q").select("q", "v", cosine(C("a"), C("b")).alias("s"))
    return scored.withColumn("r", F.row_number().over(W.partitionBy("q").orderBy(F.desc(F.round("s", 9)), "v"))).where("r <= 5").select("q", "v", F.round("s", 6).alias("score"))


op("agg_vector_norm", "SELECT label, round(avg(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)))), 6) AS norm FROM embeddings GROUP BY 1")(lambda t: t("embeddings").groupBy("label").agg(F.round(F.avg(norm(C("embedding"))), 6).alias("norm")))


@op("embedding_rank", "SELECT q, v, row_number() OVER (PARTITION BY q ORDER BY round(s, 9) DESC, v) AS rank FROM (SELECT a.vec_id AS q, b.vec_id AS v, coalesce(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: CAST(z[1] AS DOUBLE) * z[2])) / nullif(sqrt(list_sum(list_transform(a.embedding, lambda x: CAST(x AS DOUBLE) * x))) * sqrt(list_sum(list_transform(b.embedding, lambda x: CAST(x AS DOUBLE) * x))), 0), 0) AS s FROM embeddings a JOIN embeddings b ON a.vec_id % 100 = 0 AND a.vec_id <> b.vec_id)")
def _embedding_rank(t: Load) -> DataFrame:
    """The rank by cosine of every row for each vector of the stated query set."""
    q = t("embeddings").where("vec_id % 100 = 0").select(C("vec_id").alias("q"), C("embedding").alias("a"))
    pairs = t("embeddings").select(C("vec_id").alias("v"), C("embedding").alias("b")).join(F.broadcast(q), C("q") != C("v")).select("q", "v", cosine(C("a"), C("b")).alias("s"))
    return pairs.select("q", "v", F.row_number().over(W.partitionBy("q").orderBy(F.desc(F.round("s", 9)), "v")).cast("long").alias("rank"))


op("sample_md5", f"SELECT o_orderkey FROM orders WHERE {digest_sql('CAST(o_orderkey AS VARCHAR)')} % 10 = 3")(lambda t: t("orders").where(digest(C("o_orderkey").cast("string")) % 10 == 3).select("o_orderkey"))
op("sample_stratified", None)(lambda t: t("labels").sampleBy("toxic", {0: 0.2, 1: 1.0}, seed=5))
