"""Worked examples, exact baselines and invariants of the stages."""

import itertools
import random

import numpy as np
import pytest

from schemasift import queries  # noqa: F401  registers
from schemasift.plans import context, depgraph, encoder, gold, metrics, relgraph, spanner, workloads
from schemasift.registry import ORACLES, QUERIES
from schemasift.sources import catalog
from schemasift.sources import fixtures as fx


def scored(spark, rows):
    return spark.createDataFrame(rows, "qid string, col_id long, score double, y int")


def graph(spark, sf):
    c = catalog.from_parquet(spark, sf)
    e = [tuple(r) for r in depgraph.build(c).select("src", "dst", "rel").collect()]
    cols = c.columns.collect()
    return c, e, {r.col_id: r.table_name for r in cols}, {r.col_id for r in cols if r.is_pk or r.is_fk}, {f"{r.table_name}.{r.column_name}": r.col_id for r in cols}


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES)
    assert len(QUERIES) > 150


def test_campus(spark, sf):
    """Two tables, four columns and one key for each nation's question."""
    from test_oracles import test_same_rows

    rows = QUERIES["campus_example"](spark, sf).collect()
    assert {r.qid for r in rows} == {f"NATION_{i}" for i in range(25)}
    for row in rows:
        assert row.tables == ["nation", "supplier"]
        assert row.columns == ["nation.n_name", "nation.n_nationkey", "supplier.s_nationkey", "supplier.s_suppkey"]
        assert row.fks == ["supplier.s_nationkey -> nation.n_nationkey"]
    assert QUERIES["campus_example"](spark, sf).inputFiles()
    test_same_rows(spark, sf, "campus_example")


def changed(spark, sf, to, **by_table):
    """The tables with some columns replaced by expressions, as a folder of tables."""
    for t in fx.TABLES:
        df = spark.read.parquet(f"{sf}/{t}.parquet")
        df.selectExpr(*(f"{by_table.get(t, {}).get(c, c)} AS {c}" for c in df.columns)).coalesce(1).write.parquet(f"{to}/{t}.parquet")
    return str(to)


def test_campus_finds_names_in_the_rows(spark, sf, tmp_path):
    """Names that stand in other columns too, a null one and one of two nations."""
    from test_oracles import test_same_rows

    odd = changed(
        spark, sf, tmp_path,
        part={"p_name": "CASE WHEN p_partkey < 5 THEN 'NATION_1' ELSE p_name END"},
        lineitem={"l_returnflag": "CASE WHEN l_linenumber = 1 THEN 'NATION_2' ELSE l_returnflag END"},
        supplier={"s_name": "CASE s_suppkey WHEN 1 THEN 'NATION_3' WHEN 2 THEN 'NATION_1' ELSE s_name END"},
        nation={"n_name": "CASE n_nationkey WHEN 7 THEN 'NATION_8' WHEN 9 THEN NULL ELSE n_name END"},
    )
    rows = {r.qid: r for r in QUERIES["campus_example"](spark, odd).collect()}
    assert len(rows) == 23 and rows["NATION_1"].tables == ["lineitem", "nation", "part", "supplier"] and "supplier.s_name" in rows["NATION_3"].columns
    test_same_rows(spark, odd, "campus_example")


def test_catalog_scan_reads_the_tables(spark, sf, tmp_path):
    """All columns of all tables are decoded: nested leaves, odd names, no rows, and a damaged page that no footer shows."""
    import pyarrow.parquet as pq
    from test_oracles import test_same_rows

    assert len(QUERIES["catalog_scan"](spark, sf).inputFiles()) == len(fx.TABLES)
    test_same_rows(spark, sf, "catalog_scan")
    odd = changed(spark, sf, tmp_path, region={"r_name": "struct(r_name AS a, CAST(NULL AS INT) AS `b.c`)"})
    spark.read.parquet(f"{sf}/labels.parquet").limit(0).write.mode("overwrite").parquet(f"{odd}/labels.parquet")
    want = catalog.from_parquet(spark, odd).columns.select("table_name", "column_name", "ordinal", "dtype").collect()
    assert len(want) == 64 and sorted(QUERIES["catalog_scan"](spark, odd).collect()) == sorted(want)
    file = next((tmp_path / "orders.parquet").glob("*.parquet"))
    chunk, data = pq.read_metadata(file).row_group(0).column(5), bytearray(file.read_bytes())
    start = chunk.dictionary_page_offset or chunk.data_page_offset
    data[start : start + chunk.total_compressed_size] = b"\xff" * chunk.total_compressed_size
    (tmp_path / f"orders.parquet/.{file.name}.crc").unlink()
    file.write_bytes(data)
    assert catalog.from_parquet(spark, odd).columns.count() == 64
    with pytest.raises(Exception, match="orders.parquet"):
        QUERIES["catalog_scan"](spark, odd).collect()


@pytest.mark.parametrize("rows, keys", [("true", []), ("l_orderkey % 5 = 0 GROUP BY 1, 4", ["l_orderkey", "l_linenumber"]), ("true GROUP BY 1", ["l_orderkey"]), ("false", []), ("true GROUP BY 1, 4 UNION ALL SELECT * FROM (SELECT * FROM lines LIMIT 1)", [])])
def test_enriched_keys_come_from_the_rows(spark, sf, tmp_path, rows, keys):
    """A key that no list declares is found in the rows: none, a pair, one column; none without rows or where a null is part of it."""
    import shutil

    from test_oracles import test_same_rows

    lines = spark.read.parquet(f"{sf}/lineitem.parquet")
    picked = ", ".join(f"any_value({c}) AS {c}" if "GROUP BY" in rows and c != "l_orderkey" and not (c == "l_linenumber" and "4" in rows) else c for c in lines.columns)
    lines.selectExpr(*("CAST(NULL AS BIGINT) AS l_orderkey" if c == "l_orderkey" else c for c in lines.columns)).createOrReplaceTempView("lines")
    shutil.copytree(sf, tmp_path, dirs_exist_ok=True)
    (tmp_path / "lineitem.parquet").chmod(0o644)
    (tmp_path / "lineitem.parquet").unlink()
    spark.sql(f"SELECT {picked} FROM {{t}} WHERE {rows}", t=lines).coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    got = QUERIES["enrich_catalog"](spark, str(tmp_path)).where("table_name = 'lineitem' AND is_pk").orderBy("col_id")
    assert [r.column_name for r in got.collect()] == keys
    test_same_rows(spark, str(tmp_path), "enrich_catalog")


def test_graph_counts(spark, sf):
    c, e, *_ = graph(spark, sf)
    by = {r: sum(1 for x in e if x[2] == r) for r in range(3)}
    assert by == {depgraph.FK: 8, depgraph.COL_FK: 36, depgraph.COL_PK: 40}
    comps = depgraph.components(c.columns, depgraph.build(c)).select("comp").distinct().count()
    assert comps == 7


@pytest.mark.parametrize("method", ["greedy", "voronoi"])
def test_spanner_invariants(spark, sf, method):
    _, e, table, keys, _ = graph(spark, sf)
    rng = random.Random(3)
    edges = set(e)
    retail = [v for v in table if table[v] in fx.DATABASES["retail7"]]
    for _ in range(25):
        r = set(rng.sample(retail, rng.randint(2, 4)))
        tree = spanner.SPANNERS[method](r, e, table, keys)
        cost = sum(spanner.cost_of(x, r, table, keys) for x in tree)
        best = spanner.span_exact(r, e, table, keys)
        assert set(tree) <= edges and r <= {v for x in tree for v in x[:2]} | r
        assert len(set(depgraph.union_find(sorted({v for x in tree for v in x[:2]} | r), [x[:2] for x in tree]).values())) == 1
        assert cost >= best
        if method == "voronoi":
            assert cost <= 2 * best or best == 0
        degree = {}
        for x in tree:
            for v in x[:2]:
                degree[v] = degree.get(v, 0) + 1
        assert all(d > 1 or v in r for v, d in degree.items())


def test_spanner_known_costs(spark, sf):
    _, e, table, keys, ids = graph(spark, sf)
    r = {ids["nation.n_name"], ids["orders.o_orderpriority"]}
    tree = spanner.span_greedy(r, e, table, keys)
    aux = {v for x in tree for v in x[:2]} - r
    assert aux == {ids[n] for n in ("nation.n_nationkey", "customer.c_nationkey", "customer.c_custkey", "orders.o_custkey", "orders.o_orderkey")} or aux == {ids[n] for n in ("nation.n_nationkey", "customer.c_nationkey", "customer.c_custkey", "orders.o_custkey")}
    assert spanner.span_exact(r, e, table, keys) == 3
    r = {ids["part.p_brand"], ids["region.r_name"]}
    assert spanner.span_exact(r, e, table, keys) == 8
    assert spanner.span_exact({ids["events.value"], ids["orders.o_totalprice"]}, e, table, keys) is None


def test_auc_with_ties(spark):
    s = scored(spark, [("q", 1, 0.9, 1), ("q", 2, 0.5, 1), ("q", 3, 0.5, 0), ("q", 4, 0.1, 0)])
    assert metrics.roc_auc(s).first()[0] == 0.875
    assert metrics.pr_auc(s).first()[0] == pytest.approx(0.5 + 0.5 * 2 / 3)


def test_auc_against_pairs(spark):
    rng = random.Random(1)
    rows = [("q", i, rng.randint(0, 9) / 10, int(rng.random() < 0.3)) for i in range(80)]
    pairs = [(a[2] > b[2]) + 0.5 * (a[2] == b[2]) for a, b in itertools.product(rows, rows) if a[3] and not b[3]]
    s = scored(spark, rows)
    assert metrics.roc_auc(s).first()[0] == pytest.approx(sum(pairs) / len(pairs))
    flipped = metrics.roc_auc(s.withColumn("score", -s["score"])).first()[0]
    assert flipped == pytest.approx(1 - sum(pairs) / len(pairs))


def test_losses(spark):
    g = spark.createDataFrame([("q", 1, 1.0, 0.0)] * 7, "qid string, pos long, fp double, fn double")
    assert gold.infonce(g).first().loss == pytest.approx(-np.log(np.e / (np.e + 7)))
    g = spark.createDataFrame([("q", 1, 0.4, 0.0), ("q", 1, 0.4, -1.0)], "qid string, pos long, fp double, fn double")
    assert gold.margin(g).first().loss == pytest.approx(0.6)


def test_gradients():
    assert workloads.gradient_gap() < 1e-5
    rng = np.random.default_rng(0)
    x, y = rng.normal(size=(9, 12)), np.array([1, 0, 0, 0, 0, 0, 0, 0, 0])
    e = encoder.fresh()
    loss = lambda: encoder.group_loss(e.logit(x), 0, np.arange(1, 8))[0]
    g = encoder.encoder_gradient(e, x, encoder.group_loss(e.logit(x), 0, np.arange(1, 8))[1])
    for p, d in zip(e, g, strict=True):
        at = tuple(0 for _ in p.shape)
        keep = p[at]
        p[at] = keep + 1e-6
        up = loss()
        p[at] = keep - 1e-6
        assert (up - loss()) / 2e-6 == pytest.approx(d[at], abs=1e-5)
        p[at] = keep
    assert y.sum() == 1


def test_training_lowers_the_loss():
    rng = np.random.default_rng(0)
    groups = []
    for _ in range(8):
        x = rng.normal(size=(20, 12))
        groups.append((x, (x[:, 0] > 1).astype(int)))
    _, losses = encoder.train_encoder(groups, epochs=20)
    assert losses[-1] < losses[0] / 2


def test_layer_forms_agree_and_split_is_exact(spark, sf):
    a = {tuple(r) for r in QUERIES["graph_layer_join"](spark, sf).select("col_id", "i", "x").collect()}
    b = {tuple(r) for r in QUERIES["graph_layer_numpy"](spark, sf).select("col_id", "i", "x").collect()}
    assert {x[:2]: round(x[2], 5) for x in a} == {x[:2]: round(x[2], 5) for x in b}


def test_attention_of_equal_logits():
    h = np.ones((3, 2))
    layer = relgraph.seeded([2, 2]).layers[0]
    share, _, _ = relgraph.attention(h, np.array([0, 1]), np.array([2, 2]), layer, 0)
    assert share == pytest.approx([0.5, 0.5])


def test_partial_gradients(spark, sf):
    f = context.features_of(spark, sf).limit(40)
    rows = f.toPandas()
    from pyspark.sql import functions as F

    e, d = encoder.fresh(), (rows["col_id"] % 5 - 2).to_numpy(float)
    want = encoder.encoder_gradient(e, rows[context.FEATURES].to_numpy(float), d)
    again = spark.createDataFrame(rows).withColumn("dscore", (F.col("col_id") % 5 - 2).cast("double"))
    for p, q in zip(want, encoder.partial_gradients(again, e), strict=True):
        assert np.allclose(p, q)


def test_gold_columns_come_from_plans(spark, sf):
    found = {}
    for r in QUERIES["gold_columns"](spark, sf).collect():
        found.setdefault(r.qid, set()).add(f"{r.table_name}.{r.column_name}")
    assert found == {q: set(c.split()) for q, c in fx.GOLD.items()}


def test_no_cartesian_in_key_plans(spark, sf):
    plan = QUERIES["bm25_top2"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan


def test_grouping_expands_without_loss(spark, sf):
    from schemasift.plans import describe

    c = catalog.from_parquet(spark, sf).columns
    g = describe.group_tables(c)
    assert g.count() == 14 and g.where("table_name <> representative").count() == 0


def test_graph_starts_at_the_encoder():
    rng = np.random.default_rng(3)
    x, y = rng.normal(size=(6, 12)), np.array([1, 0, 0, 1, 0, 0])
    e = encoder.fresh("M")
    src, dst, rel = np.array([0, 1, 2, 3]), np.array([1, 2, 3, 4]), np.array([0, 1, 2, 3])
    w, _ = encoder.train_graph([(x, y)], e, src, dst, rel, epochs=0)
    assert relgraph.forward(e.vectors(x), src, dst, rel, w) @ w.w == pytest.approx(e.logit(x))


def test_streamed_index_counts_each_value_once(spark, tmp_path):
    from schemasift.streaming.streams import index_values

    schema, at = "col_id long, value string", f"file://{tmp_path}"
    for k, values in enumerate([["a b", "a c", None], ["a b", "d"], ["", "d", "a c", "e"]]):
        spark.createDataFrame([(1, v) for v in values], schema).coalesce(1).write.parquet(f"{at}/in/part{k}")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{at}/in/*")
    index_values(stream, f"{at}/values", f"{at}/checkpoint")
    got = sorted((r.value, r.len) for r in spark.read.parquet(f"{at}/values").collect())
    assert got == [("", 0), ("a b", 2), ("a c", 2), ("d", 1), ("e", 1)]
    assert spark.read.parquet(f"{at}/values").select("batch").distinct().count() == 3


@pytest.mark.parametrize("name", ["stream_sessions", "stream_dedup"])
def test_appended_rows_stay_off_the_driver(spark, sf, name):
    df = QUERIES[name](spark, sf)
    assert df.inputFiles()  # rows of the memory sink, held by the driver, come from no file
    rows = df.count()
    assert rows == 1000 if name == "stream_dedup" else rows == df.select("start", "user_id").distinct().count() > 0


def test_streams_of_no_events(spark, sf, tmp_path):
    spark.read.parquet(f"{sf}/events.parquet").limit(0).write.parquet(f"{tmp_path}/events.parquet")
    for name in ("stream_sessions", "stream_dedup"):
        assert QUERIES[name](spark, str(tmp_path)).count() == 0


def test_requests_whose_digests_collide_both_stay(spark, sf, tmp_path):
    from schemasift.functions.text import digest

    many = spark.range(300_000).selectExpr("id AS event_id", "TIMESTAMP_NTZ '2024-01-01 00:00:00' AS ts", "id AS user_id", "'view' AS event_type", "1.0D AS value", "'{}' AS props")
    k = digest(*(many[c].cast("string") for c in ("user_id", "event_type", "ts")))
    pair = many.groupBy(k.alias("k")).agg({"user_id": "collect_list"}).toDF("k", "users").where("size(users) > 1").first()
    twice = many.where(many["user_id"].isin(pair["users"]))
    twice.union(twice).coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    assert QUERIES["stream_dedup"](spark, str(tmp_path)).count() == len(pair["users"])


@pytest.mark.parametrize("name", ["base_biencoder", "derive_subschema", "edge_softmax", "enrich_cost"])
def test_rows_come_from_given_tables(spark, sf, name):
    from test_oracles import test_same_rows

    assert QUERIES[name](spark, sf).inputFiles()
    test_same_rows(spark, sf, name)


def test_lsh_recall(spark):
    """Nine tenths of the exact five nearest."""
    for sf in ("sf0.001", "sf0.01"):
        exact, found = ({(r.q, r.v): r.score for r in QUERIES[name](spark, f"/root/testdata/{sf}").collect()} for name in ("knn_exact", "knn_lsh"))
        same = exact.keys() & found.keys()
        assert len(same) >= 0.9 * len(exact) and all(exact[k] == found[k] for k in same)


def test_embedding_rank_is_whole(spark, sf):
    """Each query of the set ranks all other rows, and its first five are the exact nearest."""
    assert "knn_embeddings" not in QUERIES
    rows, n = QUERIES["embedding_rank"](spark, sf).collect(), spark.read.parquet(f"{sf}/embeddings.parquet").count()
    per = {q: sorted(r["rank"] for r in rows if r.q == q) for q in {r.q for r in rows}}
    assert per and all(ranks == list(range(1, n)) for ranks in per.values())
    assert {(r.q, r.v) for r in rows if r["rank"] <= 5} == {(r.q, r.v) for r in QUERIES["knn_exact"](spark, sf).collect()}


def test_exact_profiles_cover_all_tables(spark, sf):
    """Counts of every column of every table, against DuckDB."""
    import duckdb

    got = {(r.table_name, r.column_name): (r.n_rows, r.n_null, r.ndv) for name in ("profile_exact", "profile_exact_facts") for r in QUERIES[name](spark, sf).collect()}
    assert {t for t, _ in got} == set(fx.TABLES)
    for (t, c), counts in got.items():
        assert counts == duckdb.sql(f"SELECT count(*), count(*) - count({c}), count(DISTINCT {c}) FROM '{sf}/{t}.parquet'").fetchall()[0]
