"""A sample of registered queries against DuckDB at the smallest size (the driver runs all of them)."""

import os

import duckdb
import pytest

from schemasift import queries  # noqa: F401  registers
from schemasift.registry import ORACLES, QUERIES
from schemasift.sources.fixtures import TABLES

NAMES = ["fd_edges_bidir", "bm25_top2", "pair_features", "edge_softmax", "steiner_costs", "topk_curve", "base_biencoder", "neg_sample7", "fk_predict", "table_groups", "join_asof", "win_range_frame", "agg_grouping_sets", "stream_tumbling"]


def plain(v):
    if isinstance(v, float):
        return round(v, 5) + 0.0
    if hasattr(v, "quantize"):
        return round(float(v), 5)
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    return v.isoformat()[:19] if hasattr(v, "isoformat") else v


@pytest.mark.parametrize("name", NAMES)
def test_same_rows(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    df = QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    mine = sorted(repr(tuple(plain(r[c]) for c in cols)) for r in df.collect())
    out = con.execute(ORACLES[name])
    names = [d[0] for d in out.description]
    assert sorted(names) == cols
    assert mine == sorted(repr(tuple(plain(r[names.index(c)]) for c in cols)) for r in out.fetchall())
