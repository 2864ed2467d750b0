"""Queries on paths follow the rows of the given tables: an edge without matches and an empty column take no part."""

import duckdb
import pytest
from test_queries import TABLES, normal

import pathlift.registry as registry
from pathlift.functions.measures import combination_count

registry.load_all()


@pytest.fixture(scope="module")
def changed(spark, data, tmp_path_factory):
    """The given tables with nations of unknown regions and parts without brand, and DuckDB's views of them."""
    folder = tmp_path_factory.mktemp("rows")
    c = duckdb.connect()
    for t in TABLES:
        change = {"nation": "n_regionkey + 100 AS n_regionkey", "part": "NULL::VARCHAR AS p_brand"}.get(t)
        c.execute(f"copy (select *{f' replace ({change})' if change else ''} from '{data}/{t}.parquet') to '{folder}/{t}.parquet' (format parquet)")
        c.execute(f"create view {t} as select * from '{folder}/{t}.parquet'")
    return str(folder), c


def rows_of(spark, changed, name):
    folder, c = changed
    ours = registry.QUERIES[name](spark, folder).toPandas()
    assert normal(ours) == normal(c.execute(registry.ORACLES[name]).df())
    return ours


def test_tables_in_reach(spark, data, changed):
    full = {r["table"]: r["hops"] for r in registry.QUERIES["khop_tables"](spark, data).collect()}
    assert full == {"customer": 1, "lineitem": 1, "nation": 2, "part": 2, "supplier": 2, "region": 3}
    assert set(rows_of(spark, changed, "khop_tables")["table"]) == set(full) - {"region"}


def test_pairs(spark, data, changed):
    full = registry.QUERIES["feature_path_pairs"](spark, data).toPandas()
    assert len(full) == 21
    lost = full["path_id"].str.contains("e3") | (full["feature_id"] == "part.p_brand")
    assert normal(rows_of(spark, changed, "feature_path_pairs")) == normal(full[~lost]) and 0 < lost.sum() < 21


def test_selection(spark, data, changed):
    order = lambda folder: registry.QUERIES["greedy_selection"](spark, folder).toPandas()
    full, ours = order(data), order(changed[0])
    assert any("e3" in p for p in full["path_id"]) and "part.p_brand" in set(full["feature_id"])
    assert not any("e3" in p for p in ours["path_id"]) and "part.p_brand" not in set(ours["feature_id"])
    assert set(ours["variant"]) == set(full["variant"]) and (ours.groupby("variant").size() == len(ours) // 5).all()


def test_plans(spark, data, changed):
    full, ours = (f.set_index(["table", "budget"]) for f in (registry.QUERIES["combination_counts"](spark, data).toPandas(), rows_of(spark, changed, "combination_counts")))
    for frame in (full, ours):
        assert all(r.plans == combination_count(r.n, r.m, budget) for (_, budget), r in frame.iterrows())
    assert full.loc[("all", 3), "n"] > ours.loc[("all", 3), "n"] and full.loc[("all", 3), "m"] > ours.loc[("all", 3), "m"] and ("region", 1) not in ours.index
