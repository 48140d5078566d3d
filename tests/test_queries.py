"""Every query with a SQL twin against DuckDB, on a few rows of each kind; names and types of all are registered."""

import duckdb
import pytest

from dyngraph import catalog

SOME = ["snap_nation_trade", "snap_user_flow", "edge_life_3", "gcn_layer_relu", "gd_cost_chunked_P4", "window_mean_embedding", "link_dataset", "volume_vertex_P4", "speedup_table", "rel_full_outer_diff", "st_sliding_edge_life", "st_session", "st_online_diff"]


@pytest.mark.parametrize("name", SOME)
def test_query_equals_its_twin(spark, sf, name):
    con = duckdb.connect()
    from dyngraph.sources.tables import TABLES

    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = catalog.queries()[name](spark, sf).toPandas()
    want = con.execute(catalog.oracle_sql()[name]).fetchdf()
    assert sorted(got.columns) == sorted(want.columns)
    key = sorted(got.columns)
    plain = lambda df: sorted(map(str, df[key].astype(object).where(df[key].notna(), None).itertuples(index=False, name=None)))
    assert plain(got) == plain(want)


def test_registry():
    assert len(catalog.queries()) >= 90 and set(catalog.oracle_sql()) <= set(catalog.queries())


def test_reach_reads_written_pairs(spark, sf):
    """The recursion's levels read written rows and exchange nothing; they reach what the steps' pairs say."""
    from dyngraph.operators import measures
    from dyngraph.sources import tables

    got = catalog.queries()["rel_recursive_reach"](spark, sf)
    plan = measures.plan_text(got)
    assert "lineitem" not in plan and measures.plan_exchanges(got) == 0
    pairs, now, expect = {}, {0}, [(0, 1)]
    for r in tables.graph(spark, sf, "nation_trade").edges.collect():
        pairs.setdefault(r["t"], set()).add((r["src"], r["dst"]))
    for t in range(1, 81):
        now = {b for a, b in pairs.get(t, ()) if a in now}
        if not now:
            break
        expect.append((t, len(now)))
    assert sorted(map(tuple, got.collect())) == expect


MOVED = ["band_matrix", "block_plan", "evolve_weights_T", "evolve_weights_sql", "fn_sql_surface", "gd_benefit_table", "gd_gain", "layout_time_ratio", "memory_model_grid", "node_split", "owner_in_block", "random_gnm_small"]


@pytest.mark.parametrize("name", MOVED)
def test_made_up_rows_come_from_tables(spark, tmp_path, sf, name):
    """Queries that once made up their data follow the tables: all but two of each 25 orders and their lines left out, they equal their twins."""
    con = duckdb.connect()
    from dyngraph.sources.tables import TABLES

    for t in TABLES:
        some = {"orders": "WHERE o_orderkey % 25 < 2 AND year(o_orderdate) < 1999", "lineitem": "WHERE l_orderkey % 25 < 2"}.get(t, "")
        con.execute(f"COPY (SELECT * FROM '{sf}/{t}.parquet' {some}) TO '{tmp_path}/{t}.parquet' (FORMAT parquet)")
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet'")
    sql = catalog.oracle_sql()[name]
    assert "FROM orders" in sql or "FROM lineitem" in sql
    key = sorted(catalog.queries()[name](spark, str(tmp_path)).columns)
    plain = lambda df: sorted(map(str, df[key].astype(object).where(df[key].notna(), None).itertuples(index=False, name=None)))
    assert plain(catalog.queries()[name](spark, str(tmp_path)).toPandas()) == plain(con.execute(sql).fetchdf())
