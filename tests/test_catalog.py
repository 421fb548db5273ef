"""Registered queries against their SQL on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry
from netjoin.plans import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: One of each kind; the driver runs all of them at sf0.01.
CHOSEN = ["net_urban_edges", "net_interstate_edges", "net_trade_edges", "net_lines_edges", "net_mesh_edges", "net_degree_profile", "net_weight_quantiles", "ops_hash_sets", "ops_attr_sets", "ops_disjoint_check", "dj_interstate", "dj_directed_lines",
          "kcp_interstate", "kcp_alpha_0", "kcp_attr", "kcp_p_6", "kcp_bound_local_3", "kcp_interstate_r_2", "given_cross", "given_border", "given_routes", "given_local_pairs", "given_one_cross", "given_closure", "given_table_function", "bisect_sep_urban", "naive_pairs", "euclid_pairs",
          "all_pairs_recursive", "balanced_hash_cut", "hierarchy_nodes", "hierarchy_borders", "hierarchy_balance", "hierarchy_schedule", "imbalance", "idle_slots", "recall_modes", "objects_latest", "objects_closest", "objects_embedded", "objects_by_parts", "rollup_pairs_by_region", "cube_gp_pairs",
          "grouping_sets_pairs", "knn_per_u", "asof_position", "interval_meetings", "session_positions", "json_props", "set_ops_pairs", "ranked_pairs", "pairs_nearby", "paged_pairs", "chain_lengths", "pivot_events", "page_links"]


#: The SQL of k-pairs queries searches within a bound that holds k pairs from this size on.
LARGER = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def duck(sf):
    def over(folder):
        con = duckdb.connect()
        for t in TABLES:
            con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
        return con

    return {folder: over(folder) for folder in (sf, LARGER)}


def same(spark, duck, sf, query, oracle):
    df = query(spark, sf)
    names = sorted(df.columns)
    got = sorted((tuple(r[c] for c in names) for r in df.collect()), key=repr)
    rel = duck[sf].sql(oracle)
    assert sorted(rel.columns) == names
    want = sorted((tuple(r[rel.columns.index(c)] for c in names) for r in rel.fetchall()), key=repr)
    assert got == want


@pytest.mark.parametrize("name", CHOSEN)
def test_query_equals_sql(spark, duck, sf, name):
    sf = LARGER if name.startswith("kcp") or name == "naive_pairs" else sf
    same(spark, duck, sf, catalog.queries()[name], catalog.oracle_sql()[name])


@pytest.mark.parametrize("name", ["bisect_alpha", "seeds_best_of", "work_counters", "bound_trace", "balanced_assign_cut"])
def test_query_gives_rows(spark, sf, name):
    assert catalog.queries()[name](spark, sf).count() > 0


def test_entry_and_names(spark):
    assert entry.entry(spark).columns == ["u", "v", "d"]
    assert set(entry.oracle_sql()) <= set(entry.queries())
