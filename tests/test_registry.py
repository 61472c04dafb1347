"""Every kind of registered query against its SQL on the smallest tables, and the driver's contract."""

import math

import duckdb
import pytest

import __spark_entry__ as entry
from itemset_sieve.plans import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = [
    "level1_e3", "level1_e4", "level1_e8", "exact_pairs_e2", "compatible_pairs_e4", "prefix_pairs_e4", "pruned_candidates_e4", "support_bitmap_e4", "padded_hamming_e6", "pair_classes_e6", "minwise_md5_e2b",
    "params_bitsample_e4", "params_minwise_e4", "params_covering_e4", "level_stats_e4", "covering_itemsets_e4", "maximal_e4", "closed_e4", "cube_e3", "rollup_levels_e4", "topk_per_level_e4", "ranks_e4",
    "asof_signup_purchase", "interval_episode_pairs", "stream_window_items", "stream_counts_update", "stream_counts_complete", "stream_summaries", "covering_capped_e8", "one_hot_round_trip_e2b", "udtf_subsets_e4", "fpgrowth_e4", "lift_pairs_e5",
]


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 6)
    return v


@pytest.mark.parametrize("name", SOME)
def test_query_matches_sql(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    df = registry.QUERIES[name](spark, sf)
    rel = con.sql(registry.SQL[name])
    cols = sorted(df.columns)
    assert cols == sorted(rel.columns)
    got = sorted(repr(tuple(plain(r[c]) for c in cols)) for r in df.collect())
    want = sorted(repr(tuple(plain(r[rel.columns.index(c)]) for c in cols)) for r in rel.fetchall())
    assert got == want


def against_sql(spark, d, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{d}/{t}.parquet')")
    df, rel = registry.QUERIES[name](spark, d), con.sql(registry.SQL[name])
    cols = sorted(df.columns)
    got = sorted(repr(tuple(plain(r[c]) for c in cols)) for r in df.collect())
    return got, sorted(repr(tuple(plain(r[rel.columns.index(c)]) for c in cols)) for r in rel.fetchall())


def test_rules_and_windows_go_beyond_pairs(spark, sf):
    got, want = against_sql(spark, sf, "rules_all_e2c")
    assert got == want and any("," in r.antecedent for r in registry.QUERIES["rules_all_e2c"](spark, sf).collect())
    found = registry.QUERIES["stream_mined_windows"](spark, "/root/testdata/sf0.01").groupBy("level").count().collect()
    print(sorted(map(tuple, found)))
    assert max(r.level for r in found) > 2


def test_printed_rounding_is_mined_whole(spark, sf):
    got, want = against_sql(spark, sf, "bitsample_printed_itemsets_e2")
    assert got == want and len(got) > len(duckdb.sql(registry.SQL["bitsample_printed_rounding_e2"].replace("lineitem JOIN part", f"'{sf}/lineitem.parquet' JOIN '{sf}/part.parquet'")).fetchall())
    print(len(got))


def test_break_even_table_has_all_workloads(spark, sf):
    rows = registry.QUERIES["break_even_table"](spark, sf).collect()
    print(len(rows), sum(r.workload in ("e3", "e7") for r in rows))
    assert {r.workload for r in rows} == {"e2", "e3", "e4", "e6", "e7"}


def test_contract(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).columns == ["level", "itemset", "support"]


@pytest.mark.parametrize("name", ["compatible_pairs_e4", "compatible_pairs_brute_e4", "prefix_pairs_e4", "udtf_subsets_e4", "bitsample_printed_rounding_e2", "level_costs_covering_e1"])
def test_query_reads_its_tables_itself(spark, sf, monkeypatch, name):
    """Also where another query of the session has read them."""
    read = []
    load = registry.encode.__globals__["load"]
    monkeypatch.setitem(registry.encode.__globals__, "load", lambda s, d, table, *cols: read.append(table) or load(s, d, table, *cols))
    registry.store(spark, sf, name.split("_")[-1])
    if name.endswith("_e4"):
        registry.exact(spark, sf, "e4")
    read.clear()
    registry.QUERIES[name](spark, sf)
    assert read
