"""Queries against their SQL twins on the smallest tables."""

import os

import duckdb
import pytest

from balclust import catalogue

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = [
    "m03_cell_keys", "m06_cell_counts_w11", "m08_marks_w06", "m09_parts_w01", "m13_failures", "m15_coreset_lineitem", "w02_coreset_median", "w05_coreset_one_column", "w14_coreset_documents", "w20_coreset_theory",
    "m16_guess_ladder", "m18_estimates", "m20_two_centres_w04_r1", "m22_cost_w06_r1_5", "m25_half_spaces", "m28_regions", "m33_m34_extension", "m36_cell_store", "m36_overfull_store_fails", "m39_messages",
    "b02_plain_coreset", "b04_snapped_cells", "b06_ring_sample", "w07_stream_cells", "stream_restart", "stream_session_users", "csv_roundtrip", "nearest_three_centres", "udf_hash_equals_column", "grid_cells_udtf",
    "a02_a03_ratios", "w19_ablation", "m35_serve", "a04_solution_quality", "v04_capacitated_bottleneck", "v13_exhaustive_pairs", "a20_assignments_counted", "a07_heavy_bound", "a09_level_mass_bound", "a11_sampling_error",
    "w18_scale_sweep", "m25_half_spaces_four", "m28_regions_events", "m29_region_tallies_orders_r1", "m30_transfer_four", "m27_tie_exchange_orders", "v08_coreset_hashed_events", "m40_distributed_coreset_4", "m40_total_bits",
    "w10_skewed_coreset", "w10_bits_skewed_machines", "w12_purity_free", "w14_cluster_composition", "w16_free_territories", "m19_good_parts", "m37_stream_coreset", "tied_swap_pairs",
    "w11_projected_against_raw", "w19_size_sweep", "w21_leakage_cells",
]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        path = f"{SF}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path}/*.parquet')" if os.path.isdir(path) else f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path}')")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_its_twin(spark, duck, name):
    frame = catalogue.queries()[name](spark, SF)
    names = sorted(frame.columns)
    got = sorted((tuple(r[c] for c in names) for r in frame.collect()), key=repr)
    sql = duck.execute(catalogue.oracle_sql()[name])
    order = [d[0] for d in sql.description]
    assert sorted(order) == names
    want = sorted((tuple(dict(zip(order, r))[c] for c in names) for r in sql.fetchall()), key=repr)
    assert got == want


def test_half_space_order_ranks_every_row(spark, duck):
    got = [tuple(r) for r in catalogue.queries()["m24_half_space_ranks"](spark, SF).select("place", "tag", "diff").collect()]
    want = duck.execute(f"SELECT place, tag, diff FROM ({catalogue.oracle_sql()['m24_half_space_ranks']})").fetchall()
    assert len(want) == duck.execute("SELECT count(*) FROM orders").fetchone()[0] > 50
    assert sorted(got) == sorted(want)
