"""Every registered query of the engine runs, and equals its SQL twin, on the smallest tables."""

import duckdb
import pytest

from warpspan.plans import ORACLES, QUERIES
from warpspan.sources.tables import TABLES

# Large twins and slow streams have their turn on larger tables.
PICKED = [
    "series_supplier_month_walk", "gap_fill", "asof_grid", "json_value_series", "dtw_p1", "dtw_p2", "dtw_inf", "dtw_native", "pass2_p1", "pass2_inf", "ndtw_inf",
    "envelope_long", "envelope_packed", "envelope_queues", "psum_uneven_cover", "query_boxes", "box_pages", "nn_box_pass2", "knn_scan_pass2", "nn_native_scan", "within_eps_box_pass2",
    "prune_counts_box", "stage_histogram", "comparisons_scan", "fraction_sweep_supplier_month_walk", "w_sweep_supplier_month_walk", "pruning_supplier_month_walk", "pruning_supplier_month_raw", "pages_touched", "index_reach", "pruning_ratios", "approx_survivors", "nn_box_only_large_page", "nn_scan_pass2_of_50", "classify_embeddings", "classify_quality", "ndtw_band_of_one", "warp_path_cost", "sql_scalar_functions", "best_match", "nearest_in", "medoids", "second_pass_comparisons", "stream_late_rows", "stream_nearest", "gen_random_walk", "gen_shapes_control", "pruning_cube", "classify_nations", "gen_whole_walk", "stream_tumbling", "stream_envelope", "text_import_roundtrip",
]


def _cells(rows, order):
    return sorted((tuple(round(r[i], 9) if isinstance(r[i], float) else r[i] for i in order) for r in rows), key=repr)


@pytest.mark.parametrize("name", PICKED)
def test_twin(spark, sf, name):
    found = QUERIES[name](spark, sf)
    names = sorted(found.columns)
    db = duckdb.connect()
    for table in TABLES:
        db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{sf}/{table}.parquet'")
    twin = db.execute(ORACLES[name])
    columns = [c[0] for c in twin.description]
    assert sorted(columns) == names
    assert _cells([tuple(r[c] for c in names) for r in found.collect()], range(len(names))) == _cells(twin.fetchall(), [columns.index(c) for c in names])


def test_entry_and_names(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 5
    queries, twins = entry.queries(), entry.oracle_sql()
    assert set(twins) <= set(queries) and set(QUERIES) <= set(queries)


@pytest.mark.parametrize("name, source", [("gen_random_walk", "customer"), ("gen_shapes_cbf", "orders"), ("gen_shapes_control", "orders"), ("gen_whole_walk", "customer")])
def test_generators_draw_for_the_rows_of_a_table(spark, sf, name, source):
    assert [f.rsplit("/", 1)[1] for f in QUERIES[name](spark, sf).inputFiles()] == [f"{source}.parquet"]
    test_twin(spark, sf, name)
