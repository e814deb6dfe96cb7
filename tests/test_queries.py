"""Registered queries against their SQL on the smallest tables."""

import math

import pytest

from setdiff.queries import registry

QUICK = [
    "signatures_orders", "portable_rowhash_lineitem", "bins_w3", "parity_bins_w3", "bitmap_diff_w3", "decoded_bins_w3", "xor_sums_w3", "checksums_w3", "codeword_w3_m7",
    "multiset_hash_w3", "merkle_leaves_w3", "merkle_root_w3", "planner_bits", "x4_signature_lengths", "x4_pivot", "x12_filter_use", "per_group_capacity", "cell_table_w3", "filter_cells_w4", "whole_syndrome_w5", "grouped_syndrome_w3", "exceptions_by_type_w3", "tow_sketch_w3", "tow_estimate_w3", "cell_table_cells_w3", "filter_bits_w4", "p_ideal", "transition_matrix_n127_t5",
    "binomial_tail", "bits_per_group_grid", "overhead_formula_grid", "tuning_optimum", "expected_share_by_round", "comm_ledger_full_exchange_w3", "metrics_rollup", "cumulative_share",
    "topk_params", "asof_latest_events", "interval_match_events", "sql_functions", "relay_windows_batch", "bin_parity_w12", "bin_parity_w13", "bin_parity_w256_w13", "bin_parity_w8", "full_exchange_w9", "bin_parity_auto_w15",
]


def _rows(cols, rows):
    order = sorted(range(len(cols)), key=lambda i: cols[i])
    clean = lambda x: round(x, 9) if isinstance(x, float) and not math.isnan(x) else x
    return sorted(repr(tuple(clean(r[i]) for i in order)) for r in rows)


@pytest.mark.parametrize("name", QUICK)
def test_query_matches_sql(spark, sf, duck, name):
    run, sql = registry()[name]
    df = run(spark, sf)
    cur = duck.execute(sql)
    names = [c[0] for c in cur.description]
    assert sorted(df.columns) == sorted(names)
    assert _rows(df.columns, [tuple(r) for r in df.collect()]) == _rows(names, cur.fetchall())


def test_entry_points(spark):
    import __spark_entry__ as e

    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q) and len(q) >= 70
    assert e.entry(spark).count() == 27


def test_experiments_order_schemes(spark, sf):
    from setdiff import experiments as X

    ratio = {(r["w"], r["scheme"]): r["ratio"] for r in X.signature_lengths(spark).collect()}
    for w in (32, 64, 256):
        assert ratio[w, "whole_syndrome"] < ratio[w, "bin_parity"] < ratio[w, "grouped_syndrome"] < ratio[w, "cell_table"]
    assert ratio[256, "bin_parity"] < ratio[64, "bin_parity"] < ratio[32, "bin_parity"]
    kinds = {r["kind"]: r["share"] for r in X.bin_kinds(spark, 40_000).collect()}
    assert abs(kinds["ideal"] - 0.9613) < 0.005 and abs(kinds["even"] - 0.0385) < 0.005
    used = {r["d"]: r["filter_used"] for r in X.filter_use(spark).collect()}
    assert not used[10_000] and used[16_000]
    ms = {(r["scheme"], r["d"]): r["decode_ms"] for r in X.decode_growth(spark, (50, 400)).collect()}
    assert ms["whole_syndrome", 400] > 4 * ms["bin_parity", 400] and ms["whole_syndrome", 400] > 10 * ms["whole_syndrome", 50]
    rows = {r["scheme"]: r for r in X.compare(spark, sf, ("bin_parity", "cell_table"), (20,), count=10, size=300).collect()}
    assert rows["bin_parity"]["ratio"] < 3 and rows["bin_parity"]["success"] >= 0.9 and rows["cell_table"]["ratio"] > 5


def test_filter_wins_at_large_differences(spark, sf):
    """On either side of the break-even: cells alone cost more than bin parity, with the filter for many differences less. Points over half the set are left out."""
    from setdiff import experiments as X

    got = X.compare(spark, sf, ("bin_parity", "filter_cells"), (10, 500, 900), count=4, most={"filter_cells": 500}).collect()
    ratio = {(r["scheme"], r["d"]): r["ratio"] for r in got}
    assert set(ratio) == {(s, d) for s in ("bin_parity", "filter_cells") for d in (10, 500)}
    assert ratio["filter_cells", 10] > ratio["bin_parity", 10] and ratio["filter_cells", 500] < ratio["bin_parity", 500]
