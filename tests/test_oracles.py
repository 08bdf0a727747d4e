"""Queries against SQL on the smallest tables; all of them with LOSSBAND_ALL=1."""

import os

import oracle
import pytest

from lossband import queries

SF = "/root/testdata/sf0.001"
FEW = """grid_orders_weekly window_keys_events window_overlap window_arrays window_horizons dedupe_windows impute_mean impute_zero grid_bounds_of_data zero_shot_suite amortisation rfl_scaled_context_std stream_late_rows stream_cutoff_refresh select_global_cdf_80 holdout_split decontaminate_interval pack_roundtrip corpus_stats rfl_mse_snaive_orders_weekly rfl_mse_last rfl_mse_drift
rfl_mse_bands rfl_mse_ffill_phase rfl_quantile wql_window rfl_gaussian_nll linear_gram_p4 rank_global rank_cutoffs select_strat_count_80 select_strat_cdf_60 select_global_cdf_40 select_random_lcg select_sweep select_ties
share_report_global diversity_strat_vs_global spearman_per_source eval_geomean eval_prob_score gradient_identity rfl_decile_profile doc_select_quality conv_windows join_asof_events join_range_bucketed agg_cube
fn_json_props udtf_windows sql_select_central stream_tumbling stream_session stream_online_scores""".split()


@pytest.fixture(scope="module")
def con():
    return oracle.views(SF)


@pytest.mark.parametrize("name", sorted(queries.oracles()) if os.environ.get("LOSSBAND_ALL") else FEW)
def test_query(spark, con, name):
    assert oracle.differences(queries.queries()[name](spark, SF), con, queries.oracles()[name]) == ""


def test_names():
    assert set(queries.oracles()) <= set(queries.queries())
