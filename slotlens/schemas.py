"""Schemas of the long tables that pass between operators."""

SERIES = "series_id string, ts timestamp_ntz, tick bigint, y double"
SPECTRUM = "series_id string, k int, freq double, re double, im double, power double"
GROUPS = "series_id string, slot int, vp_id int"
BLOCK_GROUPS = "series_id string, period_ix bigint, vld_id int"
CURVE = "series_id string, s0 double, n_groups int, score_literal double, score_distance double"
