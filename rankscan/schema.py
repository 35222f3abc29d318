"""Canonical column sets of the intermediate tables."""

SERIES_POINTS = "series_id string, t bigint, value double"
SEGMENTS = "series_id string, seg_id int, seg_start bigint, n int, t array<bigint>, values array<double>"
NULL_LAW = "n int, w int, phi bigint, ways decimal(38,0), log10_mass double, log10_lower double, log10_upper double, method string, samples bigint"
SURFACE = "series_id string, seg_id int, s int, w int, q bigint, log10_p double"
CANDIDATES = "series_id string, seg_id int, restart int, s0 int, w0 int, s int, w int, q bigint, log10_p double, evals int, converged boolean"
REGIONS = (
    "series_id string, seg_id int, region_id int, s bigint, w int, q bigint, n int, direction string, log10_p double, censored boolean, hits int, hit_share double, "
    "members array<struct<s: bigint, w: int, log10_p: double, restart: int>>, seg_start bigint"
)
DISCORDS = "series_id string, seg_id int, n int, pos int, nn_pos int, distance double"
