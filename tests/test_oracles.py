"""Registered queries against their SQL on the smallest tables whose thresholds SQL shares: hashes, slots, joins, windows, streams."""

from __future__ import annotations

import duckdb
import pytest

from fanout.plans import methods
from fanout.plans import relational, streams, workloads  # noqa: F401  their queries register

SF = "/root/testdata/sf0.01"
NAMES = [
    "params_valid", "params_advice", "window_limits", "sketch_empty", "rate_formula",
    "hash_roundtrip", "slots_events", "windows_coverage", "exact_fanout", "exact_heavy_sliding_sweep", "linear_estimate", "recorder_sliding_all", "grid_merge_routers", "grid_point_query",
    "regain_levels", "regain_no_root_check", "regain_literal_shift", "crt_regain", "slice_regain", "acc_fixed", "w_slot_example", "w_pairs_example", "w_start_offset", "join_asof", "agg_cube",
    "fn_json", "sql_surface", "udtf_touches", "stream_tumbling", "stream_heavy_report",
]


def norm(x):
    return round(x, 6) if isinstance(x, float) else x


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, name):
    db = duckdb.connect()
    for t in ("region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations").split():
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    rel = db.sql(methods.ORACLES[name])
    df = methods.QUERIES[name](spark, SF)
    assert sorted(df.columns) == sorted(rel.columns)
    ours = sorted(repr([norm(r[c]) for c in sorted(df.columns)]) for r in df.collect())
    theirs = sorted(repr([norm(dict(zip(rel.columns, r))[c]) for c in sorted(rel.columns)]) for r in rel.fetchall())
    assert ours == theirs
