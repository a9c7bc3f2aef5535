"""The ablation has every cut whose pieces overlap enough, and both rules to merge routers."""

from __future__ import annotations

import duckdb

from fanout.plans import methods
from fanout.plans import workloads as W

from conftest import SF


def test_no_variant_is_left_out(spark):
    cuts = {"w14": W.WIDE, "w12": W._CUTS["w12"], "w16": W.WIDE.with_(w=16, d=8, r=4), "w10": W._CUTS["w10"], "w8": W._CUTS["w8"]}
    held = {(p.w, p.d, p.r) for p in W._ABLATION.values()}
    assert all((p.w, p.d, p.r) in held for p in cuts.values() if p.w - p.d >= 7)
    db = duckdb.connect()
    for t in ("documents", "labels"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    rel = db.sql(methods.ORACLES["w_ablation"])
    want = sorted(repr(dict(zip(rel.columns, r))) for r in rel.fetchall())
    rows = methods.QUERIES["w_ablation"](spark, SF).collect()
    assert sorted(repr({c: r[c] for c in rel.columns}) for r in rows) == want
    assert {"w12", "nearest", "farthest"} <= {r["variant"] for r in rows}
