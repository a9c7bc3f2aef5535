"""Parameters, hashes, codecs, slots and hand-made inputs."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from fanout.functions import hashing as H
from fanout.functions.params import GridParams, advise, hot_cutoff, linear_stderr, max_window_hours
from fanout.operators.metrics import throughput
from fanout.functions.slots import expand_windows, fixed_window
from fanout.operators import exact as E
from fanout.operators import grid as G
from fanout.operators import linear as N
from fanout.operators import recorder as R
from fanout.operators import recover as V
from fanout.sources.contacts import EVENT_SLOTS, contacts
from fanout.streaming import live as L

CONTACT = "core long, opp long, slot long, router long"


@pytest.mark.parametrize("bad", [dict(w=6, d=6), dict(w=14, d=6, r=4), dict(k=65_535), dict(m=0), dict(d=0)])
def test_invalid_parameters_are_refused(bad):
    with pytest.raises(ValueError):
        GridParams(**bad).validate()


def test_advice_is_valid_and_keeps_chains_from_growing():
    p = advise(200, 128, 0.05)
    assert 1 << (p.w - p.d) > 200 and linear_stderr(128, p.m) <= 0.05
    assert advise(2000, 128, 0.05, shards=16).w <= advise(2000, 128, 0.05).w


def test_longest_window_and_cutoff():
    assert round(max_window_hours(1), 1) == 18.2
    assert round(hot_cutoff(2048, 1024), 2) == 805.83


@pytest.mark.parametrize("p", [GridParams(), GridParams(m=1024, w=12, r=6, d=5), GridParams(w=10, d=8, r=5), GridParams(w=16, d=8, r=4)])
def test_addresses_come_back_from_their_columns(spark, p):
    p.validate()
    some = spark.createDataFrame([(x,) for x in (0xFFFFFFFF, 0, 1, 1 << 31, 63, 64, 123456789)], "core long")
    cols = some.select("core", *(H.grid_column(F.col("core"), i, p).alias(f"c{i}") for i in range(p.r)))
    assert all(r[0] == r[1] for r in cols.select("core", H.rebuild([F.col(f"c{i}") for i in range(p.r)], p)).collect())


def test_literal_shift_finds_the_low_bits_by_search(spark):
    p = GridParams(literal_shift=True).validate()
    some = spark.createDataFrame([(x,) for x in (0xFFFFFFFF, 5, 1 << 20)], "core long")
    cols = some.select(*(H.grid_column(F.col("core"), i, p).alias(f"c{i}") for i in range(p.r)))
    assert {0xFFFFFFFF, 5, 1 << 20} <= {r["core"] for r in H.rebuild_literal(cols, p).collect()}


def test_ip_text(spark):
    r = spark.createDataFrame([("255.0.1.2",)], "ip string").select(H.ip_to_long(F.col("ip")).alias("x")).select("x", H.long_to_ip(F.col("x")).alias("ip")).first()
    assert r["x"] == (255 << 24) + 258 and r["ip"] == "255.0.1.2"


def test_four_pairs(spark):
    df = spark.createDataFrame([(9, 1, 0, 0), (9, 1, 0, 1), (9, 2, 0, 2), (9, 1, 0, 3)], CONTACT)
    assert E.exact_fanout(df).first()["fan_out"] == 2 and E.racy_count(df).first()["fan_out"] == 4


def test_a_burst_is_reported_in_five_sliding_windows_and_one_block(spark):
    df = spark.createDataFrame([(7, o, 5, 0) for o in (1, 2, 3)], CONTACT)
    for how in ("sweep", "expand"):
        assert sorted(r["win"] for r in E.exact_heavy_sliding(df, 3, 5, 15, how).collect()) == [1, 2, 3, 4, 5]
    assert [r["win"] for r in E.exact_heavy_fixed(df, 3, 5, 15).collect()] == [1]
    r = E.detection_delay(df, 3, 5, 15).first()
    assert (r["sliding_slot"], r["fixed_slot"], r["delay"]) == (5, 9, 4)


def test_a_recorder_leaves_the_window_after_its_span(spark):
    s = R.touch(spark.createDataFrame([(7, 1, 2, 0)], CONTACT), 64)
    assert [R.touched(s, now, 3).count() for now in (1, 2, 3, 4, 5)] == [0, 1, 1, 1, 0]


def test_ages_saturate(spark):
    r = spark.range(1).select(R.empty_sketch(3).alias("a")).select(R.aged(F.col("a"), 70_000).alias("a")).first()
    assert r["a"] == [65_535] * 3


def test_merging_routers_needs_the_nearest_rule(spark):
    df = spark.createDataFrame([(7, o, 0, o % 2) for o in range(100)], CONTACT)
    p = GridParams(theta=50)
    central, parts = G.scan_grid(df, p), G.scan_grid(df, p, ("router",))
    assert G.merge_grids(parts).exceptAll(central).count() == 0 and G.merge_grids(parts).count() == central.count()
    shared = G.merge_grids(parts, "farthest", 2)
    assert V.regain_levels(shared, p).count() == 0 and V.regain_levels(central, p).first()["core"] == 7
    assert V.detect(df, p).first()["core"] == 7


def test_full_bitmap_is_flagged(spark):
    df = spark.createDataFrame([(1, o, 0, 0) for o in range(500)], CONTACT)
    r = N.linear_estimate(df, 4).first()
    assert r["saturated"] and r["est"] == round(4 * 1.3862943611198906, 6)


def test_empty_contacts(spark):
    none, p = spark.createDataFrame([], CONTACT), GridParams(theta=3)
    for df in (
        E.exact_fanout(none), E.exact_heavy_sliding(none, 3, 5, 15), N.linear_estimate(none, 64), N.linear_estimate(none, 64, impl="bitmap"), G.scan_grid(none, p),
        V.regain_levels(G.scan_grid(none, p), p), V.regain_dfs(G.scan_grid(none, p), p), V.regain_eager(G.scan_grid(none, p), p), V.regain_sliding(none, p.with_(k=5), 15),
        expand_windows(none, 15, 5), fixed_window(none, 5, 15),
    ):
        assert df.count() == 0 and df.columns


def test_slot_reports_go_on_after_a_restart_and_do_not_double(spark, tmp_path):
    """Files of a stream that land in two goes, with a new reporter and a new query for each; a batch that is run twice."""
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").withColumn("_at", F.expr("cast((unix_micros(cast(ts as timestamp)) - 1704067200000000) div 648000000000 as int)"))
    p, path, base = GridParams(m=1024, w=12, r=6, d=5, theta=4, k=300), f"{tmp_path}/landing", f"{tmp_path}/reports"
    want = V.regain_sliding(contacts(spark, "/root/testdata/sf0.001", "F1"), p, EVENT_SLOTS).select((F.col("win") + 299).alias("slot"), "core", "touched")
    seen = contacts(spark, "/root/testdata/sf0.001", "F1").agg(F.max("slot")).first()[0]  # no slot after it is closed
    want = {tuple(r) for r in want.collect() if r["slot"] <= seen}
    L.land(events, path, range(2))
    stream = lambda: L.event_stream(spark, "/root/testdata/sf0.001", path).select("core", "opp", "slot")
    first = {tuple(r)[:3] for r in L.heavy_report(stream(), p, base).collect()}
    assert first == {r for r in want if r[0] <= max(x[0] for x in first)} and first
    L.land(events, path, range(2, 4))
    last = L.heavy_report(stream(), p, base).collect()
    assert {tuple(r)[:3] for r in last} == want and len(last) == len(want)
    heavy = spark.createDataFrame([(1, x, seen + 1) for x in range(9)], "core long, opp long, slot long")
    for _ in range(2):  # a batch that is run again writes its tables anew
        L.SlotReporter(p, base)(heavy, 4)
    more = spark.read.parquet(f"{base}/out").filter(F.col("slot") > seen).collect()
    assert [(r["slot"], r["touched"]) for r in more if r["core"] == 1] == [(seen + 1, 9)] and {r["slot"] for r in more} == {seen + 1}


def test_published_rate():
    assert throughput(109_000_000, 1)["published_gb_s"] == 681.25
    assert throughput(6_250_000, 1)["gb_s"] == 40
