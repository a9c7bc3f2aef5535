"""Equal results by different ways, accuracy bands, and plans."""

from __future__ import annotations

import io
from contextlib import redirect_stdout

import pytest
from conftest import SF

import __spark_entry__ as entry
from fanout.functions.params import GridParams, linear_stderr
from fanout.operators import exact as E
from fanout.operators import grid as G
from fanout.operators import linear as N
from fanout.operators import metrics as A
from fanout.operators import recorder as R
from fanout.operators import recover as V
from fanout.functions.slots import expand_ranges
from fanout.sources.contacts import EVENT_SLOTS, contacts
from fanout.sources.storage import stored

P = GridParams(m=2048, w=14, r=5, d=6, theta=32)


def rows(df):
    return sorted(map(tuple, df.select(*sorted(df.columns)).collect()))


@pytest.fixture(scope="module")
def f6(spark):
    return stored(contacts(spark, SF, "F6"))


@pytest.fixture(scope="module")
def grid(f6):
    return stored(G.scan_grid(f6, P))


def test_sweep_equals_expansion(spark):
    c = contacts(spark, SF, "F3")
    assert rows(E.exact_heavy_sliding(c, 60, 12, 84)) == rows(E.exact_heavy_sliding(c, 60, 12, 84, "expand"))


def test_recorders_equal_rebuilt_bitmaps(spark):
    c = contacts(spark, SF, "F3")
    ours = expand_ranges(R.all_windows(c, 512, 12, 84)).selectExpr("win", "core", "n as touched")
    assert rows(ours) == rows(N.linear_rebuild_sliding(c, 512, 12, 84).select("win", "core", "touched"))


def test_order_and_repeats_leave_the_state_alone(f6, grid):
    again = f6.union(f6).repartition(7)
    assert rows(G.scan_grid(again, P)) == rows(grid)


@pytest.mark.parametrize("batch", [1, 50, 1 << 15])
def test_batches_leave_the_state_alone(spark, batch):
    c = contacts(spark, SF, "F3").limit(400)
    c = stored(c)
    assert rows(G.scan_batches(c, P, batch)) == rows(G.scan_grid(c, P))


def test_all_ways_of_recovery_agree(grid):
    levels = rows(V.regain_levels(grid, P))
    assert levels and levels == rows(V.regain_dfs(grid, P)) == rows(V.regain_eager(grid, P))


def test_every_core_whose_own_sketch_is_hot_is_recovered(f6, grid):
    hot = {r["core"] for r in N.linear_touched(f6, P.m).collect() if r["touched"] >= P.cutoff}
    assert hot <= {r["core"] for r in V.regain_levels(grid, P).collect()}


def test_shards_find_a_subset(f6, grid):
    one = {r["core"] for r in V.regain_levels(grid, P).collect()}
    assert {r["core"] for r in V.regain_sharded(stored(G.scan_sharded(f6, P, 4)), P, 4).collect()} <= one


def test_sliding_recovery_equals_one_recovery_for_each_window(spark):
    c, n, k = stored(contacts(spark, SF, "F1")), EVENT_SLOTS, 300
    p = GridParams(m=1024, w=12, r=6, d=5, theta=4, k=k)
    slid = V.regain_sliding(c, p, n).filter("win in (0, 777, 3300)").select("win", "core", "touched")
    each = []
    for w in (0, 777, 3300):
        g = stored(G.scan_grid(c.filter(f"slot between {w} and {w + k - 1}"), p))
        each += [(r["core"], r["touched"], w) for r in V.regain_levels(g, p).collect()]
    assert rows(slid) == sorted(each)


def test_accuracy_on_skewed_data(f6, grid):
    truth = E.exact_fanout(f6).filter("fan_out >= 32")
    r = A.accuracy(V.regain_levels(grid, P), truth).first()
    assert r["n_true"] > 50 and r["tfr"] <= 0.05
    e = A.estimate_error(N.linear_estimate(f6, P.m), E.exact_fanout(f6).filter("fan_out >= 32")).first()
    assert e["rms_error"] <= 4 * linear_stderr(32, P.m) + 0.02


def test_rates_without_heavy_hosts_are_null(spark):
    none, found = spark.createDataFrame([], "core long"), spark.createDataFrame([(1,)], "core long")
    r = A.accuracy(found, none).first()
    assert (r["n_false"], r["n_missed"], r["fpr"], r["fnr"], r["tfr"]) == (1, 0, None, None, None)


def plan(df) -> str:
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def test_scan_has_two_exchanges_and_no_python(spark):
    text = plan(G.scan_grid(contacts(spark, SF, "F3"), P))
    assert text.count(") Exchange") <= 4 and "Python" not in text and "CartesianProduct" not in text  # each is named twice
    assert "ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint,l_shipdate:timestamp_ntz>" in text


def test_filters_reach_the_scan(spark):
    from fanout.sources.storage import table

    assert "PushedFilters: [IsNotNull(o_totalprice), GreaterThan(o_totalprice" in plan(table(spark, SF, "orders").filter("o_totalprice > 200000.0").select("o_orderkey"))


def test_sliding_recovery_makes_no_product(spark):
    c = contacts(spark, SF, "F1")
    text = plan(V.regain_sliding(c, GridParams(m=1024, w=12, r=6, d=5, theta=4, k=300), EVENT_SLOTS))
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text


def test_entry_and_names(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
