"""Chains on bit sets: counts without a list of chains, and cells dealt by a shuffle."""

from __future__ import annotations

from fanout.functions.params import GridParams
from fanout.operators import baselines as B
from fanout.operators import chains as Ch
from fanout.operators import grid as G
from fanout.operators import metrics as A
from fanout.operators import recover as V


def test_counts_of_a_full_grid(spark):
    p = GridParams(m=64, w=8, d=3, r=10)
    hot = spark.range(10 * 256).selectExpr("id div 256 as row_id", "id % 256 as col_id")
    got = {r["level"]: r["chains"] for r in V.chain_counts(hot, p).collect()}
    assert got == {i: 256 * 256 * 8 ** (i - 1) for i in range(2, 10)}  # 9e12 at the end: too many to list


def test_cells_by_shuffle(spark, monkeypatch):
    p = GridParams(m=64, w=8, d=3, r=10, theta=20)
    df = spark.range(400).selectExpr("(id % 10) * 1640531541 % 4294967296 as core", "id as opp", "id as slot", "id % 2 as router")
    state = G.scan_sharded(df, p, 2)
    sent = sorted(map(tuple, V.regain_sharded(state, p, 2).collect()))
    monkeypatch.setattr(Ch, "BITS_SEND", 0)
    assert sent and sent == sorted(map(tuple, V.regain_sharded(state, p, 2).collect()))


def test_rescan_tests_addresses_in_place(spark, monkeypatch):
    p = GridParams(m=64, w=8, d=3, r=10, theta=20)
    df = spark.range(2000).selectExpr("(id % 40 + id div 900) * 1640531541 % 4294967296 as core", "id as opp", "id as slot", "id % 2 as router")
    state = G.scan_grid(df, p)
    want = sorted(map(tuple, V.query_grid(state, df, p).filter(f"touched >= {p.cutoff}").collect()))
    monkeypatch.setattr(V, "query_grid", None)  # no join of all addresses with all recorders of their cells
    assert want and sorted(map(tuple, V.rescan(df, state, p).collect())) == want
    assert V.rescan(df.limit(0), state, p).count() == 0 and V.rescan(df, state.limit(0), p).count() == 0


def test_words_hold_the_touched_recorders(spark):
    p = GridParams(m=100, w=8, d=3, r=10, theta=20)
    df = spark.range(4000).selectExpr("(id % 40) * 1640531541 % 4294967296 as core", "id as opp", "id as slot", "id % 2 as router")
    state, words = G.scan_grid(df, p, ("router",)), G.scan_words(df, p, ("router",))
    rows = lambda t: sorted(map(tuple, t.select(sorted(t.columns)).collect()))
    assert words.count() < state.count() / 10 and rows(words) == rows(G.words_of(state, ("router",)))
    assert rows(G.hot_cells(words, p, ("router",))) == rows(G.hot_cells(state, p, ("router",)))
    for rule in ("nearest", "farthest"):
        merged, one = G.merge_grids(words, rule, 2), G.merge_grids(state, rule, 2)
        assert rows(merged) == rows(G.words_of(one)) and rows(V.regain_levels(merged, p)) == rows(V.regain_levels(one, p))
    scans = ((B.crt_scan(df, 64, B.SMALL_MODULI), B.crt_words(df, 64, B.SMALL_MODULI)), (B.slice_scan(df, p), B.slice_words(df, p)))
    assert all(rows(G.words_of(a)) == rows(b) for a, b in scans)


def test_ghosts_by_either_join(spark, monkeypatch):
    found, df = spark.range(50).selectExpr("id as core", "id as touched"), spark.range(40).selectExpr("id * 2 as core")
    sent = sorted(map(tuple, V.ghosts(found, df).collect()))
    assert "BroadcastHashJoin" in V.ghosts(found, df)._jdf.queryExecution().toString() and len(sent) == 25
    monkeypatch.setattr(V, "CORES_SEND", 0)
    assert sent == sorted(map(tuple, V.ghosts(found, df).collect()))


def test_routers_are_merged_without_a_further_exchange(spark):
    p = GridParams(m=100, w=8, d=3, r=10, theta=20)
    df = spark.range(4000).selectExpr("(id % 40) * 1640531541 % 4294967296 as core", "id as opp", "id as slot", "id % 4 as router")
    rows = lambda t: sorted(map(tuple, t.select(sorted(t.columns)).collect()))
    one = G.scan_merged(df, p)
    assert rows(one) == rows(G.merge_grids(G.scan_words(df, p, ("router",)))) and one.count() > 0
    plan = one._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 2, plan  # by address and by cell; before, a third to merge


def test_counts_of_chains_equal_their_list(spark):
    p = GridParams(m=64, w=8, d=3, r=10)
    hot = spark.range(10 * 256).filter("hash(id) % 8 = 0").selectExpr("id div 256 as row_id", "id % 256 as col_id")
    c = V.start_chains(hot, p)
    want = {2: c.count()}
    for i in range(3, p.r):
        c = V.extend_chains(c, hot, i, p)
        want[i] = c.count()
    counts = V.chain_counts(hot, p)
    assert {r["level"]: r["chains"] for r in counts.collect()} == want and want[2] > 0
    assert "CartesianProduct" not in (plan := counts._jdf.queryExecution().toString()) and "BroadcastNestedLoopJoin" not in plan
    assert {r["chains"] for r in V.chain_counts(hot.limit(0), p).collect()} == {0}


def test_found_are_not_shuffled_for_accuracy(spark, monkeypatch):
    found = spark.range(3000).selectExpr("id % 3 as win", "id as core").filter("win < 2")
    truth = spark.range(0, 5000, 7).selectExpr("id % 4 as win", "id as core").unionByName(spark.range(0, 300, 3).selectExpr("0L as win", "id as core").filter("core % 7 != 0"))
    for by in ((), ("win",)):
        f, t = (x if by else x.select("core").distinct() for x in (found, truth))
        rows = lambda: sorted(map(str, A.accuracy(f, t, by).collect()))  # noqa: B023, E731
        plan = A.accuracy(f, t, by)._jdf.queryExecution().executedPlan().toString()
        assert "BroadcastHashJoin" in plan and "SortMergeJoin [core" not in plan
        sent = rows()
        monkeypatch.setattr(A, "TRUTH_SEND", 0)
        assert sent and sent == rows()
        monkeypatch.undo()
    assert A.accuracy(found, truth.limit(0)).first()["fpr"] is None


def test_sketches_share_the_words_of_addresses(spark, monkeypatch):
    from fanout.plans import workloads as W

    p = GridParams(m=100, w=8, d=3, r=10, theta=20)
    df = spark.range(4000).selectExpr("(id % 40) * 1640531541 % 4294967296 as core", "id as opp", "id as slot", "id % 4 as router")
    rows = lambda t: sorted(map(tuple, t.select(sorted(t.columns)).collect()))
    own = G.by_address(df, p.m)
    for scan in (lambda x: G.scan_words(x, p), lambda x: B.crt_words(x, p.m, B.SMALL_MODULI), lambda x: B.slice_words(x, p), lambda x: G.scan_sharded(x, p, 4)):
        assert rows(scan(own)) == rows(scan(df))
    made, scan = [], G.by_address
    monkeypatch.setattr(G, "by_address", lambda *a: made.append(a[1]) or scan(*a))
    W.detectors(df, p, 1 << 12, 64)
    assert made == [p.m]  # once for three sketches
