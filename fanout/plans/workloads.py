"""Experiment workloads on the given tables, with their DuckDB text."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import key32
from ..functions.params import GridParams
from ..functions.slots import fixed_window
from ..operators import baselines as B
from ..operators import exact as E
from ..operators import grid as G
from ..operators import metrics as A
from ..operators import recover as V
from ..sources.contacts import EVENT_SLOTS, SHIP_SLOTS, contacts, theta, tokens
from ..sources.storage import stored, table
from . import sqltext as S
from .methods import C, F1_SPAN, F3_SPAN, POOL_BITS, POOL_OWN, S1, SMALL, T1, T6, W6, WIDE, query, small, wide

#: The pool for the events of one block.
BLOCK_BITS, BLOCK_OWN = 1 << 18, 256
_PROFILE = f"""SELECT f.win, contacts, opps, cores, pairs, heavy FROM (SELECT win, count(*) AS contacts, count(DISTINCT opp) AS opps FROM x GROUP BY win) f
    JOIN (SELECT win, count(*) AS cores, sum(fan_out)::BIGINT AS pairs, count(*) FILTER (fan_out >= {T1}) AS heavy FROM t GROUP BY win) g USING (win)"""


def detectors(c: DataFrame, p: GridParams, bits: int, own: int, by: tuple[str, ...] = ()) -> dict[str, DataFrame]:
    """What each detector finds in the contacts, as (by, core). The sketches have their recorders by address in common."""
    held = stored(G.by_address(c, p.m, by))
    return {
        "grid": V.regain_levels(stored(G.scan_words(held, p, by)), p, by),
        "crt": B.crt_regain(stored(B.crt_words(held, p.m, B.MODULI, by)), p.m, p.theta, B.MODULI, by),
        "slice": B.slice_regain(stored(B.slice_words(held, p, by)), p, by),
        "pool": B.pool_regain(c, bits, own, p.theta, by=by),
    }


def compared(found: dict[str, DataFrame], truth: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    scores = (A.accuracy(f, truth, by).withColumn("detector", F.lit(name)) for name, f in found.items())
    return reduce(DataFrame.unionByName, scores)


def _compare_sql(w: S.With, src: str, p: GridParams, bits: int, own: int, by: tuple[str, ...]) -> S.With:
    S.regain(w, src, p, by)
    S.crt(w, src, p.m, p.theta, B.MODULI, by)
    S.slices(w, src, p, by)
    S.pool(w, src, bits, own, p.theta, by)
    keys = "".join(f"{b}, " for b in by)
    w.add("truth", f"SELECT {keys}core FROM {src} GROUP BY ALL HAVING count(DISTINCT opp) >= {p.theta}")
    each = (("grid", "found"), ("crt", "crt_found"), ("slice", "sl_found"), ("pool", "po_found"))
    return w.add("scores", " UNION ALL ".join(f"({S.accuracy(t, 'truth', by, f"'{n}' AS detector, ")})" for n, t in each))


_MEANS = "round(avg(fpr), 6) AS mean_fpr, round(avg(fnr), 6) AS mean_fnr, round(avg(tfr), 6) AS mean_tfr"
_FIXED = _compare_sql(C("F1").add("x", S.fixed("c", 3600, 300)), "x", S1, BLOCK_BITS, BLOCK_OWN, ("win",))


@query("w_traffic_12", C("F1").add("x", S.fixed("c", 3600, 300)).add("t", S.fan("x", ("win",))).select(_PROFILE))
def _(s, d):
    return E.traffic_profile(fixed_window(contacts(s, d, "F1"), F1_SPAN, EVENT_SLOTS), theta(s, d, "F1"))


def _fixed_scores(s, d) -> DataFrame:
    x, p = stored(fixed_window(contacts(s, d, "F1"), F1_SPAN, EVENT_SLOTS)), small(s, d)
    return compared(detectors(x, p, BLOCK_BITS, BLOCK_OWN, ("win",)), stored(E.exact_fanout(x, ("win",)).filter(F.col("fan_out") >= p.theta)), ("win",))


@query("w_fixed_compare", _FIXED.select("SELECT * FROM scores"))
def _(s, d):
    return _fixed_scores(s, d)


@query("acc_table2", _FIXED.select(f"SELECT detector, count(*) AS windows, {_MEANS} FROM scores GROUP BY detector"))
def _(s, d):
    return A.accuracy_summary(_fixed_scores(s, d))


@query("w_skew_compare", _compare_sql(C("F6"), "c", W6, POOL_BITS, POOL_OWN, ()).select("SELECT * FROM scores"))
def _(s, d):
    c, p = stored(contacts(s, d, "F6")), wide(s, d)
    return compared(detectors(c, p, POOL_BITS, POOL_OWN), stored(E.exact_fanout(c).filter(F.col("fan_out") >= p.theta)))


def _slid(fixture: str, n: int, k: int, p: GridParams) -> S.With:
    w = C(fixture).add("x", S.expanded("c", n, k))
    S.regain(w, "x", p, ("win",))
    w.add("truth", f"SELECT win, core FROM x GROUP BY ALL HAVING count(DISTINCT opp) >= {p.theta}")
    # grouped anti joins, as there are thousands of windows
    w.add("m", "SELECT win, core, bool_or(k = 1) AS f, bool_or(k = 2) AS t FROM (SELECT win, core, 1 AS k FROM found UNION ALL SELECT win, core, 2 FROM truth) GROUP BY ALL")
    w.add("n", "SELECT win, count(*) FILTER (t) AS n_true, count(*) FILTER (f) AS n_found, count(*) FILTER (NOT t) AS n_false, count(*) FILTER (NOT f) AS n_missed FROM m GROUP BY win")
    rate = lambda e: f"CASE WHEN n_true > 0 THEN round({e} / n_true, 6) END"
    return w.add("scores", f"SELECT *, {rate('n_false')} AS fpr, {rate('n_missed')} AS fnr, {rate('(n_false + n_missed)')} AS tfr FROM n")


W12 = WIDE.with_(theta=110)
_SLIDE1, _SLIDE3 = _slid("F1", 3600, 300, S1), _slid("F3", 84, 12, W12)


def _sliding_scores(s, d, fixture: str) -> DataFrame:
    c = contacts(s, d, fixture)
    p, n = (small(s, d, k=F1_SPAN), EVENT_SLOTS) if fixture == "F1" else (WIDE.with_(theta=theta(s, d, "F3"), k=F3_SPAN), SHIP_SLOTS)
    return A.accuracy(V.regain_sliding(c, p, n), E.exact_heavy_sliding(c, p.theta, p.k, n), ("win",))


@query("w_sliding_series", _SLIDE1.select("SELECT * FROM scores"))
def _(s, d):
    return _sliding_scores(s, d, "F1")


@query("w_sliding_ship", _SLIDE3.select("SELECT * FROM scores"))
def _(s, d):
    return _sliding_scores(s, d, "F3")


@query("acc_series", _SLIDE1.select(f"SELECT count(*) AS windows, {_MEANS}, round(avg((fpr < 0.02)::INT) , 6) AS low_fpr_share FROM scores"))
def _(s, d):
    return A.accuracy_series(_sliding_scores(s, d, "F1"))


@query("acc_corr", _SLIDE3.select("SELECT CASE WHEN stddev(fpr) > 0 AND stddev(fnr) > 0 THEN round(corr(fpr, fnr), 4) END AS corr FROM scores"))
def _(s, d):
    return A.fpr_fnr_corr(_sliding_scores(s, d, "F3"))


@query("w_fixed_is_sliding", S.regain(C("F1").add("x", S.fixed("c", 3600, 300)), "x", S1, ("win",)).select("SELECT win, core, touched, touched AS sliding_touched FROM found"))
def _(s, d):
    c = stored(contacts(s, d, "F1"))
    p = small(s, d)
    blocks = V.regain_levels(stored(G.scan_words(fixed_window(c, F1_SPAN, EVENT_SLOTS), p, ("win",))), p, ("win",)).select("win", "core", "touched")
    at = V.regain_sliding(c, p.with_(k=F1_SPAN), EVENT_SLOTS).filter(F.col("win") % F1_SPAN == 0)
    return blocks.join(at.select(F.expr(f"win div {F1_SPAN}").alias("win"), "core", F.col("touched").alias("sliding_touched")), ["win", "core"], "full")


_ROUTED = S.regain(S.regain(S.regain(C("F1").contacts("F6", "c6").contacts("F3", "c3"), "c", S1.with_(theta=f"6 * {T1}"), (), "_1"), "c6", W6, (), "_6"), "c3", WIDE.with_(theta=540), (), "_3")


@query("w_routers", _ROUTED.select(" UNION ALL ".join(f"SELECT '{f}' AS fixture, core, touched, est, saturated FROM found_{f[1]}" for f in ("F1", "F6", "F3"))))
def _(s, d):
    sets = (("F1", SMALL.with_(theta=6 * theta(s, d, "F1"))), ("F6", wide(s, d)), ("F3", WIDE.with_(theta=theta(s, d, "F3_all"))))
    return reduce(DataFrame.unionByName, (V.detect(contacts(s, d, f), p).withColumn("fixture", F.lit(f)) for f, p in sets))


_MEMORY = S.pool(S.slices(S.crt(C("F6").add("g", S.grid("c", W6)), "c", 2048, T6, B.MODULI), "c", W6), "c", POOL_BITS, POOL_OWN, T6)


@query("w_memory", _MEMORY.select(f"""SELECT 'grid' AS detector, {2 * 5 * (1 << 14) * 2048} AS dense_bytes, (SELECT count(*) FROM g) AS sparse_rows
    UNION ALL SELECT 'crt', {sum(B.MODULI) * 2048 // 8}, (SELECT count(*) FROM crt_g) UNION ALL SELECT 'slice', {4 * (1 << 14) * 2048 // 8}, (SELECT count(*) FROM sl_g)
    UNION ALL SELECT 'pool', {POOL_BITS // 8}, (SELECT count(*) FROM po_p)"""))
def _(s, d):
    c, p = stored(contacts(s, d, "F6")), wide(s, d)
    held = (
        ("grid", 2 * p.r * (1 << p.w) * p.m, G.scan_grid(c, p)), ("crt", sum(B.MODULI) * p.m // 8, B.crt_scan(c, p.m)),
        ("slice", (p.r - 1) * (1 << p.w) * p.m // 8, B.slice_scan(c, p)), ("pool", POOL_BITS // 8, B.pool_scan(c, POOL_BITS, POOL_OWN)),
    )
    return reduce(DataFrame.unionByName, (x.agg(F.lit(n).alias("detector"), F.lit(b).cast("long").alias("dense_bytes"), F.count("*").alias("sparse_rows")) for n, b, x in held))


_SHARDS = (1, 4, 16)


def _sharded_sql() -> str:
    w, parts = C("F6"), []
    for g in _SHARDS:
        w.add(f"x{g}", f"SELECT *, core % {g} AS shard FROM c")
        S.regain(w, f"x{g}", W6, ("shard",), f"_{g}")
        parts.append(f"SELECT {g} AS shards, core, touched FROM found_{g} WHERE core % {g} = shard")
    return w.select(" UNION ALL ".join(parts))


@query("w_sharded", _sharded_sql())
def _(s, d):
    c, p = contacts(s, d, "F6"), wide(s, d)
    own = stored(G.by_address(c, p.m))
    each = (V.regain_sharded(stored(G.scan_sharded(own, p, g)), p, g).select(F.lit(g).alias("shards"), "core", "touched") for g in _SHARDS)
    return reduce(DataFrame.unionByName, each)


_FEW = S1.with_(theta=f"6 * {T1}")


@query("w_recovery_agree", S.regain(C("F1"), "c", _FEW).select(" UNION ALL ".join(f"SELECT '{k}' AS how, core, touched FROM found" for k in ("levels", "depth", "eager", "brute"))))
def _(s, d):
    p = SMALL.with_(theta=6 * theta(s, d, "F1"))
    g = stored(G.scan_grid(contacts(s, d, "F1"), p))
    ways = {"levels": V.regain_levels(g, p), "depth": V.regain_dfs(g, p), "eager": V.regain_eager(g, p), "brute": V.regain_bruteforce(g, p)}
    return reduce(DataFrame.unionByName, (f.select(F.lit(k).alias("how"), "core", "touched") for k, f in ways.items()))


_OFFSETS = (0, 60, 120, 180, 240)


@query("w_start_offset", C("F1").select(" UNION ALL ".join(
    f"""SELECT {o} AS start_slot, count(*) AS heavy_blocks, count(DISTINCT core) AS cores FROM (SELECT (slot - {o}) // 300 AS win, core FROM c
    WHERE slot >= {o} AND slot < {o + (3600 - o) // 300 * 300} GROUP BY ALL HAVING count(DISTINCT opp) >= {T1})""" for o in _OFFSETS)))
def _(s, d):
    c = stored(contacts(s, d, "F1"))
    out = []
    for o in _OFFSETS:
        heavy = E.exact_heavy_fixed(c.withColumn("slot", F.col("slot") - o), theta(s, d, "F1"), F1_SPAN, EVENT_SLOTS - o)
        out.append(heavy.agg(F.lit(o).alias("start_slot"), F.count("*").alias("heavy_blocks"), F.countDistinct("core").alias("cores")))
    return reduce(DataFrame.unionByName, out)


@query("w_slot_example", "SELECT 'sliding' AS kind, unnest([1, 2, 3, 4, 5])::BIGINT AS win, 7::BIGINT AS core, 3::BIGINT AS fan_out UNION ALL SELECT 'fixed', 1, 7, 3")
def _(s, d):
    burst = s.createDataFrame([(7, o, 5, 0) for o in (1, 2, 3)], "core long, opp long, slot long, router long")
    sliding = E.exact_heavy_sliding(burst, 3, 5, 15).select(F.lit("sliding").alias("kind"), "win", "core", "fan_out")
    return sliding.unionByName(E.exact_heavy_fixed(burst, 3, 5, 15).select(F.lit("fixed").alias("kind"), "win", "core", "fan_out"))


@query("w_pairs_example", C("F3").add("t", S.fan("c")).add("u", S.fan("c", ("router",))).select(
    "SELECT core, t.fan_out AS exact, sum(u.fan_out)::BIGINT AS unseen FROM t JOIN u USING (core) GROUP BY core, t.fan_out"))
def _(s, d):
    # what a supplier's count becomes where routers do not see each other's pairs
    c = stored(contacts(s, d, "F3"))
    return E.exact_fanout(c).withColumnRenamed("fan_out", "exact").join(E.racy_count(c).withColumnRenamed("fan_out", "unseen"), "core")


_SIDES = (("F1", "keys"), ("F2", "users"))


@query("w_swapped", C("F1").contacts("F2", "c2").add("t", S.fan("c")).add("u", S.fan("c2")).select(
    "SELECT 'keys' AS side, fan_out, count(*) AS cores FROM t GROUP BY fan_out UNION ALL SELECT 'users', fan_out, count(*) FROM u GROUP BY fan_out"))
def _(s, d):
    each = (E.exact_fanout(contacts(s, d, f)).groupBy("fan_out").agg(F.count("*").alias("cores")).withColumn("side", F.lit(k)) for f, k in _SIDES)
    return reduce(DataFrame.unionByName, each)


def _sides_sql() -> str:
    w = C("F1").contacts("F2", "c2")
    for src, k, t in (("c", "keys", f"6 * {T1}"), ("c2", "users", T1)):
        w.add(f"truth_{k}", f"SELECT core FROM {src} GROUP BY core HAVING count(DISTINCT opp) >= {t}")
        S.regain(w, src, S1.with_(theta=t), (), f"_{k}")
    return w.select(" UNION ALL ".join(f"({S.accuracy(f'found_{k}', f'truth_{k}', (), f"'{k}' AS side, ")})" for _, k in _SIDES))


@query("w_sides_compare", _sides_sql())
def _(s, d):
    # the same events seen from either side: other cores, other loads, the same detector
    out, t = [], theta(s, d, "F1")
    for f, k in _SIDES:
        c, p = stored(contacts(s, d, f)), SMALL.with_(theta=6 * t if k == "keys" else t)
        truth = E.exact_fanout(c).filter(F.col("fan_out") >= p.theta)
        out.append(A.accuracy(V.regain_levels(stored(G.scan_words(c, p)), p), truth).withColumn("side", F.lit(k)))
    return reduce(DataFrame.unionByName, out)


#: Of the cuts those whose pieces overlap by 7 bits or more: with fewer, chains of the tokens multiply without an end.
_ABLATION = {
    "m512": WIDE.with_(m=512), "m1024": WIDE.with_(m=1024), "m2048": WIDE, "w16": WIDE.with_(w=16, d=8, r=4), "w12": WIDE.with_(w=12, d=5, r=6),
    "literal_shift": WIDE.with_(literal_shift=True), "no_root": WIDE.with_(root_check=False), "no_pad": WIDE.with_(pad_check=False),
}
#: The two rules to merge the grids of routers; the second for the number of routers.
_MERGED = {"nearest": "max(last_slot) AS last_slot FROM routed GROUP BY ALL", "farthest": "min(last_slot) AS last_slot FROM routed GROUP BY ALL HAVING count(*) = {}"}


def _ablation_sql() -> str:
    w = C("F6").add("truth", f"SELECT core FROM c GROUP BY core HAVING count(DISTINCT opp) >= {T6}")
    for k, p in _ABLATION.items():
        S.regain(w, "c", S.SqlGrid.of(p, T6), (), f"_{k}")
    w.add("routed", S.grid("c", W6, ("router",)))
    for k, rule in _MERGED.items():
        w.add(f"m_{k}", f"SELECT row_id, col_id, rec, {rule.format('(SELECT count(DISTINCT router) FROM c)')}")
        S.regain(w, "c", W6, (), f"_{k}", f"m_{k}")
    return w.select(" UNION ALL ".join(f"({S.accuracy(f'found_{k}', 'truth', (), f"'{k}' AS variant, ")})" for k in (*_ABLATION, *_MERGED)))


@query("w_ablation", _ablation_sql())
def _(s, d):
    c = stored(contacts(s, d, "F6"))
    truth = stored(E.exact_fanout(c).filter(F.col("fan_out") >= theta(s, d, "F6")))
    own = {m: stored(G.by_address(c, m)) for m in {p.m for p in _ABLATION.values()}}
    grids, each = {}, []
    for k, q in _ABLATION.items():
        q = q.with_(theta=theta(s, d, "F6"))
        cut = (q.m, q.w, q.r, q.d, q.literal_shift)  # the checks are of the recovery: variants of these alone have one grid
        if cut not in grids:
            grids[cut] = stored(G.scan_words(own[q.m], q))
        each.append(A.accuracy(V.regain_levels(grids[cut], q), truth).withColumn("variant", F.lit(k)))
    p, routers = wide(s, d), c.select("router").distinct().count()
    routed = stored(G.scan_words(c, p, ("router",)))
    for rule in _MERGED:
        merged = stored(G.merge_grids(routed, rule, routers))
        each.append(A.accuracy(V.regain_levels(merged, p), truth).withColumn("variant", F.lit(rule)))
    return reduce(DataFrame.unionByName, each)


#: Other cuts of the address, on the suppliers over the whole period, and the two rules to merge routers.
_CUTS = {"w14": WIDE, "w12": WIDE.with_(w=12, d=5, r=6), "w10": WIDE.with_(w=10, d=8, r=5), "w8": WIDE.with_(w=8, d=6, r=6)}
_ALL3 = {k: p.with_(theta=540) for k, p in _CUTS.items()}


def _ablation_ship_sql() -> str:
    w = C("F3").add("truth", "SELECT core FROM c GROUP BY core HAVING count(DISTINCT opp) >= 540")
    for k, p in _ALL3.items():
        S.regain(w, "c", p, (), f"_{k}")
    w.add("routed", S.grid("c", _ALL3["w14"], ("router",)))
    for k, rule in _MERGED.items():
        w.add(f"m_{k}", f"SELECT row_id, col_id, rec, {rule.format(4)}")
        S.regain(w, "c", _ALL3["w14"], (), f"_{k}", f"m_{k}")
    return w.select(" UNION ALL ".join(f"({S.accuracy(f'found_{k}', 'truth', (), f"'{k}' AS variant, ")})" for k in (*_ALL3, "nearest", "farthest")))


@query("w_ablation_ship", _ablation_ship_sql())
def _(s, d):
    c, t = stored(contacts(s, d, "F3")), theta(s, d, "F3_all")
    truth = stored(E.exact_fanout(c).filter(F.col("fan_out") >= t))
    grids = {k: (G.scan_words(c, p), p) for k, p in _ALL3.items()}
    p = _ALL3["w14"]
    routed = stored(G.scan_words(c, p, ("router",)))
    grids |= {"nearest": (G.merge_grids(routed), p), "farthest": (G.merge_grids(routed, "farthest", 4), p)}
    each = (A.accuracy(V.regain_levels(stored(g), q), truth).withColumn("variant", F.lit(k)) for k, (g, q) in grids.items())
    return reduce(DataFrame.unionByName, each)


@query("w_two_stage", S.regain(C("F6"), "c", W6).select(
    f"""SELECT token, count(*) AS docs, count(DISTINCT lang) AS langs, round(avg(n_chars), 4) AS mean_chars, count(*) FILTER (toxic = 1) AS toxic
    FROM (SELECT doc_id, lang, n_chars, unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]+'))) AS token FROM documents) LEFT JOIN labels USING (doc_id)
    WHERE {S.key32('token')} IN (SELECT core FROM found) GROUP BY token"""))
def _(s, d):
    p = wide(s, d)
    heavy = V.regain_levels(stored(G.scan_words(contacts(s, d, "F6"), p)), p).select("core")
    each = table(s, d, "documents").select("doc_id", "lang", "n_chars", F.explode(tokens()).alias("token")).withColumn("core", key32(F.col("token")))
    seen = each.join(heavy, "core", "left_semi").join(table(s, d, "labels").select("doc_id", "toxic"), "doc_id", "left")
    return seen.groupBy("token").agg(F.count("*").alias("docs"), F.countDistinct("lang").alias("langs"), F.round(F.avg("n_chars"), 4).alias("mean_chars"), F.count_if(F.col("toxic") == 1).alias("toxic"))
