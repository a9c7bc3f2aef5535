"""Queries for hashes, slots, exact counts, sketches, the grid, recovery, baselines and measures, each with its DuckDB text."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import hashing as H
from ..functions.params import MAX_AGE, GridParams, advise, max_window_hours
from ..functions.slots import coverage, expand_ranges, expand_windows, fixed_window, micros, slot_of, windows
from ..operators import baselines as B
from ..operators import exact as E
from ..operators import grid as G
from ..operators import linear as N
from ..operators import metrics as A
from ..operators import recorder as R
from ..operators import recover as V
from ..sources.contacts import EVENT_ORIGIN, EVENT_SLOT, EVENT_SLOTS, SHIP_SLOTS, both_directions, contacts, packets, swap_roles, theta
from ..sources.storage import stored, table
from . import sqltext as S

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
#: The large grid, and a smaller one for the events.
WIDE, SMALL = GridParams(m=2048, w=14, r=5, d=6), GridParams(m=1024, w=12, r=6, d=5)
F1_SPAN, F3_SPAN = 300, 12


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def wide(spark: SparkSession, sf_dir: str, **more) -> GridParams:
    """The large grid at the threshold of the folder's documents."""
    return WIDE.with_(theta=theta(spark, sf_dir, "F6"), **more)


def small(spark: SparkSession, sf_dir: str, **more) -> GridParams:
    return SMALL.with_(theta=theta(spark, sf_dir, "F1"), **more)


#: The same for SQL.
W6, S1 = S.SqlGrid.of(WIDE, S.theta("F6")), S.SqlGrid.of(SMALL, S.theta("F1"))
T1, T6 = S.theta("F1"), S.theta("F6")
C = lambda f: S.With().contacts(f)


# parameters

#: Parameters drawn from the rows of lineitem, so that every rule is met and broken.
_DRAWN = {"m": "l_partkey % 3 * 1024", "w": "l_suppkey % 20 + 8", "r": "l_linenumber + 1", "d": "l_orderkey % 10", "theta": "l_partkey % 5 * 256", "k": "l_orderkey % 4 * 21845"}


@query("params_valid", "SELECT DISTINCT *, d > 0 AND d < w AND (r - 2) * d + w >= 32 AND r >= 3 AND m >= 1 AND theta >= 1 AND k > 0 AND k < 65535 AS valid FROM (SELECT "
    + ", ".join(f"({e})::INT AS {k}" for k, e in _DRAWN.items()) + " FROM lineitem)")
def _(s, d):
    def holds(x: dict) -> bool:
        try:
            return bool(GridParams(**x).validate())
        except ValueError:
            return False

    def tried(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield b.assign(valid=[holds(x) for x in b.to_dict("records")])

    drawn = table(s, d, "lineitem").select(*(F.expr(e).cast("int").alias(k) for k, e in _DRAWN.items())).distinct()
    return drawn.mapInPandas(tried, "m int, w int, r int, d int, theta int, k int, valid boolean")


@query("params_advice", C("F3").add("needs", "SELECT DISTINCT hot, theta, max_error, shards FROM (SELECT count(DISTINCT core) AS hot, count(*) // count(DISTINCT core) AS theta FROM c GROUP BY slot, router), "
    "(SELECT unnest([0.05::DOUBLE, 0.02::DOUBLE]) AS max_error), (SELECT unnest([1, 16]) AS shards)").select("").rstrip() + f""",
    sizes AS (SELECT *, sqrt(m * (exp(theta::DOUBLE / m) - theta::DOUBLE / m - 1)) / theta AS err FROM needs, (SELECT 1 << unnest(range(6, 21)) AS m)),
    recs AS (SELECT hot, theta, max_error, shards, min(m) AS m FROM sizes WHERE err <= max_error OR m = 1 << 20 GROUP BY ALL),
    spare AS (SELECT *, greatest(2, ceil(log2(greatest(2, hot::DOUBLE / shards)))::INT + 1) AS spare FROM recs),
    widths AS (SELECT *, w - spare AS d, greatest(3, ceil((32 - w) / (w - spare)::DOUBLE)::INT + 2) AS r FROM spare, (SELECT unnest(range(1, 25))::INT AS w) WHERE w > spare)
    SELECT hot, theta, max_error, shards, m, w, r, d FROM widths QUALIFY row_number() OVER (PARTITION BY hot, theta, max_error, shards ORDER BY r * (1 << w), w) = 1""")
def _(s, d):
    """The grid that `advise` gives for the suppliers and the mean load of each slot and router, at two errors and two numbers of shards."""
    load = contacts(s, d, "F3").groupBy("slot", "router").agg(F.countDistinct("core").alias("hot"), F.count("*").alias("n")).select("hot", F.expr("n div hot").alias("theta"))
    each = load.select("hot", "theta", F.explode(F.array(F.lit(0.05), F.lit(0.02))).alias("max_error")).withColumn("shards", F.explode(F.array(F.lit(1), F.lit(16)))).distinct()

    def advised(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            grids = [advise(*x) for x in b[["hot", "theta", "max_error", "shards"]].itertuples(index=False, name=None)]
            yield b.assign(**{k: [getattr(g, k) for g in grids] for k in ("m", "w", "r", "d")})

    return each.mapInPandas(advised, "hot long, theta long, max_error double, shards int, m int, w int, r int, d int")


@query("window_limits", "SELECT slot_seconds, round(65534 * slot_seconds / 3600.0, 6) AS hours FROM (VALUES (1), (60), (300)) v(slot_seconds)")
def _(s, d):
    return s.createDataFrame([(x, round(max_window_hours(x), 6)) for x in (1, 60, 300)], "slot_seconds int, hours double")


@query("sketch_empty", C("F1").select("SELECT core, m, m AS recorders, 65535 AS least_age, 65535 AS most_age, 65535 AS least_age_later FROM (SELECT DISTINCT core FROM c), (SELECT unnest([8, 2048]) AS m)"))
def _(s, d):
    """A fresh sketch for each key: no recorder is young in any window, and ages stay at their top."""
    cores = contacts(s, d, "F1").select("core").distinct()
    new = cores.select("core", F.lit(8).alias("m"), R.empty_sketch(8).alias("ages")).unionByName(cores.select("core", F.lit(2048).alias("m"), R.empty_sketch(2048).alias("ages")))
    return new.select("core", "m", F.size("ages").alias("recorders"), F.array_min("ages").alias("least_age"), F.array_max("ages").alias("most_age"), F.array_min(R.aged(F.col("ages"), MAX_AGE)).alias("least_age_later"))


@query("rate_formula", "SELECT event_type, contacts, seconds, round(contacts / seconds, 6) AS contacts_s, round(contacts / seconds / 1e6 * 6400 / 1024, 6) AS published_gb_s, "
    "round(contacts / seconds * 6400 / 1e9, 6) AS gb_s FROM (SELECT event_type, count(*) AS contacts, (epoch_us(max(ts)) - epoch_us(min(ts))) / 1e6 AS seconds FROM events GROUP BY event_type)")
def _(s, d):
    """The rate of each router's events over their span."""
    span = F.max(micros(F.col("ts"))) - F.min(micros(F.col("ts")))
    n = table(s, d, "events").groupBy("event_type").agg(F.count("*").alias("contacts"), (span / F.lit(1e6)).alias("seconds"))
    return n.select("*", *(F.round(v, 6).alias(k) for k, v in A.throughput(F.col("contacts"), F.col("seconds")).items()))


# hashes

_CORES = "SELECT DISTINCT core FROM c"


@query("hash_recorder", C("F6").select(f"SELECT DISTINCT opp, {S.rec('opp', 2048)} AS rec, {S.rec('opp', 1024, 3)} AS rec_salted FROM c"))
def _(s, d):
    return contacts(s, d, "F6").select("opp").distinct().select("opp", H.rec_hash(F.col("opp"), 2048).alias("rec"), H.rec_hash(F.col("opp"), 1024, 3).alias("rec_salted"))


@query("hash_root", C("F6").select(f"SELECT core, {S.root('core', 14)} AS root FROM ({_CORES})"))
def _(s, d):
    return contacts(s, d, "F6").select("core").distinct().select("core", H.root_hash(F.col("core"), 14).alias("root"))


@query("hash_grid_columns", C("F6").add("r", f"SELECT core, {S.root('core', 14)} AS rt FROM ({_CORES})").select(
    "SELECT core, i AS row_id, CASE WHEN i = 0 THEN rt ELSE xor(core >> (greatest(i - 1, 0) * 6), rt) & 16383 END AS col_id FROM r, (SELECT unnest(range(5)) AS i)"))
def _(s, d):
    return contacts(s, d, "F6").select("core").distinct().select("core", F.posexplode(H.grid_columns(F.col("core"), WIDE)).alias("row_id", "col_id")).withColumn("row_id", F.col("row_id").cast("long"))


@query("hash_piece", C("F6").select(f"SELECT core, (core >> 6) & 16383 AS piece FROM ({_CORES})"))
def _(s, d):
    return contacts(s, d, "F6").select("core").distinct().select("core", H.piece(H.grid_column(F.col("core"), 2, WIDE), H.grid_column(F.col("core"), 0, WIDE)).alias("piece"))


@query("hash_roundtrip", C("F6").select(f"SELECT core, core AS rebuilt FROM ({_CORES})"))
def _(s, d):
    cols = contacts(s, d, "F6").select("core").distinct().select("core", *(H.grid_column(F.col("core"), i, WIDE).alias(f"c{i}") for i in range(WIDE.r)))
    return cols.select("core", H.rebuild([F.col(f"c{i}") for i in range(WIDE.r)], WIDE).alias("rebuilt"))


@query("key_codec_roundtrip", f"SELECT c_custkey AS key, {S.codec('c_custkey')} AS code, c_custkey AS decoded FROM customer")
def _(s, d):
    code = H.encode_key(F.col("c_custkey"))
    return table(s, d, "customer").select(F.col("c_custkey").alias("key"), code.alias("code"), H.decode_key(code).alias("decoded"))


@query("hash_quality", C("F6").add("g", f"SELECT core, {S.root('core', 14)} AS rt FROM ({_CORES})").add(
    "l", "SELECT i AS row_id, CASE WHEN i = 0 THEN rt ELSE xor(core >> (greatest(i - 1, 0) * 6), rt) & 16383 END AS col_id, count(*) AS n FROM g, (SELECT unnest(range(5)) AS i) GROUP BY ALL").select(
    "SELECT row_id, count(*) AS cells, max(n) AS max_load, round(avg(n), 6) AS mean_load, round(sum(n * n) / (sum(n) / 16384.0) - sum(n), 6) AS chi_square FROM l GROUP BY row_id"))
def _(s, d):
    return H.hash_quality(contacts(s, d, "F6"), WIDE)


# slots and windows


@query("slots_events", f"SELECT event_id, {S.event_slot()} AS slot FROM events")
def _(s, d):
    return table(s, d, "events").select("event_id", slot_of(F.col("ts"), EVENT_ORIGIN, EVENT_SLOT).alias("slot"))


@query("windows_list", "SELECT unnest(range(3301)) AS win")
def _(s, d):
    return windows(s, EVENT_SLOTS, F1_SPAN)


@query("windows_expand_counts", C("F3").add("x", S.expanded("c", 84, 12)).select("SELECT win, count(*) AS contacts FROM x GROUP BY win"))
def _(s, d):
    return expand_windows(contacts(s, d, "F3"), SHIP_SLOTS, F3_SPAN).groupBy("win").agg(F.count("*").alias("contacts"))


@query("windows_coverage", C("F1").add("x", S.expanded("c", 3600, 300)).select("SELECT core, opp, count(DISTINCT win) AS windows FROM x GROUP BY ALL"))
def _(s, d):
    c = coverage(contacts(s, d, "F1"), ["core", "opp"], EVENT_SLOTS, F1_SPAN)
    return c.groupBy("core", "opp").agg(F.sum(F.col("hi") - F.col("lo") + 1).alias("windows"))


@query("fixed_window_counts", C("F1").add("x", S.fixed("c", 3600, 300)).select("SELECT win, count(*) AS contacts FROM x GROUP BY win"))
def _(s, d):
    return fixed_window(contacts(s, d, "F1"), F1_SPAN, EVENT_SLOTS).groupBy("win").agg(F.count("*").alias("contacts"))


_PROFILE = """SELECT f.win, contacts, opps, cores, pairs, heavy FROM (SELECT win, count(*) AS contacts, count(DISTINCT opp) AS opps FROM x GROUP BY win) f
    JOIN (SELECT win, count(*) AS cores, sum(fan_out)::BIGINT AS pairs, count(*) FILTER (fan_out >= {0}) AS heavy FROM t GROUP BY win) g USING (win)"""


@query("traffic_profile", C("F3").add("x", S.fixed("c", 84, 12)).add("t", S.fan("x", ("win",))).select(_PROFILE.format(110)))
def _(s, d):
    return E.traffic_profile(fixed_window(contacts(s, d, "F3"), F3_SPAN, SHIP_SLOTS), theta(s, d, "F3"))


@query("normalise_directions", C("F3").select("SELECT core, opp, slot, router FROM c"))
def _(s, d):
    return both_directions(packets(s, d), F.col("away"))


@query("swap_roles_exact", C("F2").select(f"SELECT core, opp, slot, router, {S.codec('opp')} AS back FROM c"))
def _(s, d):
    # the users' side of the same events: roles swapped and keys coded for their new place
    sw = swap_roles(contacts(s, d, "F1"))
    return sw.select(H.encode_key(F.col("core")).alias("core"), H.decode_key(F.col("opp")).alias("opp"), "slot", "router", F.col("opp").alias("back"))


# exact counts


@query("exact_fanout", C("F6").select(S.fan("c")))
def _(s, d):
    return E.exact_fanout(contacts(s, d, "F6"))


@query("exact_sets", C("F3").select("SELECT core, string_agg(DISTINCT opp, ',' ORDER BY opp) AS opps FROM c GROUP BY core"))
def _(s, d):
    return E.exact_sets(contacts(s, d, "F3")).withColumn("opps", F.array_join("opps", ","))


@query("exact_racy_overcount", C("F1").add("w", S.fan("c", ("router",))).select("SELECT core, sum(fan_out)::BIGINT AS fan_out FROM w GROUP BY core"))
def _(s, d):
    return E.racy_count(contacts(s, d, "F1"))


@query("exact_heavy_fixed", C("F1").add("x", S.fixed("c", 3600, 300)).add("t", S.fan("x", ("win",))).select(f"SELECT * FROM t WHERE fan_out >= {T1}"))
def _(s, d):
    return E.exact_heavy_fixed(contacts(s, d, "F1"), theta(s, d, "F1"), F1_SPAN, EVENT_SLOTS)


_HEAVY = {f: C(f).add("x", S.expanded("c", n, k)).add("t", S.fan("x", ("win",))).select(f"SELECT * FROM t WHERE fan_out >= {th}") for f, n, k, th in (("F1", 3600, 300, T1), ("F3", 84, 12, 110))}


@query("exact_heavy_sliding_expand", _HEAVY["F3"])
def _(s, d):
    return E.exact_heavy_sliding(contacts(s, d, "F3"), theta(s, d, "F3"), F3_SPAN, SHIP_SLOTS, "expand")


@query("exact_heavy_sliding_sweep", _HEAVY["F1"])
def _(s, d):
    return E.exact_heavy_sliding(contacts(s, d, "F1"), theta(s, d, "F1"), F1_SPAN, EVENT_SLOTS)


@query("exact_sweep_ship", _HEAVY["F3"])
def _(s, d):
    return E.exact_heavy_sliding(contacts(s, d, "F3"), theta(s, d, "F3"), F3_SPAN, SHIP_SLOTS)


@query("detection_delay", C("F1").add("x", S.expanded("c", 3600, 300)).add("t", S.fan("x", ("win",))).add("y", S.fixed("c", 3600, 300)).add("u", S.fan("y", ("win",))).select(
    f"""SELECT core, sliding_slot, fixed_slot, fixed_slot - sliding_slot AS delay FROM (SELECT core, min(win) + 299 AS sliding_slot FROM t WHERE fan_out >= {T1} GROUP BY core)
    LEFT JOIN (SELECT core, (min(win) + 1) * 300 - 1 AS fixed_slot FROM u WHERE fan_out >= {T1} GROUP BY core) USING (core)"""))
def _(s, d):
    return E.detection_delay(contacts(s, d, "F1"), theta(s, d, "F1"), F1_SPAN, EVENT_SLOTS)


# bitmaps

_EST = "SELECT {by}core, touched, " + S.est(2048) + " AS est, touched >= 2048 AS saturated FROM (SELECT {by}core, count(DISTINCT " + S.rec("opp", 2048) + ") AS touched FROM {src} GROUP BY ALL)"


@query("linear_estimate", C("F6").select(_EST.format(by="", src="c")))
def _(s, d):
    return N.linear_estimate(contacts(s, d, "F6"), 2048)


@query("linear_estimate_bitmap", C("F3").select(_EST.format(by="", src="c")))
def _(s, d):
    return N.linear_estimate(contacts(s, d, "F3"), 2048, impl="bitmap")


@query("linear_salted", C("F1").select("SELECT core, round(avg(est), 4) AS est FROM (" + " UNION ALL ".join(
    f"SELECT core, {S.est(1024)} AS est FROM (SELECT core, count(DISTINCT {S.rec('opp', 1024, i)}) AS touched FROM c GROUP BY core)" for i in range(4)) + ") GROUP BY core"))
def _(s, d):
    return N.linear_salted(contacts(s, d, "F1"), 1024)


@query("linear_fixed_windows", C("F3").add("x", S.fixed("c", 84, 12)).select(_EST.format(by="win, ", src="x")))
def _(s, d):
    return N.linear_fixed(contacts(s, d, "F3"), 2048, F3_SPAN, SHIP_SLOTS)


_SLIDING_EST = C("F3").add("x", S.expanded("c", 84, 12)).select(_EST.format(by="win, ", src="x"))


@query("linear_rebuild_sliding", _SLIDING_EST)
def _(s, d):
    return N.linear_rebuild_sliding(contacts(s, d, "F3"), 2048, F3_SPAN, SHIP_SLOTS)


_LOAD = C("F6").add("t", S.fan("c")).add("e", f"SELECT core, {S.est(1024)} AS est FROM (SELECT core, count(DISTINCT {S.rec('opp', 1024)}) AS touched FROM c GROUP BY core)").add(
    "j", "SELECT est, fan_out, fan_out * 8 // 1024 AS load, (est - fan_out) / fan_out AS rel FROM t JOIN e USING (core)")


@query("linear_error_by_load", _LOAD.select(
    """SELECT load, count(*) AS cores, round(sqrt(avg(rel * rel)), 6) AS rms_error, round(sqrt(1024.0 * (exp(avg(fan_out) / 1024) - avg(fan_out) / 1024 - 1)) / avg(fan_out), 6) AS theory
    FROM j GROUP BY load"""))
def _(s, d):
    c = contacts(s, d, "F6")
    return A.error_by_load(N.linear_estimate(c, 1024), E.exact_fanout(c), 1024)


# recorders

_STATE = f"SELECT core, {S.rec('opp', 2048)} AS rec, max(slot) AS last_slot FROM c GROUP BY ALL"


@query("recorder_touch", C("F3").select(_STATE))
def _(s, d):
    return R.touch(contacts(s, d, "F3"), 2048)


@query("recorder_touched", C("F3").add("g", f"SELECT DISTINCT core, {S.rec('opp', 2048)} AS rec FROM c WHERE slot BETWEEN 39 AND 50").select("SELECT core, count(*) AS touched FROM g GROUP BY core"))
def _(s, d):
    return R.touched(R.touch(contacts(s, d, "F3").filter("slot <= 50"), 2048), 50, F3_SPAN)


@query("recorder_estimate", C("F3").add("x", "SELECT * FROM c WHERE slot BETWEEN 39 AND 50").select(_EST.format(by="", src="x")))
def _(s, d):
    return R.recorder_estimate(R.touch(contacts(s, d, "F3").filter("slot <= 50"), 2048), 50, F3_SPAN, 2048)


@query("recorder_sliding_all", _SLIDING_EST)
def _(s, d):
    n = expand_ranges(R.all_windows(contacts(s, d, "F3"), 2048, F3_SPAN, SHIP_SLOTS))
    return N.with_estimate(n.select("win", "core", F.col("n").alias("touched")), 2048)


@query("recorder_age_eager", C("F3").add("g", f"SELECT core, {S.rec('opp', 64)} AS rec, max(slot) AS last_slot FROM c WHERE slot <= 40 GROUP BY ALL").select(
    """SELECT k.core, string_agg(coalesce(least(47 - last_slot, 65535), 65535), ',' ORDER BY i) AS ages
    FROM (SELECT core, i FROM (SELECT DISTINCT core FROM g), (SELECT unnest(range(64)) AS i)) k LEFT JOIN g ON g.core = k.core AND g.rec = k.i GROUP BY k.core"""))
def _(s, d):
    dense = R.dense(R.touch(contacts(s, d, "F3").filter("slot <= 40"), 64), 40, 64)
    ages = F.col("ages")
    for _i in range(7):
        ages = R.aged(ages)
    return dense.select("core", F.array_join(ages, ",").alias("ages"))


@query("recorder_combine_nearest", C("F3").select(f"SELECT {S.rec('opp', 2048)} AS rec, max(slot) AS last_slot FROM c GROUP BY ALL"))
def _(s, d):
    return R.combine_nearest(R.touch(contacts(s, d, "F3"), 2048, ("router",)))


@query("recorder_combine_farthest", C("F3").add("g", f"SELECT router, {S.rec('opp', 2048)} AS rec, max(slot) AS last_slot FROM c GROUP BY ALL").select(
    "SELECT rec, min(last_slot) AS last_slot FROM g GROUP BY rec HAVING count(*) = 4"))
def _(s, d):
    return R.combine_farthest(R.touch(contacts(s, d, "F3"), 2048, ("router",)), 4)


@query("recorder_compact", C("F3").add("g", _STATE).select("SELECT * FROM g WHERE 83 - last_slot < 12"))
def _(s, d):
    return R.compact(R.touch(contacts(s, d, "F3"), 2048), 83, F3_SPAN)


# the grid

_GRID6 = C("F6").select(S.grid("c", W6))


@query("grid_scan", _GRID6)
def _(s, d):
    return G.scan_grid(contacts(s, d, "F6"), WIDE)


@query("grid_scan_batched", C("F1").select(S.grid("c", S1)))
def _(s, d):
    return G.scan_batches(contacts(s, d, "F1"), SMALL, 100)


@query("grid_at_window", C("F1").add("x", "SELECT * FROM c WHERE slot BETWEEN 1201 AND 1500").select(S.grid("x", S1)))
def _(s, d):
    return G.grid_at(G.scan_grid(contacts(s, d, "F1").filter("slot <= 1500"), SMALL), 1500, F1_SPAN)


@query("grid_merge_routers", C("F3").select(S.grid("c", W6)))
def _(s, d):
    return G.merge_grids(G.scan_grid(contacts(s, d, "F3"), WIDE, ("router",)))


@query("grid_merge_literal", C("F3").add("g", S.grid("c", W6, ("router",))).select("SELECT row_id, col_id, rec, min(last_slot) AS last_slot FROM g GROUP BY ALL HAVING count(*) = 4"))
def _(s, d):
    return G.merge_grids(G.scan_grid(contacts(s, d, "F3"), WIDE, ("router",)), "farthest", 4)


@query("hot_cutoff", C("F3").add("t", S.fan("c")).select(
    "SELECT DISTINCT m, fan_out AS theta, round(m * (1 - exp(-fan_out / m::DOUBLE)), 6) AS cutoff FROM t, (SELECT unnest([512, 1024, 2048]) AS m)"))
def _(s, d):
    # the cut-offs of all fan-outs that suppliers have, for three sizes of a sketch
    rows = E.exact_fanout(contacts(s, d, "F3")).select(F.explode(F.array(*map(F.lit, (512, 1024, 2048)))).alias("m"), F.col("fan_out").alias("theta")).distinct()
    return rows.withColumn("cutoff", F.round(F.col("m") * (1 - F.exp(-F.col("theta") / F.col("m").cast("double"))), 6))


@query("grid_hot_cells", C("F6").add("g", S.grid("c", W6)).select(S.hot("g", W6)))
def _(s, d):
    return G.hot_cells(G.scan_grid(contacts(s, d, "F6"), wide(s, d)), wide(s, d))


@query("grid_age", C("F3").add("g", S.grid("c", W6)).select("SELECT row_id, col_id, rec, least(83 - last_slot + 5, 65535) AS age FROM g"))
def _(s, d):
    g = G.scan_grid(contacts(s, d, "F3"), WIDE).select("row_id", "col_id", "rec", (F.lit(83) - F.col("last_slot")).alias("age"))
    return G.age_grid(g, 5)


_POINT = C("F3").add("g", S.grid("c", W6)).add("q", f"SELECT core, {S.root('core', 14)} AS c0 FROM (SELECT DISTINCT core FROM c)").add(
    "a", "SELECT core, c0, " + ", ".join(f"xor(core >> {W6.shift(i)}, c0) & 16383 AS c{i}" for i in range(1, 5)) + " FROM q").add("v", S.verified("a", "g", W6, (), 1))


@query("grid_point_query", _POINT.select(S.report("v", W6)))
def _(s, d):
    c = contacts(s, d, "F3")
    return G.query_grid(G.scan_grid(c, WIDE), c, WIDE)


_SHARDED = C("F6").add("x", "SELECT *, core % 4 AS shard FROM c")


@query("grid_sharded", S.regain(_SHARDED, "x", W6, ("shard",)).select("SELECT * FROM found WHERE core % 4 = shard"))
def _(s, d):
    p = wide(s, d)
    return V.regain_sharded(stored(G.scan_sharded(contacts(s, d, "F6"), p, 4)), p, 4)


_SWEEP = [(2048, 14, 6, 5), (1024, 14, 6, 5), (512, 14, 6, 5), (2048, 16, 8, 4)]


@query("grid_param_sweep", (lambda w: [w.add(f"g{i}", S.grid("c", S.SqlGrid(m=m, w=x, d=y, r=r, theta=T6))) for i, (m, x, y, r) in enumerate(_SWEEP)] and w.select(" UNION ALL ".join(
    f"SELECT {m} AS m, {x} AS w, {y} AS d, {r} AS r, count(*) AS hot, max(touched) AS widest FROM ({S.hot(f'g{i}', S.SqlGrid(m=m, w=x, d=y, r=r, theta=T6))})" for i, (m, x, y, r) in enumerate(_SWEEP))))(C("F6")))
def _(s, d):
    c, out = stored(contacts(s, d, "F6")), None
    for m, w, dd, r in _SWEEP:
        p = GridParams(m=m, w=w, d=dd, r=r, theta=theta(s, d, "F6")).validate()
        one = G.hot_cells(G.scan_grid(c, p), p).agg(*(F.lit(x).alias(k) for x, k in ((m, "m"), (w, "w"), (dd, "d"), (r, "r"))), F.count("*").alias("hot"), F.max("touched").alias("widest"))
        out = one if out is None else out.unionByName(one)
    return out


@query("grid_memory", C("F6").add("g", S.grid("c", W6)).select(
    "SELECT 335544320 AS dense_bytes, count(*) AS sparse_rows, (SELECT count(*) FROM (SELECT DISTINCT row_id, col_id FROM g)) AS cells_used, round(count(*) / 167772160.0, 9) AS fill FROM g"))
def _(s, d):
    return G.grid_memory(G.scan_grid(contacts(s, d, "F6"), WIDE), WIDE)


# recovery

_FOUND6 = S.regain(C("F6"), "c", W6).select("SELECT * FROM found")


@query("regain_levels", _FOUND6)
def regain_levels(s, d):
    p = wide(s, d)
    return V.regain_levels(stored(G.scan_words(contacts(s, d, "F6"), p)), p)


#: Few hot cells: the whole period of the events.
_FEW = S1.with_(theta=f"6 * {T1}")


def _few(s, d) -> tuple[DataFrame, GridParams]:
    p = SMALL.with_(theta=6 * theta(s, d, "F1"))
    return stored(G.scan_grid(contacts(s, d, "F1"), p)), p


@query("regain_bruteforce", S.regain(C("F1"), "c", _FEW).select("SELECT * FROM found"))
def _(s, d):
    return V.regain_bruteforce(*_few(s, d))


@query("regain_dfs", _FOUND6)
def _(s, d):
    p = wide(s, d)
    return V.regain_dfs(stored(G.scan_words(contacts(s, d, "F6"), p)), p)


@query("regain_eager", _FOUND6)
def _(s, d):
    p = wide(s, d)
    return V.regain_eager(stored(G.scan_words(contacts(s, d, "F6"), p)), p)


@query("regain_start_chains", C("F6").add("g", S.grid("c", W6)).add("h", S.hot("g", W6)).select(S.chains("h", W6, 2)))
def _(s, d):
    p = wide(s, d)
    return V.start_chains(stored(G.hot_cells(G.scan_words(contacts(s, d, "F6"), p), p)), p)


_LEVELS = C("F6").add("g", S.grid("c", W6)).add("h", S.hot("g", W6)).select(" UNION ALL ".join(f"SELECT {i} AS level, count(*) AS chains FROM ({S.chains('h', W6, i)})" for i in (2, 3, 4)))


@query("regain_extend_counts", _LEVELS)
def _(s, d):
    p = wide(s, d)
    return V.chain_counts(stored(G.hot_cells(G.scan_words(contacts(s, d, "F6"), p), p)), p)


@query("even_split_sizes", C("F6").add("g", S.grid("c", W6)).add("h", S.hot("g", W6)).select(
    "SELECT worker, count(*) AS items FROM (SELECT (ntile(64) OVER (ORDER BY row_id, col_id)) - 1 AS worker FROM h) GROUP BY worker"))
def _(s, d):
    p = wide(s, d)
    return V.even_split(G.hot_cells(G.scan_grid(contacts(s, d, "F6"), p), p), 64, "row_id", "col_id").groupBy("worker").agg(F.count("*").alias("items"))


@query("regain_verified", S.regain(C("F6"), "c", W6).select("SELECT * FROM ver"))
def _(s, d):
    p = wide(s, d)
    g = stored(G.scan_words(contacts(s, d, "F6"), p))
    return V.verified(g, stored(G.hot_cells(g, p)), p, full=True)


_FREE = GridParams(m=1024, w=14, d=6, r=5, root_check=False)


@query("regain_no_root_check", S.regain(C("F6"), "c", S.SqlGrid.of(_FREE, T6)).select("SELECT * FROM found"))
def _(s, d):
    p = _FREE.with_(theta=theta(s, d, "F6"))
    return V.regain_levels(stored(G.scan_words(contacts(s, d, "F6"), p)), p)


_LIT = GridParams(m=1024, w=14, d=6, r=5, literal_shift=True)


@query("regain_literal_shift", S.regain(C("F6"), "c", S.SqlGrid.of(_LIT, T6)).select("SELECT * FROM found"))
def _(s, d):
    p = _LIT.with_(theta=theta(s, d, "F6"))
    return V.regain_levels(stored(G.scan_words(contacts(s, d, "F6"), p)), p)


_WIN1 = S.regain(C("F1").add("x", S.expanded("c", 3600, 300)), "x", S1, ("win",))


@query("regain_sliding_all", _WIN1.select("SELECT * FROM found"))
def _(s, d):
    return V.regain_sliding(contacts(s, d, "F1"), small(s, d, k=F1_SPAN), EVENT_SLOTS)


@query("detect_distributed", S.regain(C("F6"), "c", W6).select("SELECT * FROM found"))
def _(s, d):
    return V.detect(contacts(s, d, "F6"), wide(s, d))


_RESCAN = C("F6").add("g", S.grid("c", W6)).add("q", f"SELECT core, {S.root('core', 14)} AS c0 FROM (SELECT DISTINCT core FROM c)").add(
    "a", "SELECT core, c0, " + ", ".join(f"xor(core >> {W6.shift(i)}, c0) & 16383 AS c{i}" for i in range(1, 5)) + " FROM q").add(
    "h", S.hot("g", W6)).add("b", "SELECT * FROM a WHERE " + " AND ".join(f"EXISTS (SELECT 1 FROM h WHERE row_id = {i} AND col_id = c{i})" for i in range(5))).add("v", S.verified("b", "g", W6))


@query("regain_rescan", _RESCAN.select(S.report("v", W6)))
def _(s, d):
    p, c = wide(s, d), contacts(s, d, "F6")
    return V.rescan(c, stored(G.scan_grid(c, p)), p)


@query("regain_ghosts", S.regain(C("F6"), "c", S.SqlGrid.of(_FREE, T6)).select("SELECT * FROM found WHERE core NOT IN (SELECT core FROM c)"))
def _(s, d):
    p, c = _FREE.with_(theta=theta(s, d, "F6")), stored(contacts(s, d, "F6"))
    return V.ghosts(V.regain_levels(stored(G.scan_words(c, p)), p), c)


# competing detectors

_CRT_G = S.crt(C("F6"), "c", 2048, T6, B.MODULI)


@query("crt_scan", _CRT_G.select("SELECT * FROM crt_g"))
def _(s, d):
    return B.crt_scan(contacts(s, d, "F6"), 2048)


@query("crt_regain", _CRT_G.select("SELECT * FROM crt_found"))
def _(s, d):
    return B.crt_regain(stored(B.crt_words(contacts(s, d, "F6"), 2048)), 2048, theta(s, d, "F6"))


_SLICE = S.slices(C("F6"), "c", W6)


@query("slice_scan", _SLICE.select("SELECT * FROM sl_g"))
def _(s, d):
    return B.slice_scan(contacts(s, d, "F6"), WIDE)


@query("slice_regain", _SLICE.select("SELECT * FROM sl_found"))
def _(s, d):
    p = wide(s, d)
    return B.slice_regain(stored(B.slice_words(contacts(s, d, "F6"), p)), p)


POOL_BITS, POOL_OWN = 1 << 22, 1024
_POOL = S.pool(C("F6"), "c", POOL_BITS, POOL_OWN, T6)


@query("pool_scan", _POOL.select("SELECT * FROM po_p"))
def _(s, d):
    return B.pool_scan(contacts(s, d, "F6"), POOL_BITS, POOL_OWN)


@query("pool_regain", _POOL.select("SELECT * FROM po_found"))
def _(s, d):
    return B.pool_regain(stored(contacts(s, d, "F6")), POOL_BITS, POOL_OWN, theta(s, d, "F6"))


@query("builtin_ndv_error")
def _(s, d):
    c, out = stored(contacts(s, d, "F3")), None
    truth = E.exact_fanout(c)
    for kind in ("approx", "hll", "theta"):
        one = A.estimate_error(B.builtin_ndv(c, kind), truth).withColumn("kind", F.lit(kind))
        out = one if out is None else out.unionByName(one)
    return out


# measures

_TRUTH6 = f"SELECT core FROM c GROUP BY core HAVING count(DISTINCT opp) >= {T6}"


@query("acc_fixed", S.regain(C("F1").add("x", S.fixed("c", 3600, 300)), "x", S1, ("win",)).add("truth", f"SELECT win, core FROM x GROUP BY ALL HAVING count(DISTINCT opp) >= {T1}").select(S.accuracy("found", "truth", ("win",))))
def _(s, d):
    x, p = stored(fixed_window(contacts(s, d, "F1"), F1_SPAN, EVENT_SLOTS)), small(s, d)
    found = V.regain_levels(stored(G.scan_words(x, p, ("win",))), p, ("win",))
    return A.accuracy(found, E.exact_fanout(x, ("win",)).filter(F.col("fan_out") >= p.theta), ("win",))


@query("acc_report_all", C("F6").add("truth", _TRUTH6).add("everyone", "SELECT DISTINCT core FROM c").select(
    "SELECT n_true, n_found, n_found - n_true AS n_false, 0 AS n_missed, round((n_found - n_true) / n_true, 6) AS fpr, 0.0::DOUBLE AS fnr, round((n_found - n_true) / n_true, 6) AS tfr "
    "FROM (SELECT (SELECT count(*) FROM truth) AS n_true, (SELECT count(*) FROM everyone) AS n_found)"))
def _(s, d):
    fan = stored(E.exact_fanout(contacts(s, d, "F6")))
    return A.accuracy(fan, fan.filter(F.col("fan_out") >= theta(s, d, "F6")))


@query("est_error", C("F6").add("t", S.fan("c")).add("e", f"SELECT core, {S.est(2048)} AS est FROM (SELECT core, count(DISTINCT {S.rec('opp', 2048)}) AS touched FROM c GROUP BY core)").select(
    """SELECT count(*) AS cores, round(avg(abs((est - fan_out) / fan_out)), 6) AS mean_error, round(sqrt(avg(((est - fan_out) / fan_out) ** 2)), 6) AS rms_error, round(avg(est - fan_out), 4) AS bias
    FROM t JOIN e USING (core)"""))
def _(s, d):
    c = stored(contacts(s, d, "F6"))
    return A.estimate_error(N.linear_estimate(c, 2048), E.exact_fanout(c))


@query("work_counters", C("F6").add("g", S.grid("c", W6)).add("h", S.hot("g", W6)).select(
    "SELECT (SELECT count(*) FROM c) AS contacts, (SELECT count(*) FROM c) * 5 AS writes, " + " * ".join(f"(SELECT count(*) FROM h WHERE row_id = {i})" for i in range(3)) + " AS start_tests, "
    + ", ".join(f"(SELECT count(*) FROM ({S.chains('h', W6, i)})) AS chains_{i}" for i in (2, 3, 4))))
def _(s, d):
    p, c = wide(s, d), stored(contacts(s, d, "F6"))
    hot = stored(G.hot_cells(G.scan_grid(c, p), p))
    return A.work_counters(c, hot, V.chain_counts(hot, p), p)


@query("topk_heavy", C("F6").add("t", S.fan("c")).select("SELECT * FROM t ORDER BY fan_out DESC, core LIMIT 20"))
def _(s, d):
    return A.top_heavy(E.exact_fanout(contacts(s, d, "F6")), 20)


@query("topk_per_window", C("F1").add("x", S.fixed("c", 3600, 300)).add("t", S.fan("x", ("win",))).select("SELECT *, row_number() OVER (PARTITION BY win ORDER BY fan_out DESC, core) AS nth FROM t QUALIFY nth <= 3"))
def _(s, d):
    return A.top_heavy(E.exact_fanout(fixed_window(contacts(s, d, "F1"), F1_SPAN, EVENT_SLOTS), ("win",)), 3, ("win",))


@query("heavy_transitions", C("F3").add("x", S.expanded("c", 84, 12)).add("t", S.fan("x", ("win",))).add("hv", "SELECT win, core FROM t WHERE fan_out >= 110").select(
    """SELECT win, count(*) FILTER (NOT b) AS entered, count(*) FILTER (NOT a) AS gone, count(*) FILTER (a AND b) AS stayed FROM (
    SELECT win, core, bool_or(k = 1) AS a, bool_or(k = 2) AS b FROM (SELECT win, core, 1 AS k FROM hv UNION ALL SELECT win + 1, core, 2 FROM hv) GROUP BY ALL) GROUP BY win"""))
def _(s, d):
    return E.heavy_transitions(stored(E.exact_heavy_sliding(contacts(s, d, "F3"), theta(s, d, "F3"), F3_SPAN, SHIP_SLOTS)))

