"""Streaming queries with the SQL of their batch meaning."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import encode_key
from ..sources.contacts import EVENT_SLOT, EVENT_SLOTS
from ..sources.storage import table
from ..streaming import live as L
from . import sqltext as S
from .methods import _WIN1, C, F1_SPAN, S1, SMALL, query, small

# the watermark stays behind the last event, so windows that it has not passed are not emitted in append mode
_E = f"SELECT ts, {S.codec(S._K)} AS core, user_id AS opp, {S.event_slot()} AS slot, event_type FROM events"
_SLOT = f"cast(floor((unix_micros(cast(ts as timestamp)) - 1704067200000000) / {EVENT_SLOT * 1_000_000}) as bigint)"
_LIMIT = "(SELECT max(ts) - INTERVAL {0} FROM events)"


@query("stream_tumbling", f"""SELECT * FROM (SELECT start, core, count(*) AS n FROM (SELECT time_bucket(INTERVAL 12 MINUTE, ts, TIMESTAMP '1970-01-01') AS start, core FROM ({_E})) GROUP BY start, core)
    WHERE start + INTERVAL 12 MINUTE <= {_LIMIT.format('12 MINUTE')}""")
def _(s, d):
    return L.drained(L.slot_counts(L.event_stream(s, d))).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_sliding", f"""SELECT w AS start, core, count(DISTINCT opp) AS fan_out FROM (SELECT *, unnest(range(0, 5)) AS k FROM ({_E})),
    LATERAL (SELECT time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 12 HOUR AS w) WHERE ts < w + INTERVAL 60 HOUR GROUP BY ALL HAVING w + INTERVAL 60 HOUR <= {_LIMIT.format('1 HOUR')}""")
def _(s, d):
    return L.drained(L.sliding_fanout(L.event_stream(s, d), "60 hours", "12 hours")).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_session", f"""SELECT min(ts) AS start, core, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY core ORDER BY ts) AS part FROM (
    SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY core ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM ({_E}))) GROUP BY core, part HAVING max(ts) + INTERVAL 6 HOUR <= {_LIMIT.format('1 HOUR')}""")
def _(s, d):
    return L.drained(L.sessions(L.event_stream(s, d))).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_grid_state", C("F1").select(S.grid("c", S1)))
def _(s, d):
    return L.drained(L.grid_state(L.event_stream(s, d), SMALL), "complete")


@query("stream_dense_state", C("F1").select(f"SELECT core, {S.rec('opp', 256)} AS rec, max(slot) AS last_slot FROM c GROUP BY ALL"))
def _(s, d):
    state = L.newest(L.dense_state(L.event_stream(s, d), 256), "core")
    return state.select("core", F.posexplode("last").alias("rec", "last_slot")).filter("last_slot >= 0").withColumn("rec", F.col("rec").cast("long"))


#: Micro-batches of the replayed events, in the order of time.
_BATCHES = 4
_BY_TIME = f"cast(floor((unix_micros(cast(ts as timestamp)) - 1704067200000000) / {EVENT_SLOT * 1_000_000 * EVENT_SLOTS // _BATCHES}) as int)"


@query("stream_heavy_report", _WIN1.select("SELECT win + 299 AS slot, core, touched, est, saturated FROM found"))
def _(s, d):
    events = L.event_stream(s, d, L.replayed(s, d, F.expr(_BY_TIME), _BATCHES))
    return L.heavy_report(events.select("core", "opp", "slot"), small(s, d, k=F1_SPAN))


@query("stream_late_merge", C("F1").select(S.grid("c", S1)))
def _(s, d):
    # even slots land first, odd ones in two later files: the maximum does not mind
    late = F.when(F.expr(f"{_SLOT} % 2 = 0"), 0).otherwise(F.expr(f"1 + {_SLOT} div 2 % 2"))
    return L.drained(L.grid_state(L.event_stream(s, d, L.replayed(s, d, late, 3)), SMALL), "complete")


# every tenth event lands after all others; a batch drops what is later than the watermark that the batch before it had, and drops are counted
_HALF = "ts < TIMESTAMP_NTZ '2024-01-16 00:00:00'"
_FIRST = "ts < TIMESTAMP '2024-01-16' AND event_id % 10 <> 0"
_KEPT = f"SELECT event_id FROM events WHERE {_FIRST} OR ts > (SELECT date_trunc('millisecond', max(ts)) - INTERVAL 1 HOUR FROM events WHERE {_FIRST})"


def _halves(s, d):
    return L.event_stream(s, d, L.replayed(s, d, F.when(F.expr("event_id % 10 = 0"), 2).when(F.expr(_HALF), 0).otherwise(1), 3))


@query("stream_late_kept", _KEPT)
def _(s, d):
    return L.on_time(_halves(s, d), "event_id")[0].select("event_id")


@query("stream_late_count", f"SELECT (SELECT count(*) FROM ({_KEPT})) AS kept, (SELECT count(*) FROM events) - (SELECT count(*) FROM ({_KEPT})) AS dropped")
def _(s, d):
    rows, late = L.on_time(_halves(s, d), "event_id")
    return rows.agg(F.count("*").alias("kept"), F.lit(late).cast("long").alias("dropped"))


# users as the cores: few contacts each, so that state expires
@query("stream_state_expiry", f"""SELECT {S.codec('user_id')} AS core, epoch_ms(max(ts)) + {F1_SPAN * EVENT_SLOT * 1_000} < (SELECT epoch_ms(max(ts)) - 3600000 FROM events) AS expired
    FROM events GROUP BY user_id""")
def _(s, d):
    events = L.event_stream(s, d, L.replayed(s, d, F.expr(_BY_TIME), _BATCHES)).select(encode_key(F.col("opp")).alias("core"), F.col("core").alias("opp"), "slot", "ts")
    return L.newest(L.dense_state(events, 64, F1_SPAN * EVENT_SLOT), "core").select("core", "expired")


@query("stream_rate", f"SELECT slot, core, count(DISTINCT opp) AS fan_out FROM ({_E}) GROUP BY ALL")
def _(s, d):
    # the events in the order of time, a file a micro-batch
    events = L.event_stream(s, d, L.replayed(s, d, F.expr(_BY_TIME), _BATCHES))
    return L.drained(events.select("slot", "core", "opp")).groupBy("slot", "core").agg(F.countDistinct("opp").alias("fan_out"))


@query("stream_memory_sink", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def _(s, d):
    return L.in_memory(L.event_stream(s, d).groupBy("event_type").agg(F.count("*").alias("n")), "complete")


@query("stream_dedup", f"SELECT DISTINCT core, opp, slot FROM ({_E})")
def _(s, d):
    return L.drained(L.distinct_contacts(L.event_stream(s, d)))


@query("stream_routers", C("F1").select(S.grid("c", S1)))
def _(s, d):
    kinds = [r[0] for r in table(s, d, "events").select("event_type").distinct().collect()]  # the routers, a fixed few
    return L.drained(L.grid_state(L.merged_routers([L.event_stream(s, d).filter(F.col("event_type") == k) for k in kinds]), SMALL), "complete")


@query("stream_enrich", "SELECT event_id, n_name FROM (SELECT event_id, user_id % 25 AS k FROM events) JOIN nation ON k = n_nationkey")
def _(s, d):
    st = L.event_stream(s, d).select("event_id", (F.col("opp") % 25).alias("k"))
    return L.drained(st.join(table(s, d, "nation"), F.col("k") == F.col("n_nationkey")).select("event_id", "n_name"))

