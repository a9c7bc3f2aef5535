"""The operators around the methods: sources, sinks, joins, aggregation, windows, functions and the SQL surface, with DuckDB text."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import hashing as H
from ..functions.sqlext import register
from ..operators import exact as E
from ..operators import grid as G
from ..operators import recorder as R
from ..sources.contacts import EVENT_SLOTS, contacts, theta
from ..sources.storage import shared_dir, stored, table
from . import sqltext as S
from .methods import C, F1_SPAN, T1, WIDE, W6, _few, _FEW, query


@query("src_parquet", "SELECT 'events' AS name, count(*) AS n FROM events UNION ALL SELECT 'orders', count(*) FROM orders UNION ALL SELECT 'lineitem', count(*) FROM lineitem")
def _(s, d):
    parts = [table(s, d, t).agg(F.lit(t).alias("name"), F.count("*").alias("n")) for t in ("events", "orders", "lineitem")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("src_roundtrip", " UNION ALL ".join(f"SELECT '{k}' AS kind, n_nationkey, n_name, n_regionkey FROM nation" for k in ("csv", "json", "orc", "text")))
def _(s, d):
    n, out = table(s, d, "nation"), None
    for kind in ("csv", "json", "orc", "text"):
        path = f"{shared_dir(s)}/roundtrip/{uuid.uuid4().hex}"
        if kind == "text":
            n.select(F.concat_ws("\t", "n_nationkey", "n_name", "n_regionkey")).write.text(path)
            parts = F.split("value", "\t")
            back = s.read.text(path).select(parts[0].cast("int").alias("n_nationkey"), parts[1].alias("n_name"), parts[2].cast("int").alias("n_regionkey"))
        else:
            n.write.format(kind).save(path)
            back = s.read.schema(n.schema).format(kind).load(path)
        back = back.select(F.lit(kind).alias("kind"), "n_nationkey", "n_name", "n_regionkey")
        out = back if out is None else out.unionByName(back)
    return out


@query("sink_state_roundtrip", C("F3").select(S.grid("c", W6)))
def _(s, d):
    name = f"state_{uuid.uuid4().hex}"
    g = G.scan_grid(contacts(s, d, "F3"), WIDE)
    path = f"{shared_dir(s)}/{name}"
    g.write.partitionBy("row_id").parquet(path)  # a table of buckets by col_id where a catalogue is at hand: see sources.storage
    return s.read.parquet(path).select(F.col("row_id").cast("long").alias("row_id"), "col_id", "rec", "last_slot")


@query("sink_bucketed", C("F3").add("g", S.grid("c", W6)).select("SELECT row_id, col_id, count(*) AS touched, max(last_slot) AS last_slot FROM g GROUP BY ALL"))
def _(s, d):
    # state in buckets by cell, sorted: counts by cell and joins of two such tables need no exchange
    name = f"fanout_state_{uuid.uuid4().hex}"
    G.scan_grid(contacts(s, d, "F3"), WIDE).write.bucketBy(8, "row_id", "col_id").sortBy("row_id", "col_id").option("path", f"{shared_dir(s)}/{name}").saveAsTable(name)
    return s.table(name).groupBy("row_id", "col_id").agg(F.count("*").alias("touched"), F.max("last_slot").alias("last_slot"))


@query("op_project", "SELECT event_id AS id, upper(event_type) AS kind, round(value * 2, 6) AS twice FROM events")
def _(s, d):
    return table(s, d, "events").select(F.col("event_id").alias("id"), F.upper("event_type").alias("kind"), F.round(F.col("value") * 2, 6).alias("twice"))


@query("op_filter_prefix", C("F3").select("SELECT DISTINCT core FROM c WHERE core >= 1073741824 AND core < 2147483648"))
def _(s, d):
    # addresses of the network 64.0.0.0/2
    return contacts(s, d, "F3").filter(F.shiftright("core", 30) == 1).select("core").distinct()


@query("op_filter_kinds", "SELECT event_id FROM events WHERE value BETWEEN 10 AND 50 AND event_type IN ('click', 'view') AND props IS NOT NULL AND event_type LIKE 'c%'")
def _(s, d):
    return table(s, d, "events").filter(F.col("value").between(10, 50) & F.col("event_type").isin("click", "view") & F.col("props").isNotNull() & F.col("event_type").like("c%")).select("event_id")


@query("op_sample_hash", C("F6").add("t", S.fan("c")).select(f"SELECT * FROM t WHERE {S.root('core', 10)} < 102"))
def _(s, d):
    return E.exact_fanout(contacts(s, d, "F6").filter(H.root_hash(F.col("core"), 10) < 102))


_ORDERS = "SELECT o_custkey, count(*) AS lines, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey"


def _lines(s, d, hint: str | None = None) -> DataFrame:
    o = table(s, d, "orders")
    o = o.hint(hint) if hint else o
    j = table(s, d, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_custkey").agg(F.count("*").alias("lines"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("join_inner", _ORDERS)
def _(s, d):
    return _lines(s, d)


@query("join_merge", _ORDERS)
def _(s, d):
    return _lines(s, d, "merge")


@query("join_shuffle_hash", _ORDERS)
def _(s, d):
    return _lines(s, d, "shuffle_hash")


@query("join_broadcast", "SELECT n_name, count(*) AS suppliers FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def _(s, d):
    # nations are a fixed list
    j = table(s, d, "supplier").join(F.broadcast(table(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey"))
    return j.groupBy("n_name").agg(F.count("*").alias("suppliers"))


def _spent(s, d) -> tuple[DataFrame, DataFrame]:
    return table(s, d, "customer").select("c_custkey"), table(s, d, "orders").filter("o_totalprice > 200000").select("o_orderkey", "o_custkey")


@query("join_left_right", """SELECT 'left' AS side, c_custkey AS k, count(o_orderkey) AS n FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_totalprice > 200000) ON c_custkey = o_custkey GROUP BY c_custkey
    UNION ALL SELECT 'right', o_custkey, count(c_custkey) FROM (SELECT * FROM customer WHERE c_acctbal > 0) RIGHT JOIN (SELECT * FROM orders WHERE o_totalprice > 200000) ON c_custkey = o_custkey GROUP BY o_custkey""")
def _(s, d):
    c, o = _spent(s, d)
    left = c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy(F.lit("left").alias("side"), F.col("c_custkey").alias("k")).agg(F.count("o_orderkey").alias("n"))
    rich = table(s, d, "customer").filter("c_acctbal > 0").select("c_custkey")
    right = rich.join(o, F.col("c_custkey") == F.col("o_custkey"), "right").groupBy(F.lit("right").alias("side"), F.col("o_custkey").alias("k")).agg(F.count("c_custkey").alias("n"))
    return left.unionByName(right)


@query("join_full_outer", """SELECT coalesce(a.k, b.k) AS k, a.n AS few, b.n AS many FROM (SELECT l_suppkey AS k, count(*) AS n FROM lineitem WHERE l_quantity < 2 GROUP BY 1) a
    FULL JOIN (SELECT l_suppkey AS k, count(*) AS n FROM lineitem WHERE l_quantity > 49 GROUP BY 1) b ON a.k = b.k""")
def _(s, d):
    few = table(s, d, "lineitem").filter("l_quantity < 2").groupBy(F.col("l_suppkey").alias("k")).agg(F.count("*").alias("few"))
    many = table(s, d, "lineitem").filter("l_quantity > 49").groupBy(F.col("l_suppkey").alias("k")).agg(F.count("*").alias("many"))
    return few.join(many, "k", "full")


@query("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 200000)")
def _(s, d):
    c, o = _spent(s, d)
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@query("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 200000)")
def _(s, d):
    c, o = _spent(s, d)
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@query("join_cross", "SELECT a.r_name AS a, b.r_name AS b FROM region a, region b WHERE a.r_regionkey < b.r_regionkey")
def _(s, d):
    r = table(s, d, "region")  # a fixed list of five
    return r.alias("a").join(r.alias("b"), F.col("a.r_regionkey") < F.col("b.r_regionkey")).select(F.col("a.r_name").alias("a"), F.col("b.r_name").alias("b"))


@query("join_range", f"SELECT w.win, count(*) AS n FROM (SELECT unnest(range(0, 3301, 100)) AS win) w JOIN (SELECT {S.event_slot()} AS slot FROM events) e ON slot BETWEEN win AND win + 299 GROUP BY win")
def _(s, d):
    # windows and contacts meet in coarse buckets of the window's length, two for each window
    w = s.range(0, EVENT_SLOTS - F1_SPAN + 1, 100).select(F.col("id").alias("win")).withColumn("at", F.explode(F.array(F.expr("win div 300"), F.expr("win div 300 + 1"))))
    e = contacts(s, d, "F1").select("slot", F.expr("slot div 300").alias("at"))
    return w.join(e, "at").filter("slot between win and win + 299").groupBy("win").agg(F.count("*").alias("n"))


@query("join_asof", """SELECT a.event_id, max(b.ts) AS before FROM (SELECT * FROM events WHERE event_type = 'purchase') a LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') b
    ON a.user_id = b.user_id AND b.ts <= a.ts GROUP BY a.event_id""")
def _(s, d):
    e = table(s, d, "events").filter(F.col("event_type").isin("purchase", "click"))
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    return e.withColumn("before", F.max(F.when(F.col("event_type") == "click", F.col("ts"))).over(w)).filter("event_type = 'purchase'").select("event_id", "before")


@query("join_self", C("F3").add("p", "SELECT DISTINCT core, opp FROM c").select("SELECT a.core AS a, b.core AS b, count(*) AS shared FROM p a JOIN p b ON a.opp = b.opp AND a.core < b.core GROUP BY ALL HAVING count(*) >= 60"))
def _(s, d):
    p = contacts(s, d, "F3").select("core", "opp").distinct()
    j = p.alias("a").join(p.alias("b"), (F.col("a.opp") == F.col("b.opp")) & (F.col("a.core") < F.col("b.core")))
    return j.groupBy(F.col("a.core").alias("a"), F.col("b.core").alias("b")).agg(F.count("*").alias("shared")).filter("shared >= 60")


@query("agg_basic", """SELECT event_type, count(*) AS n, round(sum(value), 4) AS total, min(value) AS low, max(value) AS high, round(avg(value), 4) AS mean, round(stddev(value), 4) AS sd,
    round(corr(value, user_id), 4) AS c FROM events GROUP BY event_type""")
def _(s, d):
    return table(s, d, "events").groupBy("event_type").agg(
        F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"), F.min("value").alias("low"), F.max("value").alias("high"),
        F.round(F.avg("value"), 4).alias("mean"), F.round(F.stddev("value"), 4).alias("sd"), F.round(F.corr("value", F.col("user_id").cast("double")), 4).alias("c"),
    )


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, sum(DISTINCT l_linenumber)::BIGINT AS numbers FROM lineitem GROUP BY 1")
def _(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.sum_distinct("l_linenumber").alias("numbers"))


@query("agg_filter", "SELECT user_id % 10 AS g, count(*) FILTER (event_type = 'click') AS clicks, count(*) FILTER (value > 50) AS large FROM events GROUP BY 1")
def _(s, d):
    return table(s, d, "events").groupBy((F.col("user_id") % 10).alias("g")).agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.count_if(F.col("value") > 50).alias("large"))


@query("agg_two_level", C("F1").add("x", S.fixed("c", 3600, 300)).select(f"SELECT win, core, {S.rec('opp', 1024)} AS rec, max(slot) AS last_slot FROM x GROUP BY ALL"))
def _(s, d):
    by_slot = contacts(s, d, "F1").filter("slot >= 0 and slot < 3600").groupBy("core", H.rec_hash(F.col("opp"), 1024).alias("rec"), "slot").agg(F.max("slot").alias("last_slot"))
    return by_slot.groupBy(F.expr("slot div 300").alias("win"), "core", "rec").agg(F.max("last_slot").alias("last_slot"))


_NR = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _places(s, d) -> DataFrame:
    c, n, r = (table(s, d, t) for t in ("customer", "nation", "region"))
    return c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))


@query("agg_rollup", f"SELECT r_name, n_name, count(*) AS n FROM {_NR} GROUP BY ROLLUP (r_name, n_name)")
def _(s, d):
    return _places(s, d).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("agg_cube", f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_NR} GROUP BY CUBE (r_name, c_mktsegment)")
def _(s, d):
    return _places(s, d).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query("agg_grouping_sets", f"SELECT r_name, c_mktsegment, count(*) AS n FROM {_NR} GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")
def _(s, d):
    _places(s, d).createOrReplaceTempView("fanout_places")
    return s.sql("SELECT r_name, c_mktsegment, count(*) AS n FROM fanout_places GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")


@query("agg_pivot", "SELECT l_linestatus, count(*) FILTER (l_returnflag = 'A') AS \"A\", count(*) FILTER (l_returnflag = 'N') AS \"N\", count(*) FILTER (l_returnflag = 'R') AS \"R\" FROM lineitem GROUP BY 1")
def _(s, d):
    return table(s, d, "lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).count().na.fill(0)


@query("agg_unpivot", "SELECT s_suppkey, 'key' AS what, s_suppkey::DOUBLE AS v FROM supplier UNION ALL SELECT s_suppkey, 'bal', s_acctbal FROM supplier")
def _(s, d):
    t = table(s, d, "supplier").select("s_suppkey", F.col("s_suppkey").cast("double").alias("key"), F.col("s_acctbal").alias("bal"))
    return t.unpivot("s_suppkey", ["key", "bal"], "what", "v")


@query("agg_collect", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names, arg_max(n_name, n_nationkey) AS last FROM nation GROUP BY 1")
def _(s, d):
    return table(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"), F.max_by("n_name", "n_nationkey").alias("last"))


@query("win_rank", C("F6").add("t", "SELECT router, core, count(DISTINCT opp) AS n FROM c GROUP BY ALL").select(
    "SELECT router, core, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr FROM t WINDOW w AS (PARTITION BY router ORDER BY n DESC) QUALIFY r <= 5"))
def _(s, d):
    t = E.exact_fanout(contacts(s, d, "F6"), ("router",))
    w = Window.partitionBy("router").orderBy(F.desc("fan_out"))
    out = t.select("router", "core", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"))
    return out.filter("r <= 5")


@query("win_ntile", "SELECT n_regionkey, n_nationkey, ntile(3) OVER (PARTITION BY n_regionkey ORDER BY n_nationkey) AS part, row_number() OVER (PARTITION BY n_regionkey ORDER BY n_nationkey) AS nth FROM nation")
def _(s, d):
    w = Window.partitionBy("n_regionkey").orderBy("n_nationkey")
    return table(s, d, "nation").select("n_regionkey", "n_nationkey", F.ntile(3).over(w).cast("long").alias("part"), F.row_number().over(w).cast("long").alias("nth"))


@query("win_lag_lead", """SELECT event_id, lag(event_id) OVER w AS p, lead(event_id) OVER w AS n, first_value(event_id) OVER w AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def _(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("p"), F.lead("event_id").over(w).alias("n"), F.first("event_id").over(w).alias("f"))


@query("win_nth", """SELECT event_id, last_value(event_id) OVER w AS l, nth_value(event_id, 3) OVER w AS third FROM events
    WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def _(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(s, d, "events").select("event_id", F.last("event_id").over(w).alias("l"), F.nth_value("event_id", 3).over(w).alias("third"))


@query("topk_offset", C("F6").add("t", S.fan("c")).select("SELECT * FROM t ORDER BY fan_out DESC, core LIMIT 20 OFFSET 10"))
def _(s, d):
    return E.exact_fanout(contacts(s, d, "F6")).orderBy(F.desc("fan_out"), "core").offset(10).limit(20)


@query("agg_percentile", "SELECT event_type, min(value) FILTER (c >= 0.5) AS median, min(value) FILTER (c >= 0.9) AS high FROM (SELECT event_type, value, cume_dist() OVER (PARTITION BY event_type ORDER BY value) AS c FROM events WHERE value IS NOT NULL) GROUP BY event_type")
def _(s, d):
    at = F.percentile_approx("value", [0.5, 0.9], 1_000_000)  # exact for groups of up to so many values
    return table(s, d, "events").groupBy("event_type").agg(at.alias("p")).select("event_type", F.col("p")[0].alias("median"), F.col("p")[1].alias("high"))


@query("win_frames", C("F1").add("t", "SELECT core, slot, count(*) AS n FROM c GROUP BY ALL").select(
    "SELECT core, slot, sum(n) OVER (PARTITION BY core ORDER BY slot RANGE BETWEEN 299 PRECEDING AND CURRENT ROW)::BIGINT AS in_window, sum(n) OVER (PARTITION BY core ORDER BY slot)::BIGINT AS so_far FROM t"))
def _(s, d):
    t = contacts(s, d, "F1").groupBy("core", "slot").agg(F.count("*").alias("n"))
    w = Window.partitionBy("core").orderBy("slot")
    return t.select("core", "slot", F.sum("n").over(w.rangeBetween(-299, 0)).alias("in_window"), F.sum("n").over(w).alias("so_far"))


def _heavy_blocks(s, d):
    h = E.exact_heavy_fixed(contacts(s, d, "F1"), theta(s, d, "F1"), F1_SPAN, EVENT_SLOTS)
    return h.filter("win = 0").select("core"), h.filter("win = 1").select("core")


_B01 = C("F1").add("x", S.fixed("c", 3600, 300)).add("t", S.fan("x", ("win",))).add("a", f"SELECT core FROM t WHERE win = 0 AND fan_out >= {T1}").add("b", f"SELECT core FROM t WHERE win = 1 AND fan_out >= {T1}")


@query("set_union", _B01.select("SELECT core FROM a UNION SELECT core FROM b"))
def _(s, d):
    a, b = _heavy_blocks(s, d)
    return a.union(b).distinct()


@query("set_intersect", _B01.select("SELECT core FROM a INTERSECT SELECT core FROM b"))
def _(s, d):
    a, b = _heavy_blocks(s, d)
    return a.intersect(b)


@query("set_except", _B01.select("SELECT core FROM a EXCEPT SELECT core FROM b"))
def _(s, d):
    a, b = _heavy_blocks(s, d)
    return a.exceptAll(b)


@query("fn_math", "SELECT s_suppkey, round(ln(s_suppkey + 1), 6) AS l, round(exp(-s_suppkey / 100.0), 6) AS e, s_suppkey % 7 AS m, greatest(s_suppkey, 50) AS g, least(s_suppkey, 50) AS le, round(sqrt(s_suppkey), 6) AS q, floor(s_acctbal)::BIGINT AS f FROM supplier")
def _(s, d):
    k = F.col("s_suppkey")
    return table(s, d, "supplier").select(
        "s_suppkey", F.round(F.log(k + 1), 6).alias("l"), F.round(F.exp(-k / 100.0), 6).alias("e"), F.pmod(k, F.lit(7)).alias("m"), F.greatest(k, F.lit(50)).alias("g"),
        F.least(k, F.lit(50)).alias("le"), F.round(F.sqrt(k), 6).alias("q"), F.floor("s_acctbal").alias("f"),
    )


@query("fn_bits", "SELECT c_custkey, xor(c_custkey, 12345) AS x, c_custkey & 255 AS a, c_custkey | 256 AS o, c_custkey >> 3 AS r, c_custkey << 3 AS l, bit_count(c_custkey)::BIGINT AS n, lower(to_hex(c_custkey)) AS h FROM customer")
def _(s, d):
    k = F.col("c_custkey")
    return table(s, d, "customer").select(
        "c_custkey", k.bitwiseXOR(12345).alias("x"), k.bitwiseAND(255).alias("a"), k.bitwiseOR(256).alias("o"), F.shiftright(k, 3).alias("r"), F.shiftleft(k, 3).alias("l"),
        F.bit_count(k).cast("long").alias("n"), F.lower(F.hex(k)).alias("h"),
    )


@query("fn_string", "SELECT n_nationkey, lower(n_name) AS l, substr(n_name, 2, 3) AS sub, md5(n_name) AS m, length(n_name) AS n, replace(n_name, 'A', '_') AS r, regexp_extract(n_name, '[A-Z]+', 0) AS w FROM nation")
def _(s, d):
    n = F.col("n_name")
    return table(s, d, "nation").select(
        "n_nationkey", F.lower(n).alias("l"), F.substring(n, 2, 3).alias("sub"), F.md5(n.cast("binary")).alias("m"), F.length(n).cast("long").alias("n"),
        F.replace(n, F.lit("A"), F.lit("_")).alias("r"), F.regexp_extract(n, "[A-Z]+", 0).alias("w"),
    )


@query("tok_doc_stream", C("F6").select("SELECT core, opp, slot FROM c"))
def _(s, d):
    return contacts(s, d, "F6").select("core", "opp", "slot")


@query("fn_date", "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m, datediff('day', DATE '1995-01-01', o_orderdate::DATE) AS n, extract(year FROM o_orderdate) AS y, o_orderdate + INTERVAL 30 DAY AS later FROM orders")
def _(s, d):
    o = F.col("o_orderdate")
    return table(s, d, "orders").select(
        "o_orderkey", F.date_trunc("month", o).cast("timestamp_ntz").alias("m"), F.datediff(o.cast("date"), F.lit("1995-01-01").cast("date")).cast("long").alias("n"),
        F.year(o).cast("long").alias("y"), (o + F.expr("INTERVAL 30 DAY")).alias("later"),
    )


@query("fn_array_sketch", C("F3").select(f"SELECT core, count(DISTINCT {S.rec('opp', 256)}) AS touched FROM c WHERE slot BETWEEN 39 AND 50 GROUP BY core"))
def _(s, d):
    dense = R.dense(R.touch(contacts(s, d, "F3").filter("slot <= 50"), 256), 50, 256)
    return dense.select("core", F.size(F.filter("ages", lambda a: a < 12)).cast("long").alias("touched")).filter("touched > 0")


@query("fn_map", C("F3").add("g", f"SELECT core, {S.rec('opp', 64)} AS rec, max(slot) AS last FROM c GROUP BY ALL").select("SELECT core, count(*) FILTER (last >= 80) AS young, max(last) AS newest FROM g GROUP BY core"))
def _(s, d):
    m = R.touch(contacts(s, d, "F3"), 64).groupBy("core").agg(F.map_from_entries(F.collect_list(F.struct("rec", "last_slot"))).alias("m"))
    return m.select("core", F.size(F.map_filter("m", lambda k, v: v >= 80)).cast("long").alias("young"), F.array_max(F.map_values("m")).alias("newest"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, '{\"k\":' || json_extract_string(props, '$.k') || '}' AS back FROM events")
def _(s, d):
    p = F.from_json("props", T.StructType([T.StructField("k", T.LongType())]))
    return table(s, d, "events").select("event_id", p["k"].alias("k"), F.to_json(p).alias("back"))


@query("fn_struct", C("F3").select("SELECT max(core) AS core, max(opp) AS opp FROM c"))
def _(s, d):
    c = contacts(s, d, "F3").select(F.named_struct(F.lit("core"), F.col("core"), F.lit("opp"), F.col("opp")).alias("pair"))
    return c.agg(F.max("pair.core").alias("core"), F.max("pair.opp").alias("opp"))


@query("fn_ip_text", C("F3").select("SELECT DISTINCT core, (core >> 24) || '.' || ((core >> 16) & 255) || '.' || ((core >> 8) & 255) || '.' || (core & 255) AS ip, core AS back FROM c"))
def _(s, d):
    t = contacts(s, d, "F3").select("core").distinct().withColumn("ip", H.long_to_ip(F.col("core")))
    return t.withColumn("back", H.ip_to_long(F.col("ip")))


def _mixed_py(x: int, consts: tuple[int, int, int, int]) -> int:
    h = (x * consts[0] + consts[1]) % H.PRIME
    return ((h ^ (h >> 15)) * consts[2] + consts[3]) % H.PRIME


@query("udf_hash_parity", C("F1").select(f"SELECT DISTINCT opp, {S.rec('opp', 1024)} AS native, {S.rec('opp', 1024)} AS udf FROM c"))
def _(s, d):
    own = F.pandas_udf(lambda x: pd.Series([_mixed_py(v, H.RECORDER) % 1024 for v in x.tolist()], dtype="int64"), "long")
    return contacts(s, d, "F1").select("opp").distinct().select("opp", H.rec_hash(F.col("opp"), 1024).alias("native"), own("opp").alias("udf"))


@query("udaf_estimate", C("F1").select(f"SELECT core, {S.est(1024)} AS est FROM (SELECT core, count(DISTINCT {S.rec('opp', 1024)}) AS touched FROM c GROUP BY core)"))
def _(s, d):
    @F.pandas_udf("long")
    def distinct(v: pd.Series) -> int:
        return int(v.nunique())

    marks = contacts(s, d, "F1").select("core", H.rec_hash(F.col("opp"), 1024).alias("rec")).distinct()
    return marks.groupBy("core").agg(distinct("rec").alias("touched")).select("core", H.estimate(F.col("touched"), 1024).alias("est"))


@query("udtf_touches", C("F1").select(S.grid("c", W6)))
def _(s, d):
    p = WIDE

    class Touches:
        def eval(self, core: int, rec: int):
            root = _mixed_py(core, H.ROOT) & p.mask
            yield 0, root, rec
            for i in range(1, p.r):
                yield i, ((core >> p.shift(i)) ^ root) & p.mask, rec

    s.udtf.register("fanout_touches", F.udtf(Touches, returnType="row_id bigint, col_id bigint, rec bigint"))
    contacts(s, d, "F1").select("core", H.rec_hash(F.col("opp"), p.m).alias("rec"), "slot").groupBy("core", "rec").agg(F.max("slot").alias("slot")).createOrReplaceTempView("fanout_marks")
    return s.sql("SELECT t.row_id, t.col_id, t.rec, max(m.slot) AS last_slot FROM fanout_marks m, LATERAL fanout_touches(m.core, m.rec) t GROUP BY ALL")


@query("udtf_chains", C("F1").add("g", S.grid("c", _FEW)).add("h", S.hot("g", _FEW)).select(S.chains("h", _FEW)))
def _(s, d):
    state, p = _few(s, d)
    hot = stored(G.hot_cells(state, p))

    class Chains:
        """All chains that grow from one hot cell of row 0, one at a time."""

        def eval(self, c0: int, rows: list):
            stack = [(c0,)]
            while stack:
                chain = stack.pop()
                i = len(chain)
                if i == p.r:
                    yield chain
                    continue
                low = ((chain[-1] ^ c0) >> p.d) ^ (c0 & p.overlap_mask)
                stack += [(*chain, c) for c in rows[i] if i == 1 or c & p.overlap_mask == low]

    s.udtf.register("fanout_chains", F.udtf(Chains, returnType=", ".join(f"c{i} bigint" for i in range(p.r))))
    lists = hot.groupBy().agg(*(F.collect_list(F.when(F.col("row_id") == i, F.col("col_id"))).alias(f"r{i}") for i in range(p.r)))  # at most 2^w a row
    hot.filter("row_id = 0").select("col_id").createOrReplaceTempView("fanout_roots")
    lists.select(F.array(*(f"r{i}" for i in range(p.r))).alias("rows")).createOrReplaceTempView("fanout_rows")
    return s.sql("SELECT t.* FROM fanout_roots, fanout_rows, LATERAL fanout_chains(col_id, rows) t")


@query("sql_surface", C("F3").select(f"""SELECT core, count(DISTINCT {S.rec('opp', 2048)}) AS touched, {S.est(2048, f"count(DISTINCT {S.rec('opp', 2048)})")} AS est,
    count(DISTINCT {S.rec('opp', 2048)}) >= {WIDE.with_(theta=540).cutoff!r} AS hot FROM c GROUP BY core"""))
def _(s, d):
    register(s)
    contacts(s, d, "F3").createOrReplaceTempView("fanout_contacts")
    return s.sql(
        """SELECT core, touched, fanout_estimate(touched, 2048) AS est, touched >= hot_cutoff(2048, 540) AS hot
        FROM (SELECT core, count(DISTINCT rec_hash(opp, 2048)) AS touched FROM fanout_contacts GROUP BY core)"""
    )
