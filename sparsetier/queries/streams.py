"""Streams drained over the events and orders tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from sparsetier.plans import products as M
from sparsetier.queries.base import OP, USQUARE, add
from sparsetier.sources import matrices as S
from sparsetier.store import Scratch
from sparsetier.streaming import streams as N


def _incremental(s, d):
    entries = N.source(s, d, "orders").where("o_custkey is not null").select(F.col("o_custkey").alias("i"), F.col("o_orderkey").alias("j"), F.lit(1).cast("long").alias("v"))
    return N.newest(N.drained(N.incremental_product(entries, S.order_part(s, d)), "update"), ["i", "j"])


def _squares(s, d):
    scratch = Scratch(s)
    out, n = scratch.path("squares"), S._size(s, d, "events", "user_id")
    N.daily_squares(N.events(s, d), M.relational, n, out, scratch.path("stream_state"))
    return s.read.parquet(out).groupBy("i", "j").agg(F.sum("v").alias("v"))


add("n1_incremental_product", _incremental, f"with {OP} select o_custkey i, j, cast(sum(v) as bigint) v from orders join op on o_orderkey = i group by 1, 2")
add("n2_tumbling", lambda s, d: N.drained(N.tumbling(N.events(s, d)), "complete"), "select cast(epoch(date_trunc('day', ts)) as bigint) \"day\", user_id, count(*) n from events group by 1, 2")
add("n2_window_squares", _squares, USQUARE + "select * from c")
add("n3_sliding", lambda s, d: N.drained(N.sliding(N.events(s, d)), "complete"),
    "select cast(epoch(date_trunc('hour', ts)) as bigint) - 3600 * k \"start\", event_type, count(*) n from events, (values (0), (1)) s(k) group by 1, 2")
add("n4_sessions", lambda s, d: N.drained(N.sessions(N.events(s, d)), "complete"),
    "select user_id, epoch_us(min(ts)) \"start\", count(*) n from (select *, sum(case when gap <= 1800000000 then 0 else 1 end) over (partition by user_id order by ts, event_id) g from "
    "(select *, coalesce(epoch_us(ts) - epoch_us(lag(ts) over (partition by user_id order by ts, event_id)), 9000000000) gap from events)) group by user_id, g")
add("n5_watermark", lambda s, d: N.drained(N.closed_days(N.events(s, d)), "append").select("day", "n"),
    "select * from (select cast(epoch(date_trunc('day', ts)) as bigint) \"day\", count(*) n from events group by 1) where \"day\" + 86400 <= (select epoch(max(ts)) - 86400 from events)")
add("n6_without_repeats", lambda s, d: N.drained(N.without_repeats(N.events(s, d).unionByName(N.events(s, d))), "append").select("event_id", "user_id"), "select event_id, user_id from events")
add("n7_click_then_purchase", lambda s, d: N.drained(N.click_then_purchase(N.events(s, d), N.events(s, d)), "append"),
    "select c.event_id click, p.event_id purchase, p.user_id from events c join events p on c.user_id = p.user_id and p.ts >= c.ts and p.ts <= c.ts + interval 1 hour where c.event_type = 'click' and p.event_type = 'purchase'")
add("n8_running_histogram", lambda s, d: N.newest(N.drained(N.running_histogram(N.events(s, d)), "update"), ["chunk"]), "select user_id >> 4 chunk, count(*) n from events where user_id is not null group by 1")
add("n9_restart", lambda s, d: N.run_twice(N.events(s, d).select("event_id")), "select 1::bigint run, count(*) n from events union all select 2, 0")
