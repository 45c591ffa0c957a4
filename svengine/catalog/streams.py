"""Queries over the gate feed as a stream."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions.bits import u6
from ..functions.shared import shared_folder
from ..plans.transpile import plan_blocks
from ..streaming import feed
from . import oracle as O
from . import query
from .plans import each_circuit
from .runs import _EV, _EVENTS_G, _zeros
from .states import amps, table


def _events(spark, sf_dir):
    return feed.event_stream(spark, f"{sf_dir}/events.parquet")


@query("SELECT CAST(floor(epoch(ts) / 86400) * 86400 AS BIGINT) AS start, event_type, count(*) AS gates FROM events GROUP BY ALL")
def stream_tumbling_gates(spark, sf_dir):
    return feed.last_batch(feed.drained(feed.tumbling_gates(_events(spark, sf_dir)), "complete"))


@query("SELECT CAST(floor(epoch(ts) / 86400) * 86400 - d * 86400 AS BIGINT) AS start, count(*) AS gates FROM events, range(2) t(d) GROUP BY ALL")
def stream_sliding_gates(spark, sf_dir):
    return feed.last_batch(feed.drained(feed.sliding_gates(_events(spark, sf_dir)), "complete"))


@query("""WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w > INTERVAL 12 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM e)
    SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS gates FROM s GROUP BY user_id, k""")
def stream_session_circuits(spark, sf_dir):
    return feed.last_batch(feed.drained(feed.session_circuits(_events(spark, sf_dir)), "complete"))


@query("SELECT event_type, count(DISTINCT event_id) AS gates FROM events GROUP BY event_type")
def stream_dedup(spark, sf_dir):
    """Every event sent twice; within the watermark the repeated ones are dropped."""
    e = _events(spark, sf_dir)
    twice = e.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy").withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return feed.drained(twice.select("event_id", "event_type"), "append").groupBy("event_type").agg(F.count(F.lit(1)).alias("gates"))


@query(f"SELECT event_id, {O.u6('value * f')} AS angle_u6 FROM events JOIN (VALUES ('click', 0.5), ('error', 0.25)) v(event_type, f) USING (event_type)")
def stream_static_join(spark, sf_dir):
    angles = spark.createDataFrame([("click", 0.5), ("error", 0.25)], "event_type string, f double")
    j = _events(spark, sf_dir).join(F.broadcast(angles), "event_type").select("event_id", (F.col("value") * F.col("f")).alias("a"))
    return feed.drained(j, "append").select("event_id", u6("a").alias("angle_u6"))


@query("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def stream_interval_join(spark, sf_dir):
    """Clicks with the user's purchases up to six hours later, stream with stream."""
    c = _events(spark, sf_dir).where("event_type = 'click'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t"))
    p = _events(spark, sf_dir).where("event_type = 'purchase'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("purchase"), "user_id", "ts")
    j = c.join(p, F.expr("u = user_id AND ts >= t AND ts <= t + INTERVAL 6 HOURS"))
    return feed.drained(j.select("click", "purchase"), "append").drop("batch")


def _gate_stream(events):
    e = events.withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    n, t = 6, F.col("event_type")
    q0, q1 = (F.col("k") % n).cast("int"), ((F.col("k") + 1 + F.col("user_id") % (n - 1)) % n).cast("int")
    theta, phi = F.col("value") / 500 * math.pi, F.col("k") * math.pi / 50
    kind = F.when(t == "view", "h").when(t == "click", "u3").when(t == "purchase", "cx").when(t == "error", "u1").otherwise("swap")
    qubits = F.when(t.isin("purchase", "signup"), F.array(q0, q1)).otherwise(F.array(q0))
    params = F.when(t == "click", F.array(theta, phi, F.lit(0.0))).when(t == "error", F.array(theta)).otherwise(F.array().cast("array<double>"))
    return e.select(F.col("user_id").alias("circuit_id"), F.col("event_id").alias("ord"), kind.alias("kind"), qubits.alias("qubits"), params.alias("params"))


@query(O.batch_loop(_zeros("SELECT DISTINCT user_id AS circuit_id FROM events", 6), _EVENTS_G, O.amps("fin", "circuit_id, idx"), _EV))
def stream_register_fold(spark, sf_dir):
    """A register for each user as the stream's state, folded gate by gate."""
    return amps(feed.newest(feed.drained(feed.fold_registers(_gate_stream(_events(spark, sf_dir)), 6), "update")), "circuit_id", "idx")


@query("SELECT user_id AS circuit_id, count(*) AS gates FROM events GROUP BY user_id")
def stream_foreachbatch_state(spark, sf_dir):
    """Each micro-batch plans the circuits of its gates where they meet, and counts what the plans' sections hold; batches add up. Two files, one a batch."""
    folder = shared_folder(spark, "feed")
    e = table(spark, sf_dir, "events")
    for part in (0, 1):
        e.where(F.col("event_id") % 2 == part).write.mode("append").parquet(f"{folder}/events.parquet")
    held = lambda c: [(sum(len(x.steps) for x in plan_blocks(c, 3, restore_order=False).sections),)]
    rows = feed.drained(_gate_stream(feed.event_stream(spark, f"{folder}/events.parquet", 1)), "append", "circuit_id long, gates long", lambda b, k: each_circuit(b, 6, held, "gates long"))
    return rows.groupBy("circuit_id").agg(F.sum("gates").alias("gates"))


@query("SELECT count(*) AS gates FROM events")
def stream_late_gates(spark, sf_dir):
    """Gates that come three days late in a second batch are dropped from the daily windows: the counts are those without them."""
    folder = shared_folder(spark, "late-feed")
    e = table(spark, sf_dir, "events")
    e.coalesce(1).write.parquet(f"{folder}/events.parquet")
    late = e.orderBy(F.desc("event_id")).limit(10).withColumn("ts", F.expr("ts - INTERVAL 20 DAYS"))
    end = e.agg(F.max("ts").alias("m")).first()["m"]
    marker = e.limit(1).withColumns({"ts": F.lit(end) + F.expr("INTERVAL 9 DAYS"), "event_type": F.lit("marker")})
    # a batch drops what is behind the watermark of the batch before it, which the first one has set for the one after the next
    e.limit(1).withColumns({"ts": F.lit(end), "event_type": F.lit("marker")}).write.mode("append").parquet(f"{folder}/events.parquet")
    late.unionByName(marker).coalesce(1).write.mode("append").parquet(f"{folder}/events.parquet")
    s = feed.event_stream(spark, f"{folder}/events.parquet", 1).withWatermark("ts", "1 hour")
    w = s.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("gates")).select("w.start", "event_type", "gates")
    return feed.drained(w, "append").where("event_type <> 'marker'").agg(F.sum("gates").alias("gates"))


@query("""SELECT event_type, CAST(count(*) * CASE event_type WHEN 'signup' THEN 2 ELSE 1 END AS BIGINT) AS in_time, CAST(CASE event_type WHEN 'error' THEN count(*) ELSE 0 END AS BIGINT) AS dead FROM events GROUP BY event_type""")
def stream_dead_letters(spark, sf_dir):
    """The feed, then in a second run signups sent again in time and errors sent again with times a thousand days back: those are dead letters."""
    folder = shared_folder(spark, "dead-feed")
    e = table(spark, sf_dir, "events")
    feed_ = feed.event_stream(spark, f"{folder}/in/events.parquet", 1_000_000)
    e.write.parquet(f"{folder}/in/events.parquet")
    feed.split_late(feed_, "365 DAYS", folder)
    again = e.where("event_type in ('signup', 'error')").withColumn("ts", F.expr("if(event_type = 'error', ts - INTERVAL 1000 DAYS, ts)"))
    again.write.mode("append").parquet(f"{folder}/in/events.parquet")
    rows = feed.split_late(feed_, "365 DAYS", folder)
    return rows.groupBy("event_type").agg(F.count_if(~F.col("late")).alias("in_time"), F.count_if("late").alias("dead"))
