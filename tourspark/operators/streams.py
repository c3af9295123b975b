"""Queries over streams; the batch SQL over the same rows is their oracle."""

from __future__ import annotations

from pyspark.sql import functions as F

from tourspark.functions.graph import Graph
from tourspark.functions.numbering import dense_number
from tourspark.operators.registry import query
from tourspark.plans import verify
from tourspark.plans.circuit import circuit
from tourspark.session import stage
from tourspark.streaming import events as ev

_HOUR = 3_600_000_000


def _stream(spark, sf_dir):
    return ev.stream_of(spark, ev.staged_copies(ev.halves(ev.rows_of(spark, sf_dir))))


@query("st_tumbling", f"SELECT CAST(epoch_us(ts) // {_HOUR} * {_HOUR} AS BIGINT) AS start, event_type, count(*) AS n, count(*) % 2 = 1 AS odd FROM events GROUP BY ALL")
def st_tumbling(spark, sf_dir):
    return ev.drain(ev.tumbling(_stream(spark, sf_dir)), "update", ["start", "event_type"])


@query("st_sliding", f"SELECT CAST(epoch_us(ts) // {6 * _HOUR} * {6 * _HOUR} - k * {6 * _HOUR} AS BIGINT) AS start, count(*) AS n FROM events, range(4) r(k) GROUP BY ALL")
def st_sliding(spark, sf_dir):
    return ev.drain(ev.sliding(_stream(spark, sf_dir)), "update", ["start"])


@query("st_session", """SELECT user_id, min(t) AS start, count(*) AS n FROM (SELECT user_id, t, sum(fresh) OVER (PARTITION BY user_id ORDER BY t, event_id) AS s FROM (
  SELECT user_id, event_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""")
def st_session(spark, sf_dir):
    return ev.drain(ev.sessions(_stream(spark, sf_dir)), "complete")


@query("st_dedup", "SELECT event_id, user_id FROM events")
def st_dedup(spark, sf_dir):
    rows = ev.rows_of(spark, sf_dir)
    return ev.drain(ev.deduplicated(ev.stream_of(spark, ev.staged_copies([rows, *ev.halves(rows)]))), "append")


@query("st_join", "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def st_join(spark, sf_dir):
    path = ev.staged_copies(ev.halves(ev.rows_of(spark, sf_dir)))
    clicks = ev.stream_of(spark, path).where("event_type = 'click'")
    buys = ev.stream_of(spark, path).where("event_type = 'purchase'")
    return ev.drain(ev.follow_ups(clicks, buys), "append")


@query("st_parity_state", "SELECT user_id AS v, count(*) AS degree, count(*) % 2 = 1 AS odd FROM events GROUP BY user_id")
def st_parity_state(spark, sf_dir):
    return ev.drain(ev.parity(_stream(spark, sf_dir)), "update", ["v"])


@query("st_late", f"SELECT CAST(epoch_us(ts) // {_HOUR} * {_HOUR} AS BIGINT) AS start, event_type, count(*) AS n, count(*) % 2 = 1 AS odd FROM events WHERE ts >= TIMESTAMP '2024-01-15' GROUP BY ALL")
def st_late(spark, sf_dir):
    """The later half comes first, whole in one batch; by the watermark of an hour all rows of
    the earlier half are then late and counted nowhere. (A batch judges lateness by the
    watermark that the batch before it ran with; the batch without rows that ends a run lies
    between.)"""
    rows = ev.rows_of(spark, sf_dir)
    mid = F.lit("2024-01-15").cast("timestamp")
    stream, steps = ev.stream_in_steps([rows.where(F.col("ts") >= mid), rows.where(F.col("ts") < mid)], "1 hour")
    return ev.drain(ev.tumbling(stream), "update", ["start", "event_type"], steps)


@query("st_static_join", "SELECT CAST(user_id % 8 AS INTEGER) AS part, count(*) AS n FROM events GROUP BY ALL")
def st_static_join(spark, sf_dir):
    parts = ev.rows_of(spark, sf_dir).select(F.col("user_id").alias("v"), (F.col("user_id") % 8).cast("int").alias("part")).distinct()
    return ev.drain(ev.with_parts(_stream(spark, sf_dir), parts), "update", ["part"])


_SHIFT = 1 << 32


def day_circuits(rows):
    """day, n_edges, chained, closed: the circuit of each day's users, all days as components
    of one graph whose vertices carry the day in their upper bits."""
    days = rows.select(F.struct("day", F.col("user_id").alias("u")).alias("w"), "day", "ts", "event_id")
    numbered = dense_number(days, ["day", "ts", "event_id"], "n", 0)
    vertex = F.col("w.day") * _SHIFT + F.col("w.u")
    here = numbered.select("n", "day", vertex.alias("u"))
    after = numbered.select((F.col("n") - 1).alias("n"), F.col("day").alias("next"), vertex.alias("v"))
    steps = here.join(after, "n").where("day = next").select("u", "v")
    ends = numbered.groupBy("day").agg(F.max_by(vertex, "n").alias("u"), F.min_by(vertex, "n").alias("v")).select("u", "v")
    g = Graph.from_edges(steps.unionByName(ends)).with_partition("modulo", 4)
    g = g.map_edges(stage(g.edges, "window"))
    made = verify.audit(g, stage(circuit(g, check=False), "window-circuit"))
    return made.select(F.expr(f"comp div {_SHIFT}").alias("day"), "n_edges", "chained", "closed")


@query("st_circuit_of_windows", "SELECT CAST(epoch(CAST(ts AS DATE)) // 86400 AS BIGINT) AS day, count(*) AS n_edges, true AS chained, true AS closed FROM events GROUP BY ALL")
def st_circuit_of_windows(spark, sf_dir):
    """Each day is a window; when it is closed its circuit is built. The batches are cut at a
    noon, so one day's rows come in two."""
    rows = ev.rows_of(spark, sf_dir)
    noon = F.lit("2024-01-15 12:00:00").cast("timestamp")
    stream, steps = ev.stream_in_steps([rows.where(F.col("ts") < noon), rows.where(F.col("ts") >= noon)])
    return ev.circuits_of_days(stream, day_circuits, steps=steps)[0]
