"""Streaming queries: each runs over the files there and must equal batch SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from voxtable.operators.segment import SECOND
from voxtable.registry import query
from voxtable.sources.tables import load
from voxtable.streaming import frames as st

DAY, HOUR = 86_400_000_000, 3_600_000_000
EV = "WITH ev AS (SELECT *, epoch_us(ts) AS us FROM events)"
SESSIONS = "{cte}, b AS (SELECT user_id, event_id, us, CASE WHEN us - lag(us) OVER w >= 43200000000 OR lag(us) OVER w IS NULL THEN 1 ELSE 0 END AS b FROM ev {where} WINDOW w AS (PARTITION BY user_id ORDER BY us, event_id)), s AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY us, event_id) AS k FROM b) SELECT user_id, min(us) AS us0, max(us) AS us1, count(*) AS n FROM s GROUP BY user_id, k"


@query("st_tumbling", EV + f" SELECT us // {DAY} * {DAY} AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM ev GROUP BY 1, 2")
def st_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.finished(st.tumbling(st.events(spark, sf_dir))).withColumn("total", F.round("total", 4))


@query("st_sliding", EV + f" SELECT (us // {DAY} - d) * {DAY} AS start, count(*) AS n FROM ev, (VALUES (0), (1)) AS x(d) GROUP BY 1")
def st_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.finished(st.sliding(st.events(spark, sf_dir)))


@query("st_session", SESSIONS.format(cte=EV, where=""))
def st_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.finished(st.sessions(st.events(spark, sf_dir)))


@query("w25_streaming_segments", SESSIONS.format(cte=EV, where="WHERE event_type <> 'error'"))
def w25_streaming_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.finished(st.sessions(st.events(spark, sf_dir).filter("event_type <> 'error'")))


@query("st_late", EV + f" SELECT us // {DAY} * {DAY} AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM ev GROUP BY 1, 2 HAVING us // {DAY} * {DAY} + {DAY} <= (SELECT max(us) FROM ev) - {DAY}".replace("HAVING us //", "HAVING any_value(us) //"))
def st_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Append mode: only windows that the watermark has passed are out; later rows for them would be dropped."""
    return st.finished(st.tumbling(st.events(spark, sf_dir)), "append").withColumn("total", F.round("total", 4))


CAPPED = f"""WITH RECURSIVE ev AS (SELECT event_id, user_id, epoch_us(ts) AS us, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i FROM events), k AS (SELECT event_id, user_id, i, us AS t0, 0 AS piece FROM ev WHERE i = 1
 UNION ALL SELECT ev.event_id, ev.user_id, ev.i, CASE WHEN ev.us - k.t0 >= {30 * SECOND} THEN ev.us ELSE k.t0 END, CASE WHEN ev.us - k.t0 >= {30 * SECOND} THEN k.piece + 1 ELSE k.piece END FROM k JOIN ev ON ev.user_id = k.user_id AND ev.i = k.i + 1) SELECT event_id, user_id, piece FROM k"""


@query("st_state", CAPPED)
def st_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.finished(st.capped(st.events(spark, sf_dir)), "append")


@query("st_dedup", "SELECT event_type, user_id FROM (SELECT DISTINCT event_type, user_id FROM events)")
def st_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.finished(st.deduplicated(st.events(spark, sf_dir, "400 days"), "event_type", "user_id"), "append").select("event_type", "user_id")


@query("st_join", "SELECT n_name, count(*) AS n FROM events JOIN nation ON user_id % 25 = n_nationkey GROUP BY 1")
def st_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.finished(st.enriched(st.events(spark, sf_dir), load(spark, sf_dir, "nation")))


@query("st_join_interval", EV + f" SELECT a.event_id AS signup, b.event_id AS purchase FROM ev a JOIN ev b ON a.user_id = b.user_id AND b.us BETWEEN a.us AND a.us + {HOUR} WHERE a.event_type = 'signup' AND b.event_type = 'purchase'")
def st_join_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.finished(st.followed(st.events(spark, sf_dir), st.events(spark, sf_dir)), "append")
