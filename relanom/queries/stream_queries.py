"""Streams run to the end of their input, against batch oracles."""

from __future__ import annotations

from pyspark.sql import functions as F

from relanom import rules, streaming
from relanom.registry import query

_T = "strftime({}, '%Y-%m-%d %H:%M:%S')"


def _text(c):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


@query("stream_tumbling", f"SELECT {_T.format('date_trunc(chr(100) || chr(97) || chr(121), ts)')} AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2".replace("chr(100) || chr(97) || chr(121)", "'day'"))
def _tumbling(spark, sf_dir):
    return streaming.finished(streaming.windows(streaming.source(spark, sf_dir)), "complete", spark).select(_text("w.start").alias("start"), "event_type", "n")


@query("stream_sliding", f"SELECT {_T.format('s')} AS start, event_type, count(*)::BIGINT AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '2000-01-01'), time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '2000-01-01') - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY 1, 2")
def _sliding(spark, sf_dir):
    return streaming.finished(streaming.windows(streaming.source(spark, sf_dir), "sliding"), "complete", spark).select(_text("w.start").alias("start"), "event_type", "n")


@query("stream_session", f"WITH g AS (SELECT user_id, ts, (ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR)::INT AS new FROM events), s AS (SELECT *, sum(coalesce(new, 0)) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, {_T.format('min(ts)')} AS start, count(*)::BIGINT AS n FROM s GROUP BY user_id, k")
def _session(spark, sf_dir):
    return streaming.finished(streaming.windows(streaming.source(spark, sf_dir), "session"), "complete", spark).select("user_id", _text("w.start").alias("start"), "n")


@query("stream_novelty", "SELECT event_id, row_number() OVER (PARTITION BY user_id, json_extract_string(props, '$.k') ORDER BY ts, event_id) = 1 AS novel FROM events")
def _novelty(spark, sf_dir):
    return streaming.finished(streaming.novelty(streaming.source(spark, sf_dir)), "append", spark)


@query("stream_scores", "SELECT event_id, greatest(0.0, CASE WHEN value > 100 THEN 0.7 ELSE 0 END, CASE WHEN event_type = 'error' THEN 0.4 ELSE 0 END)::DOUBLE AS score FROM events")
def _scores(spark, sf_dir):
    frozen = rules.RuleSet(("value > 100", "event_type = 'error'"), (0.7, 0.4))
    return streaming.finished(streaming.scored(streaming.source(spark, sf_dir), frozen), "append", spark)


@query("stream_join", "SELECT a.event_id, b.event_id AS before_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 6 HOUR AND a.ts WHERE a.event_type IN ('signup', 'purchase') AND b.event_type = 'click'")
def _join(spark, sf_dir):
    return streaming.finished(streaming.joined_logs(streaming.source(spark, sf_dir), 360), "append", spark)
