"""Queries of the streaming extensions."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators.counting import count_groups
from ..operators.segment import hexed
from ..session import fresh_path
from ..sources.io import table
from ..streaming import streams as T
from . import sql as S
from .core_queries import TIGHT, docs, occ_of
from .registry import query


def _split(spark, d, files: int = 4):
    """Documents as several files, read as a stream, one file a trigger."""
    path = fresh_path(spark, "arrivals")
    x = docs(spark, d).select("doc_id", "text")
    x.repartition(files, "doc_id").write.parquet(path)
    return T.read_documents(spark, path, x.schema)


@query(f"WITH {S.occ_ctes()} SELECT * FROM grp")
def stream_counts(spark, d):
    return hexed(T.stream_counts(_split(spark, d)))


_STEP = f"CASE WHEN a < greatest(1, least(n, ceil(1.0::DOUBLE + (n * pow(1.0::DOUBLE - 1.0::DOUBLE / {2.0!r}::DOUBLE, n - 1) - 1) * {S.alpha('len')}))) THEN 1 ELSE 0 END"


@query(f"WITH {S.occ_ctes()} SELECT h, freq AS seen, list_reduce(list_prepend(0, range(1, freq + 1)), lambda a, n: a + {_STEP.replace('len', 'norm_len')})::BIGINT AS admitted FROM grp")
def stream_admit(spark, d):
    """Copies are admitted one after another; the copies of a group are alike, so only their number decides."""
    return T.stream_admit(_split(spark, d), TIGHT)


@query("SELECT count(*) AS texts FROM (SELECT DISTINCT text FROM documents)")
def stream_doc_dedup(spark, d):
    # all arrive within half an hour of a day, far above the watermark's start at the epoch
    stream = _split(spark, d).withColumn("arrived", F.timestamp_seconds(F.lit(1_700_000_000) + F.pmod("doc_id", F.lit(1800))))
    return T.run_to_table(T.stream_doc_dedup(stream), "stream-docs").agg(F.count("*").alias("texts"))


@query(f"WITH {S.occ_ctes()} SELECT doc_id, pos, h, freq FROM occ JOIN grp USING (h, norm_len)")
def stream_static(spark, d):
    groups = count_groups(occ_of(spark, d))
    return hexed(T.run_to_table(T.stream_static(_split(spark, d), groups), "stream-joined")).select("doc_id", "pos", "h", "freq")


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS events FROM events GROUP BY ALL")
def win_tumbling(spark, d):
    return table(spark, d, "events").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("events")).select(F.col("w.start").alias("start"), "event_type", "events")


@query("SELECT time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS start, count(*) AS events FROM events, range(2) r(k) GROUP BY ALL")
def win_sliding(spark, d):
    return table(spark, d, "events").groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("events")).select(F.col("w.start").alias("start"), "events")


@query("WITH f AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM f) SELECT user_id, min(ts) AS start, count(*) AS events FROM s GROUP BY user_id, k")
def win_session(spark, d):
    return table(spark, d, "events").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("events")).select("user_id", F.col("w.start").alias("start"), "events")
