"""Queries over streams: each runs a stream to its end and returns what it wrote."""

from __future__ import annotations

from pyspark.sql import functions as F

from .catalogue import DEPTH, K, NODES, TABLES, WIDTH, asked, cells, doc_sets
from .functions import hashing
from .operators import search as S
from .oracle import Build
from .registry import add
from .sources.shared import stored
from .sources.tables import load
from .streaming import growth as G

MICRO = 1_000_000
#: The watermark after one batch: whole milliseconds, ten minutes behind the latest event.
MARK = "(SELECT (max(epoch_us(ts)) // 1000 - 600000) * 1000 FROM events)"
GAP = 7200 * MICRO
CENTS = "CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) cents"


def window_sql(length: int, step: int) -> str:
    moves = f"unnest(range({length // step}))"
    return f"""SELECT b // {MICRO} start_s, (b + {length * MICRO}) // {MICRO} end_s, event_type, count(*) n, {CENTS}
      FROM (SELECT event_type, value, (epoch_us(ts) // {step * MICRO} - {moves}) * {step * MICRO} b FROM events WHERE ts IS NOT NULL)
      WHERE b + {length * MICRO} <= {MARK} GROUP BY ALL"""


SESSIONS = f"""WITH e AS (SELECT event_type, value, epoch_us(ts) t FROM events WHERE ts IS NOT NULL),
  g AS (SELECT *, CASE WHEN t - lag(t) OVER w <= {GAP} THEN 0 ELSE 1 END fresh FROM e WINDOW w AS (PARTITION BY event_type ORDER BY t)),
  s AS (SELECT *, sum(fresh) OVER (PARTITION BY event_type ORDER BY t) k FROM g)
  SELECT min(t) // {MICRO} start_s, (max(t) + {GAP}) // {MICRO} end_s, event_type, count(*) n, {CENTS} FROM s GROUP BY event_type, k HAVING max(t) + {GAP} <= {MARK}"""


def events(s, d):
    return G.timed_events(G.follow(s, f"{d}/events.parquet"))


add("st02_tumbling", window_sql(86400, 86400))(lambda s, d: G.drain(G.windowed(events(s, d), G.tumbling()), "tumbling"))
add("st02_sliding", window_sql(86400, 43200))(lambda s, d: G.drain(G.windowed(events(s, d), G.sliding()), "sliding"))
add("st02_session", SESSIONS)(lambda s, d: G.drain(G.windowed(events(s, d), G.session()), "session"))
add("st03_distinct_types", "SELECT count(DISTINCT (user_id, event_type)) kept FROM events")(lambda s, d: G.drain(G.distinct_arrivals(events(s, d).select("at", "user_id", "event_type"), ["user_id", "event_type"]), "distinct").agg(F.count("*").alias("kept")))


def late(s, d):
    """The newer half in two files, then the older half: rows behind the watermark of an earlier batch are dropped, and counted by difference."""
    rows = load(s, d, "events").where("ts is not null").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    middle = rows.agg(F.expr("(min(us) + max(us)) div 2")).first()[0]
    old, tenth = F.col("us") < F.lit(middle), F.col("event_id") % 10 == 0
    path = G.shared_folder(s, "late")
    for part in (rows.where(~old & ~tenth), rows.where(~old & tenth), rows.where(old)):
        part.drop("us").coalesce(1).write.mode("append").parquet(path)
    stream = G.timed_events(G.follow(s, path, files_per_batch=1))
    got = G.drain(G.windowed(stream, G.tumbling()), "late").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("counted"))
    return got.crossJoin(rows.agg(F.count("*").alias("arrived"), F.sum(old.cast("long")).alias("late")))


LATE = f"""WITH e AS (SELECT epoch_us(ts) t FROM events WHERE ts IS NOT NULL), m AS (SELECT (min(t) + max(t)) // 2 c FROM e)
  SELECT count(*) FILTER (t >= c AND (t // {86400 * MICRO} + 1) * {86400 * MICRO} <= {MARK}) counted, count(*) arrived, count(*) FILTER (t < c) late FROM e, m"""
add("st04_late_data", LATE)(late)


def bucketed_stream(s, d):
    """Documents as a stream of files, hashed to bucket rows as they come: narrow, no state."""
    return G.follow(s, f"{d}/documents.parquet")


def growing_index(s, d):
    from .functions.features import token_sets

    b = S.build_bucket_index(token_sets(bucketed_stream(s, d), "doc_id", "text"), K, TABLES, NODES)
    return b, ["node", "table_id", "bucket_key"]


def grown_cells(s, d):
    """Cells as the stream has them at its end; each must equal the batch build's."""
    b, keys = growing_index(s, d)
    out = G.drain(G.stream_cells(b, keys, DEPTH, WIDTH), "cells", "update")
    return G.latest(out, [*keys, "row", "col"])


add("s14_stream_cells", Build().buckets(K, TABLES, NODES).cells(DEPTH, WIDTH).select('SELECT table_id, bucket_key, node, "row", col, total, cand, votes FROM cells'))(grown_cells)
EV = Build("SELECT user_id id, event_type token FROM events WHERE user_id IS NOT NULL")


def votes(s, d, parts=4):
    """Arrival-order votes over a history replayed in files; totals are those of the batch count."""
    rows = load(s, d, "events").where("user_id is not null and ts is not null")
    path = G.in_files(rows, "ts", parts, "history")
    stream = G.follow(s, path, files_per_batch=1).select("event_type", F.col("user_id").alias("id"))
    return G.latest(G.drain(G.stream_votes(stream, "event_type", 2, 64), "votes", "update"), ["key", "row", "col"])


add("st03_stream_votes")(votes)
add("w16_stream_totals", EV.add("ev", "SELECT id, token event_type FROM sets").add("sp", EV.spread("ev", 2, 64)).select('SELECT event_type AS key, "row", col, count(*) total FROM sp GROUP BY ALL'))(lambda s, d: votes(s, d).select("key", "row", "col", "total"))


def online(s, d):
    """Queries that arrive as a stream, against a stored index: each batch is one search."""
    from .functions.features import token_sets

    rows = doc_sets(s, d)
    index = stored(cells(s, d), "index")
    wanted = asked(rows).select("id")
    stream = token_sets(G.follow(s, f"{d}/documents.parquet"), "doc_id", "text")

    def answer(batch):
        keys = S.hash_queries(batch.join(wanted, "id", "left_semi"), K, TABLES)
        return S.answer(S.global_merge(S.local_merge(keys, index), NODES, "tree"), 10, DEPTH, WIDTH)

    return G.drain(stream, "online", then=answer).select("query_id", "rank", "id", "votes", "upper")


add("st05_stream_static_search", Build().buckets(K, TABLES, NODES).cells(DEPTH, WIDTH).queries().local().tree(NODES).top(10, DEPTH, WIDTH).select('SELECT query_id, "rank", id, votes, upper FROM answers'))(online)
