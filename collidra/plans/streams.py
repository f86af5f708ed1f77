"""Stream queries: window and session counts, arrival into reservoirs, answers from a snapshot."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import streaming
from ..operators import features, index
from ..sources import read_stream, read_table, scratch
from . import core, sql
from . import workloads as w

QUERIES: dict = {}
ORACLES: dict = {}


def add(name: str, oracle: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return keep


def _events(s, d):
    return read_table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def _stream(s, d, name, max_files=1):
    return read_stream(s, d, name, read_table(s, d, name).schema, max_files)


def _plain(df):
    """Times as seconds, so that zones play no part."""
    return df.withColumn("start", F.unix_seconds("start"))


add("window_counts_tumbling", "SELECT epoch(date_trunc('day', ts))::BIGINT AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(lambda s, d: _plain(streaming.tumbling(_events(s, d))))
add("window_counts_sliding", "SELECT (b * 43200)::BIGINT AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([floor(epoch(ts) / 43200), floor(epoch(ts) / 43200) - 1]) AS b FROM events) GROUP BY 1, 2")(lambda s, d: _plain(streaming.sliding(_events(s, d))))
add("window_sessions", "SELECT user_id, min(floor(epoch(ts)))::BIGINT AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT *, (lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL OR ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 4 HOUR)::INT AS fresh FROM events)) GROUP BY user_id, g")(
    lambda s, d: _plain(streaming.sessions(_events(s, d)))
)


@add("sessions_sets", f"SELECT g AS item_id, count(DISTINCT f) AS n FROM (SELECT user_id * 100 + extract('day' FROM ts) AS g, {sql.fid('event_type')} AS f FROM events) GROUP BY 1")
def sessions_sets(s, d):
    """A user's day as a set of event types."""
    ev = _events(s, d).select((F.col("user_id") * 100 + F.dayofmonth("ts")).alias("item_id"), features.feature_id(F.col("event_type")).alias("f"))
    return ev.groupBy("item_id").agg(F.size(F.collect_set("f")).cast("long").alias("n"))


# The watermark is an hour behind the last event. It closes windows and sessions that end by then; append mode leaves the rest open.
_CLOSED = "(SELECT epoch(max(ts)) - 3600 FROM events)"
_TUMBLING = f"SELECT epoch(date_trunc('day', ts))::BIGINT AS start, event_type, count(*) AS n FROM events WHERE epoch(date_trunc('day', ts)) + 86400 <= {_CLOSED} GROUP BY 1, 2"
_SLIDING = f"SELECT (b * 43200)::BIGINT AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([floor(epoch(ts) / 43200), floor(epoch(ts) / 43200) - 1]) AS b FROM events) WHERE (b + 2) * 43200 <= {_CLOSED} GROUP BY 1, 2"
_SESSIONS = ORACLES["window_sessions"] + f" HAVING epoch(max(ts)) + 14400 <= {_CLOSED}"
add("stream_tumbling", _TUMBLING)(lambda s, d: _plain(streaming.run_to_table(streaming.tumbling(streaming.event_time(_stream(s, d, "events"))), scratch(s))))
add("stream_sliding", _SLIDING)(lambda s, d: _plain(streaming.run_to_table(streaming.sliding(streaming.event_time(_stream(s, d, "events"))), scratch(s))))
add("stream_session", _SESSIONS)(lambda s, d: _plain(streaming.run_to_table(streaming.sessions(streaming.event_time(_stream(s, d, "events"))), scratch(s))))


def _arriving(s, d, *parts: str):
    """The events as a stream of files in a given order: a file per condition, so some come again and some come late."""
    path, events = scratch(s), read_table(s, d, "events")
    for i, condition in enumerate(parts):
        events.where(condition).coalesce(1).write.parquet(f"{path}/{i}")
    files = s.read.parquet(*[f"{path}/{i}" for i in range(len(parts))]).inputFiles()
    fs = s.sparkContext._jvm.org.apache.hadoop.fs
    for i in range(len(parts)):
        at = fs.Path(next(f for f in files if f"/{i}/" in f))
        store = at.getFileSystem(s.sparkContext._jsc.hadoopConfiguration())
        store.mkdirs(fs.Path(f"{path}/in"))
        to = fs.Path(f"{path}/in/events{i}.parquet")
        store.rename(at, to)
        store.setTimes(to, 1_700_000_000_000 + 60_000 * i, -1)  # files are taken in the order of their times
    return read_stream(s, f"{path}/in", "events", events.schema)


@add("stream_dedup", "SELECT event_id FROM events")
def stream_dedup(s, d):
    """Half of the events are sent again and a third a third time; each is let through once."""
    replayed = _arriving(s, d, "event_id % 2 = 0", "true", "event_id % 3 = 0")
    return streaming.run_to_table(streaming.deduplicated(streaming.event_time(replayed, "60 days")).select("event_id"), scratch(s))


add("stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")(
    lambda s, d: streaming.run_to_table(_stream(s, d, "events").join(read_table(s, d, "customer", ["c_custkey", "c_mktsegment"]), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"), scratch(s))
)


@add("stream_late", "SELECT event_id FROM events WHERE event_id % 4 <> 0 OR ts > (SELECT max(ts) FROM events WHERE event_id % 4 IN (1, 2)) - INTERVAL 2 DAY")
def stream_late(s, d):
    """A quarter of the events come after all others; those more than two days behind are too late to be told from replays.

    What counts as late is decided by the watermark of the batch before, so that of the first file applies to the third.
    """
    late = _arriving(s, d, "event_id % 4 IN (1, 2)", "event_id % 4 = 3", "event_id % 4 = 0")
    return streaming.run_to_table(streaming.deduplicated(streaming.event_time(late, "2 days")).select("event_id"), scratch(s))


@add("stream_reservoir", core.ORACLES["reservoir_priority"])
def stream_reservoir(s, d):
    """Documents arriving as a stream fill the same reservoirs as one build over all of them."""
    sets = features.token_set(_stream(s, d, "documents", 16), "doc_id", "text")  # a batch visits nearly all buckets, however few its rows
    out = streaming.run_to_table(streaming.arrivals(sets, core.HEAVY), scratch(s), "update", ("table_id", "address"), "seen")
    return out.select("table_id", "address", "seen", F.explode("members").alias("item_id"))


@add("stream_queries", core.ORACLES["knn_query_benchmark"])
def stream_queries(s, d):
    """Benchmark passages arriving as a stream are answered from a snapshot of the index of the documents."""
    path = scratch(s)
    index.build_index(w.docs_words(s, d), w.sized(s, d, "docs_words", core.BASE)).save(f"{path}/index", 8)
    asked = features.token_set(_stream(s, d, "benchmark"), "item_id", "text")
    return streaming.answer_stream(asked, index.Index.load(s, f"{path}/index"), 5, f"{path}/answers")
