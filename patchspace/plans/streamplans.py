"""Streaming operators: batch twins with SQL, and streams drained over the same rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from patchspace.plans import core
from patchspace.plans.registry import query
from patchspace.shared import new_path, table
from patchspace.streaming import queries as st

EPOCH6 = "(epoch(ts)::BIGINT // 21600)"


def events(spark, sf_dir):
    return table(sf_dir, "events", spark).withColumn("ts", F.col("ts").cast("timestamp"))


def second(c):
    return F.unix_seconds(F.col(c))


TUMBLING = "SELECT user_id, (epoch(ts)::BIGINT // 21600) * 21600 AS start, count(*) AS n, sum(round(value * 100)::BIGINT)::BIGINT AS v FROM events GROUP BY ALL"


@query("event_tumbling", TUMBLING)
def event_tumbling(spark, sf_dir):
    return st.tumbling(events(spark, sf_dir)).select("user_id", second("start").alias("start"), "n", "v")


@query("event_sliding", "SELECT event_type, w AS start, count(*) AS n FROM (SELECT event_type, unnest([(epoch(ts)::BIGINT // 21600) * 21600, (epoch(ts)::BIGINT // 21600 - 1) * 21600]) AS w FROM events) GROUP BY ALL")
def event_sliding(spark, sf_dir):
    return st.sliding(events(spark, sf_dir)).select("event_type", second("start").alias("start"), "n")


@query("event_session", """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM e)
SELECT user_id, epoch_us(min(ts))::BIGINT AS start, epoch_us(max(ts))::BIGINT + 21600000000 AS finish, count(*) AS n FROM s GROUP BY user_id, g""")
def event_session(spark, sf_dir):
    s = st.sessions(events(spark, sf_dir))
    return s.select("user_id", F.unix_micros("start").alias("start"), F.unix_micros("end").alias("finish"), "n")


@query("stream_tumbling_complete", TUMBLING)
def stream_tumbling_complete(spark, sf_dir):
    """The stream's final state equals the batch; every batch replaces the table of the one before."""
    s = st.tumbling(st.events_stream(spark, sf_dir))
    path = new_path(spark, "complete")
    put = lambda batch, _: batch.write.mode("overwrite").parquet(f"{path}/out")
    q = s.writeStream.outputMode("complete").foreachBatch(put).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(s.schema).parquet(f"{path}/out").select("user_id", second("start").alias("start"), "n", "v")


@query("stream_tumbling_final", f"SELECT * FROM ({TUMBLING}) WHERE (start + 21600) * 1000 <= (SELECT epoch_ms(max(ts)) FROM events) - 86400000")
def stream_tumbling_final(spark, sf_dir):
    """Cells that the watermark has closed, in append mode."""
    return st.drain(st.tumbling(st.events_stream(spark, sf_dir))).select("user_id", second("start").alias("start"), "n", "v")


GAP_SQL = """WITH e AS (SELECT DISTINCT user_id, (datediff('day', DATE '2024-01-01', ts::DATE) * 4 + hour(ts) // 6)::INTEGER AS slot FROM events),
w AS (SELECT (epoch_ms(max(ts)) - 86400000) // 21600000 - 1704067200000 // 21600000 AS mark FROM events),
n AS (SELECT user_id, slot, lead(slot) OVER (PARTITION BY user_id ORDER BY slot) AS following FROM e)
SELECT user_id, unnest(range(slot + 1, following))::INTEGER AS slot FROM n, w WHERE following > slot + 1 AND following < mark"""


@query("stream_gaps", GAP_SQL)
def stream_gaps(spark, sf_dir):
    """Gaps between slots that the watermark has closed by the end."""
    return st.drain(st.gaps(st.events_stream(spark, sf_dir)))


def served(spark, sf_dir, exact):
    from patchspace.operators import zindex

    d = core.dictionary(spark, sf_dir)
    path = new_path(spark, "arriving")
    q = core.queries_of(d).withColumn("ts", F.timestamp_seconds(F.col("query_id") + 1_700_000_000))
    q.repartition(2).write.parquet(path)
    index = zindex.build_index(d, core.FPS, core.K, 10, core.MU)
    stream = spark.readStream.schema(q.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return st.serve(st.distinct_queries(stream), index, d, 20, exact, exclude_radius=1)


@query("stream_query_serving")
def stream_query_serving(spark, sf_dir):
    """Arriving half-known patches answered by a saved index."""
    return served(spark, sf_dir, exact=False)


@query("stream_query_serving_exact", core.SQL_SCAN)
def stream_query_serving_exact(spark, sf_dir):
    """The same stream in exact mode: answers as of the full scan."""
    return served(spark, sf_dir, exact=True)


@query("index_increment", core.SQL_SCAN)
def index_increment(spark, sf_dir):
    """Even patches indexed, odd ones added as delta blocks; answers as for the whole index."""
    from patchspace.operators import knn, zindex

    d = core.dictionary(spark, sf_dir)
    index = zindex.build_index(d.where("patch_id % 2 = 0"), core.FPS, core.K, 10, core.MU)
    grown = st.add_to_index(index, d.where("patch_id % 2 = 1"), new_path(spark, "delta"))
    return knn.search(core.queries_of(d), grown, d, 10, exact=True, exclude_radius=1).select("query_id", "patch_id", "cost")
