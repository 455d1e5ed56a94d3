"""Streaming queries drained to tables. Windows are drained in complete mode, which also gives those that are still open at the end."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltahop import streaming as st
from deltahop.graphs import table
from deltahop.queries.registry import mix, query


def static(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("bigint").alias("item"))


K = "CAST(json_extract_string(props, '$.k') AS BIGINT)"
query("stream_edge_ingest", f"SELECT user_id * 16 AS src_id, event_type AS rel, {K} * 16 + 9 AS dst_id, ts FROM events")(
    lambda s, d: st.drain(st.as_edges(st.edge_stream(s, d)), "ingest").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
)
query("stream_dedupe", "SELECT DISTINCT event_id, user_id FROM events")(lambda s, d: st.drain(st.dedupe(st.edge_stream(s, d).union(st.edge_stream(s, d))), "dedupe").select("event_id", "user_id"))
query("stream_tumbling", "SELECT time_bucket(INTERVAL 1 DAY, ts)::TIMESTAMP AS start, time_bucket(INTERVAL 1 DAY, ts)::TIMESTAMP + INTERVAL 1 DAY AS \"end\", count(*) AS n FROM events GROUP BY ALL")(lambda s, d: st.drain(st.tumbling(st.edge_stream(s, d)), "tumbling", "complete"))
query("stream_sliding", "SELECT time_bucket(INTERVAL 6 HOURS, ts)::TIMESTAMP - k * INTERVAL 6 HOURS AS start, time_bucket(INTERVAL 6 HOURS, ts)::TIMESTAMP - k * INTERVAL 6 HOURS + INTERVAL 1 DAY AS \"end\", count(*) AS n FROM events, range(4) t(k) GROUP BY ALL")(lambda s, d: st.drain(st.sliding(st.edge_stream(s, d)), "sliding", "complete"))
query(
    "stream_session",
    """WITH a AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOURS OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
b AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM a) SELECT min(ts) AS start, max(ts) + INTERVAL 6 HOURS AS "end", user_id, count(*) AS n FROM b GROUP BY user_id, g""",
)(lambda s, d: st.drain(st.sessions(st.edge_stream(s, d)), "sessions", "complete"))
query("stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")(lambda s, d: st.drain(st.with_customers(st.edge_stream(s, d), table(s, d, "customer")).select("event_id", "c_mktsegment"), "static"))
query("stream_interval_join", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts < c.ts + INTERVAL 1 HOUR")(
    lambda s, d: st.drain(st.click_to_purchase(st.edge_stream(s, d)), "interval")
)
query(
    "stream_degree_state",
    f"""WITH e AS (SELECT user_id, {K} AS item FROM events), d AS (SELECT user_id, count(*) AS degree FROM e GROUP BY 1),
r AS (SELECT user_id, item, {mix('user_id * 1000 + item', 5)} AS p, row_number() OVER (PARTITION BY user_id ORDER BY {mix('user_id * 1000 + item', 5)}, item) AS k FROM (SELECT DISTINCT user_id, item FROM e))
SELECT d.user_id, d.degree, string_agg(CAST(r.item AS VARCHAR), ',' ORDER BY r.p, r.item) AS sample FROM d JOIN r USING (user_id) WHERE r.k <= 5 GROUP BY ALL""",
)(lambda s, d: st.drain(st.degree_and_sample(st.edge_stream(s, d)), "degree", "update", ("user_id",)))
