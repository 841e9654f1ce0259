"""Streams of events, compared with the batch query over the same rows."""

from __future__ import annotations

from pyspark.sql import functions as F

from sevenfold.sources.matrices import cells_from, table
from sevenfold.streaming import windows as st
from sevenfold.workloads.registry import as_cells, query

@query("s_tumbling", "SELECT date_trunc('day', ts) AS start, user_id, count(*) AS n FROM events GROUP BY 1, 2")
def s_tumbling(s, d):
    return (
        st.run_available_now(st.windowed_cells(st.stream_events(s, d), "tumbling"), "complete")
        .select("start", "user_id", "n")
    )


@query("s_sliding", """SELECT date_trunc('day', ts) - k * INTERVAL 1 DAY AS start, user_id, count(*) AS n FROM events, (SELECT
unnest(range(0, 2)) AS k) GROUP BY 1, 2""")
def s_sliding(s, d):
    return (
        st.run_available_now(st.windowed_cells(st.stream_events(s, d), "sliding", "2 days", "1 day"), "complete")
        .select("start", "user_id", "n")
    )


@query("s_session", """WITH x AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS new FROM events
WINDOW w AS (PARTITION BY user_id ORDER BY ts)), y AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS g
FROM x) SELECT min(ts) AS start, user_id, count(*) AS n FROM y GROUP BY user_id, g""")
def s_session(s, d):
    return (
        st.run_available_now(st.windowed_cells(st.stream_events(s, d), "session", "6 hours"), "complete")
        .select("start", "user_id", "n")
    )


# windows that the watermark (an hour behind the last event) has closed; the replayed rows are all older and count nowhere
@query("s_late", """SELECT date_trunc('day', ts) AS start, user_id, count(*) AS n FROM events GROUP BY 1, 2 HAVING date_trunc('day',
max(ts)) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)""")
def s_late(s, d):
    return st.run_in_slices(st.late_replay(s, d), lambda e: st.windowed_cells(e, "tumbling"))[0].select("start", "user_id", "n")


@query("s_dedupe", "SELECT event_id, user_id FROM events")
def s_dedupe(s, d):
    """Every third event comes twice within its slice, and the last hours of a slice come again with the next."""
    slices = st.slices_by_time(s, d)
    twice = [x.unionByName(x.where("event_id % 3 = 0")) for x in slices]
    for k in (1, 2):
        last = slices[k - 1].agg(F.max("ts")).first()[0]
        again = slices[k - 1].where(F.col("ts") > F.lit(last) - F.expr("INTERVAL 30 MINUTES"))
        twice[k] = twice[k].unionByName(again)
    return st.run_in_slices(twice, st.dedupe_events)[0].select("event_id", "user_id")


@query("s_static_join", """SELECT event_id, w FROM events JOIN (VALUES ('click', 1), ('purchase', 5), ('view', 2)) AS k(event_type, w) ON
events.event_type = k.event_type""")
def s_static_join(s, d):
    return (
        st.run_available_now(st.stream_enrich(st.stream_events(s, d), s.createDataFrame([("click", 1), ("purchase", 5), ("view", 2)], "event_type string, w int"), "event_type"))
        .select("event_id", "w")
    )


@query("s_state_transition", """SELECT before, after, count(*) AS v FROM (SELECT lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before,
event_type AS after FROM events) WHERE before IS NOT NULL GROUP BY 1, 2""")
def s_state_transition(s, d):
    """Three slices of time: a user's last event is carried from one to the next."""
    pairs = st.run_in_slices(st.slices_by_time(s, d), lambda e: st.stream_transitions(e, forget_hours=20 * 24))[0]
    return pairs.groupBy("before", "after").agg(F.count("*").alias("v"))


@query("s_incremental_product", """WITH x AS (SELECT user_id AS i, hour(ts) AS j, count(*) AS v FROM events GROUP BY 1, 2)
SELECT i, CAST(x.j % 4 AS BIGINT) AS j, CAST(sum(v * (1 + x.j)) AS BIGINT) AS v FROM x GROUP BY 1, 2""")
def s_incremental_product(s, d):
    """Four batches add to users by hours, times a fixed matrix."""
    by_hour = s.range(24).select(F.col("id").alias("i"), (F.col("id") % 4).alias("j"), (F.col("id") + 1).alias("v"))
    stream = st.stream_of_slices(st.slices_by_time(s, d, 4))
    return as_cells(st.incremental_product(stream, lambda e: cells_from(e, F.col("user_id"), F.hour("ts"), F.lit(1)), by_hour))


@query("s_two_sided_product", """WITH x AS (SELECT user_id AS i, hour(ts) AS j, count(*) AS v FROM events GROUP BY 1, 2),
y AS (SELECT hour(ts) AS i, length(event_type) AS j, count(*) AS v FROM events GROUP BY 1, 2)
SELECT x.i AS i, CAST(y.j AS BIGINT) AS j, CAST(sum(x.v * y.v) AS BIGINT) AS v FROM x JOIN y ON x.j = y.i GROUP BY 1, 2""")
def s_two_sided_product(s, d):
    """Users by hours times hours by length of type, where every batch adds to both."""
    left = lambda e: cells_from(e, F.col("user_id"), F.hour("ts"), F.lit(1))
    right = lambda e: cells_from(e, F.hour("ts"), F.length("event_type"), F.lit(1))
    return as_cells(st.two_sided_product(st.stream_of_slices(st.slices_by_time(s, d)), left, right))
