"""Queries of the relational and streaming workloads."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fragsim.queries.base import CFG, documents, slim
from fragsim.queries.sql import with_
from fragsim.sources.tables import shared_folder, table
from fragsim.streaming import activity as ST

Q, S = {}, {}


def query(name, sql=None):
    def keep(fn):
        Q[name] = fn
        if sql:
            S[name] = sql
        return fn

    return keep


@query("basket_star_join", """SELECT r_name, p_brand, CAST(count(*) AS BIGINT) AS items, CAST(count(DISTINCT o_custkey) AS BIGINT) AS baskets FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey
    JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL""")
def basket_star_join(spark, d):
    t = lambda n: table(spark, d, n)
    j = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
    j = j.join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name", "p_brand").agg(F.count("*").alias("items"), F.countDistinct("o_custkey").alias("baskets"))


@query("asof_activity", """SELECT event_id, (SELECT max(e.event_id) FROM events e WHERE e.user_id = p.user_id AND e.event_type = 'click' AND e.ts = (SELECT max(ts) FROM events c WHERE c.user_id = p.user_id AND c.event_type = 'click' AND c.ts <= p.ts)) AS last_click
    FROM events p WHERE event_type = 'purchase'""")
def asof_activity(spark, d):
    """Last click at or before each purchase of the same user: one window over the two kinds, no range join."""
    e = table(spark, d, "events").where(F.col("event_type").isin("click", "purchase")).select("event_id", "user_id", "event_type", "ts")
    order = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    click = F.max(F.when(F.col("event_type") == "click", F.struct("ts", "event_id"))).over(order)
    return e.withColumn("last", click).where("event_type = 'purchase'").select("event_id", F.col("last.event_id").alias("last_click"))


@query("activity_windows", "SELECT user_id, time_bucket(INTERVAL '1 day', ts) AS start, event_type AS action, CAST(count(*) AS BIGINT) AS f FROM events GROUP BY ALL")
def activity_windows(spark, d):
    e = table(spark, d, "events")
    return ST.window_bags(e.withColumn("ts", F.col("ts").cast("timestamp"))).withColumn("start", F.col("start").cast("timestamp_ntz"))


def _stream(spark, d):
    return ST.read_events(spark, f"{d}/events*.parquet")


@query("stream_activity_bags", S["activity_windows"])
def stream_activity_bags(spark, d):
    """The same bags by a stream that runs until its source is drained; a last event far ahead closes all windows."""
    out = ST.run_available(ST.window_bags(_stream(spark, d)), "bags_" + uuid.uuid4().hex, mode="complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_session_frags", """SELECT user_id, min(ts) AS start, max(ts) + INTERVAL '2 hours' AS stop, CAST(count(*) AS BIGINT) AS n_events FROM
    (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL '2 hours' THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s""")
def stream_session_frags(spark, d):
    out = ST.run_available(ST.session_bags(_stream(spark, d)), "sessions_" + uuid.uuid4().hex, mode="complete")
    return out.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "stop")})


@query("stream_unique_events", "SELECT event_id, user_id, event_type FROM events")
def stream_unique_events(spark, d):
    """The source is read twice; of each event one arrival stays."""
    twice = _stream(spark, d).unionByName(_stream(spark, d))
    # The delay is longer than the span of the source, since the two readings are not in step.
    return ST.run_available(ST.unique_events(twice, "60 days").select("event_id", "user_id", "event_type"), "unique_" + uuid.uuid4().hex)


@query("stream_click_to_purchase", """SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL '1 hour'
    WHERE c.event_type = 'click' AND p.event_type = 'purchase'""")
def stream_click_to_purchase(spark, d):
    clicks, purchases = (_stream(spark, d).where(F.col("event_type") == kind) for kind in ("click", "purchase"))
    return ST.run_available(ST.click_to_purchase(clicks, purchases, "60 days"), "interval_" + uuid.uuid4().hex)


@query("stream_action_counters", "SELECT event_type AS action, CAST(count(*) AS BIGINT) AS n_events, min(ts) AS first_ts, max(ts) AS last_ts FROM events GROUP BY ALL")
def stream_action_counters(spark, d):
    out = ST.run_available(ST.action_counters(_stream(spark, d)), "counters_" + uuid.uuid4().hex, mode="complete")
    return out.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("first_ts", "last_ts")})


@query("stream_consecutive_overlap", """WITH e AS (SELECT user_id, event_type, (row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1) // 10 AS n FROM events WHERE user_id IS NOT NULL),
    whole AS (SELECT user_id, n FROM e GROUP BY ALL HAVING count(*) = 10), bag AS (SELECT user_id, n, event_type, count(*) AS f FROM e GROUP BY ALL)
    SELECT w.user_id, CAST(w.n AS BIGINT) AS fragment, CAST(sum(least(a.f, coalesce(b.f, 0))) AS BIGINT) AS overlap FROM whole w LEFT JOIN bag a ON a.user_id = w.user_id AND a.n = w.n
    LEFT JOIN bag b ON b.user_id = w.user_id AND b.n = w.n - 1 AND b.event_type = a.event_type WHERE w.n > 0 GROUP BY ALL""")
def stream_consecutive_overlap(spark, d):
    """Stateful: each user's fragments of ten events against the one before."""
    return ST.run_available(ST.consecutive_overlap(_stream(spark, d)), "overlap_" + uuid.uuid4().hex)


@query("stream_incremental", with_("SELECT l AS left_id, r AS right_id, ov AS overlap FROM meet WHERE 100 * ov > 55 * least(lt, rt) AND 100 * least(ln, rn) >= 60 * greatest(ln, rn)", "meet"))
def stream_incremental(spark, d):
    """Documents arrive in two batches; the pairs equal those of one batch over all."""
    detector = ST.IncrementalDetector(spark, f"{shared_folder(spark)}/incremental-{uuid.uuid4().hex}", CFG)
    docs = slim(documents(spark, d))
    for i in range(2):
        detector.add(docs.where(F.pmod("fragment_id", F.lit(2)) == i), i)
    return detector.pairs()
