"""Contact edges from a stream of events: windows, late rows, joins, alerts and incremental search."""

from __future__ import annotations

import itertools
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..graph.builders import table as t
from ..operators.relational import query
from ..plans.workspace import shared_dir

DELAY = "1 day"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a file stream with event time ``at``; the whole table is one batch of files."""
    schema = t(spark, sf_dir, "events").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events*.parquet")
    return rows.withColumn("at", F.col("ts").cast("timestamp"))


def run_once(spark: SparkSession, stream: DataFrame, mode: str = "append", keep_open: bool = False) -> DataFrame:
    """Drives a stream over what is there into Parquet in the shared folder and returns the table."""
    root = f"{shared_dir(spark)}/relq-stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{root}/out")

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/out")

    stream.writeStream.foreachBatch(put).outputMode("complete").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{root}/out")


def _stamp(c: str) -> F.Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm")


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def st_tumbling(s, d):
    rows = event_stream(s, d).groupBy(F.window("at", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return run_once(s, rows.select(_stamp("w.start").alias("day"), "event_type", "n"), "complete")


@query("""SELECT strftime(epoch_ms(w * 43200000), '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM (SELECT unnest([floor(epoch_ms(ts) / 43200000)::BIGINT, floor(epoch_ms(ts) / 43200000)::BIGINT - 1]) AS w FROM events) GROUP BY 1""")
def st_sliding(s, d):
    rows = event_stream(s, d).groupBy(F.window("at", "1 day", "12 hours").alias("w")).agg(F.count("*").alias("n"))
    return run_once(s, rows.select(_stamp("w.start").alias("start"), "n"), "complete")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR epoch_us(ts) - epoch_us(lag(ts) OVER w) >= 86400000000 THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
k AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM g) SELECT user_id, size, count(*) AS sessions FROM (SELECT user_id, no, count(*) AS size FROM k GROUP BY user_id, no) GROUP BY user_id, size""")
def st_session(s, d):
    rows = event_stream(s, d).groupBy(F.session_window("at", DELAY), "user_id").agg(F.count("*").alias("size"))
    return run_once(s, rows.select("user_id", "size"), "complete").groupBy("user_id", "size").agg(F.count("*").alias("sessions"))


@query()
def st_watermark_late(s, d):
    """Daily counts in append mode: windows that the watermark closed, late rows left out."""
    rows = event_stream(s, d).withWatermark("at", DELAY).groupBy(F.window("at", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return run_once(s, rows.select(_stamp("w.start").alias("day"), "n"))


@query("SELECT DISTINCT user_id, event_type, event_id FROM events")
def st_dedup(s, d):
    rows = event_stream(s, d)
    return run_once(s, rows.unionByName(rows).withWatermark("at", "3650 days").dropDuplicatesWithinWatermark(["event_id"]).select("user_id", "event_type", "event_id"))


@query("SELECT c_mktsegment, event_type, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1, 2")
def st_stream_static(s, d):
    joined = event_stream(s, d).join(t(s, d, "customer").select("c_custkey", "c_mktsegment"), F.col("user_id") == F.col("c_custkey"))
    return run_once(s, joined.groupBy("c_mktsegment", "event_type").agg(F.count("*").alias("n")), "complete")


@query("SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def st_stream_stream(s, d):
    a = event_stream(s, d).where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("at").alias("clicked")).withWatermark("clicked", "3650 days")
    b = event_stream(s, d).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("at").alias("bought")).withWatermark("bought", "3650 days")
    both = a.join(b, F.expr("u = user_id AND bought >= clicked AND bought <= clicked + INTERVAL 1 DAY"))
    return run_once(s, both.select("click_id", "purchase_id"))


@query("SELECT user_id, max(n) AS n_kinds FROM (SELECT user_id, count(DISTINCT event_type) AS n FROM events GROUP BY user_id) GROUP BY user_id HAVING max(n) >= 3")
def st_stateful_alert(s, d):
    """Users whose events have touched three kinds or more; the state of a user is the set of kinds seen."""

    def watch(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen = set(state.get[0].split("|")) if state.exists else set()
        before = len(seen)
        for frame in frames:
            seen |= set(frame["event_type"].dropna())
        seen.discard("")
        state.update(("|".join(sorted(seen)),))
        if len(seen) >= 3 and len(seen) > before:
            yield pd.DataFrame({"user_id": [key[0]], "n_kinds": [len(seen)]})

    rows = event_stream(s, d).select("user_id", "event_type")
    alerts = rows.groupBy("user_id").applyInPandasWithState(watch, "user_id long, n_kinds long", "kinds string", "append", GroupStateTimeout.NoTimeout)
    return run_once(s, alerts).groupBy("user_id").agg(F.max("n_kinds").alias("n_kinds"))


def relax(dist: DataFrame, edges: DataFrame, fresh: DataFrame, work) -> DataFrame:
    """Lowers ``dist(node, hop)`` after ``fresh`` edges: only nodes that got nearer send on."""
    wave = dist.join(fresh, dist["node"] == fresh["src"]).select(F.col("dst").alias("node"), (F.col("hop") + 1).alias("hop"))
    for k in itertools.count():
        better = wave.groupBy("node").agg(F.min("hop").alias("hop"))
        had = dist.select("node", F.col("hop").alias("had"))
        gained = work.save(better.join(had, "node", "left").where(F.col("had").isNull() | (F.col("hop") < F.col("had"))).select("node", "hop"), f"gained{k}")
        if gained.isEmpty():
            break
        dist = work.save(dist.join(gained.select("node"), "node", "left_anti").unionByName(gained), f"dist{k}")
        wave = gained.join(edges, gained["node"] == edges["src"]).select(F.col("dst").alias("node"), (F.col("hop") + 1).alias("hop"))
    return dist


@query("""WITH e AS (SELECT DISTINCT 'u' || user_id AS a, 'b' || CAST(json_extract_string(props, '$.k') AS BIGINT) AS b FROM events),
d0 AS (SELECT 'b3' AS node, 0 AS hop), d1 AS (SELECT node, min(hop) AS hop FROM (SELECT * FROM d0 UNION ALL SELECT a, 1 FROM e WHERE b = 'b3') GROUP BY node),
d2 AS (SELECT node, min(hop) AS hop FROM (SELECT * FROM d1 UNION ALL SELECT e.b, hop + 1 FROM d1 JOIN e ON e.a = d1.node) GROUP BY node),
d3 AS (SELECT node, min(hop) AS hop FROM (SELECT * FROM d2 UNION ALL SELECT e.a, hop + 1 FROM d2 JOIN e ON e.b = d2.node) GROUP BY node),
d4 AS (SELECT node, min(hop) AS hop FROM (SELECT * FROM d3 UNION ALL SELECT e.b, hop + 1 FROM d3 JOIN e ON e.a = d3.node) GROUP BY node),
d5 AS (SELECT node, min(hop) AS hop FROM (SELECT * FROM d4 UNION ALL SELECT e.a, hop + 1 FROM d4 JOIN e ON e.b = d4.node) GROUP BY node)
SELECT hop, count(*) AS n FROM d5 GROUP BY hop""")
def st_incremental_edges(s, d):
    """Hops from bucket 3, kept while contact edges arrive: a batch sends on from the ends of its new edges alone."""
    from ..plans.workspace import Workspace

    work, box = Workspace(s, "incremental"), {}
    k = F.get_json_object("props", "$.k").cast("long")
    stream = event_stream(s, d).select(F.concat(F.lit("u"), "user_id").alias("a"), F.concat(F.lit("b"), k).alias("b"))
    box["dist"], box["edges"] = s.createDataFrame([("b3", 0)], "node string, hop int"), None

    def take(batch: DataFrame, number: int) -> None:
        part = Workspace(batch.sparkSession, "batch")
        fresh = part.save(batch.select(F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(batch.select(F.col("b").alias("src"), F.col("a").alias("dst"))).where("src is not null and dst is not null").distinct(), "fresh")
        box["edges"] = fresh if box["edges"] is None else part.save(box["edges"].unionByName(fresh).distinct(), "edges")
        box["dist"] = relax(box["dist"], box["edges"], fresh, part)

    stream.writeStream.foreachBatch(take).option("checkpointLocation", work.path("state")).trigger(availableNow=True).start().awaitTermination()
    return box["dist"].groupBy("hop").agg(F.count("*").alias("n"))
