"""Streams over ``events``; each runs until its input is used up and is compared with the batch answer."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..session import shared_dir

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events.parquet`` (a file or a folder of files) as a stream."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/events*.parquet")


def drain(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream until its input is used up; the last result (complete mode) or all rows (append) from shared storage."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/chaincores/stream-{uuid.uuid4().hex}"
    last: list[str] = []

    def put(df: DataFrame, epoch: int) -> None:
        path = f"{base}/out/{epoch}"
        df.write.mode("overwrite").parquet(path)
        if mode == "complete":
            last.clear()
        last.append(path)

    q = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(*last) if last else spark.createDataFrame([], stream.schema)


_K = "json_extract_string(props, '$.k') AS value"


@query("stream_popularity_tumbling", f"SELECT time_bucket(INTERVAL '1 hour', ts) AS start, event_type, value, count(*) AS n FROM (SELECT ts, event_type, {_K} FROM events) GROUP BY ALL")
def tumbling(spark, sf):
    e = events(spark, sf).withColumn("v", F.get_json_object("props", "$.k"))
    w = e.groupBy(F.window("ts", "1 hour"), "event_type", F.col("v").alias("value")).agg(F.count("*").alias("n"))
    return drain(w.select(F.col("window.start").alias("start"), "event_type", "value", "n"), "complete")


@query("stream_popularity_sliding", "SELECT s AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL '30 minutes', ts), time_bucket(INTERVAL '30 minutes', ts) - INTERVAL '30 minutes']) AS s FROM events) GROUP BY ALL")
def sliding(spark, sf):
    w = events(spark, sf).groupBy(F.window("ts", "1 hour", "30 minutes"), "event_type").agg(F.count("*").alias("n"))
    return drain(w.select(F.col("window.start").alias("start"), "event_type", "n"), "complete")


@query("stream_sessions", "WITH a AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL '30 minutes' THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), b AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM a) SELECT user_id, min(ts) AS start, count(*) AS n FROM b GROUP BY user_id, k")
def sessions(spark, sf):
    w = events(spark, sf).groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n"))
    return drain(w.select("user_id", F.col("session_window.start").alias("start"), "n"), "complete")


@query("stream_dedup", f"SELECT DISTINCT event_type, {_K} FROM events")
def dedup(spark, sf):
    return drain(events(spark, sf).select("event_type", F.get_json_object("props", "$.k").alias("value")).dropDuplicates(), "append")


@query("stream_static_join", "SELECT event_type, c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY ALL")
def static_join(spark, sf):
    c = spark.read.parquet(f"{sf}/customer.parquet")
    j = events(spark, sf).join(c, F.col("user_id") == F.col("c_custkey")).groupBy("event_type", "c_mktsegment").agg(F.count("*").alias("n"))
    return drain(j, "complete")


@query("stream_clique_growth", f"SELECT event_type || '|' || value AS clique, 2 AS size FROM (SELECT event_type, {_K} FROM events) GROUP BY event_type, value HAVING count(*) >= 2")
def clique_growth(spark, sf):
    """A counter per class and value; a clique is reported once, when its second record comes."""

    def grow(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        before = state.get[0] if state.exists else 0
        now = before + sum(len(f) for f in frames)
        state.update((now,))
        if before < 2 <= now:
            yield pd.DataFrame({"clique": [key[0]], "size": [2]})

    keyed = events(spark, sf).select(F.concat_ws("|", "event_type", F.get_json_object("props", "$.k")).alias("clique"))
    return drain(keyed.groupBy("clique").applyInPandasWithState(grow, "clique string, size int", "n long", "append", GroupStateTimeout.NoTimeout), "append")


_MID = "(SELECT min(epoch_us(ts)) + (max(epoch_us(ts)) - min(epoch_us(ts))) // 2 FROM events)"


@query("stream_late_rows", f"SELECT time_bucket(INTERVAL '1 hour', ts) AS start, count(*) AS n FROM events WHERE epoch_us(ts) >= {_MID} GROUP BY 1 HAVING epoch_us(time_bucket(INTERVAL '1 hour', ts)) + 3600000000 <= (SELECT max(epoch_us(ts)) - 3600000000 FROM events)".replace("epoch_us(time_bucket(INTERVAL '1 hour', ts)) +", "any_value(epoch_us(time_bucket(INTERVAL '1 hour', ts))) +"))
def late_rows(spark, sf):
    """The later half of the events comes first; of the earlier half, all is behind the watermark and dropped. Windows close at the watermark."""
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).withColumn("us", F.unix_micros("ts"))
    lo, hi = e.agg(F.min("us"), F.max("us")).first()
    base = f"{shared_dir(spark)}/chaincores/late-{uuid.uuid4().hex}"
    half = F.col("us") >= lo + (hi - lo) // 2
    # rows are late against the watermark of the batch before last
    for i, part in enumerate((half & (F.col("us") < hi), F.col("us") == hi, ~half)):
        e.where(part).coalesce(1).write.parquet(f"{base}/{i}")
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(base)
    w = s.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    return drain(w.select(F.col("window.start").alias("start"), "n"), "append").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_dedup_within", "SELECT event_id, event_type FROM events")
def dedup_within(spark, sf):
    """Each event comes twice; state is kept for the watermark's length only."""
    both = events(spark, sf).unionByName(events(spark, sf)).select("event_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    return drain(both.withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"), "append")


@query("stream_stream_join", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL '2 hours' WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def stream_join(spark, sf):
    """Purchases within two hours of a click of the same user; either side's state ends with its watermark."""
    side = lambda kind, name: events(spark, sf).where(F.col("event_type") == kind).select(F.col("event_id").alias(name), F.col("user_id").alias(f"{name}_user"), F.col("ts").cast("timestamp").alias(f"{name}_ts")).withWatermark(f"{name}_ts", "60 days")
    j = side("click", "click").join(side("purchase", "purchase"), F.expr("click_user = purchase_user and purchase_ts >= click_ts and purchase_ts <= click_ts + interval 2 hours"))
    return drain(j.select("click", "purchase"), "append")


_ASSIGN = """so AS (SELECT v.rid, v.name, group_id, round(1 - product(1 - 0.8::DOUBLE * w), 9) AS sim FROM v JOIN sg USING (attr, value) JOIN (SELECT DISTINCT group_id, name FROM r JOIN g USING (rid)) gn USING (group_id, name) GROUP BY ALL),
be AS (SELECT rid, group_id, sim FROM so QUALIFY row_number() OVER (PARTITION BY rid ORDER BY sim DESC, group_id) = 1)
SELECT r.rid, CASE WHEN (0.5::DOUBLE + (0.9::DOUBLE * sim + 0.5::DOUBLE * (1 - sim)) * sim) / (0.5::DOUBLE + 0.9::DOUBLE * sim + 0.5::DOUBLE * (1 - sim)) > 0.6::DOUBLE + 1e-9 THEN group_id END AS group_id FROM r LEFT JOIN be USING (rid)"""


def _assign_sql() -> str:
    from ..queries import _SIG

    return f"{_SIG}, {_ASSIGN}"


@query("stream_assign", _assign_sql())
def assign(spark, sf):
    """Arriving listings against the frozen signatures of the groups that bear their name: to the best one above the threshold of the
    greedy start, else pending (null)."""
    from ..operators import baselines as B
    from ..operators import graph as G
    from ..operators import linkage as L
    from ..plans.cluster import Settings
    from ..session import materialise
    from ..sources.planted import listings

    r, s = materialise(listings(spark, sf), "listings"), Settings()
    groups = materialise(B.connected_graph(r), "groups")
    frozen = materialise(L.signatures(groups.select(F.col("group_id").alias("owner"), "rid"), G.value_rows(r)).select("attr", "value", "owner", "weight"), "frozen")
    names = materialise(groups.join(r, "rid").select(F.col("group_id").alias("owner"), "name").distinct(), "names")
    per = frozen.join(names, "owner").groupBy("name", "attr", "value").agg(F.collect_list(F.struct("owner", "weight")).alias("held"))
    base = f"{shared_dir(spark)}/chaincores/arriving-{uuid.uuid4().hex}"
    r.write.parquet(base)
    base_out = f"{shared_dir(spark)}/chaincores/stream-{uuid.uuid4().hex}"

    def put(batch: DataFrame, epoch: int) -> None:
        v = G.value_rows(batch)
        score = v.join(per, ["name", "attr", "value"]).select("rid", F.explode("held").alias("h")).groupBy("rid", "h.owner").agg(F.round(1 - F.exp(F.sum(F.log1p(-s.p * F.col("h.weight")))), 9).alias("dom"))
        best = score.groupBy("rid").agg(F.max(F.struct("dom", (-F.col("owner")).alias("o"))).alias("b")).select("rid", (-F.col("b.o")).alias("owner"), F.col("b.dom").alias("dom"))
        wd = F.col("dom") * 0.9 + (1 - F.col("dom")) * 0.5
        strong = (0.5 + wd * F.col("dom")) / (0.5 + wd)
        batch.select("rid").join(best, "rid", "left").select("rid", F.when(strong > s.start + 1e-9, F.col("owner")).alias("group_id")).write.mode("overwrite").parquet(f"{base_out}/out/{epoch}")

    run_batches(spark.readStream.schema(r.schema).option("maxFilesPerTrigger", 1).parquet(base), put)
    return spark.read.schema("rid long, group_id long").parquet(f"{base_out}/out/*")


def run_batches(stream: DataFrame, put: Callable) -> None:
    """A stream into any sink by ``foreachBatch``, until the input is used up."""
    base = f"{shared_dir(stream.sparkSession)}/chaincores/stream-{uuid.uuid4().hex}"
    stream.writeStream.foreachBatch(put).option("checkpointLocation", base).trigger(availableNow=True).start().awaitTermination()
