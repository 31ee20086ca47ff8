"""Streams of events: windows, sessions, duplicates, late rows, stateful set expressions, and sets that grow."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.hashing import WIDTH, mother_hash_sql
from ..operators import ladder as L
from ..sources.scratch import file_system, scratch, staged

QUERIES: dict = {}
SQL: dict[str, str] = {}


def op(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return add


def event_stream(spark: SparkSession, folder: str, delay: str = "10 minutes") -> DataFrame:
    """Events as a stream with a watermark; their times are cast, since watermarks need a zone."""
    schema = spark.read.parquet(f"{folder}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def replayed(spark: SparkSession, parts: list[DataFrame]) -> DataFrame:
    """The parts as a stream, one file and one micro-batch each, in this order."""
    path = scratch(spark, "replay")
    for i, part in enumerate(parts):
        part.coalesce(1).write.mode("append").parquet(f"{path}/part={i}")
    return spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", 1).parquet(*[f"{path}/*"])


def cut_stream(spark: SparkSession, folder: str, parts: int = 3) -> DataFrame:
    """The same events from several files, one per micro-batch."""
    events = spark.read.parquet(f"{folder}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    path = scratch(spark, "stream")
    events.repartition(parts, "event_id").write.parquet(path)
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)


def written_batches(spark: SparkSession, path: str) -> list[int]:
    """Numbers of the micro-batches whose output is whole, from the store itself, so a restarted stream finds earlier ones."""
    fs, folder = file_system(spark, path)
    if not fs.exists(folder):
        return []
    whole = [s.getPath() for s in fs.listStatus(folder) if fs.exists(file_system(spark, f"{s.getPath()}/_SUCCESS")[1])]
    return sorted(int(str(p.getName()).split("=")[1]) for p in whole)


def run_to_end(stream: DataFrame, mode: str = "append", path: str | None = None) -> DataFrame:
    """Runs over all that is there. A batch is written under its own number, so a repeated batch replaces itself; with a `path` that an
    earlier run has used, the stream goes on from its checkpoint and the result holds that run's batches too."""
    spark, path = stream.sparkSession, path or scratch(stream.sparkSession, "stream")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out/batch={number}")

    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    have = written_batches(spark, f"{path}/out")
    if not have:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*[f"{path}/out/batch={n}" for n in (have[-1:] if mode == "complete" else have)])


_SEC = "CAST(floor(epoch(ts)) AS BIGINT)"
op("stream_tumbling", f"SELECT ({_SEC} // 3600) * 3600 AS start, event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1, 2")(
    lambda s, d: run_to_end(event_stream(s, d).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n")).select(F.unix_timestamp("window.start").alias("start"), "event_type", "n"), "complete")
)
op("stream_sliding", f"SELECT CAST(s AS BIGINT) AS start, CAST(count(*) AS BIGINT) AS n FROM (SELECT unnest([({_SEC} // 1800) * 1800, ({_SEC} // 1800) * 1800 - 1800]) AS s FROM events) GROUP BY 1")(
    lambda s, d: run_to_end(event_stream(s, d).groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count("*").alias("n")).select(F.unix_timestamp("window.start").alias("start"), "n"), "complete")
)
op("stream_session", """SELECT user_id, CAST(count(*) AS BIGINT) AS sessions, CAST(sum(n) AS BIGINT) AS events FROM (SELECT user_id, k, count(*) AS n FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM
    (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)) GROUP BY 1, 2) GROUP BY 1""")(
    lambda s, d: run_to_end(event_stream(s, d).groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n")).select("user_id", "n"), "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))
)
op("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")(
    # several micro-batches; the horizon is longer than the events' span, so state is kept to the end
    lambda s, d: run_to_end(cut_stream(s, d).withWatermark("ts", "36500 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"))
)


def late_parts(spark: SparkSession, folder: str) -> list[DataFrame]:
    """Events out of order: the earlier ones, the later ones, and then a tenth of the earlier ones that were held back."""
    events = spark.read.parquet(f"{folder}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    ends = events.agg(F.min(F.unix_seconds("ts")).alias("a"), F.max(F.unix_seconds("ts")).alias("b")).first()
    early = F.unix_seconds("ts") < ends["a"] + (ends["b"] - ends["a"]) * 7 // 10
    held = early & (F.col("event_id") % 10 == 0)
    return [events.where(early & ~held), events.where(~early), events.where(held)]


def late_data(spark: SparkSession, folder: str) -> DataFrame:
    """Counts by hour: held-back rows whose window the watermark had passed are gone, others count; open windows don't come out."""
    stream = replayed(spark, late_parts(spark, folder)).withWatermark("ts", "10 minutes")
    counts = stream.groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    return run_to_end(counts.select(F.unix_timestamp("window.start").alias("start"), "n"))


op("stream_late_data", f"""WITH ends AS (SELECT min({_SEC}) AS a, max({_SEC}) AS b FROM events), marked AS (SELECT *, ({_SEC} // 3600) * 3600 AS start, {_SEC} < a + (b - a) * 7 // 10 AS early FROM events, ends),
    parts AS (SELECT *, early AND event_id % 10 = 0 AS held FROM marked), passed AS (SELECT max(epoch_ms(ts)) - 600000 AS w FROM parts WHERE early AND NOT held)
    SELECT start, CAST(count(*) AS BIGINT) AS n FROM parts, passed WHERE NOT (held AND (start + 3600) * 1000 <= w) AND (start + 3600) * 1000 <= (SELECT max(epoch_ms(ts)) - 600000 FROM events) GROUP BY 1""")(late_data)


def expression_stream(events: DataFrame, needed: tuple[str, ...]) -> DataFrame:
    """Users whose set of event types first satisfies a monotone condition (all of `needed`): emitted once, never taken back."""
    bits = {t: 1 << i for i, t in enumerate(needed)}
    full = (1 << len(needed)) - 1

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        mask = before = state.get[0] if state.exists else 0
        for b in batches:
            for t in b["event_type"].unique():
                mask |= bits.get(t, 0)
        state.update((mask,))
        if mask == full and before != full:
            yield pd.DataFrame({"user_id": [key[0]]})

    return events.select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(step, "user_id long", "mask long", "append", GroupStateTimeout.NoTimeout)


op("stream_stateful_mask", "SELECT user_id FROM events WHERE event_type IN ('error', 'purchase') GROUP BY 1 HAVING count(DISTINCT event_type) = 2")(lambda s, d: run_to_end(expression_stream(cut_stream(s, d), ("error", "purchase"))))


def _followed(s: SparkSession, d: str) -> DataFrame:
    e = event_stream(s, d, "1 hour")
    errors = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("u"), F.col("ts").alias("at"))
    buys = event_stream(s, d, "1 hour").where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    both = errors.join(buys, F.expr("u = user_id AND ts >= at AND ts <= at + INTERVAL 1 HOUR"))
    return run_to_end(both.select("error_id", F.col("event_id").alias("purchase_id")))


op("stream_stream_join", "SELECT a.event_id AS error_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")(_followed)


def grow_ladder(stream: DataFrame, r: int = 18, path: str | None = None) -> DataFrame:
    """Rungs of the sets event_type -> user_id, taken up batch by batch. Each batch stores what is new as a version under its own number, on
    top of the newest one before it, so a repeated batch or a restart from the checkpoint gives the same."""
    spark, path = stream.sparkSession, path or scratch(stream.sparkSession, "stream")

    def take(batch: DataFrame, number: int) -> None:
        pairs = staged(batch.select(F.col("event_type").alias("set_id"), F.col("user_id").cast("long").alias("elem")).distinct(), "pairs")
        if any(v < number for v in L.versions(spark, path, "sets")):
            L.append_to_store(spark, path, "sets", pairs, version=number)
        else:
            L.store_ladder(L.build_ladder(pairs, schedule=[r]), spark, path, "sets", version=number)

    stream.writeStream.foreachBatch(take).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return L.members(L.read_ladder(spark, path, "sets").rungs).distinct()


op("stream_ladder", f"SELECT DISTINCT event_type AS set_id, CAST(18 AS INT) AS r, {mother_hash_sql('user_id')} >> {WIDTH - 18} AS hv FROM events")(lambda s, d: grow_ladder(cut_stream(s, d)))


def grown_then_asked(spark: SparkSession, folder: str) -> DataFrame:
    """Growth by micro-batches, then a query on the newest version."""
    from ..operators.evaluate import evaluate_packed

    path = scratch(spark, "stream")
    grow_ladder(cut_stream(spark, folder), 30, path)
    return evaluate_packed("(error & purchase) | (click & signup)", L.read_ladder(spark, path, "sets"), r=30)


_TYPE = "SELECT user_id AS elem FROM events WHERE event_type = "
op("w26_stream", f"({_TYPE}'error' INTERSECT {_TYPE}'purchase') UNION ({_TYPE}'click' INTERSECT {_TYPE}'signup')")(grown_then_asked)
