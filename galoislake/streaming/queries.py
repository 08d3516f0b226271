"""Contexts and families over streams.

A stream of events becomes objects when their window closes behind the watermark; a family grows by these
whole objects only, so a day that is split over micro-batches is one object all the same. Rows that come
later than the watermark allows are dropped; others may come in any order. Batches are written under
their number, so a repeated batch replaces its own output and nothing else. Objects that leave are not
incremental: rebuild the window's context.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState

from galoislake.functions import bits
from galoislake.operators import lattice
from galoislake.plans import oracle
from galoislake.plans.storage import new_path
from galoislake.sources.workloads import WORKLOADS, session_attributes


def events(spark: SparkSession, path: str, glob: str | None = None, files_a_batch: int | None = None) -> DataFrame:
    """A file stream of event tables; times become instants, repeated events of a day are dropped."""
    schema = "event_id BIGINT, user_id BIGINT, ts TIMESTAMP_NTZ, event_type STRING, value DOUBLE, props STRING"
    reader = spark.readStream.schema(schema)
    for key, value in (("pathGlobFilter", glob), ("maxFilesPerTrigger", files_a_batch), ("recursiveFileLookup", "true")):
        if value is not None:
            reader = reader.option(key, value)
    return reader.parquet(path)


def each_batch(stream: DataFrame, handle: Callable[[DataFrame, int], None], mode: str = "append") -> None:
    """Run all that is there, batch by batch, to the end."""
    query = stream.writeStream.foreachBatch(handle).outputMode(mode).option("checkpointLocation", new_path(stream.sparkSession, "stream")).trigger(availableNow=True).start()
    query.awaitTermination()


def daily_sessions(stream: DataFrame, delay: str = "1 day") -> DataFrame:
    """user_id, day and attrs of every day that the watermark has passed."""
    timed = stream.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", delay).dropDuplicatesWithinWatermark(["event_id"])
    named = timed.select("user_id", "at", F.explode(session_attributes()).alias("name"))
    closed = named.groupBy(F.window("at", "1 day"), "user_id").agg(F.collect_set("name").alias("attrs"))
    return closed.select("user_id", F.to_date("window.start").alias("day"), "attrs")


def _closed_sessions(spark, sf_dir, context, mined):
    out = new_path(spark, "sessions")
    each_batch(daily_sessions(events(spark, sf_dir, "events.parquet")), lambda df, k: df.write.mode("overwrite").parquet(f"{out}/batch={k}"))
    rows = spark.read.parquet(out)
    return rows.select("user_id", F.col("day").cast("string").alias("day"), F.array_join(F.array_sort("attrs"), ",").alias("names"))


_SESSION = WORKLOADS["session_mix"]


def grow_family(spark: SparkSession, stream: DataFrame, attributes: tuple[str, ...], path: str, delay: str = "1 day") -> int:
    """Update the family in path with the sessions that close in each batch; the number of the last version.

    Each batch reads the version before its own and writes its own, so a replay writes the same again."""
    full, last = bits.full_words(len(attributes)), [-1]

    def handle(df: DataFrame, k: int) -> None:
        words = [c.alias(f"w{i}") for i, c in enumerate(bits.packed_from_array(F.col("attrs"), attributes))]
        family = spark.read.parquet(f"{path}/version={k - 1}") if k else None
        lattice.update_intents(family, df.select(*words), full).write.mode("overwrite").parquet(f"{path}/version={k}")
        last[0] = k

    each_batch(daily_sessions(stream, delay), handle)
    return last[0]


def in_files(table: DataFrame, path: str, files: int) -> None:
    """Rows by time, in files of about equal size that follow one another; days are split between files."""
    cuts = table.select(F.percentile_approx(F.col("ts").cast("timestamp").cast("double"), [k / files for k in range(1, files)], 10_000)).first()[0]
    at = F.col("ts").cast("timestamp").cast("double")
    for k, (low, high) in enumerate(zip([None, *cuts], [*cuts, None], strict=True)):
        some = table.where((F.lit(True) if low is None else at >= low) & (F.lit(True) if high is None else at < high))
        some.repartition(1).write.mode("append").parquet(f"{path}/{k:03d}")


def _streamed_family(spark, sf_dir, context, mined):
    ctx = context(spark, sf_dir, "session_mix")
    files, path = new_path(spark, "events"), new_path(spark, "family")
    in_files(spark.read.parquet(f"{sf_dir}/events.parquet"), files, 3)
    last = grow_family(spark, events(spark, files, files_a_batch=1), ctx.attributes, path)
    return spark.read.parquet(f"{path}/version={last}").select(ctx.string().alias("intent"))


def _common(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    days, shared = state.get if state.exists else (0, None)
    shared = None if shared is None else set(shared)
    for b in batches:
        for attrs in b["attrs"]:
            days, shared = days + 1, set(attrs) if shared is None else shared & set(attrs)
    state.update((days, sorted(shared)))
    yield pd.DataFrame({"user_id": [key[0]], "days": [days], "shared": [",".join(sorted(shared))]})


def common_by_user(sessions: DataFrame) -> DataFrame:
    """user_id, days and shared: what all closed days of a user have in common so far, kept in keyed state."""
    return sessions.groupBy("user_id").applyInPandasWithState(_common, "user_id long, days long, shared string", "days long, shared array<string>", "update", "NoTimeout")


STATE_FILES = 4


def _keyed_state(spark, sf_dir, context, mined):
    out = new_path(spark, "state")
    stream = daily_sessions(events(spark, sf_dir, "events.parquet"))
    plain = new_path(spark, "closed")
    # Few files, as each batch of them takes its own turn through all keys of the state.
    each_batch(stream, lambda df, k: df.coalesce(STATE_FILES).write.mode("overwrite").parquet(f"{plain}/batch={k}"))
    closed = spark.readStream.schema("user_id long, day date, attrs array<string>").option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 2).parquet(plain)
    each_batch(common_by_user(closed), lambda df, k: df.write.mode("overwrite").parquet(f"{out}/batch={k}"), "update")
    return spark.read.parquet(out).groupBy("user_id").agg(F.max(F.struct("days", "shared")).alias("last")).select("user_id", "last.days", "last.shared")


def _windows(spark, sf_dir, window, delay: str):
    out = new_path(spark, "windows")
    timed = events(spark, sf_dir, "events.parquet").withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", delay)
    counts = timed.groupBy(window, "user_id").agg(F.count("*").alias("n"), F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("types"))
    each_batch(counts.select("user_id", F.col(counts.columns[0])["start"].cast("timestamp_ntz").alias("start"), "n", "types"), lambda df, k: df.write.mode("overwrite").parquet(f"{out}/batch={k}"))
    return spark.read.parquet(out).select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", "types")


_CLOSED_DAY = "CAST({day} AS DATE) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY"
_DAY_NAMES = "SELECT DISTINCT user_id, CAST(ts AS DATE) AS d, unnest(['type=' || event_type, 'part=' || (hour(ts) // 6), 'v=' || CASE WHEN value < 5 THEN 'lo' WHEN value < 15 THEN 'mid' WHEN value IS NOT NULL THEN 'hi' END]) AS name FROM events"
_TYPES = "count(*) AS n, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS types"

QUERIES = {
    "stream_session_context": (
        _closed_sessions,
        "SELECT user_id, CAST(d AS VARCHAR) AS day, string_agg(DISTINCT name, ',' ORDER BY name) AS names FROM (SELECT user_id, CAST(ts AS DATE) AS d, unnest(['type=' || event_type, 'part=' || (hour(ts) // 6), 'v=' || CASE WHEN value < 5 THEN 'lo' WHEN value < 15 THEN 'mid' WHEN value IS NOT NULL THEN 'hi' END]) AS name FROM events) WHERE d + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY AND name IS NOT NULL GROUP BY user_id, d",
    ),
    "stream_family_session_mix": (_streamed_family, oracle.concepts("session_mix", "SELECT intent FROM con", f"NOT ({_CLOSED_DAY.format(day='right(o.obj, 10)')})")),
    "stream_common_by_user": (
        _keyed_state,
        f"WITH n AS (SELECT * FROM ({_DAY_NAMES}) WHERE name IS NOT NULL AND {_CLOSED_DAY.format(day='d')}), k AS (SELECT user_id, count(DISTINCT d) AS days FROM n GROUP BY user_id), s AS (SELECT user_id, name, count(*) AS c FROM n GROUP BY ALL) SELECT k.user_id, k.days, coalesce(string_agg(s.name, ',' ORDER BY s.name), '') AS shared FROM k LEFT JOIN s ON s.user_id = k.user_id AND s.c = k.days GROUP BY k.user_id, k.days",
    ),
    "stream_session_windows": (
        lambda spark, sf_dir, context, mined: _windows(spark, sf_dir, F.session_window("at", "12 hours"), "1 day"),
        f"SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, {_TYPES} FROM (SELECT *, sum(g) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS g FROM events)) GROUP BY user_id, session HAVING max(ts) + INTERVAL 12 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY",
    ),
    "stream_sliding_windows": (
        lambda spark, sf_dir, context, mined: _windows(spark, sf_dir, F.window("at", "2 days", "1 day"), "1 day"),
        f"SELECT user_id, strftime(CAST(ts AS DATE) - k * INTERVAL 1 DAY, '%Y-%m-%d %H:%M:%S') AS start, {_TYPES} FROM events, range(0, 2) r(k) WHERE CAST(ts AS DATE) - k * INTERVAL 1 DAY + INTERVAL 2 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY user_id, CAST(ts AS DATE) - k * INTERVAL 1 DAY",
    ),
}
