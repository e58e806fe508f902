"""Structured Streaming: prompts compressed as they arrive, and event-time operators around them.

Each query runs its stream over all that is there, into a Parquet sink whose log
makes restarts exact, and returns what was written.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tokenfold.operators import backends
from tokenfold.options import CompressOptions
from tokenfold.plans.sqlviews import _TOK
from tokenfold.registry import query
from tokenfold.sources.tables import scratch, table, words


def source(spark: SparkSession, sf_dir: str, name: str, **options) -> DataFrame:
    """The files of a table, one file or a folder, as a stream; the schema comes from the footers.

    The path is a pattern, since Spark takes a plain path of a stream for a folder.
    """
    return spark.readStream.schema(table(spark, sf_dir, name).schema).options(**options).parquet(f"{sf_dir}/{name}.parque[t]")


def _drain(df: DataFrame, path: str, mode: str = "append") -> None:
    df.writeStream.outputMode(mode).format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start().awaitTermination()


def drained(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream until its source is empty and return its sink."""
    spark, path = df.sparkSession, scratch(df.sparkSession, name)
    _drain(df, path, mode)
    return spark.read.schema(df.schema).parquet(f"{path}/rows")


def events(spark: SparkSession, sf_dir: str, late: str = "10 minutes") -> DataFrame:
    return source(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)


#: Time up to which windows are complete once everything has been read; Spark keeps watermarks in whole milliseconds.
_CLOSED = "(SELECT date_trunc('milliseconds', max(ts)) - INTERVAL 10 MINUTE FROM events)"



@query("stream_file_source", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def stream_file_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(source(spark, sf_dir, "events").select("event_id", "event_type"), "file-source").groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_compress_prompts", f"WITH {_TOK} SELECT seq_id, CAST(n AS INTEGER) AS n_tokens, CAST(CASE WHEN n <= 12 THEN n ELSE 12 + ceil((n - 12) / 4.0) END AS INTEGER) AS n_macro FROM (SELECT seq_id, count(*) AS n FROM tok GROUP BY seq_id) t")
def stream_compress_prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Adaptive compression of prompts as they arrive: the batch operator, unchanged, since it needs no state."""
    prompts = source(spark, sf_dir, "documents").select(F.col("doc_id").alias("seq_id"), words("text").alias("tokens"))
    prompts = prompts.repartition(spark.sparkContext.defaultParallelism, "seq_id")
    made = backends.summarise(prompts, backends.frozen_table(spark, sf_dir), CompressOptions())
    return drained(made.select("seq_id", "n_tokens", "n_macro"), "compress")


@query("stream_tumbling", f"""SELECT * FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS low, event_type, count(*) AS n FROM events GROUP BY 1, 2) w
WHERE low + INTERVAL 1 HOUR <= {_CLOSED}""")
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    counted = events(spark, sf_dir).groupBy(F.window("at", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drained(counted.select(F.col("w.start").cast("timestamp_ntz").alias("low"), "event_type", "n"), "tumbling")


@query("stream_sliding", f"""SELECT low, count(*) AS n FROM (SELECT ts, time_bucket(INTERVAL 1 HOUR, ts) - to_hours(CAST(k AS INTEGER)) AS low FROM events CROSS JOIN range(0, 2) r(k)) w
WHERE low + INTERVAL 2 HOUR <= {_CLOSED} GROUP BY low""")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    counted = events(spark, sf_dir).groupBy(F.window("at", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return drained(counted.select(F.col("w.start").cast("timestamp_ntz").alias("low"), "n"), "sliding")


@query("stream_session", f"""WITH marked AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
numbered AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS s FROM marked)
SELECT * FROM (SELECT user_id, min(ts) AS low, count(*) AS n FROM numbered GROUP BY user_id, s HAVING max(ts) + INTERVAL 1 HOUR <= {_CLOSED}) q""")
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    counted = events(spark, sf_dir).groupBy(F.session_window("at", "1 hour").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(counted.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("low"), "n"), "session")


@query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeated pairs dropped within a watermark that spans the file, which comes as one batch."""
    seen = events(spark, sf_dir, "3650 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return drained(seen.select("user_id", "event_type"), "dedup")


#: Events that arrive after all others.
_STRAGGLERS = "event_id % 10 = 0"


@query("stream_late_data", f"""WITH first_run AS (SELECT date_trunc('milliseconds', max(ts)) - INTERVAL 10 MINUTE AS closed FROM events WHERE NOT ({_STRAGGLERS}))
SELECT * FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS low, event_type, count(*) AS n FROM events CROSS JOIN first_run
WHERE NOT ({_STRAGGLERS}) OR time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR > closed GROUP BY 1, 2) w WHERE low + INTERVAL 1 HOUR <= {_CLOSED}""")
def stream_late_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly counts over two runs of one query: the second starts from the first one's log and drops what comes too late.

    A straggler counts only where its hour was still open at the end of the first run.
    """
    path = scratch(spark, "late")
    every = table(spark, sf_dir, "events").select("event_id", "event_type", "ts")
    for wave in (f"NOT ({_STRAGGLERS})", _STRAGGLERS):
        every.filter(wave).write.mode("append").parquet(f"{path}/in")
        arriving = spark.readStream.schema(every.schema).parquet(f"{path}/in").withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", "10 minutes")
        counted = arriving.groupBy(F.window("at", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("low"), "event_type", "n")
        _drain(counted, path)
    return spark.read.schema(counted.schema).parquet(f"{path}/rows")


@query("stream_foreach_batch", "SELECT event_type, user_id % 16 AS part, count(*) AS n FROM events GROUP BY 1, 2")
def stream_foreach_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Partial counts of each batch in a folder of its number, so that a batch that runs again replaces its own rows."""
    path = scratch(spark, "batches")

    def put(batch: DataFrame, number: int) -> None:
        partial = batch.groupBy("event_type", (F.col("user_id") % 16).alias("part")).agg(F.count("*").alias("n"))
        partial.write.mode("overwrite").parquet(f"{path}/rows/batch={number}")

    source(spark, sf_dir, "events").select("event_type", "user_id").writeStream.foreachBatch(put).option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{path}/rows").groupBy("event_type", "part").agg(F.sum("n").alias("n"))


@query("stream_static_join", "SELECT c.c_mktsegment, count(*) AS n FROM events e JOIN customer c ON c.c_custkey = e.user_id GROUP BY 1")
def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    joined = source(spark, sf_dir, "events").select("user_id").join(customers, F.col("user_id") == F.col("c_custkey"))
    return drained(joined.select("c_mktsegment"), "static").groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("stream_stream_join", """SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b
ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE""")
def stream_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases within half an hour of a view by the same user; state is bounded by the interval."""

    def side(kind: str, prefix: str) -> DataFrame:
        e = source(spark, sf_dir, "events").filter(F.col("event_type") == kind)
        return e.select(F.col("event_id").alias(f"{prefix}_id"), F.col("user_id").alias(f"{prefix}_user"), F.col("ts").cast("timestamp").alias(f"{prefix}_at")).withWatermark(f"{prefix}_at", "10 minutes")

    near = F.expr("first_user = second_user AND second_at >= first_at AND second_at <= first_at + INTERVAL 30 MINUTES")
    return drained(side("view", "first").join(side("purchase", "second"), near).select("first_id", "second_id"), "interval")


#: Tokens that make a window of a conversation.
WIDTH = 16
FILLED = "conv_id long, win_id long, first_token string, n_tokens int"


def fill_in_order(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """fill_windows without a timeout, for streams that end."""
    return fill_windows(key, batches, state, None)


def fill_windows(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState, wait_ms: int | None = 3_600_000) -> Iterator[pd.DataFrame]:
    """Windows of WIDTH tokens of a conversation, as soon as they are full; the rest waits in the state.

    At the timeout the rest comes out as a short window. The state holds under WIDTH tokens.
    """
    done, waiting = state.get if state.exists else (0, [])
    waiting, out = list(waiting), []
    if state.hasTimedOut:
        if waiting:
            yield pd.DataFrame([(key[0], done, waiting[0], len(waiting))], columns=["conv_id", "win_id", "first_token", "n_tokens"])
        state.remove()
        return
    turns = pd.concat(list(batches)).sort_values("turn", kind="stable")
    for tokens in turns["tokens"]:
        waiting.extend([] if tokens is None else tokens)
    cut = len(waiting) // WIDTH
    for i in range(cut):
        out.append((key[0], done + i, waiting[i * WIDTH], WIDTH))
    state.update((done + cut, waiting[cut * WIDTH :]))
    if wait_ms:
        state.setTimeoutDuration(wait_ms)
    yield pd.DataFrame(out, columns=["conv_id", "win_id", "first_token", "n_tokens"])


@query("stream_stateful_windows", r"""WITH t AS (SELECT conv_id, turn, unnest(regexp_extract_all(text, '[^\x20\x09-\x0d]+')) AS token, generate_subscripts(regexp_extract_all(text, '[^\x20\x09-\x0d]+'), 1) AS i FROM conversations),
p AS (SELECT conv_id, token, row_number() OVER (PARTITION BY conv_id ORDER BY turn, i) - 1 AS pos FROM t)
SELECT conv_id, pos // 16 AS win_id, arg_min(token, pos) AS first_token, CAST(count(*) AS INTEGER) AS n_tokens FROM p GROUP BY conv_id, pos // 16 HAVING count(*) = 16""")
def stream_stateful_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = source(spark, sf_dir, "conversations").select("conv_id", "turn", words("text").alias("tokens"))
    filled = turns.groupBy("conv_id").applyInPandasWithState(fill_in_order, FILLED, "done long, waiting array<string>", "append", GroupStateTimeout.NoTimeout)
    return drained(filled, "stateful")
