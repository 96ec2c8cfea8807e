"""Streams: incremental gram counts, windows and sessions of events, and segmentation of texts and event sequences as they arrive."""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import kernels
from ..operators import apply, model, segment
from ..shipping import ship, work_dir
from ..sources import corpus
from ..sources.store import kept


def file_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """The rows of a Parquet file or folder as a stream, with the schema of the files that are there."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rstrip("/").rpartition("/")
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch)
    return reader.option("pathGlobFilter", name).parquet(folder) if _is_file(spark, path) else reader.parquet(path)


def _is_file(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isFile()


def count_stream(lines: DataFrame, n_max: int) -> DataFrame:
    """Running gram counts; the state is the model. For update or complete mode."""
    return model.count_grams_once(lines, n_max)


def windowed_counts(events: DataFrame, watermark: str = "1 hour", width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events by type in tumbling or sliding windows; rows later than the watermark are dropped."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)
    return timed.groupBy(F.window("ts", width, slide), "event_type").agg(F.count("*").alias("n"))


def session_counts(events: DataFrame, gap: str = "1 hour", watermark: str = "1 hour") -> DataFrame:
    """A user's sessions and the number of events in each."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)
    return timed.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))


def deduplicated(events: DataFrame, key: str = "event_id", watermark: str = "1 hour") -> DataFrame:
    """Events once each within the watermark."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark).dropDuplicatesWithinWatermark([key])


def segment_stream(texts: DataFrame, slices: apply.Model, config: segment.Config = segment.Config()) -> DataFrame:
    """A stream of texts with their tokens: stateless, against a broadcast model."""
    return apply.segment_texts(texts, slices, config)


def session_tokens(events: DataFrame, config: segment.Config = segment.Config(), gap: str = "1 hour") -> DataFrame:
    """stmt_id (user, a colon, the second in which the session begins), tok_no, token of a table of events: a session's events, the first letter of each type, are a line of their own, cut by what all sessions teach. A session's events meet, not a user's."""
    timed = events.select("user_id", F.col("ts").cast("timestamp").alias("ts"), "event_id", F.left("event_type", F.lit(1)).alias("s"))
    ordered = F.array_sort(F.collect_list(F.struct("ts", "event_id", "s")))
    made = timed.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.array_join(F.transform(ordered, lambda x: x["s"]), "").alias("text"))
    st = kept(made.select(F.lit("seq").alias("lang"), F.concat(F.col("user_id").cast("string"), F.lit(":"), F.unix_timestamp("w.start").cast("string")).alias("stmt_id"), "text"))
    grams = kept(model.count_grams(st.select("lang", F.col("text").alias("line")), max(config.ranks) + 1))
    return segment.run(st, grams, config).select("stmt_id", "tok_no", "token")


def stateful_segments(events: DataFrame, own: kernels.Slice, threshold: float = 0.4, most: int = 256, watermark: str = "1 hour", idle: str = "1 day") -> DataFrame:
    """user_id, token of each user's events in order of time, by forward freedom of single events over the running mean.

    Events wait until the watermark has passed them and are then taken by (ts, event_id), so tokens don't depend on how
    they were dealt into batches; events later than the watermark are left out. State holds what waits, the open token and
    the running sum and count. A token is closed at `most` events, and with all of a user's state when the watermark has
    passed the last event by `idle`: such a user begins anew."""
    freedom = {chr(int(k)): float(v) for k, v in zip(own.keys, own.forward, strict=True)}
    top = max(freedom.values(), default=1.0) or 1.0
    wait = int(pd.Timedelta(idle).total_seconds() * 1000)

    def run(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held, total, n, waiting = state.get if state.exists else ("", 0.0, 0, "[]")
        now, rows = state.getCurrentWatermarkMs(), json.loads(waiting)
        if not state.hasTimedOut:
            for frame in frames:
                at = frame["at"].tolist()
                rows += [[t, i, s] for t, i, s in zip(at, frame["event_id"].tolist(), frame["symbol"].tolist(), strict=True) if t // 1000 > now]
        rows.sort()
        ready = [r for r in rows if r[0] // 1000 <= now]
        rows, out = rows[len(ready) :], []
        for _, _, symbol in ready:
            v = freedom.get(symbol, 0.0) / top
            total, n, held = total + v, n + 1, held + symbol
            if v - total / n > threshold or len(held) >= most:
                out.append(held)
                held = ""
        if state.hasTimedOut and not rows and not ready:
            out += [held] * bool(held)
            state.remove()
        else:
            state.update((held, total, n, json.dumps(rows)))
            # The next row that waits, or the end of the user.
            state.setTimeoutTimestamp(max(now, rows[0][0] // 1000) + 1 if rows else now + wait)
        yield pd.DataFrame({"user_id": np.repeat(key[0], len(out)), "token": out})

    keyed = events.select("user_id", F.col("ts").cast("timestamp").alias("ts"), "event_id", F.left("event_type", F.lit(1)).alias("symbol")).where("user_id is not null and ts is not null").withWatermark("ts", watermark)
    keyed = keyed.withColumn("at", F.unix_micros("ts"))
    return keyed.groupBy("user_id").applyInPandasWithState(run, "user_id long, token string", "held string, total double, n long, waiting string", "append", GroupStateTimeout.EventTimeTimeout)


def finished(stream: DataFrame, mode: str) -> DataFrame:
    """All that a stream gives for the files that are there, as a table: each batch is written to the shared folder, and in complete mode the last one counts."""
    spark = stream.sparkSession
    ship(spark)
    at = f"{work_dir(spark)}/stream-{uuid.uuid4().hex}"
    last = {"to": None, "all": []}

    def sink(batch: DataFrame, number: int) -> None:
        to = f"{at}/out/{number}"
        batch.write.mode("overwrite").parquet(to)
        last["to"] = to
        last["all"].append(to)

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/state").foreachBatch(sink).trigger(availableNow=True).start()
    q.awaitTermination()
    paths = last["all"] if mode == "append" else [last["to"]]
    return spark.read.schema(stream.schema).parquet(*dict.fromkeys(paths))


def run_counts(spark: SparkSession, path: str, n_max: int) -> DataFrame:
    """Gram counts of a stream of documents."""
    lines = corpus.lines(file_stream(spark, path).select("lang", "text"), "text", "lang")
    return finished(count_stream(lines, n_max), "complete")


def run_windows(spark: SparkSession, files: list[DataFrame], mode: str = "append") -> DataFrame:
    """begins, event_type, n: hourly counts of a stream of events that arrive as one file after the other."""
    to = f"{work_dir(spark)}/events-{uuid.uuid4().hex}"
    for df in files:
        df.coalesce(1).write.mode("append").parquet(to)
    out = finished(windowed_counts(file_stream(spark, to)), mode)
    return out.select(F.unix_timestamp("window.start").alias("begins"), "event_type", "n")
