"""Windows and runs of an event stream, by Structured Streaming."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from canopy.model import forest_of, scratch, settle
from canopy.operators.compressor import Config, compress
from canopy.operators.analytics import write_grammar
from canopy.sources.relational import chain


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int | None = None) -> DataFrame:
    """The events table, replayed file by file."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(schema)
    reader = reader if files_per_trigger is None else reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks want a time zone


def windowed(events: DataFrame, kind: str) -> DataFrame:
    """Events by window: tumbling days, days every six hours, or sessions of a user with gaps under 30 minutes."""
    w = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "1 day", "6 hours"), "session": F.session_window("ts", "30 minutes")}[kind]
    keys = [w.alias("w"), "user_id"] if kind == "session" else [w.alias("w"), "event_type"]
    got = events.withWatermark("ts", "1 hour").groupBy(*keys).agg(F.count("*").alias("n"))
    return got.select(F.col("w.start").cast("timestamp_ntz").alias("w_start"), keys[1], "n")


def closed_runs(events: DataFrame) -> DataFrame:
    """(user_id, head, event_type, len) of runs of equal events that are over: the open run of a user is carried as state.

    A batch is sorted by (ts, event_id); batches must come in time order. ``head`` is the number of the run's first event.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        letter, length, head = state.get if state.exists else (None, 0, 0)
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for x in rows.event_type:
            if x == letter:
                length += 1
                continue
            if length:
                out.append((key[0], head, letter, length))
            head, letter, length = head + length, x, 1
        state.update((letter, length, head))
        yield pd.DataFrame(out, columns=["user_id", "head", "event_type", "len"])

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, head long, event_type string, len int", "letter string, length int, head long", "append", "NoTimeout")


def run_to_table(stream: DataFrame, mode: str = "complete", with_progress: bool = False):
    """Everything available now, as a table in the shared folder; complete mode keeps windows still open at the end. With progress also the query's reports."""
    spark = stream.sparkSession
    base = f"{scratch(spark)}/canopy-stream/{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        # a batch that is tried again writes the same folder again
        batch.write.mode("overwrite").parquet(f"{base}/table" if mode == "complete" else f"{base}/table/batch={number}")

    spark.createDataFrame([], stream.schema).write.parquet(f"{base}/table" if mode == "complete" else f"{base}/table/batch=-1")
    query = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    table = spark.read.schema(stream.schema).parquet(f"{base}/table").select(*stream.columns)
    return (table, [p if isinstance(p, dict) else p.jsonValue if hasattr(p, "jsonValue") else p for p in query.recentProgress]) if with_progress else table


def late_rows(stream: DataFrame) -> int:
    """Rows that came after their window was closed, as the state store counts them."""
    _, progress = run_to_table(windowed(stream, "tumbling"), "append", with_progress=True)
    return int(sum(op["numRowsDroppedByWatermark"] for p in progress for op in p["stateOperators"]))


def compress_closed(stream: DataFrame, out: str, cfg: Config = Config()) -> int:
    """Each batch's user chains compressed and their grammar written under its number; returns the number of batches.

    Letters are named by content, so the same key has the same letter in every batch and rules of batches can be united.
    """
    spark, seen = stream.sparkSession, []

    def put(batch: DataFrame, number: int) -> None:
        if not batch.take(1):
            return
        f = forest_of(chain(settle(batch), "user_id", ["ts", "event_id"], F.col("event_type")))
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{out}/batch={number}")
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
        write_grammar(compress(f, cfg), f"{out}/batch={number}")
        seen.append(number)

    query = stream.writeStream.foreachBatch(put).option("checkpointLocation", f"{scratch(spark)}/canopy-stream/{uuid.uuid4().hex}").trigger(availableNow=True).start()
    query.awaitTermination()
    return len(seen)
