"""Streams: windowed counts under a watermark, sketches that grow by arrival, exact-copy removal, and search against a stored index.

Every function takes a streaming (or static) DataFrame and gives one of the same kind; `drain` runs a stream over what
is there and returns what it wrote, from the shared folder.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.hashing import token_number
from ..operators import sketch
from ..sources.shared import shared_folder


def follow(spark: SparkSession, path: str, files_per_batch: int | None = None) -> DataFrame:
    """A Parquet file or folder as a stream of files. The path goes in as a pattern, since a stream's plain path must be a folder."""
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    return (reader.option("maxFilesPerTrigger", files_per_batch) if files_per_batch else reader).parquet(f"{path[:-1]}[{path[-1]}]")


def timed_events(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """Events with their instant, read as UTC whatever the session's zone, as the watermarked column `at`; null instants have no window and go."""
    return events.withColumn("at", F.from_utc_timestamp(F.col("ts").cast("timestamp"), F.current_timezone())).where("at is not null").withWatermark("at", delay)


def windowed(events: DataFrame, window: Column) -> DataFrame:
    """Counts and totals per window and type. Sums are of whole cents, so that their order does not matter."""
    cents = F.sum(F.round(F.col("value") * 100).cast("long"))
    per = events.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"), cents.alias("cents"))
    return per.select(F.unix_timestamp("w.start").alias("start_s"), F.unix_timestamp("w.end").alias("end_s"), "event_type", "n", "cents")


def tumbling(length: str = "1 day") -> Column:
    return F.window("at", length)


def sliding(length: str = "1 day", step: str = "12 hours") -> Column:
    return F.window("at", length, step)


def session(gap: str = "2 hours") -> Column:
    return F.session_window("at", gap)


def stream_cells(rows: DataFrame, keys: list[str], depth: int = sketch.DEPTH, width: int = sketch.WIDTH) -> DataFrame:
    """Cells of keys' ids by the same combinable aggregation as the batch build: state is one row a cell (complete or update mode)."""
    return sketch.build_cells(rows, keys, depth, width)


def stream_votes(rows: DataFrame, key: str, depth: int = sketch.DEPTH, width: int = sketch.WIDTH) -> DataFrame:
    """(key, row, col, total, cand, votes) with votes by arrival: state is one cell, three numbers, whatever arrives.

    A cell's rows of a batch pass through one task in Arrow parts, so memory is bounded but a hot key is slow: where a
    key may hold much of the stream, use `stream_cells`, which combines before the shuffle. Update mode.
    """
    counted = sketch.spread(rows.select(F.col(key).cast("string").alias("key"), F.col("id").cast("long")), depth, width)

    def insert(cell, parts: Iterator[pd.DataFrame], state: GroupState):
        total, cand, votes = state.get if state.exists else (0, 0, 0)
        for part in parts:
            for ident, w in part.groupby("id", sort=True).size().items():
                total += int(w)
                if cand == ident:
                    votes += int(w)
                elif votes >= w:
                    votes -= int(w)
                else:
                    cand, votes = int(ident), int(w) - votes
        state.update((total, cand, votes))
        yield pd.DataFrame([(*cell, total, cand, votes)], columns=["key", "row", "col", "total", "cand", "votes"])

    return counted.groupBy("key", "row", "col").applyInPandasWithState(insert, "key string, row int, col int, total long, cand long, votes long", "total long, cand long, votes long", "update", GroupStateTimeout.NoTimeout)


def distinct_arrivals(events: DataFrame, columns: list[str]) -> DataFrame:
    """First arrivals only, remembered as long as the watermark allows."""
    return events.dropDuplicatesWithinWatermark(columns)


def drain(stream: DataFrame, name: str, mode: str = "append", then: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Runs a stream to the end of what is there and returns the rows it wrote, with `batch` for modes other than append.

    Append goes to the Parquet sink (its log makes files count once). Other modes, and `then`, a function of each batch,
    write one folder a batch, which a repeated batch overwrites.
    """
    spark = stream.sparkSession
    root = shared_folder(spark, f"stream-{name}")
    start = stream.writeStream.option("checkpointLocation", f"{root}/log").trigger(availableNow=True)
    if mode == "append" and then is None:
        start.format("parquet").option("path", f"{root}/rows").outputMode("append").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{root}/rows")
    schema = []

    def put(batch: DataFrame, number: int) -> None:
        rows = then(batch) if then else batch
        schema[:] = [rows.schema]
        rows.write.mode("overwrite").parquet(f"{root}/rows/batch={number}")

    start.foreachBatch(put).outputMode(mode).start().awaitTermination()
    if not schema:
        return spark.createDataFrame([], stream.schema).withColumn("batch", F.lit(0))
    return spark.read.schema(T.StructType([*schema[0].fields, T.StructField("batch", T.IntegerType())])).parquet(f"{root}/rows")


def latest(drained: DataFrame, keys: list[str]) -> DataFrame:
    """The last state of each key of an update-mode stream."""
    values = [c for c in drained.columns if c not in (*keys, "batch")]
    return drained.groupBy(*keys).agg(F.max_by(F.struct(*values), "batch").alias("v")).select(*keys, "v.*")


def in_files(rows: DataFrame, by: str, parts: int, name: str) -> str:
    """rows as `parts` files in the order of `by`, written one after another: replays a history as a stream."""
    path = shared_folder(rows.sparkSession, name)
    low, high = rows.agg(F.min(by), F.max(by)).first()
    step = (high - low) / parts if low is not None else None
    for i in range(parts if step is not None else 1):
        part = rows if step is None else rows.where((F.col(by) >= F.lit(low + step * i)) if i else F.lit(True)).where((F.col(by) < F.lit(low + step * (i + 1))) if i < parts - 1 else F.lit(True))
        part.coalesce(1).write.mode("append").parquet(path)
    return path


def keep_share(ident: Column, share: int) -> Column:
    """One in `share` ids by hash."""
    return token_number(ident) % share == 0
