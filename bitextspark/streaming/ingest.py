"""Pair ingest and event streams on Structured Streaming, run to the end of what is there (AvailableNow) where a batch result is wanted."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.filters import FilterCascade


def folder(spark: SparkSession, tag: str) -> str:
    """A new folder below the shared checkpoint folder (our own where none is set)."""
    base = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if not base:
        import tempfile

        base = tempfile.mkdtemp(prefix="bitextspark-")
    return f"{base.rstrip('/')}/stream-{uuid.uuid4().hex}/{tag}"


def read_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table as a stream of its files. A table that is one file is found by its name in its folder, since a stream's source is a folder."""
    path = f"{sf_dir}/{name}.parquet"
    batch = spark.read.parquet(path)
    source = spark.readStream.schema(batch.schema)
    if batch.inputFiles()[0].endswith(f"/{name}.parquet"):
        return source.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)
    return source.parquet(path)


def drain(stream: DataFrame, mode: str = "append", tag: str = "out") -> DataFrame:
    """Run a stream until its sources are read and give what it has written as a batch.

    Batches go to Parquet by foreachBatch, each into its own folder, so a batch
    that is repeated after a failure replaces itself.
    """
    spark, path = stream.sparkSession, folder(stream.sparkSession, tag)
    # complete and update modes send rows again: each batch's number stays with them
    sink = lambda df, n: df.withColumn("__batch", F.lit(n)).write.mode("overwrite").parquet(f"{path}/data/b={n}")
    q = stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    schema = type(stream.schema)([*stream.schema.fields]).add("__batch", "integer")
    out = spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(f"{path}/data")
    if mode == "complete":
        last = out.agg(F.max("__batch").alias("m"))
        out = out.join(F.broadcast(last), F.col("__batch") == F.col("m")).drop("m")  # one row
    return out.drop("__batch")


def filtered(stream: DataFrame, cascade: FilterCascade) -> DataFrame:
    """The row rules of a cascade on a stream: they hold no state."""
    return cascade.apply(stream)


def deduplicated(stream: DataFrame, keys: list[str], time: str, late: str = "1 hour") -> DataFrame:
    """One of each key within the watermark: repeats that come later than that are new to it, unlike in a batch."""
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)


def tumbling(stream: DataFrame, time: str, width: str, late: str = "10 minutes", by: tuple[str, ...] = ()) -> DataFrame:
    out = stream.withWatermark(time, late).groupBy(F.window(time, width), *by).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return out.select(F.col("window.start").alias("start"), *by, "n", "total")


def sliding(stream: DataFrame, time: str, width: str, step: str, late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.window(time, width, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(stream: DataFrame, time: str, user: str, gap: str, late: str = "10 minutes") -> DataFrame:
    out = stream.withWatermark(time, late).groupBy(F.session_window(time, gap), user).agg(F.count("*").alias("n"))
    return out.select(user, F.col("session_window.start").alias("start"), "n")


def interval_join(left: DataFrame, right: DataFrame, on: str, most: str = "10 minutes") -> DataFrame:
    """Stream-stream join: right (r_ts) at most an interval behind left (l_ts) for the same key; both have watermarks."""
    return left.withWatermark("l_ts", most).join(right.withWatermark("r_ts", most).withColumnRenamed(on, "__k"), F.expr(f"{on} = __k AND r_ts > l_ts AND r_ts <= l_ts + INTERVAL {most}")).drop("__k")


def running_stats(stream: DataFrame, key: str) -> DataFrame:
    """(key, n, total) after each batch, by a stateful function over Arrow batches: state is two numbers a key."""

    def update(k, frames, state):
        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({key: [k[0]], "n": [n], "total": [total]})

    kind = stream.schema[key].dataType.simpleString()
    return stream.select(key, "value").groupBy(key).applyInPandasWithState(update, f"{key} {kind}, n long, total double", "n long, total double", "update", "NoTimeout")
