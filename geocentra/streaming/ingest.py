"""Event streams as graphs: arcs as they come, windows, sketches per key, and a snapshot a day."""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from geocentra.graph.model import Graph
from geocentra.operators.ordered import succession_in_steps
from geocentra.plans.checkpoint import own_folder
from geocentra.propagate.balls import ball_sketches
from geocentra.sketch.registers import alpha, register_of

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """A file stream of events with a fixed schema."""
    folder, _, name = path.rpartition("/")
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", name).parquet(folder)


def run_to_end(stream: DataFrame, mode: str = "append", each=None) -> DataFrame | None:
    """Run a stream over all that is there. Without `each`, its output comes back as a table of the shared folder."""
    spark = stream.sparkSession
    folder = f"{own_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{folder}/state").trigger(availableNow=True)
    if each is not None:
        writer.outputMode(mode).foreachBatch(each).start().awaitTermination()
        return None
    if mode == "append":
        writer.outputMode("append").format("parquet").option("path", f"{folder}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/out")

    def keep(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{folder}/out/batch={batch}")

    writer.outputMode(mode).foreachBatch(keep).start().awaitTermination()
    rows = spark.read.schema(stream.schema.add("batch", "integer")).parquet(f"{folder}/out")
    if mode == "complete":
        return rows.join(rows.agg(F.max("batch").alias("batch")), "batch").drop("batch")
    return rows


def arcs_of_days(events: DataFrame) -> DataFrame:
    """src, dst: the user of an event -> the user of the next event of the day."""
    return succession_in_steps(events, F.to_date("ts"), F.date_trunc("second", "ts"), ["ts", "event_id"], "user_id")


def stream_arcs(spark: SparkSession, path: str) -> DataFrame:
    """Arcs of a stream, appended batch by batch; a batch that is run again overwrites its own output.

    A day's arcs are right once all its events have come in one batch, as with a file a day.
    """
    folder = f"{own_folder(spark)}/arcs-{uuid.uuid4().hex}"

    def append(df: DataFrame, batch: int) -> None:
        arcs_of_days(df).write.mode("overwrite").parquet(f"{folder}/batch={batch}")

    run_to_end(event_stream(spark, path), each=append)
    return spark.read.schema("src long, dst long, batch int").parquet(folder).select("src", "dst").distinct()


def counts_by_window(stream: DataFrame, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """start, event_type, n by tumbling or sliding windows, behind a watermark."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    rows = stream.withWatermark("ts", late) if stream.isStreaming else stream
    return rows.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """user_id, start, end, n of sessions: events of a user no further apart than `gap`."""
    rows = stream.withWatermark("ts", late) if stream.isStreaming else stream
    return rows.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def registers_by_type(stream: DataFrame, p: int = 64) -> DataFrame:
    """event_type, reg, rho: a counter of users per type, kept as a streaming maximum."""
    reg, rho = register_of(F.concat_ws(":", F.lit(0), F.col("user_id").cast("string")), p)
    return stream.select("event_type", reg.alias("reg"), rho.alias("rho")).groupBy("event_type", "reg").agg(F.max("rho").alias("rho"))


def counters_by_type(stream: DataFrame, p: int = 64) -> DataFrame:
    """event_type, size: as registers_by_type, with a state of p bytes a type that a function of its own keeps."""
    reg, rho = register_of(F.concat_ws(":", F.lit(0), F.col("user_id").cast("string")), p)
    rows = stream.select("event_type", reg.alias("reg"), rho.alias("rho"))

    def update(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        regs = np.frombuffer(state.get[0], np.uint8).copy() if state.exists else np.zeros(p, np.uint8)
        for batch in batches:
            np.maximum.at(regs, batch["reg"].to_numpy(), batch["rho"].to_numpy().astype(np.uint8))
        state.update((regs.tobytes(),))
        s, z = (2.0 ** -regs.astype(float)).sum(), int((regs == 0).sum())
        raw = alpha(p) * p * p / s
        yield pd.DataFrame({"event_type": [key[0]], "size": [p * math.log(p / z) if raw <= 2.5 * p and z else raw]})

    return rows.groupBy("event_type").applyInPandasWithState(update, "event_type string, size double", "regs binary", "update", GroupStateTimeout.NoTimeout)


#: Users have smaller ids; the day is in the bits above.
USER_BITS = 40


def snapshot_centrality(events: DataFrame, p: int = 64) -> DataFrame:
    """day, node, size: the coreachable estimate of every user in each day's own graph.

    The days' graphs are one graph of disjoint copies, so that one propagation serves all days.
    """
    day = F.datediff(F.to_date("ts"), F.lit("1970-01-01").cast("date")).cast("long")
    fits = (F.col("user_id") >= 0) & (F.col("user_id") < F.lit(1 << USER_BITS))
    node = F.when(fits, F.shiftleft(day, USER_BITS) + F.col("user_id")).otherwise(F.raise_error(F.lit(f"a user id is beyond {USER_BITS} bits")).cast("long"))
    arcs = succession_in_steps(events.select("ts", "event_id", node.alias("node")), F.to_date("ts"), F.date_trunc("second", "ts"), ["ts", "event_id"], "node")
    run = ball_sketches(Graph.from_arcs(arcs), p)
    last = run.profile().groupBy("node").agg(F.max_by("size", "t").alias("size"))
    return last.select(F.shiftright("node", USER_BITS).cast("int").alias("day"), F.col("node").bitwiseAND(F.lit((1 << USER_BITS) - 1)).alias("node"), "size")


def stream_snapshots(spark: SparkSession, path: str, where: str = "true", p: int = 64) -> DataFrame:
    """Snapshots of a stream: after each batch those of the days in it, in place of earlier ones. Batches keep the events of a day they begin."""
    folder = f"{own_folder(spark)}/snapshots-{uuid.uuid4().hex}"

    def update(df: DataFrame, batch: int) -> None:
        df.where(where).write.mode("overwrite").parquet(f"{folder}/events/batch={batch}")
        days = df.select(F.to_date("ts").alias("day")).distinct()
        so_far = spark.read.schema(EVENTS + ", batch int").parquet(f"{folder}/events").drop("batch")
        of_days = so_far.join(days, F.to_date("ts") == F.col("day"), "left_semi")
        snapshot_centrality(of_days, p).write.mode("overwrite").parquet(f"{folder}/out/batch={batch}")

    run_to_end(event_stream(spark, path), each=update)
    rows = spark.read.schema("day int, node long, size double, batch int").parquet(f"{folder}/out")
    last = rows.groupBy("day").agg(F.max("batch").alias("batch"))
    return rows.join(last, ["day", "batch"]).select("day", "node", "size")
