"""Streams of arriving records: windowed bin counts, sessions, links with an encoded side, noisy counts.

Each function runs its stream over what the files hold now (availableNow) and returns the result as a
batch. State and results go below the folder that spark.checkpoint.dir names.
"""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fairlink.functions import rng
from fairlink.sources import steps


def _folder(spark: SparkSession) -> str:
    """A fresh folder that driver and executors share."""
    return steps.folder(spark, "stream")


def source(spark: SparkSession, path: str) -> DataFrame:
    """A file stream over one table, with the table's own schema."""
    schema = spark.read.parquet(path).schema
    folder, name = os.path.split(path.rstrip("/"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(_glob(folder, name))
    # Event time needs an instant; the tables hold times without a zone, read in the session's.
    return stream.withColumns({f.name: F.col(f.name).cast("timestamp") for f in schema if f.dataType.typeName() == "timestamp_ntz"})


def _glob(folder: str, name: str) -> str:
    # A stream reads folders or patterns; this pattern names the one table.
    return f"{folder}/{name[:-1]}[{name[-1]}]"


def run(stream: DataFrame, spark: SparkSession, mode: str = "append", folder: str | None = None) -> DataFrame:
    """The stream's output over all that is there. Append writes files, complete a memory table. In a folder of an earlier run it goes on."""
    folder = folder or _folder(spark)
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{folder}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/out")
    name = f"s{uuid.uuid4().hex}"
    writer.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def windowed(spark: SparkSession, path: str, size: str, slide: str | None = None) -> DataFrame:
    """Events per window and type: tumbling, or sliding with a step."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    counts = source(spark, path).withWatermark("ts", "1 hour").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return run(counts, spark, "complete").select("w.start", "event_type", "n")


#: Every row of a table counts, however late it comes: so long a session's state is kept open.
LATEST = "36500 days"


def sessions(spark: SparkSession, path: str, gap: str) -> DataFrame:
    """Events per user and session.

    Append mode writes sessions to files from the executors, none to the driver, but closed ones only. So the stream
    reads a second folder too: it is empty at first, and when all events are in the state it gets one row
    of no user, later than any event, with which the stream goes on, and which closes them.
    """
    folder = _folder(spark)
    end = spark.sql("SELECT CAST(NULL AS BIGINT) AS user_id, TIMESTAMP'9999-01-01' AS ts, true AS closing")
    end.limit(0).write.parquet(f"{folder}/end")
    events = source(spark, path).select(F.col("user_id").cast("long").alias("user_id"), "ts", F.lit(False).alias("closing"))
    both = events.unionByName(spark.readStream.schema(end.schema).parquet(f"{folder}/end")).withWatermark("ts", LATEST)
    counts = both.groupBy(F.session_window("ts", gap).alias("w"), "user_id", "closing").agg(F.count("*").alias("n"))
    run(counts, spark, folder=folder)
    end.write.mode("append").parquet(f"{folder}/end")
    return run(counts, spark, folder=folder).where("NOT closing").select("user_id", "w.start", "n")


def deduplicated(spark: SparkSession, path: str) -> DataFrame:
    """Events per type with repeated ids dropped."""
    fresh = source(spark, path).withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["event_id"])
    return run(fresh.select("event_id", "event_type"), spark).groupBy("event_type").agg(F.count("*").alias("n"))


def linked(spark: SparkSession, path: str, known: DataFrame) -> DataFrame:
    """Arriving events joined with a static table of known records."""
    found = source(spark, path).join(known, F.col("user_id") == F.col("c_custkey")).select("c_custkey", "event_id")
    return run(found, spark).groupBy("c_custkey").agg(F.count("*").alias("n"))


def noisy(spark: SparkSession, path: str, size: str, eps: float, seed: int = 7) -> DataFrame:
    """Counts of closed windows with one keyed draw each, the same after a replay."""
    counts = windowed(spark, path, size)
    x = rng.laplace(rng.uniform(seed, "stream", F.unix_micros("start"), "event_type"), 1.0 / eps)
    return counts.select("start", "event_type", F.greatest(F.lit(0), F.col("n") + F.floor(x + 0.5)).cast("long").alias("n"))


def stateful_noisy(events: DataFrame, eps: float, seed: int = 7) -> DataFrame:
    """Running count and noisy count per event type, kept in state between batches."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key: tuple, frames: Iterator, state: GroupState):
        import hashlib
        import math

        import pandas as pd

        total = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((total,))
        draw = (int(hashlib.md5(f"{seed}|state|{key[0]}|{total}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52
        noise = -math.copysign(1, draw - 0.5) * math.log(1 - 2 * abs(draw - 0.5)) / eps
        yield pd.DataFrame({"event_type": [key[0]], "n": [total], "noisy": [max(0, total + math.floor(noise + 0.5))]})

    return events.groupBy("event_type").applyInPandasWithState(update, "event_type string, n long, noisy long", "n long", "update", GroupStateTimeout.NoTimeout)
