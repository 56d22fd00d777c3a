"""The queue of ready packages as Structured Streaming, and the operators around it."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans.scratch import folder

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def items(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A file source of events as work items; the time column is made a timestamp for watermarks."""
    folder_, _, name = path.rstrip("/").rpartition("/")
    reader = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger)
    # one file of a folder is picked by its name: a stream reads folders
    raw = reader.option("pathGlobFilter", name).parquet(folder_) if _is_file(spark, path) else reader.parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def _is_file(spark: SparkSession, path: str) -> bool:
    jvm = spark._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isFile()


def packer(limit: int):
    """State of a case: the open list (its number and size). Emits each item with its list; a batch is put in id order."""

    def run(key, frames, state: GroupState):
        number, filled = state.get if state.exists else (0, 0)
        got = pd.concat(list(frames)).sort_values("event_id")
        lists = []
        for size in got["bytes"]:
            if filled and filled + size >= limit:
                number, filled = number + 1, 0
            filled += int(size)
            lists.append(number)
        state.update((number, filled))
        yield pd.DataFrame({"case": key[0], "event_id": got["event_id"], "bytes": got["bytes"], "list": lists})

    return run


def packed(stream: DataFrame, limit: int) -> DataFrame:
    """stream(event_id, case, bytes) -> (case, event_id, bytes, list)."""
    return stream.groupBy("case").applyInPandasWithState(packer(limit), "case string, event_id long, bytes long, list long", "number long, filled long", "append", GroupStateTimeout.NoTimeout)


def finished(stream: DataFrame, mode: str = "append", late: bool = False):
    """Runs a stream over all that is there, into a table of files, and returns it as a batch frame (and the drops)."""
    spark = stream.sparkSession
    out, check = folder(spark), folder(spark)
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", check).trigger(availableNow=True).start()
    else:
        def write(df: DataFrame, batch: int) -> None:  # idempotent: each batch overwrites the whole result
            df.write.mode("overwrite").parquet(out)

        q = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", check).trigger(availableNow=True).start()
    q.awaitTermination()
    dropped = sum(o.numRowsDroppedByWatermark for p in q.recentProgress for o in p.stateOperators)
    frame = spark.read.schema(stream.schema).parquet(out)
    return (frame, dropped) if late else frame


def deduplicated(stream: DataFrame, key: str, delay: str = "40 days") -> DataFrame:
    """The same item sent twice within the watermark counts once."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def windows(stream: DataFrame, length: str, slide: str | None = None, delay: str = "40 days") -> DataFrame:
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return stream.withWatermark("ts", delay).groupBy(w, "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def sessions(stream: DataFrame, gap: str, delay: str = "40 days") -> DataFrame:
    return stream.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def with_panels(stream: DataFrame, panels: DataFrame, n: int) -> DataFrame:
    """Stream-static join: an event adds its value to the density of panel user_id mod n."""
    return stream.withColumn("pid", F.pmod("user_id", F.lit(n))).join(panels, "pid")


def matched(requests: DataFrame, finishes: DataFrame, within: str = "1 hour", delay: str = "40 days") -> DataFrame:
    """Interval join of two streams of one user: finishes at most `within` after a request."""
    a = requests.select(F.col("user_id").alias("u"), F.col("ts").alias("t0"), F.col("event_id").alias("e0")).withWatermark("t0", delay)
    b = finishes.select("user_id", "ts", "event_id").withWatermark("ts", delay)
    return a.join(b, F.expr(f"u = user_id and ts >= t0 and ts <= t0 + interval {within}"))


def incremental(potential: DataFrame, column_entries: DataFrame, changes: DataFrame) -> DataFrame:
    """Adds V times the changes (i, value) of the density to a potential (i, value): linearity, not a new product."""
    delta = column_entries.join(changes.select(F.col("i").alias("j"), F.col("value").alias("d")), "j").groupBy("i").agg(F.sum(F.col("re") * F.col("d")).alias("value"))
    return potential.unionByName(delta).groupBy("i").agg(F.sum("value").alias("value"))
