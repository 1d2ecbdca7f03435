"""Incremental evidence over an event stream: windows, sessions, uniqueness within a watermark, drift alerts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semcat.functions.shared import folder


def source(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """The events table of a folder as a stream, with its schema read from the files; new files are new batches."""
    schema = spark.read.parquet(path).schema
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    folder, _, name = path.rpartition("/")
    s = raw.option("pathGlobFilter", name).parquet(folder) if name.endswith(".parquet") else raw.parquet(path)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "complete", batch: Callable[[DataFrame, int], None] | None = None) -> DataFrame | None:
    """Run a stream over what is there and stop. Each micro-batch is written below its number in the shared folder, so a batch that
    is run again replaces itself; the result is what the last batch (complete) or all batches (append) wrote. With ``batch``
    each micro-batch goes to it instead."""
    spark = stream.sparkSession
    base = folder(spark, "stream")
    w = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{base}/checkpoint")
    if batch:
        w.foreachBatch(batch).start().awaitTermination()
        return None
    done: list[int] = []

    def keep(df: DataFrame, i: int) -> None:
        df.write.mode("overwrite").parquet(f"{base}/out/{i}")
        done.append(i)

    w.outputMode(mode).foreachBatch(keep).start().awaitTermination()
    if not done:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*[f"{base}/out/{i}" for i in (done[-1:] if mode == "complete" else done)])


def replayed(spark: SparkSession, parts: list[DataFrame]) -> DataFrame:
    """A stream that brings the parts one after the other, a micro-batch each."""
    at = folder(spark, "replay")
    for i, p in enumerate(parts):
        p.coalesce(1).write.parquet(f"{at}/{i}")
    raw = spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True)
    return raw.parquet(at)


def recheck_key(stream: DataFrame, columns: list[str]) -> list[tuple[int, bool]]:
    """(rows, passed) of each micro-batch: the claim that the columns identify rows, over this batch and all before. The keys seen
    so far are a table of hashes in the shared folder; a batch meets it in a join, and nothing but counts reaches the driver."""
    at, out = folder(stream.sparkSession, "keys"), []

    def check(df: DataFrame, i: int) -> None:
        keyed = df.select(F.xxhash64(*columns).alias("a"), F.xxhash64(F.lit(7), *columns).alias("b"))
        r = keyed.groupBy("a", "b").count().agg(F.sum("count").alias("n"), F.max("count").alias("most")).first()
        again = 0
        if out:
            seen = df.sparkSession.read.schema(keyed.schema).parquet(*[f"{at}/{k}" for k in range(len(out))])
            again = keyed.join(seen, ["a", "b"], "left_semi").limit(1).count()
        keyed.write.mode("overwrite").parquet(f"{at}/{len(out)}")
        out.append((r["n"] or 0, (r["most"] or 0) <= 1 and not again))

    drain(stream, batch=check)
    return out


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", "2 days").groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("window_start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", "3 days").groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n")).select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("window_start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.withWatermark("ts", "2 days").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


def deduplicated(events: DataFrame, within: str = "7 days") -> DataFrame:
    """Repeated ids within the watermark are dropped, and ids are forgotten after it; over an endless stream only that much can be
    promised."""
    return events.withWatermark("ts", within).dropDuplicatesWithinWatermark(["event_id"])


def new_categories(events: DataFrame, known: DataFrame) -> DataFrame:
    """Rows whose category is not in the static list of the catalog."""
    return events.join(known.select("event_type"), "event_type", "left_anti")
