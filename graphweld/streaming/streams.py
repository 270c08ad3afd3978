"""Triples as streams: incremental functionality, windows, sessions, duplicates and micro-batches.

Functionality may fall when facts arrive, so counts are kept and the value is
derived from them; scores of touched relations are recomputed, never raised.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphweld.plans.lineage import delete_folder, shared_folder, table


def events(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """The events table replayed by the file source."""
    schema = table(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", "events.parquet*").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def triples(stream: DataFrame) -> DataFrame:
    """(ts, h, r, t): what users did."""
    return stream.select("ts", F.concat(F.lit("customer/"), F.col("user_id").cast("string")).alias("h"), F.lit("did").alias("r"), F.concat(F.lit('"'), "event_type").alias("t"))


def drain(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over what is there and returns the final table, written in the shared folder: no row comes to the driver. mode: append or complete.

    In complete mode every micro-batch is the whole table, so the last one stays.
    """
    spark = stream.sparkSession
    home = f"{shared_folder(spark)}/s_{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{home}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{home}/rows").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{home}/rows")
    done: list[str] = []

    def write(batch: DataFrame, k: int) -> None:
        path = f"{home}/rows-{k}"
        batch.write.mode("overwrite").parquet(path)
        for old in done:
            if old != path:
                delete_folder(spark, old)
        done[:] = [path]

    writer.foreachBatch(write).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(done[0]) if done else spark.createDataFrame([], stream.schema)


def late_rows(parts: list[DataFrame], key: str, late: str = "10 minutes") -> list[int]:
    """How many rows of each part (key, ts, ...) came after the watermark had passed them, by the counter of the operator that drops them.

    The parts arrive one after the other. Each is a run of the same query,
    which goes on from its checkpoint as it does after a restart.
    """
    spark = parts[0].sparkSession
    home = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    found = []
    for part in parts:
        part.write.mode("append").parquet(f"{home}/rows")
        rows = spark.readStream.schema(part.schema).parquet(f"{home}/rows").withWatermark("ts", late).dropDuplicatesWithinWatermark([key])
        query = rows.writeStream.outputMode("append").format("noop").option("checkpointLocation", f"{home}/state").trigger(availableNow=True).start()
        query.awaitTermination()
        found.append(sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"]))
    return found


def functionality(facts: DataFrame) -> DataFrame:
    """(r, h, n): tails of each head so far; fun(r, h) is 1/n and fun(r) the heads over the sum."""
    return facts.groupBy("r", "h").agg(F.count(F.lit(1)).alias("n"))


def tumbling(stream: DataFrame, every: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", every).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sliding(stream: DataFrame, length: str = "2 hours", every: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", length, every).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))


def distinct_facts(facts: DataFrame, late: str = "3650 days") -> DataFrame:
    """Set semantics on a stream."""
    return facts.withWatermark("ts", late).dropDuplicatesWithinWatermark(["h", "r", "t"])


def each_batch(stream: DataFrame, work: Callable[[DataFrame, int], None]) -> None:
    """Runs ``work`` on every micro-batch until the stream is drained."""
    spark = stream.sparkSession
    home = f"{shared_folder(spark)}/b_{uuid.uuid4().hex}"
    stream.writeStream.foreachBatch(work).option("checkpointLocation", home).trigger(availableNow=True).start().awaitTermination()


def with_matches(facts: DataFrame, matches: DataFrame) -> DataFrame:
    """Stream-static join: new facts whose heads have stored matches (h, h2)."""
    return facts.join(matches, "h")


def both_sides(a: DataFrame, b: DataFrame, seconds: int = 60, late: str = "10 minutes") -> DataFrame:
    """Stream-stream join of facts of two graphs about the same head within a time band."""
    x = a.withWatermark("ts", late)
    y = b.withWatermark("ts", late).withColumnsRenamed({"ts": "ts2", "h": "h2", "r": "r2", "t": "t2"})
    band = F.expr(f"h = h2 AND ts2 BETWEEN ts - INTERVAL {seconds} SECONDS AND ts + INTERVAL {seconds} SECONDS")
    return x.join(y, band)
