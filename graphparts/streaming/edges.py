"""Edge streams: counts by window, running cut against a partition, and online assignment of new vertices."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from graphparts.plans.scratch import shared_folder, written


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """``events`` as a stream, whether the table is one file or a folder of files."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger)
    one_file = spark.read.parquet(path).inputFiles()[0].rstrip("/").endswith("/events.parquet")
    stream = reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if one_file else reader.parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def hourly_edges(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """``(user_id, hour, events)``: the edges of users to hours; rows later than ``delay`` are dropped."""
    w = F.window("ts", "1 hour")
    counted = events.withWatermark("ts", delay).groupBy("user_id", w).agg(F.count("*").alias("events"))
    return counted.select("user_id", F.col("window.start").alias("hour"), "events")


def session_edges(events: DataFrame, gap: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    w = F.session_window("ts", gap)
    return events.withWatermark("ts", delay).groupBy("user_id", w).agg(F.count("*").alias("events")).select("user_id", F.col("session_window.start").alias("begun"), "events")


def sliding_edges(events: DataFrame, width: str = "2 hours", step: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """Like :func:`hourly_edges`, in windows that overlap."""
    w = F.window("ts", width, step)
    counted = events.withWatermark("ts", delay).groupBy("user_id", w).agg(F.count("*").alias("events"))
    return counted.select("user_id", F.col("window.start").alias("hour"), "events")


def part_load(touched: DataFrame, parts: DataFrame) -> DataFrame:
    """A stream of touched vertices ``(v)`` against a fixed partition: how often each part is touched."""
    return touched.join(parts, "v").groupBy("part").agg(F.count("*").alias("events"))


def alerts(load: DataFrame, p: int, tolerance: float = 0.1) -> DataFrame:
    """``load(part, events)`` with its imbalance, and whether it exceeds ``1 + tolerance``: the sign to refine the partition."""
    total = load.agg(F.sum("events").alias("total"))  # one row
    x = load.crossJoin(F.broadcast(total))
    return x.select("part", "events", F.round(F.col("events") * p / F.col("total"), 6).alias("imbalance"), (F.col("events") * p > (1 + tolerance) * F.col("total")).alias("alert"))


def late_rows(rows: DataFrame, order: str, time: str, delay_seconds: int, slices: int = 64) -> DataFrame:
    """The rows more than ``delay_seconds`` behind the latest time that came before them, in arrival ``order``.

    What a watermark that moves with every row would drop. Latest times of runs of rows are carried
    from run to run, so no task sees all rows.
    """
    runs = written(rows.repartitionByRange(slices, order).withColumn("_run", F.spark_partition_id()), "arrivals")
    tops = runs.groupBy("_run").agg(F.max(time).alias("_top"))  # a row for each run
    before = tops.select("_run", F.max("_top").over(Window.orderBy("_run").rowsBetween(Window.unboundedPreceding, -1)).alias("_before"))
    inside = F.max(time).over(Window.partitionBy("_run").orderBy(order).rowsBetween(Window.unboundedPreceding, -1))
    known = runs.withColumn("_inside", inside).join(F.broadcast(before), "_run").withColumn("_latest", F.greatest("_inside", "_before"))
    return known.where(F.col(time) < F.col("_latest") - F.expr(f"make_dt_interval(0, 0, 0, {delay_seconds})")).drop("_run", "_inside", "_before", "_latest")


def dropped_late(query) -> int:
    """Rows that a running or ended streaming query dropped as later than its watermark."""
    return sum(int(s.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for s in (p["stateOperators"] if isinstance(p, dict) else json.loads(p.json)["stateOperators"]))


def running_cut(edges: DataFrame, parts: DataFrame) -> DataFrame:
    """A stream of ``(src, dst)`` against a fixed partition: edges seen and cut, by pair of parts."""
    s, d = parts.select(F.col("v").alias("src"), F.col("part").alias("a")), parts.select(F.col("v").alias("dst"), F.col("part").alias("b"))
    return edges.join(s, "src").join(d, "dst").groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.count("*").alias("edges"))


def assign_online(edges: DataFrame, p: int, cap: int) -> DataFrame:
    """New vertices ``(bucket, v, u)`` take, within a bucket, the part most of their known neighbours have, if it holds fewer than ``cap``; else the smallest.

    Each bucket keeps its own vertices and sizes, so buckets are independent and their number bounds the state of one.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        known, sizes = (list(x) for x in state.get) if state.exists else ([], [0] * p)
        of = dict(zip(known[::2], known[1::2], strict=True)) if known else {}
        out = []
        for frame in batches:
            for v, near in frame.sort_values(["v", "u"]).groupby("v", sort=True)["u"]:
                if v in of:
                    continue
                votes = [0] * p
                for u in near:
                    if u in of:
                        votes[of[u]] += 1
                best = max(range(p), key=lambda i: (votes[i] if sizes[i] < cap else -1, -sizes[i], -i))
                of[int(v)] = best
                sizes[best] += 1
                out.append((key[0], int(v), best))
        state.update(([x for kv in of.items() for x in kv], sizes))
        yield pd.DataFrame(out, columns=["bucket", "v", "part"])

    return edges.groupBy("bucket").applyInPandasWithState(step, "bucket int, v bigint, part int", "known array<bigint>, sizes array<bigint>", "append", GroupStateTimeout.NoTimeout)


def drained(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Run ``stream`` over what is there now; the last complete result, or all appended rows, as a table."""
    spark = stream.sparkSession
    base = f"{shared_folder(spark)}/{name}-{stream._jdf.hashCode() & 0xFFFFFF}-{spark.sparkContext.startTime}-{id(stream)}"

    def keep(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite" if mode == "complete" else "append").parquet(f"{base}/rows")

    stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/rows")
