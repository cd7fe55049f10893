"""Latency of micro-batches, scaling and state loads; taken from raw runs, not private outputs."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQueryListener

from .operators.timing import assign_triggers
from .spec import StreamSpec
from .streaming import microbatch

TIMES = "size double, cores int, run int, trigger_idx int, rows long, millis double"


class BatchTimer(StreamingQueryListener):
    """Rows, duration and rate of every batch of the session's streaming queries, oldest first; keeps the newest `keep`."""

    def __init__(self, keep: int = 10_000):
        self.keep, self.batches = keep, []

    def onQueryStarted(self, event):
        pass

    def onQueryProgress(self, event):
        p = event.progress
        self.batches.append((str(p.id), p.batchId, p.numInputRows, float(p.durationMs.get("triggerExecution", 0)), float(p.processedRowsPerSecond)))
        del self.batches[: -self.keep]

    def onQueryIdle(self, event):
        pass

    def onQueryTerminated(self, event):
        pass

    def rows(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.batches, "query string, batch long, rows long, millis double, rows_per_s double")


def latency_grid(records: dict[float, DataFrame], spec: StreamSpec, root: str, triggers: int, runs: int = 2) -> DataFrame:
    """Wall time of the first `triggers` micro-batches for record frames by size; one row a batch and run.

    Cores are those of the session: repeat with other sessions for a grid of workers.
    """
    out, spark = [], None
    for size, frame in records.items():
        spark = frame.sparkSession
        src = f"{root.rstrip('/')}/latency-{uuid.uuid4().hex}"
        assign_triggers(frame, spec.timing.triggers, spec.timing.assign).write.partitionBy("trigger_idx").parquet(f"{src}/in")
        batches = spark.read.parquet(f"{src}/in")
        for run in range(runs):
            tables = microbatch.StateTables(spark, f"{src}/state-{run}")
            for i in range(1, triggers + 1):
                batch = batches.filter(F.col("trigger_idx") == i)
                n, start = batch.count(), time.perf_counter()
                microbatch.step(tables, batch, i, spec)
                out.append((float(size), spark.sparkContext.defaultParallelism, run, i, n, (time.perf_counter() - start) * 1000))
    return spark.createDataFrame(out, TIMES)


def latency(times: DataFrame) -> DataFrame:
    """size, cores, millis with standard error over runs, rows a second."""
    per = times.groupBy("size", "cores", "run").agg(F.avg("millis").alias("m"), (F.sum("rows") / F.sum("millis") * 1000).alias("rate"))
    return per.groupBy("size", "cores").agg(F.avg("m").alias("millis"), (F.coalesce(F.stddev("m"), F.lit(0.0)) / F.sqrt(F.count(F.lit(1)))).alias("millis_se"), F.avg("rate").alias("rows_per_s"))


def scaling(latencies: DataFrame) -> DataFrame:
    """Latency growth from the smallest to the largest size of a core count, and the cut by the most cores at a size."""
    by_size = latencies.groupBy("cores").agg(F.max("size").alias("size"), (F.max("size") / F.min("size")).alias("data_growth"), (F.max_by("millis", "size") / F.min_by("millis", "size")).alias("latency_growth"))
    by_cores = latencies.groupBy("size").agg((1 - F.max_by("millis", "cores") / F.min_by("millis", "cores")).alias("cut_by_cores"))
    return by_size.join(by_cores, "size").select("size", "cores", "data_growth", "latency_growth", "cut_by_cores")
