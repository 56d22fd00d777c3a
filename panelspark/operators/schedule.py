"""Who runs a package, and how busy the workers are."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def dispatch(packages: DataFrame, affinity: Column, accelerated, host) -> DataFrame:
    """Splits packages by affinity and runs two branches of one plan: Arrow batches and generated code."""
    rows = packages.withColumn("route", F.when(affinity, F.lit("accelerator")).otherwise(F.lit("host")))
    return accelerated(rows.where("route = 'accelerator'")).unionByName(host(rows.where("route = 'host'")))


def hybrid_split(packages: DataFrame, share: float, key: str) -> DataFrame:
    """Sends about a share of the packages, by a hash of their key, to the accelerators."""
    return packages.withColumn("route", F.when(F.pmod(F.xxhash64(key), F.lit(1000)) < int(share * 1000), F.lit("accelerator")).otherwise(F.lit("host")))


def proportional_cut(packages: DataFrame, rates: list[float], size: str, order: list[str]) -> DataFrame:
    """Device of each package when the total is cut in proportion to the peak rates, in order."""
    from .packages import prefix

    total = packages.agg(F.sum(size).alias("_total"))
    rows = prefix(packages.withColumn("bytes", F.col(size)), 1, order).withColumnRenamed("list", "_before").crossJoin(F.broadcast(total))
    device, passed = F.lit(len(rates) - 1), 0.0
    for k, r in reversed(list(enumerate(rates[:-1]))):
        passed = sum(rates[: k + 1]) / sum(rates)
        device = F.when(F.col("_before") < F.col("_total") * passed, F.lit(k)).otherwise(device)
    return rows.withColumn("device", device).drop("_before", "_total")


def makespan(packages: DataFrame, workers: list[int], cost: str, number: str) -> DataFrame:
    """Busy time, makespan and idle time when packages are dealt in turn to c workers, for each c."""
    spark = packages.sparkSession
    table = F.broadcast(spark.createDataFrame([(c,) for c in workers], "workers int"))
    load = packages.crossJoin(table).groupBy("workers", F.pmod(F.col(number), F.col("workers")).alias("worker")).agg(F.sum(cost).alias("busy"))
    out = load.groupBy("workers").agg(F.sum("busy").alias("busy"), F.max("busy").alias("makespan"))
    return out.withColumn("idle", F.col("makespan") * F.col("workers") - F.col("busy"))


def pulled(costs: list[float], workers: int) -> tuple[float, float]:
    """Makespan and idle time when a free worker pulls the next package (a small model, on the driver)."""
    free = [0.0] * workers
    for c in costs:
        k = min(range(workers), key=free.__getitem__)
        free[k] += c
    return max(free), max(free) * workers - sum(costs)


def occupancy(launch: float, run: float, packages: int, workers: int) -> float:
    """Share of time the device is busy when each package needs host time before its run: one worker leaves gaps."""
    ready, device = [0.0] * workers, 0.0
    for k in range(packages):
        w = k % workers
        start = max(ready[w] + launch, device)
        device = start + run
        ready[w] = device
    return packages * run / device


def queue_order(items: DataFrame, producer: str, order: str) -> DataFrame:
    """Position of each item in its producer's queue and the gap to the one before."""
    w = Window.partitionBy(producer).orderBy(order)
    return items.withColumn("position", F.row_number().over(w)).withColumn("gap", F.coalesce(F.col(order) - F.lag(order).over(w), F.lit(0)))
