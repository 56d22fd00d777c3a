"""Grouping work items into size-bounded packages, and what follows from the grouping.

items(item, producer, case, bytes). A list takes an item while its size stays strictly below the limit; an item that not
even an empty list can take is halved, down to single units.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def split_oversized(items: DataFrame, limit: int) -> DataFrame:
    """Items halved (larger half first) until each is below the limit or a single unit: (.., piece, bytes).

    After h halvings all pieces have one of two sizes that differ by one. So h - 1 halvings, with h the least number
    that fits the larger size, make the pieces of which some may fit already; the others are halved once more.
    """
    limit = max(limit, 2)
    size = F.col("bytes").cast("long")
    most = F.greatest(F.ceil(size / F.lit(limit - 1)), F.lit(1)).cast("long")
    rounds = F.when(most > 1, F.length(F.bin(most - 1))).otherwise(F.lit(0))
    before = F.pow(F.lit(2.0), F.greatest(rounds - 1, F.lit(0))).cast("long")
    parts = F.transform(F.sequence(F.lit(0).cast("long"), before - 1), lambda k: _share(size, k, rounds - 1))
    halves = F.flatten(F.transform(parts, lambda x: F.when(x < limit, F.array(x)).otherwise(F.array(F.ceil(x / 2).cast("long"), F.floor(x / 2).cast("long")))))
    pieces = F.when(rounds == 0, F.array(size)).otherwise(halves)
    return items.select(*[c for c in items.columns if c != "bytes"], F.posexplode(pieces).alias("piece", "bytes"))


def _share(size: Column, k: Column, rounds: Column) -> Column:
    """Size of piece k (in order) after so many halvings: each bit of k, from the top, picks a half."""
    steps = F.when(rounds > 0, F.sequence(F.lit(1), F.greatest(rounds, F.lit(1)))).otherwise(F.array().cast("array<int>"))

    def halve(a: Column, b: Column) -> Column:
        smaller = F.pmod(F.floor(k / F.pow(F.lit(2.0), rounds - b)).cast("long"), F.lit(2)) == 1
        return F.when(smaller, F.floor(a / 2).cast("long")).otherwise(F.ceil(a / 2).cast("long"))

    return F.aggregate(steps, size, halve)


def fold(sizes, limit: int, closes=None) -> list[int]:
    """List number of each size, in order; all sizes are below the limit or single units.

    closes: where an oversized item begins, which closes the open list before it is split.
    """
    out, number, filled = [], 0, 0
    for s, c in zip(sizes, closes if closes is not None else [False] * len(sizes), strict=True):
        if filled and (c or filled + s >= limit):
            number, filled = number + 1, 0
        filled += s
        out.append(number)
    return out


def greedy(items: DataFrame, limit: int, order: list[str], producer: str = "producer") -> DataFrame:
    """The exact sequential rule, once for each producer; a producer's items must fit a task, else use `prefix`.

    Every last, partly filled list is closed too.
    """
    pieces = split_oversized(items, limit)
    schema = pieces.select("*").schema.add("list", "long")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values([*order, "piece"], kind="stable")
        begins = (pdf["piece"] == 0) & (pdf["piece"].shift(-1) == 1)
        return pdf.assign(list=fold(pdf["bytes"].tolist(), limit, begins.tolist()))

    return pieces.groupBy(producer).applyInPandas(run, schema)


def prefix(items: DataFrame, limit: int, order: list[str], parts: int | None = None) -> DataFrame:
    """The parallel rule: list = floor(bytes before / limit), by a two-pass prefix sum over ranges.

    Every list stays below the limit plus its last item; two shuffles at any size.
    """
    from .geometry import ranged

    spread = ranged(items, order, parts)
    totals = spread.groupBy("_part").agg(F.sum("bytes").alias("_sum"))
    before = totals.withColumn("_before", F.sum("_sum").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))).select("_part", F.coalesce("_before", F.lit(0)).alias("_before"))
    w = Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    rows = spread.withColumn("_cum", F.sum("bytes").over(w) - F.col("bytes")).join(F.broadcast(before), "_part")
    return rows.withColumn("list", F.floor((F.col("_cum") + F.col("_before")) / F.lit(limit)).cast("long")).drop("_part", "_cum", "_before")


def sweep(items: DataFrame, limits: list[int], order: list[str]) -> DataFrame:
    """Number of lists and their mean fill by limit (prefix rule)."""
    total = items.agg(F.sum("bytes").alias("bytes"), F.count("*").alias("items"))
    parts = None
    for x in limits:
        one = prefix(items, x, order).groupBy("list").agg(F.sum("bytes").alias("b"), F.count("*").alias("c")).agg(F.count("*").alias("lists"), F.max("b").alias("largest"), F.max("c").alias("most_items")).withColumn("limit", F.lit(x).cast("long"))
        parts = one if parts is None else parts.unionByName(one)
    return parts.crossJoin(total).select("limit", "lists", "largest", "most_items", "items", "bytes")


def divergence(items: DataFrame, batch: str, points: str) -> DataFrame:
    """Waste of batches that run as long as their slowest row: sum of (most - own)."""
    w = Window.partitionBy(batch)
    rows = items.withColumn("_most", F.max(points).over(w))
    return rows.agg(F.sum(F.col("_most") - F.col(points)).alias("waste"), F.sum(points).alias("useful"))


def lane_utilisation(package_items: DataFrame, lanes: int, items: str = "items") -> DataFrame:
    """Busy lanes, lanes held and their share, for packages of so many items on so many lanes."""
    waves = F.ceil(F.col(items) / F.lit(lanes)).cast("long")
    return package_items.agg(F.sum(items).alias("busy"), F.sum(waves * lanes).alias("held")).withColumn("idle", F.col("held") - F.col("busy"))
