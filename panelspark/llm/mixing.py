"""Mixing sources to target weights by proportionate-fair scheduling.

The documents of a source, in order of a hash, form a stream of blocks of `block_bytes`. With share w the j-th block
(from 0) of a source may not start before slot floor(j / w) and must be done by slot ceil((j + 1) / w). Earliest
deadline first over the released blocks keeps every source, at every slot, less than one block off its share.
Whole-number weights repeat with their sum as period, so one period is scheduled once (it has as many rows as the sum
of the weights, a parameter) and every block finds its slot by arithmetic: no global sort, nothing on the driver
that grows with the data.

Every document appears once. A source that is used up leaves its slots empty, which changes no order; `balanced` tells
whether a slot comes before the first source runs out. Null sources and those without a weight of their own share the
weight of the rest. Ties: repeated rows follow each other. Empty texts take no bytes and stay with their
neighbour's block. Texts longer than a block take several block numbers.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

REST = "(rest)"
LAST = 1 << 62
ADDED = ("_stream", "_block", "_slot", "_release", "_deadline", "_place", "_balanced")


def period_schedule(weights: dict[str, int]) -> list[tuple[str, int, int, int, int]]:
    """(source, block in the period, release, deadline, slot) of one period, earliest deadline first."""
    period = sum(weights.values())
    share = {s: Fraction(w, period) for s, w in weights.items() if w > 0}
    done = dict.fromkeys(share, 0)
    out = []
    for slot in range(period):
        ready = []
        for s, w in share.items():
            j = done[s]
            release, deadline = int(j / w), -int(-((j + 1) / w) // 1)
            if release <= slot and j < weights[s]:
                ready.append((deadline, release, s, j))
        deadline, release, s, j = min(ready)
        assert slot < deadline, "a deadline was missed"
        done[s] += 1
        out.append((s, j, release, deadline, slot))
    return out


def mixed(docs: DataFrame, weights: dict[str, int], rest: int = 1, block_bytes: int = 1 << 20, shard_bytes: int = 64 << 20, seed: int = 0) -> DataFrame:
    """The columns of docs with stream, block, slot, release, deadline, place and balanced added (underscored; columns of docs
    that have one of these names are replaced, other columns may have any name).

    The prefix sums are taken in ranges of the hash, one for about `shard_bytes` of all texts, so a source with most rows
    spreads over as many tasks as its bytes ask for; the totals of the ranges are few. Their number changes no order.
    """
    spark = docs.sparkSession
    weights = {str(k): int(v) for k, v in weights.items()} | {REST: int(rest)}
    if min(weights.values()) < 0 or sum(weights.values()) < 1:
        raise ValueError("weights must not be negative, and one must be positive")
    plan = F.broadcast(spark.createDataFrame(period_schedule(weights), "s string, j long, r long, d long, t long"))
    period = sum(weights.values())
    known = [s for s, w in weights.items() if s != REST]
    fields = [c for c in docs.columns if c not in ADDED]
    own = {c: f"own_{k}" for k, c in enumerate(fields)}  # nothing of docs can clash with the columns below
    rows = docs.select(
        *[F.col(f"`{c}`").alias(name) for c, name in own.items()],
        F.when(F.col("source").isin(known), F.col("source")).otherwise(F.lit(REST)).alias("stream"),
        F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("doc_id").cast("string"))).alias("h"),
        F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("bytes"),
        F.md5(F.coalesce("text", F.lit(""))).alias("content"),
    )
    shards = 16 + int(rows.agg(F.coalesce(F.sum("bytes"), F.lit(0))).first()[0]) // shard_bytes
    rows = rows.withColumn("shard", F.floor(F.conv(F.substring("h", 1, 8), 16, 10).cast("long") * shards / F.lit(1 << 32)).cast("long"))
    # within a shard by hash; equal hashes (repeated ids) by size and content
    order = Window.partitionBy("stream", "shard").orderBy("h", own["doc_id"], "bytes", "content")
    totals = rows.groupBy("stream", "shard").agg(F.sum("bytes").alias("total"))
    before = totals.select("stream", "shard", (F.sum("total").over(Window.partitionBy("stream").orderBy("shard")) - F.col("total")).alias("offset"))
    ends = totals.groupBy("stream").agg(F.sum("total").alias("all"))
    # the first slot after which some stream with a weight has nothing left
    spent = ends.join(F.broadcast(spark.createDataFrame(list(weights.items()), "stream string, w long")), "stream").where("w > 0").agg(F.min(F.floor(F.col("all") / F.lit(block_bytes)) / F.col("w") * period).alias("spent"))
    within = rows.withColumn("from", F.sum("bytes").over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col("bytes"))
    placed = within.join(F.broadcast(before), ["stream", "shard"]).withColumn("place", F.col("from") + F.col("offset"))
    placed = placed.withColumn("block", F.floor(F.col("place") / F.lit(block_bytes)).cast("long"))
    w = F.element_at(F.create_map(*[x for s, v in weights.items() for x in (F.lit(s), F.lit(max(v, 1)).cast("long"))]), F.col("stream"))
    placed = placed.withColumn("s", F.col("stream")).withColumn("w", w).withColumn("j", F.pmod("block", "w")).withColumn("cycle", F.floor(F.col("block") / F.col("w")).cast("long"))
    out = placed.join(plan, ["s", "j"], "left").crossJoin(F.broadcast(spent))
    shift = F.col("cycle") * period
    # a stream of weight 0 has no slots: it follows after all others
    added = [F.col("stream"), F.col("block"), F.col("t") + shift, F.col("r") + shift, F.col("d") + shift, F.col("place"), F.coalesce(F.col("t") + shift, F.lit(1 << 62)) < F.coalesce("spent", F.lit(0.0))]
    return out.select(*[F.col(name).alias(c) for c, name in own.items()], *[c.alias(n) for c, n in zip(added, ADDED, strict=True)])


def scheduled(docs: DataFrame, weights: dict[str, int], rest: int = 1, block_bytes: int = 1 << 20) -> DataFrame:
    """The rows of docs with slot and place, sorted by them; as columns, the order survives files that are read in any order.

    Streams of weight 0 have the slot LAST. Columns of docs named slot or place are replaced.
    """
    own = [F.col(f"`{c}`") for c in docs.columns if c not in ("slot", "place", *ADDED)]
    out = mixed(docs, weights, rest, block_bytes).select(*own, F.coalesce("_slot", F.lit(LAST)).alias("slot"), F.col("_place").alias("place"))
    return out.repartitionByRange("slot", "place").sortWithinPartitions("slot", "place")


def interleaved(docs: DataFrame, weights: dict[str, int], rest: int = 1, block_bytes: int = 1 << 20) -> DataFrame:
    """The rows of docs, all of them and with their own columns only, sorted into the scheduled order."""
    return scheduled(docs, weights, rest, block_bytes).select(*docs.columns)


def oracle(weights: dict[str, int], rest: int, block_bytes: int, seed: int = 0) -> str:
    """The schedule of `documents` in SQL; only the period of the schedule, a table of the weights, is given."""
    weights = {**weights, REST: rest}
    period = sum(weights.values())
    plan = ", ".join(f"('{s}', {j}, {r}, {d}, {t})" for s, j, r, d, t in period_schedule(weights))
    named = ", ".join(f"'{s}'" for s in weights if s != REST)
    each = ", ".join(f"('{s}', {w})" for s, w in weights.items())
    return f"""WITH plan(s, j, r, d, t) AS (VALUES {plan}), shares(s, w) AS (VALUES {each}),
a AS (SELECT doc_id, CASE WHEN source IN ({named}) THEN source ELSE '{REST}' END AS stream, md5('{seed}:' || doc_id) AS h, coalesce(strlen(text), 0) AS bytes, md5(coalesce(text, '')) AS m FROM documents),
b AS (SELECT *, CAST(sum(bytes) OVER (PARTITION BY stream ORDER BY h, doc_id, bytes, m ROWS UNBOUNDED PRECEDING) - bytes AS BIGINT) AS place FROM a),
spent AS (SELECT min(floor(total / {block_bytes}) / w * {period}) AS spent FROM (SELECT stream, sum(bytes) AS total FROM a GROUP BY stream) JOIN shares ON s = stream WHERE w > 0),
c AS (SELECT *, place // {block_bytes} AS block FROM b JOIN shares ON s = stream)
SELECT doc_id, stream, block, t + block // w * {period} AS slot, r + block // w * {period} AS release, d + block // w * {period} AS deadline, place, t + block // w * {period} < spent AS balanced
FROM c JOIN plan ON plan.s = stream AND plan.j = block % w, spent"""
