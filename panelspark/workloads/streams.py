"""Streaming queries over the events table; each equals its batch form."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import oracles as O
from .. import streaming as S
from .registry import Registry, scaled, table

R = Registry()
LIMIT = 500


def _items(spark, sf_dir):
    return S.items(spark, f"{sf_dir}/events.parquet")


@R.add(f"""WITH RECURSIVE q AS (SELECT event_type AS case_, event_id, CAST(ceil(value) AS BIGINT) AS bytes, row_number() OVER (PARTITION BY event_type ORDER BY event_id) AS k FROM events),
w(case_, event_id, bytes, k, list, filled) AS (SELECT case_, event_id, bytes, k, CAST(0 AS BIGINT), bytes FROM q WHERE k = 1
UNION ALL SELECT q.case_, q.event_id, q.bytes, q.k, CASE WHEN w.filled + q.bytes >= {LIMIT} THEN w.list + 1 ELSE w.list END, CASE WHEN w.filled + q.bytes >= {LIMIT} THEN q.bytes ELSE w.filled + q.bytes END FROM w JOIN q ON q.case_ = w.case_ AND q.k = w.k + 1)
SELECT case_, list, count(*) AS items, CAST(sum(bytes) AS BIGINT) AS bytes FROM w GROUP BY ALL""")
def stream_packages(spark, sf_dir):
    rows = _items(spark, sf_dir).select("event_id", F.col("event_type").alias("case"), F.ceil("value").cast("long").alias("bytes"))
    out = S.finished(S.packed(rows, LIMIT))
    return out.groupBy(F.col("case").alias("case_"), "list").agg(F.count("*").alias("items"), F.sum("bytes").alias("bytes"))


@R.add("SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d') AS day, event_type, count(*) AS n, CAST(round(sum(value) * 100) AS BIGINT) AS cents FROM events GROUP BY ALL")
def stream_windows(spark, sf_dir):
    out = S.finished(S.windows(_items(spark, sf_dir), "1 day"), "complete")
    return out.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n", F.round(F.col("total") * 100).cast("long").alias("cents"))


@R.add("""WITH g AS (SELECT user_id, ts, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS fresh FROM events),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS began, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_sessions(spark, sf_dir):
    out = S.finished(S.sessions(_items(spark, sf_dir), "12 hours"), "complete")
    return out.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("began"), "n")


@R.add("SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type")
def stream_dedup(spark, sf_dir):
    """Every item sent twice counts once."""
    rows = _items(spark, sf_dir)
    twice = rows.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    out = S.finished(S.deduplicated(twice, "event_id"))
    return out.groupBy("event_type").agg(F.count("*").alias("n"))


@R.add(f"WITH {O.panels(4)} SELECT event_type, {O.scaled('sum(value * area)', 6, 'weighted')}, count(*) AS n FROM events JOIN p ON pid = user_id % 128 GROUP BY event_type")
def stream_static_join(spark, sf_dir):
    """Each event weighs with the area of its panel."""
    from .mesh import small_mesh

    out = S.finished(S.with_panels(_items(spark, sf_dir), small_mesh(spark).select("pid", "area"), 128))
    return out.groupBy("event_type").agg(scaled(F.sum(F.col("value") * F.col("area")), 6, "weighted"), F.count("*").alias("n"))


@R.add("""WITH m AS (SELECT max(ts) AS last FROM events), k AS (SELECT event_type, ts > last - INTERVAL 12 DAY AS kept FROM events, m)
SELECT event_type, CAST(sum(CAST(kept AS INT)) AS BIGINT) AS n, (SELECT CAST(sum(CAST(NOT kept AS INT)) AS BIGINT) FROM k) AS dropped FROM k WHERE kept GROUP BY event_type""")
def stream_late(spark, sf_dir):
    """Three files arrive: the last ten days, the same again, and then the older events. What is behind the watermark of twelve
    days is dropped and counted; the second file is all repeats."""
    from ..plans.scratch import folder

    e = table(spark, sf_dir, "events")
    split = e.agg((F.max("ts") - F.expr("INTERVAL 10 DAY")).alias("split"))
    rows = e.crossJoin(F.broadcast(split))
    inbox = folder(spark)
    for which in ("ts >= split", "ts >= split", "ts < split"):
        rows.where(which).drop("split").coalesce(1).write.mode("append").parquet(inbox)
    stream = spark.readStream.schema(S.EVENTS).option("maxFilesPerTrigger", 1).parquet(inbox).withColumn("ts", F.col("ts").cast("timestamp"))
    out, dropped = S.finished(S.deduplicated(stream, "event_id", "12 days"), late=True)
    return out.groupBy("event_type").agg(F.count("*").alias("n")).withColumn("dropped", F.lit(dropped).cast("long"))


@R.add("SELECT strftime(w, '%Y-%m-%d') AS day, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 1 DAY, ts), time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY]) AS w FROM events) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    """Windows of two days that begin each day."""
    out = S.finished(S.windows(_items(spark, sf_dir), "2 days", "1 day"), "complete")
    return out.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@R.add("SELECT a.user_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.user_id")
def stream_interval_join(spark, sf_dir):
    rows = _items(spark, sf_dir)
    out = S.finished(S.matched(rows.where("event_type = 'view'"), rows.where("event_type = 'purchase'")))
    return out.groupBy("user_id").agg(F.count("*").alias("n"))


def _incremental_sql():
    from ..operators.kernels import slp
    from .mesh import matrix_sql

    return matrix_sql(slp(), 2, tail=f", d AS (SELECT user_id % 32 AS pid, sum(value) AS density FROM events GROUP BY 1) SELECT i, {O.scaled('sum(re * density)', 4, 'potential')} FROM e JOIN d ON d.pid = j GROUP BY i")


@R.add(_incremental_sql())
def stream_incremental(spark, sf_dir):
    """Changes of the density laid over a potential step by step equal the product with the whole density."""
    from ..operators import assembly
    from ..operators.kernels import slp
    from ..plans.scratch import settled
    from .mesh import small_mesh

    events = table(spark, sf_dir, "events")
    v = settled(assembly.dense(small_mesh(spark, 2), slp()))
    part = lambda k: events.where(F.pmod(F.xxhash64("event_id"), F.lit(3)) == k).groupBy(F.pmod("user_id", F.lit(32)).alias("i")).agg(F.sum("value").alias("value"))
    out = v.select("i", F.lit(0.0).alias("value")).distinct()
    for k in range(3):
        out = S.incremental(out, v, part(k))
    return out.select("i", scaled(F.col("value"), 4, "potential"))
