"""Packages, dispatch and occupancy over document, page and conversation items."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import measures, packages, schedule
from .registry import Registry, table

R = Registry()
LIMIT = 8192
RATES = (197.6, 128.8)


def items(spark, sf_dir):
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item"), F.col("source").alias("producer"), F.col("lang").alias("case"), F.col("n_chars").cast("long").alias("bytes"))


SPLIT_CTE = f"""split AS (WITH RECURSIVE s(item, producer, path, bytes) AS (
SELECT doc_id, source, '', CAST(n_chars AS BIGINT) FROM documents
UNION ALL SELECT item, producer, path || h, CASE WHEN h = '0' THEN bytes - bytes // 2 ELSE bytes // 2 END FROM s, (VALUES ('0'), ('1')) AS q(h) WHERE bytes >= {LIMIT} AND bytes > 1)
SELECT item, producer, CAST(row_number() OVER (PARTITION BY item ORDER BY path) - 1 AS INTEGER) AS piece, bytes FROM s WHERE bytes < {LIMIT} OR bytes <= 1)"""


@R.add(f"WITH {SPLIT_CTE} SELECT item, piece, bytes FROM split")
def package_split(spark, sf_dir):
    return packages.split_oversized(items(spark, sf_dir), LIMIT).select("item", "piece", "bytes")


@R.add(f"""WITH RECURSIVE {SPLIT_CTE}, q AS (SELECT *, row_number() OVER (PARTITION BY producer ORDER BY item, piece) AS k, piece = 0 AND coalesce(lead(piece) OVER (PARTITION BY producer ORDER BY item, piece), 0) = 1 AS opens FROM split),
w(producer, item, piece, bytes, k, list, filled) AS (SELECT producer, item, piece, bytes, k, CAST(0 AS BIGINT), bytes FROM q WHERE k = 1
UNION ALL SELECT q.producer, q.item, q.piece, q.bytes, q.k, CASE WHEN q.opens OR w.filled + q.bytes >= {LIMIT} THEN w.list + 1 ELSE w.list END, CASE WHEN q.opens OR w.filled + q.bytes >= {LIMIT} THEN q.bytes ELSE w.filled + q.bytes END FROM w JOIN q ON q.producer = w.producer AND q.k = w.k + 1)
SELECT producer, list, count(*) AS items, CAST(sum(bytes) AS BIGINT) AS bytes FROM w GROUP BY producer, list""")
def package_greedy(spark, sf_dir):
    return packages.greedy(items(spark, sf_dir), LIMIT, ["item"]).groupBy("producer", "list").agg(F.count("*").alias("items"), F.sum("bytes").alias("bytes"))


PREFIX = "SELECT doc_id AS item, n_chars AS bytes, CAST(floor((sum(n_chars) OVER (ORDER BY doc_id ROWS UNBOUNDED PRECEDING) - n_chars) / {limit}) AS BIGINT) AS list FROM documents"


@R.add(f"SELECT list, count(*) AS items, CAST(sum(bytes) AS BIGINT) AS bytes FROM ({PREFIX.format(limit=LIMIT)}) GROUP BY list")
def package_prefix(spark, sf_dir):
    return packages.prefix(items(spark, sf_dir), LIMIT, ["item"]).groupBy("list").agg(F.count("*").alias("items"), F.sum("bytes").alias("bytes"))


LIMITS = [1000, 10_000, 100_000, 1_000_000]


@R.add(" UNION ALL ".join(f"SELECT CAST({x} AS BIGINT) AS \"limit\", count(*) AS lists, max(b) AS largest, max(c) AS most_items, CAST(sum(c) AS BIGINT) AS items, CAST(sum(b) AS BIGINT) AS bytes FROM (SELECT CAST(sum(bytes) AS BIGINT) AS b, count(*) AS c FROM ({PREFIX.format(limit=x)}) GROUP BY list)" for x in LIMITS))
def package_sweep(spark, sf_dir):
    return packages.sweep(items(spark, sf_dir), LIMITS, ["item"])


@R.add(f"SELECT list, count(*) AS items, CAST(sum(bytes) AS BIGINT) AS bytes FROM ({PREFIX.format(limit=LIMIT).replace('doc_id', 'page_id').replace('n_chars', 'length(html)').replace('documents', 'pages')}) GROUP BY list")
def package_pages(spark, sf_dir):
    pages = table(spark, sf_dir, "pages").select(F.col("page_id").alias("item"), F.length("html").cast("long").alias("bytes"))
    return packages.prefix(pages, LIMIT, ["item"]).groupBy("list").agg(F.count("*").alias("items"), F.sum("bytes").alias("bytes"))


@R.add("""WITH q AS (SELECT doc_id, row_number() OVER (ORDER BY doc_id) - 1 AS k, row_number() OVER (ORDER BY lang, doc_id) - 1 AS m, CASE lang WHEN 'en' THEN 81 WHEN 'de' THEN 1250 WHEN 'fr' THEN 3125 ELSE 3750 END AS points FROM documents)
SELECT 'mixed' AS batches, CAST(sum(top - points) AS BIGINT) AS waste, CAST(sum(points) AS BIGINT) AS useful FROM (SELECT *, max(points) OVER (PARTITION BY k // 64) AS top FROM q)
UNION ALL SELECT 'by_case', CAST(sum(top - points) AS BIGINT), CAST(sum(points) AS BIGINT) FROM (SELECT *, max(points) OVER (PARTITION BY points, m // 64) AS top FROM q)""")
def package_mixed_waste(spark, sf_dir):
    from ..operators.geometry import numbered

    points = F.when(F.col("case") == "en", 81).when(F.col("case") == "de", 1250).when(F.col("case") == "fr", 3125).otherwise(3750)
    rows = items(spark, sf_dir).withColumn("points", points)
    mixed = packages.divergence(numbered(rows, ["item"]).withColumn("batch", F.floor(F.col("_row") / 64)), "batch", "points").select(F.lit("mixed").alias("batches"), "waste", "useful")
    one = packages.divergence(numbered(rows, ["case", "item"]).withColumn("batch", F.concat_ws(":", "points", F.floor(F.col("_row") / 64))), "batch", "points").select(F.lit("by_case").alias("batches"), "waste", "useful")
    return mixed.unionByName(one)


@R.add(f"SELECT lanes, CAST(sum(c) AS BIGINT) AS busy, CAST(sum((c + lanes - 1) // lanes * lanes) AS BIGINT) AS held, CAST(sum((c + lanes - 1) // lanes * lanes) - sum(c) AS BIGINT) AS idle FROM (SELECT count(*) AS c FROM ({PREFIX.format(limit=LIMIT)}) GROUP BY list), (VALUES (32), (1024)) AS l(lanes) GROUP BY lanes")
def lane_utilisation(spark, sf_dir):
    lists = packages.prefix(items(spark, sf_dir), LIMIT, ["item"]).groupBy("list").agg(F.count("*").alias("items"))
    out = [packages.lane_utilisation(lists, x).select(F.lit(x).alias("lanes"), "busy", "held", "idle") for x in (32, 1024)]
    return out[0].unionByName(out[1])


@R.add("SELECT CASE WHEN quality = 1 THEN 'accelerator' ELSE 'host' END AS route, count(*) AS items, CAST(sum(n_chars) AS BIGINT) AS bytes FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1")
def affinity_dispatch(spark, sf_dir):
    rows = table(spark, sf_dir, "documents").select("doc_id", "n_chars").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    total = lambda df: df.groupBy("route").agg(F.count("*").alias("items"), F.sum("n_chars").alias("bytes"))
    return schedule.dispatch(rows, F.coalesce(F.col("quality") == 1, F.lit(False)), total, total)


@R.add(f"""WITH c AS (SELECT doc_id, n_chars, sum(n_chars) OVER (ORDER BY doc_id ROWS UNBOUNDED PRECEDING) - n_chars AS before, sum(n_chars) OVER () AS total FROM documents)
SELECT CASE WHEN before < total * {RATES[0] / sum(RATES)} THEN 0 ELSE 1 END AS device, count(*) AS items, CAST(sum(n_chars) AS BIGINT) AS bytes FROM c GROUP BY 1""")
def device_share(spark, sf_dir):
    out = schedule.proportional_cut(items(spark, sf_dir), list(RATES), "bytes", ["item"])
    return out.groupBy("device").agg(F.count("*").alias("items"), F.sum("bytes").alias("bytes"))


@R.add("""WITH l AS (SELECT workers, doc_id % workers AS w, sum(n_chars) AS busy FROM documents, (VALUES (1), (2), (4), (8)) AS c(workers) GROUP BY ALL)
SELECT workers, CAST(sum(busy) AS BIGINT) AS busy, CAST(max(busy) AS BIGINT) AS makespan, CAST(max(busy) * workers - sum(busy) AS BIGINT) AS idle FROM l GROUP BY workers""")
def worker_makespan(spark, sf_dir):
    return schedule.makespan(items(spark, sf_dir), [1, 2, 4, 8], "bytes", "item")


@R.add("SELECT conv_id, turn, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS position, coalesce(turn - lag(turn) OVER (PARTITION BY conv_id ORDER BY turn), 0) AS gap FROM conversations")
def queue_order(spark, sf_dir):
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn")
    return schedule.queue_order(rows, "conv_id", "turn").withColumn("position", F.col("position").cast("long"))


# Published set-up seconds (workload, degrees of freedom, host, fast card, slow card, both cards); None: not
# measured or below 0.1.
PUBLISHED = [
    ("slp", 2048, 0.3, None, None, None),
    ("slp", 8192, 1.5, 0.1, 0.2, 0.1),
    ("slp", 32768, 7.5, 0.5, 0.7, 0.3),
    ("slp", 131072, 30.0, 1.9, 2.7, 1.2),
    ("slp", 524288, 133.0, 8.3, 11.8, 5.2),
    ("slp", 2097152, 686.2, 44.6, 64.1, 27.1),
    ("dlp", 2048, 0.5, None, None, None),
    ("dlp", 8192, 2.7, 0.3, 0.4, 0.2),
    ("dlp", 32768, 13.2, 1.2, 1.7, 0.8),
    ("dlp", 131072, 55.0, 4.7, 6.8, 2.9),
    ("dlp", 524288, 237.3, 20.3, 29.5, 12.5),
    ("dlp", 2097152, 1309.0, 112.8, 165.1, 68.2),
    ("slp_higher", 2048, 1.0, None, None, None),
    ("slp_higher", 8192, 4.8, None, None, 0.2),
    ("slp_higher", 32768, 21.6, None, None, 0.7),
    ("slp_higher", 131072, 86.8, None, None, 2.8),
    ("slp_higher", 524288, 368.5, None, None, 12.0),
    ("slp_higher", 2097152, 1439.3, None, None, 48.3),
    ("dlp_higher", 2048, 1.5, None, None, 0.1),
    ("dlp_higher", 8192, 7.7, None, None, 0.4),
    ("dlp_higher", 32768, 39.0, None, None, 1.8),
    ("dlp_higher", 131072, 162.1, None, None, 7.3),
    ("dlp_higher", 524288, 702.0, None, None, 31.3),
    ("dlp_higher", 2097152, 2936.2, None, None, 131.9),
    ("slp_wave", 2048, 2.3, None, None, 0.1),
    ("slp_wave", 8192, 9.6, None, None, 0.3),
    ("slp_wave", 32768, 42.7, None, None, 1.3),
    ("slp_wave", 131072, 205.8, None, None, 6.7),
    ("slp_wave", 524288, 843.6, None, None, 27.9),
    ("dlp_wave", 2048, 2.7, None, None, 0.1),
    ("dlp_wave", 8192, 11.8, None, None, 0.4),
    ("dlp_wave", 32768, 55.2, None, None, 1.8),
    ("dlp_wave", 131072, 263.4, None, None, 8.9),
    ("dlp_wave", 524288, 1050.1, None, None, 36.9),
]
DEVICES = ("host", "fast", "slow", "both")
_RUNS = "runs(workload, dof, device, seconds) AS (VALUES " + ", ".join(f"('{w}', {d}::BIGINT, '{dev}', {x}::DOUBLE)" for w, d, *t in PUBLISHED for dev, x in zip(DEVICES, t, strict=True) if x is not None) + ")"


def published_runs(spark):
    rows = [(w, d, dev, s) for w, d, *t in PUBLISHED for dev, s in zip(DEVICES, t, strict=True) if s is not None]
    return spark.createDataFrame(rows, "workload string, dof long, device string, seconds double")


@R.add(f"WITH {_RUNS} SELECT a.workload, a.dof, CAST(round(a.seconds / b.seconds * 10) AS BIGINT) AS factor10 FROM runs a JOIN runs b ON a.workload = b.workload AND a.dof = b.dof WHERE a.device = 'host' AND b.device = 'both'")
def paper_speedups(spark, sf_dir):
    """Published factors of both cards against the host, recomputed from the published seconds."""
    return measures.speedup(published_runs(spark), "host", "both").select("workload", "dof", F.round(F.col("factor") * 10).cast("long").alias("factor10"))


@R.add(f"WITH {_RUNS} SELECT workload, dof, device, CAST(round(seconds * 1e6 / dof * 100) AS BIGINT) AS us100 FROM runs")
def paper_time_per_dof(spark, sf_dir):
    return measures.per_dof(published_runs(spark)).select("workload", "dof", "device", F.round(F.col("us_per_dof") * 100).cast("long").alias("us100"))


@R.add(f"WITH {_RUNS}, f AS (SELECT a.workload, a.dof, a.device, a.seconds / b.seconds AS factor, {sum(RATES)} / (CASE a.device WHEN 'fast' THEN {RATES[0]} ELSE {RATES[1]} END) AS ideal FROM runs a JOIN runs b ON a.workload = b.workload AND a.dof = b.dof AND b.device = 'both' WHERE a.device IN ('fast', 'slow')) SELECT workload, dof, device, CAST(round(factor * 1e4) AS BIGINT) AS factor4, CAST(round(ideal * 1e4) AS BIGINT) AS ideal4 FROM f")
def paper_device_factors(spark, sf_dir):
    """Gain of both cards against each, beside the ideal by peak rates."""
    runs = published_runs(spark)
    out = []
    for d, rate in zip(("fast", "slow"), RATES, strict=True):
        got = measures.speedup(runs, d, "both")
        out.append(got.select("workload", "dof", F.lit(d).alias("device"), F.round(F.col("factor") * 1e4).cast("long").alias("factor4"), F.round(F.lit(sum(RATES) / rate) * 1e4).cast("long").alias("ideal4")))
    return out[0].unionByName(out[1])


@R.add("SELECT event_type, count(*) AS runs, min(value) AS min, CAST(round(avg(value) * 1e6) AS BIGINT) AS mean6, max(value) AS max FROM events GROUP BY event_type")
def run_stats(spark, sf_dir):
    out = measures.run_stats(table(spark, sf_dir, "events"), ["event_type"], "value")
    return out.select("event_type", "runs", "min", F.round(F.col("mean") * 1e6).cast("long").alias("mean6"), "max")
