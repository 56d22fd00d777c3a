"""The operators around the methods: scans, joins, aggregates, windows, sets, functions, and the SQL function surface."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import oracles as O
from .mesh import small_mesh
from .registry import Registry, scaled, table

R = Registry()


def T(spark, d, name):
    return table(spark, d, name)


def q(sql, name, f):
    R.add(sql, name)(f)


q("SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'", "scan_filter_project", lambda s, d: T(s, d, "lineitem").where("l_quantity > 45 and l_returnflag = 'R'").select("l_orderkey", "l_partkey", "l_quantity"))
q(f"WITH {O.panels(O.PART_N)} SELECT pid FROM p WHERE gx BETWEEN 0.1 AND 0.5 AND gz > 0", "scan_bbox", lambda s, d: __import__("panelspark.workloads.mesh", fromlist=["x"]).part_mesh(s, d).where("gx between 0.1 and 0.5 and gz > 0").select("pid"))

_J = {"inner": "JOIN", "left": "LEFT JOIN", "right": "RIGHT JOIN", "full": "FULL JOIN"}


def _join(kind):
    def run(s, d):
        c = T(s, d, "customer").where("c_acctbal > 5000").select("c_custkey", "c_nationkey")
        o = T(s, d, "orders").where("o_totalprice > 200000").select("o_orderkey", "o_custkey")
        return c.join(o, F.col("c_custkey") == F.col("o_custkey"), kind).select(*[F.coalesce(x, F.lit(-1)).cast("long").alias(x) for x in ("c_custkey", "c_nationkey", "o_orderkey")])

    return run


for _k, _s in _J.items():
    q(f"SELECT coalesce(c_custkey, -1)::BIGINT AS c_custkey, coalesce(c_nationkey, -1)::BIGINT AS c_nationkey, coalesce(o_orderkey, -1)::BIGINT AS o_orderkey FROM (SELECT * FROM customer WHERE c_acctbal > 5000) c {_s} (SELECT * FROM orders WHERE o_totalprice > 200000) o ON c_custkey = o_custkey", f"join_{_k}", _join(_k))
for _k, _s in (("semi", ""), ("anti", "NOT ")):
    q(f"SELECT c_custkey FROM customer WHERE {_s}EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)", f"join_{_k}", lambda s, d, k=_k: T(s, d, "customer").select("c_custkey").join(T(s, d, "orders").where("o_totalprice > 300000").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", f"left_{k}"))
q("SELECT r_name, n_name FROM region, nation", "join_cross", lambda s, d: T(s, d, "region").select("r_name").crossJoin(F.broadcast(T(s, d, "nation").select("n_name"))))
for _h in ("broadcast", "merge", "shuffle_hash"):
    q("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name", f"join_{_h}", lambda s, d, h=_h: T(s, d, "customer").join(T(s, d, "nation").hint(h), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")))


def range_cells(s, d):
    """Pairs of customers within a radius: each looks into the cells it can reach, so the join is on cells."""
    r = 200.0
    c = T(s, d, "customer").select("c_custkey", "c_nationkey", "c_acctbal").withColumn("cell", F.floor(F.col("c_acctbal") / r))
    b = c.select(F.col("c_custkey").alias("other"), F.col("c_nationkey").alias("n2"), F.col("c_acctbal").alias("b2"), F.explode(F.array(F.col("cell") - 1, F.col("cell"), F.col("cell") + 1)).alias("cell"))
    return c.join(b, "cell").where((F.col("c_nationkey") == F.col("n2")) & (F.col("c_custkey") < F.col("other")) & (F.abs(F.col("c_acctbal") - F.col("b2")) <= r)).select("c_custkey", "other")


q("SELECT a.c_custkey, b.c_custkey AS other FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey AND abs(a.c_acctbal - b.c_acctbal) <= 200.0", "join_range_cells", range_cells)


def asof(s, d):
    """The last event of a user up to each of their purchases before, by union and a running last value."""
    e = T(s, d, "events").select("user_id", "ts", "event_id", "event_type", "value")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    view = F.when(F.col("event_type") == "view", F.col("event_id"))
    return e.withColumn("last_view", F.coalesce(F.last(view, ignorenulls=True).over(w), F.lit(-1))).where("event_type = 'purchase'").select("event_id", "last_view")


q("SELECT event_id, coalesce(lv, -1) AS last_view FROM (SELECT *, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS lv FROM events) WHERE event_type = 'purchase'", "join_asof_density", asof)


def overlap(s, d, length="least(n_chars, 5000)"):
    """Package lifetimes [start, start + length) of one producer that overlap: join on time buckets, counted once."""
    p = T(s, d, "documents").select("doc_id", "source", (F.col("doc_id") * 100).alias("a"), (F.col("doc_id") * 100 + F.expr(length)).alias("b"))
    k = p.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("a") / 2500), F.floor(F.col("b") / 2500))))
    o = k.select(F.col("doc_id").alias("other"), "source", F.col("a").alias("a2"), F.col("b").alias("b2"), "bucket")
    once = F.floor(F.greatest("a", "a2") / 2500) == F.col("bucket")
    return k.join(o, ["source", "bucket"]).where((F.col("doc_id") < F.col("other")) & (F.col("a") < F.col("b2")) & (F.col("a2") < F.col("b")) & once).select("doc_id", "other")


q("WITH p AS (SELECT doc_id, source, doc_id * 100 AS a, doc_id * 100 + least(n_chars, 5000) AS b FROM documents) SELECT x.doc_id, y.doc_id AS other FROM p x JOIN p y ON x.source = y.source AND x.doc_id < y.doc_id AND x.a < y.b AND y.a < x.b", "join_interval_overlap", overlap)
q("WITH p AS (SELECT doc_id, source, doc_id * 100 AS a, doc_id * 100 + n_chars AS b FROM documents) SELECT x.doc_id, y.doc_id AS other FROM p x JOIN p y ON x.source = y.source AND x.doc_id < y.doc_id AND x.a < y.b AND y.a < x.b", "join_interval_overlap_all", lambda s, d: overlap(s, d, "n_chars"))

q("SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1", "agg_distinct", lambda s, d: T(s, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("suppliers")))
q("SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, count(*) FILTER (WHERE value > 100) AS large FROM events GROUP BY 1", "agg_filtered", lambda s, d: T(s, d, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.count_if(F.col("value") > 100).alias("large")))
def quantiles(s, d):
    """Exact quantiles by rank: rows are numbered by counted ranges, so no task holds all values of a flag."""
    from ..operators.geometry import numbered

    def at(value, p, digits, name):
        rows = numbered(T(s, d, "lineitem").select("l_returnflag", value), ["l_returnflag", value])
        ends = rows.groupBy("l_returnflag").agg(F.min("_row").alias("first"), F.count("*").alias("n"))
        spot = F.col("first") + p * (F.col("n") - 1)
        near = rows.join(F.broadcast(ends), "l_returnflag").where((F.col("_row") >= F.floor(spot)) & (F.col("_row") <= F.ceil(spot)))
        return near.groupBy("l_returnflag").agg(F.round((F.min(value) + (F.max(value) - F.min(value)) * (F.first(spot) - F.floor(F.first(spot)))) * 10.0**digits).cast("long").alias(name))

    return at("l_quantity", 0.5, 6, "median6").join(at("l_extendedprice", 0.9, 4, "p90"), "l_returnflag")


q("SELECT l_returnflag, CAST(round(quantile_cont(l_quantity, 0.5) * 1e6) AS BIGINT) AS median6, CAST(round(quantile_cont(l_extendedprice, 0.9) * 1e4) AS BIGINT) AS p90 FROM lineitem GROUP BY 1", "agg_percentile", quantiles)
q("SELECT event_type, max_by(event_id, value * 1e6 + event_id) AS top, min_by(event_id, value * 1e6 + event_id) AS low FROM events GROUP BY 1", "agg_max_by", lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.max_by("event_id", F.col("value") * 1e6 + F.col("event_id")).alias("top"), F.min_by("event_id", F.col("value") * 1e6 + F.col("event_id")).alias("low")))
q("SELECT count(DISTINCT l_partkey) AS parts, true AS within FROM lineitem", "agg_approx_distinct", lambda s, d: T(s, d, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.02).alias("about")).select("parts", (F.abs(F.col("about") / F.col("parts") - 1) < 0.1).alias("within")))
q("SELECT s_nationkey AS k FROM supplier EXCEPT SELECT c_nationkey FROM customer WHERE c_acctbal > 9500", "set_except_some", lambda s, d: T(s, d, "supplier").select(F.col("s_nationkey").alias("k")).subtract(T(s, d, "customer").where("c_acctbal > 9500").select("c_nationkey")))


def frobenius_norms(s, d):
    from ..functions import register

    register(s)
    T(s, d, "events").createOrReplaceTempView("events")
    return s.sql("SELECT event_type, CAST(round(frobenius(value) * 1e4) AS BIGINT) AS norm4 FROM events GROUP BY event_type")


q("SELECT event_type, CAST(round(sqrt(sum(value * value)) * 1e4) AS BIGINT) AS norm4 FROM events GROUP BY event_type", "udaf_frobenius", frobenius_norms)


def split_blocks(s, d):
    from ..functions import register

    register(s)
    T(s, d, "documents").createOrReplaceTempView("documents")
    return s.sql("SELECT doc_id, piece, bytes FROM documents, LATERAL split_block(CAST(n_chars AS INT), 8192)")


q("""WITH RECURSIVE s(doc_id, path, bytes) AS (SELECT doc_id, '', CAST(n_chars AS BIGINT) FROM documents
UNION ALL SELECT doc_id, path || h, CASE WHEN h = '0' THEN bytes - bytes // 2 ELSE bytes // 2 END FROM s, (VALUES ('0'), ('1')) AS q(h) WHERE bytes >= 8192 AND bytes > 1)
SELECT doc_id, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY path) - 1 AS INTEGER) AS piece, bytes FROM s WHERE bytes < 8192 OR bytes <= 1""", "udtf_split_block", split_blocks)


def nearest_of_labels(s, d):
    """The five embeddings nearest to the first of each label, by JVM expressions; the query set is one row a label."""
    e = T(s, d, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("x"))
    first = e.groupBy("label").agg(F.min_by("vec_id", "vec_id").alias("query"), F.min_by("x", "vec_id").alias("y"))
    square = F.aggregate(F.zip_with("x", "y", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda a, z: a + z)
    rows = e.select("vec_id", "x").crossJoin(F.broadcast(first)).where("vec_id <> query").withColumn("d", F.round(square * 1e8).cast("long"))
    return rows.withColumn("rank", F.row_number().over(Window.partitionBy("query").orderBy("d", "vec_id")).cast("long")).where("rank <= 5").select("query", "rank", "vec_id", "d")


q("""WITH e AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS x FROM embeddings), f AS (SELECT min(vec_id) AS query FROM e GROUP BY label),
r AS (SELECT query, a.vec_id, CAST(round(list_sum(list_transform(range(1, len(a.x) + 1), lambda k: (a.x[k] - b.x[k]) * (a.x[k] - b.x[k]))) * 1e8) AS BIGINT) AS d FROM f JOIN e b ON b.vec_id = query JOIN e a ON a.vec_id <> query)
SELECT query, rank, vec_id, d FROM (SELECT *, row_number() OVER (PARTITION BY query ORDER BY d, vec_id) AS rank FROM r) WHERE rank <= 5""", "topk_nearest_embeddings", nearest_of_labels)

_SETS = {"grouping_sets": "GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())", "cube": "CUBE (l_returnflag, l_linestatus)", "rollup": "ROLLUP (l_returnflag, l_linestatus)"}
for _k, _s in _SETS.items():
    _sql = f"SELECT coalesce(l_returnflag, '*') AS flag, coalesce(l_linestatus, '*') AS status, count(*) AS n, CAST(round(sum(l_quantity)) AS BIGINT) AS quantity FROM lineitem GROUP BY {_s}"
    q(_sql, f"agg_{_k}", lambda s, d, t=_sql: (T(s, d, "lineitem").createOrReplaceTempView("lineitem"), s.sql(t))[1])


def win(s, d, users="true"):
    return T(s, d, "events").where(users).select("event_id", "user_id", "ts", "value"), Window.partitionBy("user_id").orderBy("ts", "event_id")


def _window(name, sql, make):
    """`name` has the users that its SQL has, `name`_all every user."""
    for key, users in ((name, "user_id < 40"), (f"{name}_all", "true")):

        def run(s, d, users=users):
            rows, w = win(s, d, users)
            return rows.select("event_id", *make(w))

        q(f"SELECT event_id, {sql} FROM events WHERE {users} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", key, run)


_window("win_rank", "row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr", lambda w: [F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr")])
_window("win_lag_gap", "coalesce(event_id - lag(event_id) OVER w, 0) AS gap, coalesce(lead(event_id) OVER w, -1) AS nxt", lambda w: [F.coalesce(F.col("event_id") - F.lag("event_id").over(w), F.lit(0)).alias("gap"), F.coalesce(F.lead("event_id").over(w), F.lit(-1)).alias("nxt")])
_window("win_moving_avg", "CAST(round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) * 1e4) AS BIGINT) AS avg4", lambda w: [F.round(F.avg("value").over(w.rowsBetween(-2, 0)) * 1e4).cast("long").alias("avg4")])
_window("win_ntile", "ntile(4) OVER w AS quarter", lambda w: [F.ntile(4).over(w).cast("long").alias("quarter")])
_window("win_cume", "CAST(round(cume_dist() OVER w * 1e9) AS BIGINT) AS cume, CAST(round(percent_rank() OVER w * 1e9) AS BIGINT) AS pct", lambda w: [F.round(F.cume_dist().over(w) * 1e9).cast("long").alias("cume"), F.round(F.percent_rank().over(w) * 1e9).cast("long").alias("pct")])
_window("win_first_last", "first_value(event_id) OVER w AS first_id, coalesce(nth_value(event_id, 2) OVER w, -1) AS second_id", lambda w: [F.first("event_id").over(w).alias("first_id"), F.coalesce(F.nth_value("event_id", 2).over(w), F.lit(-1)).alias("second_id")])
q("SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderpriority ORDER BY CAST(floor(o_totalprice) AS BIGINT) RANGE BETWEEN 1000 PRECEDING AND 1000 FOLLOWING) AS near FROM orders", "win_range", lambda s, d: T(s, d, "orders").select("o_orderkey", F.count("*").over(Window.partitionBy("o_orderpriority").orderBy(F.floor("o_totalprice").cast("long")).rangeBetween(-1000, 1000)).alias("near")))

q("SELECT source, doc_id, k FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS k FROM documents) WHERE k <= 3", "topk_packages", lambda s, d: T(s, d, "documents").select("source", "doc_id", F.row_number().over(Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")).cast("long").alias("k")).where("k <= 3"))


def topk_entries(s, d):
    from ..operators import assembly
    from ..operators.kernels import slp

    v = assembly.dense(small_mesh(s, 2), slp()).select("i", "j", scaled(F.col("re"), 7, "re"))
    w = Window.partitionBy("i").orderBy(F.desc("re"), "j")
    return v.withColumn("k", F.row_number().over(w).cast("long")).where("k <= 3").select("i", "k", "re")


def _topk_sql():
    from ..operators.kernels import slp
    from .mesh import matrix_sql

    return matrix_sql(slp(), 2, tail=f", z AS (SELECT i, j, {O.scaled('re', 7, 're')} FROM e) SELECT i, k, re FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY re DESC, j) AS k FROM z) WHERE k <= 3")


q(_topk_sql(), "topk_entries_per_row", topk_entries)

_A, _B = "SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 8000", "SELECT s_nationkey AS k FROM supplier"
for _k, _f in (("union", lambda a, b: a.union(b).distinct()), ("union_all", lambda a, b: a.unionAll(b)), ("intersect", lambda a, b: a.intersect(b)), ("intersect_all", lambda a, b: a.intersectAll(b)), ("except", lambda a, b: a.subtract(b)), ("except_all", lambda a, b: a.exceptAll(b))):
    q(f"{_A} {_k.upper().replace('_', ' ')} {_B}", f"set_{_k}", lambda s, d, f=_f: f(T(s, d, "customer").where("c_acctbal > 8000").select(F.col("c_nationkey").alias("k")), T(s, d, "supplier").select(F.col("s_nationkey").alias("k"))))

q("SELECT doc_id, upper(substr(source, 1, 3)) || ':' || lang AS tag, CAST(regexp_extract(source, '([0-9]+)$', 1) AS INTEGER) AS number, length(text) - length(replace(text, ' ', '')) AS spaces FROM documents", "fn_string", lambda s, d: T(s, d, "documents").select("doc_id", F.concat(F.upper(F.substring("source", 1, 3)), F.lit(":"), "lang").alias("tag"), F.regexp_extract("source", "([0-9]+)$", 1).cast("int").alias("number"), (F.length("text") - F.length(F.replace("text", F.lit(" "), F.lit("")))).cast("long").alias("spaces")))
q("SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders", "fn_date", lambda s, d: T(s, d, "orders").select("o_orderkey", F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.date_diff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days")))
q("SELECT o_orderkey, CAST(round(sqrt(o_totalprice) * 1e6) AS BIGINT) AS root6, CAST(floor(o_totalprice / 7) AS BIGINT) AS sevenths, o_orderkey % 7 AS rest, CAST(round(coalesce(o_totalprice / nullif(o_orderkey % 3, 0), -1) * 100) AS BIGINT) AS part100 FROM orders", "fn_math", lambda s, d: T(s, d, "orders").select("o_orderkey", F.round(F.sqrt("o_totalprice") * 1e6).cast("long").alias("root6"), F.floor(F.col("o_totalprice") / 7).cast("long").alias("sevenths"), F.pmod("o_orderkey", F.lit(7)).alias("rest"), F.round(F.coalesce(F.try_divide("o_totalprice", F.pmod("o_orderkey", F.lit(3))), F.lit(-1.0)) * 100).cast("long").alias("part100")))
q("SELECT vec_id, CAST(round(list_reduce(list_prepend(0.0::DOUBLE, list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), lambda a, b: a + b) * 1e6) AS BIGINT) AS norm6, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive FROM embeddings", "fn_array", lambda s, d: T(s, d, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")) * 1e6).cast("long").alias("norm6"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive")))
q("SELECT lang, CAST(sum(CASE WHEN source = 'src0' THEN n_chars ELSE 0 END) AS BIGINT) AS zero, count(*) AS n FROM documents GROUP BY lang", "fn_map", lambda s, d: T(s, d, "documents").select("lang", F.create_map("source", "n_chars").alias("m")).groupBy("lang").agg(F.sum(F.coalesce(F.try_element_at("m", F.lit("src0")), F.lit(0))).alias("zero"), F.count("*").alias("n")))
q("SELECT event_id, CAST(round((value * 0.6 - user_id * 0.8) * 1e4) AS BIGINT) AS re4, CAST(round((value * 0.8 + user_id * 0.6) * 1e4) AS BIGINT) AS im4 FROM events", "fn_struct", lambda s, d: T(s, d, "events").select("event_id", F.struct(F.col("value").alias("re"), F.col("user_id").cast("double").alias("im")).alias("z")).select("event_id", F.round((F.col("z.re") * 0.6 - F.col("z.im") * 0.8) * 1e4).cast("long").alias("re4"), F.round((F.col("z.re") * 0.8 + F.col("z.im") * 0.6) * 1e4).cast("long").alias("im4")))
q("SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1", "fn_json", lambda s, d: T(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n")))


def udf_pair(s, d):
    """slp_entry of SQL text on touching and far pairs of one panel."""
    from .. import functions
    from ..operators import assembly, classify

    functions.register(s)
    panels = small_mesh(s, 2)
    rows = classify.aligned(assembly.with_geometry(classify.touching(panels), panels))
    corners = lambda x: F.array(*[F.col(f"{x}_{p}{a}") for p in "abc" for a in "xyz"])
    rows.select("i", "j", "case", corners("a").alias("a"), corners("b").alias("b")).createOrReplaceTempView("aligned_pairs")
    return s.sql("SELECT i, j, CAST(round(slp_entry(a, b, case) * 1e8) AS BIGINT) AS re8 FROM aligned_pairs")


def _udf_sql():
    from .mesh import O as P

    from ..operators.kernels import slp

    return f"WITH {P.panels(2)}, {P.touching()}, {P.rules(3, 5, (1, 2, 3))}, {P.entries('near', 'slp', slp().kappa)} SELECT i, j, {P.scaled('re', 8, 're8')} FROM e"


q(_udf_sql(), "udf_pair", udf_pair)


def udtf_rule(s, d):
    from .. import functions

    functions.register(s)
    return s.sql("SELECT q, CAST(round(x * 1e10) AS BIGINT) AS x10, CAST(round(w * 1e10) AS BIGINT) AS w10 FROM gauss_rule(5)")


def _gauss_sql():
    from ..operators.quadrature import gauss

    return "SELECT * FROM (VALUES " + ", ".join(f"({k}, {round(x * 1e10)}::BIGINT, {round(w * 1e10)}::BIGINT)" for k, (x, w) in enumerate(zip(*gauss(5), strict=True))) + ") AS t(q, x10, w10)"


q(_gauss_sql(), "udtf_rule", udtf_rule)


def sql_functions(s, d):
    from .. import functions

    functions.register(s)
    small_mesh(s, 2).createOrReplaceTempView("mesh_panels_view")
    return s.sql("SELECT a.pid AS i, b.pid AS j, common_vertices(array(a.v0, a.v1, a.v2), array(b.v0, b.v1, b.v2)) AS common, CAST(round(box_dist(array(a.lox, a.loy, a.loz), array(a.hix, a.hiy, a.hiz), array(b.lox, b.loy, b.loz), array(b.hix, b.hiy, b.hiz)) * 1e9) AS BIGINT) AS dist9 FROM mesh_panels_view a JOIN mesh_panels_view b ON a.pid <= b.pid")


q(f"WITH {O.panels(2)} SELECT a.pid AS i, b.pid AS j, CAST(len(list_filter([a.v0, a.v1, a.v2], lambda x: list_contains([b.v0, b.v1, b.v2], x))) AS INTEGER) AS common, {O.scaled('greatest(0.0, a.lox - b.hix, b.lox - a.hix, a.loy - b.hiy, b.loy - a.hiy, a.loz - b.hiz, b.loz - a.hiz)', 9, 'dist9')} FROM p a JOIN p b ON a.pid <= b.pid", "sql_functions", sql_functions)


def source_mesh(s, d):
    from .. import sources

    sources.register(s)
    return s.read.format("sphere_mesh").option("n", 3).load().select("pid", "v0", "v1", "v2", *[scaled(F.col(f"{p}z"), 10, f"{p}z") for p in "abc"])


q(f"WITH {O.panels(3)} SELECT pid, v0, v1, v2, {O.scaled('az', 10, 'az')}, {O.scaled('kz', 10, 'bz')}, {O.scaled('cz', 10, 'cz')} FROM p", "source_mesh", source_mesh)
