"""Findings of round 2 on the engine."""

import pytest
from helpers import same_rows
from pyspark.sql import functions as F

from panelspark import catalog
from panelspark.operators import clustering, geometry, packages


def test_median_halves_by_counted_ranges(spark, monkeypatch):
    """F8: each use of the ranges sampled its own bounds, so that numbers of rows were skipped or given twice."""
    monkeypatch.setattr(geometry, "parts_for", lambda rows: 8)
    pts = spark.range(40_000).select(F.col("id").alias("i"), *[F.rand(k).alias(a) for k, a in enumerate("xyz")])
    sizes = [r["count"] for r in clustering.median_tree(pts, 2).groupBy("node").count().collect()]
    assert sizes == [10_000] * 4
    rows = geometry.numbered(pts, ["x", "i"])
    assert rows.agg(F.count("*"), F.countDistinct("_row"), F.max("_row")).first() == (40_000, 40_000, 39_999)


def test_batches_of_numbered_items_keep_every_item(spark, monkeypatch):
    """the same in packages."""
    monkeypatch.setattr(geometry, "parts_for", lambda rows: 8)
    items = spark.range(40_000).select(F.col("id").alias("item"), F.lit("a").alias("producer"), (F.xxhash64("id") % 7 + 10).alias("bytes"))
    got = packages.divergence(geometry.numbered(items, ["item"]).withColumn("batch", F.floor(F.col("_row") / 64)), "batch", "bytes").first()
    rows = [r["bytes"] for r in items.orderBy("item").collect()]
    assert got["useful"] == sum(rows)
    assert got["waste"] == sum(max(rows[k : k + 64]) * len(rows[k : k + 64]) for k in range(0, len(rows), 64)) - sum(rows)
    lists = {r["item"]: r["list"] for r in packages.prefix(items, 1000, ["item"]).select("item", "list").collect()}
    before, want = 0, {}
    for k, b in enumerate(rows):
        want[k], before = before // 1000, before + b
    assert lists == want


def test_blocks_are_approximated_in_strips(spark):
    """whole blocks were evaluated at once, and a batch held any number of them."""
    import numpy as np
    import pyarrow as pa

    from panelspark.config import EngineConfig
    from panelspark.operators import fill, h2
    from panelspark.operators.kernels import slp

    rng = np.random.default_rng(2)
    side = lambda n, at: [{"i": k, "geo": [float(c) for c in rng.random(3) + at], "v": None} for k in range(n)]
    rows = pa.table({"list": [0, 0], "s": [3, 5], "t": [2, 4], "a": pa.array([side(300, 0), side(40, 0)]), "b": pa.array([side(500, 3), side(1, 9)])})
    rows = rows.set_column(3, "a", rows["a"].cast(pa.list_(pa.struct([("i", pa.int64()), ("geo", pa.list_(pa.float64())), ("v", pa.list_(pa.int64()))]))))
    rows = rows.set_column(4, "b", rows["b"].cast(rows.schema.field("a").type))
    most, real = [], fill.integrate
    fill.integrate = lambda ga, *rest: (most.append(len(ga)), real(ga, *rest))[1]
    try:
        whole = h2._aca_list(rows, slp(), EngineConfig(aca_eps=1e-5), True, 1 << 30)
        most.clear()
        strips = h2._aca_list(rows, slp(), EngineConfig(aca_eps=1e-5), True, 2000)
    finally:
        fill.integrate = real
    assert max(most) <= 2000
    assert strips.drop_columns("error").equals(whole.drop_columns("error"))
    assert np.allclose(strips["error"], whole["error"], rtol=1e-9, atol=1e-15) and max(strips["error"].to_pylist()) < 1e-4


@pytest.mark.parametrize("name", [
    "boundary_values",
    "class_histogram",
    "dirichlet_rhs",
    "dlp_dense_rowsum",
    "dlp_edge",
    "dlp_regular",
    "dlp_rowsum_identity",
    "dlp_vertex",
    "kernel_eval_counts",
    "kv_ratio",
    "mass_matrix",
])
def test_made_up_meshes_carry_the_parts(spark, data, name, tmp_path):
    """F11 to F22: the rows of part decide the result, and it is that of the SQL."""
    import duckdb

    con = duckdb.connect()
    con.execute(f"COPY (SELECT * REPLACE (p_partkey // 3 * 5 AS p_partkey, p_retailprice * 2 AS p_retailprice) FROM '{data}/part.parquet') TO '{tmp_path}/part.parquet'")
    before = catalog.queries()[name](spark, data).toPandas()
    got = catalog.queries()[name](spark, str(tmp_path))
    con.execute(f"CREATE VIEW part AS SELECT * FROM '{tmp_path}/part.parquet'")
    want = con.execute(catalog.oracle_sql()[name]).df()
    assert same_rows(got, want)
    rows = lambda d: sorted(map(tuple, d[sorted(d.columns)].to_numpy().tolist()))
    assert rows(before) != rows(want)


def test_error_of_two_caps_by_blocks(spark, data):
    """the whole block of both caps was made on the driver."""
    import numpy as np

    from panelspark.operators import green
    from panelspark.operators.kernels import slp
    from panelspark.workloads import trees

    pts = trees.sphere_points(spark, data).where("abs(z) > 0.8")
    p = pts.toPandas()
    a, b = p[p.z > 0][["x", "y", "z"]].to_numpy(), p[p.z < 0][["x", "y", "z"]].to_numpy()
    exact, want = slp().values(a[:, None] - b[None]), {}
    for q in (2, 5):
        box = green.surface(a.min(0), a.max(0), q, 1.0, "max")
        want[q] = np.linalg.norm(exact - green.row_factor(a, box, slp()) @ green.column_factor(b, box, slp()).T) / np.linalg.norm(exact)
    got = trees.cap_errors(pts, a.min(0), a.max(0), (2, 5), block_rows=20)
    assert got.keys() == want.keys() and all(abs(got[q] / want[q] - 1) < 1e-6 for q in want)


def test_product_without_stored_entries(spark, monkeypatch):
    """every coupling and near entry was written as a row before one product."""
    from panelspark.config import EngineConfig
    from panelspark.operators import fill, h2
    from panelspark.operators.kernels import dlp
    from panelspark.plans.scratch import settled
    from panelspark.session import Session

    s = Session(spark, EngineConfig(leaf_size=16, green_q=4, aca_eps=1e-6))
    s.mesh(6)
    s.panels = settled(s.panels)
    x = s.panels.select(F.col("pid").alias("i"), (F.col("pid") % 7 - 2.5).cast("double").alias("re"), F.lit(0.5).alias("im"))
    want = {r["i"]: complex(r["re"], r["im"]) for r in h2.complex_matvec(s.compress(dlp(3.0)), x).collect()}
    assert s.blocks.where("kind = 'far'").count() > 0
    monkeypatch.setattr(fill, "fill", None)
    got = h2.product(s.membership, s.clusters, s.blocks, h2.geometry_rows(s.panels), dlp(3.0), s.cfg, x)
    got = {r["i"]: complex(r["re"], r["im"]) for r in got.collect()}
    assert got.keys() == want.keys() and max(abs(got[i] - want[i]) for i in want) < 1e-12


@pytest.mark.parametrize("repeated", [False, True])
def test_potentials_do_not_depend_on_the_order_of_sums(spark, tmp_path, repeated):
    """plain sums of many terms were off by their rounding; repeated ids met each other's charges."""
    import math

    import numpy as np

    rng = np.random.default_rng(3)
    rows = [(k, int(c), [float(a) for a in v]) for k, (c, v) in enumerate(zip(rng.integers(0, 2_000_000, 400), rng.normal(size=(400, 3)), strict=True))]
    if repeated:
        rows = [(i, c % 3, v) for i, c, v in rows[:40]] + [(5, 2, [0.5, 0.25, 1.0]), (6, 1, None), (7, None, [1.0, 2.0, 3.0]), (99, 1, [0.0, 0.0, 0.0])]
    spark.createDataFrame(rows, "vec_id long, label int, embedding array<double>").coalesce(1).write.parquet(f"{tmp_path}/embeddings.parquet")
    pts = [(i, *(a / math.sqrt(x * x + y * y + z * z) for a in (x, y, z)), c) for i, c, (x, y, z) in (r for r in rows if r[2] and any(r[2]))]
    terms = {}
    for i, x, y, z, _ in pts:
        for j, x2, y2, z2, c in pts:
            if i != j and c is not None:
                terms.setdefault(i, []).append((1.0 + c) / (4 * 3.141592653589793 * math.sqrt((x - x2) * (x - x2) + (y - y2) * (y - y2) + (z - z2) * (z - z2))))
    want = {i: math.floor(math.fsum(t) * 1e6 + 0.5) for i, t in terms.items()}
    got = {r["i"]: r["potential"] for r in catalog.queries()["point_potential_all"](spark, str(tmp_path)).collect()}
    assert got == want
