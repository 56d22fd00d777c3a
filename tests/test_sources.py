"""Readers, writers and SQL functions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from panelspark import sources
from panelspark.config import EngineConfig
from panelspark.operators import assembly, classify, fields, geometry, h2, solve
from panelspark.operators.kernels import dlp, slp
from panelspark.plans.scratch import settled
from panelspark.session import Session


@pytest.fixture(scope="module")
def panels(spark):
    return settled(geometry.with_metrics(geometry.sphere_panels(spark, 3)))


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_mesh_source_equals_the_generator(spark):
    sources.register(spark)
    got = spark.read.format("sphere_mesh").option("n", 5).load()
    assert rows(got) == rows(geometry.sphere_panels(spark, 5)) and got.count() == 200


def test_meshes_survive_text_csv_json_parquet(spark, panels, tmp_path):
    want = rows(panels.select(*geometry.sphere_panels(spark, 1).columns))
    sources.write_off(panels, f"{tmp_path}/off")
    assert rows(sources.read_off(spark, f"{tmp_path}/off")) == want
    for form in ("csv", "json", "parquet"):
        sources.write_mesh(panels, f"{tmp_path}/{form}", form)
        assert rows(sources.read_mesh(spark, f"{tmp_path}/{form}", form)) == want


def test_saved_blocks_prune_and_a_saved_matrix_reads_back(spark, tmp_path):
    s = Session(spark, EngineConfig(leaf_size=8))
    s.mesh(3)
    s.panels = settled(s.panels)
    a = s.compress(slp())
    sources.save_blocks(s.blocks, f"{tmp_path}/blocks")
    back = spark.read.parquet(f"{tmp_path}/blocks").where("kind = 'near'")
    assert back.count() == s.blocks.where("kind = 'near'").count()
    assert "PartitionFilters: [isnotnull(kind" in back._jdf.queryExecution().toString()
    h2.save(a, f"{tmp_path}/h2")
    assert spark.read.parquet(f"{tmp_path}/h2/nearfield").count() == a.nearfield.count()


def test_bucketed_tables_join_without_a_shuffle(spark, panels):
    left, right = panels.select("pid", "area"), classify.touching(panels).select(F.col("i").alias("pid"), "j")
    try:
        sources.save_bucketed(left, "bucketed_a", "pid", 4)
        sources.save_bucketed(right, "bucketed_b", "pid", 4)
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        out = spark.table("bucketed_a").join(spark.table("bucketed_b"), "pid")
        assert "Exchange" not in out._jdf.queryExecution().executedPlan().toString() and out.count() == right.count()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE IF EXISTS bucketed_a")
        spark.sql("DROP TABLE IF EXISTS bucketed_b")


def test_entry_functions_of_both_layers(spark, panels):
    from panelspark.functions import register

    register(spark)
    pairs = classify.classes(assembly.all_pairs(panels, 10**6), panels).where("i < 4 and case = 0")
    geo = panels.select("pid", F.array(*geometry.COORDS).alias("g"))
    both = pairs.join(geo.select(F.col("pid").alias("i"), F.col("g").alias("a")), "i").join(geo.select(F.col("pid").alias("j"), F.col("g").alias("b")), "j")
    both.createOrReplaceTempView("panel_pairs")
    got = spark.sql("SELECT i, j, slp_entry(a, b, case) AS v, dlp_entry(a, b, case) AS k FROM panel_pairs").toPandas().sort_values(["i", "j"])
    for kernel, column in ((slp(), "v"), (dlp(), "k")):
        want = assembly.entries(pairs, panels, kernel).toPandas().sort_values(["i", "j"])
        assert np.allclose(got[column], want["re"], atol=1e-13)


def test_exterior_wave_in_both_formulations(spark):
    mesh = settled(geometry.with_metrics(geometry.sphere_panels(spark, 2)))
    v, k = (settled(assembly.dense(mesh, x)) for x in (slp(3.0), dlp(3.0)))
    re, im = fields.f_wave(F.col("gx"), F.col("gy"), F.col("gz"), 3.0)
    rhs = mesh.select(F.col("pid").alias("i"), (re * F.col("area")).alias("re"), (im * F.col("area")).alias("im"))
    size = 32
    table = lambda df: (lambda r: np.bincount(r["i"] * size + r["j"], r["re"], size * size).reshape(size, size) + 1j * np.bincount(r["i"] * size + r["j"], r["im"], size * size).reshape(size, size))(df.toPandas())
    b = (lambda r: (r["re"] + 1j * r["im"]).to_numpy())(rhs.toPandas().sort_values("i"))
    m = np.diag(mesh.toPandas().sort_values("pid")["area"].to_numpy())
    for formulation, a in (("combined", m / 2 + table(k) - 1j * table(v)), ("single", table(v))):
        x, report = solve.wave_exterior(v, k, assembly.mass_matrix(mesh), rhs, formulation=formulation, tol=1e-9)
        got = (lambda r: (r["re"] + 1j * r["im"]).to_numpy())(x.toPandas().sort_values("i"))
        assert report.residuals[-1] < 1e-9 and np.allclose(a @ got, b, atol=1e-7)
