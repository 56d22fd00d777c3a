"""Queries against their SQL on the smallest tables, golden values and invariants."""

import pytest
from helpers import same_rows
from pyspark.sql import functions as F

from panelspark import catalog
from panelspark.config import EngineConfig
from panelspark.operators import classify, geometry, packages, schedule

FAST = [
    "mesh_vertices", "mesh_panels", "mesh_euler", "quadrature_rule", "lineitem_shared_ids", "slp_edge", "package_split", "package_greedy", "package_prefix", "worker_makespan",
    "cluster_tree", "cluster_morton", "block_tree", "boundary_values", "paper_speedups", "join_full", "join_range_cells", "join_interval_overlap", "agg_cube", "win_rank", "set_except_all", "fn_array",
]


@pytest.mark.parametrize("name", FAST)
def test_query_matches_sql(spark, data, duck, name):
    assert same_rows(catalog.queries()[name](spark, data), duck.execute(catalog.oracle_sql()[name]).df())


def test_every_query_is_listed_once():
    assert set(catalog.oracle_sql()) <= set(catalog.queries())


@pytest.mark.parametrize(("n", "counts"), [(2, {0: 656, 1: 240, 2: 96, 3: 32}), (4, {0: 14768, 1: 1104, 2: 384, 3: 128})])
def test_golden_classes(spark, n, counts):
    got = classify.class_histogram(geometry.sphere_panels(spark, n)).collect()
    assert {r["case"]: r["pairs"] for r in got} == counts


def test_no_cross_join_in_classification(spark):
    plan = classify.touching(geometry.sphere_panels(spark, 3))._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan


def test_golden_lists(spark, data):
    items = spark.read.parquet(f"{data}/documents.parquet").select(F.col("doc_id").alias("item"), F.lit("all").alias("producer"), F.col("n_chars").alias("bytes"))
    got = packages.greedy(items, 8192, ["item"]).groupBy("list").agg(F.sum("bytes").alias("b"), F.count("*").alias("c")).agg(F.count("*"), F.sum("c"), F.max("b")).first()
    assert tuple(got) == (76, 215, 8170)


def test_split_edge_cases(spark):
    rows = spark.createDataFrame([(1, 8), (2, 7), (3, 1), (4, 17), (5, 0)], "item long, bytes long")
    got = {(r["item"], r["piece"]): r["bytes"] for r in packages.split_oversized(rows, 8).collect()}
    assert got == {(1, 0): 4, (1, 1): 4, (2, 0): 7, (3, 0): 1, (4, 0): 5, (4, 1): 4, (4, 2): 4, (4, 3): 4, (5, 0): 0}
    assert packages.split_oversized(rows.limit(0), 8).count() == 0


def test_workers_hide_host_work():
    one, two, four = (schedule.occupancy(1.0, 2.0, 50, w) for w in (1, 2, 4))
    assert one < two and two > 0.95 and four >= two


def test_config_refuses_wide_admissibility():
    with pytest.raises(ValueError):
        EngineConfig(eta=2.0)
    with pytest.raises(ValueError):
        EngineConfig(norm="l1")


@pytest.mark.parametrize("name", ["win_rank_all", "win_lag_gap_all", "win_moving_avg_all", "win_ntile_all", "win_cume_all", "win_first_last_all"])
def test_windows_see_every_user(spark, data, duck, name):
    got = catalog.queries()[name](spark, data)
    assert got.count() == spark.read.parquet(f"{data}/events.parquet").count()
    assert same_rows(got, duck.execute(catalog.oracle_sql()[name]).df())


def test_shared_ids_of_all_rows(spark, tmp_path):
    rows = [(k * 7 % 400, k % 5, k % 3, 1, 1.0, float(k)) for k in range(90)] + [(900, None, 1, 1, 1.0, 1.0), (900, None, 2, 1, 1.0, 1.0)]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double").write.parquet(f"{tmp_path}/lineitem.parquet")
    want = {}
    for a in rows:
        for b in rows:
            k = sum(x is not None and x == y for x, y in zip(a[:3], b[:3], strict=True))
            want[k] = want.get(k, 0) + 1
    got = {r["common"]: r["pairs"] for r in catalog.queries()["lineitem_shared_ids_all"](spark, str(tmp_path)).collect()}
    assert got == want


def test_overlaps_of_whole_lifetimes(spark, tmp_path):
    import duckdb

    rows = [(0, "a", 128_657), (3, "a", 10), (60, "a", 100), (700, "a", 5_001), (760, "a", 0), (1286, "a", 9), (1287, "a", 9), (61, "b", 6_000), (121, "b", 1)]
    spark.createDataFrame(rows, "doc_id long, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    want = sorted((i, j) for i, s, n in rows for j, t, m in rows if s == t and i < j and i * 100 < j * 100 + m and j * 100 < i * 100 + n)
    got = catalog.queries()["join_interval_overlap_all"](spark, str(tmp_path))
    assert (0, 1286) in want and (0, 1287) not in want
    assert sorted(map(tuple, got.collect())) == want
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    assert same_rows(got, con.execute(catalog.oracle_sql()["join_interval_overlap_all"]).df())


@pytest.mark.parametrize("name", ["potential_of_price_all", "potential_of_balance_all", "representation_eval_all"])
def test_potentials_of_all_rows(spark, data, duck, name):
    assert same_rows(catalog.queries()[name](spark, data), duck.execute(catalog.oracle_sql()[name]).df())


def test_folded_panels_lose_no_row(spark):
    for n in (5, 300):
        rows = spark.range(n).select(F.col("id").alias("k"), (F.col("id") * 1.5 + 1).alias("v"))
        got = geometry.folded_panels(spark, rows, "k", "v", 4).select("pid", "density").collect()
        assert {r["pid"]: r["density"] for r in got} == {p: sum(k * 1.5 + 1 for k in range(p, n, 128)) for p in range(128)}


@pytest.fixture(scope="module")
def spread(spark, tmp_path_factory):
    """More points than the dense SQL of the compression queries has."""
    import numpy as np

    d = str(tmp_path_factory.mktemp("spread"))
    x = np.random.default_rng(7).normal(size=(420, 3))
    spark.createDataFrame([(k, k % 3, [float(a) for a in v]) for k, v in enumerate(x)], "vec_id long, label int, embedding array<double>").write.parquet(f"{d}/embeddings.parquet")
    return d, x / np.linalg.norm(x, axis=1)[:, None]


def test_compression_takes_all_points(spark, spread):
    import numpy as np

    d, u = spread
    r = np.linalg.norm(u[:, None] - u[None], axis=2)
    np.fill_diagonal(r, np.inf)
    g = 1 / (4 * np.pi * r)
    got = {x["i"]: x["y10"] for x in catalog.queries()["h2_matvec_all"](spark, d).collect()}
    assert len(got) == 420 and all(abs(got[k] - 10 * y) <= 0.5 + 1e-3 for k, y in enumerate(g.sum(1)))
    direct = {x["i"]: x["potential"] for x in catalog.queries()["point_potential_all"](spark, d).collect()}
    assert len(direct) == 420 and all(abs(direct[k] - 1e6 * y) <= 1 for k, y in enumerate(g @ (1.0 + np.arange(420) % 3)))
    assert catalog.queries()["green_factor_all"](spark, d).count() == (u[:, 2] > 0.8).sum()
    assert catalog.queries()["monopole_far"](spark, d).first()["points"] == 420
