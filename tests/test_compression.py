"""Trees, packages of entries, compressed matrices and solvers against dense versions."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from panelspark.config import EngineConfig
from panelspark.operators import assembly, blocks, classify, clustering, fields, fill, geometry, h2, measures, solve
from panelspark.operators.kernels import dlp, slp
from panelspark.plans.scratch import discard, settled
from panelspark.session import Session


@pytest.fixture(scope="module")
def sphere(spark):
    s = Session(spark, EngineConfig(leaf_size=8, green_q=5, aca_eps=1e-8, symmetric=False))
    s.mesh(3)
    s.panels = settled(s.panels)
    s.tree()
    return s


def matrix(values, n, column="re"):
    rows = values.toPandas()
    out = np.zeros((n, n))
    out[rows["i"], rows["j"]] = rows[column]
    return out


def vector(frame, column="value"):
    return frame.toPandas().set_index("i")[column].sort_index().to_numpy()


def test_trees_by_levels_and_by_tasks_are_one(spark):
    rng = np.random.default_rng(1)
    x = rng.random((400, 3)).round(2)
    x[:40] = x[0]
    pts = spark.createDataFrame([(k, *map(float, p)) for k, p in enumerate(x)], "i long, x double, y double, z double")
    trees = [sorted(map(tuple, clustering.geometric_tree(pts, 8, finish).collect())) for finish in (1 << 16, 60, 8)]
    assert trees[0] == trees[1] == trees[2] and len(trees[0]) == 400
    assert clustering.geometric_tree(pts.limit(0), 8).count() == 0


def test_trees_stop_where_points_cannot_be_told_apart(spark):
    pts = spark.createDataFrame([(k, 1e-12 * (k // 3) if k < 30 else 1.0, 0.0, 0.0) for k in range(60)], "i long, x double, y double, z double")
    tree = clustering.geometric_tree(pts, 1)
    assert tree.count() == 60 and tree.agg(F.max("level")).first()[0] <= 60


def test_median_tree_halves_by_count(spark):
    pts = spark.createDataFrame([(k, float(k * 7 % 50), float(k * 3 % 11), 0.0) for k in range(101)], "i long, x double, y double, z double")
    sizes = sorted(r["count"] for r in clustering.median_tree(pts, 3).groupBy("node").count().collect())
    assert len(sizes) == 8 and sizes[-1] - sizes[0] <= 1 and sum(sizes) == 101


@pytest.mark.parametrize("symmetric", [False, True])
def test_block_trees_cover_every_entry_once(spark, sphere, symmetric):
    a = settled(blocks.block_tree(sphere.clusters, symmetric=symmetric))
    b = blocks.block_tree(sphere.clusters, symmetric=symmetric, broadcast_rows=0)
    c = blocks.block_tree(sphere.clusters, symmetric=symmetric, seeds=2)
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect())) == sorted(map(tuple, c.collect()))
    node = {r["i"]: r["node"] for r in sphere.membership.collect()}
    count = np.zeros((72, 72), int)
    below = lambda leaf, top: leaf >> (leaf.bit_length() - top.bit_length()) == top if leaf.bit_length() >= top.bit_length() else False
    for r in a.collect():
        t, s = ([i for i, leaf in node.items() if below(leaf, r[c])] for c in "ts")
        count[np.ix_(t, s)] += 1
        if symmetric and r["t"] != r["s"]:
            count[np.ix_(s, t)] += 1
    assert (count == 1).all()
    assert blocks.coverage(a, sphere.clusters.where("is_leaf"), symmetric).first()["covered"] == 72 * 72


@pytest.mark.parametrize("kernel", [slp(), dlp(), slp(3.0), dlp(3.0)])
def test_block_packages_equal_one_pass(spark, sphere, kernel):
    member = settled(fill.members(clustering.ancestors(sphere.membership).select("node", "i").join(h2.geometry_rows(sphere.panels), "i")))
    want = assembly.one_pass(sphere.panels, kernel)
    for phases, rule, limit in (("two", "prefix", 1 << 12), ("one", "greedy", 1 << 20)):
        got = settled(fill.fill(sphere.blocks.select("t", "s"), member, member, kernel, EngineConfig(limit_bytes=limit), phases, rule))
        assert got.count() == 72 * 72
        for column in ("re", "im") if kernel.complex else ("re",):
            assert np.allclose(matrix(got, 72, column), matrix(want, 72, column), atol=1e-12)


def test_lists_stay_below_the_limit(spark):
    rows = spark.createDataFrame([(k, k + 1, 1 + k % 7, 1 + k * 5 % 90) for k in range(60)], "t long, s long, m long, n long")
    for limit in (64, 1000, 50_000):
        pieces = fill.cut(rows, limit).collect()
        assert all(p["bytes"] < max(limit, 33) for p in pieces)
        cells = {}
        for p in pieces:
            for r in range(p["r0"], p["r0"] + p["m"]):
                for c in range(p["c0"], p["c0"] + p["n"]):
                    assert (p["t"], r, c) not in cells
                    cells[p["t"], r, c] = 1
        assert len(cells) == sum(r["m"] * r["n"] for r in rows.collect())
        for rule in ("prefix", "greedy"):
            size = fill.lists(rows, limit, rule).groupBy("list").agg(F.sum("bytes").alias("b"), F.max("bytes").alias("x")).collect()
            assert all(s["b"] < limit + s["x"] for s in size) and sum(s["b"] for s in size) == 16 * len(cells)


def test_alignment_of_arrays_equals_that_of_columns(spark, sphere):
    rows = classify.aligned(assembly.with_geometry(classify.touching(sphere.panels), sphere.panels)).toPandas()
    v = sphere.panels.toPandas().set_index("pid").sort_index()[["v0", "v1", "v2"]].to_numpy()
    va, vb = v[rows["i"]], v[rows["j"]]
    case, pa_, pb_ = fill._aligned(va, vb)
    assert (case == rows["case"]).all()
    assert (np.take_along_axis(va, pa_, 1) == rows[["a_v0", "a_v1", "a_v2"]].to_numpy()).all()
    assert (np.take_along_axis(vb, pb_, 1) == rows[["b_v0", "b_v1", "b_v2"]].to_numpy()).all()


def test_touching_blocks_hold_all_touching_pairs(spark, sphere):
    got = {(r["t"], r["s"]) for r in fill.touching_blocks(sphere.blocks.select("t", "s"), sphere.membership, sphere.panels).collect()}
    node = {r["i"]: r["node"] for r in sphere.membership.collect()}
    assert got == {(node[r["i"]], node[r["j"]]) for r in classify.touching(sphere.panels).collect()}


@pytest.mark.parametrize("kernel", [slp(), dlp(), dlp(3.0)])
def test_compressed_products_equal_dense_ones(spark, kernel):
    s = Session(spark, EngineConfig(leaf_size=8, green_q=5, aca_eps=1e-9, band=2))  # several bands on a small tree
    s.mesh(4)
    s.panels = settled(s.panels)
    a = s.compress(kernel)
    assert a.symmetric == (kernel.layer == "slp") and a.depth >= 3 and s.blocks.where("kind = 'far'").count() > 0
    x = s.panels.select(F.col("pid").alias("i"), (1.0 + F.col("gx") * 2).alias("re"), (F.col("gy") if kernel.complex else F.lit(0.0)).alias("im"))
    got = h2.complex_matvec(a, x)
    dense = assembly.dense(s.panels, kernel)
    m = matrix(dense, 128) + 1j * matrix(dense, 128, "im")
    want = m @ (vector(x, "re") + 1j * vector(x, "im"))
    y = vector(got, "re") + 1j * vector(got, "im")
    assert np.linalg.norm(y - want) < 1e-5 * np.linalg.norm(want)  # the mirrored half differs by quadrature errors
    parts = {r["part"] for r in h2.storage(a).collect()}
    assert parts == {"leaf basis", "transfer", "coupling", "nearfield"} and set(a.seconds) == {"interpolation", "coupling", "near field"}


def test_forms_of_compression(spark, sphere):
    member = settled(clustering.ancestors(sphere.membership).select("node", "i").join(h2.geometry_rows(sphere.panels), "i"))
    far = sphere.blocks.where("kind = 'far'")
    every = fill.members(member)
    exact = settled(fill.fill(far, every, every, slp(), sphere.cfg, "one"))
    for method, tol in (("one_sided", 1e-4), ("two_sided", 1e-4), ("unpivoted", 1e-2)):
        worst = measures.block_error(exact, sphere.compress(slp(), method), ["t", "s"]).agg(F.max("error")).first()[0]
        assert worst < tol, (method, worst)
    aca = sphere.compress(slp(), "aca").collect()
    size = {(r["t"], r["s"]): (r["rows"], r["cols"]) for r in far.collect()}
    assert all(r["error"] is None and r["evaluated"] == r["rank"] * sum(size[r["t"], r["s"]]) for r in aca)
    partial = EngineConfig(leaf_size=8, green_q=5, aca_eps=1e-8, pivot="partial")
    row = h2.flat_basis(sphere.membership, sphere.clusters, h2.geometry_rows(sphere.panels), slp(), partial, "row", sphere.blocks)
    worst = measures.block_error(exact, h2.one_sided(far, settled(row), member, slp(), partial), ["t", "s"]).agg(F.max("error")).first()[0]
    assert worst < 1e-3


def test_accuracy_follows_the_mesh():
    cfg = EngineConfig()
    steps = [cfg.for_level(n) for n in (16, 32, 64, 128)]
    assert [c.aca_eps for c in steps] == [1e-4, 1e-4 / 4, 1e-4 / 16, 1e-4 / 64] and [c.green_q for c in steps] == [4, 4, 5, 5]


def test_conjugate_gradients_with_and_without_preconditioner(spark, sphere):
    v = settled(assembly.dense(sphere.panels, slp()))
    dense = matrix(v, 72)
    dense = (dense + dense.T) / 2
    even = v.union(v.select(F.col("j").alias("i"), F.col("i").alias("j"), "re", "im")).groupBy("i", "j").agg((F.sum("re") / 2).alias("re"))
    even = settled(even)
    b = fields.project(sphere.panels, fields.f2)
    want = np.linalg.solve(dense, vector(b))
    diag = even.where("i = j").select("i", F.col("re").alias("d"))
    leaf = solve.block_diagonal(even, sphere.membership)
    steps = {}
    for name, pre in (("none", None), ("diagonal", diag), ("leaves", leaf)):
        x, report = solve.cg(solve.entry_apply(even), b, tol=1e-8, precond=pre)
        assert np.linalg.norm(vector(x) - want) < 1e-5 * np.linalg.norm(want)
        steps[name] = report.steps
    assert max(steps.values()) < 72


def test_projection_by_means_and_centroids(spark, sphere):
    a, b = (vector(fields.project(sphere.panels, fields.f1, how)) for how in ("centroid", "mean"))
    assert 0 < np.abs(a - b).max() < 0.05


def test_hat_functions_sum_to_the_constant_ones(spark):
    """Singular classes too: the hats of a panel add up to one, so local matrices add up to the entry of constants."""
    panels = settled(geometry.with_metrics(geometry.sphere_panels(spark, 2)))
    pairs = settled(classify.classes(assembly.all_pairs(panels, 10**6), panels))
    for kernel in (slp(), dlp()):
        hats = assembly.p1_scatter(pairs, panels, kernel).agg(F.sum("re")).first()[0]
        assert hats == pytest.approx(assembly.one_pass(panels, kernel, pairs=pairs.select("i", "j")).agg(F.sum("re")).first()[0], rel=1e-9)
    local = assembly.p1_scatter(pairs.where("case = 3 and i = 0"), panels, slp()).collect()
    got = {(r["vi"], r["vj"]): r["re"] for r in local}
    assert len(got) == 9 and all(got[a, b] == pytest.approx(got[b, a], rel=1e-6) for a, b in got)


def test_facade(spark, sphere):
    assert {r["case"]: r["pairs"] for r in sphere.classify().collect()} == {0: 4296, 1: 600, 2: 216, 3: 72}
    a = sphere.compress(slp())
    report = sphere.measure(a)
    assert report["us_per_dof"] > 0 and report["of_dense"] > 0
    b = fields.project(sphere.panels, fields.f2)
    x, got = sphere.solve(a, b, tol=1e-3, maxit=3)
    assert x.count() == 72 and got.steps <= 3
    two, one = (settled(sphere.assemble(slp(), m)) for m in ("two_phase", "packages"))
    assert np.allclose(matrix(two, 72), matrix(one, 72), atol=1e-12)
    with pytest.raises(ValueError):
        sphere.compress(slp(), "none such")


def test_scratch_can_be_deleted(spark):
    import os

    step = settled(spark.range(5))
    assert os.path.isdir(step.settled_at)
    discard(step)
    assert not os.path.exists(step.settled_at)


def test_batches_equal_single_points():
    from panelspark.operators.quadrature import rule

    rng = np.random.default_rng(2)
    a, b = rng.random((5, 3, 3)), rng.random((5, 3, 3)) + 2
    normal, scale = rng.random((5, 3)), rng.random(5)
    for kernel in (slp(), dlp(), slp(2.0), dlp(2.0)):
        got = assembly.batch_values(a, b, normal, scale, 1, 3, kernel, most=200)
        for k in range(5):
            total = 0
            for s, t, u, v, w in rule(1, 3):
                x = a[k, 0] + s * (a[k, 1] - a[k, 0]) + t * (a[k, 2] - a[k, 1])
                y = b[k, 0] + u * (b[k, 1] - b[k, 0]) + v * (b[k, 2] - b[k, 1])
                total = total + w * kernel.values((x - y)[None], normal[k][None])[0]
            assert got[k] == pytest.approx(total * scale[k])


def test_packages_of_points_skip_a_point_with_itself():
    table = pa.table({"list": [0], "t": [1], "s": [1], "a": [[{"i": 1, "geo": [0.0, 0.0, 0.0], "v": None}, {"i": 2, "geo": [0.0, 0.0, 2.0], "v": None}]]}, schema=pa.schema([("list", pa.int64()), ("t", pa.int64()), ("s", pa.int64()), ("a", pa.list_(pa.struct([("i", pa.int64()), ("geo", pa.list_(pa.float64())), ("v", pa.list_(pa.int64()))])))]))
    got = fill.run_list(table.append_column("b", table.column("a")), slp(), EngineConfig().quad, "two", False)
    assert got.column("re").to_pylist() == pytest.approx([0, 1 / (8 * np.pi), 1 / (8 * np.pi), 0])
