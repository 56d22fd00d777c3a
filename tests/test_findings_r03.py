"""Findings of round 3 on the engine: products and bases of compressed panel matrices within the time."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from panelspark.config import EngineConfig
from panelspark.operators import cross, fill, geometry, green
from panelspark.operators.kernels import KernelSpec, dlp, second_normal, slp


def _panels(n=4):
    ids, x = geometry.decoded_panels(np.arange(8 * n * n), n)
    up = np.cross(x[:, 1] - x[:, 0], x[:, 2] - x[:, 1])
    gram = np.linalg.norm(up, axis=1)
    return ids, np.concatenate([x.reshape(-1, 9), gram[:, None], up / gram[:, None]], 1)


@pytest.mark.parametrize("kernel", [slp(), dlp()])
@pytest.mark.parametrize("unit", [1.0, 1.0 + 0.5j])
def test_regular_product_forms_no_entry(kernel, unit, monkeypatch):
    """each entry of a block was integrated by itself, from its own copy of both panels; only touching pairs are now."""
    _check_product(kernel, unit, monkeypatch)


def _check_product(kernel, unit, monkeypatch):
    ids, geo = _panels()
    x = np.random.default_rng(1).normal(size=len(geo)) * unit
    a = np.arange(0, len(geo), 9)
    p, q = np.repeat(a, len(geo)), np.tile(np.arange(len(geo)), len(a))
    one, two = (geo[a], a, x[a], ids[a]), (geo, np.arange(len(geo)), x, ids)
    both = np.arange(len(geo)) % 3 > 0 if kernel.layer == "slp" else None
    turn = (p < q) & (both is not None)
    r, s = np.where(turn, q, p), np.where(turn, p, q)
    entries = fill.integrate(geo[r], ids[r], geo[s], ids[s], kernel, EngineConfig().quad).reshape(len(a), -1)
    touching = int((ids[p][:, :, None] == ids[q][:, None, :]).any((1, 2)).sum())
    seen, real = [], fill.integrate
    monkeypatch.setattr(fill, "integrate", lambda ga, *rest: (seen.append(len(ga)), real(ga, *rest))[1])
    mine, theirs = fill._apply_panels(one, two, both, kernel, EngineConfig().quad, "two")
    assert seen == [touching]
    assert np.abs(mine - entries @ x).max() < 1e-13 * np.abs(entries @ x).max()
    if both is not None:
        want = np.where(both, x[a] @ entries, 0)
        assert np.abs(theirs - want).max() < 1e-13 * np.abs(want).max()


def test_a_task_reads_each_cluster_once(spark):
    """the members of both clusters went along with each block, so that clusters were sent as often as they have blocks."""
    ids, geo = _panels(2)
    member = [(int(k % 4) + 4, int(k), [float(c) for c in geo[k]], [int(c) for c in ids[k]]) for k in range(len(geo))]
    rows = spark.createDataFrame(member, "node long, i long, geo array<double>, v array<long>")
    held = fill.members(rows).withColumn("x", F.transform("members", lambda m: F.array(m.i.cast("double"), F.lit(0.0))))
    blocks = spark.createDataFrame([(t, s) for t in range(4, 8) for s in range(4, 8)], "t long, s long")
    cfg, sent, real = EngineConfig(limit_bytes=2048), spark.sparkContext.accumulator(0), fill.apply_lists

    def counted(pieces, known, *rest):
        names = list(zip(known["side"].to_pylist(), known["node"].to_pylist(), strict=True))
        assert len(set(names)) == len(names)
        sent.add(len(names))
        return real(pieces, known, *rest)

    fill.apply_lists = counted
    try:
        got = {r["i"]: r["re"] for r in fill.apply(blocks, held, held, slp(), cfg).collect()}
    finally:
        fill.apply_lists = real
    p, q = np.repeat(np.arange(len(geo)), len(geo)), np.tile(np.arange(len(geo)), len(geo))
    want = fill.integrate(geo[p], ids[p], geo[q], ids[q], slp(), cfg.quad).reshape(len(geo), -1) @ np.arange(len(geo))
    assert sorted(got) == list(range(len(geo))) and max(abs(got[i] - want[i]) for i in got) < 1e-12 * np.abs(want).max()
    assert 0 < sent.value <= 16 + 8 + 4


def _plain_factor(geo, box, kernel, side):
    z, normal, w, delta = box
    x, weight, own = green.sample_points(geo, 3)
    d = x[:, :, None, :] - z[None, None]
    if side == "col" and kernel.layer == "dlp":
        along = np.broadcast_to(own[:, None, None, :], d.shape)
        plus, minus = KernelSpec("dlp", kernel.kappa).values(-d, along), second_normal(-d, np.broadcast_to(normal[None, None], d.shape), along, kernel.kappa)
    else:
        plus, minus = KernelSpec("slp", kernel.kappa).values(d), KernelSpec("dlp", kernel.kappa).values(d, np.broadcast_to(normal[None, None], d.shape))
    return np.concatenate([np.einsum("ip,ipm->im", weight, plus) * np.sqrt(w), np.einsum("ip,ipm->im", weight, minus) * np.sqrt(w) * delta], 1)


@pytest.mark.parametrize("kernel", [slp(), dlp(), slp(3.0), dlp(3.0)])
@pytest.mark.parametrize("side", ["row", "col"])
def test_factors_and_pivots_in_place(kernel, side, monkeypatch):
    """F1 to F4: the factors were made from arrays of all differences (three numbers a pair of points), and each pivot made new
    arrays of the whole rest; factors and pivots are the same."""
    _, geo = _panels()
    geo = geo[:40]
    corners = geo[:, :9].reshape(-1, 3)
    box = green.surface(corners.min(0), corners.max(0), 5, 1.0, "max")
    want, shapes, real = _plain_factor(geo, box, kernel, side), [], np.einsum
    monkeypatch.setattr(np, "einsum", lambda *a, **k: (shapes.append(max(np.size(x) for x in a[1:])), real(*a, **k))[1])
    got = green.row_factor(geo, box, kernel, side)
    monkeypatch.undo()
    assert max(shapes, default=0) < 9 * 40 * 150
    assert np.abs(got - want).max() < 1e-13 * np.abs(want).max()
    rest, rows, cols = want.copy(), [], []
    while len(rows) < min(want.shape):
        i, j = np.unravel_index(int(np.argmax(np.abs(rest))), rest.shape)
        if rows and abs(rest[i, j]) <= 1e-9 * abs(want[rows[0], cols[0]]):
            break
        rows.append(int(i))
        cols.append(int(j))
        rest = rest - np.outer(rest[:, j] / rest[i, j], rest[i])
        rest[i], rest[:, j] = 0, 0
    assert cross.full(want, 1e-9) == (rows, cols)


@pytest.mark.parametrize("kernel", [slp(3.0), dlp(3.0)])
def test_wave_product_forms_no_entry(kernel, monkeypatch):
    """the same with waves, for which each pair of points took a cosine and a sine."""
    _check_product(kernel, 1.0, monkeypatch)
    _check_product(kernel, 1.0 + 0.5j, monkeypatch)


@pytest.mark.parametrize("kernel", [slp(3.0), dlp(3.0), slp(40.0), dlp(40.0)])
def test_wave_terms(kernel, monkeypatch):
    """strips of few wave lengths go by powers of the distance, wider ones by cosine and sine; both are the kernel."""
    from panelspark.operators.kernels import wave_series, waves

    dist = 0.2 + 0.5 * np.random.default_rng(2).random((90, 40))
    k = kernel.kappa
    want = np.exp(1j * k * dist) * ((1 - 1j * k * dist) if kernel.layer == "dlp" else 1) / dist
    for step in range(57):
        wave_series(step)
    calls, real = [], np.cos
    monkeypatch.setattr(np, "cos", lambda *a, **b: (calls.append(1), real(*a, **b))[1])
    got = sum(z * factor for z, factor in waves(kernel, 1 / dist, dist.copy(), np.empty_like(dist)))
    assert len(calls) == (k > 10)
    assert np.abs(got - want).max() < 1e-12 * np.abs(want).max()
    same = sum(z * factor for z, factor in waves(kernel, np.ones((1, 1)), np.full((1, 1), 0.3), np.empty((1, 1))))
    assert abs(same[0, 0] - np.exp(0.3j * k) * ((1 - 0.3j * k) if kernel.layer == "dlp" else 1)) < 1e-12 * (1 + k)
