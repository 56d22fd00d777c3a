"""Quadrature rules, dense matrices and compression in numpy, against known values."""

import numpy as np
import pytest

from panelspark.operators import cross, green, quadrature
from panelspark.operators.assembly import batch_values
from panelspark.operators.kernels import dlp, slp


@pytest.mark.parametrize(("case", "count3", "count4"), [(0, 81, 256), (1, 1250, 2592), (2, 3125, 6480), (3, 3750, 7776)])
def test_points_and_weights(case, count3, count4):
    for n, count in (((3 if case == 0 else 5), count3), ((4 if case == 0 else 6), count4)):
        r = quadrature.rule(case, n)
        assert len(r) == count
        assert abs(r[:, 4].sum() - 0.25) < 1e-12
        assert (r[:, :4] >= -1e-15).all() and (r[:, 1] <= r[:, 0] + 1e-15).all() and (r[:, 3] <= r[:, 2] + 1e-15).all()


def mesh(n):
    tri = []
    for face in range(8):
        s = np.array([1 - 2 * ((face >> k) & 1) for k in range(3)])
        for r in range(n):
            for slot in range(2 * r + 1):
                m, down = divmod(slot, 2)
                t = [(r - m, m, n - r), (r - m, m + 1, n - r - 1), (r - m - 1, m + 1, n - r)] if down else [(r - m, m, n - r), (r + 1 - m, m, n - r - 1), (r - m, m + 1, n - r - 1)]
                t = [tuple(s * np.array(p)) for p in t]
                tri.append([t[0], t[2], t[1]] if s.prod() < 0 else t)
    return tri


def dense(n, kernel):
    tri = mesh(n)
    p = np.array(tri, float)
    p /= np.linalg.norm(p, axis=2, keepdims=True)
    normal = np.cross(p[:, 1] - p[:, 0], p[:, 2] - p[:, 1])
    gram = np.linalg.norm(normal, axis=1)
    normal /= gram[:, None]
    out = np.zeros((len(p), len(p)), complex if kernel.complex else float)
    for i, a in enumerate(tri):
        for j, b in enumerate(tri):
            common = [v for v in a if v in b]
            pa = p[i][[a.index(v) for v in common] + [k for k in range(3) if a[k] not in common]]
            pb = p[j][[b.index(v) for v in common] + [k for k in range(3) if b[k] not in common]]
            c = len(common)
            out[i, j] = batch_values(pa[None], pb[None], normal[j][None], np.array([gram[i] * gram[j]]), c, 3 if c == 0 else 5, kernel)[0]
    return out, gram / 2, p, normal


def test_golden_sums_n2():
    v, area, _, _ = dense(2, slp())
    k, _, _, _ = dense(2, dlp())
    assert abs(v.sum() - 9.65479) < 1e-4
    assert abs(k.sum() + 5.20904) < 1e-4
    assert np.abs(k.sum(1) / area + 0.5).max() < 2e-4
    assert np.abs(v - v.T).max() < 1e-6
    assert np.linalg.eigvalsh((v + v.T) / 2).min() > 0
    assert abs((v.sum(1) / area).mean() - 0.92571) < 1e-4


def test_wave_mean_n2():
    v, area, _, _ = dense(2, slp(3.0))
    assert abs(v.sum() / area.sum() - (-0.1436 + 0.0712j)) < 2e-4


def test_far_pair():
    a = np.array([[0, 0, 0], [1, 0, 0], [0, 1, 0]], float)
    b = a + [100, 0, 0]
    x = batch_values(a[None], b[None], np.array([[0, 0, 1.0]]), np.array([1.0]), 0, 3, slp())[0]
    assert abs(x - 0.25 / (4 * np.pi * 100)) < 1e-7


def test_cross_approximation():
    r = np.random.default_rng(0)
    for a in (np.outer(r.random(8), r.random(6)), r.random((9, 3)) @ r.random((3, 7)), np.zeros((4, 5))):
        rows, cols = cross.full(a, 1e-12)
        assert len(rows) == np.linalg.matrix_rank(a)
        v = cross.interpolation(a, rows, cols)
        if rows:
            assert np.allclose(v @ a[rows], a) and np.allclose(v[rows], np.eye(len(rows)))
        _, _, u, w = cross.partial(lambda i: a[i], lambda j: a[:, j], a.shape, 1e-12)
        assert np.allclose(u @ w.T, a)


def caps(n=8):
    tri = np.array(mesh(n), float)
    p = tri / np.linalg.norm(tri, axis=2, keepdims=True)
    normal = np.cross(p[:, 1] - p[:, 0], p[:, 2] - p[:, 1])
    gram = np.linalg.norm(normal, axis=1)
    geo = np.concatenate([p.reshape(-1, 9), gram[:, None], normal / gram[:, None]], 1)
    z = p.mean(1)[:, 2]
    return geo[z > 0.85], geo[z < -0.85]


def block(a, b, kernel):
    ca, cb = a[:, :9].reshape(-1, 3, 3), b[:, :9].reshape(-1, 3, 3)
    i, j = np.meshgrid(np.arange(len(a)), np.arange(len(b)), indexing="ij")
    i, j = i.ravel(), j.ravel()
    return batch_values(ca[i], cb[j], b[j, 10:13], a[i, 9] * b[j, 9], 0, 3, kernel).reshape(len(a), len(b))


def box(g, q):
    p = g[:, :9].reshape(-1, 3)
    return green.surface(p.min(0), p.max(0), q, 1.0, "max")


def test_separation_converges():
    a, b = caps()
    exact = block(a, b, slp())
    errors = []
    for q in (2, 4, 6):
        low = green.row_factor(a, box(a, q), slp()) @ green.column_factor(b, box(a, q), slp()).T
        errors.append(np.linalg.norm(exact - low) / np.linalg.norm(exact))
    assert errors[0] > errors[1] > errors[2] and errors[2] < 1e-2


@pytest.mark.parametrize("kernel", [slp(), dlp(), slp(3.0), dlp(3.0)])
def test_two_sided_follows_the_accuracy(kernel):
    a, b = caps(12)
    exact = block(a, b, kernel)
    last = 1.0
    for eps in (1e-2, 1e-4, 1e-6):
        fa, fb = green.row_factor(a, box(a, 4), kernel), green.row_factor(b, box(b, 4), kernel, "col")
        ra, ca = cross.full(fa, eps)
        rb, cb = cross.full(fb, eps)
        low = cross.interpolation(fa, ra, ca) @ exact[np.ix_(ra, rb)] @ cross.interpolation(fb, rb, cb).T
        error = np.linalg.norm(exact - low) / np.linalg.norm(exact)
        assert error < max(30 * eps, 2e-5)
        assert error <= last
        last = error


def test_double_layer_needs_its_own_column_basis():
    a, b = caps(16)
    exact = block(a, b, dlp())
    fa, fb = green.row_factor(a, box(a, 4), dlp()), green.row_factor(b, box(b, 4), slp())
    (ra, ca), (rb, cb) = cross.full(fa, 1e-4), cross.full(fb, 1e-4)
    low = cross.interpolation(fa, ra, ca) @ exact[np.ix_(ra, rb)] @ cross.interpolation(fb, rb, cb).T
    assert np.linalg.norm(exact - low) / np.linalg.norm(exact) > 1e-3
