"""Bases, rules and curves without Spark."""

import numpy as np
import pytest

from overlapgraph.operators import basis, geometry, meshes, metrics, partition
from overlapgraph.operators.assembly import axis_matrices
from overlapgraph.operators.meshes import MeshSpec, box_pair


@pytest.mark.parametrize("p", [1, 2, 3, 4])
@pytest.mark.parametrize("n", [1, 2, 3, 7])
def test_extraction_equals_recursion(n, p):
    x = np.linspace(0, 1, 57)[:-1]
    s = np.minimum((x * n).astype(int), n - 1)
    a, da = basis.spline_recursive(x, np.array(meshes.open_knots(0, 1, n, p)), p, s)
    b, db = basis.spline_extracted(2 * (x * n - s) - 1, s, n, p, 1 / n)
    assert np.abs(a - b).max() < 1e-12 and np.abs(da - db).max() < 1e-10
    assert np.abs(a.sum(1) - 1).max() < 1e-12 and np.abs(da.sum(1)).max() < 1e-10


@pytest.mark.parametrize("p", [1, 2, 3])
def test_lagrange_and_bernstein(p):
    nodes = np.linspace(-1, 1, p + 1)
    assert np.allclose(basis.lagrange(nodes, p)[0], np.eye(p + 1))
    xi, eps = np.linspace(-0.9, 0.9, 11), 1e-6
    for f in (basis.lagrange, basis.bernstein):
        val, der = f(xi, p)
        assert np.allclose(val.sum(1), 1)
        assert np.allclose((f(xi + eps, p)[0] - f(xi - eps, p)[0]) / (2 * eps), der, atol=1e-6)


def test_knots_and_gauss():
    k = meshes.open_knots(0.0, 1.0, 5, 3)
    assert len(k) == 8 + 3 + 1 and k[:4] == [0.0] * 4
    x, w = geometry.gauss_points(4)
    assert sum(w) == pytest.approx(2) and sum(wi * xi**6 for xi, wi in zip(x, w)) == pytest.approx(2 / 7)


def test_greville_points_map_to_themselves():
    spec = MeshSpec("G", "spline", 3, (6,), (0.0,), (2.0,))
    k = np.array(meshes.open_knots(0, 2, 6, 3))
    c = np.array([k[i + 1 : i + 4].mean() for i in range(9)])
    x = np.linspace(0, 1.99, 40)
    s = np.minimum((x / spec.h[0]).astype(int), 5)
    val, _ = basis.axis_values(spec, 0, x, s)
    assert np.allclose((val * c[s[:, None] + np.arange(4)]).sum(1), x)


def test_axis_matrices():
    g, local = box_pair(5, 3, 4, 0.4)
    for spec in (g, local):
        m, k = axis_matrices(spec, 0)
        assert m.sum() == pytest.approx(spec.hi[0]) and np.abs(k.sum(1)).max() < 1e-10
        assert np.allclose(m, m.T) and np.allclose(k, k.T)


def test_overlay_must_fit():
    g, local = box_pair(4, 2, 2, 1.0)
    meshes.validate_overlay(g, local)
    with pytest.raises(ValueError):
        meshes.validate_overlay(local, MeshSpec("X", "lagrange", 1, (2,) * 3, (0.5,) * 3, (1.5,) * 3))


def test_hilbert_curve_moves_one_cell_at_a_time():
    bits = 3
    cells = np.array([[i, j, k] for i in range(8) for j in range(8) for k in range(8)])
    at = partition.hilbert_index(cells, bits)
    assert sorted(at) == list(range(512))
    steps = np.abs(np.diff(cells[np.argsort(at)], axis=0)).sum(1)
    assert (steps == 1).all()


def test_full_size_counts():
    """The published mesh sizes follow from spans and degrees alone."""
    g, local = box_pair(50, 3, 25, 0.1)
    assert g.n_vertices == 148_877 and local.n_vertices == 17_576 and g.n_elements == 125_000 and local.n_elements == 15_625
    c = metrics.operation_counts(g.n_elements, local.n_elements, 64, 64, 64, 8)
    assert c == {"gg": 32_768_000_000, "ll": 64_000_000, "gl": 512_000_000}


def test_published_reductions():
    one, last = metrics.TIMES_UNIFORM[0], metrics.TIMES_UNIFORM[-1]
    assert 1 - last[2] / one[2] == pytest.approx(0.989, abs=5e-4) and 1 - last[1] / one[1] == pytest.approx(0.956, abs=5e-4)
    at40 = {n: t[1] for n, *t in metrics.TIMES_WEIGHTED}
    assert one[3] / at40[256] == pytest.approx(55.2, abs=0.05) and 263.7 - at40[32] == pytest.approx(163.5)
