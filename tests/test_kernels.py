import numpy as np
import pytest

from evenbatch.functions import coupling
from evenbatch.functions.harmonics import bessel, harmonics
from evenbatch.operators.kernels import ContractTables, ProductTables
from evenbatch.operators.network import KernelConfig, Network


def test_known_coefficients():
    c = coupling.coefficient
    third = 1 / np.sqrt(3)
    want = [((1, 1, 1, -1, 0, 0), third), ((1, 0, 1, 0, 0, 0), -third), ((1, -1, 1, 1, 0, 0), third), ((1, 0, 1, 0, 2, 0), np.sqrt(2 / 3)), ((1, 0, 1, 0, 1, 0), 0), ((1, 1, 1, 1, 2, 2), 1), ((1, 1, 1, 0, 1, 1), np.sqrt(0.5)), ((1, 0, 1, 1, 1, 1), -np.sqrt(0.5))]
    for args, value in want:
        assert c(*args) == pytest.approx(value)


@pytest.mark.parametrize("ls,want", [((1, 1, 1), (64, 17, 16, 11)), ((2, 2, 2), (729, 117, 113, 51)), ((3, 1, 1), (256, 26, 25, 14)), ((3, 1, 2), (576, 68, 66, 34)), ((3, 2, 2), (1296, 170, 163, 64)), ((3, 3, 3), (4096, 478, 449, 156))])
def test_density(ls, want):
    got = coupling.density(*ls)
    assert (got["total"], got["admissible"], got["nonzero"]) == want[:3] and got["squares"] == pytest.approx(want[3])


def test_orthonormality():
    for l1, l2 in ((1, 1), (2, 1), (3, 2)):
        m = np.concatenate([coupling.block(l1, l2, l3).reshape(-1, 2 * l3 + 1) for l3 in range(abs(l1 - l2), l1 + l2 + 1)], axis=1)
        assert np.allclose(m.T @ m, np.eye(m.shape[1]))


def test_harmonics_norm_and_real_blocks_couple_them():
    v = np.random.default_rng(0).normal(size=(6, 3))
    y = harmonics(v / np.linalg.norm(v, axis=1, keepdims=True), 4)
    for l in range(5):
        assert np.allclose((y[:, l * l : (l + 1) ** 2] ** 2).sum(1), (2 * l + 1) / (4 * np.pi))
    for a, b, c in ((1, 1, 2), (1, 1, 0), (2, 1, 3), (1, 2, 1), (2, 2, 2)):
        p = np.einsum("na,nb,abc->nc", y[:, a * a : (a + 1) ** 2], y[:, b * b : (b + 1) ** 2], coupling.block(a, b, c, "real"))
        assert np.ptp(p / y[:, c * c : (c + 1) ** 2]) < 1e-9


def test_along_z_only_m_zero_survives():
    y = harmonics(np.array([[0.0, 0.0, 1.0]]), 3)[0]
    assert all(abs(y[coupling.index(l, m)]) < 1e-12 for l in range(4) for m in range(-l, l + 1) if m)


def test_bessel_ends_smoothly():
    assert np.allclose(bessel(np.array([0.25, 0.3]), 8, 0.25), 0) and np.abs(bessel(np.array([0.1]), 8, 0.25)).max() > 1


def test_products_agree():
    rng = np.random.default_rng(1)
    y, h, fade = rng.normal(size=(7, 9)), rng.normal(size=(7, 3, 4)), rng.random(7)
    for basis in ("complex", "real"):
        assert np.allclose(ProductTables(3, 2, 1, 2, basis).apply(y, h, fade), ProductTables(3, 2, 1, 2, basis, dense=True).apply(y, h, fade))


@pytest.mark.parametrize("nu,l", [(1, 0), (1, 2), (2, 0), (2, 1), (3, 0), (3, 1)])
def test_contractions_agree(nu, l):
    rng = np.random.default_rng(2)
    a, z = rng.normal(size=(5, 2, 4)), np.array([0, 1, 1, 2, 0])
    make = lambda **how: ContractTables(2, 1, nu, l, "real", how.pop("canonical", False), 3, **how)
    want = make().apply(a, z)
    for got in (make(canonical=True).apply(a, z), make(dense=True).apply(a, z), make().apply(a, z, nested=True), make(canonical=True).apply(a, z, nested=True)):
        assert np.allclose(got, want)


def test_canonical_terms_are_fewer():
    full, short = (len(coupling.chain_terms(2, 2, 0, "real", c)) for c in (False, True))
    assert short <= full
    assert coupling.chain_terms(1, 2, 0, "complex")[0][-1] == pytest.approx(1.0) and all(len(t[2]) == 3 for t in coupling.chain_terms(1, 3, 1, "real", True))


@pytest.mark.parametrize("dtype,limit", [("double", 1e-9), ("float", 1e-3)])
def test_symmetries(dtype, limit):
    net = Network(KernelConfig(lmax_sh=3, channels=3, dtype=dtype))
    rng = np.random.default_rng(3)
    x, z = rng.normal(size=(9, 3)) * 0.08, rng.integers(0, 10, 9)
    turn = np.linalg.qr(rng.normal(size=(3, 3)))[0]
    turn *= np.sign(np.linalg.det(turn))
    e = net.energies(x, z).sum()
    scale = 1 + np.abs(net.energies(x, z)).sum()
    order = rng.permutation(9)
    for other in (net.energies(x @ turn.T, z).sum(), net.energies(x + 2.0, z).sum(), net.energies(x[order], z[order]).sum()):
        assert abs(other - e) / scale < limit
    if dtype == "double":
        f = net.forces(x, z)
        assert np.abs(f.sum(0)).max() / (1 + np.abs(f).max()) < 1e-5
        assert np.abs(net.forces(x @ turn.T, z) - f @ turn.T).max() / (1 + np.abs(f).max()) < 1e-5
        apart = np.concatenate((x, x + 50.0))
        assert net.energies(apart, np.concatenate((z, z))).sum() == pytest.approx(2 * e)


def test_tuple_chain_equals_joins(spark, sf):
    from evenbatch.kernel_queries import _y
    from evenbatch.operators import graphs, kernels

    v = graphs.vertices(spark, sf).where("graph_id = 0")
    inputs = kernels.edge_inputs(graphs.radius_edges(v, 0.25), v, _y(), 0.25)
    a = {(r.dst, r.k, r.l3, r.m3): r.val for r in kernels.product_tuple_chain(inputs, 1).collect()}
    b = {(r.dst, r.k, r.l3, r.m3): r.val for r in kernels.product_sparse(inputs, 1, 1, 1, 1).collect()}
    assert a.keys() == b.keys() and all(a[k] == pytest.approx(b[k]) for k in a)


def test_tuple_chain_query_covers_all_graphs(spark, sf):
    from evenbatch import kernel_queries as q

    a, b = ({(r.dst, r.k, r.l3, r.m3): r.val for r in f(spark, sf).collect()} for f in (q.edge_product_tuple_chain, q.edge_product_sparse))
    assert a.keys() == b.keys() and all(abs(a[x] - b[x]) < 2e-6 for x in b)
