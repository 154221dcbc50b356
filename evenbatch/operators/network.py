"""The two-layer network on geometric graphs, its energies and forces, and the training of its readout.

Graphs are independent and small, so many are evaluated whole at a time, as blocks of one adjacency: graphs are spread
over tasks by their id, come sorted, and a task takes as many whole graphs as BLOCK_VERTICES hold. Work and memory grow
with the vertices' pairs inside graphs and with the edges, not with all pairs of a block. Parameters are deterministic,
small and sent with the function.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import coupling
from ..functions.harmonics import bessel, harmonics, small_weight
from ..sources.tables import settled


#: Vertices that a task evaluates at a time, but at least one graph, and values of an edge product that it holds.
BLOCK_VERTICES = 2048
PRODUCT_VALUES = 4_000_000


@dataclass(frozen=True)
class KernelConfig:
    lmax_sh: int = 3
    lmax_feat: int = 1
    lmax_out: int = 2
    nu_max: int = 2
    channels: int = 4
    layers: int = 2
    n_radial: int = 8
    r_cut: float = 0.25
    dtype: str = "double"
    parity: bool = True


class Network:
    """Edge embedding, product and pooling, channel mixing, contraction to messages, residual update, readouts."""

    def __init__(self, config: KernelConfig = KernelConfig(), species: int = 10):
        c = self.config = config
        self.species = species
        self.paths = coupling.paths(c.lmax_sh, c.lmax_feat, c.lmax_out, c.parity)
        rng = np.random.default_rng(11)
        self.embed = rng.normal(size=(species, c.channels)) * 0.5
        self.radial = [(rng.normal(size=(c.n_radial, 16)) * 0.4, rng.normal(size=(16, c.channels * len(self.paths))) * 0.3) for _ in range(c.layers)]
        self.mix = rng.normal(size=(c.layers, c.lmax_out + 1, c.channels, c.channels)) / np.sqrt(c.channels)
        self.terms = [[(np.array([t[2] for t in ts]).reshape(-1, nu), np.array([t[1] for t in ts]) + l, np.array([[[x[3] * small_weight(z, k, nu, x[0]) for x in ts] for k in range(c.channels)] for z in range(species)])) for nu in range(1, c.nu_max + 1) if (ts := coupling.chain_terms(c.lmax_out, nu, l, "real", True))] for l in range(c.lmax_feat + 1)]
        # the non-zero coefficients, in the order of their outputs
        flat = sorted((l * l + int(m), a * a + int(i), b * b + int(k), p, float(block[i, k, m])) for p, (a, b, l) in enumerate(self.paths) for block in [coupling.block(a, b, l, "real")] for i, k, m in zip(*np.nonzero(block)))
        out, begin = np.unique([t[0] for t in flat], return_index=True)
        self.sparse = (out, begin, *(np.array([t[n] for t in flat]) for n in (1, 2, 3, 4)))
        self.linear = rng.normal(size=c.channels) * 0.3
        self.hidden, self.last = rng.normal(size=(c.channels, 16)) * 0.5, rng.normal(size=16) * 0.3

    def edges(self, x: np.ndarray, graph: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(receiver, sender, displacement) inside each graph, by receiver. graph: a number for each vertex, sorted."""
        if graph is None:
            graph = np.zeros(len(x), dtype=int)
        _, begin, sizes = np.unique(graph, return_index=True, return_counts=True)
        found = [(np.empty(0, int), np.empty(0, int))]
        for n in np.unique(sizes):  # graphs of one size at a time
            at = begin[sizes == n][:, None] + np.arange(n)
            for part in np.array_split(at, max(1, len(at) * n * n // PRODUCT_VALUES)):
                place = x[part]
                r = np.linalg.norm(place[:, :, None] - place[:, None], axis=3)
                g, i, j = np.nonzero((r <= self.config.r_cut) & ~np.eye(n, dtype=bool))
                found.append((part[g, i], part[g, j]))
        i, j = (np.concatenate(c) for c in zip(*found))
        by = np.lexsort((j, i))
        i, j = i[by], j[by]
        return i, j, x[i] - x[j]

    def pooled_messages(self, i: np.ndarray, j: np.ndarray, y: np.ndarray, weight: np.ndarray, h: np.ndarray) -> np.ndarray:
        """The sparse product of harmonics, senders' features and weights on all edges, added up on the receivers: terms
        of non-zero coefficients only, so many edges at a time that they fit."""
        out, begin, first, second, path, c = self.sparse
        n, channels = len(h), h.shape[1]
        pooled = np.zeros((n, channels, coupling.width(self.config.lmax_out)), h.dtype)
        step = max(1, PRODUCT_VALUES // (channels * len(c)))
        for a in range(0, len(i), step):
            b = slice(a, a + step)
            terms = y[b][:, None, first] * h[j[b]][:, :, second] * weight[b][:, :, path] * c.astype(h.dtype)
            message = np.add.reduceat(terms, begin, axis=2)
            to, at = np.unique(i[b], return_index=True)  # receivers are sorted
            pooled[to[:, None, None], np.arange(channels)[:, None], out] += np.add.reduceat(message, at, axis=0)
        return pooled

    def features(self, x: np.ndarray, z: np.ndarray, graph: np.ndarray | None = None) -> list[np.ndarray]:
        """h of each layer: [vertices, channels, (lmax_feat + 1)**2]."""
        c = self.config
        kind = np.float32 if c.dtype == "float" else np.float64
        i, j, d = self.edges(x, graph)
        r = np.linalg.norm(d, axis=1)
        y = harmonics(d / r[:, None], c.lmax_sh).astype(kind) if len(r) else np.zeros((0, coupling.width(c.lmax_sh)), kind)
        basis = bessel(r, c.n_radial, c.r_cut).astype(kind) if len(r) else np.zeros((0, c.n_radial), kind)
        h = np.zeros((len(x), c.channels, coupling.width(c.lmax_feat)), kind)
        h[:, :, 0] = self.embed[z]
        out = [h]
        for layer in range(c.layers):
            w1, w2 = self.radial[layer]
            u = basis @ w1.astype(kind)
            weight = ((u / (1 + np.exp(-u))) @ w2.astype(kind)).reshape(len(r), c.channels, len(self.paths))
            pooled = self.pooled_messages(i, j, y, weight, h) * kind(0.02)  # about the neighbours times the basis scale
            for l in range(c.lmax_out + 1):
                pooled[:, :, l * l : (l + 1) ** 2] = np.einsum("ij,njm->nim", self.mix[layer, l].astype(kind), pooled[:, :, l * l : (l + 1) ** 2])
            update = np.zeros_like(h)
            for l, by_nu in enumerate(self.terms):
                for lms, m, weights in by_nu:
                    product = np.prod(pooled[:, :, lms], axis=3) * weights[z].astype(kind)
                    for k in range(2 * l + 1):
                        update[:, :, l * l + k] += product[:, :, m == k].sum(2)
            h = h + update
            out.append(h)
        return out

    def energies(self, x: np.ndarray, z: np.ndarray, graph: np.ndarray | None = None) -> np.ndarray:
        """The contribution of each vertex: linear readouts of invariant channels, and a small perceptron at the end."""
        h = self.features(x, z, graph)
        total = sum(f[:, :, 0] @ self.linear for f in h[1:-1]) if len(h) > 2 else 0.0
        u = h[-1][:, :, 0] @ self.hidden
        return total + (u / (1 + np.exp(-u))) @ self.last

    def forces(self, x: np.ndarray, z: np.ndarray, graph: np.ndarray | None = None, eps: float = 1e-6) -> np.ndarray:
        """Minus the gradient of each graph's energy, by central differences. As graphs are independent, a vertex of each
        is moved at a time: the runs are as many as the largest graph needs."""
        if graph is None:
            graph = np.zeros(len(x), dtype=int)
        number, begin = np.unique(graph, return_inverse=True)[1], np.unique(graph, return_index=True)[1]
        place = np.arange(len(x)) - begin[number] if len(x) else number
        out = np.zeros_like(x)
        for v in range(int(place.max()) + 1 if len(x) else 0):
            at = np.flatnonzero(place == v)
            for k in range(3):
                step = np.zeros_like(x)
                step[at, k] = eps
                total = [np.bincount(number, weights=self.energies(x + s * step, z, graph), minlength=len(begin)) for s in (1, -1)]
                out[at, k] = -((total[0] - total[1]) / (2 * eps))[number[at]]
        return out


def _by_blocks(v: DataFrame, each: Callable[[pd.DataFrame], pd.DataFrame], schema: str) -> DataFrame:
    """each, over blocks of whole graphs as frames sorted by graph_id and v."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pd.DataFrame] = []
        size = 0

        def emit(frame: pd.DataFrame) -> Iterator[pa.RecordBatch]:
            if len(frame):
                yield pa.RecordBatch.from_pandas(each(frame.reset_index(drop=True)), preserve_index=False)

        for batch in batches:
            for a in range(0, batch.num_rows, BLOCK_VERTICES):
                part = batch.slice(a, BLOCK_VERTICES).to_pandas()
                held.append(part)
                size += len(part)
                if size >= BLOCK_VERTICES:
                    frame = pd.concat(held, ignore_index=True)
                    cut = int((frame["graph_id"] != frame["graph_id"].iloc[-1]).sum())  # the last graph may go on
                    yield from emit(frame.iloc[:cut])
                    held, size = [frame.iloc[cut:]], len(frame) - cut
        if held:
            yield from emit(pd.concat(held, ignore_index=True))

    return v.select("graph_id", "v", "z", "x", "y", "zc").repartition("graph_id").sortWithinPartitions("graph_id", "v").mapInArrow(run, schema)


def _arrays(frame: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    return frame[["x", "y", "zc"]].to_numpy(dtype=float), frame["z"].to_numpy(dtype=int)


def energy(v: DataFrame, net: Network) -> DataFrame:
    """(graph_id, energy)."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        names, number = np.unique(frame["graph_id"], return_inverse=True)
        return pd.DataFrame({"graph_id": names, "energy": np.bincount(number, weights=net.energies(*_arrays(frame), number))})

    return _by_blocks(v, run, "graph_id long, energy double")


def forces(v: DataFrame, net: Network) -> DataFrame:
    """(graph_id, v, fx, fy, fz)."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        f = net.forces(*_arrays(frame), frame["graph_id"].to_numpy())
        return pd.DataFrame({"graph_id": frame["graph_id"], "v": frame["v"], "fx": f[:, 0], "fy": f[:, 1], "fz": f[:, 2]})

    return _by_blocks(v, run, "graph_id long, v long, fx double, fy double, fz double")


def batched_energy(v: DataFrame, assignment: DataFrame, net: Network) -> DataFrame:
    """(graph_id, energy) computed mini-batch by mini-batch: the graphs of a bin as blocks of one adjacency, which no
    edge leaves. Must equal energy()."""

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["graph_id", "v"])
        names, number = np.unique(frame["graph_id"], return_inverse=True)
        return pd.DataFrame({"graph_id": names, "energy": np.bincount(number, weights=net.energies(*_arrays(frame), number))})

    return v.join(assignment.select("graph_id", "bin_id"), "graph_id").groupBy("bin_id").applyInPandas(run, "graph_id long, energy double")


def equivariance_error(v: DataFrame, net: Network, angle: float = 0.7) -> DataFrame:
    """Greatest relative change of energies under rotation, shift and renumbering of vertices, and of forces under rotation."""
    c, s = np.cos(angle), np.sin(angle)
    turn = np.array([[c, -s, 0], [s, c, 0], [0, 0, 1]]) @ np.array([[1, 0, 0], [0, c, -s], [0, s, c]])

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        x, z = _arrays(frame.sort_values("v"))
        e = net.energies(x, z).sum()
        f = net.forces(x, z)
        scale, force = 1 + np.abs(net.energies(x, z)).sum(), 1 + np.abs(f).max()
        return pd.DataFrame({
            "graph_id": [frame["graph_id"].iloc[0]], "rotation": [abs(net.energies(x @ turn.T, z).sum() - e) / scale], "shift": [abs(net.energies(x + 3.0, z).sum() - e) / scale],
            "order": [abs(net.energies(x[::-1], z[::-1]).sum() - e) / scale], "forces": [float(np.abs(net.forces(x @ turn.T, z) - f @ turn.T).max() / force)], "net_force": [float(np.abs(f.sum(0)).max() / force)],
        })

    return v.select("graph_id", "v", "z", "x", "y", "zc").groupBy("graph_id").applyInPandas(run, "graph_id long, rotation double, shift double, order double, forces double, net_force double")


def train_readout(rows: DataFrame, features: list[str], target: str, epochs: int = 16, lr: float = 0.005, decay: float = 0.99, weight: str | None = None) -> list[tuple[int, float]]:
    """(epoch, loss) of a linear readout trained on batches, given as rows with step. Each step's gradient is one
    grouped sum over the whole table; Adam and a moving average of the parameters run on the driver."""
    n = len(features) + 1
    cols = [F.col(f).cast("double") for f in features] + [F.lit(1.0)]
    w = F.col(weight) if weight else F.lit(1.0)
    # sums of products per step are all that a squared loss needs: one pass, reused by all epochs
    sums = settled(rows.groupBy("step").agg(*[F.sum(w * cols[i] * cols[j]).alias(f"q{i}_{j}") for i in range(n) for j in range(i, n)], *[F.sum(w * cols[i] * F.col(target)).alias(f"b{i}") for i in range(n)], F.sum(w * F.col(target) * F.col(target)).alias("c"), F.sum(w).alias("w")))
    steps = sums.orderBy("step").collect()  # one row a step: a few numbers each
    quad = np.array([[[r[f"q{min(i, j)}_{max(i, j)}"] for j in range(n)] for i in range(n)] for r in steps], dtype=float)
    lin, const, mass = np.array([[r[f"b{i}"] for i in range(n)] for r in steps], dtype=float), np.array([r["c"] for r in steps], dtype=float), np.array([r["w"] for r in steps], dtype=float)
    theta, mean, square, shadow, out, t = np.zeros(n), np.zeros(n), np.zeros(n), np.zeros(n), [], 0
    for epoch in range(epochs):
        for q, b, m in zip(quad, lin, mass):
            t += 1
            g = 2 * (q @ theta - b) / m
            mean, square = 0.9 * mean + 0.1 * g, 0.999 * square + 0.001 * g * g
            theta = theta - lr * (mean / (1 - 0.9**t)) / (np.sqrt(square / (1 - 0.999**t)) + 1e-8)
            shadow = decay * shadow + (1 - decay) * theta
        at = shadow / (1 - decay**t)
        out.append((epoch, float((const - 2 * lin @ at + np.einsum("sij,i,j->s", quad, at, at)).sum() / mass.sum())))
    return out
