"""The tensor kernels: the channelwise product on edges with its pooling, and the symmetric contraction on vertices.

Each exists as the dense chain (every index combination, a materialised result per path), one job per index tuple, the
sparse relational form (joins with the broadcast table of non-zero coefficients), and fused (one Arrow stage that
reads packed tensors and writes packed tensors, with the non-zero table, or dense). Tables are rows of the selection
rules: a few hundred, whatever the data.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import coupling
from ..functions.harmonics import bessel_column, harmonics, harmonics_column, small_weight
from ..sources.tables import literal_table, settled

LMAX_SH, LMAX_FEAT, LMAX_OUT = 2, 1, 2
CG = "path int, l1 int, m1 int, l2 int, m2 int, l3 int, m3 int, c double"


def cg_frame(spark, l1=LMAX_SH, l2=LMAX_FEAT, l3=LMAX_OUT, basis="complex") -> DataFrame:
    return F.broadcast(literal_table(spark, coupling.table(l1, l2, l3, basis), CG))


def admissible() -> Column:
    """coupling.admissible() of the columns l1, m1, l2, m2, l3, m3."""
    l1, m1, l2, m2, l3, m3 = map(F.col, ("l1", "m1", "l2", "m2", "l3", "m3"))
    return (F.abs(l1 - l2) <= l3) & (l3 <= l1 + l2) & (m1 + m2 == m3) & (F.abs(m1) <= l1) & (F.abs(m2) <= l2) & (F.abs(m3) <= l3)


def lm_columns(lmax: int):
    """(l, m) structs in flat order, for exploding packed tensors."""
    return F.array(*[F.struct(F.lit(l).alias("l"), F.lit(m).alias("m"), F.lit(coupling.index(l, m)).alias("at")) for l in range(lmax + 1) for m in range(-l, l + 1)])


def edge_inputs(edges: DataFrame, v: DataFrame, y, r_cut: float) -> DataFrame:
    """(e, graph_id, dst, r, y, h): each edge with its harmonics and the sender's features; one join on the vertex."""
    sender = v.select(F.col("v").alias("src"), "h", "graph_id")
    rows = edges.withColumn("y", y).withColumn("fade", F.lit(1.0) - F.col("r") / r_cut)
    more = ["w"] if "w" in edges.columns else []
    return rows.join(sender, ["graph_id", "src"]).select("graph_id", "dst", "src", "sx", "sy", "sz", "fade", "y", "h", *more)


def path_weights(spark, channels: int, l1=LMAX_SH, l2=LMAX_FEAT, l3=LMAX_OUT) -> DataFrame:
    n = len(coupling.paths(l1, l2, l3))
    return F.broadcast(literal_table(spark, [(p, k, small_weight(p, k)) for p in range(n) for k in range(channels)], "path int, k int, w double"))


def product_sparse(inputs: DataFrame, channels: int, l1=LMAX_SH, l2=LMAX_FEAT, l3=LMAX_OUT, basis="complex", dense=False) -> DataFrame:
    """Pooled (dst, k, l3, m3, val) by joins: harmonics and features as rows, non-zero coefficients broadcast, one
    grouped sum. dense keeps the zeros. Where inputs have radial weights w, these weigh channels and paths."""
    spark = inputs.sparkSession
    radial = "w" in inputs.columns
    cg = cg_frame(spark, l1, l2, l3, basis)
    if dense:
        rows = [(p, a, i, b, j, c, k, float(coupling.block(a, b, c, basis)[i + a, j + b, k + c])) for p, (a, b, c) in enumerate(coupling.paths(l1, l2, l3)) for i in range(-a, a + 1) for j in range(-b, b + 1) for k in range(-c, c + 1)]
        cg = F.broadcast(literal_table(spark, rows, CG))
    ys = inputs.withColumnsRenamed({"w": "rw"} if radial else {})
    more = ["rw"] if radial else []
    ys = ys.select("dst", "fade", "h", *more, F.explode(lm_columns(l1)).alias("t"), "y").select("dst", "fade", "h", *more, F.col("t.l").alias("l1"), F.col("t.m").alias("m1"), F.get("y", F.col("t.at")).alias("yv"))
    terms = ys.join(cg, ["l1", "m1"]).join(path_weights(spark, channels, l1, l2, l3), "path")
    at = F.col("k") * coupling.width(l2) + F.col("l2") * F.col("l2") + F.col("l2") + F.col("m2")
    weight = F.get("rw", F.col("k") * len(coupling.paths(l1, l2, l3)) + F.col("path")) if radial else F.col("w") * F.col("fade")
    value = F.col("c") * weight * F.col("yv") * F.get("h", at)
    return terms.groupBy("dst", "k", "l3", "m3").agg(F.sum(value).alias("val"))


def product_dense_chain(inputs: DataFrame, channels: int, l1=LMAX_SH, l2=LMAX_FEAT, l3=LMAX_OUT, basis="complex") -> DataFrame:
    """The unfused baseline: for each path all index combinations, zeros too, its result written out before the next,
    and a sum over paths at the end."""
    spark, parts = inputs.sparkSession, []
    inputs = settled(inputs)
    for p, (a, b, c) in enumerate(coupling.paths(l1, l2, l3)):
        rows = [(i, j, k, float(coupling.block(a, b, c, basis)[i + a, j + b, k + c])) for i in range(-a, a + 1) for j in range(-b, b + 1) for k in range(-c, c + 1)]
        grid = F.broadcast(literal_table(spark, rows, "m1 int, m2 int, m3 int, c double"))
        weights = F.broadcast(literal_table(spark, [(k, small_weight(p, k)) for k in range(channels)], "k int, w double"))
        terms = inputs.crossJoin(grid).crossJoin(weights)
        at = F.col("k") * coupling.width(l2) + (b * b + b) + F.col("m2")
        value = F.col("c") * F.col("w") * F.col("fade") * F.get("y", F.col("m1") + (a * a + a)) * F.get("h", at)
        parts.append(settled(terms.groupBy("dst", "k", F.lit(c).alias("l3"), "m3").agg(F.sum(value).alias("val"))))
    return reduce(DataFrame.unionByName, parts).groupBy("dst", "k", "l3", "m3").agg(F.sum("val").alias("val"))


def product_tuple_chain(inputs: DataFrame, channels: int, l1=1, l2=1, l3=1, basis="complex") -> DataFrame:
    """The finest baseline: one job for each index tuple. For tiny inputs."""
    inputs, parts = settled(inputs), []
    for p, a, i, b, j, c, m, value in coupling.table(l1, l2, l3, basis):
        for k in range(channels):
            term = F.get("y", F.lit(coupling.index(a, i))) * F.get("h", F.lit(k * coupling.width(l2) + coupling.index(b, j))) * F.col("fade") * (value * small_weight(p, k))
            parts.append(settled(inputs.groupBy("dst").agg(F.sum(term).alias("val")).select("dst", F.lit(k).alias("k"), F.lit(c).alias("l3"), F.lit(m).alias("m3"), "val")))
    return reduce(DataFrame.unionByName, parts).groupBy("dst", "k", "l3", "m3").agg(F.sum("val").alias("val"))


class ProductTables:
    """The non-zero coefficients in the order of their outputs, for one grouped sum over the terms."""

    def __init__(self, channels: int, l1: int, l2: int, l3: int, basis: str, dense: bool = False):
        self.shape = (channels, coupling.width(l1), coupling.width(l2), coupling.width(l3))
        self.kernel = np.zeros(self.shape) if dense else None
        terms = sorted((coupling.index(x[5], x[6]), coupling.index(x[1], x[2]), coupling.index(x[3], x[4]), x[7], x[0]) for x in coupling.table(l1, l2, l3, basis))
        self.out, self.begin = np.unique([t[0] for t in terms], return_index=True)
        self.first, self.second = np.array([t[1] for t in terms]), np.array([t[2] for t in terms])
        self.c, self.path = np.array([t[3] for t in terms]), np.array([t[4] for t in terms])
        self.weight = np.array([[t[3] * small_weight(t[4], k) for t in terms] for k in range(channels)])
        if dense:
            for n, t in enumerate(terms):
                self.kernel[:, t[1], t[2], t[0]] += self.weight[:, n]

    def apply(self, y: np.ndarray, h: np.ndarray, fade: np.ndarray, w: np.ndarray | None = None) -> np.ndarray:
        """y [e, n1], h [e, channels, n2], fade [e], radial weights w [e, channels, paths] -> [e, channels, n3]."""
        if w is not None:
            out = np.zeros((len(y), self.shape[0], self.shape[3]), dtype=h.dtype)
            terms = y[:, None, self.first] * h[:, :, self.second] * w[:, :, self.path] * self.c.astype(h.dtype)
            out[:, :, self.out] = np.add.reduceat(terms, self.begin, axis=2)
            return out
        y = y * fade[:, None]
        if self.kernel is not None:
            return np.einsum("ea,ekb,kabc->ekc", y, h, self.kernel)
        out = np.zeros((len(y), self.shape[0], self.shape[3]), dtype=h.dtype)
        terms = (y[:, None, self.first] * h[:, :, self.second]) * self.weight[None].astype(h.dtype)
        out[:, :, self.out] = np.add.reduceat(terms, self.begin, axis=2)
        return out


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, width)


def _lists(values: np.ndarray) -> pa.Array:
    flat = np.ascontiguousarray(values, dtype=np.float64)
    return pa.ListArray.from_arrays(pa.array(np.arange(0, flat.size + 1, flat.shape[1], dtype=np.int32)), pa.array(flat.ravel()))


#: Edges whose terms a task holds at a time.
EDGE_ROWS = 2048


def product_fused(inputs: DataFrame, channels: int, l1=LMAX_SH, l2=LMAX_FEAT, l3=LMAX_OUT, basis="complex", dense=False, dtype="double") -> DataFrame:
    """Packed (dst, a): product and partial pooling in one Arrow stage; only one packed row a receiver and batch leaves
    it. One shuffle by the receiver then brings these together, in order, and a second Arrow stage adds up runs of equal
    receivers, whatever the number of channels. Where inputs have radial weights w, these weigh channels and paths."""
    shared = inputs.sparkSession.sparkContext.broadcast(ProductTables(channels, l1, l2, l3, basis, dense))
    kind = np.float32 if dtype == "float" else np.float64
    radial = "w" in inputs.columns and not dense

    def pooled(dst: np.ndarray, a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        by = np.argsort(dst, kind="stable")
        keys, begin = np.unique(dst[by], return_index=True)
        return keys, np.add.reduceat(a[by], begin, axis=0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = shared.value
        for whole in batches:
            for first in range(0, whole.num_rows, EDGE_ROWS):
                batch = whole.slice(first, EDGE_ROWS)
                y, h = _matrix(batch.column(2), t.shape[1]).astype(kind), _matrix(batch.column(3), t.shape[0] * t.shape[2]).astype(kind)
                w = _matrix(batch.column(4), len(batch.column(4)[0])).astype(kind).reshape(len(y), t.shape[0], -1) if radial else None
                got = t.apply(y, h.reshape(-1, t.shape[0], t.shape[2]), batch.column(1).to_numpy().astype(kind), w).reshape(len(y), -1)
                keys, a = pooled(batch.column(0).to_numpy(), got)
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), _lists(a)], ["dst", "a"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by dst; the last receiver of a batch may go on in the next."""
        last: tuple[int, np.ndarray] | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            a = _matrix(batch.column(1), shared.value.shape[0] * shared.value.shape[3])
            keys, a = pooled(batch.column(0).to_numpy(), a)
            if last is not None and last[0] == keys[0]:
                a[0] += last[1]
            elif last is not None:
                yield pa.RecordBatch.from_arrays([pa.array([last[0]], pa.int64()), _lists(last[1][None])], ["dst", "a"])
            if len(keys) > 1:
                yield pa.RecordBatch.from_arrays([pa.array(keys[:-1], pa.int64()), _lists(a[:-1])], ["dst", "a"])
            last = int(keys[-1]), a[-1].copy()
        if last is not None:
            yield pa.RecordBatch.from_arrays([pa.array([last[0]], pa.int64()), _lists(last[1][None])], ["dst", "a"])

    parts = inputs.select("dst", "fade", "y", "h", *(["w"] if radial else [])).mapInArrow(run, "dst long, a array<double>")
    return parts.repartition("dst").sortWithinPartitions("dst").mapInArrow(add, "dst long, a array<double>")


def unpack(packed: DataFrame, key: str, channels: int, lmax: int) -> DataFrame:
    """(key, k, l3, m3, val) of packed tensors."""
    names = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(l).alias("l3"), F.lit(m).alias("m3"), F.lit(k * coupling.width(lmax) + coupling.index(l, m)).alias("at")) for k in range(channels) for l in range(lmax + 1) for m in range(-l, l + 1)])
    return packed.select(key, F.explode(names).alias("t"), "a").select(key, "t.k", "t.l3", "t.m3", F.get("a", F.col("t.at")).alias("val"))


def pool_isolated(packed: DataFrame, v: DataFrame, channels: int, lmax: int) -> DataFrame:
    """All vertices; those without neighbours have zeros."""
    zeros = F.array_repeat(F.lit(0.0), channels * coupling.width(lmax))
    return v.select(F.col("v").alias("dst"), "z").join(packed, "dst", "left").select("dst", "z", F.coalesce("a", zeros).alias("a"))


def mix_channels(packed: DataFrame, channels: int, lmax: int) -> DataFrame:
    """A linear map among channels, one for each l."""
    u = np.array([[[small_weight(l, i, j) + (i == j) for j in range(channels)] for i in range(channels)] for l in range(lmax + 1)])
    order = np.array([l for l in range(lmax + 1) for _ in range(2 * l + 1)])
    shared = packed.sparkSession.sparkContext.broadcast(u[order])
    names = packed.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                a = _matrix(batch.column(names.index("a")), channels * len(order)).reshape(-1, channels, len(order))
                mixed = np.einsum("mij,njm->nim", shared.value, a).reshape(len(a), -1)
                yield pa.RecordBatch.from_arrays([_lists(mixed) if c == "a" else batch.column(c) for c in names], names)

    return packed.mapInArrow(run, packed.schema)


def contraction_terms(lmax: int, nu_max: int, l_out: int, basis="complex", canonical=False) -> list[tuple[int, int, int, list[int], float]]:
    """(nu, path, M, flat indices, c) of all orders up to nu_max."""
    return [(nu, p, m, list(lms), c) for nu in range(1, nu_max + 1) for p, m, lms, c in coupling.chain_terms(lmax, nu, l_out, basis, canonical)]


def contract_sparse(packed: DataFrame, channels: int, lmax: int, nu_max: int, l_out: int, basis="complex", canonical=False) -> DataFrame:
    """(dst, k, m3, val): products of the listed components, coupled, weighed by species, channel and path, summed. The
    terms are broadcast; each vertex row meets each term once."""
    spark = packed.sparkSession
    terms = F.broadcast(literal_table(spark, contraction_terms(lmax, nu_max, l_out, basis, canonical), "nu int, path int, m3 int, lms array<int>, c double"))
    rows = packed.select("dst", "z", "a", F.explode(F.sequence(F.lit(0), F.lit(channels - 1))).alias("k")).crossJoin(terms)
    product = F.aggregate("lms", F.lit(1.0), lambda acc, i: acc * F.get(F.col("a"), F.col("k") * coupling.width(lmax) + i))
    return rows.groupBy("dst", "k", "m3").agg(F.sum(F.col("c") * species_weight() * product).alias("val"))


def contract_dense_chain(packed: DataFrame, channels: int, lmax: int, nu_max: int, l_out: int, basis="complex") -> DataFrame:
    """The unfused baseline: for each order and path all combinations of components, zeros too, its result written out
    before the next, and a sum over all at the end."""
    spark, parts, n = packed.sparkSession, [], coupling.width(lmax)
    rows = settled(packed.select("dst", "z", "a", F.explode(F.sequence(F.lit(0), F.lit(channels - 1))).alias("k")))
    for nu in range(1, nu_max + 1):
        for p, (_, tensor) in enumerate(coupling.chains(lmax, nu, l_out, basis)):
            grid = F.broadcast(literal_table(spark, [([int(i) for i in at[:-1]], int(at[-1]) - l_out, float(tensor[at])) for at in np.ndindex(*tensor.shape)], "lms array<int>, m3 int, c double"))
            product = F.aggregate("lms", F.lit(1.0), lambda acc, i: acc * F.get(F.col("a"), F.col("k") * n + i))
            one = rows.crossJoin(grid).withColumns({"nu": F.lit(nu), "path": F.lit(p)})
            parts.append(settled(one.groupBy("dst", "k", "m3").agg(F.sum(F.col("c") * species_weight() * product).alias("val"))))
    return reduce(DataFrame.unionByName, parts).groupBy("dst", "k", "m3").agg(F.sum("val").alias("val"))


def body_features(packed: DataFrame, channels: int, lmax: int, nu_max: int, l_out: int, basis="complex") -> DataFrame:
    """(dst, z, k, nu, path, m3, val): the coupled products of each order and path, not yet weighed."""
    terms = F.broadcast(literal_table(packed.sparkSession, contraction_terms(lmax, nu_max, l_out, basis), "nu int, path int, m3 int, lms array<int>, c double"))
    rows = packed.select("dst", "z", "a", F.explode(F.sequence(F.lit(0), F.lit(channels - 1))).alias("k")).crossJoin(terms)
    product = F.aggregate("lms", F.lit(1.0), lambda acc, i: acc * F.get(F.col("a"), F.col("k") * coupling.width(lmax) + i))
    return rows.groupBy("dst", "z", "k", "nu", "path", "m3").agg(F.sum(F.col("c") * product).alias("val"))


def message(body: DataFrame) -> DataFrame:
    """(dst, k, m3, val): body features weighed by species, channel and path, and added up."""
    return body.groupBy("dst", "k", "m3").agg(F.sum(species_weight() * F.col("val")).alias("val"))


def update_features(h: DataFrame, messages: DataFrame, channels: int) -> DataFrame:
    """(v, h): the scalars of each channel mixed among channels, plus the message; vertices without one keep theirs.
    h: (v, h); messages: (v, m), both packed with a value a channel."""
    mixed = F.array(*[sum((F.get("h", F.lit(j)) * (small_weight(7, i, j) + (i == j)) for j in range(channels)), F.lit(0.0)) for i in range(channels)])
    rows = h.join(messages, "v", "left")
    return rows.select("v", F.zip_with(mixed, F.coalesce("m", F.array_repeat(F.lit(0.0), channels)), lambda a, b: a + b).alias("h"))


def readout(h: DataFrame, channels: int, last: bool, hidden: int = 16) -> DataFrame:
    """(v, e): the energy that a vertex' scalars give: linear at a layer between, a small perceptron at the last."""
    at = lambda k: F.get("h", F.lit(k))
    if not last:
        return h.select("v", sum((at(k) * small_weight(8, k) for k in range(channels)), F.lit(0.0)).alias("e"))
    units = [sum((at(k) * small_weight(9, k, j) for k in range(channels)), F.lit(0.0)) for j in range(hidden)]
    return h.select("v", sum((u / (F.lit(1.0) + F.exp(-u)) * small_weight(10, j) for j, u in enumerate(units)), F.lit(0.0)).alias("e"))


def species_weight():
    """small_weight(z, k, nu, path) as a column."""
    seed = F.lit(0)
    for c in ("z", "k", "nu", "path"):
        seed = seed * 31 + F.col(c) + 1
    return (F.pmod(seed, F.lit(7)) - 3) / F.lit(8.0)


class ContractTables:
    def __init__(self, channels: int, lmax: int, nu_max: int, l_out: int, basis: str, canonical: bool, species: int, dense: bool = False):
        self.shape, self.nu_max, self.l_out = (channels, coupling.width(lmax)), nu_max, l_out
        self.by_nu = []
        for nu in range(1, nu_max + 1):
            terms = coupling.chain_terms(lmax, nu, l_out, basis, canonical and not dense)
            weight = np.array([[[c * small_weight(z, k, nu, p) for p, _, _, c in terms] for k in range(channels)] for z in range(species)])
            self.by_nu.append((np.array([t[2] for t in terms], dtype=int).reshape(-1, nu), np.array([t[1] for t in terms], dtype=int) + l_out, weight))
        self.dense = None
        if dense:
            self.dense = []
            for nu, (lms, m, weight) in enumerate(self.by_nu, 1):
                full = np.zeros((species, channels, *[self.shape[1]] * nu, 2 * l_out + 1))
                np.add.at(full, (slice(None), slice(None), *lms.T, m), weight)
                self.dense.append(full)

    def apply(self, a: np.ndarray, z: np.ndarray, nested: bool = False) -> np.ndarray:
        """a [n, channels, width], z [n] -> [n, channels, 2 l_out + 1]."""
        out = np.zeros((len(a), self.shape[0], 2 * self.l_out + 1), dtype=a.dtype)
        for s in np.unique(z):
            at = np.flatnonzero(z == s)
            x = a[at]
            for nu in range(self.nu_max):
                if self.dense is not None:
                    letters = "abc"[: nu + 1]
                    out[at] += np.einsum(f"k{letters}m,{','.join('nk' + c for c in letters)}->nkm", self.dense[nu][s], *[x] * (nu + 1))
                    continue
                lms, m, weight = self.by_nu[nu]
                if not len(lms):
                    continue
                if nested and nu:  # products of the first factors are made once and shared
                    heads, back = np.unique(lms[:, :-1], axis=0, return_inverse=True)
                    shared = np.prod(x[:, :, heads], axis=3)
                    product = shared[:, :, back.ravel()] * x[:, :, lms[:, -1]]
                else:
                    product = np.prod(x[:, :, lms], axis=3)
                product = product * weight[s][None].astype(a.dtype)
                for k in range(2 * self.l_out + 1):
                    out[at, :, k] += product[:, :, m == k].sum(2)
        return out


def contract_fused(packed: DataFrame, channels: int, lmax: int, nu_max: int, l_out: int, basis="complex", canonical=True, dense=False, nested=False, species=10, dtype="double") -> DataFrame:
    """Packed (dst, a): the whole contraction row by row in one Arrow stage, without a shuffle."""
    shared = packed.sparkSession.sparkContext.broadcast(ContractTables(channels, lmax, nu_max, l_out, basis, canonical, species, dense))
    kind = np.float32 if dtype == "float" else np.float64

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                a = _matrix(part.column(2), channels * coupling.width(lmax)).reshape(-1, *t.shape).astype(kind)
                yield pa.RecordBatch.from_arrays([part.column(0), _lists(t.apply(a, part.column(1).to_numpy(), nested).reshape(len(a), -1))], ["dst", "a"])

    return packed.select("dst", "z", "a").mapInArrow(run, "dst long, a array<double>")


def unpack_order(packed: DataFrame, channels: int, l: int) -> DataFrame:
    names = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(m).alias("m3"), F.lit(k * (2 * l + 1) + m + l).alias("at")) for k in range(channels) for m in range(-l, l + 1)])
    return packed.select("dst", F.explode(names).alias("t"), "a").select("dst", "t.k", "t.m3", F.get("a", F.col("t.at")).alias("val"))


def flop_count(n_edges: int, channels: int, l1: int, l2: int, l3: int) -> dict[str, int]:
    """Multiply-adds of the dense and the sparse product."""
    return {"dense": n_edges * channels * coupling.width(l1) * coupling.width(l2) * coupling.width(l3), "sparse": n_edges * channels * len(coupling.table(l1, l2, l3))}


def harmonics_fused(edges: DataFrame, lmax: int) -> DataFrame:
    """edges with packed harmonics y of any order."""
    names = edges.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                xyz = np.stack([batch.column(c).to_numpy() for c in ("dx", "dy", "dz")], axis=1)
                yield pa.RecordBatch.from_arrays([*batch.columns, _lists(harmonics(xyz / np.linalg.norm(xyz, axis=1, keepdims=True), lmax))], [*names, "y"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in edges.schema) + ", y array<double>"
    return edges.mapInArrow(run, schema)


def embed(v: DataFrame, channels: int, species: int = 10) -> DataFrame:
    """v with h0: the species' scalar of each channel, from a broadcast table of one row a species. A vertex of another
    or of no species stays, with zeros."""
    table = literal_table(v.sparkSession, [(z, [small_weight(z, k) for k in range(channels)]) for z in range(species)], "z int, h0 array<double>")
    return v.join(F.broadcast(table), "z", "left").withColumn("h0", F.coalesce("h0", F.array_repeat(F.lit(0.0), channels)))


def embed_edges(edges: DataFrame, n_radial: int, r_cut: float) -> DataFrame:
    """edges with packed harmonics y and radial functions b, as columns."""
    return edges.withColumn("y", harmonics_column(F.col("dx"), F.col("dy"), F.col("dz"), F.col("r"), 2)).withColumn("b", F.array(*[bessel_column(F.col("r"), n, r_cut) for n in range(1, n_radial + 1)]))


def radial_tables(channels: int, n_paths: int, n_radial: int, hidden: int = 16) -> tuple[np.ndarray, np.ndarray]:
    """The perceptron's weights, from a rule."""
    first = np.array([[small_weight(5, n, j) for j in range(hidden)] for n in range(n_radial)])
    return first, np.array([[small_weight(6, j, k, p) for k in range(channels) for p in range(n_paths)] for j in range(hidden)])


def radial_weights(edges: DataFrame, channels: int, n_paths: int, n_radial: int, r_cut: float) -> DataFrame:
    """edges with w: the weights of each channel and path, from a perceptron on the radial basis, in one Arrow stage."""
    from ..functions.harmonics import bessel

    shared = edges.sparkSession.sparkContext.broadcast(radial_tables(channels, n_paths, n_radial))
    names = edges.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first, second = shared.value
        for batch in batches:
            if batch.num_rows:
                u = bessel(batch.column(names.index("r")).to_numpy(), n_radial, r_cut) @ first
                yield pa.RecordBatch.from_arrays([*batch.columns, _lists((u / (1 + np.exp(-u))) @ second)], [*names, "w"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in edges.schema) + ", w array<double>"
    return edges.mapInArrow(run, schema)


def plan_stats(df: DataFrame) -> dict[str, int]:
    """Stages that a form needs: exchanges, joins, aggregations and Arrow stages of its physical plan."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return {"exchanges": plan.count("Exchange"), "joins": plan.count("Join"), "aggregates": plan.count("HashAggregate"), "arrow": plan.count("MapInArrow"), "materialised": plan.count("Scan ExistingRDD") + plan.count("RDDScan")}
