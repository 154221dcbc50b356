"""Kernels and network on the geometric graphs of the embeddings, with the SQL that says the same in long form."""

from __future__ import annotations

from pyspark.sql import functions as F

from .functions import coupling
from .functions.harmonics import bessel_column, harmonics_column
from .operators import graphs, kernels
from .operators.network import KernelConfig, Network, batched_energy, energy, equivariance_error, forces, train_readout
from .operators.packing import batch_fixed_count, pack_balanced, schedule
from .sources.tables import doc_sizes, literal_table, read_table
from .workloads import CAPACITY, RANKS, _edges_sql, query

R_CUT, K = 0.25, 2

FACT = lambda x: f"CAST(factorial(CAST({x} AS INTEGER)) AS DOUBLE)"


def cg_sql(l1: int, l2: int, l3: int) -> str:
    """CTEs t (admissible tuples) and cg (path, l1, m1, l2, m2, l3, m3, c)."""
    f = FACT
    args = ["k", "l1 + l2 - l3 - k", "l1 - m1 - k", "l2 + m2 - k", "l3 - l2 + m1 + k", "l3 - l1 - m2 + k"]
    root = f"sqrt((2 * l3 + 1) * {f('l3 + l1 - l2')} * {f('l3 - l1 + l2')} * {f('l1 + l2 - l3')} / {f('l1 + l2 + l3 + 1')}) * sqrt({f('l3 + m3')} * {f('l3 - m3')} * {f('l1 - m1')} * {f('l1 + m1')} * {f('l2 - m2')} * {f('l2 + m2')})"
    return f"""t AS (SELECT CAST(l1 AS INTEGER) AS l1, CAST(m1 AS INTEGER) AS m1, CAST(l2 AS INTEGER) AS l2, CAST(m2 AS INTEGER) AS m2, CAST(l3 AS INTEGER) AS l3, CAST(m1 + m2 AS INTEGER) AS m3
        FROM range({l1 + 1}) a(l1), range({l2 + 1}) b(l2), range({l3 + 1}) c(l3), range(-{l1}, {l1 + 1}) d(m1), range(-{l2}, {l2 + 1}) e(m2) WHERE abs(l1 - l2) <= l3 AND l3 <= l1 + l2 AND abs(m1) <= l1 AND abs(m2) <= l2 AND abs(m1 + m2) <= l3),
    pth AS (SELECT l1, l2, l3, CAST(row_number() OVER (ORDER BY l1, l2, l3) - 1 AS INTEGER) AS path FROM (SELECT DISTINCT l1, l2, l3 FROM t)),
    ks AS (SELECT l1, m1, l2, m2, l3, m3, sum((CASE WHEN k % 2 = 0 THEN 1.0 ELSE -1.0 END) / ({' * '.join(f(x) for x in args)})) AS s FROM t, range(0, 12) r(k) WHERE {' AND '.join(f'{x} >= 0' for x in args)} GROUP BY ALL),
    cg AS (SELECT path, l1, m1, l2, m2, l3, m3, {root} * s AS c FROM ks JOIN pth USING (l1, l2, l3) WHERE abs(s) > 1e-12)"""


TUPLE = ["l1", "m1", "l2", "m2", "l3", "m3"]
_NAMES = ", ".join(TUPLE)
_KEYS = ("l_partkey", "l_suppkey", "l_orderkey")


def _place(key: str, n: int) -> str:
    return f"(({key} % {n} + {n}) % {n})"


def named_sql(l1: int, l2: int, l3: int, name: str = "named") -> str:
    """CTE {name} (l1, m1, l2, m2, l3, m3, items): see named_entries()."""
    order = lambda i: f"CAST(floor(sqrt(p{i})) AS INTEGER)"
    columns = ", ".join(f"{order(i)} AS l{i}, CAST(p{i} - {order(i)} * {order(i)} - {order(i)} AS INTEGER) AS m{i}" for i in (1, 2, 3))
    places = ", ".join(f"{_place(k, coupling.width(l))} AS p{i}" for i, (k, l) in enumerate(zip(_KEYS, (l1, l2, l3)), 1))
    return f"{name} AS (SELECT {columns}, items FROM (SELECT {places}, count(*) AS items FROM lineitem GROUP BY ALL))"


def named_entries(spark, d, sets):
    """(l1max, l2max, l3max, l1, m1, l2, m2, l3, m3, items): for each set of largest orders the entries of the dense tensor
    that the items of the orders name, and how many name each. The part names the first factor's place, the supplier the
    second's, the order that of the product, as keys modulo the widths. A missing key leaves its place open."""
    of = F.array(*[F.struct(*[F.lit(x).alias(f"l{i}max") for i, x in enumerate(s, 1)]) for s in sets])
    rows = read_table(spark, d, "lineitem", list(_KEYS)).withColumn("of", F.explode(of)).select("of.*", *_KEYS)
    width = lambda i: (F.col(f"l{i}max") + 1) * (F.col(f"l{i}max") + 1)
    cells = rows.groupBy("l1max", "l2max", "l3max", *[F.pmod(F.col(k), width(i)).cast("int").alias(f"p{i}") for i, k in enumerate(_KEYS, 1)]).agg(F.count("*").alias("items"))
    order = lambda i: F.floor(F.sqrt(F.col(f"p{i}"))).cast("int")
    places = [c for i in (1, 2, 3) for c in (order(i).alias(f"l{i}"), (F.col(f"p{i}") - order(i) * order(i) - order(i)).alias(f"m{i}"))]
    entry = F.inline(F.array(F.struct(*places)))  # a generator: rules on the entry are not evaluated on every item
    return cells.select("l1max", "l2max", "l3max", entry, "items")


def _named(spark, d):
    return named_entries(spark, d, [(3, 1, 2)]).select(*TUPLE, "items")


@query(f"WITH {cg_sql(3, 1, 2)}, {named_sql(3, 1, 2)} SELECT {_NAMES}, items FROM named JOIN t USING ({_NAMES})")
def cg_admissible(spark, d):
    """The entries that items name and the selection rules admit."""
    return _named(spark, d).where(kernels.admissible())


@query(f"WITH {cg_sql(3, 1, 2)}, {named_sql(3, 1, 2)} SELECT {_NAMES}, round(c, 9) AS c, items FROM named JOIN cg USING ({_NAMES})")
def cg_table_complex(spark, d):
    """The coefficients, where they are not zero, of the entries that items name."""
    return _named(spark, d).join(kernels.cg_frame(spark, 3, 1, 2), TUPLE).select(*TUPLE, F.round("c", 9).alias("c"), "items")


_ROOT = "sqrt(0.5)"
REAL_SQL = f"""{cg_sql(3, 1, 2)}, lx AS (SELECT CAST(l AS INTEGER) AS l, CAST(x AS INTEGER) AS x FROM range(4) a(l), range(-3, 4) b(x) WHERE abs(x) <= l), sg AS (SELECT l, x, CASE WHEN x % 2 = 0 THEN {_ROOT} ELSE -{_ROOT} END AS s FROM lx),
    u AS (SELECT l, x, x AS m, CASE WHEN x > 0 THEN s WHEN x = 0 THEN 1.0 ELSE 0.0 END AS re, CASE WHEN x < 0 THEN {_ROOT} ELSE 0.0 END AS im FROM sg UNION ALL SELECT l, x, -x, CASE WHEN x > 0 THEN {_ROOT} ELSE 0.0 END, CASE WHEN x < 0 THEN -s ELSE 0.0 END FROM sg WHERE x <> 0),
    three AS (SELECT path, cg.l1, a.x AS m1, cg.l2, b.x AS m2, cg.l3, z.x AS m3, sum(c * ((a.re * b.re - a.im * b.im) * z.re + (a.re * b.im + a.im * b.re) * z.im)) AS re, sum(c * ((a.re * b.re - a.im * b.im) * z.im - (a.re * b.im + a.im * b.re) * z.re)) AS im
        FROM cg JOIN u a ON a.l = cg.l1 AND a.m = cg.m1 JOIN u b ON b.l = cg.l2 AND b.m = cg.m2 JOIN u z ON z.l = cg.l3 AND z.m = cg.m3 GROUP BY ALL),
    rcg AS (SELECT path, {_NAMES}, CASE WHEN (l1 + l2 + l3) % 2 = 0 THEN re ELSE -im END AS c FROM three)"""


@query(f"WITH {REAL_SQL}, {named_sql(3, 1, 2)} SELECT path, {_NAMES}, round(c, 9) AS c, items FROM named JOIN rcg USING ({_NAMES}) WHERE abs(c) > 1e-12")
def cg_table_real(spark, d):
    """As cg_table_complex, in the real basis."""
    return _named(spark, d).join(kernels.cg_frame(spark, 3, 1, 2, "real"), TUPLE).select("path", *TUPLE, F.round("c", 9).alias("c"), "items")


_SETS = ((1, 1, 1), (2, 2, 2), (3, 1, 2), (3, 2, 2), (3, 3, 3))


@query(" UNION ALL ".join(f"SELECT * FROM (WITH {cg_sql(a, b, c)}, {named_sql(a, b, c)} SELECT {a} AS l1max, {b} AS l2max, {c} AS l3max, CAST(sum(items) AS BIGINT) AS total, CAST(coalesce(sum(items) FILTER (t.l1 IS NOT NULL), 0) AS BIGINT) AS admissible, CAST(coalesce(sum(items) FILTER (cg.l1 IS NOT NULL), 0) AS BIGINT) AS nonzero, round(coalesce(sum(items * c * c), 0), 6) AS squares FROM named LEFT JOIN t USING ({_NAMES}) LEFT JOIN cg USING ({_NAMES}) HAVING count(*) > 0)" for a, b, c in _SETS))
def cg_density(spark, d):
    """Of the items of each dense tensor: all, those whose entry the rules admit, those whose coefficient is not zero, and
    the sum of squares."""
    of = ["l1max", "l2max", "l3max"]
    cg = F.broadcast(literal_table(spark, [(*s, *row[1:]) for s in _SETS for row in coupling.table(*s)], ", ".join(f"{x} int" for x in of + TUPLE) + ", c double"))
    sum_if = lambda x: F.coalesce(F.sum(F.when(x, F.col("items"))), F.lit(0)).alias
    squares = F.round(F.coalesce(F.sum(F.col("items") * F.col("c") * F.col("c")), F.lit(0.0)), 6)
    return named_entries(spark, d, _SETS).join(cg, of + TUPLE, "left").groupBy(*of).agg(F.sum("items").alias("total"), sum_if(kernels.admissible())("admissible"), sum_if(F.col("c").isNotNull())("nonzero"), squares.alias("squares"))


Y_SQL = """[0.5 * sqrt(1 / pi()), dy / r * sqrt(3 / (4 * pi())), dz / r * sqrt(3 / (4 * pi())), dx / r * sqrt(3 / (4 * pi())), dx / r * dy / r * 0.5 * sqrt(15 / pi()), dy / r * dz / r * 0.5 * sqrt(15 / pi()),
    (3 * dz / r * dz / r - 1) * 0.25 * sqrt(5 / pi()), dx / r * dz / r * 0.5 * sqrt(15 / pi()), (dx / r * dx / r - dy / r * dy / r) * 0.25 * sqrt(15 / pi())]"""


def _edges(spark, d):
    return graphs.radius_edges(graphs.vertices(spark, d, channels=K), R_CUT)


def _y():
    return harmonics_column(F.col("dx"), F.col("dy"), F.col("dz"), F.col("r"), 2)


@query(f"WITH {_edges_sql(None)} SELECT dst, src, list_transform({Y_SQL}, lambda x: round(x, 6) + 0.0) AS y FROM edges")
def harmonics_l2(spark, d):
    return _edges(spark, d).select("dst", "src", F.transform(_y(), lambda x: F.round(x, 6) + F.lit(0.0)).alias("y"))


@query(f"WITH {_edges_sql(None)} SELECT dst, src, list_transform({Y_SQL}, lambda x: round(x, 6) + 0.0) AS y FROM edges")
def udf_harmonics(spark, d):
    """The vectorised recursion gives the polynomials' values."""
    return kernels.harmonics_fused(_edges(spark, d), 2).select("dst", "src", F.transform("y", lambda x: F.round(x, 6) + F.lit(0.0)).alias("y"))


_U = "(r / 0.25)"
_ENV = f"(1 - 28 * pow({_U}, 6) + 48 * pow({_U}, 7) - 21 * pow({_U}, 8))"


@query(f"WITH {_edges_sql(None)} SELECT dst, src, " + ", ".join(f"round(CASE WHEN {_U} < 1 THEN sqrt(8.0) * sin({n} * pi() * {_U}) / r * {_ENV} ELSE 0 END, 5) + 0.0 AS b{n}" for n in (1, 2, 8)) + " FROM edges")
def bessel_basis(spark, d):
    return _edges(spark, d).select("dst", "src", *[(F.round(bessel_column(F.col("r"), n, R_CUT), 5) + F.lit(0.0)).alias(f"b{n}") for n in (1, 2, 8)])


PRODUCT = f"""{_edges_sql(None)}, {cg_sql(2, 1, 2)}, he AS (SELECT vec_id, embedding FROM embeddings),
    ey AS (SELECT dst, 1 - r / {R_CUT} AS fade, {Y_SQL} AS y, embedding FROM edges JOIN he ON vec_id = src),
    a AS (SELECT dst, CAST(k AS INTEGER) AS k, l3, m3, sum(c * (((path + 1) * 31 + k + 1) % 7 - 3) / 8.0 * fade * y[l1 * l1 + l1 + m1 + 1] * CAST(embedding[CAST(4 + 4 * k + l2 * l2 + l2 + m2 AS BIGINT)] AS DOUBLE)) AS val FROM ey, cg, range(0, {K}) r(k) GROUP BY ALL)"""
SHOW_PRODUCT = f"WITH {PRODUCT} SELECT dst, k, l3, m3, round(val, 6) + 0.0 AS val FROM a"


def _inputs(spark, d):
    v = graphs.vertices(spark, d, channels=K)
    return kernels.edge_inputs(graphs.radius_edges(v, R_CUT), v, _y(), R_CUT)


def _rounded(df, *keys):
    return df.select(*keys, (F.round("val", 6) + F.lit(0.0)).alias("val"))


def kernel_seconds(spark, d) -> tuple[float, float]:
    """Measured seconds of the dense chain and of the fused product on the same stored edges, after a run to warm up."""
    import time

    from .sources.tables import sink_noop, stored

    inputs = stored(_inputs(spark, d), "edges")
    sink_noop(kernels.product_fused(inputs, K))
    took = []
    for form in (kernels.product_dense_chain, kernels.product_fused):
        began = time.perf_counter()
        sink_noop(form(inputs, K))
        took.append(time.perf_counter() - began)
    return took[0], took[1]


@query(SHOW_PRODUCT)
def edge_product_sparse(spark, d):
    return _rounded(kernels.product_sparse(_inputs(spark, d), K), "dst", "k", "l3", "m3")


@query(SHOW_PRODUCT)
def edge_product_dense(spark, d):
    return _rounded(kernels.product_dense_chain(_inputs(spark, d), K), "dst", "k", "l3", "m3")


@query(SHOW_PRODUCT)
def edge_product_dense_join(spark, d):
    return _rounded(kernels.product_sparse(_inputs(spark, d), K, dense=True), "dst", "k", "l3", "m3")


@query(SHOW_PRODUCT)
def edge_product_fused(spark, d):
    return _rounded(kernels.unpack(kernels.product_fused(_inputs(spark, d), K), "dst", K, 2), "dst", "k", "l3", "m3")


@query(SHOW_PRODUCT)
def edge_product_fused_dense(spark, d):
    return _rounded(kernels.unpack(kernels.product_fused(_inputs(spark, d), K, dense=True), "dst", K, 2), "dst", "k", "l3", "m3")


def _pooled(spark, d):
    return kernels.pool_isolated(kernels.product_fused(_inputs(spark, d), K), graphs.vertices(spark, d), K, 2)


ALL_A = f"""{PRODUCT}, lm AS (SELECT CAST(k AS INTEGER) AS k, CAST(l AS INTEGER) AS l3, CAST(m AS INTEGER) AS m3 FROM range(0, {K}) a(k), range(0, 3) b(l), range(-2, 3) c(m) WHERE abs(m) <= l),
    full_a AS (SELECT vec_id AS dst, label AS z, lm.k, lm.l3, lm.m3, coalesce(val, 0) AS val FROM embeddings CROSS JOIN lm LEFT JOIN a ON a.dst = vec_id AND a.k = lm.k AND a.l3 = lm.l3 AND a.m3 = lm.m3)"""


@query(f"WITH {ALL_A} SELECT dst, k, l3, m3, round(val, 6) + 0.0 AS val FROM full_a")
def pool_messages(spark, d):
    """Messages added up on their receiver; vertices without neighbours have zeros."""
    return _rounded(kernels.unpack(_pooled(spark, d), "dst", K, 2), "dst", "k", "l3", "m3")


def _w(nu: str, path: str) -> str:
    return f"(((((z + 1) * 31 + k + 1) * 31 + {nu} + 1) * 31 + {path} + 1) % 7 - 3) / 8.0"


ONE = f"SELECT dst, k, m3, {_w('1', '0')} * val AS val FROM full_a WHERE l3 = 0"
TWO = f"SELECT x.dst, x.k, 0 AS m3, {_w('2', 'x.l3').replace('z +', 'x.z +').replace('k +', 'x.k +')} * c * x.val * y.val AS val FROM full_a x JOIN full_a y ON x.dst = y.dst AND x.k = y.k AND x.l3 = y.l3 JOIN cz ON cz.l1 = x.l3 AND cz.m1 = x.m3 AND cz.l2 = y.l3 AND cz.m2 = y.m3"


def _cz() -> str:
    return cg_sql(2, 2, 0).replace("cg AS", "cz AS").replace("t AS", "tz AS", 1).replace("FROM t)", "FROM tz)").replace("FROM t, range", "FROM tz, range").replace("pth", "pz").replace("ks AS", "kz AS").replace("FROM ks", "FROM kz")


NU2 = f"WITH {ALL_A}, {_cz()}, m AS ({ONE} UNION ALL {TWO}) SELECT dst, k, m3, round(sum(val), 6) + 0.0 AS val FROM m GROUP BY dst, k, m3"


@query(f"WITH {ALL_A}, m AS ({ONE.replace('l3 = 0', 'l3 = 1')}) SELECT dst, k, m3, round(val, 6) + 0.0 AS val FROM m")
def symmetric_contract_nu1(spark, d):
    return _rounded(kernels.contract_sparse(_pooled(spark, d), K, 2, 1, 1), "dst", "k", "m3")


@query(NU2)
def symmetric_contract_nu2(spark, d):
    return _rounded(kernels.contract_sparse(_pooled(spark, d), K, 2, 2, 0), "dst", "k", "m3")


@query(NU2)
def symmetric_contract_fused(spark, d):
    return _rounded(kernels.unpack_order(kernels.contract_fused(_pooled(spark, d), K, 2, 2, 0, canonical=False), K, 0), "dst", "k", "m3")


@query(NU2)
def symmetric_contract_canonical(spark, d):
    return _rounded(kernels.unpack_order(kernels.contract_fused(_pooled(spark, d), K, 2, 2, 0, canonical=True), K, 0), "dst", "k", "m3")


@query(NU2)
def symmetric_contract_fused_dense(spark, d):
    return _rounded(kernels.unpack_order(kernels.contract_fused(_pooled(spark, d), K, 2, 2, 0, dense=True), K, 0), "dst", "k", "m3")


@query(NU2)
def symmetric_contract_nested(spark, d):
    return _rounded(kernels.unpack_order(kernels.contract_fused(_pooled(spark, d), K, 2, 2, 0, nested=True), K, 0), "dst", "k", "m3")


def _terms_sql(l_out: int) -> str:
    """CTEs over full_a: f (dst, z, k, i, val) and terms (nu, path, m3, i1, i2, i3, c) of up to three coupled factors."""
    return f"""{_cz_of(4, 2, 4)}, f AS (SELECT dst, z, k, l3 * l3 + l3 + m3 AS i, val FROM full_a),
    terms AS (SELECT 1 AS nu, 0 AS path, m3, l3 * l3 + l3 + m3 AS i1, 0 AS i2, 0 AS i3, CAST(1 AS DOUBLE) AS c FROM lm WHERE l3 = {l_out} AND k = 0
      UNION ALL SELECT 2, dense_rank() OVER (ORDER BY l1, l2) - 1, m3, l1 * l1 + l1 + m1, l2 * l2 + l2 + m2, 0, c FROM cz WHERE l1 <= 2 AND l3 = {l_out}
      UNION ALL SELECT 3, dense_rank() OVER (ORDER BY a.l3, a.l1, a.l2, b.l2) - 1, b.m3, a.l1 * a.l1 + a.l1 + a.m1, a.l2 * a.l2 + a.l2 + a.m2, b.l2 * b.l2 + b.l2 + b.m2, a.c * b.c FROM cz a JOIN cz b ON b.l1 = a.l3 AND b.m1 = a.m3 WHERE a.l1 <= 2 AND b.l3 = {l_out}),
    products AS (SELECT f.dst, f.z, f.k, nu, path, t.m3, c * f.val * CASE WHEN nu > 1 THEN g.val ELSE 1 END * CASE WHEN nu > 2 THEN h.val ELSE 1 END AS val
      FROM terms t JOIN f ON f.i = t.i1 JOIN f g ON g.dst = f.dst AND g.k = f.k AND g.i = t.i2 JOIN f h ON h.dst = f.dst AND h.k = f.k AND h.i = t.i3)"""


def _cz_of(l1: int, l2: int, l3: int) -> str:
    return cg_sql(l1, l2, l3).replace("cg AS", "cz AS").replace("t AS", "tz AS", 1).replace("FROM t)", "FROM tz)").replace("FROM t, range", "FROM tz, range").replace("pth", "pz").replace("ks AS", "kz AS").replace("FROM ks", "FROM kz")


def _seeded(*parts: str) -> str:
    seed = "0"
    for x in parts:
        seed = f"({seed} * 31 + {x} + 1)"
    return f"(({seed} % 7 - 3) / 8.0)"


def _contracted(nu: int, l_out: int) -> str:
    return f"WITH {ALL_A}, {_terms_sql(l_out)} SELECT dst, k, CAST(m3 AS INTEGER) AS m3, round(sum({_seeded('z', 'k', 'nu', 'path')} * val), 6) + 0.0 AS val FROM products WHERE nu <= {nu} GROUP BY dst, k, m3"


@query(_contracted(3, 1))
def symmetric_contract_nu3(spark, d):
    return _rounded(kernels.unpack_order(kernels.contract_fused(_pooled(spark, d), K, 2, 3, 1), K, 1), "dst", "k", "m3")


@query(NU2)
def symmetric_contract_dense(spark, d):
    """The unfused baseline of the contraction: a written result for each order and path."""
    return _rounded(kernels.contract_dense_chain(_pooled(spark, d), K, 2, 2, 0), "dst", "k", "m3")


_FLAT = [f"CAST({_place(k, coupling.width(2))} AS INTEGER)" for k in _KEYS]
_LISTS = "lists AS (" + " UNION ALL ".join(f"SELECT {n} AS nu, [{', '.join(_FLAT[:n])}] AS lms, count(*) AS items FROM lineitem WHERE " + " AND ".join(f"{k} IS NOT NULL" for k in _KEYS[:n]) + " GROUP BY ALL" for n in (2, 3)) + ")"


@query(f"WITH {_cz_of(4, 2, 4)}, g AS (SELECT 2 AS nu, dense_rank() OVER (ORDER BY l1, l2) - 1 AS path, m3, [l1 * l1 + l1 + m1, l2 * l2 + l2 + m2] AS lms, c FROM cz WHERE l1 <= 2 AND l3 = 1 UNION ALL SELECT 3, dense_rank() OVER (ORDER BY a.l3, a.l1, a.l2, b.l2) - 1, b.m3, [a.l1 * a.l1 + a.l1 + a.m1, a.l2 * a.l2 + a.l2 + a.m2, b.l2 * b.l2 + b.l2 + b.m2], a.c * b.c FROM cz a JOIN cz b ON b.l1 = a.l3 AND b.m1 = a.m3 WHERE a.l1 <= 2 AND b.l3 = 1), {_LISTS} SELECT g.nu, CAST(path AS INTEGER) AS path, CAST(m3 AS INTEGER) AS m3, g.lms, round(c, 9) AS c, items FROM g JOIN lists ON lists.nu = g.nu AND lists.lms = g.lms")
def generalized_cg(spark, d):
    """The coupling coefficients of two and three factors of order up to 2 that end in order 1, of the factors that items
    name by part, supplier and order."""
    terms = F.broadcast(literal_table(spark, [t for t in kernels.contraction_terms(2, 3, 1) if t[0] > 1], "nu int, path int, m3 int, lms array<int>, c double"))
    flat = [F.pmod(F.col(k), F.lit(coupling.width(2))).cast("int").alias(k) for k in _KEYS]
    cells = read_table(spark, d, "lineitem", list(_KEYS)).groupBy(*flat).agg(F.count("*").alias("items"))
    lists = cells.withColumn("lms", F.explode(F.array(F.array(*_KEYS[:2]), F.array(*_KEYS)))).groupBy("lms").agg(F.sum("items").alias("items"))
    return lists.join(terms, "lms").select("nu", "path", "m3", "lms", F.round("c", 9).alias("c"), "items")


BODY = f"WITH {ALL_A}, {_terms_sql(0)}"


@query(f"{BODY} SELECT dst, k, nu, CAST(path AS INTEGER) AS path, round(sum(val), 6) + 0.0 AS val FROM products WHERE nu <= 2 GROUP BY dst, k, nu, path")
def body_features(spark, d):
    """Invariant products of one and two factors on each vertex, not yet weighed."""
    return _rounded(kernels.body_features(_pooled(spark, d), K, 2, 2, 0), "dst", "k", "nu", "path")


@query(_contracted(2, 0))
def message(spark, d):
    """Body features weighed by species, channel and path."""
    return _rounded(kernels.message(kernels.body_features(_pooled(spark, d), K, 2, 2, 0)), "dst", "k", "m3")


UPDATED = f"""{BODY}, m AS (SELECT dst, k, sum({_seeded('z', 'k', 'nu', 'path')} * val) AS m FROM products WHERE nu <= 2 GROUP BY dst, k), h0 AS (SELECT vec_id AS v, CAST(j AS INTEGER) AS k, {_seeded('label', 'j')} AS h FROM embeddings, range({K}) r(j)),
    h1 AS (SELECT i.v, i.k, sum(j.h * ({_seeded('7', 'i.k', 'j.k')} + CASE WHEN i.k = j.k THEN 1 ELSE 0 END)) + coalesce(any_value(m.m), 0) AS h FROM h0 i JOIN h0 j ON j.v = i.v LEFT JOIN m ON m.dst = i.v AND m.k = i.k GROUP BY i.v, i.k)"""


def _updated(spark, d):
    v = graphs.vertices(spark, d, channels=K)
    got = kernels.contract_fused(_pooled(spark, d), K, 2, 2, 0).select(F.col("dst").alias("v"), F.col("a").alias("m"))
    return kernels.update_features(kernels.embed(v, K).select("v", F.col("h0").alias("h")), got, K)


@query(f"{UPDATED} SELECT v, list(round(h, 6) + 0.0 ORDER BY k) AS h FROM h1 GROUP BY v")
def update_features(spark, d):
    """The embedding's scalars, mixed among channels, plus the message of the first layer."""
    return _updated(spark, d).select("v", F.transform("h", lambda x: F.round(x, 6) + F.lit(0.0)).alias("h"))


@query(f"""{UPDATED}, u AS (SELECT v, j, sum(h * {_seeded('9', 'k', 'j')}) AS u FROM h1, range(16) r(j) GROUP BY v, j), p AS (SELECT v, sum(u / (1 + exp(-u)) * {_seeded('10', 'j')}) AS e FROM u GROUP BY v)
    SELECT v, round(l.e, 6) + 0.0 AS linear, round(p.e, 6) + 0.0 AS perceptron FROM (SELECT v, sum(h * {_seeded('8', 'k')}) AS e FROM h1 GROUP BY v) l JOIN p USING (v)""")
def readout(spark, d):
    """The linear readout of a layer between, and the perceptron of the last, on the same scalars."""
    h = _updated(spark, d)
    e = lambda last, name: kernels.readout(h, K, last).select("v", (F.round("e", 6) + F.lit(0.0)).alias(name))
    return e(False, "linear").join(e(True, "perceptron"), "v")


@query(f"WITH {ALL_A} SELECT i.dst, i.k, i.l3, i.m3, round(sum(({_seeded('i.l3', 'i.k', 'j.k')} + CASE WHEN i.k = j.k THEN 1 ELSE 0 END) * j.val), 6) + 0.0 AS val FROM full_a i JOIN full_a j ON j.dst = i.dst AND j.l3 = i.l3 AND j.m3 = i.m3 GROUP BY ALL")
def mix_channels(spark, d):
    return _rounded(kernels.unpack(kernels.mix_channels(_pooled(spark, d), K, 2), "dst", K, 2), "dst", "k", "l3", "m3")


N_PATHS = len(coupling.paths(2, 1, 2))
RADIAL = f"""{_edges_sql(None)}, {cg_sql(2, 1, 2)}, he AS (SELECT vec_id, embedding FROM embeddings),
    en AS (SELECT row_number() OVER () AS e, dst, src, r, {Y_SQL} AS y, embedding FROM edges JOIN he ON vec_id = src),
    eb AS (SELECT e, n, sqrt(8.0) * sin((n + 1) * pi() * r / {R_CUT}) / r * (1 - 28 * pow(r / {R_CUT}, 6) + 48 * pow(r / {R_CUT}, 7) - 21 * pow(r / {R_CUT}, 8)) * (r < {R_CUT})::INT AS b FROM en, range(8) x(n)),
    eu AS (SELECT e, j, sum(b * {_seeded('5', 'n', 'j')}) AS u FROM eb, range(16) x(j) GROUP BY e, j),
    ew AS (SELECT e, k, path, sum(u / (1 + exp(-u)) * {_seeded('6', 'j', 'k', 'path')}) AS w FROM eu, range({K}) a(k), range({N_PATHS}) b(path) GROUP BY e, k, path)"""
RADIAL_PRODUCT = f"WITH {RADIAL} SELECT dst, CAST(k AS INTEGER) AS k, l3, m3, round(sum(c * w * y[l1 * l1 + l1 + m1 + 1] * CAST(embedding[CAST(4 + 4 * k + l2 * l2 + l2 + m2 AS BIGINT)] AS DOUBLE)), 5) + 0.0 AS val FROM en JOIN ew USING (e) JOIN cg USING (path) GROUP BY dst, k, l3, m3"


def _radial_inputs(spark, d, channels=K):
    v = graphs.vertices(spark, d, channels=channels)
    return kernels.edge_inputs(kernels.radial_weights(graphs.radius_edges(v, R_CUT), channels, N_PATHS, 8, R_CUT), v, _y(), R_CUT)


@query(RADIAL_PRODUCT)
def edge_product_radial(spark, d):
    """The sparse product with weights of each channel and path from the radial perceptron."""
    return kernels.product_sparse(_radial_inputs(spark, d), K).select("dst", "k", "l3", "m3", (F.round("val", 5) + F.lit(0.0)).alias("val"))


@query(RADIAL_PRODUCT)
def edge_product_radial_fused(spark, d):
    return kernels.unpack(kernels.product_fused(_radial_inputs(spark, d), K), "dst", K, 2).select("dst", "k", "l3", "m3", (F.round("val", 5) + F.lit(0.0)).alias("val"))


@query(f"WITH {_edges_sql(None)}, ey AS (SELECT dst, src, r, {Y_SQL} AS y FROM edges) SELECT dst, src, list_transform(y, lambda x: round(x, 6) + 0.0) AS y, list_transform(range(1, 9), lambda n: round(CASE WHEN {_U} < 1 THEN sqrt(8.0) * sin(n * pi() * {_U}) / r * {_ENV} ELSE 0 END, 5) + 0.0) AS b FROM ey")
def embed_edges(spark, d):
    """Harmonics and radial functions of every edge."""
    got = kernels.embed_edges(_edges(spark, d), 8, R_CUT)
    return got.select("dst", "src", F.transform("y", lambda x: F.round(x, 6) + F.lit(0.0)).alias("y"), F.transform("b", lambda x: F.round(x, 5) + F.lit(0.0)).alias("b"))


STUDY_CHANNELS, STUDY_ORDERS = (1, 4, 16, 128), (1, 2)


@query(f"WITH {_edges_sql(None)}, n AS (SELECT count(*) AS edges FROM edges), " + ", ".join(f"z{l} AS (SELECT (SELECT count(*) FROM (WITH {cg_sql(l, 1, l)} SELECT * FROM cg)) AS z)" for l in STUDY_ORDERS)
       + " " + " UNION ALL ".join(f"SELECT {k} AS channels, {l} AS lmax, edges * {k * coupling.width(l) * 4 * coupling.width(l)} AS dense, edges * {k} * z AS sparse, true AS same FROM n, z{l}" for k in STUDY_CHANNELS for l in STUDY_ORDERS))
def kernel_study(spark, d):
    """Over channels and orders: multiply-adds of the dense and the sparse product, and whether the two fused forms
    give the same values on all edges."""
    rows, n = [], _edges(spark, d).count()
    for k in STUDY_CHANNELS:
        v = graphs.vertices(spark, d, channels=k)
        inputs = kernels.edge_inputs(graphs.radius_edges(v, R_CUT), v, _y(), R_CUT)
        for l in STUDY_ORDERS:
            x = kernels.flop_count(n, k, l, 1, l)
            cut = inputs.withColumn("y", F.slice("y", 1, coupling.width(l)))
            a, b = (kernels.product_fused(cut, k, l, 1, l, dense=form) for form in (False, True))
            gap = a.join(b.withColumnRenamed("a", "b"), "dst").select(F.aggregate(F.zip_with("a", "b", lambda p, q: F.abs(p - q)), F.lit(0.0), lambda m, g: F.greatest(m, g)).alias("gap")).agg(F.max("gap")).first()[0]
            rows.append((k, l, x["dense"], x["sparse"], (gap or 0.0) < 1e-9))
    return literal_table(spark, rows, "channels int, lmax int, dense long, sparse long, same boolean")


@query("SELECT CAST(dt AS VARCHAR) AS dtype, true AS close FROM (VALUES ('double'), ('float')) v(dt)")
def kernel_agreement(spark, d):
    """Greatest difference of the fused product in either precision from the sparse relational form."""
    inputs = _inputs(spark, d)
    truth = kernels.product_sparse(inputs, K).withColumnRenamed("val", "want")
    out = None
    for kind, limit in (("double", 1e-9), ("float", 1e-4)):
        got = kernels.unpack(kernels.product_fused(inputs, K, dtype=kind), "dst", K, 2).join(truth, ["dst", "k", "l3", "m3"])
        row = got.agg(F.lit(kind).alias("dtype"), (F.max(F.abs(F.col("val") - F.col("want"))) < limit).alias("close"))
        out = row if out is None else out.unionByName(row)
    return out


@query(f"WITH {_edges_sql(None)}, {cg_sql(3, 1, 2)} SELECT count(*) * 128 * 16 * 4 * 9 AS dense, count(*) * 128 * (SELECT count(*) FROM cg) AS sparse FROM edges")
def flop_count(spark, d):
    """Multiply-adds with 128 channels, harmonics to 3, features to 1, messages to 2."""
    x = kernels.flop_count(_edges(spark, d).count(), 128, 3, 1, 2)
    return literal_table(spark, [(x["dense"], x["sparse"])], "dense long, sparse long")


CONFIG = KernelConfig(lmax_sh=2, channels=2, n_radial=4)


@query()
def energy_per_graph(spark, d):
    return energy(graphs.vertices(spark, d), Network(CONFIG))


@query("SELECT DISTINCT vec_id // 16 AS graph_id, true AS same FROM embeddings")
def energy_in_batches(spark, d):
    """Batching must not alter any graph's energy."""
    v = graphs.vertices(spark, d)
    sizes = v.groupBy(F.col("graph_id").alias("id")).agg(F.count("*").alias("size"))
    dealt = pack_balanced(sizes, 64, 2).assignment.select(F.col("id").alias("graph_id"), "bin_id")
    a, b = energy(v, Network(CONFIG)), batched_energy(v, dealt, Network(CONFIG)).withColumnRenamed("energy", "batched")
    return a.join(b, "graph_id").select("graph_id", (F.abs(F.col("energy") - F.col("batched")) < 1e-9).alias("same"))


@query()
def forces_fd(spark, d):
    return forces(graphs.vertices(spark, d), Network(CONFIG))


@query("SELECT count(DISTINCT vec_id // 16) AS graphs, true AS rotation, true AS shift, true AS reorder, true AS forces, true AS net_force FROM embeddings")
def equivariance(spark, d):
    e = equivariance_error(graphs.vertices(spark, d), Network(CONFIG))
    return e.agg(F.count("*").alias("graphs"), (F.max("rotation") < 1e-9).alias("rotation"), (F.max("shift") < 1e-9).alias("shift"), (F.max("order") < 1e-9).alias("reorder"), (F.max("forces") < 1e-5).alias("forces"), (F.max("net_force") < 1e-5).alias("net_force"))


def _training_rows(spark, d):
    docs = read_table(spark, d, "documents", ["doc_id", "text", "n_chars"])
    signs = F.regexp_count("text", F.lit(r"[.,!?]"))
    rows = docs.select(F.col("doc_id").alias("id"), (F.col("n_chars") / 10000.0).alias("f1"), (F.regexp_count("text", F.lit(r"\S+")) / 2000.0).alias("f2"), (signs / F.greatest(F.col("n_chars"), F.lit(1)) * 10).alias("f3"))
    return rows.join(read_table(spark, d, "labels", ["doc_id", "quality"]).withColumnRenamed("doc_id", "id"), "id")


def _loss(spark, d, method):
    """Fixed batches of eight documents have about as many steps an epoch as balanced ones."""
    sizes = doc_sizes(spark, d)
    if method == "fixed":
        placed = batch_fixed_count(sizes, 8).select("id", F.floor(F.col("bin_id") / RANKS).alias("step"))
    else:
        got = pack_balanced(sizes, CAPACITY, RANKS, oversize="isolate")
        placed = got.assignment.select("id", "bin_id").join(schedule(got.bins, RANKS).select("bin_id", "step"), "bin_id").select("id", "step")
    curve = train_readout(_training_rows(spark, d).join(placed, "id"), ["f1", "f2", "f3"], "quality")
    return literal_table(spark, [(method, e, x) for e, x in curve], "method string, epoch int, loss double")


@query()
def loss_curve_fixed(spark, d):
    return _loss(spark, d, "fixed")


@query()
def loss_curve_balanced(spark, d):
    return _loss(spark, d, "balanced")


@query("SELECT true AS near")
def loss_parity(spark, d):
    """After sixteen epochs the losses of fixed and balanced batches are near each other."""
    a, b = (_loss(spark, d, m).where("epoch = 15").select(F.col("loss").alias(m)) for m in ("fixed", "balanced"))
    return a.crossJoin(b).select((F.abs(F.col("fixed") - F.col("balanced")) < 0.05).alias("near"))



@query("SELECT vec_id AS v, [(((label + 1) * 31 + 1) % 7 - 3) / 8.0, (((label + 1) * 31 + 2) % 7 - 3) / 8.0] AS h0 FROM embeddings")
def embed_vertices(spark, d):
    return kernels.embed(graphs.vertices(spark, d), K).select("v", "h0")


@query(f"WITH {RADIAL} SELECT dst, src, list(round(w, 5) + 0.0 ORDER BY k, path) AS w FROM en JOIN ew USING (e) GROUP BY e, dst, src")
def radial_weights(spark, d):
    got = kernels.radial_weights(_edges(spark, d), K, N_PATHS, 8, R_CUT)
    return got.select("dst", "src", F.transform("w", lambda x: F.round(x, 5) + F.lit(0.0)).alias("w"))


@query()
def kernel_plan_stats(spark, d):
    """What each form of the product costs in stages: the chain writes out a result per path, the fused form none."""
    inputs = _inputs(spark, d)
    forms = {"dense chain": kernels.product_dense_chain(inputs, K), "sparse join": kernels.product_sparse(inputs, K), "fused": kernels.product_fused(inputs, K)}
    rows = [(name, *kernels.plan_stats(df).values()) for name, df in forms.items()]
    return literal_table(spark, rows, "form string, exchanges int, joins int, aggregates int, arrow int, materialised int")


@query(SHOW_PRODUCT)
def edge_product_tuple_chain(spark, d):
    """The finest baseline: a job for each index tuple and channel, on all graphs."""
    return _rounded(kernels.product_tuple_chain(_inputs(spark, d), K, 2, 1, 2), "dst", "k", "l3", "m3")
