"""Building, profiling and batching of graphs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import read_table


def vertices(spark: SparkSession, sf_dir: str, group: int = 16, channels: int = 1) -> DataFrame:
    """(graph_id, v, z, x, y, zc, h): sixteen vectors are a graph; position, species and features are taken from them.
    h is flat: for each channel one scalar and a vector of three; many channels go round the vector again."""
    e = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding", "label"])
    at = lambda i: F.get("embedding", F.lit(i)).cast("double")
    h = F.array(*[at(3 + (4 * k + m) % 61) for k in range(channels) for m in range(4)])
    return e.select(F.floor(F.col("vec_id") / group).alias("graph_id"), F.col("vec_id").alias("v"), F.col("label").alias("z"), at(0).alias("x"), at(1).alias("y"), at(2).alias("zc"), h.alias("h"))


def radius_edges(v: DataFrame, r_cut: float, box: tuple[float, float, float] | None = None, cells: bool = False) -> DataFrame:
    """Directed edges dst <- src up to the cutoff, both ways, with displacement dst - src and length.

    One equi-join on the graph with the distance as residual. With cells the key also has the cell of the cutoff's
    size, and a vertex meets only the 27 cells around its own: for graphs of many vertices. With box, periodic images
    of the sender count, as many shells as the cutoff needs; a vertex may meet its own images.
    """
    a = v.select("graph_id", F.col("v").alias("dst"), F.col("x").alias("ax"), F.col("y").alias("ay"), F.col("zc").alias("az"))
    b = v.select("graph_id", F.col("v").alias("src"), F.col("x").alias("bx"), F.col("y").alias("by"), F.col("zc").alias("bz"))
    if box is None:
        b = b.select("*", *[F.lit(0).alias(c) for c in ("sx", "sy", "sz")])
    else:
        for c, axis, side in zip(("sx", "sy", "sz"), ("bx", "by", "bz"), box):
            n = -(-r_cut // side) if r_cut > side else 1
            b = b.withColumn(c, F.explode(F.sequence(F.lit(-int(n)), F.lit(int(n))))).withColumn(axis, F.col(axis) + F.col(c) * side)
    keys = ["graph_id"]
    if cells:
        cell = lambda c: F.floor(F.col(c) / r_cut)
        a = a.withColumns({"cx": cell("ax"), "cy": cell("ay"), "cz": cell("az")})
        for c, axis in (("cx", "bx"), ("cy", "by"), ("cz", "bz")):
            b = b.withColumn(c, F.explode(F.sequence(cell(axis) - 1, cell(axis) + 1)))
        keys += ["cx", "cy", "cz"]
    pairs = a.join(b, keys).withColumns({"dx": F.col("ax") - F.col("bx"), "dy": F.col("ay") - F.col("by"), "dz": F.col("az") - F.col("bz")})
    square = F.col("dx") * F.col("dx") + F.col("dy") * F.col("dy") + F.col("dz") * F.col("dz")
    self_edge = (F.col("dst") == F.col("src")) & (F.col("sx") == 0) & (F.col("sy") == 0) & (F.col("sz") == 0)
    return pairs.where((square <= r_cut * r_cut) & ~self_edge).select("graph_id", "dst", "src", "sx", "sy", "sz", "dx", "dy", "dz", F.sqrt(square).alias("r"))


def aggregate_neighbors(edges: DataFrame, states: DataFrame, message: Column, ops: dict[str, str], empty: float | None = 0.0) -> DataFrame:
    """(graph_id, v, one column an operation): messages over a vertex' incoming edges, aggregated by each of ops (a name
    to sum, mean, max, min or count). message may use the edge's columns and those of its sender in states (graph_id, v,
    ..). Vertices without neighbours have empty. One join on the sender, one grouped sum on the receiver."""
    known = {"sum": F.sum, "mean": F.avg, "max": F.max, "min": F.min, "count": F.count}
    sent = edges.join(states.withColumnRenamed("v", "src"), ["graph_id", "src"]).select("graph_id", F.col("dst").alias("v"), message.alias("_message"))
    got = sent.groupBy("graph_id", "v").agg(*[known[op]("_message").cast("double").alias(name) for name, op in ops.items()])
    rows = states.select("graph_id", "v").join(got, ["graph_id", "v"], "left")
    return rows.select("graph_id", "v", *[F.coalesce(n, F.lit(0.0 if ops[n] == "count" else empty)).alias(n) for n in ops])


def profile_of_counts(counts: DataFrame) -> DataFrame:
    """Density and sparsity of (graph_id, n_vertices, n_edges); null for single vertices."""
    pairs = F.col("n_vertices") * (F.col("n_vertices") - 1)
    density = F.when(F.col("n_vertices") > 1, F.col("n_edges") / pairs)
    return counts.select("graph_id", "n_vertices", "n_edges", F.round(density, 6).alias("density"), F.round(1 - density, 6).alias("sparsity"))


def graph_profile(edges: DataFrame, v: DataFrame) -> DataFrame:
    n = v.groupBy("graph_id").agg(F.count("*").alias("n_vertices"))
    m = edges.groupBy("graph_id").agg(F.count("*").alias("n_edges"))
    return profile_of_counts(n.join(m, "graph_id", "left").select("graph_id", "n_vertices", F.coalesce("n_edges", F.lit(0)).alias("n_edges")))


def histogram(df: DataFrame, column: str, keys: list[str], per_decade: int = 4) -> DataFrame:
    """Counts in logarithmic buckets."""
    return df.groupBy(*keys, F.floor(F.log10(F.greatest(F.col(column), F.lit(1))) * per_decade).alias("bucket")).agg(F.count("*").alias("graphs"))


def corpus_table(graphs: DataFrame) -> DataFrame:
    """Graphs, share and size range of each source."""
    n = graphs.groupBy("source").agg(F.count("*").alias("graphs"), F.min("n_vertices").alias("least"), F.max("n_vertices").alias("most"))
    whole = n.agg(F.sum("graphs").alias("whole"))
    return n.crossJoin(whole).select("source", "graphs", F.round(F.col("graphs") * 100.0 / F.col("whole"), 6).alias("share"), "least", "most")


def order_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    cols = ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice"]
    items = read_table(spark, sf_dir, "lineitem", ["l_orderkey", *cols])
    return items.select(F.col("l_orderkey").alias("graph_id"), F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*cols)).alias("v"), "l_shipdate")


def order_edges(spark: SparkSession, sf_dir: str, days: int = 365) -> DataFrame:
    """Items of an order whose ship dates are near each other."""
    items = order_items(spark, sf_dir)
    a = items.select("graph_id", F.col("v").alias("dst"), F.col("l_shipdate").alias("at"))
    b = items.select("graph_id", F.col("v").alias("src"), F.col("l_shipdate").alias("bt"))
    return a.join(b, "graph_id").where((F.col("dst") != F.col("src")) & (F.abs(F.datediff("at", "bt")) <= days)).select("graph_id", "dst", "src")


def interval_edges(df: DataFrame, key: str, node: str, ts: str, seconds: int) -> DataFrame:
    """Pairs of rows of a key within a time span, both ways: an equi-join on buckets of that span."""
    micros = F.unix_micros(F.col(ts).cast("timestamp"))
    span = seconds * 1_000_000
    rows = df.select(key, node, micros.alias("t"))
    a = rows.select(key, F.col(node).alias("dst"), F.col("t").alias("ta"), F.floor(F.col("t") / span).alias("bucket"))
    b = rows.select(key, F.col(node).alias("src"), F.col("t").alias("tb"), F.explode(F.array(*[F.floor(F.col("t") / span) + k for k in (-1, 0, 1)])).alias("bucket"))
    return a.join(b, [key, "bucket"]).where((F.col("dst") != F.col("src")) & (F.abs(F.col("ta") - F.col("tb")) <= span)).select(key, "dst", "src")


def block_diagonal(assignment: DataFrame, v: DataFrame, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Vertices and edges of each bin with ids shifted, so that its graphs are blocks of one matrix. assignment:
    (graph_id, size, bin_id)."""
    before = Window.partitionBy("bin_id").orderBy("graph_id").rowsBetween(Window.unboundedPreceding, -1)
    first = assignment.select("graph_id", "bin_id", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("first"))
    placed = v.join(first, "graph_id").withColumn("k", F.col("first") + F.row_number().over(Window.partitionBy("graph_id").orderBy("v")) - 1)
    ids = placed.select("graph_id", "bin_id", "v", "k")
    moved = edges.join(ids.withColumnsRenamed({"v": "dst", "k": "new_dst"}), ["graph_id", "dst"]).join(ids.drop("bin_id").withColumnsRenamed({"v": "src", "k": "new_src"}), ["graph_id", "src"])
    return placed, moved.drop("dst", "src").withColumnsRenamed({"new_dst": "dst", "new_src": "src"})


def padded(assignment: DataFrame, capacity: int) -> DataFrame:
    """A row a bin with its dense token mask: ones for tokens, zeros up to the capacity."""
    filled = assignment.groupBy("bin_id").agg(F.sum("size").cast("long").alias("filled"))
    pad = F.greatest(F.lit(capacity).cast("long") - F.col("filled"), F.lit(0).cast("long"))
    return filled.select("bin_id", "filled", pad.alias("padded"), F.concat(F.array_repeat(F.lit(1), F.col("filled").cast("int")), F.array_repeat(F.lit(0), pad.cast("int"))).alias("mask"))
