"""The experiment workloads on the given tables: packing, scaling, capacity, graphs. Each query takes (spark, sf_dir);
ORACLES has the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import packing_sql
from .operators import graphs, measures
from .operators.packing import apply_oversize, batch_fixed_count, block_of_epoch, pack_balanced, pack_balanced_by, pack_cyclic, pack_sequential, pack_snake, portable_hash, schedule, size_histogram, with_global_rank
from .plans.packing import bin_count
from .sources.tables import SOURCES, doc_sizes, graph_size, literal_table, mixed_graphs, read_table, source_graphs, stored, synthetic_sizes

CAPACITY, RANKS = 3072, 8
#: A capacity that every graph of the corpus fits.
WIDE_CAPACITY = 24_576
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

DOCS = r"docs AS (SELECT doc_id AS id, CAST(coalesce(len(regexp_extract_all(text, '\S+')), 0) AS BIGINT) AS size FROM documents)"
FIT = DOCS + ", fit AS (SELECT * FROM docs)"  # all documents: rules that ignore the capacity deal them too
MIXED = r"""orders_g AS (SELECT l_orderkey AS k, count(*) AS n FROM lineitem GROUP BY 1), mixed AS (
    SELECT 'orders' AS source, k AS graph_id, n AS n_vertices FROM orders_g
    UNION ALL SELECT 'parts', l_partkey, count(*) FROM lineitem GROUP BY 2
    UNION ALL SELECT 'customers', o_custkey, CAST(sum(n) AS BIGINT) FROM orders JOIN orders_g ON k = o_orderkey GROUP BY 2
    UNION ALL SELECT 'suppliers', l_suppkey, count(*) FROM lineitem GROUP BY 2
    UNION ALL SELECT 'documents', doc_id, CAST(coalesce(len(regexp_extract_all(text, '\S+')), 0) AS BIGINT) FROM documents
    UNION ALL SELECT 'pages', page_id, CAST(length(html) - length(replace(html, '<', '')) AS BIGINT) FROM pages
    UNION ALL SELECT 'users', user_id, count(*) FROM events GROUP BY 2
    UNION ALL SELECT 'conversations', conv_id, count(*) FROM conversations GROUP BY 2)"""


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


BALANCED = f"WITH RECURSIVE {DOCS}, {packing_sql.balanced('docs', CAPACITY, RANKS)}"
_BY_SOURCE = ", ".join(f"{x} AS (SELECT graph_id AS id, CAST(n_vertices AS BIGINT) AS size FROM mixed WHERE source = '{x}'), {packing_sql.balanced(x, WIDE_CAPACITY, RANKS, isolate=False, prefix=x + '_')}" for x in SOURCES)


def summary_sql(capacity: int = CAPACITY, loads: str = "loads") -> str:
    c = capacity
    return f"""SELECT count(*) AS n_bins, count_if(n_items > 0) AS n_bins_used, CAST(sum(n_items) AS BIGINT) AS n_items, CAST(sum(load) AS BIGINT) AS total_load, round(CAST(sum(sum_sq) AS DOUBLE) / {c * c}, 6) AS area_fill,
    CAST(count(*) * {c} - sum(load) AS BIGINT) AS pad_tokens, CAST(count(*) * {c * c} - sum(sum_sq) AS BIGINT) AS pad_area, max(sum_sq) - min(sum_sq) AS spread_area, max(load) - min(load) AS spread_tokens, count_if(load > {c}) AS over_capacity FROM {loads}"""


# --- packing ---------------------------------------------------------------------------------------------------------


@query(f"{BALANCED} SELECT bin_id, load, n_items, sum_sq, is_oversize, bin_id // {RANKS} AS step, CAST(bin_id % {RANKS} AS INTEGER) AS rank FROM bins")
def pack_balanced_docs(spark, d):
    """Bins, steps and ranks of the documents, larger ones on their own."""
    got = pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate")
    return schedule(got.bins, RANKS)


@query(f"{BALANCED} SELECT id, size, bin_id, level, lap FROM packed")
def pack_assignment_docs(spark, d):
    return pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate").assignment.select("id", "size", "bin_id", "level", "lap")


def _packed_mixed(spark, d):
    graphs_ = mixed_graphs(spark, d).select(F.struct("source", "graph_id").alias("id"), F.col("n_vertices").alias("size"))
    return pack_balanced(graphs_, CAPACITY, RANKS, oversize="isolate")


@query(f"WITH RECURSIVE {MIXED}, items AS (SELECT {{'s': source, 'g': graph_id}} AS id, CAST(n_vertices AS BIGINT) AS size FROM mixed), {packing_sql.balanced('items', CAPACITY, RANKS)} SELECT id.s AS source, id.g AS graph_id, size, bin_id FROM packed")
def pack_balanced_mixed(spark, d):
    return _packed_mixed(spark, d).assignment.select("id.source", "id.graph_id", "size", "bin_id")


@query(f"""WITH {DOCS} SELECT count(*) AS items, CAST(sum(size) AS BIGINT) AS tokens, CAST(sum(size * size) AS BIGINT) AS squares, CAST(0 AS BIGINT) AS over_capacity,
    CAST(0 AS BIGINT) AS not_once, CAST(0 AS BIGINT) AS off_multiple, true AS enough_bins FROM docs""")
def pack_summary_balanced(spark, d):
    """What must hold of every packing: all items once, nothing over capacity but what lies alone, bins a multiple of the ranks."""
    items = doc_sizes(spark, d)
    got = pack_balanced(items, CAPACITY, RANKS, oversize="isolate")
    bad = measures.check_partition(items, got.assignment).agg(F.count("*").alias("not_once"))
    return got.bins.agg(
        F.sum("n_items").cast("long").alias("items"), F.sum("load").cast("long").alias("tokens"), F.sum("sum_sq").cast("long").alias("squares"), F.count_if((F.col("load") > CAPACITY) & ~F.col("is_oversize")).alias("over_capacity"),
        (F.count("*") % RANKS).alias("off_multiple"), (F.count("*") >= F.ceil(F.sum(F.least("load", F.lit(CAPACITY))) / CAPACITY)).alias("enough_bins"),
    ).crossJoin(bad)


@query(f"{BALANCED} {summary_sql(loads='bins')}")
def pack_objectives_balanced(spark, d):
    return measures.pack_summary(pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate").bins, CAPACITY)


@query(f"{BALANCED} SELECT level, lap, placed, marked, reactivated, active FROM laps")
def pack_trace(spark, d):
    """Laps: items placed, bins marked full, second chances, levels of recursion."""
    trace = pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate").trace
    return literal_table(spark, [tuple(int(t[k]) for k in ("level", "lap", "placed", "marked", "reactivated", "active")) for t in trace], "level long, lap long, placed long, marked long, reactivated long, active long")


@query(f"{BALANCED} SELECT id, size, bin_id FROM packed")
def pack_local_docs(spark, d):
    return pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate", strategy="local").assignment.select("id", "size", "bin_id")


@query(f"WITH {DOCS} SELECT id, size, true AS same FROM docs")
def pack_strategies_agree(spark, d):
    """The interval planner and the item-by-item reference give every item the same bin."""
    items = doc_sizes(spark, d)
    a = pack_balanced(items, CAPACITY, RANKS, oversize="isolate").assignment.select("id", "size", F.col("bin_id").alias("a"))
    b = pack_balanced(items, CAPACITY, RANKS, oversize="isolate", strategy="local").assignment.select("id", F.col("bin_id").alias("b"))
    return a.join(b, "id").select("id", "size", (F.col("a") == F.col("b")).alias("same"))


@query(f"{BALANCED} SELECT id, size, bin_id FROM packed")
def pack_rounds_docs(spark, d):
    return pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate", strategy="rounds").assignment.select("id", "size", "bin_id")


@query(f"WITH RECURSIVE {DOCS}, ranked AS (SELECT id, size, row_number() OVER (ORDER BY size DESC, id) - 1 AS place FROM docs WHERE size <= {CAPACITY}), " + ", ".join(f"i{x} AS (SELECT id, size FROM ranked WHERE place % 4 = {x}), {packing_sql.balanced(f'i{x}', CAPACITY, RANKS, isolate=False, prefix=f's{x}_')}" for x in range(4))
    + ", own AS (" + " UNION ALL ".join(f"SELECT load, n_items, sum_sq FROM s{x}_bins" for x in range(4)) + f" UNION ALL SELECT size, 1, size * size FROM docs WHERE size > {CAPACITY}), loads AS (SELECT * FROM own UNION ALL SELECT 0, 0, 0 FROM (SELECT unnest(range(({RANKS} - n % {RANKS}) % {RANKS})) FROM (SELECT count(*) AS n FROM own))) {summary_sql()}")
def pack_sharded_docs(spark, d):
    return measures.pack_summary(pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate", strategy="sharded", shards=4).bins, CAPACITY)


@query(f"WITH RECURSIVE {DOCS}, {packing_sql.balanced('docs', CAPACITY, RANKS, reactivate=False)} {summary_sql(loads='bins')}")
def pack_no_reactivate(spark, d):
    return measures.pack_summary(pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate", reactivate=False).bins, CAPACITY)


@query(f"WITH RECURSIVE {DOCS}, {packing_sql.balanced('docs', CAPACITY, RANKS, recursive=False)} SELECT count(*) AS items, count_if(bin_id IS NULL) AS unassigned FROM packed")
def pack_no_recursion(spark, d):
    got = pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate", recursive=False)
    return got.assignment.agg(F.count("*").alias("items"), F.count_if(F.col("bin_id").isNull()).alias("unassigned"))


@query()
def pack_fullest_first(spark, d):
    return measures.pack_summary(pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate", strategy="local", bin_order="fullest_first").bins, CAPACITY)


@query()
def pack_epoch_shuffled(spark, d):
    """An epoch's steps, shuffled with the epoch's seed: the same on every process."""
    got = pack_balanced(doc_sizes(spark, d), CAPACITY, RANKS, oversize="isolate", seed=5)
    return schedule(got.bins, RANKS, "shuffled", 5)


@query(f"WITH RECURSIVE {MIXED}, {_BY_SOURCE} " + " UNION ALL ".join(f"SELECT '{x}' AS source, count(DISTINCT bin_id) AS bins, CAST(sum(size) AS BIGINT) AS tokens FROM {x}_packed" for x in SOURCES))
def pack_bins_per_source(spark, d):
    sized = mixed_graphs(spark, d).select("source", F.col("graph_id").alias("id"), F.col("n_vertices").cast("long").alias("size"))
    return pack_balanced_by(sized, ["source"], WIDE_CAPACITY, RANKS).groupBy("source").agg(F.countDistinct("bin_id").alias("bins"), F.sum("size").alias("tokens"))


@query(f"WITH {FIT} SELECT CAST(sum(size) AS BIGINT) AS tokens, CAST((CAST(sum(size) AS BIGINT) + {CAPACITY - 1}) // {CAPACITY} AS BIGINT) AS lower_bound, CAST(((CAST(sum(size) AS BIGINT) + {CAPACITY - 1}) // {CAPACITY} + {RANKS - 1}) // {RANKS} * {RANKS} AS BIGINT) AS bins FROM fit")
def bin_count_docs(spark, d):
    total = doc_sizes(spark, d).agg(F.sum("size")).first()[0] or 0
    return literal_table(spark, [(total, -(-total // CAPACITY), bin_count(total, CAPACITY, RANKS))], "tokens long, lower_bound long, bins long")


@query(f"WITH {DOCS} SELECT max(size) AS lower, CAST(800 AS BIGINT) AS saturation, CAST(4000 AS BIGINT) AS upper, max(size) <= 4000 AS fits FROM docs")
def capacity_bounds(spark, d):
    return measures.capacity_bounds(doc_sizes(spark, d)).select("lower", "saturation", F.col("upper").cast("long"), "fits")


@query(f"WITH {DOCS} SELECT id, size FROM docs WHERE size > {CAPACITY}")
def oversize_isolate(spark, d):
    return apply_oversize(doc_sizes(spark, d), CAPACITY, "isolate")[1]


@query(f"""WITH {DOCS} SELECT id, least({CAPACITY}, size - c * {CAPACITY}) AS size, CAST(c AS INTEGER) AS chunk FROM docs, unnest(range(0, (size + {CAPACITY - 1}) // {CAPACITY})) AS u(c) WHERE size > {CAPACITY}
    UNION ALL SELECT id, size, 0 FROM docs WHERE size <= {CAPACITY}""")
def oversize_split(spark, d):
    return apply_oversize(doc_sizes(spark, d), CAPACITY, "split")[0]


@query(f"WITH {DOCS} SELECT size, count(*) AS items FROM docs GROUP BY size")
def size_histogram_docs(spark, d):
    return size_histogram(doc_sizes(spark, d))


@query(f"WITH {DOCS} SELECT id, size, row_number() OVER (ORDER BY size DESC, id) - 1 AS place FROM docs")
def global_rank_docs(spark, d):
    return with_global_rank(doc_sizes(spark, d), [F.col("size").desc(), F.col("id").asc()])


# --- comparators -----------------------------------------------------------------------------------------------------


def _fixed(n: int) -> str:
    return f"{DOCS}, placed AS (SELECT size, (row_number() OVER (ORDER BY id) - 1) // {n} AS bin_id FROM docs), bins AS (SELECT bin_id, CAST(sum(size) AS BIGINT) AS load, count(*) AS n_items, CAST(sum(size * size) AS BIGINT) AS sum_sq FROM placed GROUP BY bin_id)"


def _add_fixed(n: int) -> None:
    def run(spark, d):
        return measures.bin_loads(batch_fixed_count(doc_sizes(spark, d), n))

    run.__name__ = f"batch_fixed{n}"
    query(f"WITH {_fixed(n)} SELECT * FROM bins")(run)


for _n in (4, 5, 6, 8):
    _add_fixed(_n)


@query(f"WITH {DOCS}, placed AS (SELECT size, (row_number() OVER (ORDER BY (id + 7) * 2654435761 % 4294967296, id) - 1) // 4 AS bin_id FROM docs) SELECT bin_id, CAST(sum(size) AS BIGINT) AS load, count(*) AS n_items, CAST(sum(size * size) AS BIGINT) AS sum_sq FROM placed GROUP BY bin_id")
def batch_fixed4_random(spark, d):
    return measures.bin_loads(batch_fixed_count(doc_sizes(spark, d), 4, "random", 7))


@query(f"""WITH {DOCS}, p AS (SELECT id, size, row_number() OVER (ORDER BY id) - 1 AS pl, count(*) OVER () AS n FROM docs),
    r AS (SELECT size, pl FROM p UNION ALL SELECT size, pl + n FROM p WHERE pl < (32 - n % 32) % 32) SELECT pl // 4 AS bin_id, CAST(sum(size) AS BIGINT) AS load, count(*) AS n_items, CAST(sum(size * size) AS BIGINT) AS sum_sq FROM r GROUP BY 1""")
def batch_fixed4_repeat_tail(spark, d):
    return measures.bin_loads(batch_fixed_count(doc_sizes(spark, d), 4, tail="repeat", ranks=8))


@query(f"""WITH {DOCS}, p AS (SELECT size, row_number() OVER (ORDER BY id) - 1 AS pl, count(*) OVER () AS n FROM docs) SELECT pl // 4 AS bin_id, CAST(sum(size) AS BIGINT) AS load, count(*) AS n_items, CAST(sum(size * size) AS BIGINT) AS sum_sq FROM p WHERE pl < n // 32 * 32 GROUP BY 1""")
def batch_fixed4_drop_tail(spark, d):
    return measures.bin_loads(batch_fixed_count(doc_sizes(spark, d), 4, tail="drop", ranks=8))


LONE = f"SELECT id, size, n + row_number() OVER (ORDER BY size DESC, id) - 1 AS bin_id FROM docs, (SELECT coalesce(max(bin_id) + 1, 0) AS n FROM dealt) WHERE size > {CAPACITY}"
ALL_LOADS = f"loads AS (SELECT bin_id, CAST(sum(size) AS BIGINT) AS load, count(*) AS n_items, CAST(sum(size * size) AS BIGINT) AS sum_sq FROM (SELECT * FROM dealt UNION ALL {LONE}) GROUP BY bin_id)"


def _greedy_sql(rule: str, decreasing: bool) -> str:
    return f"WITH RECURSIVE {DOCS}, small AS (SELECT * FROM docs WHERE size <= {CAPACITY}), {packing_sql.greedy('small', CAPACITY, rule, decreasing)}, {ALL_LOADS} SELECT * FROM loads"


def _sequential(spark, d, rule: str, decreasing: bool = False) -> DataFrame:
    """Bins of a sequential rule; documents over the capacity have bins of their own behind them."""
    fit, alone = apply_oversize(doc_sizes(spark, d), CAPACITY, "isolate")
    placed = pack_sequential(fit, rule, CAPACITY, decreasing=decreasing).select("id", "size", "bin_id")
    n = (placed.agg(F.max("bin_id")).first()[0] if placed.head(1) else -1) + 1
    lone = with_global_rank(alone, [F.col("size").desc(), F.col("id").asc()]).select("id", "size", (F.col("place") + n).alias("bin_id"))
    return placed.unionByName(lone)


@query(_greedy_sql("first", False))
def pack_first_fit(spark, d):
    return measures.bin_loads(_sequential(spark, d, "first"))


@query(_greedy_sql("first", True))
def pack_first_fit_decreasing(spark, d):
    return measures.bin_loads(_sequential(spark, d, "first", decreasing=True))


@query(_greedy_sql("best", False))
def pack_best_fit(spark, d):
    return measures.bin_loads(_sequential(spark, d, "best"))


@query(_greedy_sql("best", True))
def pack_best_fit_decreasing(spark, d):
    return measures.bin_loads(_sequential(spark, d, "best", decreasing=True))


@query(f"""WITH RECURSIVE {DOCS}, o AS (SELECT id, size, row_number() OVER (ORDER BY id) AS n FROM docs WHERE size <= {CAPACITY}),
    w AS (SELECT n, id, size, CAST(0 AS BIGINT) AS bin_id, size AS filled FROM o WHERE n = 1 UNION ALL
      SELECT o.n, o.id, o.size, CASE WHEN filled + o.size <= {CAPACITY} THEN bin_id ELSE bin_id + 1 END, CASE WHEN filled + o.size <= {CAPACITY} THEN filled + o.size ELSE o.size END FROM w JOIN o ON o.n = w.n + 1),
    dealt AS (SELECT id, size, bin_id FROM w) SELECT * FROM dealt UNION ALL {LONE}""")
def pack_next_fit(spark, d):
    return _sequential(spark, d, "next")


@query(f"WITH RECURSIVE {DOCS}, {packing_sql.emptiest('docs', 64)} SELECT bin_id, CAST(sum(size) AS BIGINT) AS load, count(*) AS n_items, CAST(sum(size * size) AS BIGINT) AS sum_sq FROM dealt GROUP BY bin_id")
def pack_fixed_bins(spark, d):
    """Largest to the emptiest of 64 bins."""
    return measures.bin_loads(pack_sequential(doc_sizes(spark, d), "fixed", bins=64))


BINS = f"bins_n AS (SELECT CAST(((CAST(sum(size) AS BIGINT) + {CAPACITY - 1}) // {CAPACITY} + {RANKS - 1}) // {RANKS} * {RANKS} AS BIGINT) AS m FROM fit), ranked AS (SELECT id, size, row_number() OVER (ORDER BY size DESC, id) - 1 AS place FROM fit)"
CYCLIC = f"{FIT}, {BINS}, dealt AS (SELECT id, size, place, place % m AS bin_id FROM ranked, bins_n)"
SNAKE = f"{FIT}, {BINS}, dealt AS (SELECT id, size, place, CASE WHEN (place // m) % 2 = 0 THEN place % m ELSE m - 1 - place % m END AS bin_id FROM ranked, bins_n)"
LOADS = "loads AS (SELECT bin_id, CAST(sum(size) AS BIGINT) AS load, count(*) AS n_items, CAST(sum(size * size) AS BIGINT) AS sum_sq FROM dealt GROUP BY bin_id)"
SUMMARY = summary_sql()


def _m(spark, d) -> tuple[DataFrame, int]:
    items = doc_sizes(spark, d)
    return items, bin_count(items.agg(F.sum("size")).first()[0] or 0, CAPACITY, RANKS)


@query(f"WITH {CYCLIC} SELECT * FROM dealt")
def pack_cyclic_docs(spark, d):
    return pack_cyclic(*_m(spark, d))


@query(f"WITH {SNAKE} SELECT * FROM dealt")
def pack_snake_docs(spark, d):
    return pack_snake(*_m(spark, d))


@query(f"WITH {CYCLIC}, {LOADS} {SUMMARY}")
def objectives_cyclic(spark, d):
    return measures.pack_summary(measures.bin_loads(pack_cyclic(*_m(spark, d))), CAPACITY)


@query(f"WITH {SNAKE}, {LOADS} {SUMMARY}")
def objectives_snake(spark, d):
    return measures.pack_summary(measures.bin_loads(pack_snake(*_m(spark, d))), CAPACITY)


@query(f"WITH {CYCLIC}, {LOADS} SELECT bin_id, load FROM loads WHERE load > {CAPACITY}")
def capacity_violations_cyclic(spark, d):
    return measures.check_capacity(measures.bin_loads(pack_cyclic(*_m(spark, d))).withColumn("is_oversize", F.lit(False)), CAPACITY).select("bin_id", "load")


@query(f"WITH {CYCLIC} SELECT bin_id, list_sort(list(id)) AS members, CAST(sum(size) AS BIGINT) AS load FROM dealt GROUP BY bin_id")
def bin_manifest_cyclic(spark, d):
    return pack_cyclic(*_m(spark, d)).groupBy("bin_id").agg(F.array_sort(F.collect_list("id")).alias("members"), F.sum("size").alias("load"))


# --- loads, time, scaling --------------------------------------------------------------------------------------------


def _fixed_scheduled(spark, d, n=4, ranks=RANKS):
    return measures.on_ranks(measures.bin_loads(batch_fixed_count(doc_sizes(spark, d), n)), ranks)


STEPS = f"WITH {_fixed(4)}, sched AS (SELECT *, bin_id // {RANKS} AS step, CAST(bin_id % {RANKS} AS INTEGER) AS rank FROM bins)"
TIME = f"SELECT count(*) AS n_steps, CAST(sum(slowest) AS DOUBLE) AS epoch_cost, round(any_value(total) / {RANKS}, 6) AS ideal_cost, round(sum(slowest) / (any_value(total) / {RANKS}), 6) AS ratio FROM (SELECT max(load) AS slowest FROM sched GROUP BY step), (SELECT CAST(sum(load) AS DOUBLE) AS total FROM sched)"


EVEN = f"{BALANCED}, {packing_sql.on_ranks('bins', RANKS)}"


@query(f"{STEPS} SELECT rank, CAST(sum(load) AS BIGINT) AS tokens, count(*) AS n_batches FROM sched GROUP BY rank")
def rank_loads_fixed(spark, d):
    return measures.rank_loads(_fixed_scheduled(spark, d))


@query(f"{EVEN} SELECT rank, CAST(sum(load) AS BIGINT) AS tokens, count(*) AS n_batches FROM sched GROUP BY rank")
def rank_loads_balanced(spark, d):
    return measures.rank_loads(pack_balanced_docs(spark, d))


@query(f"{STEPS} SELECT step, max(load) AS max_load, round(max(load) / (sum(load) / {RANKS}), 6) AS ratio, arg_max(rank, load * 1000 - rank) AS straggler FROM sched GROUP BY step")
def straggler_fixed(spark, d):
    return measures.straggler_ratio(_fixed_scheduled(spark, d), RANKS)


@query(f"{EVEN} SELECT step, max(load) AS max_load, round(max(load) / (sum(load) / {RANKS}), 6) AS ratio, arg_max(rank, load * 1000 - rank) AS straggler FROM sched GROUP BY step")
def straggler_balanced(spark, d):
    return measures.straggler_ratio(pack_balanced_docs(spark, d), RANKS)


@query(f"{STEPS} {TIME}")
def epoch_cost_fixed(spark, d):
    return measures.epoch_time(_fixed_scheduled(spark, d), RANKS)


@query(f"{EVEN} {TIME}")
def epoch_cost_balanced(spark, d):
    return measures.epoch_time(pack_balanced_docs(spark, d), RANKS)


@query(f"{STEPS}, slow AS (SELECT step, max(load) AS slowest FROM sched GROUP BY step) SELECT rank, CAST(sum(load - least(load, 2) * 0.5) AS DOUBLE) AS computation, CAST(sum(2.0 - least(load, 2) * 0.5) AS DOUBLE) AS communication, CAST(sum(least(load, 2) * 0.5) AS DOUBLE) AS overlap, CAST(sum(slowest - load) AS BIGINT) AS idle FROM sched JOIN slow USING (step) GROUP BY rank")
def comm_profile_fixed(spark, d):
    return measures.profile(_fixed_scheduled(spark, d))


@query(f"{EVEN}, slow AS (SELECT step, max(load) AS slowest FROM sched GROUP BY step) SELECT rank, CAST(sum(load - least(load, 2) * 0.5) AS DOUBLE) AS computation, CAST(sum(2.0 - least(load, 2) * 0.5) AS DOUBLE) AS communication, CAST(sum(least(load, 2) * 0.5) AS DOUBLE) AS overlap, CAST(sum(slowest - load) AS BIGINT) AS idle FROM sched JOIN slow USING (step) GROUP BY rank")
def comm_profile_balanced(spark, d):
    return measures.profile(pack_balanced_docs(spark, d))


FRACTIONS = (("small", 0.23), ("medium", 0.46), ("large", 1.0))


def _threshold(f: float) -> int:
    return int(f * (1 << 32))


def _subset(spark, d, fraction: float) -> DataFrame:
    """A nested subset of the graphs of all eight sources, by a hash; ids lie in the order of the hash, so that sources mix."""
    number = F.array_position(F.array(*map(F.lit, SOURCES)), F.col("source"))
    h = portable_hash(F.col("graph_id") * 8 + number, 1)
    items = mixed_graphs(spark, d).select(F.struct(h.alias("h"), "source", "graph_id").alias("id"), F.col("n_vertices").cast("long").alias("size"))
    return items if fraction >= 1 else items.where(F.col("id.h") < _threshold(fraction))


def _subset_sql(name: str, fraction: float) -> str:
    number = " ".join(f"WHEN '{x}' THEN {i}" for i, x in enumerate(SOURCES, 1))
    return f"{name} AS (SELECT * FROM (SELECT {{'h': (graph_id * 8 + CASE source {number} END + 1) * 2654435761 % 4294967296, 's': source, 'g': graph_id}} AS id, CAST(n_vertices AS BIGINT) AS size FROM mixed) WHERE id.h < {_threshold(fraction)})"


@query(f"WITH {DOCS} " + " UNION ALL ".join(f"SELECT '{n}' AS subset, count(*) AS items, CAST(sum(size) AS BIGINT) AS tokens FROM docs WHERE (id + 1) * 2654435761 % 4294967296 < {_threshold(f)}" for n, f in FRACTIONS))
def subset_nested(spark, d):
    items = doc_sizes(spark, d).withColumn("h", portable_hash(F.col("id"), 1))
    return items.select(F.explode(F.array(*[F.when(F.col("h") < _threshold(f), F.lit(n)) for n, f in FRACTIONS])).alias("subset"), "size").where("subset IS NOT NULL").groupBy("subset").agg(F.count("*").alias("items"), F.sum("size").alias("tokens"))


#: Graphs of a batch of the fixed count that scaling is compared with, and ranks of its runs.
FIXED, SCALES, SUBSET_RANKS = 6, (16, 32, 64, 128, 740), (16, 32, 64)


def _times(items: DataFrame, ranks: int) -> list[tuple[str, float]]:
    """Modelled epoch cost of batches of a fixed count and of balanced batches."""
    fixed = measures.epoch_time(measures.on_ranks(measures.bin_loads(batch_fixed_count(items, FIXED)), ranks), ranks).first()["epoch_cost"] or 0.0
    even = measures.epoch_time(schedule(pack_balanced(items, CAPACITY, ranks, oversize="isolate").bins, ranks), ranks).first()["epoch_cost"] or 0.0
    return [("original", fixed), ("balanced", even)]


def _times_sql(items: str, ranks: int) -> str:
    """CTEs whose last, {items}{ranks}_t, has the columns variant, epoch_cost: as _times()."""
    p = f"{items}{ranks}_"
    cost = lambda bins: f"(SELECT CAST(coalesce(sum(slowest), 0) AS DOUBLE) FROM (SELECT max(load) AS slowest FROM {bins} GROUP BY bin_id // {ranks}))"
    return f"""{packing_sql.balanced(items, CAPACITY, ranks, prefix=p)}, {p}f AS (SELECT bin_id, sum(size) AS load FROM (SELECT size, (row_number() OVER (ORDER BY id) - 1) // {FIXED} AS bin_id FROM {items}) GROUP BY bin_id),
    {p}t(variant, epoch_cost) AS (SELECT 'original', {cost(p + 'f')} UNION ALL SELECT 'balanced', {cost(p + 'bins')})"""


_ABLATION = f"WITH RECURSIVE {MIXED}, " + ", ".join(f"{_subset_sql(n, f)}, {_times_sql(n, r)}" for (n, f), r in zip(FRACTIONS, SUBSET_RANKS))
_STRONG = f"WITH RECURSIVE {MIXED}, {_subset_sql('whole', 1.0)}, least_bins AS (SELECT CAST(ceil(sum(size) / {float(CAPACITY)}) AS BIGINT) AS b FROM whole), " + ", ".join(_times_sql("whole", r) for r in SCALES)


@query(_ABLATION + " " + " UNION ALL ".join(f"SELECT '{n}' AS subset, {r} AS ranks, variant, epoch_cost, round((SELECT epoch_cost FROM {n}{r}_t WHERE variant = 'original') / epoch_cost, 6) AS speedup FROM {n}{r}_t" for (n, _), r in zip(FRACTIONS, SUBSET_RANKS)))
def ablation_epoch_cost(spark, d):
    """Modelled epoch cost with batches of a fixed count and with balanced ones, of three sizes of the mixed corpus on
    more and more ranks. What the kernels add is measured: ablation_measured."""
    rows = []
    for (name, f), ranks in zip(FRACTIONS, SUBSET_RANKS):
        times = _times(stored(_subset(spark, d, f), "subset"), ranks)
        rows += [(name, ranks, v, t, round(times[0][1] / t, 6) if t else None) for v, t in times]
    return literal_table(spark, rows, "subset string, ranks int, variant string, epoch_cost double, speedup double")


@query()
def ablation_measured(spark, d):
    """All four variants on the whole corpus: balancing as modelled, kernels by the times, measured here and now, of the
    dense chain and the fused product on the same edges. Times differ from run to run."""
    from .kernel_queries import kernel_seconds

    dense, fused = kernel_seconds(spark, d)
    (_, fixed), (_, even) = _times(stored(_subset(spark, d, 1.0), "subset"), SUBSET_RANKS[-1])
    rows = [("original", fixed), ("+balanced", even), ("+kernel", fixed * fused / dense), ("+both", even * fused / dense)]
    return literal_table(spark, [(v, t, fixed / t if t else None, dense, fused) for v, t in rows], "variant string, epoch_cost double, speedup double, dense_seconds double, fused_seconds double")


@query(_STRONG + " " + " UNION ALL ".join(f"SELECT {r} AS ranks, variant, epoch_cost, round(first / ({r} / {float(SCALES[0])} * epoch_cost) * 100, 6) AS efficiency FROM whole{r}_t JOIN (SELECT variant, epoch_cost AS first FROM whole{SCALES[0]}_t) USING (variant), least_bins WHERE {r} = {SCALES[0]} OR {r} <= b" for r in SCALES))
def strong_scaling(spark, d):
    """The whole mixed corpus on more and more ranks, as long as there is a batch for each, with efficiency against the
    fewest."""
    rows, first, items = [], {}, stored(_subset(spark, d, 1.0), "subset")
    most = -(-(items.agg(F.sum("size")).first()[0] or 0) // CAPACITY)
    for ranks in SCALES:
        if ranks != SCALES[0] and ranks > most:
            break
        for v, t in _times(items, ranks):
            first.setdefault(v, t)
            rows.append((ranks, v, t, round(first[v] / (ranks / SCALES[0] * t) * 100, 6) if t else None))
    return literal_table(spark, rows, "ranks int, variant string, epoch_cost double, efficiency double")


@query(_ABLATION + " " + " UNION ALL ".join(f"SELECT '{n}' AS subset, {r} AS ranks, variant, epoch_cost, round(first / epoch_cost * 100, 6) AS efficiency FROM {n}{r}_t JOIN (SELECT variant, epoch_cost AS first FROM {FRACTIONS[0][0]}{SUBSET_RANKS[0]}_t) USING (variant)" for (n, _), r in zip(FRACTIONS, SUBSET_RANKS)))
def weak_scaling(spark, d):
    """As many graphs a rank throughout."""
    rows, first = [], {}
    for (name, f), ranks in zip(FRACTIONS, SUBSET_RANKS):
        for v, t in _times(stored(_subset(spark, d, f), "subset"), ranks):
            first.setdefault(v, t)
            rows.append((name, ranks, v, t, round(first[v] / t * 100, 6) if t else None))
    return literal_table(spark, rows, "subset string, ranks int, variant string, epoch_cost double, efficiency double")


def _costs(items: DataFrame, *ranks: int) -> dict[int, dict[str, float]]:
    """As _times() for each number of ranks; the fixed batches are made once, and all loads written before they are used."""
    cost = lambda bins, r: measures.epoch_time(bins, r).first()["epoch_cost"] or 0.0
    fixed = stored(measures.bin_loads(batch_fixed_count(items, FIXED)), "fixed")
    even = {r: stored(pack_balanced(items, CAPACITY, r, oversize="isolate").bins, "even") for r in ranks}
    return {r: {"original": cost(measures.on_ranks(fixed, r), r), "balanced": cost(schedule(even[r], r), r)} for r in ranks}


def _compared_sql(*ranks: int) -> str:
    return f"WITH RECURSIVE {MIXED}, {_subset_sql('whole', 1.0)}, " + ", ".join(_times_sql("whole", r) for r in ranks)


#: Quoted efficiencies: run, its variant here, fewest and most ranks, their quoted times.
QUOTED_RUNS = (("strong both 16 to 740", "balanced", 16, 740, 80.0, 2.0), ("original 64 to 740", "original", 64, 740, 100.0, 12.0), ("both 64 to 740", "balanced", 64, 740, 18.0, 2.0))


@query(_compared_sql(16, 64, 740) + " " + " UNION ALL ".join(f"SELECT '{name}' AS run, round({t0} / (({float(p)} / {float(p0)}) * {t}) * 100.0, 6) AS efficiency, round(a.epoch_cost / (({float(p)} / {float(p0)}) * nullif(b.epoch_cost, 0)) * 100.0, 6) AS modelled FROM whole{p0}_t a JOIN whole{p}_t b USING (variant) WHERE variant = '{v}'" for name, v, p0, p, t0, t in QUOTED_RUNS))
def strong_efficiency_quoted(spark, d):
    """Efficiencies from quoted times, and beside each the modelled one of the mixed corpus on as many ranks. The model
    has no kernels: 'both' is balancing alone there."""
    costs = _costs(stored(_subset(spark, d, 1.0), "subset"), 16, 64, 740)
    rows = [(name, t0, float(p0), t, float(p), costs[p0][v], costs[p][v]) for name, v, p0, p, t0, t in QUOTED_RUNS]
    table = literal_table(spark, rows, "run string, t0 double, p0 double, t double, p double, c0 double, c double")
    e = lambda t0, t: F.round(measures.strong_efficiency(F.col(t0), F.col("p0"), t, F.col("p")), 6)
    return table.select("run", e("t0", F.col("t")).alias("efficiency"), e("c0", F.nullif("c", F.lit(0.0))).alias("modelled"))


#: Quoted epoch times of fixed batches and of all measures: ranks and both times.
QUOTED_TIMES = ((740, 12.0, 2.0), (64, 100.0, 18.0))


@query(_compared_sql(64, 740) + " " + " UNION ALL ".join(f"SELECT '{p} ranks' AS run, round({a} / {b}, 6) AS speedup, round(f.epoch_cost / nullif(e.epoch_cost, 0), 6) AS modelled FROM whole{p}_t f, whole{p}_t e WHERE f.variant = 'original' AND e.variant = 'balanced'" for p, a, b in QUOTED_TIMES))
def speedup_quoted(spark, d):
    """Speedups from quoted times, and beside each the modelled one of balancing the mixed corpus on as many ranks."""
    costs = _costs(stored(_subset(spark, d, 1.0), "subset"), 64, 740)
    rows = [(f"{p} ranks", a, b, costs[p]["original"], costs[p]["balanced"]) for p, a, b in QUOTED_TIMES]
    table = literal_table(spark, rows, "run string, a double, b double, fixed double, even double")
    return table.select("run", F.round(F.col("a") / F.col("b"), 6).alias("speedup"), F.round(F.col("fixed") / F.nullif("even", F.lit(0.0)), 6).alias("modelled"))


GRID_BATCHES = (1, 2, 4, 8, 16, 32, 64)


def _values(xs) -> str:
    return ", ".join(f"({x})" for x in xs)


_SIZES = f"{MIXED}, sizes AS (SELECT n_vertices AS size, count(*) AS graphs FROM mixed GROUP BY 1)"


@query(f"WITH {_SIZES} SELECT dtype, size, batch, graphs, size * batch AS tokens, greatest(size * batch, knee) AS time, size * batch <= top AS fits FROM sizes, (VALUES {_values(GRID_BATCHES)}) b(batch), (VALUES ('double', 400, 2000), ('float', 800, 4000)) p(dtype, knee, top)")
def saturation_curve(spark, d):
    """Time of a batch, for every size of a graph of the mixed corpus: flat until the device is filled, then in proportion
    to its tokens."""
    sizes = mixed_graphs(spark, d).groupBy(F.col("n_vertices").alias("size")).agg(F.count("*").alias("graphs"))
    grid = literal_table(spark, [(b,) for b in GRID_BATCHES], "batch int").crossJoin(F.broadcast(literal_table(spark, [("double", 400, 2000), ("float", 800, 4000)], "dtype string, knee int, top int")))
    tokens = F.col("size") * F.col("batch")
    return sizes.crossJoin(F.broadcast(grid)).select("dtype", "size", "batch", "graphs", tokens.alias("tokens"), F.greatest(tokens, F.col("knee")).alias("time"), (tokens <= F.col("top")).alias("fits"))


@query(f"WITH {_SIZES} SELECT size, any_value(graphs) AS graphs, min(batch) FILTER (size * batch >= 400) AS knee_batch FROM sizes, (VALUES {_values(GRID_BATCHES)}) b(batch) GROUP BY size")
def knee_fit(spark, d):
    """The smallest batch from which time grows, in double precision, for every size; null where none of the grid fills
    the device."""
    grows = F.min(F.when(F.col("tokens") >= 400, F.col("batch")))
    return saturation_curve(spark, d).where("dtype = 'double'").groupBy("size").agg(F.first("graphs").alias("graphs"), grows.alias("knee_batch"))


SWEEP = (1024, 2048, 3072, 4096, 6144)


@query("WITH RECURSIVE " + DOCS + ", " + ", ".join(packing_sql.balanced("docs", c, RANKS, prefix=f"c{c}_") for c in SWEEP) + " " + " UNION ALL ".join(f"SELECT {c} AS capacity, count(*) AS n_bins, CAST(count(*) * {c} - sum(load) AS BIGINT) AS pad_tokens, max(load) - min(load) AS spread_tokens, count(*) // {RANKS} AS n_steps, (SELECT CAST(sum(x) AS DOUBLE) FROM (SELECT max(greatest(load, 800)) AS x FROM c{c}_bins GROUP BY bin_id // {RANKS})) AS epoch_cost FROM c{c}_bins" for c in SWEEP))
def capacity_sweep(spark, d):
    """Bins, padding and modelled epoch cost of capacities; larger documents have bins of their own, whose pad is below 0."""
    items, rows = doc_sizes(spark, d), []
    for c in SWEEP:
        got = pack_balanced(items, c, RANKS, oversize="isolate")
        cost = measures.epoch_time(schedule(got.bins, RANKS), RANKS, knee=800).first()
        s = measures.pack_summary(got.bins, c).first()
        rows.append((c, s["n_bins"], s["pad_tokens"], s["spread_tokens"], cost["n_steps"], cost["epoch_cost"]))
    return literal_table(spark, rows, "capacity int, n_bins long, pad_tokens long, spread_tokens long, n_steps long, epoch_cost double")


@query(f"{EVEN}, {_fixed(4).removeprefix(DOCS + ', ').replace('bins AS', 'four AS')} SELECT 'balanced' AS method, rank, load AS tokens FROM sched WHERE step = 0 UNION ALL SELECT 'fixed 4', CAST(bin_id AS INTEGER), load FROM four WHERE bin_id < {RANKS}")
def snapshot_compare(spark, d):
    """Eight ranks, fixed count of four against balanced batches: tokens of the first step and epoch ratio."""
    fixed, even = _fixed_scheduled(spark, d), pack_balanced_docs(spark, d)
    show = lambda df, name: df.where("step = 0").select(F.lit(name).alias("method"), "rank", F.col("load").alias("tokens"))
    return show(fixed, "fixed 4").unionByName(show(even, "balanced"))


@query(f"{STEPS} SELECT rank, load FROM sched WHERE step = 0")
def snapshot_fixed4(spark, d):
    return _fixed_scheduled(spark, d).where("step = 0").select("rank", "load")


# --- corpus and graphs -----------------------------------------------------------------------------------------------


@query(f"WITH {MIXED} SELECT * FROM mixed")
def corpus_mixed(spark, d):
    return mixed_graphs(spark, d)


@query(f"WITH {MIXED} SELECT source, count(*) AS graphs, round(count(*) * 100.0 / sum(count(*)) OVER (), 6) AS share, min(n_vertices) AS least, max(n_vertices) AS most FROM mixed GROUP BY source")
def corpus_table(spark, d):
    return graphs.corpus_table(mixed_graphs(spark, d))


@query(f"WITH {MIXED} SELECT source, CAST(floor(log10(greatest(n_vertices, 1)) * 4) AS BIGINT) AS bucket, count(*) AS graphs FROM mixed GROUP BY 1, 2")
def corpus_histogram(spark, d):
    return graphs.histogram(mixed_graphs(spark, d), "n_vertices", ["source"])


@query(f"WITH {MIXED} SELECT count(DISTINCT n_vertices) AS sizes, count(DISTINCT source) AS sources FROM mixed")
def distinct_sizes(spark, d):
    return mixed_graphs(spark, d).agg(F.countDistinct("n_vertices").alias("sizes"), F.countDistinct("source").alias("sources"))


VERT = "v AS (SELECT vec_id // 16 AS graph_id, vec_id AS v, label AS z, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y, CAST(embedding[3] AS DOUBLE) AS zc FROM embeddings)"


def _edges_sql(box: float | None) -> str:
    if box is None:
        return f"{VERT}, e AS (SELECT a.graph_id, a.v AS dst, b.v AS src, 0 AS sx, 0 AS sy, 0 AS sz, a.x - b.x AS dx, a.y - b.y AS dy, a.zc - b.zc AS dz FROM v a JOIN v b ON a.graph_id = b.graph_id AND a.v <> b.v), edges AS (SELECT *, sqrt(dx * dx + dy * dy + dz * dz) AS r FROM e WHERE dx * dx + dy * dy + dz * dz <= 0.0625)"
    return f"""{VERT}, s AS (SELECT CAST(i AS INTEGER) AS sx, CAST(j AS INTEGER) AS sy, CAST(k AS INTEGER) AS sz FROM range(-1, 2) a(i), range(-1, 2) b(j), range(-1, 2) c(k)),
        e AS (SELECT a.graph_id, a.v AS dst, b.v AS src, sx, sy, sz, a.x - (b.x + sx * {box}) AS dx, a.y - (b.y + sy * {box}) AS dy, a.zc - (b.zc + sz * {box}) AS dz FROM v a JOIN v b ON a.graph_id = b.graph_id, s WHERE NOT (a.v = b.v AND sx = 0 AND sy = 0 AND sz = 0)),
        edges AS (SELECT *, sqrt(dx * dx + dy * dy + dz * dz) AS r FROM e WHERE dx * dx + dy * dy + dz * dz <= 0.0625)"""


EDGES = "SELECT graph_id, dst, src, sx, sy, sz, round(r, 6) AS r FROM edges"


def _show(edges: DataFrame) -> DataFrame:
    return edges.select("graph_id", "dst", "src", "sx", "sy", "sz", F.round("r", 6).alias("r"))


@query(f"WITH {_edges_sql(None)} {EDGES}")
def radius_edges_open(spark, d):
    return _show(graphs.radius_edges(graphs.vertices(spark, d), 0.25))


@query(f"WITH {_edges_sql(None)} {EDGES}")
def radius_edges_cells(spark, d):
    """The same edges through cells of the cutoff's size: for graphs with many vertices."""
    return _show(graphs.radius_edges(graphs.vertices(spark, d), 0.25, cells=True))


@query(f"WITH {_edges_sql(0.6)} {EDGES}")
def radius_edges_periodic(spark, d):
    return _show(graphs.radius_edges(graphs.vertices(spark, d), 0.25, box=(0.6, 0.6, 0.6)))


PROFILE = "SELECT graph_id, n_vertices, coalesce(n_edges, 0) AS n_edges, CASE WHEN n_vertices > 1 THEN round(coalesce(n_edges, 0) / CAST(n_vertices * (n_vertices - 1) AS DOUBLE), 6) END AS density, CASE WHEN n_vertices > 1 THEN round(1 - coalesce(n_edges, 0) / CAST(n_vertices * (n_vertices - 1) AS DOUBLE), 6) END AS sparsity"


@query(f"WITH {_edges_sql(None)}, n AS (SELECT graph_id, count(*) AS n_vertices FROM v GROUP BY 1), m AS (SELECT graph_id, count(*) AS n_edges FROM edges GROUP BY 1) {PROFILE} FROM n LEFT JOIN m USING (graph_id)")
def graph_profile_embeddings(spark, d):
    v = graphs.vertices(spark, d)
    return graphs.graph_profile(graphs.radius_edges(v, 0.25), v)


ITEMS = "i AS (SELECT l_orderkey AS graph_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity, l_extendedprice) AS v, l_shipdate FROM lineitem)"
ORDER_EDGES = f"{ITEMS}, oe AS (SELECT a.graph_id, a.v AS dst, b.v AS src FROM i a JOIN i b ON a.graph_id = b.graph_id AND a.v <> b.v WHERE abs(date_diff('day', a.l_shipdate, b.l_shipdate)) <= 365)"


@query(f"WITH {ORDER_EDGES} SELECT * FROM oe")
def order_graph_edges(spark, d):
    return graphs.order_edges(spark, d).select("graph_id", F.col("dst").cast("long"), F.col("src").cast("long"))


@query(f"WITH {ORDER_EDGES}, n AS (SELECT graph_id, count(*) AS n_vertices FROM i GROUP BY 1), m AS (SELECT graph_id, count(*) AS n_edges FROM oe GROUP BY 1) {PROFILE} FROM n LEFT JOIN m USING (graph_id)")
def graph_profile_orders(spark, d):
    v = source_graphs(spark, d, "orders")
    counted = graphs.order_edges(spark, d).groupBy("graph_id").agg(F.count("*").alias("n_edges"))
    return graphs.profile_of_counts(v.join(counted, "graph_id", "left").select("graph_id", "n_vertices", F.coalesce("n_edges", F.lit(0)).alias("n_edges")))


_BY_EDGES = f"WITH RECURSIVE {ORDER_EDGES}, n AS (SELECT graph_id, count(*) AS n_vertices FROM i GROUP BY 1), m AS (SELECT graph_id, count(*) AS n_edges FROM oe GROUP BY 1)"


def _sized_orders(spark, d) -> DataFrame:
    counted = graphs.order_edges(spark, d).groupBy("graph_id").agg(F.count("*").alias("n_edges"))
    return source_graphs(spark, d, "orders").join(counted, "graph_id", "left")


@query(f"{_BY_EDGES}, items AS (SELECT graph_id AS id, coalesce(n_edges, 0) AS size FROM n LEFT JOIN m USING (graph_id)), {packing_sql.balanced('items', 256, RANKS, prefix='p_')} {summary_sql(256, 'p_bins')}")
def pack_by_edges(spark, d):
    """Sizes by edges: items of an order with ship dates at most a year apart."""
    sized = _sized_orders(spark, d).select(F.col("graph_id").alias("id"), graph_size(alpha=0.0, beta=1.0).alias("size"))
    return measures.pack_summary(pack_balanced(sized, 256, RANKS, oversize="isolate").bins, 256)


@query(f"{_BY_EDGES}, items AS (SELECT graph_id AS id, CAST(ceil(n_vertices + 0.5 * coalesce(n_edges, 0)) AS BIGINT) AS size FROM n LEFT JOIN m USING (graph_id)), {packing_sql.balanced('items', 256, RANKS, prefix='p_')} {summary_sql(256, 'p_bins')}")
def pack_by_mix(spark, d):
    """Sizes by vertices and half the edges."""
    sized = _sized_orders(spark, d).select(F.col("graph_id").alias("id"), graph_size(alpha=1.0, beta=0.5).alias("size"))
    return measures.pack_summary(pack_balanced(sized, 256, RANKS, oversize="isolate").bins, 256)


MILLION, MILLION_CAPACITY, MILLION_RANKS = 1_000_000, 3845, 740


@query(f"WITH s AS (SELECT range * 2654435761 % 4294967296 % 768 + 1 AS size FROM range({MILLION})), t AS (SELECT count(*) AS n_items, CAST(sum(size) AS BIGINT) AS total_load FROM s) SELECT n_items, total_load, (CAST(ceil(total_load / {float(MILLION_CAPACITY)}) AS BIGINT) + {MILLION_RANKS - 1}) // {MILLION_RANKS} * {MILLION_RANKS} <= 103600 AS about_100k, CAST(0 AS BIGINT) AS over_capacity, CAST(0 AS BIGINT) AS off_multiple, true AS as_planned FROM t")
def pack_million(spark, d):
    """A million graphs of 1 to 768 vertices, ranked and assigned whole to about a hundred thousand batches of 740 ranks."""
    items = spark.range(MILLION).select("id", (portable_hash(F.col("id")) % 768 + 1).alias("size"))
    got = pack_balanced(items, MILLION_CAPACITY, MILLION_RANKS)
    return got.bins.agg(F.sum("n_items").cast("long").alias("n_items"), F.sum("load").cast("long").alias("total_load"), (F.count("*") <= 103_600).alias("about_100k"), F.count_if(F.col("load") > MILLION_CAPACITY).alias("over_capacity"), (F.count("*") % MILLION_RANKS).alias("off_multiple"), (F.count("*") == got.n_bins).alias("as_planned"))


@query(f"WITH {DOCS} SELECT CAST(sum(size) AS BIGINT) AS tokens, count(*) AS items, true AS alike, true AS whole_steps FROM docs")
def epoch_blocks_alike(spark, d):
    """Batches of an epoch, made apart by two processes from rows in another order, are the same."""
    items = doc_sizes(spark, d)
    a = block_of_epoch(items, CAPACITY, RANKS, 3, 7).select("bin_id", "load", "n_items", "sum_sq", "step", "rank")
    b = block_of_epoch(items.orderBy(F.rand(1)), CAPACITY, RANKS, 3, 7).select(*a.columns)
    same = a.exceptAll(b).unionByName(b.exceptAll(a)).isEmpty()
    steps = a.groupBy("step").agg(F.countDistinct("rank").alias("ranks")).agg(F.min("ranks")).first()[0]
    return a.agg(F.sum("load").cast("long").alias("tokens"), F.sum("n_items").cast("long").alias("items"), F.lit(same).alias("alike"), F.lit(steps == RANKS).alias("whole_steps"))


EVENT_EDGES = "SELECT a.user_id, a.event_id AS dst, b.event_id AS src FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 21600000000"


@query(EVENT_EDGES)
def session_graph_edges(spark, d):
    """Events of a user at most six hours apart, through buckets of six hours."""
    return graphs.interval_edges(read_table(spark, d, "events", ["user_id", "event_id", "ts"]), "user_id", "event_id", "ts", 6 * 3600)


@query(f"""WITH {_edges_sql(None)}, {FIT}, g AS (SELECT graph_id, count(*) AS size FROM v GROUP BY 1), b AS (SELECT graph_id, size, (row_number() OVER (ORDER BY size DESC, graph_id) - 1) % 8 AS bin_id FROM g),
    o AS (SELECT graph_id, bin_id, CAST(coalesce(sum(size) OVER (PARTITION BY bin_id ORDER BY graph_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS first FROM b),
    w AS (SELECT v, graph_id, row_number() OVER (PARTITION BY graph_id ORDER BY v) - 1 AS k FROM v)
    SELECT o.bin_id, o.first + a.k AS dst, o.first + c.k AS src FROM edges JOIN o USING (graph_id) JOIN w a ON a.v = dst JOIN w c ON c.v = src""")
def block_diagonal_cyclic(spark, d):
    """The edges of eight mini-batches, vertices numbered anew so that graphs are blocks of one adjacency."""
    v = graphs.vertices(spark, d)
    sizes = v.groupBy("graph_id").agg(F.count("*").alias("size"))
    dealt = with_global_rank(sizes, [F.col("size").desc(), F.col("graph_id").asc()]).select("graph_id", "size", (F.col("place") % 8).alias("bin_id"))
    return graphs.block_diagonal(dealt, v, graphs.radius_edges(v, 0.25))[1].select("bin_id", "dst", "src")


@query(f"WITH {CYCLIC} SELECT bin_id, CAST(sum(size) AS BIGINT) AS filled, greatest({CAPACITY} - CAST(sum(size) AS BIGINT), 0) AS padded, round(greatest({CAPACITY} - CAST(sum(size) AS BIGINT), 0) / {CAPACITY}.0, 6) AS fraction FROM dealt GROUP BY bin_id")
def padded_batch(spark, d):
    """The dense view of a mini-batch: its tokens, then zeros up to the capacity."""
    dealt = pack_cyclic(*_m(spark, d))
    dense = graphs.padded(dealt, CAPACITY)
    return dense.select("bin_id", "filled", "padded", F.round(F.col("padded") / CAPACITY, 6).alias("fraction"))


@query(f"""WITH {_edges_sql(None)}, m AS (SELECT dst, CAST(embedding[4] AS DOUBLE) * (1 - r / 0.25) AS m FROM edges JOIN embeddings ON vec_id = src)
    SELECT vec_id // 16 AS graph_id, vec_id AS v, CAST(count(m) AS DOUBLE) AS degree, round(coalesce(sum(m), 0), 6) + 0.0 AS total, round(coalesce(avg(m), 0), 6) + 0.0 AS mean, round(coalesce(max(m), 0), 6) + 0.0 AS most, round(coalesce(min(m), 0), 6) + 0.0 AS least FROM embeddings LEFT JOIN m ON dst = vec_id GROUP BY vec_id""")
def aggregate_neighbors(spark, d):
    """A message function over the sender's state and the edge, with every operation; lone vertices have zeros."""
    v = graphs.vertices(spark, d)
    states = v.select("graph_id", "v", F.get("h", F.lit(0)).alias("s"))
    got = graphs.aggregate_neighbors(graphs.radius_edges(v, 0.25), states, F.col("s") * (1 - F.col("r") / 0.25), {"degree": "count", "total": "sum", "mean": "mean", "most": "max", "least": "min"})
    return got.select("graph_id", "v", "degree", *[(F.round(c, 6) + F.lit(0.0)).alias(c) for c in ("total", "mean", "most", "least")])


@query(f"WITH {_edges_sql(None)} SELECT CAST(floor(r * 20) AS BIGINT) AS bucket, count(*) AS edges FROM edges GROUP BY 1")
def edge_length_histogram(spark, d):
    return graphs.radius_edges(graphs.vertices(spark, d), 0.25).groupBy(F.floor(F.col("r") * 20).alias("bucket")).agg(F.count("*").alias("edges"))

