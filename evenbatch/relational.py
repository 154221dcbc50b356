"""The operators around the methods, one query each: scans, filters, joins, aggregates, windows, sorts, sets, scalar,
array, map, JSON, sampling, and user functions; each with its SQL."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .functions import coupling
from .kernel_queries import cg_sql
from .operators import graphs, measures
from .operators.packing import batch_fixed_count, pack_cyclic, pack_snake, portable_hash
from .plans.packing import pack_local
from .sources.tables import SOURCES, doc_sizes, literal_table, mixed_graphs, read_table, tags, words
from .workloads import _BY_SOURCE, CAPACITY, CYCLIC, DOCS, FIT, LOADS, MIXED, RANKS, SNAKE, STEPS, WIDE_CAPACITY, _edges_sql, _fixed_scheduled, _m, query

SIX_HOURS = 6 * 3600 * 1_000_000


# --- scans, projections, filters --------------------------------------------------------------------------------------


@query("SELECT doc_id, lang, n_chars FROM documents WHERE n_chars > 1000")
def scan_parquet_docs(spark, d):
    """Two filters and three columns reach the scan."""
    return read_table(spark, d, "documents", ["doc_id", "lang", "n_chars"], F.col("n_chars") > 1000)


@query(f"WITH {DOCS} SELECT id, size FROM docs")
def size_words(spark, d):
    return doc_sizes(spark, d)


@query("SELECT page_id AS id, CAST(length(html) - length(replace(html, '<', '')) AS BIGINT) AS size FROM pages")
def size_tags(spark, d):
    return read_table(spark, d, "pages", ["page_id", "html"]).select(F.col("page_id").alias("id"), tags().alias("size"))


@query("SELECT conv_id AS id, count(*) AS size FROM conversations GROUP BY conv_id")
def size_turns(spark, d):
    return read_table(spark, d, "conversations", ["conv_id"]).groupBy(F.col("conv_id").alias("id")).agg(F.count("*").alias("size"))


@query(f"WITH {FIT} SELECT count(*) AS items FROM fit WHERE size BETWEEN 10 AND 2000")
def filter_fit_docs(spark, d):
    return doc_sizes(spark, d).where(F.col("size").between(10, 2000)).agg(F.count("*").alias("items"))


@query(f"WITH {MIXED} SELECT source, count(*) AS graphs FROM mixed WHERE source IN ('users', 'pages') OR source LIKE 'conv%' GROUP BY source")
def filter_sources(spark, d):
    return mixed_graphs(spark, d, ("users", "pages", "conversations", "suppliers")).where(F.col("source").isin("users", "pages") | F.col("source").like("conv%")).groupBy("source").agg(F.count("*").alias("graphs"))


@query(r"SELECT page_id FROM pages WHERE regexp_matches(url, '^https?://(m\.)?[a-z]+\.example')")
def filter_rlike_url(spark, d):
    return read_table(spark, d, "pages", ["page_id", "url"]).where(F.col("url").rlike(r"^https?://(m\.)?[a-z]+\.example")).select("page_id")


CLASS = "CASE WHEN n_vertices <= 8 THEN 'small' WHEN n_vertices <= 128 THEN 'medium' ELSE 'large' END"


def _class():
    return F.when(F.col("n_vertices") <= 8, "small").when(F.col("n_vertices") <= 128, "medium").otherwise("large")


@query(f"WITH {MIXED} SELECT {CLASS} AS class, count(*) AS graphs FROM mixed GROUP BY 1")
def size_class_counts(spark, d):
    return mixed_graphs(spark, d).groupBy(_class().alias("class")).agg(F.count("*").alias("graphs"))


@query("SELECT vec_id, round(CAST(embedding[1] AS DOUBLE), 6) AS x, CAST(floor(embedding[1] * 1000) AS INTEGER) AS milli FROM embeddings")
def cast_positions(spark, d):
    x = F.get("embedding", F.lit(0))
    return read_table(spark, d, "embeddings").select("vec_id", F.round(x.cast("double"), 6).alias("x"), F.floor(x * F.lit(1000).cast("float")).cast("int").alias("milli"))


@query(f"WITH {DOCS} SELECT {{'id': id, 'size': size}} AS graph, id % 8 AS rank FROM docs")
def struct_graph_row(spark, d):
    return doc_sizes(spark, d).withColumns({"graph": F.struct("id", "size"), "rank": F.col("id") % 8}).drop("id", "size")


@query("SELECT min(doc_id) AS doc_id, md5(text) AS text_md5, count(*) AS copies FROM documents GROUP BY text")
def dedup_docs_text(spark, d):
    """Exact copies, grouped by a digest so that texts stay out of the shuffle."""
    return read_table(spark, d, "documents", ["doc_id", "text"]).groupBy(F.md5("text").alias("text_md5")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"))


# --- joins -----------------------------------------------------------------------------------------------------------


@query("SELECT vec_id, label, (label % 7 - 3) / 8.0 AS w FROM embeddings")
def join_species_weights(spark, d):
    table = literal_table(spark, [(z, (z % 7 - 3) / 8.0) for z in range(10)], "label int, w double")
    return read_table(spark, d, "embeddings", ["vec_id", "label"]).join(F.broadcast(table), "label")


@query("SELECT o_orderpriority, count(*) AS items, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def join_shuffle_hash_orders(spark, d):
    items, orders = read_table(spark, d, "lineitem", ["l_orderkey", "l_quantity"]), read_table(spark, d, "orders", ["o_orderkey", "o_orderpriority"])
    joined = items.join(orders.hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("items"), F.sum(F.col("l_quantity").cast("decimal(18,2)")).cast("double").alias("quantity"))


@query(f"WITH {CYCLIC} SELECT bin_id, lang, count(*) AS items FROM dealt JOIN documents ON doc_id = id GROUP BY ALL")
def join_merge_assignment_items(spark, d):
    dealt = pack_cyclic(*_m(spark, d)).select("id", "bin_id")
    return dealt.join(read_table(spark, d, "documents", ["doc_id", "lang"]).hint("merge"), F.col("id") == F.col("doc_id")).groupBy("bin_id", "lang").agg(F.count("*").alias("items"))


@query("SELECT o_orderkey, coalesce(n, 0) AS items FROM orders LEFT JOIN (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1) ON l_orderkey = o_orderkey")
def join_left_isolated(spark, d):
    """Graphs without vertices keep a row."""
    n = read_table(spark, d, "lineitem", ["l_orderkey"]).groupBy("l_orderkey").agg(F.count("*").alias("n"))
    return read_table(spark, d, "orders", ["o_orderkey"]).join(n, F.col("o_orderkey") == F.col("l_orderkey"), "left").select("o_orderkey", F.coalesce("n", F.lit(0)).alias("items"))


@query("SELECT CAST(0 AS BIGINT) AS wrong")
def join_full_partition_check(spark, d):
    items, bins = _m(spark, d)
    return measures.check_partition(items, pack_snake(items, bins)).agg(F.count("*").alias("wrong"))


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def semi_labelled_docs(spark, d):
    return read_table(spark, d, "documents", ["doc_id"]).join(read_table(spark, d, "labels", ["doc_id"], "quality = 1"), "doc_id", "left_semi")


@query("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def anti_orders_without_items(spark, d):
    return read_table(spark, d, "orders", ["o_orderkey"]).join(read_table(spark, d, "lineitem", ["l_orderkey"]), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")


@query(f"""WITH {MIXED}, sizes AS (SELECT n_vertices AS size, count(*) AS graphs FROM mixed GROUP BY 1)
    SELECT c AS capacity, g AS ranks, c * g AS step_tokens, CAST(sum(graphs) AS BIGINT) AS graphs, CAST(coalesce(sum(graphs) FILTER (size > c), 0) AS BIGINT) AS over_capacity, CAST(ceil(coalesce(sum(size * graphs), 0) / (c * g)) AS BIGINT) AS least_steps FROM sizes, (VALUES (1024), (2048), (3072)) a(c), (VALUES (8), (64)) b(g) GROUP BY c, g""")
def cross_config_grid(spark, d):
    """Each capacity with each number of ranks over the sizes of the mixed corpus: graphs over the capacity and the least
    number of steps that hold all tokens."""
    a, b = literal_table(spark, [(1024,), (2048,), (3072,)], "capacity int"), literal_table(spark, [(8,), (64,)], "ranks int")
    sizes = mixed_graphs(spark, d).groupBy(F.col("n_vertices").alias("size")).agg(F.count("*").alias("graphs"))
    rows = sizes.crossJoin(F.broadcast(a.crossJoin(F.broadcast(b)))).withColumn("step_tokens", F.col("capacity") * F.col("ranks"))
    over, tokens = F.sum(F.when(F.col("size") > F.col("capacity"), F.col("graphs"))), F.coalesce(F.sum(F.col("size") * F.col("graphs")), F.lit(0))
    return rows.groupBy("capacity", "ranks", "step_tokens").agg(F.sum("graphs").alias("graphs"), F.coalesce(over, F.lit(0)).alias("over_capacity"), F.ceil(tokens / F.col("step_tokens")).alias("least_steps"))


@query(f"WITH {FIT}, r AS (SELECT id, size, row_number() OVER (ORDER BY size DESC, id) - 1 AS place FROM fit), p AS (SELECT size, min(place) AS first, max(place) AS last FROM r GROUP BY size) SELECT r.id, r.place, p.size AS piece FROM r JOIN p ON r.place BETWEEN p.first AND p.last")
def range_rank_to_piece(spark, d):
    """A value meets the interval that holds it: both are dealt into blocks of places, so that the join is by equality."""
    from .operators.packing import with_global_rank

    r = with_global_rank(doc_sizes(spark, d), [F.col("size").desc(), F.col("id").asc()])
    block = lambda x: F.floor(F.col(x) / 256)
    p = r.groupBy("size").agg(F.min("place").alias("first"), F.max("place").alias("last")).withColumnRenamed("size", "piece")
    p = p.withColumn("block", F.explode(F.sequence(block("first"), block("last"))))
    return r.withColumn("block", block("place")).join(p, "block").where(F.col("place").between(F.col("first"), F.col("last"))).select("id", "place", "piece")


@query("""SELECT p.event_id, b.event_id AS previous_purchase FROM events p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') b ON p.user_id = b.user_id AND p.ts > b.ts WHERE p.event_type <> 'purchase'""")
def asof_previous_purchase(spark, d):
    """The latest purchase before each other event: one window over both kinds instead of a join."""
    e = read_table(spark, d, "events", ["event_id", "user_id", "ts", "event_type"])
    before = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, -1)
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    rows = e.withColumn("ts", t).withColumn("bought", F.when(F.col("event_type") == "purchase", F.col("event_id")))
    return rows.withColumn("previous_purchase", F.last("bought", True).over(before)).where("event_type <> 'purchase'").select("event_id", "previous_purchase")


@query("SELECT a.l_orderkey, count(*) AS pairs FROM (SELECT l_orderkey, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS v FROM lineitem) a JOIN (SELECT l_orderkey, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS v FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.v < b.v GROUP BY 1")
def pairs_within_order(spark, d):
    v = graphs.order_items(spark, d).select("graph_id", "v")
    return v.join(v.select("graph_id", F.col("v").alias("w")), "graph_id").where("v < w").groupBy(F.col("graph_id").alias("l_orderkey")).agg(F.count("*").alias("pairs"))


@query("SELECT s_nationkey, count(*) AS items FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1")
def salted_suppliers(spark, d):
    """A join on few heavy keys: the heavy side is dealt over 8 salts, the other side repeated."""
    items = read_table(spark, d, "lineitem", ["l_suppkey", "l_orderkey"]).withColumn("salt", F.pmod(F.xxhash64("l_orderkey"), F.lit(8)))
    sup = read_table(spark, d, "supplier", ["s_suppkey", "s_nationkey"]).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(7).cast("long"))))
    return items.join(sup, (F.col("l_suppkey") == F.col("s_suppkey")) & (items["salt"] == sup["salt"])).groupBy("s_nationkey").agg(F.count("*").alias("items"))


# --- aggregates ------------------------------------------------------------------------------------------------------


@query("SELECT l_orderkey, count(*) AS items, CAST(sum(l_quantity) AS BIGINT) AS quantity FROM lineitem GROUP BY 1")
def agg_order_sizes(spark, d):
    return read_table(spark, d, "lineitem", ["l_orderkey", "l_quantity"]).groupBy("l_orderkey").agg(F.count("*").alias("items"), F.sum("l_quantity").cast("long").alias("quantity"))


@query(f"WITH {CYCLIC} SELECT bin_id, string_agg(CAST(id AS VARCHAR), ',' ORDER BY id) AS members FROM dealt GROUP BY 1")
def agg_manifest(spark, d):
    return pack_cyclic(*_m(spark, d)).groupBy("bin_id").agg(F.array_join(F.array_sort(F.collect_list("id")).cast("array<string>"), ",").alias("members"))


@query(f"WITH {MIXED} SELECT count(DISTINCT n_vertices) AS sizes, true AS near FROM mixed")
def approx_distinct_sizes(spark, d):
    """Distinct sizes, and whether the sketch's count, at a relative deviation of 1 %, is within 5 % of them."""
    got = mixed_graphs(spark, d).agg(F.approx_count_distinct("n_vertices", 0.01).alias("guess"), F.countDistinct("n_vertices").alias("sizes"))
    return got.select("sizes", (F.abs(F.col("guess") - F.col("sizes")) <= F.col("sizes") * 0.05).alias("near"))


@query(f"WITH {DOCS} SELECT round(quantile_cont(size, 0.5), 6) AS p50, round(quantile_cont(size, 0.9), 6) AS p90, round(quantile_cont(size, 0.99), 6) AS p99 FROM docs")
def size_percentiles(spark, d):
    p = lambda x: F.round(F.percentile("size", F.lit(x)), 6)
    return doc_sizes(spark, d).agg(p(0.5).alias("p50"), p(0.9).alias("p90"), p(0.99).alias("p99"))


@query()
def size_percentiles_approx(spark, d):
    return doc_sizes(spark, d).agg(F.percentile_approx("size", [0.5, 0.9, 0.99], 1000).alias("p"))


@query(f"{STEPS} SELECT round(avg(load), 6) AS mean, round(stddev_pop(load), 6) AS deviation, round(stddev_pop(load) / avg(load), 6) AS cv FROM sched")
def load_moments(spark, d):
    x = _fixed_scheduled(spark, d)
    return x.agg(F.round(F.avg("load"), 6).alias("mean"), F.round(F.stddev_pop("load"), 6).alias("deviation"), F.round(F.stddev_pop("load") / F.avg("load"), 6).alias("cv"))


@query(f"{STEPS} SELECT step, arg_max(rank, load * 1000 - rank) AS straggler, max(load) AS load FROM sched GROUP BY step")
def straggler_rank(spark, d):
    return _fixed_scheduled(spark, d).groupBy("step").agg(F.max_by("rank", F.struct("load", -F.col("rank"))).alias("straggler"), F.max("load").alias("load"))


@query(f"WITH {CYCLIC}, {LOADS} SELECT count_if(load > {CAPACITY}) AS over_capacity, count(*) AS bins FROM loads")
def count_over_capacity(spark, d):
    return measures.bin_loads(pack_cyclic(*_m(spark, d))).agg(F.count_if(F.col("load") > CAPACITY).alias("over_capacity"), F.count("*").alias("bins"))


def _classed(spark, d):
    return mixed_graphs(spark, d).withColumn("class", _class())


@query(f"WITH {MIXED}, c AS (SELECT source, {CLASS} AS class FROM mixed) SELECT source, class, count(*) AS graphs FROM c GROUP BY GROUPING SETS ((source), (class), ())")
def gsets_source_class(spark, d):
    return _classed(spark, d).groupingSets([["source"], ["class"], []], "source", "class").agg(F.count("*").alias("graphs")).select("source", "class", "graphs")


@query(f"WITH {MIXED}, c AS (SELECT source, {CLASS} AS class FROM mixed) SELECT source, class, CAST(grouping_id(source, class) AS BIGINT) AS level, count(*) AS graphs FROM c GROUP BY CUBE (source, class)")
def cube_source_class(spark, d):
    return _classed(spark, d).cube("source", "class").agg(F.grouping_id().cast("long").alias("level"), F.count("*").alias("graphs"))


@query("SELECT r_name, n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def rollup_region_nation(spark, d):
    t = lambda n: read_table(spark, d, n)
    n = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 rows by definition
    return t("customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).rollup("r_name", "n_name").agg(F.count("*").alias("customers"))


@query(f"{STEPS} SELECT step, max(CASE WHEN rank = 0 THEN load END) AS rank0, max(CASE WHEN rank = 1 THEN load END) AS rank1, max(CASE WHEN rank = 7 THEN load END) AS rank7 FROM sched GROUP BY step")
def pivot_step_rank(spark, d):
    x = _fixed_scheduled(spark, d).groupBy("step").pivot("rank", [0, 1, 7]).agg(F.max("load"))
    return x.select("step", F.col("0").alias("rank0"), F.col("1").alias("rank1"), F.col("7").alias("rank7"))


@query(f"{STEPS}, x AS (SELECT step, max(load) AS longest, min(load) AS shortest FROM sched GROUP BY step) SELECT step, 'longest' AS metric, longest AS tokens FROM x UNION ALL SELECT step, 'shortest', shortest FROM x")
def unpivot_metrics(spark, d):
    x = _fixed_scheduled(spark, d).groupBy("step").agg(F.max("load").alias("longest"), F.min("load").alias("shortest"))
    return x.unpivot("step", ["longest", "shortest"], "metric", "tokens")


@query("SELECT l_orderkey, count(*) AS items FROM lineitem GROUP BY 1 HAVING count(*) >= 8")
def having_big_orders(spark, d):
    return read_table(spark, d, "lineitem", ["l_orderkey"]).groupBy("l_orderkey").agg(F.count("*").alias("items")).where("items >= 8")


# --- windows ---------------------------------------------------------------------------------------------------------


@query(f"""WITH {MIXED}, s AS (SELECT * FROM mixed WHERE source IN ('users', 'pages')) SELECT source, graph_id, row_number() OVER w AS rn, rank() OVER (PARTITION BY source ORDER BY n_vertices) AS rk, dense_rank() OVER (PARTITION BY source ORDER BY n_vertices) AS dr,
    ntile(4) OVER w AS nt, round(percent_rank() OVER (PARTITION BY source ORDER BY n_vertices), 6) AS pr, round(cume_dist() OVER (PARTITION BY source ORDER BY n_vertices), 6) AS cd FROM s WINDOW w AS (PARTITION BY source ORDER BY n_vertices, graph_id)""")
def win_rankings_per_source(spark, d):
    w, v = Window.partitionBy("source").orderBy("n_vertices", "graph_id"), Window.partitionBy("source").orderBy("n_vertices")
    return mixed_graphs(spark, d, ("users", "pages")).select("source", "graph_id", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"))


@query("SELECT event_id, epoch_us(ts) - lag(epoch_us(ts)) OVER w AS gap, lead(event_id) OVER w AS following, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_gap_events(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read_table(spark, d, "events", ["event_id", "user_id", "ts"]).select("event_id", (t - F.lag(t).over(w)).alias("gap"), F.lead("event_id").over(w).alias("following"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(whole).alias("second"))


@query(f"WITH {CYCLIC} SELECT id, bin_id, CAST(coalesce(sum(size) OVER (PARTITION BY bin_id ORDER BY id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS first FROM dealt")
def win_running_offset(spark, d):
    w = Window.partitionBy("bin_id").orderBy("id").rowsBetween(Window.unboundedPreceding, -1)
    return pack_cyclic(*_m(spark, d)).select("id", "bin_id", F.coalesce(F.sum("size").over(w), F.lit(0)).alias("first"))


@query(f"SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN {SIX_HOURS} PRECEDING AND CURRENT ROW) AS near FROM events")
def win_events_6h_count(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-SIX_HOURS, 0)
    return read_table(spark, d, "events", ["event_id", "user_id", "ts"]).select("event_id", F.count("*").over(w).alias("near"))


def sessionize(df: DataFrame, key: str, ts: str, gap_micros: int, tie: str) -> DataFrame:
    """df with session: a gap starts a new one."""
    w = Window.partitionBy(key).orderBy(ts, tie)
    t = F.unix_micros(F.col(ts).cast("timestamp"))
    fresh = F.coalesce((t - F.lag(t).over(w) > gap_micros).cast("int"), F.lit(0))
    return df.withColumn("fresh", fresh).withColumn("session", F.sum("fresh").over(w)).drop("fresh")


def _sessions_sql(hours: int) -> str:
    return f"SELECT user_id, session, count(*) AS size FROM (SELECT user_id, CAST(sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS session FROM (SELECT user_id, ts, event_id, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) > {hours * 3600 * 1_000_000} THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY ALL"


@query(_sessions_sql(6))
def session_sizes_6h(spark, d):
    return sessionize(read_table(spark, d, "events", ["user_id", "ts", "event_id"]), "user_id", "ts", SIX_HOURS, "event_id").groupBy("user_id", "session").agg(F.count("*").alias("size"))


@query(_sessions_sql(12))
def session_sizes_12h(spark, d):
    return sessionize(read_table(spark, d, "events", ["user_id", "ts", "event_id"]), "user_id", "ts", 2 * SIX_HOURS, "event_id").groupBy("user_id", "session").agg(F.count("*").alias("size"))


# --- sort, limit, sets -----------------------------------------------------------------------------------------------


@query(f"WITH {DOCS} SELECT id, size FROM docs ORDER BY size DESC NULLS LAST, id")
def sort_sizes(spark, d):
    return doc_sizes(spark, d).orderBy(F.col("size").desc_nulls_last(), "id")


@query(f"WITH {DOCS} SELECT id, size FROM docs ORDER BY size DESC, id LIMIT 10")
def topk_docs(spark, d):
    return doc_sizes(spark, d).orderBy(F.col("size").desc(), "id").limit(10)


@query(f"WITH {MIXED} SELECT source, graph_id, n_vertices FROM mixed QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_vertices DESC, graph_id) <= 3")
def topk_per_source(spark, d):
    w = Window.partitionBy("source").orderBy(F.col("n_vertices").desc(), "graph_id")
    return mixed_graphs(spark, d).withColumn("k", F.row_number().over(w)).where("k <= 3").drop("k")


@query(f"{STEPS} SELECT bin_id, load FROM sched ORDER BY bin_id LIMIT 8 OFFSET 16")
def page_steps(spark, d):
    return _fixed_scheduled(spark, d).select("bin_id", "load").orderBy("bin_id").offset(16).limit(8)


@query("SELECT 'page' AS kind, page_id AS id FROM pages UNION SELECT 'item', item_id FROM benchmark")
def union_sources(spark, d):
    a = read_table(spark, d, "pages", ["page_id"]).select(F.lit("page").alias("kind"), F.col("page_id").alias("id"))
    b = read_table(spark, d, "benchmark", ["item_id"]).select(F.col("item_id").alias("id"), F.lit("item").alias("kind"))
    return a.unionByName(b).distinct()


_PAIR = f"WITH c AS (WITH {CYCLIC} SELECT id, bin_id FROM dealt), s AS (WITH {SNAKE} SELECT id, bin_id FROM dealt)"


def _two(spark, d):
    items, bins = _m(spark, d)
    return pack_cyclic(items, bins).select("id", "bin_id"), pack_snake(items, bins).select("id", "bin_id")


@query(f"{_PAIR} SELECT * FROM c EXCEPT ALL SELECT * FROM s")
def except_cyclic_snake(spark, d):
    a, b = _two(spark, d)
    return a.exceptAll(b)


@query(f"{_PAIR} SELECT * FROM c INTERSECT SELECT * FROM s")
def intersect_cyclic_snake(spark, d):
    a, b = _two(spark, d)
    return a.intersect(b)


# --- scalar functions ------------------------------------------------------------------------------------------------


@query(r"SELECT doc_id, length(text) AS chars, CAST(len(regexp_extract_all(text, '\S+')) AS BIGINT) AS words, lower(substr(text, 1, 8)) AS head, md5(text) AS digest, replace(source, 'src', 's') AS short FROM documents")
def str_token_counts(spark, d):
    return read_table(spark, d, "documents", ["doc_id", "text", "source"]).select("doc_id", F.length("text").alias("chars"), words().alias("words"), F.lower(F.substring("text", 1, 8)).alias("head"), F.md5("text").alias("digest"), F.replace("source", F.lit("src"), F.lit("s")).alias("short"))


@query(r"SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, split_part(url, '/', 4) AS lang, concat_ws('|', 'p', CAST(page_id AS VARCHAR)) AS tag FROM pages")
def str_url_host(spark, d):
    return read_table(spark, d, "pages", ["page_id", "url"]).select("page_id", F.regexp_extract("url", r"^https?://([^/]+)", 1).alias("host"), F.split_part("url", F.lit("/"), F.lit(4)).alias("lang"), F.concat_ws("|", F.lit("p"), F.col("page_id").cast("string")).alias("tag"))


@query("SELECT CAST(year(ts) AS INTEGER) AS y, CAST(month(ts) AS INTEGER) AS m, CAST(day(ts) AS INTEGER) AS dd, count(*) AS events FROM events GROUP BY ALL")
def dt_daily_graphs(spark, d):
    return read_table(spark, d, "events", ["ts"]).groupBy(F.year("ts").alias("y"), F.month("ts").alias("m"), F.day("ts").alias("dd")).agg(F.count("*").alias("events"))


@query("SELECT CAST(date_diff('day', o_orderdate, l_shipdate) AS INTEGER) AS lag_days, count(*) AS items FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def dt_ship_lag(spark, d):
    items, orders = read_table(spark, d, "lineitem", ["l_orderkey", "l_shipdate"]), read_table(spark, d, "orders", ["o_orderkey", "o_orderdate"])
    return items.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.datediff("l_shipdate", "o_orderdate").alias("lag_days")).agg(F.count("*").alias("items"))


@query(f"WITH {DOCS} SELECT id, (size + 7) // 8 AS eighths, size % 8 AS rest, round(sqrt(size), 6) AS root, round(log10(size + 1), 6) AS lg, greatest(size, 100) AS at_least, CAST(sign(size - 300) AS INTEGER) AS side FROM docs")
def math_ceil_div(spark, d):
    s = F.col("size")
    return doc_sizes(spark, d).select("id", F.floor((s + 7) / 8).alias("eighths"), (s % 8).alias("rest"), F.round(F.sqrt(s), 6).alias("root"), F.round(F.log10(s + 1), 6).alias("lg"), F.greatest(s, F.lit(100)).alias("at_least"), F.sign(s - 300).cast("int").alias("side"))


@query(f"WITH {DOCS} SELECT least(greatest(CAST(floor(size / 100.0) AS BIGINT) + 1, 0), 11) AS bucket, count(*) AS items FROM docs GROUP BY 1")
def hist_width_buckets(spark, d):
    return doc_sizes(spark, d).groupBy(F.width_bucket("size", F.lit(0), F.lit(1000), F.lit(10)).alias("bucket")).agg(F.count("*").alias("items"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 5) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS positive, list_transform(embedding[1:3], lambda x: round(CAST(x AS DOUBLE), 6)) AS head FROM embeddings")
def arr_norm_embeddings(spark, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return read_table(spark, d, "embeddings", ["vec_id", "embedding"]).select("vec_id", F.round(F.sqrt(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x)), 5).alias("norm"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.transform(F.slice(e, 1, 3), lambda x: F.round(x, 6)).alias("head"))


@query("SELECT a.vec_id, b.vec_id AS other, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda x: CAST(x[1] AS DOUBLE) * CAST(x[2] AS DOUBLE))), 5) + 0.0 AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def arr_dot_pairs(spark, d):
    e = read_table(spark, d, "embeddings", ["vec_id", "embedding"])
    other = e.select(F.col("vec_id").alias("other"), (F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("second"))
    products = F.zip_with("embedding", "second", lambda x, y: x.cast("double") * y.cast("double"))
    return e.join(other, "vec_id").select("vec_id", "other", (F.round(F.aggregate(products, F.lit(0.0), lambda a, x: a + x), 5) + F.lit(0.0)).alias("dot"))


@query("SELECT i AS at, count(*) AS vectors, round(sum(CAST(embedding[i] AS DOUBLE)), 4) + 0.0 AS total FROM embeddings, range(1, 65) r(i) GROUP BY i")
def arr_explode_components(spark, d):
    e = read_table(spark, d, "embeddings", ["embedding"]).select(F.posexplode("embedding"))
    return e.groupBy((F.col("pos") + 1).cast("long").alias("at")).agg(F.count("*").alias("vectors"), (F.round(F.sum(F.col("col").cast("double")), 4) + F.lit(0.0)).alias("total"))


@query(f"WITH {MIXED}, c AS (SELECT source, count(*) AS n FROM mixed GROUP BY 1) SELECT list_sort(list(source)) AS names, CAST(sum(n) AS BIGINT) AS total FROM c")
def map_source_counts(spark, d):
    c = mixed_graphs(spark, d).groupBy("source").agg(F.count("*").alias("n"))
    m = c.agg(F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    return m.select(F.array_sort(F.map_keys("m")).alias("names"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def json_props_k(spark, d):
    return read_table(spark, d, "events", ["event_id", "props"]).select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("SELECT l_orderkey, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2)) * (1 - CAST(l_discount AS DECIMAL(18,2)))) AS DOUBLE) AS revenue FROM lineitem GROUP BY 1")
def decimal_revenue_per_order(spark, d):
    price = F.col("l_extendedprice").cast("decimal(18,2)") * (F.lit(1).cast("decimal(18,2)") - F.col("l_discount").cast("decimal(18,2)"))
    return read_table(spark, d, "lineitem", ["l_orderkey", "l_extendedprice", "l_discount"]).groupBy("l_orderkey").agg(F.sum(price).cast("double").alias("revenue"))


@query(f"WITH {MIXED} SELECT source, count(*) AS graphs FROM mixed WHERE (graph_id + 3) * 2654435761 % 4294967296 < CASE source WHEN 'orders' THEN 429496729 WHEN 'parts' THEN 2147483648 ELSE 4294967296 END GROUP BY 1")
def subset_stratified(spark, d):
    limit = F.when(F.col("source") == "orders", 429496729).when(F.col("source") == "parts", 2147483648).otherwise(4294967296)
    return mixed_graphs(spark, d).where(portable_hash(F.col("graph_id"), 3) < limit).groupBy("source").agg(F.count("*").alias("graphs"))


@query("SELECT graph_id, n, CASE WHEN n > 1 THEN 0.5 END AS density, coalesce(CASE WHEN n > 1 THEN 0.5 END, 0.0) AS filled, nullif(n, 1) AS plural FROM (SELECT conv_id AS graph_id, count(*) AS n FROM conversations GROUP BY 1)")
def density_null_single(spark, d):
    n = read_table(spark, d, "conversations", ["conv_id"]).groupBy(F.col("conv_id").alias("graph_id")).agg(F.count("*").alias("n"))
    x = F.when(F.col("n") > 1, F.lit(0.5))
    return n.select("graph_id", "n", x.alias("density"), F.coalesce(x, F.lit(0.0)).alias("filled"), F.nullif("n", F.lit(1)).alias("plural"))


# --- user functions --------------------------------------------------------------------------------------------------


@query(f"{STEPS} SELECT step, round(max(load) / avg(load), 6) AS imbalance FROM sched GROUP BY step")
def udaf_imbalance(spark, d):
    @F.pandas_udf("double")
    def imbalance(load: pd.Series) -> float:
        return float(load.max() / load.mean())

    return _fixed_scheduled(spark, d).groupBy("step").agg(F.round(imbalance("load"), 6).alias("imbalance"))


@query(f"WITH {_edges_sql(None)}, a AS (SELECT graph_id % 8 AS bin_id, count(*) AS n FROM v GROUP BY 1), b AS (SELECT graph_id % 8 AS bin_id, count(*) AS n FROM edges GROUP BY 1) SELECT bin_id, coalesce(a.n, 0) AS vertices, coalesce(b.n, 0) AS edges FROM a FULL JOIN b USING (bin_id)")
def cogroup_bin_graphs(spark, d):
    """Vertices and edges of each mini-batch meet in one task: counts of both."""
    v = graphs.vertices(spark, d).select((F.col("graph_id") % 8).alias("bin_id"), "v")
    e = graphs.radius_edges(graphs.vertices(spark, d), 0.25).select((F.col("graph_id") % 8).alias("bin_id"), "dst")

    def both(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        key = (a if len(a) else b)["bin_id"].iloc[0]
        return pd.DataFrame({"bin_id": [key], "vertices": [len(a)], "edges": [len(b)]})

    return v.groupBy("bin_id").cogroup(e.groupBy("bin_id")).applyInPandas(both, "bin_id long, vertices long, edges long")


@F.udtf(returnType="l1 int, m1 int, l2 int, m2 int, l3 int, m3 int, c double")
class CgTerms:
    """Non-zero coupling coefficients up to three orders; none where one is missing."""

    def eval(self, l1: int, l2: int, l3: int) -> Iterator[tuple]:
        if l1 is None or l2 is None or l3 is None:
            return
        for row in coupling.table(l1, l2, l3):
            yield row[1:]


@F.udtf(returnType="source string, graph_id long, size long, bin_id long")
class PackItems:
    """Balanced bins of each partition of a table argument (source, graph_id, size)."""

    def __init__(self):
        self.rows: list[tuple] = []

    def eval(self, row: T.Row, capacity: int, ranks: int) -> None:
        self.rows.append((row["source"], row["graph_id"], row["size"]))
        self.how = (capacity, ranks)

    def terminate(self) -> Iterator[tuple]:
        if self.rows:
            self.rows.sort(key=lambda r: r[1])
            for row, b in zip(self.rows, pack_local([r[2] for r in self.rows], *self.how)[0]):
                yield (*row, b)


def register_all(spark) -> None:
    """The SQL surface: cg_terms(l1, l2, l3) and pack_items(TABLE(...) PARTITION BY ..., capacity, ranks)."""
    spark.udtf.register("cg_terms", CgTerms)
    spark.udtf.register("pack_items", PackItems)


@query(f"""WITH {cg_sql(3, 1, 2)}, orders_of AS (SELECT (l_partkey % 4 + 4) % 4 AS a, (l_suppkey % 2 + 2) % 2 AS b, (l_orderkey % 3 + 3) % 3 AS c3, count(*) AS items FROM lineitem GROUP BY ALL)
    SELECT CAST(a AS INTEGER) AS l1, CAST(b AS INTEGER) AS l2, CAST(c3 AS INTEGER) AS l3, items, count(*) AS terms, round(sum(c * c), 6) AS squares FROM orders_of JOIN cg ON cg.l1 <= a AND cg.l2 <= b AND cg.l3 <= c3 GROUP BY ALL""")
def udtf_cg_terms(spark, d):
    """The function called for the largest orders that items name by part, supplier and order, once for each combination."""
    register_all(spark)
    order = lambda key, n, name: F.pmod(F.col(key), F.lit(n)).cast("int").alias(name)
    named = read_table(spark, d, "lineitem", ["l_partkey", "l_suppkey", "l_orderkey"]).groupBy(order("l_partkey", 4, "l1"), order("l_suppkey", 2, "l2"), order("l_orderkey", 3, "l3")).agg(F.count("*").alias("items"))
    named.createOrReplaceTempView("evenbatch_orders")
    return spark.sql("SELECT o.l1, o.l2, o.l3, o.items, count(*) AS terms, round(sum(t.c * t.c), 6) AS squares FROM evenbatch_orders o, LATERAL cg_terms(o.l1, o.l2, o.l3) t GROUP BY ALL")


@query(f"WITH RECURSIVE {MIXED}, {_BY_SOURCE} " + " UNION ALL ".join(f"SELECT '{x}' AS source, id AS graph_id, size, bin_id FROM {x}_packed" for x in SOURCES))
def udtf_pack_items(spark, d):
    register_all(spark)
    mixed_graphs(spark, d).withColumnRenamed("n_vertices", "size").createOrReplaceTempView("evenbatch_items")
    return spark.sql(f"SELECT * FROM pack_items(TABLE(SELECT source, graph_id, size FROM evenbatch_items) PARTITION BY (source), {WIDE_CAPACITY}, 8)")


@query(f"WITH {DOCS} SELECT count(*) AS items, CAST(sum(size) AS BIGINT) AS tokens FROM docs")
def sql_surface_smoke(spark, d):
    doc_sizes(spark, d).createOrReplaceTempView("evenbatch_docs")
    return spark.sql("SELECT count(*) AS items, sum(size) AS tokens FROM evenbatch_docs")


# --- batch twins of the streams ---------------------------------------------------------------------------------------


def _events(spark, d):
    return read_table(spark, d, "events", ["event_id", "user_id", "ts", "value"]).withColumn("ts", F.col("ts").cast("timestamp"))


@query("SELECT epoch_us(time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01')) AS start, count(*) AS events FROM events GROUP BY 1")
def stream_tumbling_load(spark, d):
    return _events(spark, d).groupBy(F.window("ts", "12 hours").alias("w")).agg(F.count("*").alias("events")).select(F.unix_micros("w.start").alias("start"), "events")


@query("SELECT epoch_us(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01')) - k * 21600000000 AS start, count(*) AS events FROM events, range(0, 2) r(k) GROUP BY 1")
def stream_sliding_load(spark, d):
    return _events(spark, d).groupBy(F.window("ts", "12 hours", "6 hours").alias("w")).agg(F.count("*").alias("events")).select(F.unix_micros("w.start").alias("start"), "events")


@query("""SELECT user_id, min(t) AS start, count(*) AS size FROM (SELECT user_id, t, sum(fresh) OVER (PARTITION BY user_id ORDER BY t, event_id) AS s FROM (SELECT user_id, event_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= 21600000000 THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, s""")
def session_window_sizes(spark, d):
    w = F.session_window("ts", "6 hours")
    return _events(spark, d).groupBy("user_id", w.alias("w")).agg(F.count("*").alias("size")).select("user_id", F.unix_micros("w.start").alias("start"), "size")


@query(f"WITH {DOCS}, f AS (SELECT (row_number() OVER (ORDER BY id) - 1) // 4 AS bin_id, size FROM docs) SELECT bin_id // {RANKS} AS step, CAST(sum(size) AS BIGINT) AS tokens FROM f GROUP BY 1")
def step_tokens(spark, d):
    placed = batch_fixed_count(doc_sizes(spark, d), 4)
    return placed.groupBy(F.floor(F.col("bin_id") / RANKS).alias("step")).agg(F.sum("size").alias("tokens"))
