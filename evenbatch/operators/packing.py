"""Balanced batches and their comparators as DataFrame operators.

Items are (id, size) rows, written once: what gives the sizes is read a single time. Planning uses the histogram of
sizes, which has at most capacity + 1 rows; the only shuffle of items is the range sort that gives places, and it moves
ids and sizes, never payloads. Larger items stand before all others in the same sort.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.packing import OversizeError, Plan, bin_count, pack_fixed_bins, pack_greedy, pack_local, plan_intervals
from ..sources.tables import settled, stored

#: Pieces above which a plan is no longer broadcast: items then meet the pieces of their block of places in a shuffle.
BROADCAST_PIECES = 2_000_000


@dataclass
class PackResult:
    assignment: DataFrame
    bins: DataFrame
    trace: list[dict]
    n_bins: int


def with_global_rank(df: DataFrame, keys: list[Column], name: str = "place") -> DataFrame:
    """A place from 0 in the order of keys: range partitions, sorted, counted, and numbered from where they begin."""
    ordered = stored(df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_part", F.spark_partition_id()).withColumn("_row", F.monotonically_increasing_id()), "ranked")
    sizes = ordered.groupBy("_part").agg(F.count("*").alias("_n"), F.min("_row").alias("_first"))
    # one row a range partition in this window
    begins = sizes.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n") - F.col("_first")).alias("_shift"))
    return ordered.join(F.broadcast(begins), "_part").select(*df.columns, (F.col("_row") + F.col("_shift")).alias(name))


def size_histogram(df: DataFrame, size: str = "size") -> DataFrame:
    return df.groupBy(F.col(size).cast("long").alias("size")).agg(F.count("*").alias("items"))


def apply_oversize(df: DataFrame, capacity: int, policy: str = "error") -> tuple[DataFrame, DataFrame]:
    """(items that fit, items on their own). Policies: error, isolate, split (chunks of capacity), drop."""
    fit, large = df.where(F.col("size") <= capacity), df.where(F.col("size") > capacity)
    if policy == "error":
        first = large.orderBy("id").limit(1).collect()
        if first:
            raise OversizeError(f"item {first[0]['id']} of size {first[0]['size']} exceeds the capacity {capacity}")
        return fit, large
    if policy == "isolate":
        return fit, large
    if policy == "split":
        chunks = large.select("id", F.posexplode(F.sequence(F.lit(0).cast("long"), F.col("size") - 1, F.lit(capacity).cast("long"))), "size")
        parts = chunks.select("id", F.least(F.lit(capacity).cast("long"), F.col("size") - F.col("col")).alias("size"), F.col("pos").alias("chunk"))
        return fit.withColumn("chunk", F.lit(0)).unionByName(parts), large.limit(0)
    if policy == "drop":
        return fit, large.limit(0)
    raise ValueError(policy)


def place_pieces(ranked: DataFrame, plan: Plan, first: int = 0) -> DataFrame:
    """The bin of each place, counted from first. The plan's pieces are broadcast and searched, without a shuffle, as long
    as they are few; else pieces and items are joined by blocks of places."""
    starts = np.array([p.first + first for p in plan.pieces], dtype=np.int64)
    table = np.array([(p.bin_lo, p.level, p.lap) for p in plan.pieces], dtype=np.int64).reshape(-1, 3)
    if len(starts) > BROADCAST_PIECES:
        return _place_by_blocks(ranked, plan, first)
    shared = ranked.sparkSession.sparkContext.broadcast((starts, table))
    known = first + sum(p.count for p in plan.pieces)
    names = ranked.columns
    at_place = names.index("place")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        begins, rows = shared.value
        for batch in batches:
            place = batch.column(at_place).to_numpy(zero_copy_only=False)
            k = np.searchsorted(begins, place, side="right") - 1
            ok = (place < known) & (k >= 0)
            k = np.maximum(k, 0)
            bins = rows[k, 0] + place - begins[k] if len(begins) else place
            cols = [pa.array(x, t, mask=~ok) for x, t in ((bins, pa.int64()), (rows[k, 1] if len(begins) else place, pa.int32()), (rows[k, 2] if len(begins) else place, pa.int32()))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *cols], [*names, "bin_id", "level", "lap"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in ranked.schema) + ", bin_id long, level int, lap int"
    return ranked.mapInArrow(run, schema)


#: Places of a block, in which items meet the pieces that reach into it.
BLOCK = 100_000


def _place_by_blocks(ranked: DataFrame, plan: Plan, first: int) -> DataFrame:
    rows = [(p.first + first, p.first + first + p.count, p.bin_lo, p.level, p.lap) for p in plan.pieces]
    pieces = ranked.sparkSession.createDataFrame(rows, "_lo long, _hi long, _bin long, level int, lap int")
    pieces = pieces.withColumn("_block", F.explode(F.sequence(F.floor(F.col("_lo") / BLOCK), F.floor((F.col("_hi") - 1) / BLOCK))))
    inside = (F.col("place") >= F.col("_lo")) & (F.col("place") < F.col("_hi"))
    items = ranked.withColumn("_block", F.floor(F.col("place") / BLOCK))
    met = items.join(pieces.withColumnRenamed("_block", "_of"), (F.col("_block") == F.col("_of")) & inside, "left")
    return met.select(*ranked.columns, (F.col("_bin") + F.col("place") - F.col("_lo")).alias("bin_id"), "level", "lap")


def bins_of(assignment: DataFrame, n_bins: int, oversize: DataFrame | None = None) -> DataFrame:
    """One row a bin, empty ones too."""
    filled = assignment.where("bin_id IS NOT NULL").groupBy("bin_id").agg(F.sum("size").alias("load"), F.count("*").alias("n_items"), F.sum(F.col("size") * F.col("size")).alias("sum_sq"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return assignment.sparkSession.range(n_bins).withColumnRenamed("id", "bin_id").join(filled, "bin_id", "left").select("bin_id", zero("load"), zero("n_items"), zero("sum_sq"))


def pack_balanced(df: DataFrame, capacity: int, ranks: int, strategy: str = "interval", oversize: str = "error", reactivate: bool = True, recursive: bool = True, bin_order: str = "emptiest_first", shards: int = 8, seed: int | None = None) -> PackResult:
    """Balanced batches of (id, size). Strategies: interval (exact, any scale), rounds (exact, a job a lap), local
    (exact, one task), sharded (each shard packed apart). seed orders equal sizes by a hash instead of by id."""
    if bin_order != "emptiest_first" and strategy != "local":
        raise ValueError("only the local strategy can turn the bin order")
    spark = df.sparkSession
    df = stored(df.select("id", "size"), "items")
    ties = [F.xxhash64("id", F.lit(seed)).asc()] if seed is not None else []
    trace: list[dict] = []
    if strategy == "interval" and oversize in ("isolate", "drop"):
        runs = size_histogram(df.select(F.least("size", F.lit(capacity + 1)).alias("size"))).collect()  # at most capacity + 2 rows
        n_alone = sum(r["items"] for r in runs if r["size"] > capacity)
        plan = plan_intervals([(r["size"], r["items"]) for r in runs if r["size"] <= capacity], capacity, ranks, reactivate, recursive)
        ranked = with_global_rank(df if oversize == "isolate" else df.where(F.col("size") <= capacity), [F.col("size").desc(), *ties, F.col("id").asc()])
        if oversize == "drop":
            n_alone = 0
        got = place_pieces(ranked, plan, n_alone)
        own = F.col("place") < n_alone
        got = got.withColumn("bin_id", F.when(own, F.col("place") + plan.n_bins).otherwise(F.col("bin_id")))
        n_bins = bin_count(plan.n_bins + n_alone, 1, ranks) if n_alone else plan.n_bins
        bins = bins_of(got, n_bins).withColumn("is_oversize", (F.col("bin_id") >= plan.n_bins) & (F.col("n_items") > 0))
        return PackResult(got.select("id", "size", "bin_id", "level", "lap"), bins, plan.trace, n_bins)
    fit, alone = apply_oversize(df, capacity, oversize)
    keys = [F.col("size").desc(), *ties, F.col("id").asc(), *([F.col("chunk").asc()] if "chunk" in fit.columns else [])]
    if strategy == "interval":
        runs = [(r["size"], r["items"]) for r in size_histogram(fit).collect()]  # at most capacity + 1 rows
        plan = plan_intervals(runs, capacity, ranks, reactivate, recursive)
        assignment, n_bins, trace = place_pieces(with_global_rank(fit, keys), plan), plan.n_bins, plan.trace
    elif strategy == "local":
        ordered = with_global_rank(fit, keys)
        columns = ordered.columns

        def one(frame: pd.DataFrame) -> pd.DataFrame:
            frame = frame.sort_values("place")
            got, n = pack_local(frame["size"].tolist(), capacity, ranks, reactivate, recursive, bin_order == "emptiest_first")
            return frame.drop(columns="_one").assign(bin_id=pd.array([b if b >= 0 else None for b in got], dtype="Int64"), n_bins=n)

        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in ordered.schema) + ", bin_id long, n_bins long"
        got = settled(ordered.withColumn("_one", F.lit(0)).groupBy("_one").applyInPandas(one, schema))
        n_bins = got.agg(F.max("n_bins")).first()[0] or 0
        assignment = got.select(*columns, "bin_id")
    elif strategy == "sharded":
        ordered = with_global_rank(fit, keys).withColumn("shard", F.col("place") % shards)

        def each(frame: pd.DataFrame) -> pd.DataFrame:
            frame = frame.sort_values("place")
            got, n = pack_local(frame["size"].tolist(), capacity, ranks, reactivate, recursive)
            return frame.assign(inner=got, opened=n)

        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in ordered.schema) + ", inner long, opened long"
        got = settled(ordered.groupBy("shard").applyInPandas(each, schema))
        opened = {r["shard"]: r["n"] for r in got.groupBy("shard").agg(F.max("opened").alias("n")).collect()}  # one row a shard
        begin, total = {}, 0
        for s in sorted(opened):
            begin[s], total = total, total + opened[s]
        first = F.create_map(*[F.lit(x) for kv in begin.items() for x in kv]) if begin else F.create_map()
        assignment, n_bins = got.select(*fit.columns, "place", (F.col("inner") + first[F.col("shard")] if begin else F.col("inner")).alias("bin_id")), total
    elif strategy == "rounds":
        assignment, n_bins, trace = _rounds(with_global_rank(fit, keys), capacity, ranks, reactivate, recursive)
    else:
        raise ValueError(strategy)
    bins = bins_of(assignment, n_bins).withColumn("is_oversize", F.lit(False))
    if oversize == "isolate":
        lone = with_global_rank(alone, [F.col("size").desc(), F.col("id").asc()])
        n_alone = lone.count()
        lone = lone.withColumn("bin_id", F.col("place") + n_bins)
        pad = bin_count(n_bins + n_alone, 1, ranks)
        kept = [c for c in ("id", "size", "bin_id", "level", "lap") if c in assignment.columns]
        assignment = assignment.select(*kept).unionByName(lone.select("id", "size", "bin_id"), allowMissingColumns=True)
        own = bins_of(lone, pad).where(F.col("bin_id") >= n_bins).withColumn("is_oversize", F.col("n_items") > 0)
        bins, n_bins = bins.unionByName(own), pad
    return PackResult(assignment, bins, trace, n_bins)


def _rounds(ranked: DataFrame, capacity: int, ranks: int, reactivate: bool, recursive: bool) -> tuple[DataFrame, int, list[dict]]:
    """Each lap as a DataFrame job: sort the active bins, zip them with the next items, cut at the first misfit."""
    spark = ranked.sparkSession
    items = settled(ranked)
    total = items.count()
    at, opened, level, trace, done = 0, 0, 0, [], None
    while at < total:
        left = items.where(F.col("place") >= at).agg(F.sum("size")).first()[0]
        n = bin_count(left, capacity, ranks, total - at)
        bins = spark.range(opened, opened + n).select(F.col("id").alias("bin_id"), F.lit(capacity).cast("long").alias("room"), F.lit(False).alias("full"), (F.col("id") - opened).alias("turn"))
        opened, lap = opened + n, 0
        while at < total:
            lined = bins.where("NOT full").withColumn("k", F.row_number().over(Window.orderBy(F.desc("room"), "turn")) - 1)
            pairs = settled(lined.join(items.withColumn("k", F.col("place") - at).select("k", "place", "size"), "k", "left"))
            misfit = pairs.where("size > room").agg(F.min("k")).first()[0]
            width = pairs.count()
            if not width:
                break
            cut = width if misfit is None else misfit
            placed = pairs.where((F.col("k") < cut) & F.col("size").isNotNull())
            got = placed.select("place", "bin_id", F.lit(level).alias("level"), F.lit(lap).alias("lap"))
            done = got if done is None else done.unionByName(got)
            moved = min(cut, total - at)
            stuck = misfit is not None
            after = pairs.select("bin_id", (F.col("room") - F.when(F.col("k") < cut, F.coalesce("size", F.lit(0))).otherwise(0)).alias("room"), (F.lit(stuck) & (F.col("k") >= cut)).alias("full"), F.col("k").alias("turn"))
            old = bins.where("full").select("bin_id", "room", "full", "turn")
            bins = settled(after.unionByName(old.withColumn("turn", F.col("turn"))))
            edge = bins.agg(F.min(F.when(~F.col("full"), F.col("room"))).alias("lo"), F.max(F.when(F.col("full"), F.col("room"))).alias("hi")).first()
            back = bool(reactivate and edge["lo"] is not None and edge["hi"] is not None and edge["lo"] < edge["hi"])
            # those marked now stand behind those marked before, and all of them behind the open ones
            bins = bins.withColumn("turn", F.when(F.col("full") & (F.col("turn") < (lap + 1) * (1 << 32)) & (F.col("turn") < (1 << 32)), F.col("turn") + (lap + 1) * (1 << 32)).otherwise(F.col("turn")))
            if back:
                bins = bins.withColumn("full", F.lit(False))
            trace.append({"level": level, "lap": lap, "placed": moved, "reactivated": back})
            at, lap = at + moved, lap + 1
            bins = settled(bins)
        if not recursive:
            break
        level += 1
    empty = items.select(*items.columns, F.lit(None).cast("long").alias("bin_id"), F.lit(None).cast("int").alias("level"), F.lit(None).cast("int").alias("lap"))
    return (items.join(done, "place", "left").select(*empty.columns) if done is not None else empty.limit(0)), opened, trace


def pack_balanced_by(df: DataFrame, keys: list[str], capacity: int, ranks: int) -> DataFrame:
    """One exact plan a group; bin ids start at 0 in each. A group is planned from its histogram of sizes, which has at
    most capacity + 1 rows, and its items then meet the pieces of their size by a join: no task holds a group's items.
    Equal sizes go by id."""
    if df.where(F.col("size") > capacity).head(1):
        raise OversizeError(f"an item exceeds the capacity {capacity}")
    df = stored(df, "items")
    names = ", ".join(f"`{k}` {dict(df.dtypes)[k]}" for k in keys)

    def plan(frame: pd.DataFrame) -> pd.DataFrame:
        got = plan_intervals(list(zip(frame["size"].tolist(), frame["items"].tolist())), capacity, ranks)
        out = pd.DataFrame([(p.first, p.first + p.count, p.bin_lo) for p in got.pieces], columns=["_lo", "_hi", "_bin"])
        for k in keys:
            out[k] = frame[k].iloc[0]
        return out[[*keys, "_lo", "_hi", "_bin"]]

    pieces = df.groupBy(*keys, F.col("size").cast("long").alias("size")).agg(F.count("*").alias("items")).groupBy(*keys).applyInPandas(plan, f"{names}, _lo long, _hi long, _bin long")
    # places inside a group: those of the whole order less where the group begins
    ranked = with_global_rank(df, [*[F.col(k).asc() for k in keys], F.col("size").desc(), F.col("id").asc()], "_at")
    begins = ranked.groupBy(*keys).agg(F.min("_at").alias("_begin"))
    placed = ranked.join(begins, keys).withColumn("place", F.col("_at") - F.col("_begin"))
    blocks = pieces.withColumn("_block", F.explode(F.sequence(F.floor(F.col("_lo") / BLOCK), F.floor((F.col("_hi") - 1) / BLOCK))))
    met = placed.withColumn("_block", F.floor(F.col("place") / BLOCK)).join(blocks, [*keys, "_block"])
    met = met.where((F.col("place") >= F.col("_lo")) & (F.col("place") < F.col("_hi")))
    return met.select(*df.columns, (F.col("_bin") + F.col("place") - F.col("_lo")).alias("bin_id"))


def batch_fixed_count(df: DataFrame, count: int, order: str = "input", seed: int = 0, tail: str = "none", ranks: int = 1) -> DataFrame:
    """Batches of a fixed number of items, in order of id or of a hash. tail: none, drop or repeat, to a multiple of ranks."""
    keys = [F.col("id").asc()] if order == "input" else [portable_hash(F.col("id"), seed).asc(), F.col("id").asc()]
    ranked = with_global_rank(df, keys)
    if tail != "none":
        n, unit = df.count(), count * ranks
        if tail == "drop":
            ranked = ranked.where(F.col("place") < n // unit * unit)
        else:
            lack = -n % unit
            ranked = ranked.unionByName(ranked.where(F.col("place") < lack).withColumn("place", F.col("place") + n))
    return ranked.withColumn("bin_id", F.floor(F.col("place") / count))


def portable_hash(key: Column, seed: int = 0) -> Column:
    """A multiplicative hash that SQL engines can repeat: 0 .. 2**32 - 1."""
    return F.pmod((key + F.lit(seed)) * F.lit(2654435761), F.lit(1 << 32))


def pack_cyclic(df: DataFrame, bins: int) -> DataFrame:
    """Largest first, round robin, whatever the room."""
    return with_global_rank(df, [F.col("size").desc(), F.col("id").asc()]).withColumn("bin_id", F.col("place") % bins)


def pack_snake(df: DataFrame, bins: int) -> DataFrame:
    """As pack_cyclic, every other lap backwards."""
    at = F.col("place") % bins
    return with_global_rank(df, [F.col("size").desc(), F.col("id").asc()]).withColumn("bin_id", F.when(F.floor(F.col("place") / bins) % 2 == 0, at).otherwise(F.lit(bins - 1) - at))


def pack_sequential(df: DataFrame, rule: str, capacity: int | None = None, bins: int | None = None, decreasing: bool = False) -> DataFrame:
    """first, best, next fit, or fixed (largest to emptiest of a number of bins): sequential by nature, in one task."""

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("id")
        sizes = frame["size"].tolist()
        got = pack_fixed_bins(sizes, bins, capacity) if rule == "fixed" else pack_greedy(sizes, capacity, rule, decreasing)
        return pd.DataFrame({"id": frame["id"], "size": frame["size"], "bin_id": got})

    return df.select("id", "size", F.lit(0).alias("_one")).groupBy("_one").applyInPandas(one, "id long, size long, bin_id long")


def block_of_epoch(df: DataFrame, capacity: int, ranks: int, epoch: int, seed: int = 0) -> DataFrame:
    """(bin_id, step, rank) of an epoch: equal sizes and steps are shuffled by the epoch, alike on all processes."""
    got = pack_balanced(df, capacity, ranks, oversize="isolate", seed=seed + epoch)
    return schedule(got.bins, ranks, "shuffled", seed + epoch)


def schedule(bins: DataFrame, ranks: int, order: str = "bin", seed: int = 0) -> DataFrame:
    """Step and rank of each bin. order: bin (as opened, neighbours are alike), load (fullest first) or shuffled (whole
    steps are permuted)."""
    if order == "load":
        out = with_global_rank(bins, [F.col("load").desc(), F.col("bin_id").asc()], "_at")
    else:  # bin ids have no gaps
        out = bins.withColumn("_at", F.col("bin_id"))
    out = out.withColumn("step", F.floor(F.col("_at") / ranks)).withColumn("rank", (F.col("_at") % ranks).cast("int")).drop("_at")
    if order == "shuffled":
        steps = with_global_rank(out.select("step").distinct(), [F.xxhash64("step", F.lit(seed)).asc(), F.col("step").asc()], "new_step")
        out = out.join(steps, "step").drop("step").withColumnRenamed("new_step", "step")
    return out
