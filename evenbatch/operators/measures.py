"""Objectives, constraints, loads, modelled time and scaling of packings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def pack_summary(bins: DataFrame, capacity: int) -> DataFrame:
    """The three objectives and padding: bins, fill (size squared over capacity squared, which no complete packing
    changes), pad tokens and areas, and spread of squares and of tokens, as the greatest difference of any two bins."""
    c2 = capacity * capacity
    return bins.agg(
        F.count("*").alias("n_bins"), F.count_if(F.col("n_items") > 0).alias("n_bins_used"), F.sum("n_items").cast("long").alias("n_items"), F.sum("load").cast("long").alias("total_load"),
        F.round(F.sum("sum_sq") / c2, 6).alias("area_fill"), (F.count("*") * capacity - F.sum("load")).cast("long").alias("pad_tokens"), (F.count("*") * c2 - F.sum("sum_sq")).cast("long").alias("pad_area"),
        (F.max("sum_sq") - F.min("sum_sq")).cast("long").alias("spread_area"), (F.max("load") - F.min("load")).cast("long").alias("spread_tokens"), F.count_if(F.col("load") > capacity).alias("over_capacity"),
    )


def check_capacity(bins: DataFrame, capacity: int) -> DataFrame:
    return bins.where((F.col("load") > capacity) & ~F.coalesce(F.col("is_oversize"), F.lit(False)))


def check_partition(items: DataFrame, assignment: DataFrame) -> DataFrame:
    """Items that are not in exactly one bin."""
    there = assignment.where("bin_id IS NOT NULL").groupBy("id").agg(F.count("*").alias("times"))
    return items.select("id").join(there, "id", "full").where("times IS NULL OR times <> 1")


def check_multiple(bins: DataFrame, ranks: int) -> DataFrame:
    return bins.agg((F.count("*") % ranks).alias("remainder")).where("remainder <> 0")


def bin_loads(assignment: DataFrame) -> DataFrame:
    return assignment.groupBy("bin_id").agg(F.sum("size").cast("long").alias("load"), F.count("*").alias("n_items"), F.sum(F.col("size") * F.col("size")).cast("long").alias("sum_sq"))


def on_ranks(bins: DataFrame, ranks: int) -> DataFrame:
    """Step and rank straight from a gapless bin id."""
    return bins.withColumn("step", F.floor(F.col("bin_id") / ranks)).withColumn("rank", (F.col("bin_id") % ranks).cast("int"))


def rank_loads(scheduled: DataFrame) -> DataFrame:
    return scheduled.groupBy("rank").agg(F.sum("load").cast("long").alias("tokens"), F.count("*").alias("n_batches"))


def step_cost(load: Column, knee: int = 0, per_token: float = 1.0) -> Column:
    """A batch's time: flat up to the knee, then in proportion."""
    return F.greatest(load, F.lit(knee)) * per_token


def step_times(scheduled: DataFrame, knee: int = 0) -> DataFrame:
    """Each step lasts as long as its slowest rank."""
    return scheduled.groupBy("step").agg(F.max(step_cost(F.col("load"), knee)).alias("slowest"), F.avg("load").alias("mean_load"), F.max("load").alias("max_load"), F.max_by("rank", F.struct("load", -F.col("rank"))).alias("straggler"))


def epoch_time(scheduled: DataFrame, ranks: int, knee: int = 0) -> DataFrame:
    """Steps, modelled epoch time, the time if loads were even, and their ratio."""
    total = scheduled.agg(F.sum("load").alias("total"))
    steps = step_times(scheduled, knee).agg(F.count("*").alias("n_steps"), F.sum("slowest").cast("double").alias("epoch_cost"))
    return steps.crossJoin(total).select("n_steps", "epoch_cost", F.round(F.col("total") / ranks, 6).alias("ideal_cost"), F.round(F.col("epoch_cost") / (F.col("total") / ranks), 6).alias("ratio"))


def straggler_ratio(scheduled: DataFrame, ranks: int) -> DataFrame:
    """max / mean load of each step; ranks without a batch count as load 0."""
    return scheduled.groupBy("step").agg(F.max("load").cast("long").alias("max_load"), F.round(F.max("load") / (F.sum("load") / ranks), 6).alias("ratio"), F.max_by("rank", F.struct("load", -F.col("rank"))).alias("straggler"))


def profile(scheduled: DataFrame, latency: int = 0, comm: int = 2, overlap: float = 0.5) -> DataFrame:
    """Per rank: computation without what runs at once with communication, communication, both at once, and idle time
    while waiting for the slowest."""
    slow = scheduled.groupBy("step").agg(F.max("load").alias("slowest"))
    both = F.least(F.col("load"), F.lit(comm + latency)) * overlap
    rows = scheduled.join(slow, "step").select("rank", "load", both.alias("both"), (F.col("slowest") - F.col("load")).alias("idle"))
    return rows.groupBy("rank").agg(
        F.round(F.sum(F.col("load") - F.col("both")), 6).alias("computation"), F.round(F.sum(F.lit(float(comm + latency)) - F.col("both")), 6).alias("communication"), F.round(F.sum("both"), 6).alias("overlap"), F.sum("idle").cast("long").alias("idle")
    )


def strong_efficiency(t_ref: Column, p_ref: Column, t: Column, p: Column) -> Column:
    return t_ref / ((p / p_ref) * t) * 100.0


def weak_efficiency(t_ref: Column, t: Column) -> Column:
    return t_ref / t * 100.0


def capacity_bounds(df: DataFrame, dtype: str = "float") -> DataFrame:
    """Bounds of the capacity: the largest item, the tokens that fill a device, and what fits its memory."""
    floor, top = (800, 4000) if dtype == "float" else (400, 2000)
    return df.agg(F.max("size").cast("long").alias("lower"), F.lit(floor).cast("long").alias("saturation"), F.lit(top).cast("long").alias("upper"), (F.max("size") <= top).alias("fits"))
