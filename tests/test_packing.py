import random

import pytest
from pyspark.sql import functions as F

from evenbatch import workloads
from evenbatch.operators import measures
from evenbatch.operators.packing import apply_oversize, batch_fixed_count, pack_balanced, schedule
from evenbatch.plans.packing import OversizeError, bin_count, pack_exact, pack_fixed_bins, pack_greedy, pack_local, plan_intervals


def by_plan(sizes, capacity, ranks, **how):
    order = sorted(range(len(sizes)), key=lambda i: -sizes[i])
    runs = {}
    for s in sizes:
        runs[s] = runs.get(s, 0) + 1
    plan = plan_intervals(list(runs.items()), capacity, ranks, **how)
    out = [-1] * len(sizes)
    for p in plan.pieces:
        for k in range(p.count):
            out[order[p.first + k]] = p.bin_lo + k
    return out, plan


# sizes, capacity, ranks, bins of the items, number of bins
TRACED = [
    ([7, 6, 5, 4, 3, 2, 2, 1], 10, 2, [0, 1, 2, 3, 3, 2, 1, 0], 4),
    ([16, 8, 5, 5, 3], 20, 2, [0, 1, 1, 1, 0], 2),
    ([6, 6, 6], 10, 1, [0, 1, 2], 3),
    ([6, 6, 6], 10, 2, [0, 1, 2], 4),
    ([3, 2], 10, 4, [0, 1], 4),
    ([5, 5, 5, 5], 10, 2, [0, 1, 0, 1], 2),
    ([10, 10], 10, 2, [0, 1], 2),
    ([], 10, 4, [], 0),
    ([8, 5, 4, 2, 1], 10, 2, [0, 1, 1, 0, 1], 2),
]


@pytest.mark.parametrize("sizes,capacity,ranks,bins,n", TRACED)
def test_traced_examples(sizes, capacity, ranks, bins, n):
    assert pack_local(sizes, capacity, ranks) == (bins, n)
    got, plan = by_plan(sizes, capacity, ranks)
    assert got == bins and plan.n_bins == n


def test_without_second_chance():
    got, plan = by_plan([16, 8, 5, 5, 3], 20, 2, reactivate=False)
    assert got == [0, 1, 1, 1, 2] and plan.n_bins == 4
    _, plan = by_plan([16, 8, 5, 5, 3], 20, 2)
    assert len(plan.trace) == 4 and sum(t["reactivated"] for t in plan.trace) == 1
    _, plan = by_plan([6, 6, 6], 10, 2, recursive=False)
    assert plan.unassigned == 1


def test_planner_equals_the_reference_and_keeps_the_rules():
    rng = random.Random(1)
    for _ in range(1500):
        capacity, ranks = rng.randint(1, 40), rng.randint(1, 6)
        sizes = [rng.randint(0, capacity) for _ in range(rng.randint(0, 60))]
        how = {"reactivate": rng.random() < 0.7, "recursive": rng.random() < 0.8}
        want, n = pack_local(sizes, capacity, ranks, **how)
        got, plan = by_plan(sizes, capacity, ranks, **how)
        assert got == want and plan.n_bins == n and n % ranks == 0
        loads = [0] * n
        for s, b in zip(sizes, want):
            if b >= 0:
                loads[b] += s
        assert all(x <= capacity for x in loads) and (not how["recursive"] or -1 not in want)


def test_optimum_is_never_beaten():
    rng = random.Random(2)
    for _ in range(60):
        sizes = [rng.randint(1, 10) for _ in range(rng.randint(1, 7))]
        bins, n = pack_local(sizes, 12, 2)
        squares = [sum(s * s for s, b in zip(sizes, bins) if b == k) for k in range(n)]
        best = pack_exact(sizes, 12, 2)
        assert (n, n * 12 - sum(sizes), max(squares) - min(squares)) >= best


def test_comparators_on_the_first_example():
    sizes = [7, 6, 5, 4, 3, 2, 2, 1]
    for rule in ("first", "best"):
        assert pack_greedy(sizes, 10, rule, True) == [0, 1, 2, 1, 0, 2, 2, 2]
    loads = lambda b: [sum(s for s, x in zip(sizes, b) if x == k) for k in range(max(b) + 1)]
    assert loads(pack_greedy(sizes, 10, "next")) == [7, 6, 9, 8]
    assert sorted(loads(pack_fixed_bins(sizes, 3)), reverse=True) == [11, 10, 9]


def test_bin_count_is_exact_for_large_totals():
    assert bin_count(10**18 + 1, 10, 8) == 10**17 + 8 and bin_count(0, 10, 4, 3) == 4
    with pytest.raises(ValueError):
        bin_count(1, 0, 1)


@pytest.mark.parametrize("strategy", ["interval", "local", "rounds"])
def test_strategies_agree(spark, strategy):
    rng = random.Random(6)
    sizes = [rng.choice([1, 2, 3, 5, 8, 13, 20]) for _ in range(60)]
    frame = spark.createDataFrame([(i, s) for i, s in enumerate(sizes)], "id long, size long").repartition(3)
    got = pack_balanced(frame, 25, 2, strategy=strategy)
    want, n = pack_local(sizes, 25, 2)
    assert {r.id: r.bin_id for r in got.assignment.collect()} == dict(enumerate(want)) and got.n_bins == n
    assert measures.check_partition(frame, got.assignment).count() == 0 and measures.check_capacity(got.bins, 25).count() == 0 and measures.check_multiple(got.bins, 2).count() == 0


def test_sharded_keeps_the_rules(spark):
    frame = spark.range(200).selectExpr("id", "id % 17 + 1 AS size")
    got = pack_balanced(frame, 30, 2, strategy="sharded", shards=3)
    assert measures.check_partition(frame, got.assignment).count() == 0 and measures.check_capacity(got.bins, 30).count() == 0 and got.n_bins % 2 == 0


def test_oversize_policies(spark):
    frame = spark.createDataFrame([(1, 12), (2, 3)], "id long, size long")
    with pytest.raises(OversizeError, match="item 1"):
        pack_balanced(frame, 10, 2)
    got = pack_balanced(frame, 10, 2, oversize="isolate")
    assert got.n_bins % 2 == 0 and [r.load for r in got.bins.where("is_oversize").collect()] == [12]
    assert sorted(r.size for r in apply_oversize(frame, 10, "split")[0].collect()) == [2, 3, 10]
    assert [r.id for r in pack_balanced(frame, 10, 2, oversize="drop").assignment.collect()] == [2]


def test_fixed_count_tails(spark):
    frame = spark.createDataFrame([(i, s) for i, s in enumerate([7, 6, 5, 4, 3, 2, 2, 1, 9])], "id long, size long")
    loads = {r.bin_id: r.load for r in measures.bin_loads(batch_fixed_count(frame, 2)).collect()}
    assert loads == {0: 13, 1: 9, 2: 5, 3: 3, 4: 9}
    assert batch_fixed_count(frame, 2, tail="drop", ranks=2).count() == 8
    assert batch_fixed_count(frame, 2, tail="repeat", ranks=2).count() == 12


def test_even_batches_beat_fixed_counts(spark, sf):
    from evenbatch.sources.tables import doc_sizes

    docs = doc_sizes(spark, sf)
    even = measures.epoch_time(schedule(pack_balanced(docs, 3072, 8).bins, 8), 8).first()
    fixed = measures.epoch_time(measures.on_ranks(measures.bin_loads(batch_fixed_count(docs, 4)), 8), 8).first()
    assert round(fixed.ratio, 4) == 2.2099 and even.ratio < 1.1


def test_experiments_keep_what_is_over_the_capacity(spark, sf, monkeypatch):
    monkeypatch.setattr(workloads, "CAPACITY", 300)
    docs = workloads.doc_sizes(spark, sf)
    n, tokens = docs.agg(F.count("*"), F.sum("size")).first()
    assert docs.where("size > 300").count()
    got = workloads.pack_objectives_balanced(spark, sf).first()
    assert (got.n_items, got.total_load) == (n, tokens)
    assert workloads.pack_assignment_docs(spark, sf).count() == n
    assert workloads.pack_first_fit(spark, sf).agg(F.sum("load")).first()[0] == tokens
    assert workloads._subset(spark, sf, 1.0).agg(F.sum("size")).first()[0] == workloads.mixed_graphs(spark, sf).agg(F.sum("n_vertices")).first()[0]


def test_many_pieces_are_joined_by_blocks_of_places(spark, monkeypatch):
    from evenbatch.operators import packing

    items = spark.createDataFrame([(i, (i * 37) % 50 + 1) for i in range(400)], "id long, size long")
    want = sorted(map(tuple, packing.pack_balanced(items, 60, 4).assignment.select("id", "bin_id").collect()))
    monkeypatch.setattr(packing, "BROADCAST_PIECES", 0)
    monkeypatch.setattr(packing, "BLOCK", 16)
    assert sorted(map(tuple, packing.pack_balanced(items, 60, 4).assignment.select("id", "bin_id").collect())) == want


def test_groups_are_packed_as_each_alone(spark):
    from evenbatch.operators import packing
    from evenbatch.plans.packing import OversizeError, pack_local

    rows = [(g, i, (i * 13 + g) % 20 + 1) for g in range(3) for i in range(50 * (g + 1))] + [(None, 7, 5)]
    frame = spark.createDataFrame(rows, "g int, id long, size long")
    got = packing.pack_balanced_by(frame.where("g IS NOT NULL"), ["g"], 30, 2).collect()
    for g in range(3):
        own = sorted((r for r in got if r.g == g), key=lambda r: r.id)
        assert [r.bin_id for r in own] == pack_local([r.size for r in own], 30, 2)[0]
    with pytest.raises(OversizeError):
        packing.pack_balanced_by(frame, ["g"], 10, 2)


def test_recursive_sql_packs_as_the_reference():
    import random

    import duckdb

    from evenbatch import packing_sql
    from evenbatch.plans.packing import pack_fixed_bins, pack_greedy, pack_local

    rng = random.Random(4)
    for _ in range(25):
        cap, ranks = rng.choice([10, 50, 400]), rng.choice([1, 2, 3, 8])
        sizes = [rng.randint(1, cap) if rng.random() < 0.5 else rng.randint(1, 5) for _ in range(rng.randint(1, 60))]
        flags = {"reactivate": rng.random() < 0.7, "recursive": rng.random() < 0.7}
        con = duckdb.connect()
        con.execute("CREATE TABLE items AS SELECT * FROM (VALUES " + ", ".join(f"({i}::BIGINT, {s}::BIGINT)" for i, s in enumerate(sizes)) + ") v(id, size)")
        ask = lambda cte, name: dict(con.execute(f"WITH RECURSIVE {cte} SELECT id, bin_id FROM {name}").fetchall())
        got = ask(packing_sql.balanced("items", cap, ranks, isolate=False, **flags), "packed")
        assert [-1 if got[i] is None else got[i] for i in range(len(sizes))] == pack_local(sizes, cap, ranks, **flags)[0]
        for rule in ("first", "best"):
            got = ask(packing_sql.greedy("items", cap, rule, ranks > 2), "dealt")
            assert [got[i] for i in range(len(sizes))] == pack_greedy(sizes, cap, rule, ranks > 2)
        got = ask(packing_sql.emptiest("items", 5), "dealt")
        assert [got[i] for i in range(len(sizes))] == pack_fixed_bins(sizes, 5)


def test_graph_size_takes_vertices_edges_or_both(spark):
    from evenbatch.sources.tables import graph_size

    row = spark.createDataFrame([(5, 9), (3, None)], "n_vertices long, n_edges long")
    got = row.select(graph_size().alias("a"), graph_size(alpha=0.0, beta=1.0).alias("b"), graph_size(alpha=1.0, beta=0.5).alias("c")).collect()
    assert [tuple(r) for r in got] == [(5, 9, 10), (3, 0, 3)]
