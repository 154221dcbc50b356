import pytest

from evenbatch.operators import measures
from evenbatch.operators.packing import pack_balanced, schedule, with_global_rank
from evenbatch.sources import tables
from pyspark.sql import functions as F


def test_formats_round_trip(spark, tmp_path):
    df = spark.range(20).selectExpr("id", "id * 2 AS size")
    for fmt in ("csv", "json", "orc", "parquet"):
        df.write.format(fmt).save(str(tmp_path / fmt))
        assert tables.read_any(spark, str(tmp_path / fmt), fmt, "id long, size long").agg(F.sum("size")).first()[0] == 380


def test_missing_columns_are_named(spark, sf):
    with pytest.raises(ValueError, match="nothing"):
        tables.read_table(spark, sf, "documents", ["doc_id", "nothing"])


def test_batches_are_written_by_rank(spark, tmp_path):
    got = schedule(pack_balanced(tables.synthetic_sizes(spark, 300, 1, 50), 200, 4).bins, 4)
    tables.write_batches(got, str(tmp_path / "b"))
    assert spark.read.parquet(str(tmp_path / "b")).where("rank = 1").count() == got.where("rank = 1").count()
    assert measures.straggler_ratio(got, 4).agg(F.max("ratio")).first()[0] < 1.2


def test_rank_is_the_same_however_rows_lie(spark):
    df = tables.synthetic_sizes(spark, 500, 1, 20)
    keys = [F.col("size").desc(), F.col("id").asc()]
    a = {r.id: r.place for r in with_global_rank(df.repartition(7), keys).collect()}
    b = {r.id: r.place for r in with_global_rank(df.repartition(2), keys).collect()}
    assert a == b and sorted(a.values()) == list(range(500))


def test_plans_have_no_cartesian_product(spark, sf):
    import __spark_entry__ as e

    for name in ("radius_edges_open", "radius_edges_cells", "order_graph_edges", "session_graph_edges", "edge_product_fused", "pack_assignment_docs"):
        plan = e.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan, name
    scan = e.queries()["scan_parquet_docs"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThan(n_chars,1000)" in scan and "text" not in scan


def test_every_oracle_has_a_query():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries()) and len(e.queries()) > 150


def test_bucketed_table_and_foreach_sink(spark, tmp_path):
    from evenbatch.sources import tables

    rows = spark.createDataFrame([(i, i % 3) for i in range(20)], "id long, rank int")
    spark.sql("DROP TABLE IF EXISTS evenbatch_bucketed")
    tables.write_bucketed(rows, "evenbatch_bucketed", 4, "rank")
    assert spark.table("evenbatch_bucketed").count() == 20
    assert "Buckets" in "".join(r[0] for r in spark.sql("DESCRIBE EXTENDED evenbatch_bucketed").collect())
    spark.sql("DROP TABLE evenbatch_bucketed")
    out = str(tmp_path)

    def keep(part):
        import os
        import uuid

        with open(os.path.join(out, uuid.uuid4().hex), "w") as f:
            f.write("".join(f"{r.id}\n" for r in part))

    tables.sink_foreach(rows, keep)
    assert sorted(int(x) for p in tmp_path.iterdir() for x in p.read_text().split()) == list(range(20))


def test_text_and_csv_options(spark, tmp_path):
    from evenbatch.sources import tables

    (tmp_path / "a.txt").write_text("one\ntwo\n")
    assert [r[0] for r in tables.read_any(spark, str(tmp_path / "a.txt"), "text").collect()] == ["one", "two"]
    (tmp_path / "b.csv").write_text("x;y\n1;2\n")
    got = tables.read_any(spark, str(tmp_path / "b.csv"), "csv", "x long, y long", header="true", sep=";").collect()
    assert [tuple(r) for r in got] == [(1, 2)]


def test_a_vertex_of_an_unknown_species_stays(spark):
    from evenbatch.operators import graphs, kernels

    v = spark.createDataFrame([(1, 3), (2, None), (3, 99)], "v long, z int")
    got = {r.v: r.h0 for r in kernels.embed(v, 2).collect()}
    assert len(got) == 3 and got[2] == got[3] == [0.0, 0.0] and got[1] != [0.0, 0.0]
    edges = spark.createDataFrame([(0, 1, 2, 1.0)], "graph_id long, dst long, src long, r double")
    states = spark.createDataFrame([(0, 1, 5.0), (0, 2, 7.0)], "graph_id long, v long, s double")
    got = {r.v: (r.n, r.most) for r in graphs.aggregate_neighbors(edges, states, edges["r"] * states["s"], {"n": "count", "most": "max"}, empty=None).collect()}
    assert got == {1: (1.0, 7.0), 2: (0.0, None)}
