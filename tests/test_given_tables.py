"""Queries that once made up their rows: each reads a given table and gives what its SQL gives, on odd rows too."""

import shutil
from pathlib import Path

import duckdb
import pytest

import __spark_entry__ as entry

READS = (
    "cg_admissible",
    "cg_density",
    "cg_table_complex",
    "cg_table_real",
    "cross_config_grid",
    "generalized_cg",
    "saturation_curve",
    "knee_fit",
    "udtf_cg_terms",
)


@pytest.fixture(scope="module")
def odd(tmp_path_factory, sf):
    """The smallest tables with keys that are missing, negative or very large, and a page without text."""
    out = tmp_path_factory.mktemp("odd")
    for p in Path(sf).glob("*.parquet"):
        shutil.copy(p, out)
    con = duckdb.connect()
    keys = "CASE WHEN l_linenumber = 2 THEN NULL ELSE l_partkey - 90 END AS l_partkey, CASE WHEN l_linenumber = 3 THEN NULL ELSE -l_suppkey END AS l_suppkey, l_orderkey * 9007199254 - 40 AS l_orderkey"
    con.execute(f"COPY (SELECT * REPLACE ({keys}) FROM '{sf}/lineitem.parquet') TO '{out}/lineitem.parquet' (FORMAT parquet)")
    con.execute(f"COPY (SELECT * REPLACE (CASE WHEN page_id % 2 = 0 THEN html END AS html) FROM '{sf}/pages.parquet') TO '{out}/pages.parquet' (FORMAT parquet)")
    return str(out)


def plain(value):
    return tuple(map(plain, value)) if isinstance(value, (list, tuple)) else round(value, 6) if isinstance(value, float) else value


def same_as_sql(spark, name, folder):
    con = duckdb.connect()
    for p in Path(folder).glob("*.parquet"):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
    want = con.execute(entry.oracle_sql()[name])
    columns = [x[0] for x in want.description]
    got = entry.queries()[name](spark, folder)
    assert sorted(got.columns) == sorted(columns)
    rows = got.select(*columns).collect()
    assert sorted((plain(r) for r in rows), key=repr) == sorted((plain(r) for r in want.fetchall()), key=repr) and rows
    return got


@pytest.mark.parametrize("name", READS)
def test_reads_a_given_table(spark, sf, odd, name):
    for folder in (sf, odd):
        assert "Scan parquet" in same_as_sql(spark, name, folder)._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", [
    "speedup_quoted",
    "strong_efficiency_quoted",
])
def test_quoted_figures_lie_beside_those_of_the_tables(spark, sf, name):
    got = {r.run: r.modelled for r in same_as_sql(spark, name, sf).collect()}
    assert all(x and x > 0 for x in got.values())


def test_selection_rules_see_entries_not_items(spark, sf):
    plan = entry.queries()["cg_admissible"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    above, _, below = plan.partition("Aggregate")
    assert "abs(" in above and "abs(" not in below
