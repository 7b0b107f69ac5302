import duckdb
import pytest

import __spark_entry__ as entry
from pathwindow import catalog

SF = "/root/testdata/sf0.001"
FAST = ["dedupe_edges", "win_rank_family", "join_asof_latest", "discretize_power_4", "converge_pivot_3", "graph_profile_customer_part", "agg_cube"]


def test_entry_and_names(spark):
    assert set(catalog.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).columns == ["v", "dist"]


@pytest.mark.parametrize("name", FAST)
def test_query_matches_sql(spark, name):
    con = duckdb.connect()
    for table in ("lineitem", "orders", "events", "part", "customer", "supplier", "nation"):
        con.sql(f"CREATE VIEW {table} AS SELECT * FROM '{SF}/{table}.parquet'")
    got, want = catalog.queries()[name](spark, SF).toPandas(), con.sql(catalog.oracle_sql()[name]).df()
    columns = sorted(want.columns)
    rows = lambda f: sorted(map(str, f[columns].astype(object).where(f[columns].notna(), None).apply(lambda r: [None if v is None else round(float(v), 6) if not isinstance(v, str) else v for v in r], axis=1)))
    assert sorted(got.columns) == columns and rows(got) == rows(want)


def test_names_can_be_read_without_a_session():
    import subprocess
    import sys

    code = "import __spark_entry__ as e; assert e.queries() and e.oracle_sql()"
    assert subprocess.run([sys.executable, "-c", code], timeout=120).returncode == 0


TABLED = ["edge_list_rejects", "graph_profile_brick_wall_30_30", "edges_brick_wall_30_30", "edges_kron_10_4", "edges_kron_10_8", "edges_kron_10_16", "edges_kron_10_32", "edges_lattice_30_30", "edges_path_300", "edges_star_200", "edges_unif_10_16"]


@pytest.mark.parametrize("name", TABLED)
def test_query_follows_its_table(spark, tmp_path, name):
    """Without rows in the tables nothing comes out: the job runs over them, not over made-up rows."""
    for table in ("customer", "part", "events"):
        spark.read.parquet(f"{SF}/{table}.parquet").limit(0).write.parquet(f"{tmp_path}/{table}.parquet")
    assert {tuple(r) for r in catalog.queries()[name](spark, str(tmp_path)).collect()} <= {(0,), (None,) * 6}
    test_query_matches_sql(spark, name)
