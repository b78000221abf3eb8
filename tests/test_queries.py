"""A few queries against their SQL on the smallest tables; the driver runs them all."""

import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

SF = Path("/root/testdata/sf0.001")


@pytest.mark.skipif(not SF.exists(), reason="no tables here")
@pytest.mark.parametrize("name", ["product_supplier_customer", "product_random_placement", "gram_parts", "nmf_h_update", "pagerank_part_graph", "nodes_without_inlinks"])
def test_query_equals_sql(spark, name):
    import __spark_entry__ as entry

    db = duckdb.connect()
    for f in SF.glob("*.parquet"):
        db.sql(f"CREATE VIEW {f.stem} AS SELECT * FROM '{f}'")
    want = db.sql(entry.oracle_sql()[name])
    got = entry.queries()[name](spark, str(SF)).select(*want.columns).collect()
    assert sorted(map(tuple, got), key=str) == sorted(want.fetchall(), key=str)


def test_names_can_be_read_without_a_session():
    code = "import __spark_entry__ as e; assert set(e.oracle_sql()) <= set(e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).resolve().parents[1], check=True, timeout=120)
