"""Queries that made their data up work on a given table."""

import duckdb
import pytest

from privgrove.queries import registry


def test_noise_variance_of_the_groups_of_a_table(spark, sf_dir):
    db = duckdb.connect()
    db.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{sf_dir}/lineitem.parquet'")
    got, want = registry.QUERIES["a08_noise_variance"](spark, sf_dir).collect(), db.execute(registry.SQL["a08_noise_variance"]).fetchall()
    assert sorted(map(tuple, got)) == sorted(want) and sum(r["n"] for r in got) == db.execute("SELECT count(*) FROM lineitem").fetchone()[0]


@pytest.mark.parametrize("name, eps", [("m01_audit_exponential", 1.0), ("m01_audit_laplace", 0.5)])
def test_audits_have_a_run_for_every_row_of_a_table(spark, sf_dir, name, eps):
    out = registry.QUERIES[name](spark, sf_dir)
    assert [f.rsplit("/", 1)[1] for f in out.inputFiles()] == ["lineitem.parquet"]
    rows = out.collect()
    assert rows and all(r["log_ratio"] - 1.5 * r["error"] <= eps for r in rows)
    if name == "m01_audit_exponential":
        assert sum(r["n_one"] for r in rows) == spark.read.parquet(f"{sf_dir}/lineitem.parquet").count()
