"""A sample of registered queries against DuckDB at the smallest scale."""

import duckdb
import pytest

from privgrove.queries import registry
from privgrove.sources.io import TABLES

NAMES = ["m18_dp_histogram", "m19_private_cuts", "m21_candidates", "m22_dp_split", "m25_noisy_average", "m30_seeded_private_stump", "j08_as_of_join", "g07_cube", "t02_daily_counts", "u01_pandas_scoring", "w03_rows"]


@pytest.mark.parametrize("name", NAMES)
def test_same_rows_as_duckdb(spark, sf_dir, name):
    db = duckdb.connect()
    for t in TABLES:
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    got, want = registry.QUERIES[name](spark, sf_dir).toPandas(), db.execute(registry.SQL[name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    plain = lambda v: None if v is None or v != v else float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)
    rows = lambda df: sorted((tuple(plain(v) for v in r) for r in df[cols].itertuples(index=False)), key=repr)
    assert rows(got) == rows(want)


@pytest.mark.parametrize("how", ["left", "right", "full"])
def test_outer_joins_keep_every_row_of_the_outer_side(spark, sf_dir, how):
    rows = registry.QUERIES[f"j03_{how}_outer"](spark, sf_dir).toPandas()
    customers, orders = (spark.read.parquet(f"{sf_dir}/{t}.parquet").count() for t in ("customer", "orders"))
    assert (rows.iloc[:, 0].nunique() == customers) == (how != "right") and (rows.iloc[:, 1].nunique() == orders) == (how != "left")
    assert rows.isna().any().tolist() == [how != "left", how != "right"]
    db = duckdb.connect()
    for t in ("customer", "orders"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    got = [tuple(r) for r in registry.QUERIES[f"j03_{how}_outer"](spark, sf_dir).collect()]
    assert sorted(got, key=repr) == sorted(db.execute(registry.SQL[f"j03_{how}_outer"]).fetchall(), key=repr)
