"""Costs, budgets and cells are those of a table: with other rows they are others."""

import duckdb
import pytest

from codecut.plans import load_queries
from codecut.plans.registry import ORACLE_SQL, QUERIES

load_queries()
NAMES = ["cost_bound", "cost_by_dim", "cost_models_baselines", "cost_training", "encoder_params_budget", "grid_cells"]


@pytest.mark.parametrize("name", NAMES)
def test_of_the_table(spark, sf, tmp_path, name):
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    e.where("vec_id % 10 < 3 and label < 4").coalesce(1).write.parquet(f"{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.sql(f"create view embeddings as select * from '{tmp_path}/embeddings.parquet/*.parquet'")
    rel = con.sql(ORACLE_SQL[name])
    rows = [tuple(r) for r in QUERIES[name](spark, str(tmp_path)).select(*rel.columns).collect()]
    assert sorted(rows) == sorted(rel.fetchall())
    if name != "encoder_params_budget":
        assert sorted(rows) != sorted(tuple(r) for r in QUERIES[name](spark, sf).select(*rel.columns).collect())
