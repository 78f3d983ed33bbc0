"""Queries that once made their data up read the given tables, with the results of their SQL."""

import duckdb
import pytest
from pyspark.errors import AnalysisException

from prefgraph.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events".split()


@pytest.mark.parametrize("name", ["wide_path_ge", "wide_path_gt", "reduction_acyclic_subgraph", "realised_profile"])
def test_same_as_sql_on_a_given_table(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        QUERIES[name](spark, str(tmp_path)).collect()
    got = QUERIES[name](spark, SF)
    db = duckdb.connect()
    db.execute("SET TimeZone='UTC'")
    for t in TABLES:
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = db.execute(f"SELECT {', '.join(got.columns)} FROM ({ORACLES[name]})").fetchall()
    assert sorted(tuple(r) for r in got.collect()) == sorted(want) and want


def test_mallows_ballots_of_customers(spark, tmp_path):
    with pytest.raises(AnalysisException):
        QUERIES["mallows_ballots"](spark, str(tmp_path)).collect()
    rows = QUERIES["mallows_ballots"](spark, SF).collect()
    orders = {r[0] for r in spark.read.parquet(f"{SF}/orders.parquet").select("o_orderpriority").distinct().collect()}
    ballots = {}
    for r in rows:
        ballots.setdefault(r.voter, {})[r.alt] = r.rank
    assert set(ballots) == {str(r[0]) for r in spark.read.parquet(f"{SF}/customer.parquet").select("c_custkey").collect()}
    assert all(set(b) == orders and sorted(b.values()) == list(range(1, len(orders) + 1)) for b in ballots.values())
