import pytest

from jointsem import catalog
from jointsem.workloads import workload


@pytest.mark.parametrize(("name", "of"), [("score_matching", "S4"), ("score_independent", "S4"), ("contextual_summaries", "W4"), ("embedding_kmeans", "W4"), ("keyphrase_kmeans", "W4"), ("semantic_group_by", "W4")])
def test_operator_queries_see_whole_tables(spark, monkeypatch, name, of):
    """Every record gets an answer, whatever a sample would hold."""
    sf = "/root/testdata/sf0.001"
    monkeypatch.setattr(catalog, "evaluation_sample", lambda df, *a: df.limit(10))
    ids = [r.id for r in getattr(catalog, name)(spark, sf).select("id").collect()]
    assert sorted(ids) == sorted(r.id for r in workload(spark, sf, of).records.select("id").collect())


def test_pairwise_accuracy_of_all_orders(spark):
    """Equal to the SQL, and to its count over all pairs where orders go beyond key 4000."""
    duckdb = pytest.importorskip("duckdb")
    sf = "/root/testdata/sf0.01"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW orders AS SELECT * FROM '{sf}/orders.parquet'")
    got = catalog.queries()["metric_pairwise_whole"](spark, sf).first()[0]
    pairs = catalog.oracle_sql()["metric_pairwise"].replace(" AND o_orderkey <= 4000", "")
    assert got == pytest.approx(con.execute(catalog.oracle_sql()["metric_pairwise_whole"]).fetchone()[0], abs=1e-9)
    assert got == pytest.approx(con.execute(pairs).fetchone()[0], abs=1e-9)
