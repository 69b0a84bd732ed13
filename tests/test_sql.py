import pytest

from spreadlab import sql
from spreadlab.sources import graphs as G


def test_sql_surface(spark):
    sql.register(spark)
    rows = spark.sql("SELECT * FROM strata(array(0.6D, 0.3D), 'staircase')").collect()
    assert [r.pi for r in rows] == pytest.approx([0.28, 0.60, 0.12])
    assert [r.status for r in rows] == [[0, 0], [1], [0, 1]]
    G.example(spark).createOrReplaceTempView("example_edges")
    got = sql.influence(spark, "example_edges", 5, "stair_recursive_bfs", n=2000, r=3).collect()[0]
    assert got.f_hat == pytest.approx(2.020416, abs=0.1)
