"""The transport cost reads all rows."""

from vecmend.operators import upkeep as U


def test_transport_cost_takes_every_row_in_blocks(spark):
    a = spark.createDataFrame([(i, [i / 100, 0.0]) for i in range(300)], "query_id bigint, vec array<double>").repartition(3)
    moved = a.selectExpr("query_id", "array(vec[0], vec[1] + 3.0D) AS vec")
    got = U.sinkhorn(a, moved, blur=0.05, rounds=5, block=64).first()
    assert (got.n_a, got.n_b) == (300, 300) and abs(got.distance - 3.0) < 0.05
