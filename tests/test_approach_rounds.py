"""The approach mend goes on until no walk is stuck."""

from vecmend.operators import graph as G
from vecmend.operators import mend as M
from vecmend.operators import truth as T


def test_a_walk_that_is_led_on_a_step_a_round_arrives(spark):
    # from the middle of the line each round leads the walk on by one row
    base = spark.createDataFrame([(i, [float(i), 0.0]) for i in range(20)], "vec_id bigint, vec array<double>").coalesce(1)
    asked = spark.createDataFrame([(0, [19.0, 0.1])], "query_id bigint, vec array<double>").coalesce(1)
    edges = G.as_edges(spark.createDataFrame([(0, 1)], "src bigint, dst bigint"))
    near = T.exact_blocked(base, asked, 3, "l2").localCheckpoint()
    mended = M.approach(base, edges, asked, near, 1, 1, 1, "l2")
    assert M.stuck(base, mended, asked, near, 1, 1, "l2").isEmpty()
    assert mended.where("kind = 'extra'").groupBy("src").count().where("count > 1").isEmpty()
