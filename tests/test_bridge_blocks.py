"""The bridge baseline reads every block of its history."""

from vecmend.operators import graph as G
from vecmend.sources import families as D


def test_bridge_takes_every_block_of_history(spark, tiny):
    base, q = D.sphere(spark, tiny)
    base, history = base.where("vec_id < 60").cache(), q.where("role = 'history'").limit(40).cache()
    one = {(r.src, r.dst) for r in G.query_bridge(base, history, 8, 4, 10).collect()}
    assert {(r.src, r.dst) for r in G.query_bridge(base, history, 8, 4, 10, block_bytes=8 * 64 * 7).collect()} == one
