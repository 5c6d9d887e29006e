"""Transport cost from one set of exponentials a round, also where these vanish."""

import numpy as np

from vecmend.operators import upkeep as U


def plain(x, y, blur, rounds):
    c, g = np.sqrt(((x[:, None] - y[None, :]) ** 2).sum(2)), np.zeros(len(y))

    def soft(m, axis):
        high = m.max(axis)
        return high + np.log(np.exp(m - np.expand_dims(high, axis)).sum(axis))

    for _ in range(rounds):
        f = -blur * (soft((g[None, :] - c) / blur, 1) - np.log(len(y)))
        g = -blur * (soft((f[:, None] - c) / blur, 0) - np.log(len(x)))
    f = -blur * (soft((g[None, :] - c) / blur, 1) - np.log(len(y)))
    return (np.exp((f[:, None] + g[None, :] - c) / blur) * c).sum() / c.size


def test_near_and_far_rows_cost_what_the_plain_sums_say(spark):
    rng = np.random.default_rng(4)
    for scale, blur in ((1.0, 0.05), (400.0, 0.05)):  # at the second scale most exponentials are 0
        x, y = rng.normal(size=(60, 4)) * scale, rng.normal(size=(25, 4)) * scale
        a, b = (spark.createDataFrame([(v.tolist(),) for v in z], "vec array<double>").repartition(2) for z in (x, y))
        got = U.sinkhorn(a, b, blur, rounds=6, cells=200).first()
        assert (got.n_a, got.n_b) == (60, 25) and np.isclose(got.distance, plain(x, y, blur, 6), rtol=1e-9)
