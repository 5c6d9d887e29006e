"""Transport potentials get to the fixed point of the plain rounds, from a start in single precision too."""

import numpy as np

from vecmend.operators import upkeep as U


def plain(x, y, blur, rounds):
    c = np.sqrt(((x[:, None] - y[None]) ** 2).sum(2))
    g = np.zeros(len(y))
    for _ in range(rounds):
        m = (g - c) / blur
        f = -blur * (m.max(1) + np.log(np.exp(m - m.max(1)[:, None]).mean(1)))
        m = (f[:, None] - c) / blur
        g = -blur * (m.max(0) + np.log(np.exp(m - m.max(0)).mean(0)))
    m = (g - c) / blur
    m = np.exp(m - m.max(1)[:, None])
    return float(((m * c).sum(1) / m.sum(1)).mean())


def test_transport_gets_to_the_fixed_point(spark):
    rng = np.random.default_rng(12)
    x, y = rng.normal(size=(90, 3)), rng.normal(size=(60, 3)) + 0.3
    a, b = (spark.createDataFrame([(v.tolist(),) for v in z], "vec array<double>") for z in (x, y))
    want = plain(x, y, 0.05, 20000)
    assert abs(plain(x, y, 0.05, 200) - want) > 1e-6
    assert abs(U.sinkhorn(a, b).first().distance - want) < 1e-9
    assert abs(U.sinkhorn(a, b, many=0, cells=999).first().distance - want) < 1e-9
    assert abs(U.sinkhorn(a, b, rounds=7).first().distance - plain(x, y, 0.05, 7)) < 1e-9
