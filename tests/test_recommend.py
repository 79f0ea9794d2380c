"""The best items of every user: equal to scoring all pairs, without scoring them all."""

import numpy as np
import pytest

from vertexalg.algorithms import cf


def model_of(spark, p, q):
    frame = lambda x, ids: spark.createDataFrame([(int(i), *map(float, r)) for i, r in zip(ids, x, strict=True)], "id long, " + ", ".join(f"{f} double" for f in cf.fields(p.shape[1])))
    return cf.CFModel(frame(p, range(len(p))), frame(q, range(1000, 1000 + len(q))), [], p.shape[1])


def brute(p, q, rated, n):
    s = np.round(sum(p[:, j : j + 1] * q[None, :, j] for j in range(p.shape[1])), 9)
    out = set()
    for u in range(len(p)):
        order = [i for i in np.lexsort((np.arange(len(q)), -s[u])) if (u, 1000 + i) not in rated and np.isfinite(s[u, i])]
        out |= {(u, r + 1, 1000 + int(i)) for r, i in enumerate(order[:n])}
    return out


@pytest.mark.parametrize("low", [0, -3])  # many equal scores; negative factors too
def test_best_of_all(spark, monkeypatch, low):
    rng = np.random.default_rng(7)
    for name, value in (("GROUP", 40), ("BLOCK", 8), ("STRONG", 3)):
        monkeypatch.setattr(cf, name, value, raising=False)
    p, q = rng.integers(low, 4, (90, 3)) / 2, rng.integers(low, 4, (150, 3)) / 2
    q[4] = np.nan
    rated = {(int(u), 1000 + int(i)) for u, i in zip(rng.integers(0, 90, 900), rng.integers(0, 150, 900), strict=True)} | {(3, 1000 + i) for i in range(147)}
    got = [(r.user, r["rank"], r.item) for r in cf.recommend(model_of(spark, p, q), spark.createDataFrame(sorted(rated), "user long, item long"), 5, users=16).collect()]
    assert len(got) == len(set(got)) and set(got) == brute(p, q, rated, 5)


def test_few_contenders(spark):
    """Copies of items have equal scores, and most items are under the bounds."""
    rng = np.random.default_rng(8)
    p, q = rng.random((300, 4)), np.tile(rng.random((200, 4)), (20, 1))
    rated = spark.createDataFrame([(u, 1000 + u % 200) for u in range(300)], "user long, item long")
    assert cf.contenders(model_of(spark, p, q), rated).count() < 300 * 5 * 3
    assert cf.recommend(model_of(spark, p, q), rated).count() == 1500
