"""The search misses nothing on rows whose codes tell little."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from segsum.llm import ann


def crowded(rng):
    """Crowds of near copies, far more than the pool."""
    centres = rng.normal(size=(4, 32))
    return centres[rng.integers(0, 4, 3000)] + rng.normal(scale=1e-3, size=(3000, 32))


def uneven(rng):
    """Norms over many magnitudes, one component that outweighs the others."""
    x = rng.normal(size=(3000, 32)) * np.exp(rng.normal(scale=2, size=(3000, 1)))
    x[:, 0] += 50
    return x


def repeated(rng):
    """Copies in groups of a thousand: ties by id."""
    return np.repeat(rng.normal(size=(3, 32)), 1000, axis=0)


@pytest.mark.parametrize("make", [crowded, uneven, repeated, lambda rng: crowded(rng) * 1e-25, lambda rng: -np.abs(crowded(rng)) * np.where(np.arange(3000) % 20, 1, -1)[:, None]])
def test_every_true_neighbour_is_found(spark, make):
    x = make(np.random.default_rng(5))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = {}
    for r in ann.nearest(df, F.col("vec_id") % 20 == 0, shard_rows=1500).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
    assert len(got) == 150
    for q, found in got.items():
        true = np.einsum("nd,d->n", x, x[q])
        true[q] = -np.inf
        want = np.lexsort((np.arange(len(x)), -true))[:20]
        assert [i for i, _ in found] == want.tolist()
        assert np.allclose([s for _, s in found], true[want], rtol=1e-12)
