import numpy as np
import pytest

from segsum.llm import embed_dedup


def crowded(spark, n=600, dim=6):
    """Points around a few directions, many of them across the borders of bands."""
    rng = np.random.default_rng(8)
    x = rng.normal(size=(12, dim))[rng.integers(0, 12, n)] + rng.normal(size=(n, dim)) * 0.12
    x = x.astype(np.float32)
    return x.astype(float), spark.createDataFrame([(i, x[i].tolist(), i % 2) for i in range(n)], "vec_id long, embedding array<float>, label int")


@pytest.mark.parametrize("axes", [None, 1, 2, 3, 4])
def test_links_are_the_same_with_any_number_of_axes(spark, axes):
    x, df = crowded(spark)
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    label = np.arange(len(x)) % 2
    want = ((unit @ unit.T >= 0.98) & (label[:, None] == label[None, :])).sum(1) - 1
    got = {r["vec_id"]: r["n_links"] for r in embed_dedup.near_duplicates(df, tile=16, axes_taken=axes).collect()}
    assert want.sum() > 2000 and [got[i] for i in range(len(x))] == want.tolist()
