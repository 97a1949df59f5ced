import pytest
from pyspark.sql import functions as F

from segsum.llm import ann, embed_dedup


@pytest.mark.parametrize("odd", [[1.0] * 5, [float("nan")] * 5])
def test_one_longer_vector_leaves_the_others_in(spark, odd):
    rows = [(i, [1.0, i % 3, 0.5, i % 2], 1) for i in range(12)] + [(99, odd, 1)]
    df = spark.createDataFrame([(i, [float(x) for x in v], c) for i, v, c in rows], "vec_id long, embedding array<float>, label int")
    links = {r["vec_id"]: r["n_links"] for r in embed_dedup.near_duplicates(df).collect()}
    assert links == {i: 1 if i < 12 else 0 for i in [*range(12), 99]}
    found = ann.nearest(df, F.col("vec_id") == 0, k=3).collect()
    assert len(found) == 3 and all(r["query_id"] == 0 and 0 < r["vec_id"] < 12 for r in found)
