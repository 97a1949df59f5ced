from segsum.llm import toxicity


def test_no_expression_goes_by_the_size_of_the_table(spark, monkeypatch):
    docs = spark.createDataFrame([(i, f"common words {'bad' if i % 2 else 'good'} end") for i in range(400)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(400)], "doc_id long, toxic int")
    whole = len(toxicity.fit(docs, labels).keys)
    monkeypatch.setattr(toxicity, "MOST", 1, raising=False)
    again = toxicity.fit(docs, labels)
    assert len(again.keys) == whole > 10
