"""What op7_toxicity may learn from."""

from sortbit.llm import toxicity


def test_samples_are_not_cut_below_their_bounds(spark, monkeypatch):
    bounds = []

    def sample(df, id_col, bound, seed=0):
        bounds.append(bound)
        return df

    monkeypatch.setattr(toxicity, "bounded_sample", sample)
    df = spark.createDataFrame([(i, f"word{i % 7} horrid villain" if i % 2 else f"word{i % 7} kind friend") for i in range(60)], "doc_id long, text string")
    toxicity.fit(df, df.selectExpr("doc_id", "cast(doc_id % 2 as int) AS toxic"))
    assert bounds == [3000, 6000]
