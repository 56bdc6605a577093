"""the language model is learned from every training row."""

import numpy as np
from cellgraph.llm import langid


def test_model_uses_every_row_however_rows_are_dealt(spark):
    words = {"aa": "alpha beta gamma delta", "bb": "uno dos tres cuatro"}
    rows = [(i, f"{words[g]} {'xyz' * (i % 5)} {i}", g) for i, g in enumerate(["aa", "bb"] * 700)]
    rows += [(9000, "qwvx kjzh " * 9, "bb"), (9001, None, "aa"), (9002, "12 34", "bb"), (9003, "lost", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    one, other = langid.fit(df.repartition(1)), langid.fit(df.repartition(7, "doc_id"))
    assert (one.centroids == other.centroids).all() and (one.idf == other.idf).all() and (one.threshold == other.threshold).all()
    # 700 rows a language are more than the former sample; the odd one has a centroid near it
    got = langid.identify(spark.createDataFrame([(1, "qwvx kjzh " * 9)], "doc_id long, text string"), one).first()
    assert got["lang_pred"] == "bb" and got["lang_score"] > 0.9
    without = langid.fit(df.filter("doc_id <> 9000"))
    assert not np.array_equal(without.centroids, one.centroids)
