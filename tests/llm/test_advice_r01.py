"""What the first review found cut short, each against brute force."""

import numpy as np

from cellgraph.llm import ef_ngram, jaccard_join
from test_operators import DOCS, components_by_hand, table


def test_near_stage_takes_five_words_and_eighty_percent(spark):
    import corpus_pipeline as c

    words = [f"w{k}" for k in range(60)]
    texts = {1: words, 2: words[:55] + [f"x{k}" for k in range(5)], 3: words[:40] + [f"y{k}" for k in range(20)], 4: [f"z{k}" for k in range(60)]}
    texts = {i: " ".join(w) for i, w in texts.items()}
    df = table(spark, [(i, t, "en", "s", len(t), "m", "k") for i, t in texts.items()], DOCS)
    wide, narrow = components_by_hand(texts, 80, 5), components_by_hand(texts)
    assert wide[2][1] == 1 and narrow[2][1] == 2  # linked by 5 words and 80 % only
    assert {r["doc_id"] for r in c.near_dedup(spark, df, "").collect()} == {i for i, (_, root) in wide.items() if i == root} == {1, 3, 4}
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(df, width=5, percent=80).collect()}
    assert got == wide


def test_pool_leaves_every_prefix_a_choice():
    for percent in (50, 80, 85, 95):
        share = int(jaccard_join.pool_limit(percent)) / (1 << 63)
        assert abs(share - 4 / 3 * (1 - percent / 100)) < 1e-9
        assert share * 1000 > 1.3 * (jaccard_join.prefix_length(1000, percent) - 1)


def test_language_model_keeps_pairs_seen_once(spark):
    rows = [(k, f"alpha{k} beta{k}", False) for k in range(6)] + [(10, "alpha3 beta3", True), (11, "alpha3 beta4", True)]
    df = table(spark, rows, "doc_id long, text string, held_out boolean")
    manifest = ef_ngram.build_model(df.filter("NOT held_out"))
    got = {r["doc_id"]: r["score"] for r in ef_ngram.score_texts(df, manifest).collect()}
    assert got[10] > got[11] + 0.5  # the two differ only in whether the pair was seen, once


def test_rare_pairs_of_frequent_words_are_not_rounded_up():
    for c in (1e4, 1e8, 1e10):
        p = (1 - ef_ngram.DISCOUNT) / c
        assert 0.8 * p < ef_ngram.CODEBOOK[ef_ngram.quantise(np.array([p]))[0]] <= p * (1 + 1e-9)
