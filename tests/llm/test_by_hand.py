"""Scores by hand, and long texts and odd columns beside the operators' own."""

import math
import re

import numpy as np
from pyspark.sql import functions as F

from cellgraph.llm import decontam, langid, packing, pu_toxicity, scan
from test_operators import table


def hash_of(word: bytes) -> int:
    return int(scan.word_hashes(np.frombuffer(word, np.uint8), np.array([0]), np.array([len(word)]))[0])


def test_toxicity_scores_are_those_of_the_words(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet").select("doc_id", "toxic")
    model = pu_toxicity.fit(docs.filter(~langid.held_out(5, 0)), labels.filter(~langid.held_out(5, 0)))
    assert len(model.words)
    weight = dict(zip(model.words.tolist(), model.weights.tolist(), strict=True))
    rows = docs.unionByName(table(spark, [(-1, None), (-2, ""), (-3, "12 !?"), (-4, "Idiot idiot " * 100_000)]))
    texts = {r["doc_id"]: r["text"] for r in rows.collect()}
    scores = [(r["doc_id"], r["tox_score"], r["w"]) for r in pu_toxicity.score(rows.withColumns({"w": F.lit(1), "tox_score": F.lit("old")}), model).collect()]
    assert len(scores) == len(texts)
    for i, got, kept in scores:
        traits = set()
        for word in set(re.findall(rb"[A-Za-z\x80-\xff]+", (texts[i] or "").encode())):
            word = bytes(b + 32 if 65 <= b <= 90 else b for b in word)
            traits.add(hash_of(word))
            traits |= {hash_of(word[:n]) ^ (0x9E37 * n) for n in pu_toxicity.PREFIXES if len(word) > n}
        logit = model.bias + sum(weight.get(t, 0.0) for t in traits)
        assert kept == 1 and abs(got - 1 / (1 + math.exp(-max(-35, min(35, logit))))) < 1e-9


def test_training_lowers_the_non_negative_risk():
    rng = np.random.default_rng(1)
    words = np.sort(rng.integers(0, 1 << 62, 300).astype(np.uint64))
    common, bad = words[:280], words[280:]
    pos = [np.unique(np.concatenate([rng.choice(common, 30), rng.choice(bad, 4)])) for _ in range(150)]
    unl = [np.unique(rng.choice(common, 30)) for _ in range(850)] + pos[:100]
    prior = 100 / 950
    model = pu_toxicity.train_nnpu(pos, unl, prior)
    weight = dict(zip(model.words.tolist(), model.weights.tolist(), strict=True))
    loss = lambda docs, sign: sum(math.log1p(math.exp(-sign * (model.bias + sum(weight.get(w, 0.0) for w in d.tolist())))) for d in docs) / len(docs)
    risk = prior * loss(pos, 1) + max(0.0, loss(unl, -1) - prior * loss(pos, -1))
    assert 0 <= risk < 0.1 * math.log(2)  # a classifier of zeros has log 2


def test_long_texts_and_columns_of_clashing_names(spark):
    item = "one two three four five six seven eight nine ten eleven"
    filler = "word " * 600_000
    rows = [(1, filler + item.upper() + " " + filler), (2, filler), (2, filler), (None, None), (3, "")]
    wide = table(spark, rows).withColumns({c: F.lit("mine") for c in ("source", "shard", "piece", "n_words", "n_hit", "spans", "_held", "cluster", "n_tokens")})
    bench = table(spark, [(7, item), (8, None), (7, item)], "item_id long, text string").withColumns({"doc_id": F.lit(5), "n_hit": F.lit("x")})
    hits = {(r["doc_id"], r["n_words"]): (r["n_hit"], len(r["item_ids"])) for r in decontam.scan_documents(wide, bench).collect()}
    assert hits == {(1, 1_200_011): (11, 1), (2, 600_000): (0, 0), (None, 0): (0, 0), (3, 0): (0, 0)}
    clean = decontam.clean_documents(wide, bench)
    assert clean.columns == wide.columns and sorted(r["doc_id"] or 0 for r in clean.select("doc_id").collect()) == [0, 2, 2, 3]
    placed = packing.pack_texts(wide, 2048).toPandas()
    assert placed.n_tokens.sum() == 1_200_012 + 2 * 600_001 + 2 and placed.groupby("bin_id").n_tokens.sum().max() <= 2048
    assert packing.pack_texts(wide.limit(0)).count() == 0 and decontam.scan_documents(wide.limit(0), bench).count() == 0
