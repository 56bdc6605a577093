"""What the second round mended, each against brute force or by hand."""

import pytest
from pyspark.sql import functions as F

from cellgraph.llm import exact_stream, jaccard_join, langid, packing
from test_operators import components_by_hand, near_copies, table

A, B = " ".join(f"a{k}" for k in range(60)), " ".join(f"b{k}" for k in range(60))


@pytest.mark.parametrize("one", [None, 5])
def test_links_of_repeated_and_null_ids(spark, one):
    """Two texts under one id (or none) keep their own links."""
    rows = [(one, A), (one, B), (1, A + " x"), (2, B + " y"), (3, "alone here")]
    got = sorted((r["doc_id"] or -1, r["component_id"]) for r in jaccard_join.jaccard_components(table(spark, rows)).collect())
    assert got == sorted([(one or -1, 1), (one or -1, 2), (1, 1), (2, 2), (3, 3)])
    df = table(spark, rows).withColumns({"_id": F.lit("mine"), "T1": F.lit(1)})
    kept = jaccard_join.keep_one_of_each(df)
    assert kept.columns == ["doc_id", "text", "_id", "T1"]
    assert sorted((r["doc_id"], r["text"]) for r in kept.collect()) == [(1, A + " x"), (2, B + " y"), (3, "alone here")]


def test_rows_without_any_id_and_twins(spark):
    rows = [(None, A), (None, A + " x"), (None, B), (7, "q"), (7, "q"), (8, None), (8, None), (None, "")]
    kept = sorted(((r["doc_id"] or -1, r["text"] or "") for r in jaccard_join.keep_one_of_each(table(spark, rows)).collect()))
    assert len([x for x in kept if x[1].startswith("a0")]) == 1
    assert [x for x in kept if not x[1].startswith("a0")] == sorted([(-1, B), (7, "q"), (8, ""), (8, ""), (-1, "")])


def test_hot_copies_and_very_long_text(spark):
    """A text that holds most rows goes through the broadcast of hot sets."""
    rows = [(k, A) for k in range(300)] + [(1000 + k, f"only {k} of its kind {k * k}") for k in range(40)] + near_copies(20, 9)
    rows = [(i + 5000 * (k >= 340), t) for k, (i, t) in enumerate(rows)] + [(9000, "w " * 200_000), (9001, "w " * 200_001)]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(table(spark, rows)).collect()}
    assert got == components_by_hand(dict(rows), 80, 5)


def test_exact_dedup_leaves_other_columns_alone(spark):
    rows = [(1, "a b", 1), (2, "ab", 2), (3, "long " * 300_000, 3), (3, "long " * 300_000, 4), (None, None, 5), (None, "", 6)]
    df = table(spark, rows, "doc_id long, text string, k long").withColumns({n: F.col("k") for n in ("_file", "_row", "_own_sha", "_gone_id", "_metadata", "key")})
    kept = exact_stream.keep_firsts(df)
    assert kept.columns == df.columns
    assert {(r["doc_id"], r["_metadata"] == r["_own_sha"] == r["k"]) for r in kept.collect()} == {(1, True), (3, True), (None, True)}
    assert kept.count() == 3
    path = exact_stream.shared_dir(spark, "scan")
    df.drop("_metadata").write.parquet(path)
    again = exact_stream.keep_firsts(spark.read.parquet(path).filter("k > 0"))
    assert again.columns == df.drop("_metadata").columns and again.count() == 3


def test_hot_digest_goes_by_broadcast(spark):
    rows = [(k, "same text" if k % 2 else f"text {k}") for k in range(4000)]
    got = exact_stream.dedup_exact(table(spark, rows)).groupBy("group_size", "kept").count().collect()
    assert {(r["group_size"], r["kept"]): r["count"] for r in got} == {(1, True): 2000, (2000, True): 1, (2000, False): 1999}


def slow_best_fit(pieces, capacity):
    """The packing rule, bin by bin: (bin, offset) of (n, source, cluster) in order."""
    bins, out = [], []
    for n, source, cluster in pieces:
        fits = [(capacity - b[0] - n, k) for k, b in enumerate(bins) if b[0] < capacity and b[0] + n <= capacity and (source is None or source not in b[1]) and (cluster is None or cluster not in b[2])]
        k = min(fits)[1] if fits else len(bins)
        if not fits:
            bins.append([0, set(), set()])
        out.append((k, bins[k][0]))
        bins[k][0] += n
        bins[k][1].add(source)
        bins[k][2].add(cluster)
    return out


def test_whole_packing_against_brute_force(spark):
    """Sources, duplicate clusters, long texts and ids of bins, on one shard."""
    import numpy as np

    rng = np.random.default_rng(8)
    rows = [(int(i), int(rng.integers(1, 230)), None if i % 11 == 0 else f"s{i % 5}", f"c{int(rng.integers(0, 25))}") for i in range(300)]
    df = table(spark, rows, "doc_id long, n_tokens long, source string, cluster string")
    got = {(r["doc_id"], r["piece"]): (r["bin_id"], r["bin_offset"], r["n_tokens"]) for r in packing.pack_documents(df, 64).collect()}
    rest = sorted(((-(n % 64), i, n // 64, s, c) for i, n, s, c in rows if n % 64), key=lambda x: x[:3])
    often = {c for _, _, _, c in rows}
    placed = slow_best_fit([(-n, s, c if c in often else None) for n, _, _, s, c in rest], 64)
    for (n, i, piece, _, _), (k, at) in zip(rest, placed, strict=True):
        assert got[i, piece] == (k, at, -n)
    full = sorted((i, p) for i, n, _, _ in rows for p in range(n // 64))
    bins = max(k for k, _ in placed) + 1
    assert [got[x] for x in full] == [(bins + k, 0, 64) for k in range(len(full))] and len(got) == len(full) + len(rest)
    fill = packing.fill_rate(packing.pack_documents(df, 64), 64).first()
    assert fill["bins"] == bins + len(full) and abs(fill["fill"] - sum(n for _, n, _, _ in rows) / (64 * fill["bins"])) < 1e-12


def test_short_texts_of_a_learned_language_stay(spark):
    rows = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = langid.fit(rows.select("doc_id", "text", "lang"))
    words = rows.filter("lang IS NOT NULL AND text IS NOT NULL").selectExpr("doc_id", "lang", "element_at(filter(split(text, '[^\\\\p{L}]+'), x -> length(x) > 1), 1) AS text").filter("text IS NOT NULL")
    got = langid.identify(words.withColumn("_found", F.lit(1)), model).toPandas()
    assert len(got) > 500 and got.lang_rejected.mean() < 0.02
    far = langid.identify(table(spark, [(1, "это совсем другой язык и другие буквы, которых здесь никто не учил " * 5), (2, "zqxj vkwq xzzq qjxv kqzx wvqj " * 30)]), model).collect()
    assert all(r["lang_rejected"] for r in far)


def centroids_by_hand(texts, model):
    """Nearest centroid from plain trigram counts, text by text."""
    import numpy as np

    out = {}
    for i, t in texts.items():
        raw = np.frombuffer((t or "").encode(), np.uint8)
        counts = langid.bin_counts(raw, np.array([0, len(raw)]))[0].astype(float)
        v = [np.log1p(c) * w for c, w in zip(counts, model.idf)]
        norm = sum(x * x for x in v) ** 0.5
        best = max(((sum(a * b for a, b in zip(v, c)) / norm if norm else 0.0, -k) for k, c in enumerate(model.centroids)), default=(0, 0))
        out[i] = model.langs[model.owner[-best[1]]], best[0]
    return out


def test_predictions_are_those_of_the_nearest_centroid(spark):
    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").filter("doc_id % 10 = 0 AND text RLIKE '[a-z]'")
    model = langid.fit(spark.read.parquet("/root/testdata/sf0.001/documents.parquet").filter(~langid.held_out(4, 2)))
    want = centroids_by_hand({r["doc_id"]: r["text"] for r in rows.collect()}, model)
    for r in langid.identify(rows, model).collect():
        assert abs(r["lang_score"] - want[r["doc_id"]][1]) < 1e-4 and r["lang_pred"] == want[r["doc_id"]][0]
