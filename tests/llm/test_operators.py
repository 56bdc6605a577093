"""Operators of the training-data subpackage against brute force, round trips and edge cases."""

import hashlib
import io
import math
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from cellgraph.llm import chat_pref, components, decontam, ef_ngram, exact_stream, jaccard_join, langid, packing, pu_toxicity, scan, storage, suffix_levels, warc_zstd

SMALL = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, _metadata_x string, key string"


def table(spark, rows, schema="doc_id long, text string"):
    return spark.createDataFrame(rows, schema)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SMALL}/documents.parquet")


def texts_of(df):
    return {r["doc_id"]: (r["text"] or "") for r in df.select("doc_id", "text").collect()}


def fold(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text)


# ------------------------------------------------------------------------------- scanning


def test_word_borders_and_hashes():
    column = pa.array(["Ab  cd", None, "", "ef\tAB é"])
    (lo, hi, data, starts), = scan.blocks(column)
    begin, end, doc = scan.words(data, starts, scan.NOT_SPACE)
    raw = data.tobytes()
    assert (lo, hi) == (0, 4)
    assert [raw[a:b] for a, b in zip(begin, end)] == [b"Ab", b"cd", b"ef", b"AB", "é".encode()]
    assert doc.tolist() == [0, 0, 3, 3, 3]
    h = scan.word_hashes(data, begin, end)
    assert h[0] == h[3] != h[1]
    assert int(h[2]) == scan.hash_bytes(b"ef")


# ----------------------------------------------------------------------- 1 chat formatting


def test_preferences_share_prompt_and_mask(spark):
    rows = [(1, s, 0, "user", "hi") for s in ("chosen", "rejected")] + [(1, "chosen", 1, "assistant", "good"), (1, "rejected", 1, "assistant", None), (1, "rejected", 2, "user", "why"), (2, "chosen", 0, None, "x")]
    got = {r["pair_id"]: r for r in chat_pref.format_preferences(table(spark, rows, "pair_id long, side string, turn long, role string, text string")).collect()}
    one = got[1]
    assert one["prompt"] == "<|im_start|>user\nhi<|im_end|>\n" and one["n_prompt_turns"] == 1
    assert one["chosen"] == "<|im_start|>assistant\ngood<|im_end|>\n"
    trained = ["".join(one["chosen"][m["begin"] : m["begin"] + m["length"]] for m in one["chosen_mask"] if m["train"])]
    assert trained == ["good<|im_end|>\n"]
    assert sum(m["length"] for m in one["rejected_mask"]) == len(one["rejected"])
    assert got[2]["rejected"] == "" and got[2]["prompt"] == "" and got[2]["chosen"].startswith("<|im_start|>\nx")


def test_preferences_of_an_empty_table(spark):
    assert chat_pref.format_preferences(chat_pref.neighbour_pairs(table(spark, [], "conv_id long, turn long, role string, text string, pair_id string"))).count() == 0


# ------------------------------------------------------------------- 2 repeated byte strings


def repeats_by_hand(texts, length):
    seen, out = set(), {}
    for i in sorted(texts):
        b = texts[i].encode()
        edge = np.zeros(len(b) + 1, int)
        for p in range(len(b) - length + 1):
            w = b[p : p + length]
            if w in seen:
                edge[p] += 1
                edge[p + length] -= 1
            seen.add(w)
        gone = np.cumsum(edge[:-1]) > 0
        kept = bytes(np.frombuffer(b, np.uint8)[~gone]) if b else b""
        out[i] = len(b), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(kept).hexdigest()
    return out


@pytest.mark.parametrize("options", [dict(), dict(shard_bytes=20_000, batches=5)])
def test_repeats_match_brute_force(spark, docs, options):
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_levels.remove_repeats(docs, **options).collect()}
    assert got == repeats_by_hand(texts_of(docs), 100)


def test_repeats_in_periodic_and_degenerate_texts(spark):
    rng = np.random.default_rng(1)
    rows = [(i, "".join(rng.choice(list("ab"), int(rng.integers(0, 300))))) for i in range(40)] + [(100, "x" * 400), (101, "x" * 300), (102, None), (103, "ab" * 200), (104, ""), (105, "é" * 90)]
    df = table(spark, rows)
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_levels.remove_repeats(df, length=24, gram=12, shard_bytes=2000).collect()}
    assert got == repeats_by_hand(texts_of(df), 24)
    again = suffix_levels.remove_repeats(table(spark, [(1, "q" + "z" * 150), (1, "q" + "z" * 150), (None, "k" * 10)])).collect()
    assert len(again) == 3 and len({r["kept_sha256"] for r in again if r["doc_id"] == 1}) == 1
    assert suffix_levels.remove_repeats(table(spark, [])).count() == 0


def test_level_family_marks_all_but_the_earliest():
    rng = np.random.default_rng(3)
    text = rng.integers(97, 100, 900).astype(np.uint8)
    family, marked = suffix_levels.LevelFamily(8), []
    for lo in (600, 300, 0):  # later batches may come first
        part = text[lo : lo + 300]
        at = np.arange(293)
        marked.append(family.add(part, at, at + lo))
    seen, want, raw = {}, set(), text.tobytes()
    for p in [x for lo in (0, 300, 600) for x in range(lo, lo + 293)]:
        w = raw[p : p + 8]
        if w in seen:
            want.add(p)
        seen.setdefault(w, p)
    assert set(np.concatenate(marked).tolist()) == want
    assert [level is not None for level in family.levels] == [True, True]
    for level in family.levels:
        keys = [int(level.words[a]) for a in level.at]
        assert keys == sorted(keys)


# --------------------------------------------------------------------------- 3 benchmarks


def test_decontamination_both_ways_and_offsets(spark):
    item = "The quick brown fox jumps over the lazy dog again today"
    rows = [(1, f"x, {item.upper()}! y"), (2, "the quick brown"), (3, None), (4, ""), (5, "short ITEM here"), (5, "short ITEM here"), (6, "xshort item")]
    benchmark = table(spark, [(7, item), (8, "short item"), (9, None), (10, "!!"), (11, "Short Item.")], "item_id long, text string")
    df = table(spark, rows)
    a = sorted(map(tuple, decontam.scan_documents(df, benchmark).drop("spans").collect()), key=str)
    b = sorted(map(tuple, decontam.scan_documents(df, benchmark, max_automaton_bytes=1).drop("spans").collect()), key=str)
    assert [(x[0], x[1], x[2], list(x[3])) for x in a] == [(x[0], x[1], x[2], list(x[3])) for x in b]
    few, many = (sorted((r["doc_id"], str(r["spans"])) for r in decontam.scan_documents(df, benchmark, max_automaton_bytes=n).collect()) for n in (1 << 28, 3000))
    assert few == many and sum("begin" in s for _, s in many) == 3  # offsets at any number of slices
    assert len(list(decontam.slices_of([(7, item), (8, "short item")], 10, 3000))) == 2
    assert len(list(decontam.slices_of([(7, item), (8, "short item")], 10, 1))) == 3
    span = decontam.scan_documents(df, benchmark).filter("doc_id = 1").first()["spans"]
    text = rows[0][1].encode()
    assert [text[s["begin"] : s["end"]].decode() for s in span] == [item.upper()]
    for limit in (16 << 20, 1):
        assert sorted(r["doc_id"] for r in decontam.clean_documents(df, benchmark, max_automaton_bytes=limit).collect()) == [2, 3, 4, 6]
    assert decontam.scan_documents(df, benchmark.limit(0)).filter("n_hit > 0").count() == 0
    assert decontam.scan_documents(df.limit(0), benchmark).count() == 0


# ----------------------------------------------------------------------- 4 exact duplicates


@pytest.mark.parametrize("key_hex", [64, 1])
def test_exact_dedup_with_colliding_keys(spark, key_hex):
    rows = [(3, "a b"), (1, "ab"), (2, "a  b"), (5, None), (4, " \n"), (9, "c"), (9, "c"), (None, "d"), (7, "d"), (8, "xyz" * 5000)]
    df = table(spark, [(i, t, "z", "y", 1, "m", "k") for i, t in rows], DOCS)
    got = exact_stream.dedup_exact(df, key_hex=key_hex).collect()
    assert len(got) == len(rows)
    by = {}
    for r in got:
        by.setdefault(r["text_sha256"], []).append(r)
    for text, (keep, size) in {"ab": (2, 3), "": (4, 2), "c": (9, 2), "d": (7, 2), "xyz" * 5000: (8, 1)}.items():
        group = by[hashlib.sha256(text.encode()).hexdigest()]
        assert len(group) == size and {(r["keep_id"], r["group_size"]) for r in group} == {(keep, size)} and sum(r["kept"] for r in group) == 1


def test_exact_dedup_stream_keeps_state_between_drains(spark):
    folder = storage.shared_dir(spark, "test")

    def inbox(rows):
        return exact_stream.inbox_rows(exact_stream.located(table(spark, rows))[0], "doc_id", "text", 64, "_file", "_row")

    first = inbox([(5, "one"), (6, "two")])
    first.write.parquet(f"{folder}/inbox")
    exact_stream.drain(spark, f"{folder}/inbox", first.schema, folder)
    inbox([(2, "one")]).write.mode("append").parquet(f"{folder}/inbox")
    state = exact_stream.drain(spark, f"{folder}/inbox", first.schema, folder).filter("group_size > 1").collect()
    assert [(-r["keep"]["neg_id"], r["group_size"]) for r in state] == [(2, 2)]


def test_keep_firsts_keeps_one_twin(spark):
    df = table(spark, [(1, "a"), (1, "a"), (2, "a "), (3, None)])
    assert sorted((r["doc_id"], r["text"]) for r in exact_stream.keep_firsts(df).collect()) == [(2, "a "), (3, None)]
    assert exact_stream.keep_firsts(table(spark, [(1, "a"), (1, "a")])).count() == 1
    assert exact_stream.keep_firsts(df.limit(0)).count() == 0


# ------------------------------------------------------------------------------ 5 packing


def test_best_fit_is_the_tightest_compatible_bin():
    rng = np.random.default_rng(5)
    bins, slow = packing.BestFit(64), []
    for _ in range(800):
        n, s, c = int(rng.integers(1, 65)), int(rng.integers(-1, 5)), int(rng.integers(-1, 3))
        fits = [(64 - u, k) for k, (u, ss, cc) in enumerate(slow) if u + n <= 64 and u < 64 and s not in ss and c not in cc]
        got, at = bins.place(n, s, c)
        if not fits:
            assert got == len(slow)
            slow.append((0, set(), set()))
        else:
            assert got in [k for room, k in fits if room == min(fits)[0]]
        u, ss, cc = slow[got]
        assert at == u
        slow[got] = u + n, ss | ({s} - {-1}), cc | ({c} - {-1})


def test_packing_places_every_token_once(spark, docs):
    placed = packing.pack_texts(docs, capacity=512, shard_tokens=20_000).toPandas()
    source = {r["doc_id"]: r["source"] for r in docs.collect()}
    for i, text in texts_of(docs).items():
        own = placed[placed.doc_id == i].sort_values("piece")
        assert own.token_begin.tolist() == np.concatenate([[0], own.n_tokens.cumsum()[:-1]]).tolist()
        assert own.n_tokens.sum() == len(re.findall(r"[^\x20\x09-\x0D]+", text)) + 1
    for _, b in placed.groupby("bin_id"):
        spans = sorted(zip(b.bin_offset, b.n_tokens))
        assert all(x + n <= y for (x, n), (y, _) in zip(spans, spans[1:])) and spans[-1][0] + spans[-1][1] <= 512
        names = [source[i] for i in b.doc_id]
        assert len(names) == len(set(names))
    odd = packing.pack_texts(table(spark, [(None, None, None), (1, "a", None), (1, "a", None)], "doc_id long, text string, source string"))
    assert odd.agg(F.sum("n_tokens")).first()[0] == 5
    assert packing.pack_texts(table(spark, [], "doc_id long, text string, source string")).count() == 0


# -------------------------------------------------------------------------- 6 n-gram model


def test_elias_fano_matches_sorted_array():
    rng = np.random.default_rng(0)
    for n in (0, 1, 5, 700):
        for top in (50, 1 << 63):
            v = np.sort(rng.integers(0, top, n, dtype=np.uint64))
            ef, x = ef_ngram.EliasFano.build(v), rng.integers(0, top + 10 if top == 50 else top, 300, dtype=np.uint64)
            assert (ef.access(np.arange(n)) == v).all()
            if n:
                assert (ef.successor(x) == np.searchsorted(v, x)).all()
            assert ((ef.find(x) >= 0) == np.isin(x, v)).all()


@pytest.mark.parametrize("options", [dict(), dict(shard_bytes=60_000, hot_tokens=300), dict(order=2), dict(order=4, min_count=2)])
def test_language_model_matches_brute_force(spark, docs, options):
    rows = docs.select("doc_id", "text", langid.held_out(10, 0).alias("held_out")).unionByName(table(spark, [(-1, None, False), (-2, "", True)], "doc_id long, text string, held_out boolean"))
    manifest = ef_ngram.build_model(rows.filter("NOT held_out"), **options)
    got = ef_ngram.score_texts(rows, manifest).collect()
    tokens = {r["doc_id"]: re.findall(r"[^\x20\x09-\x0D]+", fold(r["text"] or "")) + ["<end>"] for r in rows.collect()}
    held = {r["doc_id"]: r["held_out"] for r in got}
    order, least = options.get("order", ef_ngram.ORDER), options.get("min_count", ef_ngram.MIN_COUNT)
    grams, n = [Counter() for _ in range(order + 1)], 0
    for i, w in tokens.items():
        if not held[i]:
            grams[1].update(w)
            n += 1
            x = ["<s>", *w]
            for k in range(2, order + 1):
                grams[k].update(tuple(x[j : j + k]) for j in range(len(x) - k + 1))
    one = grams[1]
    total, distinct = sum(one.values()), len(one)
    kept, mass = {}, Counter()
    for k in range(2, order + 1):
        for g, c in grams[k].items():
            if c < least or (k > 2 and g[:-1] not in kept):
                continue
            seen = (n if g[0] == "<s>" else one[g[0]]) if k == 2 else grams[k - 1][g[:-1]]
            kept[g] = ef_ngram.CODEBOOK[ef_ngram.quantise(np.array([(c - ef_ngram.DISCOUNT) / seen]))[0]]
            mass[g[:-1]] += kept[g]
    base = lambda w: (one[w] + 0.1) / (total + 0.1 * (distinct + 1))

    def p(h, w):
        return kept.get((*h, w), 0) + (1 - mass[h]) * p(h[1:], w) if h else base(w)

    for r in got:
        w = tokens[r["doc_id"]]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(w), sum(one[x] > 0 for x in w), total)
        assert math.isclose(r["base_score"], sum(math.log10(base(x)) for x in w), rel_tol=1e-9)
        x = ["<s>", *w]
        want = sum(math.log10(p(tuple(x[max(0, j - order + 1) : j]), x[j])) for j in range(1, len(x)))
        assert abs(r["score"] - want) < 1e-2 + 4e-3 * len(w), r
    assert sum(kept.values()) > 0
    empty = ef_ngram.build_model(rows.limit(0).select("text"))
    assert ef_ngram.score_texts(rows.limit(0), empty).count() == 0
    assert all(r["score"] == r["base_score"] == 0 for r in ef_ngram.score_texts(table(spark, [(1, "a b", True)], "doc_id long, text string, held_out boolean"), empty).collect())


# -------------------------------------------------------------------------- 7 Jaccard join


def components_by_hand(texts, percent=85, width=4):
    sets = {}
    for i, t in texts.items():
        w = re.findall(r"[^\x20\x09-\x0D]+", fold(t))
        sets[i] = {tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1))} if w else set()
    up = {i: i for i in sets}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), root(i)) for i in ids}


def near_copies(n, seed=2):
    rng = np.random.default_rng(seed)
    base = [f"w{k}" for k in rng.integers(0, 3000, 120)]
    rows = []
    for i in range(n):
        w = list(base)
        for _ in range(int(rng.integers(0, 7))):
            w[int(rng.integers(0, len(w)))] = f"v{int(rng.integers(0, 3000))}"
        rows.append((i, " ".join(w)))
    return rows


@pytest.mark.parametrize("region_sets,max_levels", [(2000, 4), (15, 4), (10, 1)])
def test_jaccard_components_of_a_hot_group(spark, region_sets, max_levels):
    rows = near_copies(90) + [(200, "a b"), (201, "A  b"), (202, "a b c"), (203, None), (204, ""), (205, "one two three four"), (206, "one two three four")]
    df = table(spark, rows)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(df, width=4, percent=85, region_sets=region_sets, max_levels=max_levels).collect()}
    assert got == components_by_hand(texts_of(df))


@pytest.mark.parametrize("region_sets,max_levels", [(2000, 4), (12, 3), (5, 1)])
def test_jaccard_components_of_chains(spark, region_sets, max_levels):
    """Windows sliding over long texts: neighbours link, ends only through those between, and
    the members that connect two pivots' balls are neither's pivot."""
    rng = np.random.default_rng(11)
    rows = [(100 + 200 * c + i, " ".join(["same", "head", "of", "all"] + [f"c{c}x{k}" for k in range(off, off + int(rng.integers(100, 130)))])) for c in range(3) for i, off in enumerate(rng.integers(0, 260, 25).tolist())]
    rows = [(int(i), t) for i, t in zip(rng.permutation(len(rows)), [t for _, t in rows], strict=True)]
    df = table(spark, rows)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(df, width=4, percent=80, region_sets=region_sets, max_levels=max_levels).collect()}
    assert got == components_by_hand(texts_of(df), 80, 4)


def test_region_join_of_chains_and_homes():
    rng = np.random.default_rng(5)
    for trial in range(60):
        sets = [np.arange(o, o + 100, dtype=np.uint64) for o in rng.integers(0, 150, 14)]
        home = np.ones(14, bool) if trial % 2 else rng.random(14) < 0.5
        every = [(a, b) for a in range(14) for b in range(a) if (home[a] or home[b]) and 100 * len(np.intersect1d(sets[a], sets[b])) >= 80 * len(np.union1d(sets[a], sets[b]))]
        links = jaccard_join.join_region(sets, 80, home)
        reach = []
        for pairs in (links, every):
            up = np.arange(14)
            for a, b in pairs:
                up[up == up[b]] = up[a]
            reach.append(up[:, None] == up[None, :])
        assert (reach[0] == reach[1]).all()


def test_jaccard_components_of_documents(spark, docs):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_components(docs, width=4, percent=85).collect()}
    assert got == components_by_hand(texts_of(docs))
    assert jaccard_join.jaccard_components(docs.limit(0)).count() == 0
    odd = jaccard_join.jaccard_components(table(spark, [(None, "p q r s t"), (4, "p q r s t"), (None, None)])).collect()
    assert len(odd) == 3
    assert sorted((r["doc_id"] or -1, r["component_id"] or -1) for r in odd) == [(-1, -1), (-1, 4), (4, 4)]


def test_region_join_finds_every_link():
    rng = np.random.default_rng(4)
    base = np.unique(rng.integers(0, 1 << 40, 60).astype(np.uint64))
    sets = [np.unique(np.concatenate([np.delete(base, rng.integers(0, len(base), int(rng.integers(0, 6)))), rng.integers(0, 1 << 40, int(rng.integers(0, 5))).astype(np.uint64)])) for _ in range(60)]
    links = jaccard_join.join_region(sets, 85)

    def classes(pairs):
        up = list(range(60))
        for a, b in pairs:
            ra, rb = a, b
            while up[ra] != ra:
                ra = up[ra]
            while up[rb] != rb:
                rb = up[rb]
            up[max(ra, rb)] = min(ra, rb)
        out = []
        for i in range(60):
            while up[i] != i:
                i = up[i]
            out.append(i)
        return out

    every = [(a, b) for a in range(60) for b in range(a) if 100 * len(np.intersect1d(sets[a], sets[b])) >= 85 * len(np.union1d(sets[a], sets[b]))]
    assert classes(links) == classes(every) and set(map(frozenset, links)) <= set(map(frozenset, every))


def test_components_of_a_long_path(spark):
    links = spark.range(1, 60).select(F.col("id").alias("a"), (F.col("id") - 1).alias("b"))
    got = {r["node"]: r["component"] for r in components.connected_components(links).collect()}
    assert got == {k: 0 for k in range(1, 60)}


# ---------------------------------------------------------------------------- 8 languages


def test_language_accuracy_rejection_and_extra_columns(spark):
    rows = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = langid.fit(rows.filter(~langid.held_out(4, 2)))
    got = langid.identify(rows.withColumn("lang_score", F.lit("mine")), model).select("doc_id", "lang", "lang_pred", "lang_score", "lang_rejected", langid.held_out(4, 2).alias("h")).toPandas()
    assert (got[got.h].lang == got[got.h].lang_pred).mean() > 0.97
    assert got.lang_rejected.mean() < 0.02 and got.lang_score.between(0, 1).all()
    odd = table(spark, [(1, None), (2, ""), (3, "123 !!"), (4, "the and of"), (None, "the")])
    und = {r["doc_id"]: r for r in langid.identify(odd, model).collect()}
    assert [und[k]["lang_pred"] for k in (1, 2, 3)] == ["und"] * 3 and und[4]["lang_pred"] == "en"
    assert all(und[k]["lang_rejected"] for k in (1, 2, 3))
    nothing = langid.fit(rows.limit(0).select("doc_id", "text", "lang"))
    assert {r["lang_pred"] for r in langid.identify(odd, nothing).collect()} == {"und"}
    assert langid.identify(odd.limit(0), model).count() == 0


# --------------------------------------------------------------------------------- 9 WARC


def test_bundle_round_trip_and_random_access():
    sink, rng = io.BytesIO(), np.random.default_rng(0)
    writer = warc_zstd.BundleWriter(sink, frame_bytes=2000)
    records = [bytes(rng.integers(97, 105, int(rng.integers(0, 3000))).astype(np.uint8)) for _ in range(40)]
    places = [writer.add(r) for r in records]
    writer.close()
    reader = warc_zstd.BundleReader(sink)
    assert len(reader) > 5
    assert [reader.record(f, o, len(r)) for (f, o), r in zip(places, records)] == records
    import zstandard

    plain = zstandard.ZstdDecompressor().stream_reader(io.BytesIO(sink.getvalue()), read_across_frames=True).read()
    assert plain == b"".join(records)


def test_archives_with_revisits_and_odd_rows(spark):
    big, small = "é" * 80, "x" * 99
    rows = [(5, "u\r\nX: y", big), (3, None, big), (7, "u", small), (8, "u", small), (9, "u", None), (3, "again", big), (None, "u", big)]
    read, index, folder = warc_zstd.archive_pages(table(spark, rows, "page_id long, url string, html string"), frame_bytes=300)
    got = sorted(((r["page_id"] or -1, r["record_type"], r["refers_to"], r["payload_bytes"]) for r in read.collect()), key=str)
    assert got == sorted([(5, "revisit", 3, 160), (3, "response", None, 160), (3, "response", None, 160), (7, "response", None, 99), (8, "response", None, 99), (9, "response", None, 0), (-1, "response", None, 160)], key=str)
    entry = index.filter("record_id = 7").first()
    (head, block), = warc_zstd.parse_records(warc_zstd.fetch(folder, entry["bundle"], entry["frame"], entry["frame_offset"], entry["record_bytes"]))
    assert block.endswith(small.encode()) and head["WARC-Type"] == "response"
    assert warc_zstd.archive_pages(table(spark, [], "page_id long, url string, html string"))[0].count() == 0


# ----------------------------------------------------------------------------- 10 toxicity


def test_pu_learning_on_real_and_odd_rows(spark):
    rows = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet").select("doc_id", "toxic")
    model = pu_toxicity.fit(rows.filter(~langid.held_out(5, 0)), labels.filter(~langid.held_out(5, 0)))
    got = pu_toxicity.score(rows, model).join(labels, "doc_id").filter(langid.held_out(5, 0)).toPandas()
    pos, neg = got[got.toxic == 1].tox_score.to_numpy(), got[got.toxic == 0].tox_score.to_numpy()
    auc = (pos[:, None] > neg[None, :]).mean() + 0.5 * (pos[:, None] == neg[None, :]).mean()
    assert auc > 0.9 and (neg >= 0.5).mean() < 0.02
    odd = pu_toxicity.score(table(spark, [(1, None), (2, ""), (None, "x")]).withColumn("tox_score", F.lit("mine")), model).collect()
    assert all(0 <= r["tox_score"] < 0.5 for r in odd)
    blank = pu_toxicity.fit(rows, labels.limit(0))
    assert all(r["tox_score"] < 1e-9 for r in pu_toxicity.score(table(spark, [(1, "idiot")]), blank).collect())


def test_nnpu_risk_ranks_planted_words():
    rng = np.random.default_rng(0)
    words = rng.integers(0, 1 << 62, 400).astype(np.uint64)
    common, bad = words[:390], words[390:]
    pos = [np.unique(np.concatenate([rng.choice(common, 40), rng.choice(bad, 3)])) for _ in range(200)]
    unl = [np.unique(rng.choice(common, 40)) for _ in range(900)] + pos[:100]
    model = pu_toxicity.train_nnpu(pos, unl, 0.1)
    assert set(model.words.tolist()) >= set(bad.tolist())
    weight = dict(zip(model.words.tolist(), model.weights))
    assert min(weight[b] for b in bad.tolist()) > 1


# ------------------------------------------------------------------------------- pipeline


def test_pipeline_against_brute_force(spark, docs):
    import corpus_pipeline as c

    rows = docs
    kept = {}
    for name, stage in c.STAGES[:-1]:
        rows = storage.materialise(stage(spark, rows, SMALL), storage.shared_dir(spark, "stage"))
        assert rows.columns == list(c.COLUMNS)
        kept[name] = {r["doc_id"] for r in rows.select("doc_id").collect()}
    text = texts_of(docs)
    best = {}
    for i in kept["language_id"]:
        k = re.sub(r"[\x20\x09-\x0D]", "", text[i])
        best[k] = min(best.get(k, (1, 0)), (-len(text[i]), i))
    assert kept["exact_dedup"] == {i for _, i in best.values()}
    comp = components_by_hand({i: text[i] for i in kept["exact_dedup"]}, 80, 5)
    assert kept["near_dedup"] == {i for i, (_, c_) in comp.items() if i == c_}
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{SMALL}/benchmark.parquet").collect()]
    windows = {w for _, t in items for w in decontam.item_windows((t or "").encode())}
    hit = {i for i in kept["near_dedup"] if any(f" {w.decode()} " in f" {b' '.join(decontam.normal_words(text[i].encode())).decode()} " for w in windows)}
    assert kept["decontaminate"] == kept["near_dedup"] - hit
    placed = c.STAGES[-1][1](spark, rows, SMALL).toPandas()
    assert set(placed.doc_id) == kept["decontaminate"]
    assert zlib.crc32(b"1") == 2212294583  # the split rule of the queries


def test_query_names():
    from cellgraph.llm import queries

    assert sorted(int(re.match(r"op(\d+)_", k)[1]) for k in queries.QUERIES) == list(range(1, 11))
