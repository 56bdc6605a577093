"""Language identification by nearest centroid.

A text is the L2-normalised TF-IDF vector of its byte trigrams (letters folded, everything
else one blank), hashed to ``BINS``.  Document frequencies, centroids and thresholds come
from every training row: the counts of each are written once to the shared folder, and
spherical k-means splits the vectors of each language into ``CLUSTERS`` in distributed
passes over them, with sums in whole numbers, so that the result doesn't depend on how rows
are dealt.  The prediction is the language of
the centroid with the greatest cosine, and that cosine is the score.  A text is rejected
when it has no letter, or is farther from every centroid of its language than the
language's threshold for texts of its length.  Thresholds are derived from the distances of
all training texts and of short passages cut from each, in bands of their number of
trigrams: a text of a word or two has a low cosine by nature.

Null texts and texts without a letter are ``und`` with score 0.  With no labelled training
row everything is ``und``.  Ties go to the first language in sort order.  A block of texts
is bounded in bytes and in rows; a very long text is a block of its own.  Repeated rows are
counted and answered one by one; empty tables give no rows; columns of other names come
along unchanged, whatever they are called.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import scan
from .storage import fresh_names, materialise, remove, shared_dir

BINS = 4096
CLUSTERS = 4
#: Rounds of k-means at most; fewer where nothing moves any more.
ROUNDS = 12
#: A vector's entry is summed as a whole number of this part of one.
UNIT = 1 << 30
#: Cosines are counted in steps of this part of one for thresholds.
STEPS = 1024
#: A text is rejected at less than this share of the lowest typical cosine.
REJECT_SHARE = 0.5
#: Texts whose numbers of trigrams have the same number of binary digits share a threshold.
BANDS = 24
#: Words of the passages that calibrate short texts, and how many passages of a band are enough.
PASSAGES = (1, 1, 1, 2, 2, 4, 8, 16)
ENOUGH = 30
#: Rows whose vectors are held at once.
BLOCK_ROWS = 512
UNKNOWN = "und"


def _blocks(column):
    """:func:`scan.blocks`, bounded in rows as well: a vector takes ``4 * BINS`` bytes."""
    for lo, hi, data, starts in scan.blocks(column):
        for a in range(0, hi - lo, BLOCK_ROWS):
            b = min(a + BLOCK_ROWS, hi - lo)
            yield lo + a, lo + b, data[starts[a] : starts[b]], starts[a : b + 1] - starts[a]


def band_of(counts: np.ndarray) -> np.ndarray:
    """The length band of each row of trigram counts."""
    total = counts.sum(axis=1)
    return np.minimum(np.floor(np.log2(np.maximum(total, 1))).astype(np.int64), BANDS - 1)


def passages_of(data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bytes, starts, document) of short passages from all over each text of a block, each
    from a word with a letter to another."""
    begin, end, doc = scan.words(data, starts, scan.NOT_SPACE)
    letters = scan.by_document(scan.LETTERS[data].astype(np.int64))
    worded = letters[end] > letters[begin]
    begin, end, doc = begin[worded], end[worded], doc[worded]
    many = np.bincount(doc, minlength=len(starts) - 1)
    first, step = scan.by_document(many)[:-1], many // len(PASSAGES)
    b, e, d = [], [], []
    for k, n in enumerate(PASSAGES):
        of = np.flatnonzero((step > 0) & (many > n))
        at = first[of] + k * step[of]
        b.append(begin[at])
        e.append(end[np.minimum(at + n, first[of] + many[of]) - 1])
        d.append(of)
    b, e, d = np.concatenate(b), np.concatenate(e), np.concatenate(d)
    cuts = scan.by_document(e - b)
    return data[np.repeat(b - cuts[:-1], e - b) + np.arange(cuts[-1])], cuts, d


def bin_counts(data: np.ndarray, starts: np.ndarray, bins: int = BINS) -> np.ndarray:
    """Trigram counts (float32) of each document of a block; documents are padded by blanks."""
    n = len(starts) - 1
    lens = np.diff(starts)
    # one blank before and after each text keeps trigrams inside their document
    padded = np.full(len(data) + 2 * n, 32, np.uint8)
    at = np.arange(len(data)) + np.repeat(2 * np.arange(n) + 1, lens)
    letters = scan.FOLD[data]
    letters = np.where(scan.LETTERS[data], letters, np.uint8(32))
    padded[at] = letters
    wide = padded.astype(np.uint32)
    code = wide[:-2] * np.uint32(0x9E3779B1) + wide[1:-1] * np.uint32(0x85EBCA77) + wide[2:] * np.uint32(0xC2B2AE3D)
    code = ((code ^ (code >> np.uint32(15))) * np.uint32(0x2C1B3C6D)) >> np.uint32(32 - int(bins).bit_length() + 1)
    # three blanks in a row say nothing
    blank = (padded[:-2] == 32) & (padded[1:-1] == 32) & (padded[2:] == 32)
    out = np.zeros((n, bins), np.float32)
    first = starts[:-1] + 2 * np.arange(n)
    for k in range(n):
        lo, hi = first[k], first[k] + lens[k]
        if hi > lo:
            own = code[lo:hi]
            quiet = blank[lo:hi]
            out[k] = np.bincount(own[~quiet] if quiet.any() else own, minlength=bins)
    return out


def weigh(counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    """Sublinear TF-IDF rows of unit length (all zero where nothing was counted)."""
    x = np.log1p(counts) * idf
    norm = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return np.divide(x, norm, out=np.zeros_like(x), where=norm > 0)


@dataclass
class CentroidModel:
    """Everything a prediction needs; its size depends on languages and bins, not on the data."""

    langs: list[str]
    idf: np.ndarray
    centroids: np.ndarray  # (languages * clusters, bins)
    owner: np.ndarray  # language of each centroid
    threshold: np.ndarray  # (languages, bands): least accepted cosine by length
    fallback: int = 0

    def predict(self, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(language index, cosine, accepted) of each row of trigram counts."""
        cos = weigh(counts, self.idf) @ self.centroids.T
        best = np.argmax(cos, axis=1)
        score = np.clip(cos[np.arange(len(cos)), best], 0.0, 1.0)
        lang = np.where(score > 0, self.owner[best], self.fallback)
        return lang, score.astype(np.float64), score >= self.threshold[lang, band_of(counts)]


def _text(rows: DataFrame) -> DataFrame:
    return rows.withColumn("text", F.coalesce(F.col("text").cast("string"), F.lit("")))


def _vectors(train: DataFrame, bins: int) -> DataFrame:
    """(lang, doc_id, letter, bins, counts): the trigram counts of each row that aren't 0."""

    def count(batches):
        for batch in batches:
            for lo, hi, data, starts in _blocks(batch.column(3)):
                counts = bin_counts(data, starts, bins)
                row, at = np.nonzero(counts)
                cut = np.searchsorted(row, np.arange(hi - lo + 1))
                values = counts[row, at].astype("<u4")
                at = at.astype("<u4")
                packed = [pa.array([x[a:b].view(np.uint8).reshape(-1, 4).T.tobytes() for a, b in zip(cut[:-1], cut[1:])], pa.binary()) for x in (at, values)]  # planes of bytes pack well
                yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(lo, hi - lo) for c in range(3)), *packed], names=["lang", "doc_id", "letter", "bins", "counts"])

    rows = _text(train).select("lang", F.col("doc_id").cast("string").alias("doc_id"), F.col("text").rlike(r"\p{L}").alias("letter"), "text")
    return rows.mapInArrow(count, "lang string, doc_id string, letter boolean, bins binary, counts binary")


def _unpack(column) -> list[np.ndarray]:
    return [np.ascontiguousarray(np.frombuffer(b.as_py(), np.uint8).reshape(4, -1).T).view("<u4").ravel() for b in column]


def _frequencies(vectors: DataFrame, bins: int) -> tuple[np.ndarray, int]:
    """In how many texts each bin occurs, and how many there are; ``bins`` numbers reach the driver."""

    def count(batches):
        df = np.zeros(bins + 1, np.int64)
        for batch in batches:
            for x in _unpack(batch.column(0)):
                df[x] += 1
            df[bins] += len(batch)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(bins + 1), pa.int32()), pa.array(df, pa.int64())], names=["bin", "df"])

    out = np.zeros(bins + 1, np.int64)
    for r in vectors.select("bins").mapInArrow(count, "bin int, df long").groupBy("bin").agg(F.sum("df").alias("df")).collect():
        out[r["bin"]] = r["df"]
    return out[:-1], int(out[-1])


def _sparse(batch, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bins, weights, starts) of a batch's unit vectors, one after another; none is empty."""
    at, counts = _unpack(batch.column(2)), _unpack(batch.column(3))
    starts = scan.by_document(np.array([len(x) for x in at], np.int64))
    at = np.concatenate(at).astype(np.int64)
    w = np.log1p(np.concatenate(counts).astype(np.float64)) * idf[at]
    norm = np.sqrt(np.add.reduceat(w * w, starts[:-1]))
    return at, w / np.repeat(norm, np.diff(starts)), starts


def _cosines(at, w, starts, own: np.ndarray, centres: np.ndarray) -> np.ndarray:
    """Products of each vector with the centres (languages, k, bins) of its language."""
    of = np.repeat(own, np.diff(starts))
    return np.stack([np.add.reduceat(w * centres[of, k, at], starts[:-1]) for k in range(centres.shape[1])], axis=1)


def _totals(vectors: DataFrame, langs: list[str], idf: np.ndarray, centres: np.ndarray | None, k: int) -> np.ndarray:
    """(languages, k, bins): the summed vectors nearest to each centre; all in the first
    without centres."""
    bins = len(idf)
    shared = vectors.sparkSession.sparkContext.broadcast((langs, idf, centres))

    def add(batches):
        langs, idf, centres = shared.value
        number, sums = {x: i for i, x in enumerate(langs)}, {}
        for batch in batches:
            if not len(batch):
                continue
            own = np.array([number[x] for x in batch.column(0).to_pylist()])
            at, w, starts = _sparse(batch, idf)
            group = own * k + (np.argmax(_cosines(at, w, starts, own, centres), axis=1) if centres is not None else 0)
            names, index = np.unique(group, return_inverse=True)
            total = np.bincount(np.repeat(index, np.diff(starts)) * bins + at, np.rint(w * UNIT), len(names) * bins).astype(np.int64).reshape(-1, bins)
            for name, row in zip(names.tolist(), total):
                sums[name] = sums[name] + row if name in sums else row
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([x.tobytes() for x in sums.values()], pa.binary())], names=["name", "total"])

    def fold(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        total = np.zeros(bins, np.int64)
        for x in frame["total"]:
            total += np.frombuffer(x, np.int64)
        return pd.DataFrame({"name": [key[0]], "total": [total.tobytes()]})

    out = np.zeros((len(langs) * k, bins), np.int64)
    for r in vectors.select("lang", "doc_id", "bins", "counts").mapInArrow(add, "name int, total binary").groupBy("name").applyInPandas(fold, "name int, total binary").collect():
        out[r["name"]] = np.frombuffer(r["total"], np.int64)
    return out.reshape(len(langs), k, bins)


def _outermost(vectors: DataFrame, langs: list[str], idf: np.ndarray, centres: np.ndarray, sign: int) -> np.ndarray:
    """(languages, bins): the vector of each language whose greatest cosine with the centres is
    the greatest (``sign`` 1) or the least (-1); ties: the last id."""
    shared = vectors.sparkSession.sparkContext.broadcast((langs, idf, centres))

    def best(batches):
        langs, idf, centres = shared.value
        number = {x: i for i, x in enumerate(langs)}
        for batch in batches:
            if not len(batch):
                continue
            own = np.array([number[x] for x in batch.column(0).to_pylist()])
            score = sign * _cosines(*_sparse(batch, idf), own, centres).max(axis=1)
            ids = np.array([x or "" for x in batch.column(1).to_pylist()], object)
            order = sorted(range(len(own)), key=lambda i: (own[i], score[i], ids[i]))
            last = [i for i, j in zip(order, [*order[1:], None]) if j is None or own[i] != own[j]]
            yield pa.RecordBatch.from_arrays([*(batch.column(c).take(pa.array(last)) for c in range(4)), pa.array(score[last])], names=["lang", "doc_id", "bins", "counts", "score"])

    found = vectors.select("lang", "doc_id", "bins", "counts").mapInArrow(best, "lang string, doc_id string, bins binary, counts binary, score double")
    out = np.zeros((len(langs), len(idf)))
    for r in found.groupBy("lang").agg(F.max_by(F.struct("lang", "doc_id", "bins", "counts"), F.struct("score", F.coalesce("doc_id", F.lit("")), "bins")).alias("x")).collect():
        one = pa.RecordBatch.from_pylist([r["x"].asDict()], pa.schema([("lang", pa.string()), ("doc_id", pa.string()), ("bins", pa.binary()), ("counts", pa.binary())]))
        at, w, _ = _sparse(one, idf)
        out[langs.index(r["lang"]), at] = w
    return out


def _cluster(vectors: DataFrame, langs: list[str], idf: np.ndarray, k: int) -> np.ndarray:
    """(languages, k, bins): spherical k-means of each language's vectors; farthest-first start,
    so no randomness."""

    def unit(x):
        x = x.astype(np.float64)
        return x / np.maximum(np.sqrt((x * x).sum(axis=-1, keepdims=True)), 1e-12)

    mean = unit(_totals(vectors, langs, idf, None, 1))
    c = _outermost(vectors, langs, idf, mean, 1)[:, None]
    while c.shape[1] < k:
        c = np.concatenate([c, _outermost(vectors, langs, idf, c, -1)[:, None]], axis=1)
    last = None
    for _ in range(ROUNDS):
        total = _totals(vectors, langs, idf, c, k)
        if last is not None and (total == last).all():
            break
        c, last = np.where(total.any(axis=2, keepdims=True), unit(total), c), total
    return c


def _cosine_counts(train: DataFrame, langs: list[str], idf: np.ndarray, centres: np.ndarray) -> dict:
    """{(language, band, whether a passage): how many cosines fall into each of ``STEPS``}."""
    shared = train.sparkSession.sparkContext.broadcast((langs, idf, centres.astype(np.float32)))

    def count(batches):
        langs, idf, centres = shared.value
        number, found = {x: i for i, x in enumerate(langs)}, {}
        for batch in batches:
            every = np.array([number[x] for x in batch.column(0).to_pylist()], np.int64)
            for lo, hi, data, starts in _blocks(batch.column(1)):
                own = every[lo:hi]
                short, cuts, of = passages_of(data, starts)
                parts = [(0, data, starts, own)]
                for a in range(0, len(of), BLOCK_ROWS):
                    b = min(a + BLOCK_ROWS, len(of))
                    parts.append((1, short[cuts[a] : cuts[b]], cuts[a : b + 1] - cuts[a], own[of[a:b]]))
                for passage, bytes_, at, lang in parts:
                    counts = bin_counts(bytes_, at, len(idf))
                    cos = weigh(counts, idf) @ centres.reshape(-1, len(idf)).T
                    near = cos.reshape(len(cos), *centres.shape[:2])[np.arange(len(cos)), lang].max(axis=1)
                    step = np.clip(np.floor(near * STEPS), 0, STEPS - 1).astype(np.int64)
                    codes, many = np.unique(((lang * BANDS + band_of(counts)) * 2 + passage) * STEPS + step, return_counts=True)
                    for code, n in zip(codes.tolist(), many.tolist()):
                        found[code] = found.get(code, 0) + n
        yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.int64()), pa.array(list(found.values()), pa.int64())], names=["code", "n"])

    out = {}
    for r in _text(train).filter(F.col("text").rlike(r"\p{L}")).select("lang", "text").mapInArrow(count, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).collect():
        rest, step = divmod(r["code"], STEPS)
        out.setdefault((rest // 2 // BANDS, rest // 2 % BANDS, bool(rest % 2)), np.zeros(STEPS, np.int64))[step] = r["n"]
    return out


def _thresholds(counts: dict, lang: int) -> np.ndarray:
    """Least accepted cosine of each band: a share of the lowest typical one of the texts and
    passages there, never more than that of all texts; bands with too few take that of the
    next shorter one, and the shortest accept what has any likeness."""

    def low(x):
        return REJECT_SHARE * int(np.searchsorted(np.cumsum(x), 0.01 * x.sum())) / STEPS

    nothing = np.zeros(STEPS, np.int64)
    top = low(sum((counts.get((lang, b, False), nothing) for b in range(BANDS)), nothing))
    out, last = np.zeros(BANDS), 0.0
    for b in range(BANDS):
        here = counts.get((lang, b, False), nothing) + counts.get((lang, b, True), nothing)
        if here.sum() >= ENOUGH:
            last = min(top, low(here))
        out[b] = last
    # a longer text is never held to less than a shorter one
    return np.maximum.accumulate(out)


def fit(train: DataFrame, bins: int = BINS, clusters: int = CLUSTERS) -> CentroidModel:
    """Fit on all rows (doc_id, text, lang); rows without a language add nothing."""
    spark = train.sparkSession
    train = train.filter(F.col("lang").isNotNull())
    folder = shared_dir(spark, "langid")
    try:
        every = materialise(_vectors(train, bins), folder)
        sizes = {r["lang"]: (r["n"], r["x"]) for r in every.groupBy("lang").agg(F.count("*").alias("n"), F.count_if("letter").alias("x")).collect()}
        df, n = _frequencies(every, bins)
        idf = (np.log((1 + n) / (1 + df)) + 1).astype(np.float32)
        langs = sorted(k for k, (_, x) in sizes.items() if x)
        if not langs:
            return CentroidModel([], idf, np.zeros((0, bins), np.float32), np.zeros(0, np.int64), np.zeros((0, BANDS)))
        centres = _cluster(every.filter("letter"), langs, idf, clusters)
    finally:
        remove(spark, folder)
    counts = _cosine_counts(train, langs, idf, centres)
    threshold = np.stack([_thresholds(counts, k) for k in range(len(langs))])
    # a language of fewer texts than clusters has no more centroids than texts
    kept = [(i, j) for i, lang in enumerate(langs) for j in range(min(clusters, sizes[lang][1]))]
    owner = np.array([i for i, _ in kept])
    return CentroidModel(langs, idf, np.stack([centres[i, j] for i, j in kept]).astype(np.float32), owner, threshold, fallback=max(range(len(langs)), key=lambda k: (sizes[langs[k]][0], -k)))


def identify(docs: DataFrame, model: CentroidModel, bins: int = BINS) -> DataFrame:
    """All columns of ``docs`` with lang_pred, lang_score and lang_rejected added (columns of
    these names are replaced)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    letter = F.coalesce(F.col("text").cast("string").rlike(r"\p{L}"), F.lit(False))

    def predict(column_batches):
        m = shared.value
        for texts, has_letter in column_batches:
            langs = np.full(len(texts), UNKNOWN, object)
            scores, reject = np.zeros(len(texts)), np.ones(len(texts), bool)
            for lo, hi, data, starts in _blocks(pa.Array.from_pandas(texts, type=pa.string())):
                if m.langs:
                    k, s, ok = m.predict(bin_counts(data, starts, bins))
                    names = np.array(m.langs, object)[k]
                    there = has_letter.to_numpy()[lo:hi].astype(bool)
                    langs[lo:hi] = np.where(there, names, UNKNOWN)
                    scores[lo:hi] = np.where(there, s, 0.0)
                    reject[lo:hi] = ~(ok & there)
            yield langs, scores, reject

    # only the new columns are made in Python; the others come along unchanged
    @F.pandas_udf("lang_pred string, lang_score double, lang_rejected boolean")
    def predicted(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
        for langs, scores, reject in predict(batches):
            yield pd.DataFrame({"lang_pred": langs, "lang_score": scores, "lang_rejected": reject})

    inner = fresh_names(docs, "found")[0]
    rows = docs.withColumn(inner, predicted(F.coalesce(F.col("text").cast("string"), F.lit("")), letter))
    return rows.select(*[F.col(f"`{c}`") for c in docs.columns if c not in ("lang_pred", "lang_score", "lang_rejected")], *[F.col(inner)[c].alias(c) for c in ("lang_pred", "lang_score", "lang_rejected")])


def held_out(modulus: int, remainder: int):
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(modulus)) == remainder, F.lit(False))


def op8_language_centroids(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    model = fit(docs.filter(~held_out(4, 2)))
    return identify(docs.select("doc_id", "text"), model).select("doc_id", held_out(4, 2).alias("held_out"), "lang_pred", F.col("lang_score").alias("score"), F.col("lang_rejected").alias("rejected"))
