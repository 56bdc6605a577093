"""Suffix array levels that outlive a run."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellgraph.llm import storage, suffix_levels
from test_operators import table


def seen_before(batches, length):
    """Per batch and document: the bytes kept when windows seen in any earlier place go."""
    seen, out = set(), []
    for batch in batches:
        kept = {}
        for doc, text in sorted(batch, key=lambda r: r[0]):
            raw = (text or "").encode()
            gone = np.zeros(len(raw), bool)
            for p in range(len(raw) - length + 1):
                window = raw[p : p + length]
                if window in seen:
                    gone[p : p + length] = True
                seen.add(window)
            kept[doc] = hashlib.sha256(bytes(b for b, g in zip(raw, gone, strict=True) if not g)).hexdigest(), int(gone.sum())
        out.append(kept)
    return out


def test_later_batches_meet_the_levels_of_former_runs(spark):
    rng = np.random.default_rng(4)
    text = lambda n: "".join(rng.choice(list("abc d"), n))
    shared = [text(90) for _ in range(6)]
    batches = [[(100 * (7 - b) + k, text(60) + shared[(b * k) % 6] + text(40) + "é" * (k % 3)) for k in range(6)] for b in range(7)]
    batches[3] += [(9000, batches[0][0][1]), (9001, None), (9002, ""), (9003, "tiny"), (9004, "xy" * 200)]
    batches[5] = []
    want = seen_before(batches, 24)
    folder = storage.shared_dir(spark, "levels")
    shape = []
    for batch, expected in zip(batches, want, strict=True):
        index = suffix_levels.LevelIndex(spark, folder, shards=5, length=24, gram=12)  # a new run each time
        got = {r["doc_id"]: (r["kept_sha256"], r["n_removed"]) for r in index.add(table(spark, batch).withColumns({"dg": F.lit("mine"), "ID": F.lit(2)})).collect()}
        assert got == expected
        shape.append([bool(x) for x in index.state["levels"]])
    assert shape[0] == [True] and shape[2] == [True, True] and shape[3] == [False, False, True] and shape[6] == [True, True, True]
    assert not [t for t in spark.catalog.listTables() if t.name.startswith("suffix_")]
    with pytest.raises(ValueError):
        suffix_levels.LevelIndex(spark, folder, length=30, gram=12)


def test_a_batch_that_lost_a_race_changes_nothing(spark):
    folder = storage.shared_dir(spark, "levels")
    one, two = (suffix_levels.LevelIndex(spark, folder, shards=2, length=24, gram=12) for _ in range(2))
    one.add(table(spark, [(1, "a" * 3 + "bcdefghij" * 9)])).count()
    with pytest.raises(RuntimeError):
        two.add(table(spark, [(2, "other text " * 9)]))
    again = suffix_levels.LevelIndex(spark, folder, length=24, gram=12)
    assert again.state == one.state and again.state["shards"] == 2
    assert again.add(table(spark, [(0, "bcdefghij" * 9)])).first()["n_removed"] == 81
