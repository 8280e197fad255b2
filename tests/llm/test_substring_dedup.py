import collections
import hashlib
import random
import re

import pytest
from pyspark.sql import functions as F

from colpick.llm import substring_dedup as sd
from colpick.llm.common import text_key

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(rows, n):
    words = [WORD.findall(t or "") for _, t in rows]
    times = collections.Counter(tuple(w[i : i + n]) for w in words for i in range(len(w) - n + 1))
    out = []
    for (key, _), w in zip(rows, words):
        gone = {j for i in range(len(w) - n + 1) if times[tuple(w[i : i + n])] > 1 for j in range(i, i + n)}
        kept = [x for j, x in enumerate(w) if j not in gone]
        out.append((key, len(w), len(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return sorted(out, key=repr)


def corpus(seed, n):
    rng = random.Random(seed)
    word = lambda k=60: f"w{rng.randrange(k)}"
    passages = [[word() for _ in range(rng.choice([n - 1, n, n + 1, 2 * n, 5 * n]))] for _ in range(6)]
    rows = []
    for i in range(60):
        w = [word() for _ in range(rng.choice([0, 1, n - 1, n, 4 * n]))]
        for _ in range(rng.choice([0, 1, 2])):
            at = rng.randrange(len(w) + 1)
            w[at:at] = rng.choice(passages)
        rows.append((i, rng.choice([" ", "\n", " \t "]).join(w)))
    rows += [(70, rows[5][1]), (70, rows[5][1]), (None, rows[8][1]), (71, None), (72, ""), (73, "same " * (n + 3)), (74, "a b " * n), (75, " ".join(word(9) for _ in range(3000)))]
    return rows


@pytest.mark.parametrize(("seed", "block_rows"), [(1, 2000), (2, 3), (3, 1)])
def test_equals_brute_force(spark, seed, block_rows):
    rows = corpus(seed, 35)
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("tk", F.lit("clash")).repartition(3)
    got = sd.remove_repeats(df, block_rows=block_rows)
    assert sorted((tuple(r) for r in got.collect()), key=repr) == brute(rows, 35)


def test_short_windows_and_empty_table(spark):
    rows = corpus(4, 6)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted((tuple(r) for r in sd.remove_repeats(df, window=6, gram=2, block_rows=5).collect()), key=repr) == brute(rows, 6)
    assert sd.remove_repeats(df.limit(0)).count() == 0


def test_windows_that_agree_in_48_bits_only_are_distinct():
    import numpy as np
    import pyarrow as pa

    def block(x, y):
        rows = [np.array([h], dtype=np.uint64).view(np.uint8)[: sd.KEPT].tobytes() for h in (x, y)]
        batch = pa.RecordBatch.from_arrays([pa.array([1, 1]), pa.array([b"a", b"b"]), pa.array([0, 0], pa.int32()), pa.array(rows), pa.array([False, False])], schema=pa.schema([*sd.STRETCH, ("heavy", pa.bool_())]))
        return sum(b.num_rows for b in sd._parse(10)(iter([batch])))

    assert block(5, 5) == 2
    assert block(5, 5 + (1 << 48)) == 0 and block(5, 5 + (1 << 63)) == 0


def test_heavy_anchors_take_another_way_to_the_same_result(spark, monkeypatch):
    rows = corpus(6, 35)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    every = sorted(r.anchor for r in sd.stretches(df).select("anchor").distinct().collect())
    assert sd.heavy_anchors(df, 35, 8, "text", 1.0, 0.9) == []
    for heavy in (every, every[::2]):
        monkeypatch.setattr(sd, "heavy_anchors", lambda *_, h=heavy: h)
        assert sorted((tuple(r) for r in sd.remove_repeats(df).collect()), key=repr) == brute(rows, 35)


def test_every_factor_has_a_source_of_the_same_words(spark):
    rows = corpus(7, 35)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    words = {r.tk: WORD.findall(r.text or "") for r in df.select(text_key(F.col("text")).alias("tk"), "text").collect()}
    spans = sd.repeated_spans(df, block_rows=20).collect()
    assert spans
    for s in spans:
        mine, source = words[s.tk], words[s.source]
        assert mine[s.start : s.start + s.n + 34] == source[s.at : s.at + s.n + 34] and len(source) >= s.at + s.n + 34


def test_factors_whose_source_has_other_words_are_not_removed(spark, monkeypatch):
    a, b = " ".join(f"a{i}" for i in range(50)), " ".join(f"b{i}" for i in range(50))
    df = spark.createDataFrame([(1, a), (2, b)], "doc_id long, text string")
    key = {r.doc_id: r.tk for r in df.select("doc_id", text_key(F.col("text")).alias("tk")).collect()}
    lie = spark.createDataFrame([(key[1], 0, 3, key[2], 0)], "tk binary, start int, n int, source binary, at int")
    monkeypatch.setattr(sd, "repeated_spans", lambda *_: lie)
    assert [r.n_removed for r in sd.remove_repeats(df).collect()] == [0, 0]


def test_greedy_factors_follow_one_source():
    import numpy as np

    # stretches 1 2 3 4 | 9 2 3 | 3 4 of one block: 2 3 from the second, then 3 4 from the first
    h = np.array([1, 2, 3, 4, 9, 2, 3, 3, 4], dtype=np.uint64)
    first, last, source = sd.factors(np.zeros(3, dtype=np.int64), h, np.array([4, 3, 2]))
    assert list(zip(first.tolist(), last.tolist(), source.tolist())) == [(1, 2, 5), (3, 3, 8), (5, 6, 1), (7, 8, 2)]
