import random
import re

from pyspark.sql import functions as F

import corpus_pipeline
from colpick.llm import near_copies, simhash


def brute_groups(rows):
    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else {()}

    sets = [shingles(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        return x if root[x] == x else find(root[x])

    for i in range(len(rows)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    out = {}
    for i in range(len(rows)):
        out.setdefault(find(i), []).append(rows[i][0])
    return {min(g) for g in out.values()}


def test_stage_keeps_one_of_each_group_at_080(spark):
    rng = random.Random(3)
    rows = []
    for _ in range(40):
        words = [f"w{rng.randrange(4000)}" for _ in range(150)]
        for changes in (0, 0, 1, 2, 3, 5, 8, 20):
            copy = list(words)
            for at in rng.sample(range(150), changes):
                copy[at] = f"x{rng.randrange(4000)}"
            rows.append((len(rows), " ".join(copy)))
    rows += [(1000, None), (1001, ""), (1002, " \n"), (1003, "one two"), (1004, "one  two"), (1005, "one two three")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("root", F.lit(1))
    got = corpus_pipeline.drop_near_duplicates(spark, df, "")
    assert got.columns == df.columns
    assert sorted(r.doc_id for r in got.collect()) == sorted(brute_groups(rows))
    assert corpus_pipeline.drop_near_duplicates(spark, df.limit(0), "").count() == 0


def test_crowded_buckets_give_the_same_groups(spark):
    rng = random.Random(5)
    rows = []
    common = [f"c{i}" for i in range(120)]  # texts that share three quarters of their words but are no near copies
    for _ in range(60):
        words = common + [f"w{rng.randrange(9000)}" for _ in range(45)]
        rows.append((len(rows), " ".join(words)))
        if rng.random() < 0.4:
            words[130] = "changed"
            rows.append((len(rows), " ".join(words)))
    df = spark.createDataFrame([(f"{k}".encode(), t) for k, t in rows], "tk binary, text string")
    want = brute_groups(rows)
    for most in (3, 2048):
        root = {int(r.tk): int(r.root) for r in simhash.components(near_copies.links(df, most=most)).select(F.col("node").alias("tk"), "root").collect()}
        groups = {}
        for k, _ in rows:
            groups.setdefault(root.get(k, k), []).append(k)
        assert {min(g) for g in groups.values()} == want, most


def test_stage_takes_candidates_from_simhash(spark, monkeypatch):
    rng = random.Random(9)
    words = [f"w{rng.randrange(4000)}" for _ in range(400)]
    one = " ".join(words)
    other = next(t for i in range(400) if (simhash.fingerprint(t := " ".join([*words[:i], "changed", *words[i + 1 :]])) ^ simhash.fingerprint(one)).bit_count() <= simhash.RADIUS)
    far = " ".join(f"v{rng.randrange(4000)}" for _ in range(150))
    monkeypatch.setattr(near_copies, "links", lambda texts, *_: spark.createDataFrame([], "a binary, b binary"))
    df = spark.createDataFrame([(7, other), (3, one), (9, far), (11, None), (12, "")], "doc_id long, text string")
    assert sorted(r.doc_id for r in corpus_pipeline.drop_near_duplicates(spark, df, "").collect()) == [3, 9, 11]
