import random
import re

import xxhash
from pyspark.sql import functions as F

from colpick.llm import simhash


def brute_fingerprint(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    sh = [" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))] if w else []
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_components(nodes):
    nodes = list(nodes)
    root = {x: x for x in nodes}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, x in enumerate(nodes):
        for y in nodes[:i]:
            if (x ^ y).bit_count() <= 3:
                a, b = find(x), find(y)
                root[max(a, b)] = min(a, b)
    return {x: find(x) for x in nodes}


TEXTS = [None, "", "  \t ", "one", "one two", "Ünder\x0bthe Bridge the bridge THE bridge", "x\x1fy z w", "a b c d " * 5000, "z" * 70000]


def test_fingerprint_matches_brute_force():
    rng = random.Random(1)
    for t in [*TEXTS, *[" ".join(rng.choice("ab cD é    foo bar".split(" ")) for _ in range(n)) for n in (2, 3, 4, 50)]]:
        assert simhash.fingerprint(t) == brute_fingerprint(t)


def test_links_have_the_components_of_all_pairs(spark):
    rng = random.Random(7)
    seeds = [rng.getrandbits(64) for _ in range(12)]
    pool = {rng.getrandbits(64) for _ in range(60)} | {0, (1 << 64) - 1, 1 << 63}
    for s in seeds:  # distances of exactly 1 to 4, chains, and dense clusters
        for _ in range(20):
            y = s
            for b in rng.sample(range(64), rng.choice([1, 2, 3, 4])):
                y ^= 1 << b
            pool.add(y)
    for _ in range(150):
        pool.add(seeds[0] ^ sum(1 << b for b in rng.sample(range(24), rng.choice([1, 2, 3]))))
    want = {simhash._signed(k): v for k, v in brute_components(sorted(pool)).items()}
    fps = spark.createDataFrame([(simhash._signed(x),) for x in pool], "fp long")
    for bucket in (2, 5, 64):
        got = {r.node: r.root for r in simhash.components(simhash.links(fps, bucket)).collect()}
        mine, theirs = {}, {}
        for x in want:
            mine.setdefault(got.get(x, x), set()).add(x)
            theirs.setdefault(want[x], set()).add(x)
        assert sorted(map(sorted, mine.values())) == sorted(map(sorted, theirs.values())), bucket


def test_balls_are_the_neighbours_of_each_masked_fingerprint(spark):
    fps = [5, -7, 1 << 40]
    rows = simhash.balls(spark.createDataFrame([(x,) for x in fps], "fp long")).collect()
    assert len(rows) == 3 * (3 + 64 * 2)
    mask = (1 << 64) - 1
    want = set()
    for fp in fps:
        for k, (low, high) in enumerate(simhash.THIRDS):
            bits = f"{fp & mask:064b}"[::-1]
            kept = bits[:low] + bits[high:]
            base = sum(1 << i for i, b in enumerate(kept) if b == "1") + (k << 60)
            want |= {(fp, base), *((fp, base ^ 1 << i) for i in range(len(kept)))}
    assert {(r.fp, r.point & mask) for r in rows} == want
    links = simhash.links(spark.createDataFrame([(x,) for x in fps], "fp long"), 64).collect()
    assert [(r.a, r.b) for r in links] == [(5, 1 << 40)]  # three bits apart


def test_points_of_two_masks_never_meet(spark):
    rng = random.Random(11)
    fps = [simhash._signed(rng.getrandbits(64) & rng.getrandbits(64) & 0x0000_0600_0003) for _ in range(30)] + [1, 2 << 22, 3 << 43]
    rows = simhash.balls(spark.createDataFrame([(x,) for x in set(fps)], "fp long")).collect()
    assert {r.point >> 60 for r in rows} == {0, 1, 2}
    found = simhash.links(spark.createDataFrame([(x,) for x in set(fps)], "fp long"), 64).collect()
    assert all(r.a < r.b and (r.a ^ r.b).bit_count() <= 3 for r in found)


def test_keep_first_with_columns_named_like_its_own(spark):
    rows = [(2, "one text of several words", "x"), (1, "one text of several words", "y"), (1, "one text of several words", "z"), (None, None, "n")]
    df = spark.createDataFrame(rows, "doc_id long, text string, _id string").selectExpr("*", "_id as _tk", "_id as _row", "_id as fp", "_id as root", "_id as no_id")
    kept = simhash.keep_first(df)
    assert kept.columns == df.columns
    got = kept.collect()
    assert sorted(str(r.doc_id) for r in got) == ["1", "None"]
    assert all(r._id == r._tk == r._row == r.fp for r in got)


def test_rows_nulls_ties_and_clashing_columns(spark):
    rows = [(3, "the same text here", 1), (1, "the same text here", 2), (1, "the same text here", 2), (9, None, 3), (None, "", 4), (8, "   ", 5), (5, "quite another text than that", 6)]
    df = spark.createDataFrame(rows, "doc_id long, text string, fingerprint int").withColumn("fp", F.lit("x")).withColumn("component_id", F.lit(0))
    got = sorted(((r.doc_id, r.fingerprint, r.component_id) for r in simhash.near_duplicates(df).collect()), key=repr)
    zero = "0" * 16
    same, other = (f"{simhash.fingerprint(t):016x}" for t in ("the same text here", "quite another text than that"))
    assert got == sorted([(3, same, 1), (1, same, 1), (1, same, 1), (9, zero, 8), (None, zero, 8), (8, zero, 8), (5, other, 5)], key=repr)
    assert simhash.near_duplicates(df.limit(0)).count() == 0
    one = simhash.near_duplicates(spark.createDataFrame([(None, "alone")], "doc_id long, text string")).first()
    assert one.component_id is None
