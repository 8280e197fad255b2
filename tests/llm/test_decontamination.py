import collections
import hashlib
import random
import re

import pytest
from pyspark.sql import functions as F

from colpick.llm import decontamination as dc

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def split(text):
    return WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))


def brute(docs, items, n=13):
    out = []
    for key, text in docs:
        w = split(text)
        hit, found = set(), set()
        for item, t in items:
            q = split(t)
            for i in range(max(1, len(q) - n + 1) if q and item is not None else 0):
                win = q[i : i + n]
                for p in range(len(w) - len(win) + 1):
                    if w[p : p + len(win)] == win:
                        hit.update(range(p, p + len(win)))
                        found.add(str(item))
        out.append((key, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=repr)


def case(seed):
    rng = random.Random(seed)
    word = lambda: rng.choice(["a", "b", "c", "É", "d9", "the"])
    items = [(i, " ".join(word() for _ in range(rng.choice([0, 1, 5, 13, 14, 30])))) for i in range(12)] + [(None, "a b"), (3, "c c the"), (99, None)]
    docs = [(i, " ".join(word() for _ in range(rng.choice([0, 3, 40, 300])))) for i in range(40)]
    for i in range(20):
        base = rng.choice(items)[1] or ""
        docs.append((100 + i, docs[i][1] + ", " + base.upper().replace(" ", "; ") + "! " + docs[i + 1][1]))
    return docs + [(None, "a b c"), (5, None), (5, None), (7, ""), (8, "zz " * 20000)], items


@pytest.mark.parametrize("seed", [1, 2])
def test_equals_brute_force(spark, seed):
    docs, items = case(seed)
    d = spark.createDataFrame(docs, "doc_id long, text string").withColumn("n_words", F.lit(-1)).repartition(3)
    b = spark.createDataFrame(items, "item_id long, text string")
    assert sorted((tuple(r) for r in dc.contamination(d, b).collect()), key=repr) == brute(docs, items)


def test_small_blocks_phrases_and_proximity(spark):
    docs = [(1, "x a b c y"), (2, "a b"), (3, "c c a q b"), (4, "b a b a b")]
    d = spark.createDataFrame(docs, "doc_id long, text string").coalesce(1)
    index = dc.build_index(d, gap=5, block_words=8)
    assert index.count() > 1
    exact = {(r.doc_id, r.phrase, r.start, r.end) for r in dc.phrase_matches(index, {1: (b"a", b"b"), 2: (b"c", b"c"), 3: ()}).collect()}
    assert exact == {(1, 1, 1, 3), (2, 1, 0, 2), (4, 1, 1, 3), (4, 1, 3, 5), (3, 2, 0, 2)}
    near = {(r.doc_id, r.start, r.end) for r in dc.proximity_matches(index, {1: (b"c", b"b")}, 3).collect()}
    assert near == {(1, 2, 4)}
    assert {r.doc_id for r in dc.proximity_matches(index, {1: (b"c", b"b")}, 4).collect()} == {1, 3}


def test_empty_tables_and_a_test_set_too_large(spark):
    d = spark.createDataFrame([], "doc_id long, text string")
    b = spark.createDataFrame([(1, "a b c d")], "item_id long, text string")
    assert dc.contamination(d, b).count() == 0
    one = dc.contamination(spark.createDataFrame([(1, "a b")], d.schema), b.limit(0)).first()
    assert (one.n_words, one.n_hit, one.contaminated) == (2, 0, False)
    large = b.withColumn("text", F.repeat("text", 100))
    assert dc.contamination(d, large, max_windows=1).count() == 0 and dc.keep_clean(d, large, max_windows=1).count() == 0


def test_a_test_set_in_pieces_gives_the_same_rows(spark):
    docs, items = case(3)
    d = spark.createDataFrame(docs, "doc_id long, text string").withColumn("row", F.lit(1)).withColumn("block", F.lit(2)).repartition(3)
    b = spark.createDataFrame(items, "item_id long, text string")
    want = brute(docs, items)
    assert sorted((tuple(r) for r in dc.contamination(d, b, max_windows=7).collect()), key=repr) == want
    kept = dc.keep_clean(d, b, max_windows=7)
    assert kept.columns == d.columns
    assert sorted((r.doc_id for r in kept.collect()), key=repr) == sorted((r[0] for r in want if not r[5]), key=repr) == sorted((r.doc_id for r in dc.keep_clean(d, b).collect()), key=repr)


def brute_near(words, terms, slop):
    need = collections.Counter(terms)
    ok = {(a, b) for a in range(len(words)) for b in range(a + 1, min(len(words), a + slop) + 1) if not need - collections.Counter(words[a:b])}
    return {(a, b) for a, b in ok if not any((c, e) != (a, b) and a <= c and e <= b for c, e in ok)}


def test_proximity_equals_brute_force(spark):
    rng = random.Random(8)
    docs = [(i, " ".join(rng.choice("aabcd") for _ in range(rng.choice([0, 1, 5, 40])))) for i in range(40)]
    d = spark.createDataFrame(docs, "doc_id long, text string").coalesce(2)
    phrases = {1: (b"a", b"b"), 2: (b"c", b"a", b"c"), 3: (b"d", b"d"), 4: (b"zz",), 5: ()}
    for slop in (2, 3, 6):
        index = dc.build_index(d, gap=slop, block_words=60)
        got = {(r.doc_id, r.phrase, r.start, r.end) for r in dc.proximity_matches(index, phrases, slop).collect()}
        want = {(i, k, *s) for i, t in docs for k, p in phrases.items() if p for s in brute_near(t.split(), [x.decode() for x in p], slop)}
        assert got == want, slop
    with pytest.raises(Exception, match="gap"):
        dc.proximity_matches(dc.build_index(d, gap=2), phrases, 6).collect()
