import hashlib
import random

import public_tokenizers
import pytest
import tiktoken
from pyspark.sql import functions as F

from colpick.llm import byte_bpe

PATH = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


@pytest.fixture(scope="module")
def reference():
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.codec(PATH).ranks, special_tokens={})


def same(texts, reference):
    c = byte_bpe.codec(PATH)
    for t, ids in zip(texts, c.encode_batch(texts), strict=True):
        assert ids.tolist() == reference.encode_ordinary(t or ""), repr(t)[:200]
        assert c.decode(ids) == (t or "").encode()
        at = c.offsets(ids)
        assert at[-1] == len((t or "").encode()) and len(at) == len(ids) + 1


def test_hand_cases(reference):
    same(["", None, " ", "  ", "\n", "a\n\nb", "a \n b", "it's", "it'sabc", "'s's's", " 's", "\n's", "''s", "x!'s", "'re've'll'd'm't", "'r'v'l", "'S", "1'd2", "a'", "don't  stop\t\tnow ", "　x y\x85z\x1cq", "a" * 300, "!" * 300, " " * 300 + "x", "é́ÄÖ 日本語 ½²٣", "<|endoftext|>"], reference)


def test_random_texts(reference):
    rng = random.Random(3)
    parts = list("aZé日1٣½ '  \n\t!- ́😀") + ["'s", "'re", "'ll", "the", " of"]
    same(["".join(rng.choice(parts) for _ in range(rng.choice([1, 5, 40, 400]))) for _ in range(400)], reference)
    same(["".join(rng.choice(parts) for _ in range(60000))], reference)


def test_every_code_point(reference):
    points = [c for c in range(0x110000) if not 0xD800 <= c <= 0xDFFF and chr(c).isprintable() | (c < 0x3001)]
    same(["".join(f"a{chr(c)}1 {chr(c)}!" for c in points[i : i + 4000]) for i in range(0, len(points), 4000)], reference)


def test_rows(spark, reference):
    rows = [(1, "Hello wörld's"), (1, "Hello wörld's"), (None, "x"), (2, None), (3, ""), (4, "ab " * 40000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("ids", F.lit("clash"))
    want = sorted(((k, len(i := reference.encode_ordinary(t or "")), hashlib.sha256(b"".join(x.to_bytes(4, "little") for x in i)).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()) for k, t in rows), key=repr)
    assert sorted((tuple(r) for r in byte_bpe.digests(df, PATH).collect()), key=repr) == want
    back = byte_bpe.decode(byte_bpe.encode(df, PATH), PATH)
    assert all(bytes(r.decoded) == (r.text or "").encode() and len(r.offsets) == len(r.ids) + 1 for r in back.collect())
    assert byte_bpe.digests(df.limit(0), PATH).count() == 0
