"""Registered queries of the training-data operators, and SQL where it can say the same."""

from __future__ import annotations

import uuid

import public_tokenizers

from . import byte_bpe, decontamination, html_text, secrets, sharding, simhash, substring_dedup, token_counts, topk, toxicity
from .common import load, shared_folder


def _token_counts(spark, sf_dir):
    """Batches: all documents put in under two tokenizer versions, one version counted anew, and the
    documents that are labelled toxic taken out again; the first is sent twice.

    The ledger is a new folder beside the session's checkpoints.
    """
    docs = load(spark, sf_dir, "documents", "doc_id", "text", "source", "lang")
    toxic = load(spark, sf_dir, "labels", "doc_id", "toxic").where("toxic = 1").select("doc_id").distinct()
    words, letters = token_counts.word_tokens, token_counts.letter_tokens
    load_words = token_counts.counted(docs, "words-1", words)
    load_letters = token_counts.counted(docs, "letters-1", words)
    recount = token_counts.revised(docs, "letters-1", words, letters)
    # counted before they meet the labels, so that no text is shuffled
    out = token_counts.counted(docs, "words-1", words, -1, keep=("doc_id",)).unionByName(token_counts.counted(docs, "letters-1", letters, -1, keep=("doc_id",)))
    taken = out.join(toxic, "doc_id", "left_semi").drop("doc_id")
    batches = [("load-words", load_words), ("load-letters", load_letters), ("recount", recount), ("taken-down", taken), ("load-words", load_words)]
    return token_counts.commit_batches(spark, f"{shared_folder(spark)}/token-counts-{uuid.uuid4()}", batches)


def _toxicity(spark, sf_dir):
    docs = load(spark, sf_dir, "documents", "doc_id", "text")
    return toxicity.score(docs, toxicity.train(docs, load(spark, sf_dir, "labels", "doc_id", "toxic")))


QUERIES = {
    "op1_token_counts": _token_counts,
    "op2_simhash": lambda s, d: simhash.near_duplicates(load(s, d, "documents", "doc_id", "text")),
    "op3_decontamination": lambda s, d: decontamination.contamination(load(s, d, "documents", "doc_id", "text"), load(s, d, "benchmark", "item_id", "text")),
    "op5_substring_dedup": lambda s, d: substring_dedup.remove_repeats(load(s, d, "documents", "doc_id", "text")),
    "op4_sharding": lambda s, d: sharding.shard_documents(load(s, d, "documents", "doc_id", "text")),
    "op6_html_text": lambda s, d: html_text.extract(load(s, d, "pages", "page_id", "url", "html")),
    "op7_topk": lambda s, d: topk.top_k(load(s, d, "embeddings", "vec_id", "embedding")),
    "op8_byte_bpe": lambda s, d: byte_bpe.digests(load(s, d, "documents", "doc_id", "text"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken")),
    "op9_toxicity": _toxicity,
    "op10_secrets": lambda s, d: secrets.scan(load(s, d, "documents", "doc_id", "text")),
}

_DIGEST = "substr(md5(coalesce(doc_id::VARCHAR, 'null') || ':' || {s}), 1, 13)"
ORACLES = {
    "op1_token_counts": r"""
WITH c AS (SELECT source, lang, strlen(coalesce(text, '')) AS b,
    len(list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w != '')) AS words,
    len(list_filter(regexp_split_to_array(coalesce(text, ''), '[^A-Za-z0-9]+'), lambda w: w != '')) AS letters FROM documents WHERE doc_id IS NULL OR doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1 AND doc_id IS NOT NULL))
SELECT source, lang, tokenizer, count(*) AS n_docs, sum(CASE WHEN tokenizer = 'words-1' THEN words ELSE letters END)::BIGINT AS n_tokens, sum(b)::BIGINT AS n_bytes
FROM c, (VALUES ('words-1'), ('letters-1')) v(tokenizer) GROUP BY ALL""",
    "op7_topk": """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)::BIGINT) AS q FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT a.vec_id AS query_id, b.vec_id, list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2]))::BIGINT AS score FROM v a, v b WHERE a.vec_id % 20 = 0 AND a.vec_id != b.vec_id),
r AS (SELECT *, (row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id))::INTEGER AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20""",
    "op4_sharding": """
WITH table_ AS (SELECT list(c ORDER BY i) AS t FROM (
    SELECT i, list_reduce([i] || [0, 0, 0, 0, 0, 0, 0, 0]::BIGINT[], lambda c, z: CASE WHEN c % 2 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END) AS c FROM range(256) r(i))),
d AS (SELECT doc_id, strlen(coalesce(text, '')) + 16 AS size, hex(encode(coalesce(text, ''))) AS h FROM documents),
c AS (SELECT doc_id, size, xor(list_reduce([4294967295::BIGINT] || list_transform(range(0, size - 16), lambda i: ('0x' || substr(h, 2 * i + 1, 2))::BIGINT), lambda c, b: xor(c >> 8, t[(xor(c, b) & 255) + 1])), 4294967295) AS crc FROM d, table_),
p AS (SELECT c.*, list_max(list_transform(range(0, 40), lambda s: {u: <some>, s: -s})) AS best FROM c),
q AS (SELECT *, (-(best.s))::INTEGER AS shard, <new> AS grown FROM p)
SELECT doc_id, size::BIGINT AS size, crc::BIGINT AS text_crc32, 'key' AS law, shard, row_number() OVER (PARTITION BY shard ORDER BY substr(md5(coalesce(doc_id::VARCHAR, 'null') || ':' || crc::VARCHAR), 1, 2), doc_id NULLS FIRST, size, crc) - 1 AS slot, CASE WHEN grown > best.u THEN 40 ELSE shard END::INTEGER AS grown_shard FROM q""".replace("<some>", _DIGEST.format(s="s::VARCHAR")).replace("<new>", _DIGEST.format(s="'40'")),
}
