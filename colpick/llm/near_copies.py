"""Groups of near copies: texts whose sets of word shingles have a Jaccard similarity of at least a bound.

Texts that SimHash links are compared first, on the shingles of both.  It can't
give all groups: at a similarity of 0.8 two 64-bit fingerprints differ
in about 10 bits, and balls of half that radius have no bounded size.  So
further candidates come from min-wise hashing in bands; every colliding pair is verified
exactly on the shingles of both texts.  With 20 bands of 4 a pair at 0.8 fails
to collide once in 37,000.

First the text of most company in each bucket is compared with the others, which
connects large groups by stars.  Then the texts of a bucket are compared where
they aren't connected yet, each pair in the first band that it shares, if 48 of
their 80 minima agree, which a pair at 0.8 misses twice in a million.  A bucket
of more than ``most`` texts is not compared as it is: its texts go into finer
buckets, one for each further band that they share, until all are small; those
of the last level, five bands, are compared whatever their size.  A pair that
shares one band alone is missed if that bucket is large.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Rolling, batch_of, chunks, durable, marked, mix64, pieces, release, text_key
from .simhash import LOWER, classes, components, fingerprint, least_rows
from .substring_dedup import Tokens

SHINGLE, SIMILAR = 5, 0.8
BANDS, ROWS = 20, 4
MOST, LEVELS = 2048, 5
FACTORS = mix64(np.arange(1, BANDS * ROWS + 1, dtype=np.uint64)) | np.uint64(1)
#: Agreeing minima that make a pair of one bucket a candidate.
AGREE = 48
SIGNS = pa.schema([("tk", pa.binary()), ("keys", pa.list_(pa.int64())), ("least", pa.binary())])
PRINTS = pa.schema([("tk", pa.binary()), ("fp", pa.int64())])
SETS = pa.schema([("tk", pa.binary()), ("items", pa.binary())])
PAIRS = pa.schema([("a", pa.binary()), ("b", pa.binary())])
MET = pa.schema([*PAIRS, ("key", pa.int64()), ("bands", pa.list_(pa.int32()))])


def shingle_sets(texts: list[str | None], shingle: int = SHINGLE) -> list[np.ndarray]:
    """Distinct 64-bit hashes of the word shingles of each text, in lower case; of all words if they are fewer."""
    tokens, grams, out = Tokens(), Rolling(0xA24BAED4963EE407), []
    for low, high in chunks(texts):
        part = [(t or "").encode().translate(LOWER).decode() for t in texts[low:high]]
        hashes, counts = tokens.words(part)
        at = 0
        for n in counts.tolist():
            h, at = hashes[at : at + n], at + n
            out.append(np.unique(grams.windows(grams.prefix(h), min(shingle, n))) if n else h)
    return out + [np.empty(0, dtype=np.uint64)] * (len(texts) - len(out))


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both) if both else 0.0


def _sign(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        band = np.arange(1, BANDS + 1, dtype=np.uint64)
        for batch in pieces(batches, 1):
            names, keys, minima = [], [], []
            for tk, items in zip(batch.column(0).to_pylist(), shingle_sets(batch.column(1).to_pylist(), shingle)):
                if len(items):
                    least = np.full(len(FACTORS), np.iinfo(np.uint64).max, dtype=np.uint64)
                    for at in range(0, len(items), 4096):
                        np.minimum(least, np.multiply.outer(FACTORS, items[at : at + 4096]).min(axis=1), out=least)
                    key = band
                    for j in range(ROWS):
                        key = mix64(key * np.uint64(0x9E3779B97F4A7C15) + least[j::ROWS])
                    names.append(tk)
                    keys.append(key.view(np.int64))
                    minima.append((least >> np.uint64(48)).astype(np.uint16).tobytes())
            if names:
                yield batch_of(SIGNS, names, keys, minima)

    return run


def connections(roots: np.ndarray, least: np.ndarray, sets: list[np.ndarray], bands: list[int], similar: float) -> Iterator[tuple[int, int]]:
    """Pairs of places of near copies of a bucket that connect what differs in root, most alike first.

    ``bands`` are those of the bucket; a pair counts if they are the first ones that it shares.
    """
    roots, size = roots.copy(), np.array([len(x) for x in sets])
    for i in range(len(roots) - 1):
        other = np.flatnonzero(roots[i + 1 :] != roots[i]) + i + 1
        if not len(other):
            continue
        agree = least[other] == least[i]
        score = agree.sum(axis=1)
        shared = agree.reshape(len(other), BANDS, ROWS).all(axis=2)
        first = (shared[:, : bands[-1] + 1].sum(axis=1) == len(bands)) & shared[:, bands].all(axis=1)
        alike = np.minimum(size[other], size[i]) >= similar * np.maximum(size[other], size[i])
        good = np.flatnonzero(first & alike & (score >= AGREE))
        for j in other[good[np.argsort(-score[good], kind="stable")]].tolist():
            if roots[j] != roots[i] and jaccard(sets[i], sets[j]) >= similar:
                yield i, j
                roots[roots == roots[j]] = roots[i]


def _collide(most: int, last: bool, similar: float, most_bytes: int = 64 << 20):
    """Kernel over (key, bands, tk, root, least, items) sorted by key: verified pairs of small buckets, the rows of others.

    It holds ``most`` + 1 rows, or a little over ``most_bytes``, of one bucket; at the last level all rows of a bucket.
    """

    def pairs(rows: list[tuple]):
        if len(rows) < 2:
            return
        roots = np.unique([r[1] for r in rows], return_inverse=True)[1]
        least = np.frombuffer(b"".join(r[2] for r in rows), dtype=np.uint16).reshape(len(rows), -1)
        found = list(connections(roots, least, [np.frombuffer(r[4], dtype=np.uint64) for r in rows], rows[0][3], similar))
        if found:
            i, j = zip(*found)
            yield batch_of(MET, [rows[k][0] for k in i], [rows[k][0] for k in j], pa.nulls(len(i), pa.int64()), pa.nulls(len(i), MET.field("bands").type))

    def rest(key, rows: list[tuple]):
        if rows:
            yield batch_of(MET, [r[0] for r in rows], pa.nulls(len(rows), pa.binary()), [key] * len(rows), [r[3] for r in rows])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, held, size, large = None, [], 0, False
        for batch in pieces(batches, 5):
            for key, bands, tk, root, least, items in zip(*(c.to_pylist() for c in batch.columns)):
                if key != known:
                    yield from rest(known, held) if large else pairs(held)
                    known, held, size, large = key, [], 0, False
                held.append((tk, root, least, bands, items))
                size += len(items)
                if (len(held) > most or size > most_bytes and len(held) > 2 or large and len(held) > 64) and not last:
                    large, size = True, 0
                    yield from rest(known, held)
                    held = []
        yield from rest(known, held) if large else pairs(held)

    return run


def _sets(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, 1):
            if batch.num_rows:
                yield batch_of(SETS, batch.column(0), [x.tobytes() for x in shingle_sets(batch.column(1).to_pylist(), shingle)])

    return run


def _verify(similar: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, 2, 3):
            x, y = ([np.frombuffer(v, dtype=np.uint64) for v in batch.column(i).to_pylist()] for i in (2, 3))
            near = [i for i, (p, q) in enumerate(zip(x, y)) if jaccard(p, q) >= similar]
            if near:
                yield batch_of(PAIRS, batch.column(0).take(pa.array(near)), batch.column(1).take(pa.array(near)))

    return run


def _set_frame(texts: DataFrame, needed: DataFrame, shingle: int) -> DataFrame:
    """(tk, items): the shingle sets of the texts whose keys are needed, which are distinct.

    Few texts are needed as a rule, so the others are left out before any text is moved.
    """
    likely = marked(texts, needed, "tk")
    single = (likely[0] if likely else texts).groupBy("tk").agg(F.first("text").alias("text")).join(needed, "tk", "left_semi")
    return durable(single.mapInArrow(_sets(shingle), "tk binary, items binary"))


def _verified(pairs: DataFrame, texts: DataFrame, similar: float, shingle: int) -> DataFrame:
    """Of the distinct ``pairs``, those that are near copies by the shingles of both texts."""
    found = durable(pairs.distinct())
    release(found.sparkSession)
    sets = _set_frame(texts, found.select(F.col("a").alias("tk")).union(found.select("b")).distinct(), shingle)
    both = found.join(sets.toDF("a", "x"), "a").join(sets.toDF("b", "y"), "b").select("a", "b", "x", "y")
    return durable(both.mapInArrow(_verify(similar), "a binary, b binary"))


def links(texts: DataFrame, similar: float = SIMILAR, shingle: int = SHINGLE, most: int = MOST) -> DataFrame:
    """(a, b): verified pairs of near copies among the texts (tk, text), enough to connect each group; rows of one key have one text."""
    signs = texts.mapInArrow(_sign(shingle), "tk binary, keys array<long>, least binary")
    signs = durable(signs.groupBy("tk").agg(F.first("keys").alias("keys"), F.first("least").alias("least")))
    rows = signs.select("tk", F.posexplode("keys").alias("band", "key"))
    shared = durable(rows.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"))
    rows = durable(rows.join(shared, "key").select("key", "band", "tk", F.log2("n").alias("n")))
    # stars around the text of most company in each bucket
    company = rows.groupBy("tk").agg(F.sum("n").alias("company"))
    centre = rows.join(company, "tk").groupBy("key").agg(F.max(F.struct("company", "tk")).alias("m")).select("key", F.col("m.tk").alias("a"))
    stars = _verified(rows.join(centre, "key").where("a != tk").select("a", F.col("tk").alias("b")), texts, similar, shingle)
    # what they leave unconnected
    roots = components(stars).select(F.col("node").alias("tk"), "root")
    signed = signs.join(rows.select("tk").distinct(), "tk", "left_semi").join(roots, "tk", "left")
    signed = durable(signed.select("tk", "keys", "least", F.coalesce("root", "tk").alias("root")))
    found, now, sets = stars, rows.select("key", F.array("band").alias("bands"), "tk"), None
    for level in range(1, LEVELS + 1):
        # a bucket within one group, however large, has nothing to add
        rooted = now.join(signed.select("tk", F.xxhash64("root").alias("r")), "tk")
        mixed = rooted.groupBy("key").agg(F.min("r").alias("low"), F.max("r").alias("high")).where("low != high").select("key")
        now = durable(now.join(mixed, "key", "left_semi"))
        release(now.sparkSession)
        sets = _set_frame(texts, now.select("tk").distinct(), shingle) if sets is None else sets
        full = now.join(signed.select("tk", "root", "least"), "tk").join(sets, "tk").select("key", "bands", "tk", "root", "least", "items")
        met = full.repartition("key").sortWithinPartitions("key", "tk").mapInArrow(_collide(most, level == LEVELS, similar), "a binary, b binary, key long, bands array<int>")
        met = durable(met)
        found = found.unionByName(met.where("b is not null").select("a", "b"))
        dense = met.where("b is null").select("key", "bands", F.col("a").alias("tk"))
        if dense.isEmpty():
            break
        finer = dense.join(signed.select("tk", F.posexplode("keys").alias("next", "other")), "tk").where("next > element_at(bands, -1)")
        now = finer.select(F.xxhash64("key", "other").alias("key"), F.concat("bands", F.array("next")).alias("bands"), "tk")
    return found


def groups(texts: DataFrame, similar: float = SIMILAR, shingle: int = SHINGLE) -> DataFrame:
    """(tk, root) of the texts (tk, text) that have a near copy; root is the smallest key of the group."""
    return components(links(texts, similar, shingle)).select(F.col("node").alias("tk"), "root")


def fingerprint_links(texts: DataFrame, bucket: int = 64) -> DataFrame:
    """(a, b): candidates among the texts (tk, text), each text that SimHash links with the smallest key of its component."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches, 1):
            if batch.num_rows:
                fps = np.array([fingerprint(t) for t in batch.column(1).to_pylist()], dtype=np.uint64).view(np.int64)
                yield batch_of(PRINTS, batch.column(0), fps)

    prints = durable(texts.mapInArrow(run, "tk binary, fp long").distinct())
    roots = classes(prints.select(F.lit(0).cast("long").alias("doc_id"), "fp"), bucket).select("fp", "root")
    placed = prints.join(roots, "fp").select("tk", F.col("root").alias("r"))
    least = placed.groupBy("r").agg(F.min("tk").alias("a"), F.count("*").alias("n")).where("n > 1")
    return placed.join(least, "r").where("a != tk").select("a", F.col("tk").alias("b"))


def keep_first(docs: DataFrame, similar: float = SIMILAR, shingle: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one row of each group of equal texts and near copies, found by SimHash and, beyond its reach, by min-wise hashing: as in :func:`simhash.keep_first`.

    Texts without words, null ones included, are one group.
    """
    text = F.col(text_col)
    keyed = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), text_key(text).alias("tk"))
    rows = durable(keyed.select("doc_id", "tk", F.coalesce(F.regexp_like("text", F.lit(r"[^\x20\x09-\x0D]")), F.lit(False)).alias("words")))
    texts = keyed.select("tk", "text")
    linked = _verified(fingerprint_links(texts), texts, similar, shingle)
    near = components(linked.unionByName(links(texts, similar, shingle))).select(F.col("node").alias("tk"), "root")
    release(docs.sparkSession)
    placed = rows.join(near, "tk", "left").withColumn("root", F.when(F.col("words"), F.coalesce("root", "tk")).otherwise(text_key(F.lit(""))))
    return least_rows(docs, rows, placed, id_col, text_col)
