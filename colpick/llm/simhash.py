"""SimHash fingerprints and exact linking of those that differ in few bits.

Linking is meet-in-the-middle ball hashing.  Two fingerprints at distance 3 or
less differ in some third of the bits, or not at all; with that third masked
out they are at distance 2 or less, so that the balls of half the radius around
both masked fingerprints share a point.  Every distinct fingerprint emits its
ball for each of the three masks, the shuffle is on the points, and colliding
pairs are deduplicated and verified over all 64 bits.

A point shared by more than ``bucket`` fingerprints isn't paired out.  Its
fingerprints are linked exactly in another way, see :func:`dense_links`, whose
output is linear in their number.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import batch_of, durable, marked, parts_for, text_key, unused

RADIUS = 3
#: Bit ranges that the three masks leave out.
THIRDS = ((0, 22), (22, 43), (43, 64))
#: Fingerprints whose balls one task emits.
BALLS = 20_000
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
FINGERPRINTS = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])
LINKS = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("dense", pa.bool_())])


def fingerprint(text: str | None, shingle: int = 3, seed: int = 42) -> int:
    """64-bit SimHash of the word shingles of a text; 0 if it has no words."""
    words = (text or "").encode().translate(LOWER).split()
    if not words:
        return 0
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), seed)
    digest, joined = xxhash.xxh64_intdigest, b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = [0, *(ends[:-1] + 1).tolist()]
    hashes = np.array([digest(joined[a:b], seed) for a, b in zip(starts, ends[shingle - 1 :].tolist())], dtype=">u8")
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 65536):
        ones += np.unpackbits(hashes[at : at + 65536].view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp) for every row; a null text has no words, fp is signed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([fingerprint(t) for t in batch.column(1).to_pylist()], dtype=np.uint64).view(np.int64)
            yield batch_of(FINGERPRINTS, batch.column(0), fps)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, fp long")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def balls(fps: DataFrame) -> DataFrame:
    """(point, fp): the ball of radius 1 around each masked fingerprint, for each mask.

    A point holds the 42 or 43 bits that its mask leaves, closed up, and above
    them, from bit 60, the number of the mask: points of two masks never meet.
    """
    parts = []
    for k, (low, high) in enumerate(THIRDS):
        below = F.col("fp").bitwiseAND(F.lit((1 << low) - 1).cast("long"))
        above = F.shiftleft(F.shiftrightunsigned("fp", high), low) if high < 64 else F.lit(0).cast("long")
        centre = below.bitwiseOR(above).bitwiseOR(F.lit(k << 60).cast("long"))
        flips = [0, *(1 << b for b in range(64 - high + low))]
        parts.append(F.array(*[centre.bitwiseXOR(F.lit(x).cast("long")) for x in flips]))
    return fps.select("fp", F.explode(F.concat(*parts)).alias("point"))


def _popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x.view(np.uint64))


def _pairs(bucket: int):
    """Kernel over rows sorted by point: verified pairs of small buckets, members of large ones.

    It holds one batch and at most ``bucket`` + 1 rows of the point at its end.
    """

    def settle(point, fp, first_is_dense):
        """All rows of whole points; the first point may be known as dense from before."""
        starts = np.flatnonzero(np.concatenate(([True], point[1:] != point[:-1])))
        sizes = np.diff(np.append(starts, len(point)))
        dense = sizes > bucket
        if first_is_dense:
            dense[0] = True
        of = np.repeat(dense, sizes)
        heavy = np.unique(fp[of])
        point, fp = point[~of], fp[~of]
        found = []
        for d in range(1, bucket):
            same = np.flatnonzero(point[d:] == point[:-d]) if len(point) > d else []
            if not len(same):
                break
            a, b = fp[same], fp[same + d]
            near = _popcount(a ^ b) <= RADIUS
            found.append(np.stack([np.minimum(a, b)[near], np.maximum(a, b)[near]], axis=1))
        pairs = np.unique(np.concatenate(found), axis=0) if found else np.empty((0, 2), dtype=np.int64)
        n = len(pairs) + len(heavy)
        if n:
            yield batch_of(LINKS, np.concatenate([pairs[:, 0], heavy]), np.concatenate([pairs[:, 1], heavy]), np.arange(n) >= len(pairs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        point, fp = np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
        known = None
        for batch in batches:
            if not batch.num_rows:
                continue
            point = np.concatenate([point, batch.column(0).to_numpy()])
            fp = np.concatenate([fp, batch.column(1).to_numpy()])
            last = int(np.searchsorted(point, point[-1]))
            if len(point) - last > bucket:  # dense for sure: its rows needn't wait
                yield from settle(point, fp, known == point[0])
                known, point, fp = point[-1], point[:0], fp[:0]
            elif last:
                yield from settle(point[:last], fp[:last], known == point[0])
                point, fp = point[last:], fp[last:]
                known = known if known == point[0] else None
        if len(point):
            yield from settle(point, fp, known == point[0])

    return run


def dense_links(fps: DataFrame) -> DataFrame:
    """Edges (a, b) that connect exactly what is connected among ``fps``, without pairing buckets.

    On full fingerprints, all within 1 of a point are within 2 of each other,
    and within 3 of what is at 2 from it.  Fingerprints at distance 3 differ in
    parity, so only odd ones emit radius 2.  Each point then links its first
    member at radius 1, if any, with all others: a star, linear in the members.
    """
    one = [1 << b for b in range(64)]
    near = [0, *one]
    lits = lambda xs: F.array(*[F.lit(_signed(x)).cast("long") for x in xs])
    bit = F.explode(F.sequence(F.lit(0), F.lit(63)))
    close = fps.select("fp", F.explode(lits(near)).alias("flip")).select(F.col("fp").bitwiseXOR(F.col("flip")).alias("point"), "fp", F.lit(0).alias("ring"))
    odd = fps.where(F.bit_count("fp") % 2 == 1)
    wide = odd.select("fp", bit.alias("i")).select("fp", "i", bit.alias("k")).where("k < i")
    wide = wide.select(F.expr("fp ^ shiftleft(1L, i) ^ shiftleft(1L, k)").alias("point"), "fp", F.lit(2).alias("ring"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, anchor = None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            point, fp, ring = (batch.column(i).to_numpy() for i in range(3))
            starts = np.flatnonzero(np.concatenate(([True], point[1:] != point[:-1])))
            sizes = np.diff(np.append(starts, len(point)))
            has, lead = ring[starts] == 0, fp[starts].copy()
            if at is not None and point[0] == at:
                has[0], lead[0] = anchor is not None, anchor if anchor is not None else 0
            a, ok = np.repeat(lead, sizes), np.repeat(has, sizes)
            at, anchor = point[-1], lead[-1] if has[-1] else None
            keep = ok & (a != fp)
            edges = np.unique(np.stack([np.minimum(a, fp)[keep], np.maximum(a, fp)[keep]], axis=1), axis=0)
            if len(edges):
                yield batch_of(LINKS, edges[:, 0], edges[:, 1], np.zeros(len(edges), dtype=bool))

    rows = close.unionByName(wide).repartition("point").sortWithinPartitions("point", "ring", "fp")
    return rows.mapInArrow(run, "a long, b long, dense boolean").select("a", "b").distinct()


def links(fps: DataFrame, bucket: int = 64) -> DataFrame:
    """Edges (a, b), a < b, whose components are those of all pairs within RADIUS bits.

    ``fps`` has distinct fingerprints.  Pairs that only meet in large buckets
    can be replaced by paths of linked pairs.  The fingerprints are dealt out by
    a count of their own, so that no task makes more than 131 * ``BALLS`` points.
    """
    spread = fps.select("fp").repartition(parts_for(fps, BALLS), "fp")
    rows = balls(spread).select("point", "fp").repartition("point").sortWithinPartitions("point")
    found = durable(rows.mapInArrow(_pairs(bucket), "a long, b long, dense boolean").distinct())
    dense = found.where("dense").select(F.col("a").alias("fp")).distinct()
    return found.where("not dense").select("a", "b").unionByName(dense_links(dense)).distinct()


def components(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """(node, root): the smallest node of each component, for every node with an edge.

    Alternates two star operations, each a minimum over neighbours and a join
    back; hot nodes are met by partial aggregation and skew-join splitting.
    Raises if it doesn't settle, which takes a path of more than 2**rounds nodes.
    """
    now = durable(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v").distinct())
    for _ in range(rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        large = durable(large)
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        after = durable(small.unionByName(least.select("u", F.col("m").alias("v"))).where("u != v").distinct())
        # settled when every node points to one root, and no root points on
        many = after.groupBy("u").count().where("count > 1").limit(1)
        onward = after.select(F.col("v").alias("u")).distinct().join(after.select("u").distinct(), "u", "left_semi").limit(1)
        now = after
        if many.unionByName(onward.withColumn("count", F.lit(0).cast("long"))).isEmpty():
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    raise RuntimeError("components did not settle")


def classes(fps: DataFrame, bucket: int = 64) -> DataFrame:
    """(fp, root, component_id) of every distinct fingerprint of (doc_id, fp): the smallest id of its component."""
    least = durable(fps.groupBy("fp").agg(F.min("doc_id").alias("least")))
    comps = components(links(least.select("fp"), bucket))
    placed = least.join(comps.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    names = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    return placed.join(names, "root").select("fp", "root", "component_id")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket: int = 64) -> DataFrame:
    """(doc_id, fingerprint, component_id), one row per input row.

    Rows with repeated ids or texts each keep a row.  A null text has
    fingerprint zero.  A null id is returned but never names a component: a
    component of null ids alone has a null component_id.  Empty in, empty out.
    """
    fps = durable(fingerprints(docs, id_col, text_col))
    mapping = classes(fps, bucket).drop("root")
    return fps.join(mapping, "fp", "left").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket: int = 64) -> DataFrame:
    """``docs`` with one row of each component: that of its smallest id, null ids last, ties by the text's digest.

    Columns stay as they are; of equal (id, text) rows one stays.
    """
    keyed = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), text_key(F.col(text_col)).alias("tk"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([*FINGERPRINTS, ("tk", pa.binary())])
        for batch in batches:
            fps = np.array([fingerprint(t) for t in batch.column(1).to_pylist()], dtype=np.uint64).view(np.int64)
            yield batch_of(schema, batch.column(0), fps, batch.column(2))

    rows = durable(keyed.mapInArrow(run, "doc_id long, fp long, tk binary"))
    placed = rows.join(classes(rows.select("doc_id", "fp"), bucket).select("fp", "root"), "fp")
    return least_rows(docs, rows, placed, id_col, text_col)


def least_rows(docs: DataFrame, rows: DataFrame, placed: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """``docs`` with one row of each root, of their (doc_id, tk) in ``rows`` and (doc_id, tk, root) in ``placed``.

    Only rows that may be among those to drop are moved, unless these are very many.
    """
    names = {n: unused(f"_{n}", docs, rows) for n in ("id", "tk", "row")}
    best = placed.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "tk")).alias("m"))
    best = durable(best.select(F.col("m.doc_id").alias(names["id"]), F.col("m.tk").alias(names["tk"])))
    same = F.col(names["id"]).eqNullSafe(F.col(id_col).cast("long")) & (F.col(names["tk"]) == text_key(F.col(text_col)))
    best_id, best_tk = F.col(names["id"]), F.col(names["tk"])
    dropped = durable(rows.join(best, best_id.eqNullSafe(F.col("doc_id")) & (best_tk == F.col("tk")), "left_anti").select(F.col("doc_id").alias(names["id"]), F.col("tk").alias(names["tk"])).distinct())
    parts = marked(docs, dropped, F.col(id_col).cast("long"), text_key(F.col(text_col)))
    kept = parts[1].unionByName(parts[0].join(dropped, same, "left_anti")) if parts else docs.join(best, same, "left_semi")
    twice = rows.join(best, F.col(names["id"]).eqNullSafe(F.col("doc_id")) & (F.col(names["tk"]) == F.col("tk")), "left_semi").groupBy("doc_id", "tk").count().where("count > 1")
    if twice.isEmpty():
        return kept
    row = Window.partitionBy(F.col(id_col), text_key(F.col(text_col))).orderBy(F.lit(1))
    return kept.withColumn(names["row"], F.row_number().over(row)).where(F.col(names["row"]) == 1).drop(names["row"])
