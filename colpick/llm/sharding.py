"""Rendezvous hashing of stable record keys over weighted shards.

A record goes to the shard with the highest score -weight / ln(u), where u is a
hash of the record's key and the shard's name in (0, 1).  Adding a shard moves
only records that it wins; removing one moves only its own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import unused


def uniform(key: Column, shard: object) -> Column:
    """A number in (0, 1) from 52 bits of a digest of key and shard."""
    digits = F.substring(F.md5(F.concat_ws(":", key.cast("string"), F.lit(str(shard))).cast("binary")), 1, 13)
    return (F.conv(digits, 16, 10).cast("double") + 0.5) / float(1 << 52)


def place(key: Column, shards: int | dict[int, float]) -> Column:
    """The shard of a key: shards is their number, or a weight for each shard number.

    A null key is a key of its own.  Equal weights compare the digests
    themselves, which gives the same order without logarithms.  Ties, of
    measure zero, go to the lower shard.
    """
    weights = {s: 1.0 for s in range(shards)} if isinstance(shards, int) else dict(shards)
    if not weights or min(weights.values()) < 0 or max(weights.values()) <= 0:
        raise ValueError("a shard with a positive weight is needed")
    live = {s: w for s, w in sorted(weights.items()) if w > 0}
    key = F.coalesce(key.cast("string"), F.lit("null"))
    if len(set(live.values())) == 1:
        scores = [F.struct(F.substring(F.md5(F.concat_ws(":", key, F.lit(str(s))).cast("binary")), 1, 13).alias("u"), F.lit(-s).alias("s")) for s in live]
    else:
        scores = [F.struct((-w / F.ln(uniform(key, s))).alias("u"), F.lit(-s).alias("s")) for s, w in live.items()]
    best = F.greatest(*scores) if len(scores) > 1 else scores[0]
    return (-best["s"]).cast("int")


def slots(df: DataFrame, shard: str, part: Column, order: list[str]) -> DataFrame:
    """``df`` with ``slot``: gapless numbers from 0 within each shard.

    ``part`` cuts each shard into a bounded number of parts.  Parts are counted,
    the counts of one shard summed up in a window over its parts, and rows
    numbered within their part, so that no task gets a whole shard.
    """
    p, n, row, at, of, before = (unused(f"_{x}", df) for x in ("part", "n", "row", "shard", "of", "before"))
    cut = df.withColumn(p, part)
    sizes = cut.groupBy(shard, p).agg(F.count("*").alias(n))
    sums = F.coalesce(F.sum(n).over(Window.partitionBy(shard).orderBy(p).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sizes.select(F.col(shard).alias(at), F.col(p).alias(of), sums.alias(before))
    numbered = cut.withColumn(row, F.row_number().over(Window.partitionBy(shard, p).orderBy(*order)) - 1)
    joined = numbered.join(F.broadcast(offsets), (F.col(shard) == F.col(at)) & (F.col(p) == F.col(of)))
    return joined.withColumn("slot", (F.col(row) + F.col(before)).cast("long")).drop(p, row, at, of, before)


def shard_documents(docs: DataFrame, shards: int = 40, id_col: str = "doc_id", text_col: str = "text", overhead: int = 16) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) by the ``key`` law.

    The document id and the number of shards alone decide.  size: UTF-8 bytes
    plus ``overhead``; a null text has none and crc32 0.  Null ids form one key,
    rows with repeated ids share a shard and get slots of their own.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    key = F.col(id_col).cast("long")
    rows = docs.select(key.alias("doc_id"), (F.octet_length(text) + F.lit(overhead)).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    rows = rows.withColumn("shard", place(F.col("doc_id"), shards))
    grown = F.when(uniform_text(F.col("doc_id"), shards) > uniform_text(F.col("doc_id"), F.col("shard")), F.lit(shards)).otherwise(F.col("shard"))
    rows = rows.withColumn("grown_shard", grown.cast("int"))
    part = F.substring(F.md5(F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.col("text_crc32").cast("string")).cast("binary")), 1, 2)
    return slots(rows, "shard", part, ["doc_id", "size", "text_crc32"]).select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def uniform_text(key: Column, shard: Column | int) -> Column:
    """The digest that :func:`place` compares for equal weights."""
    shard = F.lit(str(shard)) if isinstance(shard, int) else shard.cast("string")
    return F.substring(F.md5(F.concat_ws(":", F.coalesce(key.cast("string"), F.lit("null")), shard).cast("binary")), 1, 13)
