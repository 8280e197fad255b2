"""Removal of passages that occur more than once, by relative Lempel-Ziv parsing.

Reference blocks.  The corpus is indexed in blocks by content: a window of
``window`` words belongs to the block of its anchor, the ``gram``-word phrase
in it with the smallest hash.  Equal windows have equal anchors, so a document
can only match in the blocks of its own anchors; consecutive windows with one
anchor form a stretch, which is parsed against the one block that can hold it
and so, in effect, against every block.

Parsing.  The windows of a block are indexed with their places.  A stretch is
factored greedily: at a window that occurs elsewhere in the block the parse takes
one such place as the source, and the factor runs on for as long as the next
window is the source's next; then the parse looks up the next window again.  So
every factor has ``window`` words at least, and a source of the same length.
Factors of neighbouring stretches overlap where they belong together, so that
the union of all factors is exactly the set of words covered by repeated windows.

Check.  Windows are looked up by 64-bit hashes.  Before anything is removed, the
words of each factor, from boundary to boundary, are compared with those of its
source by an MD5 digest taken from the source's own text.

Sizes.  A block of more than ``block_rows`` stretches isn't parsed in one task:
its stretches and windows are counted by partially aggregated group-bys and
joined back.  Anchors that make up more than a part in 512 of a random sixteenth
of the texts are dealt over all tasks from the start; the sample only decides
the way that a stretch takes, and the result is the same.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Rolling, batch_of, chunks, durable, mix64, text_key

WINDOW = 35
GRAM = 8
#: Bytes of a window's hash that are kept, within its anchor's block: all of it.
KEPT = 8
SPACES = np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])
STRETCH = pa.schema([("anchor", pa.int64()), ("tk", pa.binary()), ("start", pa.int32()), ("windows", pa.binary())])
STRETCH_DDL = "anchor long, tk binary, start int, windows binary"
FACTOR = pa.schema([("anchor", pa.int64()), ("tk", pa.binary()), ("start", pa.int32()), ("n", pa.int32()), ("windows", pa.binary()), ("source", pa.binary()), ("at", pa.int32())])
FACTOR_DDL = "anchor long, tk binary, start int, n int, windows binary, source binary, at int"
DIGEST = pa.schema([("source", pa.binary()), ("at", pa.int32()), ("n", pa.int32()), ("digest", pa.binary())])
#: Parts of the texts that are looked at for anchors that are very frequent, and the share that makes one so.
ROUTE_SAMPLE, ROUTE_SHARE = 1 / 16, 1 / 512
RESULT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string())])
RESULT_DDL = "doc_id long, n_words long, n_removed long, kept_sha256 string"


class Tokens:
    """Word hashes of many texts at once, from the bytes of their concatenation."""

    def __init__(self):
        self.bytes, self.grams = Rolling(0x9E3779B97F4A7C15), Rolling(0xD6E8FEB86659FD93)

    def words(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """(hash of each word, number of words of each text)."""
        raw = [(t or "").encode() for t in texts]
        flat = np.frombuffer(b"\n".join([*raw, b""]), dtype=np.uint8)
        space = SPACES[flat]
        before = np.concatenate(([True], space[:-1]))
        start, end = np.flatnonzero(before & ~space), np.flatnonzero(~before & space)
        prefix = self.bytes.prefix(flat.astype(np.uint64) + np.uint64(1))
        hashes = mix64(self.bytes.ranges(prefix, start, end) + (end - start).astype(np.uint64))
        edges = np.cumsum([0, *[len(r) + 1 for r in raw]])
        return hashes, np.diff(np.searchsorted(start, edges))

    def stretches(self, h: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of one text: (first window of each stretch, its anchor, hashes of all windows)."""
        prefix = self.grams.prefix(h)
        grams, whole = self.grams.windows(prefix, gram), self.grams.windows(prefix, window)
        span = window - gram + 1
        best = np.lib.stride_tricks.sliding_window_view(grams, span).argmin(axis=1) + np.arange(len(whole))
        first = np.flatnonzero(np.concatenate(([True], best[1:] != best[:-1])))
        return first, grams[best[first]], whole


def stretches(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, text_col: str = "text") -> DataFrame:
    """(anchor, tk, start, windows) of every text; texts of fewer words than a window have none.

    From the third of the equal texts that a task meets none are emitted: two say
    all that there is to say of them.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens, seen = Tokens(), {}
        for batch in batches:
            keys, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            if len(seen) > 200_000:
                seen = {}
            for i, key in enumerate(keys):
                seen[key] = seen.get(key, 0) + 1
                if seen[key] > 2:
                    texts[i] = None
            for low, high in chunks(texts):
                hashes, counts = tokens.words(texts[low:high])
                anchor, tk, start, cut = [], [], [], []
                at = 0
                for key, n in zip(keys[low:high], counts.tolist()):
                    h, at = hashes[at : at + n], at + n
                    if n < window:
                        continue
                    first, names, whole = tokens.stretches(h, window, gram)
                    data = np.ascontiguousarray(whole.view(np.uint8).reshape(-1, 8)[:, :KEPT]).tobytes()
                    ends = np.append(first[1:], len(whole))
                    anchor.append(names)
                    start.append(first)
                    tk.extend([key] * len(first))
                    cut.extend([data[KEPT * a : KEPT * b] for a, b in zip(first.tolist(), ends.tolist())])
                if tk:
                    yield batch_of(STRETCH, np.concatenate(anchor).view(np.int64), tk, np.concatenate(start).astype(np.int32), cut)

    return docs.select(text_key(F.col(text_col)).alias("tk"), F.col(text_col)).mapInArrow(run, STRETCH_DDL)


def _expand(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(all window hashes, number of windows of each row)."""
    items = column.to_pylist()
    return np.frombuffer(b"".join(items), dtype=np.uint64), np.array([len(x) // KEPT for x in items], dtype=np.int64)


def factors(anchor: np.ndarray, hashes: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first window, last window, first window of the source) of each factor of a run of blocks.

    Windows are numbered through the stretches, of which the k-th has anchor
    ``anchor[k]`` and ``n[k]`` windows.  The index is the windows' sorted order:
    the source of a window is the first place of its block that has it, or the
    second if it is the first itself.
    """
    of = np.repeat(np.arange(len(n)), n)
    order = np.lexsort((hashes, anchor[of]))
    a, h = anchor[of][order], hashes[order]
    new = np.flatnonzero(np.concatenate(([True], (a[1:] != a[:-1]) | (h[1:] != h[:-1]))))
    times = np.diff(np.append(new, len(a)))
    source = np.full(len(a), -1, dtype=np.int64)
    often = times > 1
    source[order] = np.where(np.repeat(often, times), np.repeat(order[new], times), -1)
    source[order[new[often]]] = order[new[often] + 1]
    repeated = source >= 0
    place = np.where(repeated, of[source], -1)
    # a factor runs on while the next window of this stretch is the next one of the source's stretch
    on = repeated[1:] & repeated[:-1] & (of[1:] == of[:-1]) & (source[1:] == source[:-1] + 1) & (place[1:] == place[:-1])
    first, last = np.flatnonzero(repeated & np.concatenate(([True], ~on))), np.flatnonzero(repeated & np.concatenate((~on, [True])))
    return first, last, source[first]


def _parse(block_rows: int):
    """Kernel over stretches sorted by anchor: factors, and the rows of blocks that are too large or marked as such."""

    def parse(rows: pa.Table):
        start = rows.column("start").to_numpy()
        hashes, n = _expand(rows.column("windows"))
        first, last, source = factors(rows.column("anchor").to_numpy(), hashes, n)
        if len(first):
            of, edge = np.repeat(np.arange(len(n)), n), np.cumsum(n) - n
            tk = rows.column("tk").combine_chunks()
            place = lambda p: (tk.take(pa.array(of[p])), (start[of[p]] + p - edge[of[p]]).astype(np.int32))
            yield batch_of(FACTOR, pa.nulls(len(first), pa.int64()), *place(first), (last - first + 1).astype(np.int32), pa.nulls(len(first), pa.binary()), *place(source))

    def hand_on(rows: pa.Table):
        for batch in rows.combine_chunks().to_batches():
            k = batch.num_rows
            yield batch_of(FACTOR, batch.column("anchor"), batch.column("tk"), batch.column("start"), pa.nulls(k, pa.int32()), batch.column("windows"), pa.nulls(k, pa.binary()), pa.nulls(k, pa.int32()))

    def settle(rows: pa.Table, dense_first: bool):
        anchor = rows.column("anchor").to_numpy()
        starts = np.flatnonzero(np.concatenate(([True], anchor[1:] != anchor[:-1])))
        sizes = np.diff(np.append(starts, len(anchor)))
        dense = sizes > block_rows
        if dense_first:
            dense[0] = True
        # equal windows of one stretch would put its anchor at two places: a stretch alone in its block repeats nothing
        of, single = np.repeat(dense, sizes), np.repeat((sizes == 1) & ~dense, sizes)
        if len(rest := rows.filter(pa.array(~of & ~single))):
            yield from parse(rest)
        if of.any():
            yield from hand_on(rows.filter(pa.array(of)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, known = None, None
        for batch in batches:
            heavy = batch.column("heavy")
            if heavy.true_count:
                yield from hand_on(pa.Table.from_batches([batch.filter(heavy)]))
                batch = batch.filter(pa.array(~heavy.to_numpy(zero_copy_only=False)))
            if not batch.num_rows:
                continue
            now = pa.Table.from_batches([batch])
            held = pa.concat_tables([held, now]).combine_chunks() if held is not None and len(held) else now
            anchor = held.column("anchor").to_numpy()
            last = int(np.searchsorted(anchor, anchor[-1]))
            if len(anchor) - last > block_rows:
                yield from settle(held, known == anchor[0])
                known, held = anchor[-1], None
            elif last:
                yield from settle(held.slice(0, last), known == anchor[0])
                known, held = None, held.slice(last)
        if held is not None and len(held):
            yield from settle(held, known == held.column("anchor")[0].as_py())

    return run


WINDOWS = pa.schema([("anchor", pa.int64()), ("tk", pa.binary()), ("start", pa.int32()), ("n", pa.int64()), ("h", pa.int64())])
WINDOWS_DDL = "anchor long, tk binary, start int, n long, h long"


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each window of (anchor, tk, start, n, windows)."""
    for batch in batches:
        if batch.num_rows:
            hashes, n = _expand(batch.column(4))
            row = pa.array(np.repeat(np.arange(len(n)), n))
            within = np.arange(len(hashes)) - np.repeat(np.cumsum(n) - n, n)
            start = batch.column(2).take(row).to_numpy() + within
            yield batch_of(WINDOWS, batch.column(0).take(row), batch.column(1).take(row), start.astype(np.int32), batch.column(3).take(row), hashes.view(np.int64))


def dense_spans(rows: DataFrame) -> DataFrame:
    """(tk, start, n, source, at) for stretches (anchor, tk, start, windows) of large blocks, without gathering a block.

    Equal texts, then equal stretches, are counted before anything is shuffled.
    A stretch that occurs twice is a factor as a whole; only the windows of
    stretches that occur once are looked up among all windows of the block.  The
    source is the least place that has the same, or the greatest for the least.
    """
    here = F.struct("tk", "start")
    from_one = lambda low, high: F.when(here == low, high).otherwise(low)
    each = durable(rows.groupBy("anchor", "windows", "tk", "start").agg(F.count("*").alias("copies")))
    kinds = each.groupBy("anchor", "windows").agg(F.sum("copies").alias("n"), F.min(here).alias("one"), F.max(here).alias("other"))
    kinds = durable(kinds.select("anchor", F.col("one.tk").alias("tk"), F.col("one.start").alias("start"), "n", "windows", "one", "other"))
    whole = each.join(kinds.where("n > 1").select("anchor", "windows", "one", "other"), ["anchor", "windows"])
    whole = whole.select("tk", "start", (F.octet_length("windows") / KEPT).cast("int").alias("n"), from_one(F.col("one"), F.col("other")).alias("s"))
    unpack = lambda k: k.select("anchor", "tk", "start", "n", "windows").mapInArrow(_unpack, WINDOWS_DDL)
    often = unpack(kinds).groupBy("anchor", "h").agg(F.sum("n").alias("times"), F.min(here).alias("one"), F.max(here).alias("other")).where("times > 1").drop("times")
    alone = unpack(kinds.where("n = 1")).join(often, ["anchor", "h"]).select("tk", "start", F.lit(1).alias("n"), from_one(F.col("one"), F.col("other")).alias("s"))
    return whole.unionByName(alone).select("tk", "start", "n", F.col("s.tk").alias("source"), F.col("s.start").alias("at"))


def heavy_anchors(docs: DataFrame, window: int, gram: int, text_col: str, sample: float = ROUTE_SAMPLE, share: float = ROUTE_SHARE) -> list[int]:
    """Anchors of more than ``share`` of the stretches of a random ``sample`` of the texts: 1 / share of them at most."""
    counts = durable(stretches(docs.where(F.rand(11) < sample), window, gram, text_col).groupBy("anchor").count())
    total = counts.agg(F.sum("count")).first()[0] or 0
    return [r.anchor for r in counts.where(F.col("count") > max(64, total * share)).collect()]


def repeated_spans(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, block_rows: int = 2000, text_col: str = "text") -> DataFrame:
    """(tk, start, n, source, at): runs of n windows from word ``start``, each of which also starts elsewhere.

    They are the factors of the parse; ``source`` is the key of a text that has
    the same n windows from word ``at``, another place or an equal text.
    """
    heavy = heavy_anchors(docs, window, gram, text_col)
    rows = stretches(docs, window, gram, text_col).withColumn("heavy", F.col("anchor").isin(heavy) if heavy else F.lit(False))
    salt = F.when(F.col("heavy"), F.xxhash64("tk", "start"))
    rows = rows.repartition("anchor", salt).sortWithinPartitions("anchor")
    parsed = durable(rows.mapInArrow(_parse(block_rows), FACTOR_DDL))
    found = parsed.where("windows is null").select("tk", "start", "n", "source", "at")
    dense = dense_spans(parsed.where("windows is not null").select("anchor", "tk", "start", "windows"))
    return found.unionByName(dense).dropDuplicates(["tk", "start", "n"])


def _digests(window: int):
    """Kernel over (tk, text, spans (at, n)): the digest of each span's words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for key, text, spans in zip(*(c.to_pylist() for c in batch.columns)):
                w = (text or "").encode().split()
                out += [(key, s["at"], s["n"], digest_of(w, s["at"], s["n"] + window - 1)) for s in spans]
            if out:
                yield batch_of(DIGEST, *map(list, zip(*out)))

    return run


def digest_of(words: list[bytes], start: int, n: int) -> bytes:
    return hashlib.md5(b" ".join(words[start : start + n])).digest()


def checked_spans(docs: DataFrame, spans: DataFrame, window: int = WINDOW, text_col: str = "text") -> DataFrame:
    """(tk, start, n, digest): the factors with the digest of their source's words, from the source's text."""
    spans = durable(spans)
    wanted = spans.select("source", "at", "n").distinct().groupBy("source").agg(F.collect_list(F.struct("at", "n")).alias("spans"))
    texts = docs.select(text_key(F.col(text_col)).alias("source"), F.col(text_col).alias("text"))
    sources = texts.join(wanted, "source").groupBy("source").agg(F.first("text").alias("text"), F.first("spans").alias("spans"))
    digests = sources.mapInArrow(_digests(window), "source binary, at int, n int, digest binary")
    return spans.join(digests, ["source", "at", "n"]).select("tk", "start", "n", "digest")


def _cut(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for key, text, spans in zip(*(c.to_pylist() for c in batch.columns)):
                w = (text or "").encode().split()
                if spans:
                    edge = np.zeros(len(w) + 1, dtype=np.int32)
                    for s in spans:
                        if digest_of(w, s["start"], s["n"] + window - 1) == s["digest"]:
                            edge[s["start"]] += 1
                            edge[s["start"] + s["n"] + window - 1] -= 1
                    keep = np.flatnonzero(np.cumsum(edge[:-1]) == 0).tolist()
                    out.append((key, len(w), len(w) - len(keep), hashlib.sha256(b" ".join([w[i] for i in keep])).hexdigest()))
                else:
                    out.append((key, len(w), 0, hashlib.sha256(b" ".join(w)).hexdigest()))
            if out:
                yield batch_of(RESULT, *map(list, zip(*out)))

    return run


def remove_repeats(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, block_rows: int = 2000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256), one row per input row.

    Words covered by a window that also starts elsewhere, in the same text
    included, go; so do both of two equal texts that are long enough.  Null and
    empty texts have no words and keep the digest of nothing; null or repeated
    ids keep their rows.
    """
    spans = checked_spans(docs, repeated_spans(docs, window, gram, block_rows, text_col), window, text_col)
    spans = spans.groupBy("tk").agg(F.collect_list(F.struct("start", "n", "digest")).alias("spans"))
    keyed = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), text_key(F.col(text_col)).alias("tk"))
    return keyed.join(spans, "tk", "left").select("doc_id", "text", "spans").mapInArrow(_cut(window), RESULT_DDL)
