"""Benchmark decontamination with a distributed positional inverted index.

The index is partitioned by document: a row of it is a block of documents with,
for each term, the sorted list of its positions in the block's token stream.
Documents stand further apart in that stream than any phrase is long.  A query
phrase starts from the list of its rarest term in the block, shifted by the
term's offset, and intersects it with the shifted lists of the other terms,
rarest first; what is left are the exact occurrences.  Nothing is shuffled, so
no term or document is too frequent, and test phrases reach the blocks in
pieces of bounded size.
"""

from __future__ import annotations

import hashlib
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, durable, unused

WINDOW = 13
#: Lower-cased ASCII letters, digits and all bytes of non-ASCII letters are kept; the rest separates words.
FOLD = bytes((b + 32 if 65 <= b <= 90 else b) if 48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
INDEX = pa.schema([("doc_ids", pa.list_(pa.int64())), ("starts", pa.list_(pa.int32())), ("n_words", pa.list_(pa.int32())), ("terms", pa.list_(pa.binary())), ("ends", pa.list_(pa.int32())), ("postings", pa.binary())])
INDEX_DDL = "doc_ids array<bigint>, starts array<int>, n_words array<int>, terms array<binary>, ends array<int>, postings binary"
RESULT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_())])
RESULT_DDL = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"
MATCH = pa.schema([("doc_id", pa.int64()), ("phrase", pa.int64()), ("start", pa.int64()), ("end", pa.int64())])
MATCH_DDL = "doc_id long, phrase long, start long, end long"


def words(text: str | None) -> list[bytes]:
    """The words of a text, lower-cased in A-Z, as UTF-8."""
    return (text or "").encode().translate(FOLD).split()


def index_rows(rows: Iterable[tuple[object, str | None]], wanted: frozenset[bytes] | None, gap: int, block_words: int) -> Iterator[dict]:
    """Rows of the index over (id, text) pairs."""
    ids, starts, counts, lists, at = [], [], [], defaultdict(list), 0

    def pack() -> dict:
        order = sorted(lists)
        flat = np.concatenate([np.asarray(lists[t], dtype=np.int32) for t in order]) if order else np.empty(0, dtype=np.int32)
        return {"doc_ids": ids, "starts": starts, "n_words": counts, "terms": order, "ends": np.cumsum([len(lists[t]) for t in order], dtype=np.int32).tolist(), "postings": flat.tobytes()}

    for key, text in rows:
        found = words(text)
        ids.append(key)
        starts.append(at)
        counts.append(len(found))
        if wanted is None:
            for i, w in enumerate(found, at):
                lists[w].append(i)
        else:
            for i, w in enumerate(found, at):
                if w in wanted:
                    lists[w].append(i)
        at += len(found) + gap
        if at >= block_words:
            yield pack()
            ids, starts, counts, lists, at = [], [], [], defaultdict(list), 0
    if ids:
        yield pack()


def build_index(docs: DataFrame, terms: Iterable[bytes] | None = None, gap: int = WINDOW, block_words: int = 2_000_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The index of all whole texts, one row per block of about ``block_words`` words.

    terms: index these only (default all); positions and word counts are of all
    words.  gap: no phrase may be longer.  A null text has no words; a null or
    repeated id keeps its own row; a document is never divided between blocks.
    """
    wanted = None if terms is None else frozenset(terms)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = ((k, t) for batch in batches for k, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))
        for row in index_rows(rows, wanted, gap, block_words):
            yield batch_of(INDEX, *([row[f.name]] for f in INDEX))

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, INDEX_DDL)


class Block:
    """One row of the index, for lookups."""

    def __init__(self, row: dict):
        self.ids, self.starts, self.n_words = row["doc_ids"], np.array(row["starts"], dtype=np.int64), np.array(row["n_words"], dtype=np.int64)
        flat, ends = np.frombuffer(row["postings"], dtype=np.int32), row["ends"]
        self.lists = {t: flat[a:b] for t, a, b in zip(row["terms"], [0, *ends[:-1]], ends)}
        self.size = int(self.starts[-1] + self.n_words[-1]) if len(self.starts) else 0

    def phrase(self, terms: tuple[bytes, ...]) -> np.ndarray:
        """Positions where the terms stand in sequence."""
        lists = [(self.lists.get(t), k) for k, t in enumerate(terms)]
        if any(x is None for x, _ in lists):
            return np.empty(0, dtype=np.int64)
        lists.sort(key=lambda x: len(x[0]))
        at = lists[0][0].astype(np.int64) - lists[0][1]
        for found, k in lists[1:]:
            if not len(at):
                break
            i = np.searchsorted(found, at + k)
            at = at[(i < len(found)) & (found[np.minimum(i, len(found) - 1)] == at + k)]
        return at

    def near(self, terms: tuple[bytes, ...], slop: int) -> list[tuple[int, int]]:
        """Least spans (start, end) of at most ``slop`` words that hold each term as often as ``terms`` names it.

        A span is least if no span within it will do.  The search starts from the
        term with the shortest list: only what stands near one of its places counts.
        """
        need = Counter(terms)
        lists = sorted(((self.lists.get(t, np.empty(0, dtype=np.int32)), k) for t, k in need.items()), key=lambda x: len(x[0]))
        if not lists or any(len(x) < k for x, k in lists):
            return []
        rare, near = lists[0][0], []
        for x, _ in lists:
            i = np.searchsorted(rare, x - slop + 1)
            near.append(x[(i < len(rare)) & (rare[np.minimum(i, len(rare) - 1)] < x + slop)])
        at = np.concatenate(near)
        order = np.argsort(at, kind="stable")
        at, which = at[order].tolist(), np.repeat(np.arange(len(near)), [len(x) for x in near])[order].tolist()
        have, missing, left, out = [0] * len(lists), len(terms), 0, []
        for end, w in zip(at, which):
            have[w] += 1
            missing -= have[w] <= lists[w][1]
            while not missing:
                v = which[left]
                if have[v] == lists[v][1]:
                    if end + 1 - at[left] <= slop:
                        out.append((at[left], end + 1))
                    missing += 1
                have[v] -= 1
                left += 1
        return out

    def check_gap(self, words: int) -> None:
        """Raises if a match of so many words could reach from one document into the next."""
        if len(self.starts) > 1 and int((self.starts[1:] - self.starts[:-1] - self.n_words[:-1]).min()) < words - 1:
            raise ValueError(f"the index's gap is too small for matches of {words} words")

    def owner(self, at: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.starts, at, side="right") - 1


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[Block]:
    for batch in batches:
        for k in range(batch.num_rows):
            yield Block(batch.slice(k, 1).to_pylist()[0])


def phrase_matches(index: DataFrame, phrases: dict[int, tuple[bytes, ...]]) -> DataFrame:
    """(doc_id, phrase, start, end): every exact occurrence, in words from the document's start."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in _rows(batches):
            block.check_gap(max(map(len, phrases.values()), default=0))
            for key, terms in phrases.items():
                if len(at := block.phrase(terms) if terms else []):
                    of = block.owner(at)
                    yield batch_of(MATCH, [block.ids[i] for i in of], [key] * len(at), at - block.starts[of], at - block.starts[of] + len(terms))

    return index.mapInArrow(run, MATCH_DDL)


def proximity_matches(index: DataFrame, phrases: dict[int, tuple[bytes, ...]], slop: int) -> DataFrame:
    """(doc_id, phrase, start, end): spans of at most ``slop`` words that hold all the phrase's terms in any order.

    A term that the phrase repeats must be there as often.  An index whose gap
    is less than ``slop`` - 1 raises.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in _rows(batches):
            block.check_gap(slop)
            for key, terms in phrases.items():
                for a, b in block.near(terms, slop):
                    of = int(block.owner(np.array([a]))[0])
                    yield batch_of(MATCH, [block.ids[of]], [key], [a - int(block.starts[of])], [b - int(block.starts[of])])

    return index.mapInArrow(run, MATCH_DDL)


def windows_of(items: Iterable[tuple[object, str | None]], window: int = WINDOW) -> dict[tuple[bytes, ...], list[str]]:
    """Each distinct window with the ids of its items; an item of fewer words, but not none, is one window."""
    found: dict[tuple[bytes, ...], list[str]] = {}
    for item, text in items:
        if item is None:
            continue
        w = words(text)
        for i in range(max(1, len(w) - window + 1) if w else 0):
            found.setdefault(tuple(w[i : i + window]), []).append(str(item))
    return found


def _judge(windows: dict[tuple[bytes, ...], list[str]]):
    """The judge of a block's words, for these windows."""
    vocabulary = sorted({t for w in windows for t in w})
    number = {t: i for i, t in enumerate(vocabulary)}
    keys = list(windows)
    width = max(map(len, keys), default=1)
    table = np.full((len(keys), width), len(vocabulary), dtype=np.int64)
    for i, w in enumerate(keys):
        table[i, : len(w)] = [number[t] for t in w]

    def judge(block: Block) -> tuple[np.ndarray, dict[int, set[str]]]:
        """(whether each place of the block's stream is hit, items by document)."""
        present = np.array([t in block.lists for t in vocabulary] + [True])
        edge = np.zeros(block.size + 1, dtype=np.int32)
        items: dict[int, set[str]] = defaultdict(set)
        for i in np.flatnonzero(present[table].all(axis=1)) if len(keys) else []:
            if len(at := block.phrase(keys[i])):
                edge[at] += 1
                np.subtract.at(edge, at + len(keys[i]), 1)
                for d in np.unique(block.owner(at)).tolist():
                    items[d].update(windows[keys[i]])
        return np.cumsum(edge[:-1]) > 0, items

    return judge


def _hits(block: Block, hit: np.ndarray) -> np.ndarray:
    """Number of hit words of each document of a block."""
    sums = np.concatenate(([0], np.cumsum(hit)))
    return sums[block.starts + block.n_words] - sums[block.starts]


def _verdicts(ids, n_words: np.ndarray, n_hit: np.ndarray, names: list[list[str]]) -> pa.RecordBatch:
    return batch_of(RESULT, ids, n_words, n_hit, [len(x) for x in names], [hashlib.sha256(",".join(x).encode()).hexdigest() for x in names], _is_contaminated(n_hit, n_words))


def _is_contaminated(n_hit: np.ndarray, n_words: np.ndarray) -> np.ndarray:
    return (n_hit > 0) & (20 * n_hit >= n_words)


def _small_test_set(benchmark: DataFrame, window: int, max_windows: int, item_col: str, item_text_col: str) -> dict[tuple[bytes, ...], list[str]] | None:
    """The windows of a test set of at most 64 * max_windows bytes; None for a larger one, of which nothing is fetched."""
    items = benchmark.select(F.col(item_col), F.col(item_text_col).alias("text"))
    if (items.agg(F.sum(F.octet_length("text"))).first()[0] or 0) > 64 * max_windows:
        return None
    return windows_of(((r[0], r[1]) for r in items.collect()), window)


def _pieces(benchmark: DataFrame, window: int, max_windows: int, item_col: str, item_text_col: str) -> Iterator[dict[tuple[bytes, ...], list[str]]]:
    """The windows of a test set of any size, about ``max_windows`` (window, item) pairs at a time."""
    schema = pa.schema([("terms", pa.binary()), ("item", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for item, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                found = list(windows_of([(item, text)], window))
                for at in range(0, len(found), 100_000):
                    part = found[at : at + 100_000]
                    yield batch_of(schema, [b" ".join(w) for w in part], [str(item)] * len(part))

    items = benchmark.select(F.col(item_col), F.col(item_text_col).alias("text"))
    pairs = durable(items.mapInArrow(run, "terms binary, item string").distinct())
    n = max(1, -(-pairs.count() // max_windows))
    for k in range(n):
        out: dict[tuple[bytes, ...], list[str]] = {}
        for r in pairs.where(F.pmod(F.xxhash64("terms", "item"), F.lit(n)) == k).collect():
            out.setdefault(tuple(bytes(r.terms).split(b" ")), []).append(r.item)
        yield out


HIT = pa.schema([("block", pa.int64()), ("pos", pa.int32()), ("starts", pa.list_(pa.int32())), ("ends", pa.list_(pa.int32())), ("items", pa.list_(pa.string()))])
HIT_DDL = "block long, pos int, starts array<int>, ends array<int>, items array<string>"


def _piece_hits(index: DataFrame, windows: dict[tuple[bytes, ...], list[str]]) -> DataFrame:
    """(block, pos, starts, ends, items) of the documents that hold windows of one piece of a test set."""
    judge = _judge(windows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for number, block in zip(batch.column("block").to_pylist(), _rows(iter([batch]))):
                hit, items = judge(block)
                edge = np.diff(np.concatenate(([0], hit.astype(np.int8), [0])))
                begin, end = np.flatnonzero(edge > 0), np.flatnonzero(edge < 0)
                of = block.owner(begin) if len(begin) else begin
                for d, names in sorted(items.items()):
                    mine = of == d
                    yield batch_of(HIT, [number], [d], [(begin[mine] - block.starts[d]).tolist()], [(end[mine] - block.starts[d]).tolist()], [sorted(names)])

    return index.mapInArrow(run, HIT_DDL)


def _merge_hits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Results of (doc_id, n_words, starts, ends, items): the hits of all pieces, each word counted once."""
    for batch in batches:
        if batch.num_rows:
            ids, n_words, starts, ends, items = (c.to_pylist() for c in batch.columns)
            n_hit = []
            for n, s, e in zip(n_words, starts, ends):
                edge = np.zeros(n + 1, dtype=np.int64)
                np.add.at(edge, np.array(s or [], dtype=np.int64), 1)
                np.subtract.at(edge, np.array(e or [], dtype=np.int64), 1)
                n_hit.append(int((np.cumsum(edge[:-1]) > 0).sum()))
            yield _verdicts(ids, np.array(n_words, dtype=np.int64), np.array(n_hit, dtype=np.int64), [sorted(set(x or ())) for x in items])


def _in_pieces(docs: DataFrame, pieces: Iterator[dict], window: int, id_col: str, text_col: str) -> DataFrame:
    index = durable(build_index(docs, None, window, id_col=id_col, text_col=text_col).withColumn("block", F.monotonically_increasing_id()))
    found = None
    for windows in pieces:
        hits = durable(_piece_hits(index, windows))
        found = hits if found is None else found.unionByName(hits)
    gathered = [F.flatten(F.collect_list(c)).alias(c) for c in ("starts", "ends", "items")]
    rows = index.select("block", F.posexplode(F.arrays_zip("doc_ids", "n_words")).alias("pos", "d"))
    rows = rows.join(found.groupBy("block", "pos").agg(*gathered), ["block", "pos"], "left")
    return rows.select(F.col("d.doc_ids"), F.col("d.n_words"), "starts", "ends", "items").mapInArrow(_merge_hits, RESULT_DDL)


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, max_windows: int = 200_000, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """One row per document: (doc_id, n_words, n_hit, n_items, items_sha256, contaminated).

    A word inside any occurrence of a benchmark window is hit; a document is
    contaminated if at least one word and at least one in twenty are.  Null
    texts have no words, items with a null id are ignored, repeated rows count
    once as items and keep their rows as documents.  The test set is the stated
    query set and goes to every task, so its size is checked first: one of more
    than 64 * ``max_windows`` bytes meets the index in pieces of about
    ``max_windows`` windows, and the hits of all pieces are merged by word.
    """
    windows = _small_test_set(benchmark, window, max_windows, item_col, item_text_col)
    if windows is None:
        return _in_pieces(docs, _pieces(benchmark, window, max_windows, item_col, item_text_col), window, id_col, text_col)
    index = build_index(docs, {t for w in windows for t in w}, window, id_col=id_col, text_col=text_col)
    judge = _judge(windows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in _rows(batches):
            hit, items = judge(block)
            yield _verdicts(block.ids, block.n_words, _hits(block, hit), [sorted(items.get(d, ())) for d in range(len(block.ids))])

    return durable(index).mapInArrow(run, RESULT_DDL)


def keep_clean(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, max_windows: int = 200_000, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", block_words: int = 500_000) -> DataFrame:
    """``docs`` without the contaminated rows, by the rule of :func:`contamination`; other rows and all columns are unchanged.

    The blocks of the index are made of the rows as they pass and dropped again;
    for a test set that takes several pieces the rows are numbered and judged first.
    """
    windows = _small_test_set(benchmark, window, max_windows, item_col, item_text_col)
    if windows is None:
        row = unused("row", docs)
        numbered = durable(docs.withColumn(row, F.monotonically_increasing_id()))
        judged = _in_pieces(numbered, _pieces(benchmark, window, max_windows, item_col, item_text_col), window, row, text_col)
        return numbered.join(judged.where("contaminated").select(F.col("doc_id").alias(row)), row, "left_anti").select(*[f"`{c}`" for c in docs.columns])
    terms, judge = frozenset(t for w in windows for t in w), _judge(windows)

    @F.pandas_udf("boolean")
    def fine(texts):
        import pandas as pd

        out = []
        for row in index_rows(((None, t) for t in texts), terms, window, block_words):
            block = Block(row)
            out.append(~_is_contaminated(_hits(block, judge(block)[0]), block.n_words))
        return pd.Series(np.concatenate(out) if out else np.empty(0, dtype=bool))

    return docs.where(fine(F.col(text_col)))
