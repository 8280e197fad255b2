"""Byte-level BPE without regular expressions: vectorised pre-tokenisation, cached pair merging, decoding by offsets.

Pre-tokenisation.  Code points become symbols of a small alphabet (a table of
code-point classes, refined by a look at the next characters), and a finite
automaton over these symbols says where a piece starts.  Its runs over a long
text are found by an associative scan: the text is cut into columns, the
transition functions within each column are composed for all columns at once,
the columns' functions are composed in turn, recursively, and give the state in
which each column begins.

Pieces: a space and letters, digits or other characters; the English
contractions; white space, whose last character stays with what follows.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Rolling, batch_of, chunks, portions, unused

# The white space of Unicode, and the contractions that are pieces of their own.
WHITE_SPACE = [9, 10, 11, 12, 13, 32, 133, 160, 5760, *range(8192, 8203), 8232, 8233, 8239, 8287, 12288]
CONTRACTIONS = ["'s", "'t", "'re", "'ve", "'m", "'ll", "'d"]

LETTER, NUMBER, OTHER, SPACE = range(4)
#: Symbols: letter, number, other, apostrophe before one or two letters of a contraction, plain space before a
#: non-space, white space before white space or the end, other white space before a non-space, end of a text.
SYMBOLS = L, N, O, Q1, Q2, P, W, X, Z = range(9)
#: States: nothing open, in letters, in numbers, in others, after a plain space, in white space, one or two letters
#: of a contraction to come.
STATES = NONE, IN_L, IN_N, IN_O, IN_P, IN_W, TO_1, TO_2 = range(8)


def _automaton() -> tuple[np.ndarray, np.ndarray]:
    """(next state, whether a piece starts) by symbol and state."""
    step = np.zeros((len(SYMBOLS), len(STATES)), dtype=np.uint8)
    begins = np.ones((len(SYMBOLS), len(STATES)), dtype=bool)
    for symbol, own in ((L, IN_L), (N, IN_N), (O, IN_O), (Q1, IN_O), (Q2, IN_O)):
        step[symbol] = own
        begins[symbol, [own, IN_P]] = False
    for symbol, after in ((Q1, TO_1), (Q2, TO_2)):
        opens = [s for s in STATES if s not in (IN_O, IN_P)]
        step[symbol, opens] = after
    step[L, TO_1], step[L, TO_2] = NONE, TO_1
    begins[L, [TO_1, TO_2]] = False
    step[P], step[W], step[X], step[Z] = IN_P, IN_W, NONE, NONE
    begins[W, IN_W] = False
    begins[Z] = False
    return step, begins


STEP, BEGINS = _automaton()
#: No id: beyond a piece's end, and for a pair that doesn't merge; an empty place of the table of pairs.
PAD, NO_PAIR = np.uint32((1 << 31) - 1), np.uint32((1 << 32) - 1)
EMPTY = np.uint64((1 << 64) - 1)


@lru_cache(1)
def classes() -> np.ndarray:
    """Class of each code point."""
    by = {"L": LETTER, "N": NUMBER}
    table = np.array([by.get(unicodedata.category(chr(c))[0], OTHER) for c in range(0x110000)], dtype=np.uint8)
    table[WHITE_SPACE] = SPACE
    return table


def scan(symbols: np.ndarray, step: np.ndarray = STEP, start: int = NONE, width: int = 128) -> np.ndarray:
    """State before each symbol: the prefix composition of the symbols' transition functions."""
    n = len(symbols)
    if n <= width:
        out = np.empty(n, dtype=np.uint8)
        state = start
        for i, s in enumerate(symbols.tolist()):
            out[i] = state
            state = step[s, state]
        return out
    columns = -(-n // width)
    grid = np.full(columns * width, len(step), dtype=np.uint8)  # the last symbol is the identity
    grid[:n] = symbols
    grid = np.ascontiguousarray(grid.reshape(columns, width).T)
    states = step.shape[1]
    flat = np.vstack([step, np.arange(states, dtype=np.uint8)]).ravel()
    row = grid.astype(np.int32) * states
    held = np.tile(np.arange(states, dtype=np.uint8), (columns, 1))
    for i in range(width):
        held = flat[row[i][:, None] + held]
        if not i % 8 and (held == held[:, :1]).all():  # every column's function is constant from here on
            one = held[:, 0].copy()
            for k in range(i + 1, width):
                one = flat[row[k] + one]
            held = np.broadcast_to(one[:, None], held.shape)
            break
    unique, names = np.unique(held, axis=0, return_inverse=True)
    if len(unique) <= 255:
        begin = scan(names.astype(np.uint8).ravel(), np.ascontiguousarray(unique), start, width)
    else:
        begin, state = np.empty(columns, dtype=np.uint8), start
        for i, function in enumerate(held):
            begin[i] = state
            state = function[state]
    out = np.empty((width, columns), dtype=np.uint8)
    now = begin
    for i in range(width):
        out[i] = now
        now = flat[row[i] + now]
    return out.T.ravel()[:n]


def piece_starts(points: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Whether a piece starts at each code point of concatenated texts; each text has one code point after it, at ``ends``."""
    kind = classes()[points]
    space = kind == SPACE
    kind[ends] = SPACE
    after = np.append(kind[1:] == SPACE, True)  # white space, or the end, comes next
    symbol = kind.copy()
    symbol[space] = np.where(after[space], W, np.where(points[space] == 32, P, X))
    at = np.flatnonzero(points == 39)
    if len(at):
        padded = np.append(points, [0, 0])
        one, two = padded[at + 1], padded[at + 2]
        for word in CONTRACTIONS:
            fits = one == ord(word[1])
            if len(word) == 3:
                fits &= two == ord(word[2])
            symbol[at[fits]] = Q1 if len(word) == 2 else Q2
    symbol[ends] = Z
    return BEGINS[symbol, scan(symbol)]


class Codec:
    """Encoder and decoder for a table of byte strings and their ranks."""

    def __init__(self, ranks: dict[bytes, int], cached: int = 100_000):
        self.ranks, self.cached, self.cache, self.older = ranks, cached, {}, {}
        self.rolling = Rolling(0xA24BAED4963EE407)
        self.single = np.array([ranks.get(bytes([b]), PAD) for b in range(256)], dtype=np.uint32)
        self.table, self.shift = None, 0
        self.vocabulary = {i: b for b, i in ranks.items()}

    @classmethod
    def from_file(cls, path: str) -> Codec:
        with open(path, "rb") as f:
            return cls({base64.b64decode(a): int(b) for a, b in map(bytes.split, f)})

    def merge(self, piece: bytes) -> list[int]:
        """Ids of one piece: the pair of lowest rank, leftmost first, is merged again and again."""
        if (whole := self.ranks.get(piece)) is not None:
            return [whole]
        n, ranks = len(piece), self.ranks
        after, before, live = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n
        ends = list(range(1, n + 1))
        heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(piece[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, end = heapq.heappop(heap)
            j = after[i] if live[i] else n
            if not live[i] or j >= n or ends[j] != end:
                continue
            live[j], ends[i], after[i] = False, end, after[j]
            if after[i] < n:
                before[after[i]] = i
                if (r := ranks.get(piece[i : ends[after[i]]])) is not None:
                    heapq.heappush(heap, (r, i, ends[after[i]]))
            if (p := before[i]) >= 0 and (r := ranks.get(piece[p:end])) is not None:
                heapq.heappush(heap, (r, p, end))
        out, i = [], 0
        while i < n:
            out.append(ranks[piece[i : ends[i]]])
            i = after[i]
        return out

    def _pairs(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The id that two neighbouring ids merge to, or NO_PAIR."""
        if self.table is None:
            self._fill()
        key = left.astype(np.uint64) << np.uint64(32) | right.astype(np.uint64)
        out = np.full(key.shape, NO_PAIR, dtype=np.uint32)
        slot = (key * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(self.shift)).astype(np.int64)
        keys, ids = self.table
        open_ = np.arange(key.size)
        key, slot, flat = key.ravel(), slot.ravel(), out.ravel()
        while len(open_):
            there = keys[slot]
            hit = there == key
            flat[open_[hit]] = ids[slot[hit]]
            go = ~hit & (there != EMPTY)
            open_, key, slot = open_[go], key[go], slot[go] + 1
        return flat.reshape(out.shape)

    def _fill(self) -> None:
        """An open-addressed table of all pairs of ids whose bytes together have a rank."""
        ranks, pairs = self.ranks, []
        for piece, i in ranks.items():
            for k in range(1, len(piece)):
                if (a := ranks.get(piece[:k])) is not None and (b := ranks.get(piece[k:])) is not None:
                    pairs.append((a << 32 | b, i))
        key = np.array([p for p, _ in pairs], dtype=np.uint64)
        value = np.array([i for _, i in pairs], dtype=np.uint32)
        bits = max(4, int(4 * len(pairs) + 1).bit_length())
        self.shift = 64 - bits
        keys, ids = np.full((1 << bits) + len(pairs) + 1, EMPTY), np.zeros((1 << bits) + len(pairs) + 1, dtype=np.uint32)
        slot = (key * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(self.shift)).astype(np.int64)
        while len(key):
            free = keys[slot] == EMPTY
            _, one = np.unique(slot[free], return_index=True)
            now = np.flatnonzero(free)[one]
            keys[slot[now]], ids[slot[now]] = key[now], value[now]
            rest = np.ones(len(key), dtype=bool)
            rest[now] = False
            key, value, slot = key[rest], value[rest], slot[rest]
            slot = slot + (keys[slot] != EMPTY)
        self.table = keys, ids

    def merge_many(self, pieces: list[bytes]) -> list[tuple[int, ...]]:
        """Ids of many pieces; short ones are merged together, one pair of each at a time."""
        out: list = [None] * len(pieces)
        size = np.array([len(p) for p in pieces])
        for low, high in ((0, 8), (8, 16), (16, 32)):
            of = np.flatnonzero((size > low) & (size <= high))
            if not len(of):
                continue
            grid = np.frombuffer(b"".join([pieces[i].ljust(high, b"\0") for i in of.tolist()]), dtype=np.uint8).reshape(-1, high)
            column = np.arange(high)
            ids = np.where(column < size[of][:, None], self.single[grid], PAD)
            pair = self._pairs(ids[:, :-1], ids[:, 1:])
            while len(of):
                at = pair.argmin(axis=1)
                rows = np.arange(len(of))
                best = pair[rows, at]
                done = best == NO_PAIR
                if done.any():
                    for i, row in zip(of[done].tolist(), ids[done].tolist()):
                        out[i] = tuple(x for x in row if x != PAD)
                    of, ids, pair, at, best = of[~done], ids[~done], pair[~done], at[~done], best[~done]
                    rows = np.arange(len(of))
                    if not len(of):
                        break
                moved = np.append(ids, np.full((len(of), 1), PAD, dtype=ids.dtype), axis=1)
                ids = np.where(column <= at[:, None], moved[:, :-1], moved[:, 1:])
                ids[rows, at] = best
                moved = np.append(pair, np.full((len(of), 1), NO_PAIR, dtype=pair.dtype), axis=1)
                pair = np.where(column[:-1] < at[:, None], moved[:, :-1], moved[:, 1:])
                wide = np.append(ids, np.full((len(of), 1), PAD, dtype=ids.dtype), axis=1)
                inside = at < high - 1
                pair[rows[inside], at[inside]] = self._pairs(wide[rows, at], wide[rows, at + 1])[inside]
                back = at > 0
                pair[rows[back], at[back] - 1] = self._pairs(wide[rows[back], at[back] - 1], wide[rows[back], at[back]])
        for i in np.flatnonzero(size > 32).tolist():
            out[i] = tuple(self.merge(pieces[i]))
        return out

    def _ids(self, pieces: list[bytes]) -> list[tuple[int, ...]]:
        """Ids of pieces, from the cache of recent ones where they are there."""
        found = [self.cache.get(p) or self.older.get(p) for p in pieces]
        new = [i for i, x in enumerate(found) if x is None]
        for i, ids in zip(new, self.merge_many([pieces[i] for i in new])):
            found[i] = ids
            if len(pieces[i]) <= 64:
                if len(self.cache) >= self.cached:
                    self.cache, self.older = {}, self.cache
                self.cache[pieces[i]] = ids
        return found

    def encode_batch(self, texts: list[str | None]) -> Iterator[np.ndarray]:
        """Ids of each text, as unsigned 32-bit integers."""
        for low, high in chunks(texts, 1 << 18):
            part = [t or "" for t in texts[low:high]]
            joined = "\n".join([*part, ""])
            points = np.frombuffer(joined.encode("utf-32-le"), dtype=np.uint32)
            ends = np.cumsum([len(t) + 1 for t in part]) - 1
            starts = np.flatnonzero(piece_starts(points, ends))
            raw = joined.encode()
            width = 1 + (points > 0x7F) + (points > 0x7FF) + (points > 0xFFFF)
            offset = np.concatenate(([0], np.cumsum(width)))
            # a piece ends where the next one starts, or at its text's end
            first = np.searchsorted(starts, np.concatenate(([0], ends + 1)))
            begin, end = offset[starts], np.append(offset[starts[1:]], 0)
            filled = first[1:] > first[:-1]
            end[first[1:][filled] - 1] = offset[ends][filled]
            unique, name = self._distinct(raw, begin, end)
            found = self._ids([raw[a:b] for a, b in zip(begin[unique].tolist(), end[unique].tolist())])
            size = np.array([len(x) for x in found], dtype=np.int64)
            flat = np.array([i for x in found for i in x], dtype="<u4")
            n = size[name]
            before = np.concatenate(([0], np.cumsum(n)))
            place = np.arange(before[-1]) + np.repeat((np.cumsum(size) - size)[name] - before[:-1], n)
            ids = flat[place]
            for a, b in zip(before[first[:-1]].tolist(), before[first[1:]].tolist()):
                yield ids[a:b]

    def _distinct(self, raw: bytes, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(one place of each distinct slice, the number of each slice's), by hash and verified."""
        data = np.frombuffer(raw, dtype=np.uint8)
        hashes = self.rolling.ranges(self.rolling.prefix(data.astype(np.uint64) + np.uint64(1)), begin, end)
        _, unique, name = np.unique(hashes, return_index=True, return_inverse=True)
        size, one = end - begin, unique[name]
        if (size == size[one]).all():
            shift = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            if (data[np.repeat(begin, size) + shift] == data[np.repeat(begin[one], size) + shift]).all():
                return unique, name
        return np.arange(len(begin)), np.arange(len(begin))

    def encode(self, text: str | None) -> np.ndarray:
        return next(self.encode_batch([text]), np.empty(0, dtype="<u4"))

    def decode(self, ids) -> bytes:
        return b"".join([self.vocabulary[i] for i in np.asarray(ids).tolist()])

    def offsets(self, ids) -> np.ndarray:
        """Byte range starts of the ids, and the end: decode(ids)[offsets[i]:offsets[i + 1]] is the i-th id's."""
        return np.concatenate(([0], np.cumsum([len(self.vocabulary[i]) for i in np.asarray(ids).tolist()], dtype=np.int64)))


@lru_cache(4)
def codec(path: str) -> Codec:
    """The codec of a rank file, once a process."""
    return Codec.from_file(path)


def encode(docs: DataFrame, path: str, text_col: str = "text", ids_col: str = "ids", offsets_col: str = "offsets") -> DataFrame:
    """``docs`` with the ids of each whole text and their byte offsets; null and empty texts have none.  Columns of these names are replaced."""

    @F.pandas_udf("struct<ids: array<int>, offsets: array<long>>")
    def run(texts):
        import pandas as pd

        c = codec(path)
        ids = list(c.encode_batch(texts.tolist()))
        return pd.DataFrame({"ids": [x.astype(np.int32) for x in ids], "offsets": [c.offsets(x) for x in ids]})

    done = unused("_encoded", docs, ids_col, offsets_col)
    out = docs.withColumn(done, run(F.coalesce(F.col(text_col), F.lit(""))))
    return out.withColumn(ids_col, F.col(f"{done}.ids")).withColumn(offsets_col, F.col(f"{done}.offsets")).drop(done)


def decode(encoded: DataFrame, path: str, ids_col: str = "ids", bytes_col: str = "decoded") -> DataFrame:
    """``encoded`` with the bytes of its ids; null ids are an empty list."""

    @F.pandas_udf("binary")
    def run(ids):
        import pandas as pd

        c = codec(path)
        return pd.Series([c.decode(x) for x in ids])

    return encoded.withColumn(bytes_col, run(F.coalesce(F.col(ids_col), F.array().cast("array<int>"))))


RESULT = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])
RESULT_DDL = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of every row: its whole text encoded, and the ids decoded again.

    Null texts are empty and have no tokens; null or repeated ids keep their rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            n, ids_of, bytes_of = [], [], []
            for texts in portions(batch.column(1)):
                for ids in c.encode_batch(texts):
                    n.append(len(ids))
                    ids_of.append(hashlib.sha256(ids.tobytes()).hexdigest())
                    bytes_of.append(hashlib.sha256(c.decode(ids)).hexdigest())
            if n:
                yield batch_of(RESULT, batch.column(0), n, ids_of, bytes_of)

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, RESULT_DDL)
