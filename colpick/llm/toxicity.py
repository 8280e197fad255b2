"""Toxicity by a gap-tolerant subsequence string kernel and a support vector machine over Nystroem landmarks.

Kernel.  k(s, t) sums, over all pairs of equal subsequences of ``P`` characters
of s and t, DECAY to the number of characters skipped in both.  Landmarks are
short strings taken from the labelled texts; a text is represented by its
strongest match k(w, l) / k(l, l) with each landmark over all its words w.
Inserted or left out characters lower a match but don't destroy it.  Two kernels
are made of the matches, by how far they exceed either of two levels, and both
rows of the kernel matrix go through the landmarks' Nystroem map.

Training.  A label is of a whole text.  All sentences of a clean text are clean;
of a toxic text one at least is toxic, and the machine is trained again with the
one that it scores highest as its witness.

Words are lower-cased runs of non-space bytes without ASCII punctuation; letters
set apart by single spaces are joined.  They are read between a mark for their
beginning and one for their end, and in overlapping pieces if longer than SPAN.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, portions

P, DECAY, SPAN = 3, 0.5, 16
#: Matches below LEVELS[0] count as none; those above LEVELS[1] count again.
LEVELS = (0.45, 0.8)
PUNCTUATION = bytes(b for b in range(33, 128) if not chr(b).isalnum()) + b"\x7f"
SPACED = re.compile(rb"(?<!\S)(?:[a-z] ){3,}[a-z](?!\S)")
RESULT = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())])


def words(text: str | None) -> set[bytes]:
    """The distinct words of a text between ^ and $, long ones in overlapping pieces of SPAN bytes."""
    raw = (text or "").lower().encode()
    joined = [m.replace(b" ", b"") for m in SPACED.findall(raw)]
    found = {b"^%b$" % w for w in {*raw.translate(None, PUNCTUATION).split(), *joined}}
    long = [w for w in found if len(w) > SPAN]
    found.difference_update(long)
    for w in long:
        found.update(w[i : i + SPAN] for i in range(0, len(w) - SPAN // 2, SPAN // 2))
    return found


def _gaps(n: int) -> np.ndarray:
    """n x n: DECAY to the characters skipped between an earlier and a later place."""
    i = np.arange(n)
    d = i[:, None] - i[None] - 1
    return np.where(d >= 0, DECAY ** np.maximum(d, 0), 0).astype(np.float32)


def kernel(grid: np.ndarray, landmark: bytes) -> np.ndarray:
    """k(w, landmark) of each row of a grid of words, padded by zeros."""
    same = (grid[:, :, None] == np.frombuffer(landmark, dtype=np.uint8)[None, None]).astype(np.float32)
    left, right = _gaps(grid.shape[1]), _gaps(len(landmark)).T
    held = same
    for _ in range(P - 1):
        held = same * (left @ held @ right)
    return held.sum(axis=(1, 2), dtype=np.float64)


def grid_of(found: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join([w.ljust(SPAN, b"\0") for w in found]), dtype=np.uint8).reshape(len(found), SPAN)


class Matcher:
    """Matches of words with the landmarks, remembering words that match and recent ones that don't."""

    def __init__(self, landmarks: list[bytes], cold: int = 400_000):
        self.landmarks, self.limit = landmarks, cold
        self.own = [float(kernel(grid_of([x]), x)[0]) for x in landmarks]
        self.masks = [self._mask(np.frombuffer(x, dtype=np.uint8)[None])[0] for x in landmarks]
        self.hot: dict[bytes, np.ndarray] = {}
        self.cold: set[bytes] = set()

    @staticmethod
    def _mask(grid: np.ndarray) -> np.ndarray:
        bits = np.where(grid > 0, np.left_shift(np.uint64(1), (grid & 63).astype(np.uint64)), 0).astype(np.uint64)
        return np.bitwise_or.reduce(bits, axis=1)

    def learn(self, found: set[bytes]) -> None:
        new = sorted(found.difference(self.cold).difference(self.hot))
        for at in range(0, len(new), 20_000):
            part = new[at : at + 20_000]
            grid = grid_of(part)
            masks, values = self._mask(grid), np.zeros((len(part), len(self.landmarks)), dtype=np.float32)
            for j, x in enumerate(self.landmarks):
                # a match is looked for where most of the landmark's characters occur at all
                rows = np.flatnonzero(np.bitwise_count(masks & self.masks[j]) >= np.ceil(0.7 * int(self.masks[j]).bit_count()))
                if len(rows):
                    values[rows, j] = np.minimum(kernel(grid[rows], x) / self.own[j], 1)
            match = (values >= LEVELS[0]).any(axis=1)
            for i in np.flatnonzero(match).tolist():
                self.hot[part[i]] = values[i]
            if len(self.cold) + len(part) > self.limit:
                self.cold = set()
            self.cold.update(w for w, m in zip(part, match.tolist()) if not m)
        if len(self.hot) > self.limit:
            self.hot = {}
            self.learn(found)

    def row(self, found: set[bytes]) -> np.ndarray:
        """The strongest match with each landmark; call learn() with these words before."""
        hits = [self.hot[w] for w in found if w in self.hot]
        return np.max(hits, axis=0) if hits else np.zeros(len(self.landmarks), dtype=np.float32)

    def rows(self, texts: list[str | None], group: int = 64) -> np.ndarray:
        out = np.zeros((len(texts), len(self.landmarks)))
        for at in range(0, len(texts), group):
            sets = [words(t) for t in texts[at : at + group]]
            self.learn(set().union(*sets))
            for i, found in enumerate(sets, at):
                out[i] = self.row(found)
        return out


@dataclass
class Model:
    """Landmarks, their Nystroem map, the machine's weights and the calibration of its margin."""

    landmarks: list[bytes]
    whiten: np.ndarray
    weights: np.ndarray
    slope: float = 1.0
    offset: float = 0.0

    def features(self, rows: np.ndarray) -> np.ndarray:
        low, high = (np.maximum(rows - x, 0) / (1 - x) for x in LEVELS)
        return np.hstack([low @ self.whiten, high @ self.whiten, np.ones((len(rows), 1))])

    def scores(self, rows: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * (self.features(rows) @ self.weights) + self.offset, -50, 50)))


def unlike(texts: list[str | None], size: int = 16, shared: int = 7) -> list[int]:
    """Numbers of texts no two of which are near copies: their sketches, the ``size`` three-word shingles of least hash, share less than ``shared``."""
    kept, holders = [], {}
    for i, t in enumerate(texts):
        w = (t or "").lower().encode().split()
        sketch = sorted({xxhash.xxh64_intdigest(b" ".join(w[j : j + 3]), 3) for j in range(max(1, len(w) - 2))})[:size]
        seen = Counter(k for h in sketch for k in holders.get(h, ()))
        if not seen or max(seen.values()) < min(shared, len(sketch)):
            kept.append(i)
            for h in sketch:
                holders.setdefault(h, []).append(i)
    return kept


def choose_landmarks(texts: list[str | None], labels: list[int], most: int = 40, least_docs: int = 3) -> list[bytes]:
    """Words and word beginnings that mark toxic texts: frequent there, all but absent elsewhere, and unlike each other."""

    def parts(text):
        out = set()
        for w in words(text):
            if w[:1] == b"^":
                if w[-1:] == b"$" and 6 <= len(w) <= 14:
                    out.add(w)
                out.update(w[:n] for n in range(5, min(len(w), 10)))
        return out

    holders: dict[bytes, set[int]] = {}
    for i, (t, y) in enumerate(zip(texts, labels)):
        if y == 1:
            for x in parts(t):
                holders.setdefault(x, set()).add(i)
    holders = {x: h for x, h in holders.items() if len(h) >= least_docs}
    clean: Counter = Counter()
    for t, y in zip(texts, labels):
        if y != 1:
            clean.update(parts(t) & holders.keys())
    n1, n0 = max(1, sum(y == 1 for y in labels)), max(1, sum(y != 1 for y in labels))
    good = [x for x, h in holders.items() if len(h) >= 0.008 * n1 and len(h) / n1 > 20 * (clean[x] + 0.2) / n0]
    chosen: list[bytes] = []
    for x in sorted(good, key=lambda x: (-round(8 * np.log(len(holders[x]))), -len(x), x)):
        if all(len(holders[x] & holders[c]) < 0.7 * len(holders[x]) or x[:5] != c[:5] for c in chosen):
            chosen.append(x)
            if len(chosen) == most:
                break
    return chosen


def train_machine(x: np.ndarray, y: np.ndarray, cost: float = 10.0, rounds: int = 60) -> np.ndarray:
    """Weights of an L2-regularised machine with squared hinge loss and balanced classes, by Newton's method."""
    w = np.zeros(x.shape[1])
    balance = cost * np.where(y > 0, 1 / max(1, (y > 0).sum()), 1 / max(1, (y < 0).sum())) * len(y) / 2
    keep = np.eye(x.shape[1])
    keep[-1, -1] = 1e-3  # the constant is all but unpenalised
    for _ in range(rounds):
        active = y * (x @ w) < 1
        xa, ca = x[active], balance[active]
        new = np.linalg.solve(keep + (xa.T * ca) @ xa, xa.T @ (ca * y[active]))
        if np.abs(new - w).max() < 1e-9:
            break
        w = new if _ < 20 else (w + new) / 2
    return w


def sentences_of(text: str | None) -> list[str]:
    return [s for s in re.split(r"[.!?\n]+", text or "") if s.strip()]


def distinct(rows: np.ndarray) -> np.ndarray:
    return np.unique(np.round(rows, 2), axis=0)


def witnesses(model: Model, bags: list[np.ndarray]) -> np.ndarray:
    """Of the sentences of each toxic text, the row that the machine scores highest."""
    return distinct(np.array([rows[np.argmax(model.features(rows) @ model.weights)] for rows in bags])) if bags else np.zeros((0, len(model.landmarks)))


def calibrate(margin: np.ndarray, y: np.ndarray, rounds: int = 100) -> tuple[float, float]:
    """(slope, offset) of the logistic curve through the margins, both classes of equal weight and targets smoothed by a case."""
    up, down = max(1, int((y > 0).sum())), max(1, int((y < 0).sum()))
    goal = np.where(y > 0, (up + 1) / (up + 2), 1 / (down + 2))
    weight = np.where(y > 0, 0.5 / up, 0.5 / down)
    x, at = np.column_stack([margin, np.ones(len(margin))]), np.array([1.0, 0.0])
    loss = lambda p: float((weight * (np.logaddexp(0, x @ p) - goal * (x @ p))).sum())
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ at, -50, 50)))
        step = np.linalg.solve((x.T * (weight * p * (1 - p))) @ x + 1e-9 * np.eye(2), x.T @ (weight * (p - goal)))
        size = 1.0
        while size > 1e-6 and loss(at - size * step) > loss(at):
            size /= 2
        at = at - size * step
        if np.abs(size * step).max() < 1e-8:
            break
    return float(at[0]), float(at[1])


def fit(texts: list[str | None], labels: list[int], rounds: int = 2) -> Model:
    """Landmarks, machine and calibration from labelled texts; without both classes every score is the majority's."""
    if len(set(labels)) < 2:
        return Model([], np.zeros((0, 0)), np.zeros(1), 1.0, 2.0 if labels and labels[0] == 1 else -2.0)
    own = unlike(texts)
    landmarks = choose_landmarks([texts[i] for i in own], [labels[i] for i in own])
    matcher = Matcher(landmarks)
    rows = matcher.rows(texts)
    grid = grid_of([x.ljust(SPAN, b"\0") for x in landmarks]) if landmarks else np.zeros((0, SPAN), dtype=np.uint8)
    gram = np.array([kernel(grid, x) for x in landmarks]).reshape(len(landmarks), -1)
    root = np.sqrt(np.diag(gram)) if len(landmarks) else np.zeros(0)
    values, vectors = np.linalg.eigh(gram / np.outer(root, root)) if len(landmarks) else (np.zeros(0), np.zeros((0, 0)))
    whiten = vectors @ np.diag(1 / np.sqrt(np.maximum(values, 1e-2))) @ vectors.T
    model = Model(landmarks, whiten, np.zeros(2 * len(landmarks) + 1))
    y = np.where(np.array(labels) == 1, 1.0, -1.0)
    model.weights = train_machine(model.features(rows), y)
    bags = [matcher.rows(s) for t, v in zip(texts, y) if v > 0 and (s := sentences_of(t))]
    clean = [s for t, v in zip(texts, y) if v < 0 for s in sentences_of(t)]
    clean = distinct(matcher.rows(clean)) if clean else np.zeros((0, len(landmarks)))
    for _ in range(rounds):
        found = witnesses(model, bags)
        all_rows, all_y = np.vstack([rows, found, clean]), np.concatenate([y, np.ones(len(found)), -np.ones(len(clean))])
        model.weights = train_machine(model.features(all_rows), all_y)
    model.slope, model.offset = calibrate(model.features(rows) @ model.weights, y)
    return model


def fold(id_col) -> F.Column:
    """crc32 of the id as text, modulo 5; a null id has that of an empty text."""
    return F.crc32(F.coalesce(id_col.cast("string"), F.lit("")).cast("binary")) % 5


def train(docs: DataFrame, labels: DataFrame, toxic_rows: int = 1500, clean_rows: int = 3500, id_col: str = "doc_id", text_col: str = "text") -> Model:
    """A model from at most so many labelled rows of each class, those of smallest id hash outside the held-out fold."""
    known = labels.select(F.col("doc_id").cast("long").alias("k"), F.col("toxic").cast("int").alias("y")).where(F.col("k").isNotNull() & F.col("y").isin(0, 1) & (fold(F.col("k")) != 0))
    part = lambda y, n: known.where(F.col("y") == y).orderBy(F.xxhash64("k"), "k").limit(n)
    sample = part(1, toxic_rows).unionByName(part(0, clean_rows))
    rows = docs.select(F.col(id_col).cast("long").alias("k"), F.col(text_col).alias("text")).join(F.broadcast(sample), "k")
    got = rows.orderBy(F.xxhash64("k"), "k", "y", "text").limit(toxic_rows + clean_rows).collect()
    return fit([r.text for r in got], [r.y for r in got])


def _scorer(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(model.landmarks)
        for batch in batches:
            if batch.num_rows:
                s = model.scores(matcher.rows(batch.column(2).to_pylist()))
                yield batch_of(RESULT, batch.column(0), batch.column(1), s, (s >= 0.5).astype(np.int32))

    return run


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row's whole text; the score sees the text alone.

    Null and empty texts get the score of a text without matches; null or
    repeated ids keep their rows.
    """
    key = F.col(id_col).cast("long")
    return docs.select(key.alias("doc_id"), (fold(key) == 0).alias("held_out"), F.col(text_col).alias("text")).mapInArrow(_scorer(model), "doc_id long, held_out boolean, score double, predicted int")


def keep_clean(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """``docs`` without the rows that score 0.5 or more; columns and other rows are unchanged."""
    held: list[Matcher] = []

    @F.arrow_udf("boolean")
    def fine(texts: pa.Array) -> pa.Array:
        if not held:
            held.append(Matcher(model.landmarks))
        return pa.array([s < 0.5 for part in portions(texts) for s in model.scores(held[0].rows(part)).tolist()], pa.bool_())

    return docs.where(fine(F.col(text_col)))
