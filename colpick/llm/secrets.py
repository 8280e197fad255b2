"""Secret scans: fixed patterns, and character Markov models of random strings and identifiers.

Two first-order Markov models over characters, with add-one smoothing, are
trained from labelled strings: random ones and ordinary identifiers.  A
candidate run of secret-like characters is a secret if the log-likelihood ratio
of the models, a character, and its length are large enough.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, portions, unused

# The base patterns and their least lengths.
ASSIGN = re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
LEAST_ASSIGN, LEAST_ACCESS = 12, 18
KINDS = ("assign", "access", "hex", "markov")
KEYWORDS = ("password", "passwd", "secret", "token", "api_key", "apikey")
CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-."
RESULT = pa.schema([("doc_id", pa.int64()), ("n_assign", pa.int64()), ("n_access", pa.int64()), ("n_hex", pa.int64()), ("base_sha256", pa.string()), ("spans", pa.string())])
RESULT_DDL = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the fixed patterns, leftmost and non-overlapping within a kind."""
    low = text.lower()
    out = []
    if any(k in low for k in KEYWORDS):
        out += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= LEAST_ASSIGN]
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


class Markov:
    """Log-likelihood ratios of two first-order character models; ``table[a][b]`` is that of b after a."""

    def __init__(self, random_strings: Iterable[str], identifiers: Iterable[str]):
        code = {c: i + 1 for i, c in enumerate(ALPHABET)}
        self.code = code
        n = len(ALPHABET) + 2  # 0: start; last: any other character

        def model(strings):
            count = np.ones((n, n))
            for s in strings:
                at = 0
                for c in s:
                    to = code.get(c, n - 1)
                    count[at, to] += 1
                    at = to
            return np.log(count / count.sum(axis=1, keepdims=True))

        self.table = (model(random_strings) - model(identifiers)).tolist()

    def gains(self, s: str) -> list[float]:
        """Log-likelihood ratio of each character after the one before it."""
        at, out, other = 0, [], len(self.table) - 1
        for c in s:
            to = self.code.get(c, other)
            out.append(self.table[at][to])
            at = to
        return out

    def ratio(self, s: str) -> float:
        """Log-likelihood ratio a character."""
        return sum(self.gains(s)) / max(1, len(s))


def best_runs(gains: list[float]) -> list[tuple[int, int]]:
    """The maximal runs of positive sum: none can be made longer or shorter at an end to its advantage."""
    runs: list[tuple[int, int, float, float]] = []  # (start, end, sum before, sum up to the end)
    total = 0.0
    for i, g in enumerate(gains):
        now = (i, i + 1, total, total + g)
        total += g
        while g > 0:
            j = next((j for j in range(len(runs) - 1, -1, -1) if runs[j][2] < now[2]), None)
            if j is None or runs[j][3] >= now[3]:
                runs.append(now)
                break
            now = (runs[j][0], now[1], runs[j][2], now[3])
            del runs[j:]
    return [(a, b) for a, b, _, _ in runs]


def random_samples(n: int = 6000, seed: int = 5) -> list[str]:
    """Labelled random strings, drawn evenly from the usual alphabets of keys."""
    rng = random.Random(seed)
    sets = [ALPHABET[:62], ALPHABET[:64], ALPHABET[:62] + "_-", ALPHABET[:26] + "0123456789", ALPHABET[26:62], "0123456789abcdef"]
    return ["".join(rng.choice(sets[i % len(sets)]) for _ in range(rng.randint(16, 64))) for i in range(n)]


def identifier_samples(words: Iterable[str], n: int = 12000, seed: int = 6) -> list[str]:
    """Labelled identifiers: words alone and joined in the usual ways."""
    rng = random.Random(seed)
    words = sorted({w for w in words if 2 <= len(w) <= 24}) or ["value", "index", "name"]
    out = []
    for i in range(n):
        part = [rng.choice(words) for _ in range(rng.randint(2, 4))]
        join = i % 6
        s = "".join(w.capitalize() for w in part) if join == 0 else part[0] + "".join(w.capitalize() for w in part[1:]) if join == 1 else "_".join(part) if join == 2 else "-".join(part) if join == 3 else "/".join(part) if join == 4 else part[0]
        if i % 12 == 11:
            s = "_".join(part).upper()
        if rng.random() < 0.15:
            s += str(rng.randint(0, 2030))
        out.append(s)
    return out


def train(docs: DataFrame, sample_docs: int = 2000, id_col: str = "doc_id", text_col: str = "text") -> Markov:
    """Models from labelled samples: random strings against identifiers made of the corpus's words.

    The words come from at most ``sample_docs`` documents, those with the
    smallest hash of their id; strings that a fixed pattern matches are
    labelled random.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("k"), F.col(text_col).alias("text")).where("text is not null")
    # ids first, so that no task sends texts that another's replace
    ids = rows.select("k").where("k is not null").orderBy(F.xxhash64("k"), "k").limit(sample_docs).distinct()
    rows = rows.join(F.broadcast(ids), "k")
    texts = [r.text for r in rows.orderBy(F.xxhash64("k"), "k", F.length("text"), "text").limit(sample_docs).collect()]
    words, found = set(), []
    for t in texts:
        spans = base_spans(t)
        found += [t[a:b] for a, b, kind in spans if kind != "assign"]
        for a, b, _ in reversed(spans):
            t = t[:a] + " " + t[b:]
        words.update(re.findall(r"[A-Za-z]+", t))
    return Markov(random_samples() + found, identifier_samples(words))


def free_parts(a: int, b: int, taken: list[tuple[int, int, str]]) -> list[tuple[int, int]]:
    """What sorted spans leave of the range a to b."""
    out = []
    for x, y, _ in taken:
        if y > a and x < b:
            if x > a:
                out.append((a, x))
            a = max(a, y)
    return [*out, (a, b)] if a < b else out


def markov_spans(text: str, model: Markov, threshold: float, least: int = 20, taken: list[tuple[int, int, str]] = ()) -> list[tuple[int, int, str]]:
    """Stretches of secret-like characters that look random, outside the spans ``taken``.

    Of a run of such characters the parts count whose log-likelihood ratio is
    above ``threshold`` a character, each up to the ends of its letters and
    digits, so that a key at the end of a long path stands out.  A part that has
    no digit or no letter needs twice the ratio.
    """
    out = []
    for m in CANDIDATE.finditer(text):
        for a, b in free_parts(*m.span(), taken):
            if b - a < least:
                continue
            s, end = text[a:b], 0
            for x, y in best_runs([g - threshold for g in model.gains(s)]):
                if y - x < least // 2 or x < end:
                    continue
                while x > end and s[x - 1].isalnum():
                    x -= 1
                while y < len(s) and s[y].isalnum():
                    y += 1
                x += len(s[x:y]) - len(s[x:y].lstrip("=/-_+"))
                part = s[x:y]
                need = threshold if any(c.isdigit() for c in part) and any(c.isalpha() for c in part) else 2 * threshold
                if len(part) >= least and len(set(part)) >= 8 and model.ratio(part) >= need:
                    out.append((a + x, a + y, "markov"))
                    end = y
    return out


def spans_of(text: str | None, model: Markov, threshold: float) -> tuple[list, list]:
    """(base spans, all spans), each sorted by start and kind; all of a null text's are none."""
    text = text or ""
    base = base_spans(text)
    return base, sorted(base + markov_spans(text, model, threshold, taken=base), key=lambda s: (s[0], KINDS.index(s[2])))


def spell(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def scan(docs: DataFrame, model: Markov | None = None, threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans) of every row's whole text.

    Offsets are code points, ends exclusive.  Null and empty texts have no
    spans; null or repeated ids keep their rows.
    """
    model = model or train(docs, id_col=id_col, text_col=text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                base, every = spans_of(text, model, threshold)
                count = [sum(s[2] == k for s in base) for k in KINDS[:3]]
                out.append((key, *count, hashlib.sha256(spell(base).encode()).hexdigest(), spell(every)))
            if out:
                yield batch_of(RESULT, *map(list, zip(*out)))

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, RESULT_DDL)


def redact(docs: DataFrame, model: Markov | None = None, threshold: float = 0.5, mark: str = "[SECRET]", id_col: str = "doc_id", text_col: str = "text", length_col: str | None = "n_chars") -> DataFrame:
    """``docs`` with every span replaced by ``mark``, and the length column, if any, recounted for changed texts.

    Overlapping spans are replaced together.  Texts without spans, null ones
    included, stay as they are.
    """
    model = model or train(docs, id_col=id_col, text_col=text_col)

    def cleaned(text: str | None) -> str | None:
        """The text with marks; None if it has no span."""
        _, spans = spans_of(text, model, threshold)
        if not spans:
            return None
        merged: list[list[int]] = []
        for a, b, _ in spans:
            if merged and a < merged[-1][1]:
                merged[-1][1] = max(b, merged[-1][1])
            else:
                merged.append([a, b])
        parts, at = [], 0
        for a, b in merged:
            parts += [text[at:a], mark]
            at = b
        return "".join([*parts, text[at:]])

    # only changed texts come back from Python
    @F.arrow_udf("string")
    def clean(texts: pa.Array) -> pa.Array:
        return pa.array([cleaned(text) for part in portions(texts) for text in part], pa.string())

    done = unused("_clean", docs)
    out = docs.withColumn(done, clean(F.col(text_col)))
    if length_col and length_col in docs.columns:
        kind = docs.schema[length_col].dataType
        out = out.withColumn(length_col, F.when(F.col(done).isNull() | (F.col(done) == F.col(text_col)), F.col(length_col)).otherwise(F.length(done).cast(kind)))
    return out.withColumn(text_col, F.coalesce(done, text_col)).drop(done)
