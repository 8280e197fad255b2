"""Token counts as rollups that deltas maintain.

A batch is a table of signed changes: a document put in (+1), taken out (-1),
or counted anew (its old count out, its new one in).  Totals by source,
language and tokenizer version are additive, so a batch is summed up by itself
and added.  A batch commits under its name, once: the same name again changes
nothing, whether retried after a failure or sent twice.
"""

from __future__ import annotations

import re
from collections.abc import Iterable

from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

KEYS = ["source", "lang", "tokenizer"]
TOTALS = ["n_docs", "n_tokens", "n_bytes"]


def word_tokens(text: Column) -> Column:
    """Runs of anything but ASCII white space."""
    return F.size(F.filter(F.split(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+"), lambda w: w != "")).cast("long")


def letter_tokens(text: Column) -> Column:
    """Runs of ASCII letters and digits."""
    return F.size(F.filter(F.split(F.coalesce(text, F.lit("")), "[^A-Za-z0-9]+"), lambda w: w != "")).cast("long")


def bpe_tokens(path: str):
    """A counter of byte-level BPE tokens by a rank file."""

    def count(text: Column) -> Column:
        @F.pandas_udf("long")
        def run(texts):
            import pandas as pd

            from . import byte_bpe

            return pd.Series([len(x) for x in byte_bpe.codec(path).encode_batch(texts.tolist())], dtype="int64")

        return run(F.coalesce(text, F.lit("")))

    return count


def counted(docs: DataFrame, tokenizer: str, counter, sign: int = 1, text_col: str = "text", keep: Iterable[str] = ()) -> DataFrame:
    """A batch of changes: each document with its count under a tokenizer version, put in or taken out.

    Null texts count as empty; null sources and languages are groups of their own.
    ``keep`` names columns that stay, for a join by which the batch is chosen.
    """
    text = F.col(text_col)
    return docs.select(*keep, F.col("source").cast("string").alias("source"), F.col("lang").cast("string").alias("lang"), F.lit(tokenizer).alias("tokenizer"), F.lit(sign).cast("long").alias("sign"), counter(text).alias("n_tokens"), F.coalesce(F.octet_length(text), F.lit(0)).cast("long").alias("n_bytes"))


def revised(docs: DataFrame, tokenizer: str, old, new, text_col: str = "text") -> DataFrame:
    """A batch that replaces the counts of documents already in: the old ones out, the new ones in."""
    return counted(docs, tokenizer, old, -1, text_col).unionByName(counted(docs, tokenizer, new, 1, text_col))


def summed(batch: DataFrame) -> DataFrame:
    """Additive totals of a batch; summed up before the shuffle, so hot keys don't matter."""
    return batch.groupBy(*KEYS).agg(F.sum("sign").alias("n_docs"), F.sum(F.col("sign") * F.col("n_tokens")).alias("n_tokens"), F.sum(F.col("sign") * F.col("n_bytes")).alias("n_bytes"))


def rollup(totals: DataFrame) -> DataFrame:
    """Totals of several batches added up; groups with nothing left are not listed."""
    out = totals.groupBy(*KEYS).agg(*[F.sum(c).alias(c) for c in TOTALS])
    return out.where(" or ".join(f"{c} != 0" for c in TOTALS))


class Ledger:
    """Totals by batch in a shared folder, one directory a batch.

    A batch is written aside and renamed into place by a rename that refuses a
    target that exists (the plain one would move the directory into it), so of
    two writers of one batch one wins and nothing is counted twice.  Compaction
    adds up what is there into a base, which also keeps the names of its batches;
    a directory whose name is in the base no longer counts.
    """

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self.jvm = spark.sparkContext._jvm
        self.fs = self._path("").getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _path(self, name: str):
        return self.jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}" if name else self.path)

    def _names(self, start: str) -> list[str]:
        if not self.fs.exists(self._path("")):
            return []
        return sorted(n.removeprefix(start) for s in self.fs.listStatus(self._path("")) if (n := s.getPath().getName()).startswith(start))

    def _base(self) -> str | None:
        """The folder of the last base."""
        numbers = [int(n) for n in self._names("base=")]
        return f"{self.path}/base={max(numbers)}" if numbers else None

    def _in_base(self) -> set[str]:
        base = self._base()
        return {r.name for r in self.spark.read.parquet(f"{base}/names").collect()} if base else set()

    def batches(self) -> list[str]:
        """Names of all batches that are in, those of the base included."""
        return sorted({*self._names("batch="), *self._in_base()})

    def commit(self, name: str, batch: DataFrame) -> bool:
        """Adds a batch under a name; False, and nothing changed, if the name is in already."""
        if not re.fullmatch(r"[A-Za-z0-9._-]+", name):
            raise ValueError(f"not a batch name: {name!r}")
        final = self._path(f"batch={name}")
        if self.fs.exists(final) or name in self._in_base():
            return False
        return self._write(final, f"{name}-", lambda place: summed(batch).write.parquet(place))

    def _write(self, final, mark: str, write) -> bool:
        aside = f"_writing-{mark}{self.jvm.java.util.UUID.randomUUID()}"
        self.fs.mkdirs(self._path(""))
        write(f"{self.path}/{aside}/part")
        try:
            return self._publish(self._path(f"{aside}/part"), final)
        finally:
            self.fs.delete(self._path(aside), True)

    def compact(self) -> bool:
        """Makes one base of the last one and all batches beside it, then deletes what it replaces.

        False if there is nothing to add or another compaction was faster.
        """
        before, new = self._base(), [n for n in self._names("batch=") if n not in self._in_base()]
        if not new:
            return False
        names, number = [(n,) for n in self.batches()], 1 + int(before.rpartition("=")[2]) if before else 0

        def write(place: str) -> None:
            self.totals().write.parquet(f"{place}/totals")
            self.spark.createDataFrame(names, "name string").coalesce(1).write.parquet(f"{place}/names")

        if not self._write(self._path(f"base={number}"), "base-", write):
            return False
        for old in [*(f"batch={n}" for n in new), *([before.rpartition("/")[2]] if before else [])]:
            self.fs.delete(self._path(old), True)
        return True

    def sweep(self, older_than_seconds: float = 86_400) -> int:
        """Deletes what writers that died have left aside for so long; returns how many."""
        limit = self.jvm.java.lang.System.currentTimeMillis() - int(1000 * older_than_seconds)
        old = [s.getPath() for s in self.fs.listStatus(self._path("")) if s.getPath().getName().startswith("_writing-") and s.getModificationTime() <= limit] if self.fs.exists(self._path("")) else []
        for place in old:
            self.fs.delete(place, True)
        return len(old)

    def _publish(self, source, final) -> bool:
        """Renames a directory to a name that doesn't exist; False if it does."""
        fs, sc = self.jvm.org.apache.hadoop.fs, self.spark.sparkContext
        files = fs.FileContext.getFileContext(self.fs.getUri(), sc._jsc.hadoopConfiguration())
        try:
            files.rename(source, final, sc._gateway.new_array(fs.Options.Rename, 0))
        except Py4JJavaError as error:
            if error.java_exception.getClass().getSimpleName() != "FileAlreadyExistsException":
                raise
            return False
        return True

    def totals(self) -> DataFrame:
        """The rollup over the base and all batches beside it; no batch, no rows."""
        base, inside = self._base(), self._in_base()
        places = [f"{self.path}/batch={n}" for n in self._names("batch=") if n not in inside] + ([f"{base}/totals"] if base else [])
        if not places:
            return self.spark.createDataFrame([], ", ".join([*(f"{k} string" for k in KEYS), *(f"{t} long" for t in TOTALS)]))
        return rollup(self.spark.read.parquet(*places))


def commit_batches(spark: SparkSession, path: str, batches: Iterable[tuple[str, DataFrame]]) -> DataFrame:
    """Commits named batches to the ledger at ``path``, one after another, and returns its totals."""
    ledger = Ledger(spark, path)
    for name, batch in batches:
        ledger.commit(name, batch)
    return ledger.totals()


def apply_batches(batches: Iterable[tuple[str, DataFrame]]) -> DataFrame:
    """The rollup of named batches without a ledger, each name once: one plan, no files."""
    seen: dict[str, DataFrame] = {}
    for name, batch in batches:
        seen.setdefault(name, batch)
    frames = [summed(b) for b in seen.values()]
    if not frames:
        raise ValueError("no batch")
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return rollup(out)


__all__ = ["KEYS", "TOTALS", "Ledger", "apply_batches", "bpe_tokens", "commit_batches", "counted", "letter_tokens", "revised", "rollup", "summed", "word_tokens"]
