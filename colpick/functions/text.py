"""Tokens, vocabularies and hashed features."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import vec
from .random_maps import hashed, hashed_number


def tokens(text: Column) -> Column:
    """Runs of a-z of the lower-cased text."""
    return F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0))


def visible(html: Column) -> Column:
    """Text of a page without scripts, styles and tags."""
    return F.regexp_replace(F.regexp_replace(html, r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), r"<[^>]*>", " ")


def counts(df: DataFrame, id_col: str, text: Column) -> DataFrame:
    """(col_key, row_key, value): occurrences of each token in each text."""
    return df.select(F.col(id_col).alias("col_key"), F.explode(tokens(text)).alias("row_key")).groupBy("col_key", "row_key").agg(F.count("*").cast("double").alias("value"))


def frequent(cells: DataFrame, least: int) -> DataFrame:
    """Cells of tokens that at least so many texts have.

    Both sides ask for the value, so that the cells are counted once and their shuffle is read twice.
    """
    common = cells.groupBy("row_key").agg(F.count_if(F.col("value") > 0).alias("df")).where(F.col("df") >= least).select("row_key")
    return cells.join(common, "row_key", "left_semi")


def hash_rows(cells: DataFrame, buckets: int) -> DataFrame:
    """Cells with the token's bucket for a row, summed up."""
    return cells.select("col_key", (hashed(F.col("row_key")) % buckets).alias("row_key"), "value").groupBy("col_key", "row_key").agg(F.sum("value").alias("value"))


def histograms(buckets: int, rows: int = 1024):
    """Kernel over (col_id, tokens): (col_id, vec), the counts of :func:`hash_rows` for each row by itself."""
    schema = pa.schema([("col_id", pa.int64()), ("vec", pa.list_(pa.float64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low in range(0, batch.num_rows, rows):
                part = batch.slice(low, rows)
                words = part.column(1).flatten().dictionary_encode()
                at = np.array([hashed_number(w) % buckets for w in words.dictionary.to_pylist()], dtype=np.int64)
                n = pc.fill_null(pc.list_value_length(part.column(1)), 0).to_numpy()
                place = np.repeat(np.arange(len(n)) * buckets, n) + at[words.indices.to_numpy()]
                yield pa.RecordBatch.from_arrays([part.column(0), vec.unstack(np.bincount(place, minlength=len(n) * buckets).reshape(len(n), buckets))], schema=schema)

    return run
