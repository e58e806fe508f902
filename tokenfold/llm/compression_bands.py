"""Quality rules from compression ratios.

zstandard shrinks repetitive text far more than prose and random text hardly at
all. Each document is compressed whole and in fixed chunks; a ratio outside the
band of its length rejects. Short texts compress worse, so the bands move with
the length.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import WORD, fresh, table, texts

SYMBOLS = "#*$%&|<>"
_DROP_SYMBOLS = str.maketrans("", "", SYMBOLS)
_DROP_SPACE = str.maketrans("", "", " \t\n\v\f\r")


@dataclass(frozen=True)
class Bands:
    """Limits of compressed bytes over bytes: (least length in bytes, lowest, highest ratio).

    Prose in alphabetic scripts lies well inside them at every length; tables and
    repeated phrases fall below, base64 and random characters above.
    """

    whole: tuple[tuple[int, float, float], ...] = ((0, 0.00, 9.0), (256, 0.44, 0.88), (1024, 0.41, 0.74), (4096, 0.37, 0.64), (16384, 0.34, 0.60))
    chunk: tuple[tuple[int, float, float], ...] = ((0, 0.00, 9.0), (256, 0.44, 0.88), (1024, 0.41, 0.74), (4096, 0.37, 0.64))
    chunk_bytes: int = 4096
    #: Share of a text's chunks, by bytes, that may lie outside their band.
    chunks_out: float = 0.25
    level: int = 3
    least_words: int = 50
    repeat_percent: int = 50


SCHEMA = T.StructType([
    T.StructField("n_words", T.LongType()), T.StructField("word_chars", T.LongType()), T.StructField("n_symbols", T.LongType()),
    T.StructField("n_dup_lines", T.LongType()), T.StructField("n_repeat_words", T.LongType()), T.StructField("base_failed", T.BooleanType()),
    T.StructField("kept", T.BooleanType()), T.StructField("n_bytes", T.LongType()), T.StructField("ratio", T.DoubleType()),
    T.StructField("chunks", T.LongType()), T.StructField("lowest_chunk", T.DoubleType()), T.StructField("highest_chunk", T.DoubleType()),
    T.StructField("out_share", T.DoubleType()), T.StructField("reason", T.StringType()),
])


def repeated_words(words: list[str], n: int = 3) -> int:
    """Words that lie in a window of n words found at least twice."""
    if len(words) <= n:
        return 0
    ids = {w: i for i, w in enumerate(dict.fromkeys(words))}
    v = np.fromiter(map(ids.__getitem__, words), np.int64, len(words))
    if len(ids) == len(words):
        return 0
    m = len(v) - n + 1
    if len(ids) ** n < 2**62:
        keys = v[:m].copy()
        for i in range(1, n):
            keys = keys * len(ids) + v[i : i + m]
    else:  # longer than any product: number the pairs first
        keys = v[:m].copy()
        for i in range(1, n):
            keys = np.unique(keys, return_inverse=True)[1] * len(ids) + v[i : i + m]
    _, back, counts = np.unique(keys, return_inverse=True, return_counts=True)
    twice = counts[back] > 1
    covered = np.zeros(len(v), bool)
    for i in range(n):
        covered[i : i + m] |= twice
    return int(covered.sum())


def duplicate_lines(text: str) -> int:
    """Lines with a word that equal an earlier line."""
    lines = text.split("\n")
    if len(lines) < 2 or len(set(lines)) == len(lines):
        return 0
    return sum(n - 1 for line, n in pd.Series(lines).value_counts().items() if n > 1 and WORD.search(line))


def _outside(size: int, ratio: float, bands: tuple[tuple[int, float, float], ...]) -> str:
    _, low, high = max(b for b in bands if b[0] <= size)
    return "repetitive" if ratio < low else "incompressible" if ratio > high else ""


class Meter:
    def __init__(self, bands: Bands):
        self.bands, self.zstd = bands, zstandard.ZstdCompressor(level=bands.level)

    def ratio(self, data: bytes) -> float:
        return len(self.zstd.compress(data)) / len(data)

    def __call__(self, text: str) -> tuple:
        b = self.bands
        words = WORD.findall(text)
        n, repeats = len(words), repeated_words(words)
        failed = n < b.least_words or 100 * repeats > b.repeat_percent * n
        data = text.encode("utf-8", "surrogatepass")
        whole, why, low, high, out, k = None, "", None, None, 0.0, 0
        if data:
            whole = self.ratio(data)
            why = _outside(len(data), whole, b.whole)
            if len(data) <= b.chunk_bytes:
                low = high = whole
                k = 1
            else:
                # equal chunks of at most chunk_bytes, so that none is a short rest with a ratio of its own
                k = -(-len(data) // b.chunk_bytes)
                cuts = [len(data) * i // k for i in range(k + 1)]
                low, high = 9.0, 0.0
                for i, j in zip(cuts, cuts[1:], strict=False):
                    r = self.ratio(data[i:j])
                    low, high = min(low, r), max(high, r)
                    if _outside(j - i, r, b.chunk):
                        out += (j - i) / len(data)
                if out > b.chunks_out:
                    why = why or "chunks"
        return (n, len(text.translate(_DROP_SPACE)), len(text) - len(text.translate(_DROP_SYMBOLS)), duplicate_lines(text), repeats, failed, not failed and not why, len(data), whole, k, low, high, out, "base" if failed else why)


def _judge(bands: Bands):
    def judge(column: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        meter = Meter(bands)
        for series in column:
            yield pd.DataFrame([meter(t) for t in texts(series)], columns=SCHEMA.names)

    judge.__annotations__ = {"column": Iterator[pd.Series], "return": Iterator[pd.DataFrame]}
    return F.pandas_udf(judge, SCHEMA).asNondeterministic()


def verdict(text: str | Column = "text", bands: Bands = Bands()) -> Column:
    """Struct of the counts, ratios and the verdict of one text.

    Null and empty texts have no word and fail the base rules. Ratios are null
    for empty texts. Very long texts are judged whole and by all their chunks.
    """
    return _judge(bands)(text)


def keep_good(df: DataFrame, text: str = "text", bands: Bands = Bands()) -> DataFrame:
    """The rows whose text passes; all columns as they were."""
    v = fresh(df, "_verdict")
    return df.withColumn(v, verdict(text, bands)).filter(F.col(v)["kept"]).drop(v)


def op4_compression_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return docs.select("doc_id", verdict("text").alias("v")).select("doc_id", *(F.col("v")[c].alias(c) for c in SCHEMA.names))
