"""Duplicate lines or paragraphs, removed from all but their first place.

Units are normalised and hashed to 128 bits; digests are grouped over the whole
corpus, the occurrence of the lowest rank (document id, then place in the text)
stays, and the others are reported with their offsets in the original text.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import WORD, fresh, settle, table, texts

_SPACE = re.compile(r"[\x20\x09-\x0d]+")
_BREAK = {"line": re.compile(r"\n"), "paragraph": re.compile(r"\n(?:[\x20\x09-\x0d]*\n)+")}
#: Digests with more than one in HOT_SHARE of all units are joined by broadcast; there are at most HOT_SHARE of them.
HOT_SHARE = 1000
_UNITS = "said long, unit int, start int, length int, digest binary"


def normalised(unit: str) -> str:
    """Lower case, with runs of ASCII white space as one space and none at the ends."""
    return _SPACE.sub(" ", unit).strip(" ").lower()


def units(text: str, unit: str = "line", least_words: int = 1) -> list[tuple[int, int, int, bytes]]:
    """Number, start, length and digest of the units with enough words."""
    out, at = [], 0
    cuts = [(m.start(), m.end()) for m in _BREAK[unit].finditer(text)] + [(len(text), len(text))]
    for i, (end, after) in enumerate(cuts):
        plain = normalised(text[at:end])
        if plain and plain.count(" ") + 1 >= least_words:
            out.append((i, at, end - at, hashlib.md5(plain.encode("utf-8", "surrogatepass")).digest()))
        at = after
    return out


def _spell(key: pa.DataType, unit: str, least_words: int):
    def spell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, found = batch.column(0), [units(t, unit, least_words) for t in texts(batch.column(2).to_pylist())]
            rows = [u for us in found for u in us]
            of = pa.array([i for i, us in enumerate(found) for _ in us], pa.int32())
            columns = list(zip(*rows, strict=True)) or [()] * 4
            kinds = (pa.int32(), pa.int32(), pa.int32(), pa.binary())
            yield pa.RecordBatch.from_arrays([keys.take(of), batch.column(1).take(of), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], ["_id", "said", "unit", "start", "length", "digest"])

    return spell


def repeated_units(df: DataFrame, key: str = "doc_id", text: str = "text", unit: str = "line", least_words: int = 1) -> DataFrame:
    """Occurrences after the first: key, unit, start, length (code points) and first_<key>.

    Null texts hold no unit; null keys rank after all others. Rows that repeat a
    key and its text are the same occurrence, so a repeated row loses nothing
    that its twin keeps; other texts under the key are documents of their own. Ties
    between equal units are broken by key, place and the text's hash.
    """
    return _repeated(df, key, text, unit, least_words).drop("said")


def _repeated(df: DataFrame, key: str, text: str, unit: str, least_words: int) -> DataFrame:
    """As repeated_units, with said, the hash of the text that the unit is in."""
    kind = df.schema[key].dataType.simpleString()
    slim = df.select(F.col(key).alias("_id"), F.col(text).cast("string").alias("_text")).select("_id", F.xxhash64("_text").alias("said"), "_text")
    spelled = settle(slim.mapInArrow(_spell(None, unit, least_words), f"_id {kind}, {_UNITS}"), "units")
    rank = F.struct(F.col("_id").isNull().alias("last"), F.col("_id").alias("id"), F.col("unit").alias("unit"), F.col("said").alias("said"))
    groups = settle(spelled.groupBy("digest").agg(F.min(rank).alias("first"), F.count("*").alias("n")).filter("n > 1"), "digests")
    total = spelled.count()
    hot = groups.filter(F.col("n") * HOT_SHARE >= total)
    cold = groups.filter(F.col("n") * HOT_SHARE < total)
    found = spelled.join(F.broadcast(hot), "digest").unionByName(spelled.join(F.broadcast(hot.select("digest")), "digest", "left_anti").join(cold, "digest"))
    same = F.col("first.id").eqNullSafe(F.col("_id")) & (F.col("first.unit") == F.col("unit")) & (F.col("first.said") == F.col("said"))
    return found.filter(~same).select(F.col("_id").alias(key), "said", "unit", "start", "length", F.col("first.id").alias(f"first_{key}"))


def _places(text: str, spans: list) -> list[tuple[int, int]]:
    """Characters to cut, from spans of characters and of words, in order and without overlap."""
    words = [m.span() for m in WORD.finditer(text)] if any(s["words"] for s in spans) else []
    places = []
    for s in spans:
        start, length = s["start"], s["length"]
        if not s["words"]:
            places.append((start, min(len(text), start + length + 1)))  # with the line break after it
        elif start + length <= len(words):
            end = words[start + length - 1][1]
            while end < len(text) and text[end] == " ":
                end += 1
            places.append((words[start][0], end))
    out: list[tuple[int, int]] = []
    for a, b in sorted(places):
        if out and a <= out[-1][1]:
            out[-1] = out[-1][0], max(b, out[-1][1])
        else:
            out.append((a, b))
    return out


@F.pandas_udf(T.StringType())
def _cut(text: pd.Series, spans: pd.Series) -> pd.Series:
    out = []
    for t, ss in zip(text, spans, strict=True):
        if t is not None and ss is not None and len(ss):
            at, kept = 0, []
            for a, b in _places(t, ss):
                kept.append(t[at:a])
                at = b
            t = "".join([*kept, t[at:]])
        out.append(t)
    return pd.Series(out)


def drop_repeated_units(df: DataFrame, key: str = "doc_id", text: str = "text", unit: str = "line", least_words: int = 1, length: str | None = None, passages: DataFrame | None = None) -> DataFrame:
    """The rows with repeated units cut out of their text; all other columns stay.

    length names a column that holds the text's length in code points, if there is one.
    passages: further spans to cut, as words of the texts (_id, said, start, length). A
    unit's first occurrence stays, so a text without a repeat stays as it is, as do null
    texts; a row that repeats is cut as its twin is. Texts of any length are cut whole.
    """
    spans = _repeated(df, key, text, unit, least_words).select(F.col(key).alias("_of"), "said", F.struct(F.lit(False).alias("words"), "start", "length").alias("s"))
    if passages is not None:
        spans = spans.unionByName(passages.select(F.col("_id").alias("_of"), "said", F.struct(F.lit(True).alias("words"), "start", "length").alias("s")))
    s, o, h, t = (fresh(df, c) for c in ("_spans", "_of", "_said", "_hash"))
    by_doc = spans.groupBy(F.col("_of").alias(o), F.col("said").alias(h)).agg(F.collect_set("s").alias(s))
    hashed = df.withColumn(t, F.xxhash64(F.col(text).cast("string")))
    out = hashed.join(by_doc, hashed[key].eqNullSafe(by_doc[o]) & (hashed[t] == by_doc[h]), "left").drop(o, h, t)
    out = out.withColumn(text, F.when(F.col(s).isNull(), F.col(text)).otherwise(_cut(F.when(F.col(s).isNotNull(), F.col(text)), F.col(s)))).drop(s)
    if length:
        out = out.withColumn(length, F.char_length(F.coalesce(F.col(text), F.lit(""))).cast(df.schema[length].dataType))
    return out.select(df.columns)


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_units(table(spark, sf_dir, "documents").select("doc_id", "text"))


OP2_SQL = r"""
WITH lines AS (
  SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents
), units AS (
  SELECT doc_id, u - 1 AS unit, ls[u] AS line,
         list_sum(list_transform(ls[1:u - 1], lambda l: length(l) + 1)) AS before
  FROM (SELECT doc_id, ls, unnest(range(1, len(ls) + 1)) AS u FROM lines)
), norm AS (
  SELECT doc_id, unit, coalesce(before, 0) AS start, length(line) AS length,
         md5(lower(trim(regexp_replace(line, '[\x20\x09-\x0d]+', ' ', 'g'), ' '))) AS digest
  FROM units WHERE regexp_matches(line, '[^\x20\x09-\x0d]')
), ranked AS (
  SELECT *, first_value(doc_id) OVER w AS first_doc_id, row_number() OVER w AS nth
  FROM norm WINDOW w AS (PARTITION BY digest ORDER BY doc_id, unit)
)
SELECT doc_id, CAST(unit AS INTEGER) AS unit, CAST(start AS INTEGER) AS start, CAST(length AS INTEGER) AS length, first_doc_id
FROM ranked WHERE nth > 1
"""
