"""What the operators share: tables, settled intermediate results, column names, word hashes."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterable

import numpy as np
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words of a text: runs without ASCII white space.
WORD = re.compile(r"[^\x20\x09-\x0d]+")
#: Entries that a worker's memo of words may hold before it starts anew.
MEMO_WORDS = 400_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one in a local session that names none."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = f"file://{tempfile.mkdtemp(prefix='tokenfold-')}"
        spark.sparkContext.setCheckpointDir(root)
    return root


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write a result that is read more than once to the shared folder, and read it from there.

    A lost executor then costs no recomputation of what stands before, and what
    follows sees the same rows each time.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def fresh(df: DataFrame, name: str) -> str:
    """A column name that the frame does not have yet."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def bitmap(df: DataFrame, column: str, bits: int) -> np.ndarray:
    """Which places of a table of bits (a power of two) a column's hashes fall on, 64 to a number.

    Its size is fixed, however many rows there are: the fuller it is, the more strangers it lets through.
    """
    place, low = F.col(column).bitwiseAND(bits - 1), F.col(column).bitwiseAND(63).cast("int")
    rows = df.groupBy(F.shiftright(place, 6).alias("number")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), low)).alias("bits")).toArrow()
    out = np.zeros(bits >> 6, np.int64)
    out[rows.column("number").to_numpy()] = rows.column("bits").to_numpy()
    return out


def in_bitmap(seen: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    place = hashes & np.int64(64 * len(seen) - 1)
    return (seen[place >> 6] >> (place & 63) & 1).astype(bool)


class WordHashes:
    """64-bit hashes of words, remembered up to a fixed number of words."""

    def __init__(self, seed: int = 0, most: int = MEMO_WORDS):
        self.seed, self.most = seed, most
        self.memo: dict[str, int] = {}

    def __call__(self, words: list[str]) -> np.ndarray:
        memo = self.memo
        if len(memo) > self.most:
            memo.clear()
        got = list(map(memo.get, words))
        if None in got:
            digest, seed = xxhash.xxh3_64_intdigest, self.seed
            for i, h in enumerate(got):
                if h is None:
                    w = words[i]
                    got[i] = memo[w] = digest(w.encode("utf-8", "surrogatepass"), seed)
        return np.array(got, dtype=np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit integers (the finaliser of splitmix64)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def gram_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Hashes of all runs of n words, from the words' hashes; none if there are fewer."""
    m = len(words) - n + 1
    if m <= 0:
        return np.empty(0, np.uint64)
    out = words[:m].copy()
    for i in range(1, n):
        out = mix(out * np.uint64(0x9E3779B97F4A7C15) + words[i : i + m])
    return out


def texts(column: Iterable) -> list[str]:
    """Python strings of an Arrow or pandas column; null becomes the empty text."""
    return ["" if t is None or t != t else t for t in column]
