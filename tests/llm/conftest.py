import random

import pytest
from pyspark.sql import types as T

DOCS = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()),
    T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType()),
])
SYLLABLES = "an be cor dal en fir gon hal is jor kel lum mar nos ot per qui ras sel tur ur ves wyn".split()


def prose(rng: random.Random, words: int) -> str:
    out = []
    for i in range(words):
        w = "".join(rng.choice(SYLLABLES) for _ in range(rng.randint(1, 3)))
        out.append(w + (".\n" if i % 17 == 16 else " "))
    return "".join(out).rstrip(" ")


def edited(rng: random.Random, text: str, words: int) -> str:
    ws = text.split(" ")
    for i in rng.sample(range(len(ws)), min(words, len(ws))):
        ws[i] = "".join(rng.choice(SYLLABLES) for _ in range(3))
    return " ".join(ws)


def row(i, text, lang="en", source="s", n=None):
    return (i, text, lang, source, len(text or "") if n is None else n)


@pytest.fixture(scope="session")
def corpus(spark):
    """Prose with copies, near copies, a shared passage, and rows with nulls, no text and one very long text."""
    rng = random.Random(7)
    base = [prose(rng, rng.randint(60, 300)) for _ in range(30)]
    passage = prose(rng, 70).replace("\n", " ")
    rows = [row(i, t) for i, t in enumerate(base)]
    rows += [row(100 + i, base[3]) for i in range(12)]
    rows += [row(200 + i, edited(rng, base[5], 2)) for i in range(10)]
    rows += [row(300 + i, prose(rng, 40) + "\n" + passage + "\n" + prose(rng, 30)) for i in range(4)]
    rows += [row(400, None), row(401, ""), row(402, " \n\t"), row(403, "one two"), row(404, "one two"), (405, base[7], None, None, None), (None, base[8], "en", "s", 3)]
    rows += [row(500, prose(rng, 9000)), row(6, base[6])]
    return rows


@pytest.fixture(scope="session")
def docs(spark, corpus):
    return spark.createDataFrame(corpus, DOCS)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], DOCS)
