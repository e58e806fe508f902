"""The pipeline's stages, each on its own input, against brute force on a small corpus with planted cases."""

import collections
import random

import pytest

pipeline = pytest.importorskip("corpus_pipeline")

from tokenfold.llm import compression_bands
from tokenfold.llm.common import WORD

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
SYLLABLES = ("an", "er", "the", "ou", "st", "in", "ing", "ly", "o", "re", "mi", "ka", "lu", "ve", "ba", "tion", "qua", "ri", "sel", "dom")


def words(rng, n):
    return ["".join(rng.choice(SYLLABLES) for _ in range(rng.randrange(2, 5))) for _ in range(n)]


def text(rng, n=160):
    out, ws = [], words(rng, n)
    while ws:
        k = rng.randrange(6, 14)
        out.append(" ".join(ws[:k]).capitalize() + ".")
        ws = ws[k:]
    return "\n".join(" ".join(out[i : i + 2]) for i in range(0, len(out), 2))


@pytest.fixture(scope="module")
def planted():
    """Rows and benchmark items: clean texts, copies, near copies, shared lines and passages, junk, leaks, nulls."""
    rng = random.Random(11)
    clean = [text(rng) for _ in range(12)]
    items = [(i, " ".join(words(rng, 25))) for i in range(4)]
    passage, line = " ".join(words(rng, 70)), " ".join(words(rng, 9))
    near = clean[1].split(" ")
    near[20] = "other"
    made = {i: t for i, t in enumerate(clean)}
    made |= {20: clean[0], 21: clean[0], 22: " ".join(near)}
    made |= {30: f"{text(rng)} {passage} {text(rng, 60)}", 31: f"{text(rng, 60)} {passage} {text(rng)}", 32: f"{text(rng)}\n{line}\n{text(rng, 60)}", 33: f"{line}\n{text(rng)}"}
    made |= {40: f"{text(rng)} {items[0][1]} {text(rng, 60)}", 41: f"{items[1][1].replace('a', 'e', 3)}\n{text(rng)}"}
    made |= {50: " ".join(["spam and eggs"] * 200), 51: "too short", 52: None, 53: ""}
    rows = [(k, t, "en", None if k % 2 else "web", None if t is None else len(t)) for k, t in made.items()]
    rows += [rows[3], (4, text(rng), None, "other text of a key", None), (None, text(rng), "en", "no key", 1)]
    return rows, items


@pytest.fixture
def folder(spark, planted, tmp_path):
    rows, items = planted
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    return str(tmp_path)


def bag(rows):
    return collections.Counter(tuple(r) for r in rows)


def grams(t):
    w = [x.lower() for x in WORD.findall(t)]
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def test_stages_return_documents(spark, folder, planted):
    rows, items = planted
    docs = spark.createDataFrame(rows, SCHEMA)
    stages = dict(pipeline.STAGES)
    assert list(stages) == ["quality rules", "n-gram Jaccard join", "substring dedup", "benchmark decontamination", "packing"]

    meter = compression_bands.Meter(compression_bands.Bands())
    kept = [r for r in rows if meter(r[1] or "")[6]]
    got = stages["quality rules"](spark, docs, folder)
    assert got.columns == docs.columns and bag(got.collect()) == bag(kept)
    assert {r[0] for r in rows} - {r[0] for r in kept} == {50, 51, 52, 53}

    # one text of each class of pairs at 0.8 or more, that of the least key
    texts = sorted({(r[0] is None, r[0] or 0, r[1]) for r in kept})
    sets, root = [grams(t) for *_, t in texts], list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                root = [root[j] if x == root[i] else x for x in root]
    heads = {texts[min(i for i in range(len(texts)) if root[i] == r)] for r in set(root)}
    distinct = {r for r in kept if (r[0] is None, r[0] or 0, r[1]) in heads}
    got = stages["n-gram Jaccard join"](spark, spark.createDataFrame(kept, SCHEMA), folder)
    assert got.columns == docs.columns and bag(got.collect()) == bag(distinct)
    assert not {20, 21, 22} & {r[0] for r in distinct}

    # texts without a repeat stay as they are; later copies of lines and passages go
    got = stages["substring dedup"](spark, spark.createDataFrame(sorted(distinct, key=repr), SCHEMA), folder)
    after = {(r.doc_id, r.source): r for r in got.collect()}
    assert len(after) == len(distinct) and got.columns == docs.columns
    for r in distinct:
        new = after[r[0], r[3]]
        assert new.n_chars == len(new.text)
        if r[0] in (31, 33):
            said = WORD.findall(r[1])
            left = WORD.findall(new.text)
            assert len(said) - len(left) == {31: 70, 33: 9}[r[0]]
        else:
            assert new.text == r[1]

    cleaned = [tuple(r) for r in after.values()]
    got = stages["benchmark decontamination"](spark, spark.createDataFrame(cleaned, SCHEMA), folder)
    assert got.columns == docs.columns and bag(got.collect()) == bag(r for r in cleaned if r[0] not in (40, 41))

    last = [r for r in cleaned if r[0] not in (40, 41)]
    pieces = stages["packing"](spark, spark.createDataFrame(last, SCHEMA), folder).collect()
    tokens = {r.doc_id: r.doc_tokens for r in pieces if r.doc_id != 4}
    held = collections.Counter()
    for r in pieces:
        held[r.doc_id] += r.length
        assert r.offset + r.length <= 2048
    assert {k: held[k] for k in tokens} == tokens and set(held) == {r[0] for r in last}


def test_whole_run(spark, folder, planted):
    rows, _ = planted
    got = pipeline.run(spark, folder).collect()
    assert {r.doc_id for r in got} == {r[0] for r in rows} - {20, 21, 22, 40, 41, 50, 51, 52, 53}


def test_run_over_nothing(spark, tmp_path):
    spark.createDataFrame([], SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert pipeline.run(spark, str(tmp_path)).count() == 0
