"""Operators against brute force over whole small corpora, and cases that earlier versions got wrong."""

import collections
import random

import numpy as np
import pytest

from tokenfold.llm import cgk_decontamination, chosen_path, line_dedup, sparse_suffixes
from tokenfold.llm.common import WORD

SCHEMA = "doc_id long, text string"


def words(rng, n, vocabulary=300):
    return [f"w{rng.randrange(vocabulary)}" for _ in range(n)]


# -- repeated passages --------------------------------------------------------------------------------------------


def spans_by_brute_force(rows, n):
    """Per distinct (key, text): the unions of overlapping windows of n words that stand twice."""
    docs = {(k, t): [w.lower() for w in WORD.findall(t or "")] for k, t in rows}
    seen = collections.defaultdict(set)
    for d, ws in docs.items():
        for i in range(len(ws) - n + 1):
            seen[tuple(ws[i : i + n])].add((d, i))
    out = []
    for (key, _), ws in docs.items():
        spans = []
        for i in range(len(ws) - n + 1):
            if len(seen[tuple(ws[i : i + n])]) > 1:
                if spans and i < spans[-1][1]:
                    spans[-1][1] = i + n
                else:
                    spans.append([i, i + n])
        out.extend((key, a, b - a) for a, b in spans)
    return sorted(out, key=repr)


@pytest.mark.parametrize("opts", [sparse_suffixes.Suffixes(), sparse_suffixes.Suffixes(words=20, window=8, run=3, group=3), sparse_suffixes.Suffixes(words=20, window=8, run=3, map_bits=64)])
def test_passages_are_those_of_brute_force(spark, opts):
    rng = random.Random(5)
    base, rows = [words(rng, 400) for _ in range(5)], []
    for i in range(60):
        ws = words(rng, rng.randrange(120))
        for _ in range(rng.randrange(4)):
            b, a = rng.choice(base), rng.randrange(300)
            ws += b[a : a + rng.randrange(10, 90)] + words(rng, rng.randrange(30))
        rows.append((i if i < 4 else rng.choice([i, i, 7, None]), " ".join(ws)))
    rows += [rows[3], rows[5], (200, rows[9][1]), (201, None), (202, ""), (203, " ".join(["a"] * 200))]
    got = sparse_suffixes.repeated_passages(spark.createDataFrame(rows, SCHEMA), opts=opts).collect()
    assert sorted(((r.doc_id, r.start_word, r.n_words) for r in got), key=repr) == spans_by_brute_force(rows, opts.words)


def test_overlapping_short_repeats_make_no_passage(spark):
    rng = random.Random(1)
    a, b = words(rng, 36, 10**6), words(rng, 38, 10**6)
    # 36 and 38 words repeat and touch in one text, in the others they stand apart
    rows = [(1, " ".join(a + b)), (2, " ".join(a + words(rng, 40, 10**6))), (3, " ".join(words(rng, 40, 10**6) + b))]
    assert sparse_suffixes.repeated_passages(spark.createDataFrame(rows, SCHEMA)).count() == 0


def test_later_copies_are_cut_and_the_first_stays(spark):
    rng = random.Random(2)
    shared = words(rng, 60, 10**6)
    texts = [" ".join(words(rng, 30, 10**6)) for _ in range(4)]
    rows = [(1, f"{texts[0]} {' '.join(shared)} {texts[1]}"), (2, f"{texts[2]}\n{' '.join(shared[:30])}\n{' '.join(shared[30:])} {texts[3]}"), (2, texts[0].upper()), (3, None)]
    df = spark.createDataFrame(rows, SCHEMA)
    got = line_dedup.drop_repeated_units(df, passages=sparse_suffixes.later_passages(df)).collect()
    kept = collections.Counter((r.doc_id, r.text) for r in got)
    assert kept == collections.Counter([rows[0], (2, f"{texts[2]}\n{texts[3]}"), rows[2], rows[3]])


# -- benchmark passages -------------------------------------------------------------------------------------------


def edited(rng, text, share):
    """The same text with a share of edits of all kinds at random places."""
    t = list(text)
    for _ in range(int(share * len(text))):
        i, kind = rng.randrange(len(t)), rng.randrange(3)
        t[i : i + (kind < 2)] = [rng.choice("abcdefghijklmnopqrstuvwxyz ")][: kind != 1]
    return "".join(t)


def prose(rng, n):
    return " ".join("".join(rng.choice(("an", "er", "the", "ou", "st", "in", "ing", "ly", "o", "re")) for _ in range(rng.randrange(1, 4))) for _ in range(n))


def distance(item, text):
    """Least edit distance of an item to any part of a text, row by row."""
    row = np.zeros(len(text) + 1, int)
    for i, c in enumerate(item, 1):
        new = np.empty_like(row)
        new[0] = i
        same = np.array([c != d for d in text], int)
        best = np.minimum(row[:-1] + same, row[1:] + 1)
        for j in range(1, len(row)):
            new[j] = min(best[j - 1], new[j - 1] + 1)
        row = new
    return row.min()


@pytest.mark.parametrize("length", [4, 9, 15, 23, 47, 80, 110])
def test_short_items_are_found_as_by_brute_force(length):
    rng = random.Random(length)
    items = [(i, prose(rng, 40)[:length]) for i in range(12)]
    docs = [prose(rng, 30) + edited(rng, items[i % 12][1], share) + prose(rng, 30) for i, share in enumerate([0.0, 0.1, 0.2, 0.25] * 6)]
    opts = cgk_decontamination.Walks()
    got = {(d, i): e for d, i, e, _, _ in cgk_decontamination.Items(items, opts)(docs)}
    want = {}
    for d, text in enumerate(docs):
        for i, (_, item) in enumerate(items):
            if (e := distance(cgk_decontamination.folded(item), cgk_decontamination.folded(text))) <= int(opts.edits * len(item)):
                want[d, i] = e
    assert got == want


def test_runs_count_only_near_their_place():
    rng = random.Random(3)
    item, other = "".join(rng.choice("abcdefghijklm") for _ in range(100)), "".join(rng.choice("nopqrstuvwxyz") for _ in range(400))
    short = cgk_decontamination.ShortItems([(0, item)], 0.2)
    # the first quarter has enough runs, but a passage that starts over 70 characters before it and the blocks' width can't use them
    _, about, half = short(cgk_decontamination._symbols(other[:200] + item[:25] + other[200:]))
    assert len(about) and (about - half).min() >= 200 - 70 - cgk_decontamination.ShortItems.BLOCK
    _, about, half = short(cgk_decontamination._symbols(other[:203] + item + other[203:]))
    assert ((about - half <= 203) & (203 < about + half)).any()


def test_the_bound_leaves_every_passage():
    rng = random.Random(8)
    items = [prose(rng, 120)[:n] for n in (20, 63, 64, 65, 128, 129, 300)]
    bounds = cgk_decontamination.PartBounds(items, 0.2)
    item = np.repeat(np.arange(len(items)), 40)
    docs = [prose(rng, 9) + edited(rng, items[i], 0.01 * k) + prose(rng, 9) for i in range(len(items)) for k in range(40)]
    pad = prose(rng, 60)
    symbols, about = cgk_decontamination._symbols("".join(pad + d for d in docs) + pad), []
    at = 0
    for d in docs:
        about.append(at + len(pad) + len(d) // 4)
        at += len(pad) + len(d)
    left = set(bounds(item, symbols, np.array(about), np.array([len(d) // 2 for d in docs]), step=64).tolist())
    near = {k for k, d in enumerate(docs) if distance(items[item[k]], d) <= int(0.2 * len(items[item[k]]))}
    assert near <= left and len(near) > 120 and len(left) < len(docs)


def test_portions_hold_every_row_once():
    column = ["", "ab", "abcdefgh", "a", "", "abc", "abcd"]
    got = list(cgk_decontamination._portions(column, 4))
    assert [t for _, own in got for t in own] == column
    assert all(column[low : low + len(own)] == own and (len(own) == 1 or sum(map(len, own)) <= 4) for low, own in got)
    assert list(cgk_decontamination._portions([], 4)) == []


@pytest.mark.parametrize("share", [0.1, 0.2])
def test_recall_at_the_limit_of_edits(share):
    rng = random.Random(int(100 * share))
    items = [(i, prose(rng, rng.randrange(9, 61))) for i in range(240)]
    docs = [f"{prose(rng, 50)} {edited(rng, t, share)} {prose(rng, 50)}" for _, t in items]
    found = {(d, i) for d, i, *_ in cgk_decontamination.Items(items, cgk_decontamination.Walks())(docs)}
    assert np.mean([(i, i) in found for i in range(240)]) >= 0.97


def test_nothing_is_found_in_other_texts():
    rng = random.Random(9)
    items = [(i, prose(rng, 30)) for i in range(30)]
    docs = ["", "x", prose(rng, 3), *(prose(rng, 200) for _ in range(10))]
    block = cgk_decontamination.Items([*items, (99, None), (100, "")], cgk_decontamination.Walks())
    for d, i, edits, start, end in block(docs):  # short syllables may meet by chance, but never beyond the limit
        assert edits <= 0.2 * len(items[i][1]) and distance(items[i][1], docs[d][start:end]) == edits


# -- Jaccard join -------------------------------------------------------------------------------------------------


def test_a_recall_that_the_values_cannot_reach_is_refused():
    with pytest.raises(ValueError, match="values"):
        chosen_path.Join(least=0.3)
    assert chosen_path.Join(least=0.3, values=256).runs > 32


@pytest.mark.parametrize(("least", "changes"), [(0.8, 0.012), (0.8, 0.02), (0.6, 0.05)])
def test_recall_of_pairs_end_to_end(spark, least, changes):
    """Near copies at all similarities around the least one: every pair that brute force links is in one class."""
    rng, rows = random.Random(4), []
    for i in range(120):
        ws = words(rng, 200, 10**6)
        rows.append((2 * i, " ".join(ws)))
        rows.append((2 * i + 1, " ".join(w if rng.random() > changes else "x" for w in ws)))

    def grams(t):
        w = t.split()
        return {tuple(w[k : k + 5]) for k in range(len(w) - 4)}

    want = set()
    for i in range(120):
        a, b = grams(rows[2 * i][1]), grams(rows[2 * i + 1][1])
        if len(a & b) >= least * len(a | b):
            want.add(2 * i)
    opts = chosen_path.Join(least=least, values=64 if least == 0.8 else 128)
    got = {r.doc_id: r for r in chosen_path.similar_documents(spark.createDataFrame(rows, SCHEMA), opts=opts).collect()}
    joined = {2 * i for i in range(120) if got[2 * i + 1].class_id == 2 * i}
    assert joined <= want
    assert len(joined) >= 0.99 * len(want) and len(want) > 10


def test_hubs_and_chains_join(spark):
    from tokenfold.llm.components import components

    star = [(0, k) for k in range(1, 400)]
    chain = [(k, k + 1) for k in range(1000, 1060)]
    got = {r.node: r.root for r in components(spark.createDataFrame(star + chain + [(5, 5)], "a long, b long")).collect()}
    assert {got[k] for k in range(400)} == {0}
    assert {got[k] for k in range(1000, 1061)} == {1000}
