"""Each operator against brute force, and on nulls, empty tables, ties, repeated rows and clashing names."""

import collections
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
import zstandard
from pyspark.sql import functions as F
from tokenizers import Tokenizer, models, pre_tokenizers

import public_tokenizers
import sentencepiece
from tests.llm.conftest import DOCS, edited, prose, row
from tokenfold.llm import cgk_decontamination, chosen_path, compression_bands, cotraining, licence_scan, line_dedup, packing, piece_counts, sharding, sparse_suffixes
from tokenfold.llm.common import WORD
from tokenfold.llm.components import components


def clash(df):
    return df.withColumns({c: F.lit("x") for c in ("_id", "_text", "shard", "slot", "kept", "size", "unit", "node", "lead", "ids", "_spans", "_verdict", "_key", "m")})


# -- packing ------------------------------------------------------------------------------------------------------


def word_ids(text):
    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    return np.array([*t.encode(text or "", add_special_tokens=False).ids, 1], "<u4")


def test_packing_holds_every_id_once(docs, corpus):
    pieces, sequences = collections.defaultdict(list), collections.defaultdict(list)
    want = collections.Counter((r[0], word_ids(r[1]).tobytes()) for r in corpus)
    for r in packing.pack(clash(docs), opts=packing.Packing(shard_tokens=4000)).collect():
        pieces[r["doc_id"], r["doc_tokens"]].append((r["start"], r["length"], bytes(r["ids"])))
        sequences[r["sequence_id"]].append((r["offset"], r["length"]))
        assert len(r["ids"]) == 4 * r["length"]
    for (key, ids), copies in want.items():
        own = sorted(pieces[key, len(ids) // 4])
        assert sum(n for _, n, _ in own) == copies * len(ids) // 4
        for start, n, got in own:
            assert got == ids[4 * start : 4 * (start + n)]
    for parts in sequences.values():
        at = 0
        for offset, n in sorted(parts):
            assert offset == at
            at += n
        assert at == 2048 or at & (at - 1) == 0


def test_packing_of_nothing(no_docs):
    assert packing.pack(no_docs).count() == 0


def test_words_are_tokenised_as_whole_texts():
    rng, words = random.Random(3), packing.WordIds(public_tokenizers.path("word_bpe_49k.json"))
    batch = ["", " ", "a\x1cb", "x<|endoftext|>y", "É é́", "İstanbul ΣΑΣ'S can't", "日本語 123 ½"]
    batch += ["".join(rng.choice("ab'st́ \x85\x1cİ<|>1½\n") for _ in range(30)) for _ in range(200)]
    for text, got in zip(batch, words(pa.array(batch))[1].to_pylist(), strict=True):
        assert np.frombuffer(got, words.dtype).tolist() == words.tokenizer.encode(text, add_special_tokens=False).ids


def test_neighbours_share_a_window():
    weights = packing.Weights(np.full(100, 3), 10, 8, packing.Packing())
    a, b = np.array([1, 2, 3, 4], "<u2"), np.array([50, 51, 52, 53], "<u2")
    windows = packing.fill_windows([a, b, a + 0, b + 0], weights, 8)
    assert [sorted(p for p, _, _ in w) for w in windows] == [[0, 2], [1, 3]]


# -- line deduplication -------------------------------------------------------------------------------------------


def test_lines_are_found_as_by_brute_force(docs, corpus):
    seen, want = {}, set()
    for key, text in sorted({(r[0], r[1]) for r in corpus if r[1]}, key=lambda r: (r[0] is None, r[0] or 0)):
        at = 0
        for i, line in enumerate(text.split("\n")):
            plain = " ".join(WORD.findall(line)).lower()
            if plain:
                first = seen.setdefault(plain, (key, i))
                if first != (key, i):
                    want.add((key, i, at, len(line), first[0]))
            at += len(line) + 1
    got = {tuple(r) for r in line_dedup.repeated_units(clash(docs)).collect()}
    assert got == want


def test_lines_are_cut_and_columns_stay(spark, docs, no_docs):
    small = spark.createDataFrame([row(1, "Same line\nown a"), row(2, "same  LINE\nown b\nSame line"), row(3, None), row(2, "same  LINE\nown b\nSame line")], DOCS)
    out = line_dedup.drop_repeated_units(clash(small), length="n_chars")
    assert out.columns == clash(small).columns
    assert sorted((r["doc_id"], r["text"], r["n_chars"]) for r in out.collect() if r["text"] is not None) == [(1, "Same line\nown a", 15), (2, "own b\n", 6), (2, "own b\n", 6)]
    assert line_dedup.repeated_units(no_docs).count() == 0
    assert line_dedup.units("a b\n \nA  B\nc", "paragraph") == [(0, 0, 3, line_dedup.units("a b")[0][3]), (1, 6, 6, line_dedup.units("a b c")[0][3])]


# -- decontamination ----------------------------------------------------------------------------------------------


def plain_distance(a, b):
    before = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        now = [i]
        for j, y in enumerate(b, 1):
            now.append(min(before[j] + 1, now[-1] + 1, before[j - 1] + (x != y)))
        before = now
    return before[-1]


def test_edit_distance_is_exact():
    rng = random.Random(1)
    for _ in range(60):
        a, b = ("".join(rng.choice("abc") for _ in range(rng.randint(1, n))) for n in (9, 12))
        want = min((plain_distance(a, b[s:e]), e) for s in range(len(b) + 1) for e in range(s, len(b) + 1))
        assert cgk_decontamination.EditDistance(a).nearest(b)[0] == want[0]
        assert cgk_decontamination.EditDistance(a).nearest(b, True)[0] == min(plain_distance(a, b[:e]) for e in range(len(b) + 1))


@pytest.mark.parametrize(("share", "recall"), [(0, 1.0), (0.05, 0.98), (0.1, 0.97), (0.2, 0.85)])
def test_recall_under_edits(share, recall):
    rng = random.Random(5)
    items = [(i, prose(rng, rng.randint(14, 60)).replace("\n", " ")) for i in range(60)]
    batch = []
    for _, t in items:
        chars = list(t)
        for _ in range(int(share * len(t))):
            chars[rng.randrange(len(chars))] = rng.choice("aeiou ")
        batch.append(prose(rng, 50) + " " + "".join(chars) + " " + prose(rng, 50))
    found = cgk_decontamination.Items(items, cgk_decontamination.Walks())(batch)
    assert sum((i, i) in {f[:2] for f in found} for i in range(len(items))) >= recall * len(items)
    for d, i, edits, start, end in found:
        item = items[i][1]
        assert plain_distance(item, cgk_decontamination.folded(batch[d])[start:end]) == edits <= 0.2 * len(item)


@pytest.mark.parametrize(("length", "recall"), [(30, 1.0), (60, 1.0), (90, 1.0), (150, 0.95), (260, 0.95)])
def test_recall_with_all_edits_of_all_kinds(length, recall):
    rng = random.Random(length)
    items = [(i, prose(rng, 80).replace("\n", " ")[:length]) for i in range(60)]
    batch, near = [], set()
    for i, t in items:
        chars = list(t)
        for _ in range(int(0.2 * length)):
            at, kind = rng.randrange(len(chars)), rng.randrange(3)
            chars[at : at + (kind < 2)] = [rng.choice("aeioux")][: kind != 1]
        batch.append(prose(rng, 50) + " " + "".join(chars) + " " + prose(rng, 50))
        near.add((i, i))
    found = {f[:2] for f in cgk_decontamination.Items(items, cgk_decontamination.Walks())(batch)}
    assert len(found & near) >= recall * len(near)


def test_contaminated_rows_go_and_clean_ones_stay(spark, docs, no_docs, corpus):
    rng = random.Random(9)
    items = spark.createDataFrame([(1, corpus[0][1][:150]), (2, None), (3, ""), (4, prose(rng, 40)), (5, "a short item of words")], "item_id long, text string")
    dirty = spark.createDataFrame([row(1000, prose(rng, 30) + "A Short item of words" + prose(rng, 30))], DOCS)
    both = docs.unionByName(dirty)
    hits = {(r["doc_id"], r["item_id"]): r["edits"] for r in cgk_decontamination.contaminated(clash(both), items).collect()}
    assert hits == {(0, 1): 0, (1000, 5): 0}
    kept = cgk_decontamination.drop_contaminated(both, items)
    assert kept.columns == both.columns
    assert kept.count() == both.count() - 2
    assert cgk_decontamination.contaminated(no_docs, items).count() == 0
    assert cgk_decontamination.drop_contaminated(docs, items.limit(0)).count() == docs.count()


# -- compression bands --------------------------------------------------------------------------------------------


def test_base_counts(spark, docs, corpus, no_docs):
    got = {(r["doc_id"]): r for r in docs.select("doc_id", compression_bands.verdict("text").alias("v")).select("doc_id", "v.*").collect()}
    for key, text, *_ in corpus:
        words = WORD.findall(text or "")
        grams = collections.Counter(zip(words, words[1:], words[2:], strict=False))
        covered = {i + k for i in range(len(words) - 2) if grams[tuple(words[i : i + 3])] > 1 for k in range(3)}
        lines, dup = set(), 0
        for line in (text or "").split("\n"):
            dup += bool(WORD.search(line)) and line in lines
            lines.add(line)
        r = got[key]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text or ""), dup, len(covered))
        assert r["base_failed"] == (len(words) < 50 or 100 * len(covered) > 50 * len(words))
        assert not (r["base_failed"] and r["kept"])
        if text and WORD.search(text):
            data = text.encode()
            assert r["ratio"] == len(zstandard.ZstdCompressor(level=3).compress(data)) / len(data)
    assert no_docs.select(compression_bands.verdict("text")).count() == 0


def test_bands_reject_both_ends():
    rng = random.Random(2)
    meter, names = compression_bands.Meter(compression_bands.Bands()), compression_bands.SCHEMA.names
    assert dict(zip(names, meter(prose(rng, 400)), strict=True))["kept"]
    noise = " ".join("".join(rng.choice("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/") for _ in range(60)) for _ in range(80))
    assert dict(zip(names, meter(noise), strict=True))["reason"] == "incompressible"
    table = " ".join(f"key{i} value{i} |" for i in range(300))
    assert dict(zip(names, meter(table), strict=True))["reason"] == "repetitive"
    mixed = prose(rng, 3000) + " ".join(f"row{i} cell{i} |" for i in range(900))
    assert dict(zip(names, meter(mixed), strict=True))["kept"] is False


def test_good_rows_keep_their_columns(docs):
    out = compression_bands.keep_good(clash(docs))
    assert out.columns == clash(docs).columns
    assert 0 < out.count() < docs.count()


def test_repeats_in_texts_of_many_words():
    words = [str(i) for i in range(3000)] + ["1", "2", "3"]
    assert compression_bands.repeated_words(words) == 6
    assert compression_bands.repeated_words(["a"] * 5) == 5
    assert compression_bands.repeated_words(["a", "b", "c"]) == 0


# -- Jaccard join -------------------------------------------------------------------------------------------------


def shingles(text):
    w = WORD.findall((text or "").lower())
    n = min(5, len(w))
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set()


def brute_links(rows):
    sets = [shingles(t) for t in (r[1] for r in rows)]
    links = [0] * len(rows)
    up = list(range(len(rows)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a and b and len(a & b) >= 0.8 * len(a | b) - 1e-9:
                links[i] += 1
                links[j] += 1
                x, y = find(i), find(j)
                up[max(x, y)] = min(x, y)
    heads = {}
    for i, r in enumerate(rows):
        k = (r[0] is None, r[0])
        heads[find(i)] = min(heads.get(find(i), k), k, key=lambda x: (x[0], x[1] or 0))
    return collections.Counter((r[0], heads[find(i)][1], links[i]) for i, r in enumerate(rows))


@pytest.mark.parametrize("opts", [chosen_path.Join(), chosen_path.Join(bucket=4, block=5, depth=3)])
def test_join_finds_what_brute_force_finds(docs, corpus, opts):
    got = collections.Counter((r["doc_id"], r["class_id"], r["n_links"]) for r in chosen_path.similar_documents(clash(docs), opts=opts).collect())
    assert got == brute_links(corpus)


def test_one_of_each_class_stays(docs, no_docs, corpus):
    out = chosen_path.drop_similar(clash(docs))
    assert out.columns == clash(docs).columns
    kept = collections.Counter(r["doc_id"] for r in out.collect())
    classes = {c for _, c, _ in brute_links(corpus)}
    assert set(kept) == classes
    assert set(kept.values()) == {1}
    assert chosen_path.similar_documents(no_docs).count() == 0


def test_other_texts_under_a_key_stay(spark):
    rng = random.Random(11)
    a, b, near = prose(rng, 200), prose(rng, 200), None
    near = edited(rng, b, 1)
    rows = [row(5, a), row(5, b), row(7, near), row(5, b, "fr"), row(9, a), row(None, b), row(None, a + " " + near)]
    for order in (rows, rows[::-1]):
        kept = [(r["doc_id"], r["text"], r["lang"]) for r in chosen_path.drop_similar(clash(spark.createDataFrame(order, DOCS))).collect()]
        assert sorted(kept[: len(kept)], key=str) == sorted([(5, a, "en"), (5, b, "en"), (None, a + " " + near, "en")], key=str)


def test_lines_of_other_texts_under_a_key_stay(spark):
    rows = [row(1, "One line\nown a"), row(2, "one LINE\nown b"), row(2, "own c\nown d"), row(3, "x y\nown e"), row(3, "x y\nown f")]
    got = [r["text"] for r in line_dedup.drop_repeated_units(clash(spark.createDataFrame(rows, DOCS))).collect()]
    assert got.count("own b") == 1 and "own c\nown d" in got and "One line\nown a" in got
    assert sorted(got)[-2:] in (["own f", "x y\nown e"], ["own e", "x y\nown f"])


def test_runs_reach_the_recall():
    rng, opts = random.Random(4), chosen_path.Join()
    assert opts.runs <= opts.values // 2
    hashes, hit, n = chosen_path.WordHashes(), 0, 200
    for _ in range(n):
        a = prose(rng, 120)
        b = edited(rng, a, 2)
        x, y = (chosen_path.minhash(chosen_path.grams(t, hashes, 5), opts.values) for t in (a, b))
        hit += bool((x[: opts.runs] == y[: opts.runs]).any())
    assert hit == n


def test_intersections():
    rng = np.random.default_rng(1)
    sets = [np.unique(rng.integers(0, 60 * (i + 1), 50)).astype(np.uint64) for i in range(40)]
    got = chosen_path.intersections(sets, heavy=0.3)
    for i, a in enumerate(sets):
        for j, b in enumerate(sets):
            if i != j:
                assert got[i, j] == len(np.intersect1d(a, b))


def test_components(spark):
    rng = random.Random(8)
    edges = [(rng.randint(0, 300), rng.randint(0, 300)) for _ in range(200)] + [(i, i + 1) for i in range(1000, 1040)]
    up = {}
    find = lambda x: x if up.setdefault(x, x) == x else find(up[x])
    for a, b in edges:
        x, y = find(a), find(b)
        up[max(x, y)] = min(x, y)
    want = {x: find(x) for a, b in edges if a != b for x in (a, b)}
    assert {r["node"]: r["root"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()} == want


# -- co-training --------------------------------------------------------------------------------------------------


def test_co_training_on_held_out_rows(spark):
    rng = random.Random(11)
    rows, labels = [], []
    for i in range(600):
        bad = i % 4 == 0
        text = prose(rng, 60)
        if bad:
            text = " ".join(rng.choice(["worthless", "junk"]) if rng.random() < 0.05 else w for w in text.split(" ")) + " junk"
        rows.append(row(i, text, "xx" if bad and rng.random() < 0.7 else "en", f"s{i % 3}"))
        if i < 300:
            labels.append((i, int(bad)))
    docs = spark.createDataFrame([*rows, row(900, None), (901, "x", None, None, None)], DOCS)
    labels = spark.createDataFrame([*labels, (5, None), (None, 1)], "doc_id long, bad int")
    opts = cotraining.CoTraining(bits=12, labelled=250, pool=200, gives=30)
    got = {r["doc_id"]: r for r in cotraining.classify(clash(docs), labels, ["bad"], opts=opts).collect()}
    right = sum((got[i]["bad"] >= 0.5) == (i % 4 == 0) for i in range(300, 600))
    assert right >= 285
    assert len(got) == 602
    none = cotraining.classify(docs, labels.limit(0), ["bad"], opts=opts).select("bad").distinct().collect()
    assert len(none) == 1


def test_all_unlabelled_documents_take_part(spark):
    """One document of which the text view is sure, behind more others than any fixed pool held."""
    rng = random.Random(8)
    good, bad = "fine words of calm prose", "vile shouting rubbish noise"
    rows = [(i, f"{good if i % 2 else bad} {prose(rng, 3)}", "en", "s", 40) for i in range(400)]
    rows += [(1000 + i, "", "en", "s", 0) for i in range(5000)]
    labels = spark.createDataFrame([(i, i % 2) for i in range(200)], "doc_id long, quality int")
    frame = spark.createDataFrame(rows, DOCS)
    opts = cotraining.CoTraining(rounds=1, gives=300)
    pair = cotraining.fit_views(frame, labels, ["quality"], opts=opts)["quality"]
    assert pair.given[0] >= 190


def test_views_give_each_other_examples():
    rng = np.random.default_rng(0)
    y = (np.arange(400) % 2).astype(float)
    rows = [np.array([int(v), 2 + int(rng.integers(20))]) for v in y]
    opts = cotraining.CoTraining(bits=6, gives=10)
    pair = cotraining.co_train(rows, rows, y, rows[:100], rows[:100], opts)
    assert min(pair.given) > 0
    assert ((pair(rows, rows)[0] >= 0.5) == (y > 0)).mean() > 0.99


# -- sparse suffix arrays -----------------------------------------------------------------------------------------


def covered(rows, n):
    """Places of each (key, text) in a passage of n words that stands twice."""
    places = collections.defaultdict(list)
    for key, text in rows:
        w = WORD.findall((text or "").lower())
        for i in range(len(w) - n + 1):
            places[tuple(w[i : i + n])].append((key, text, i))
    out = collections.defaultdict(set)
    for where in places.values():
        if len(where) > 1:
            for key, text, i in where:
                out[key, text].update(range(i, i + n))
    return out


def test_repeated_passages_are_covered(docs, no_docs, corpus):
    rows = {(r[0], r[1]) for r in corpus}
    opts = sparse_suffixes.Suffixes()
    got = collections.defaultdict(list)
    for r in sparse_suffixes.repeated_passages(clash(docs)).collect():
        assert r["n_words"] >= opts.words
        assert r["doc_id"] is None or r["first_doc_id"] <= r["doc_id"]
        got[r["doc_id"]].extend(range(r["start_word"], r["start_word"] + r["n_words"]))
    want = collections.defaultdict(list)
    for (key, _), places in covered(rows, opts.words).items():
        want[key].extend(places)
    assert {k: sorted(v) for k, v in got.items()} == {k: sorted(v) for k, v in want.items()}
    assert {300, 301, 302, 303} <= set(got)
    assert sparse_suffixes.repeated_passages(no_docs).count() == 0


def test_core_hashes_depend_on_the_words_alone():
    rng = np.random.default_rng(2)
    w = rng.integers(0, 2**63, 60).astype(np.uint64)
    doubled = np.concatenate([w, w])
    got = sparse_suffixes.core_hashes(doubled, np.array([3, 63, 4]), 26)
    assert got[0] == got[1] != got[2]


# -- token counts -------------------------------------------------------------------------------------------------


def test_piece_counts_equal_the_tokenizer(docs, corpus):
    pieces = piece_counts.vocabulary(public_tokenizers.path("piece_bpe_32k.model"))
    whole = Tokenizer(models.Unigram(pieces, 0, True))
    whole.pre_tokenizer = pre_tokenizers.Metaspace(replacement=piece_counts.MARK, prepend_scheme="always", split=True)
    got = {r["doc_id"]: r["c"]["n_tokens"] for r in clash(docs).select("doc_id", piece_counts.piece_count("text").alias("c")).collect()}
    for key, text, *_ in corpus:
        assert got[key] == len(whole.encode(text or "", add_special_tokens=False).ids)
    counter = piece_counts.PieceCounter(pieces)
    for text in ["", " ", "  ", "a  b", "▁", "▁a ▁", "日本語 テスト", "x\n\ny <s> <0x0A>", " lead", "trail ", "\U0001f600é́", "ﷺ", "a b"]:
        assert counter(text)[1] == len(whole.encode(text, add_special_tokens=False).ids), text


def test_op8_counts_are_a_unigram_tokenizers_and_the_models_own(spark, corpus, tmp_path):
    path = public_tokenizers.path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    whole = Tokenizer(models.Unigram(piece_counts.vocabulary(path), 0, True))
    whole.pre_tokenizer = pre_tokenizers.Metaspace(replacement=piece_counts.MARK, prepend_scheme="always", split=True)
    odd = ["<s> </s>", "x\n\ny <s> <0x0A>", " lead  trail ", "日本語 \U0001f600", "The unbelievable tokenisation of words"]
    rows = [(i, r[1]) for i, r in enumerate(corpus)] + [(1000 + i, t) for i, t in enumerate(odd)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["doc_id"]: (r["n_tokens"], r["model_tokens"]) for r in piece_counts.op8_viterbi_counts(spark, str(tmp_path)).collect()}
    assert got == {i: (len(whole.encode(t or "", add_special_tokens=False).ids), len(sp.encode(t or ""))) for i, t in rows}


def test_ties_go_to_the_earlier_start():
    pieces = [("<unk>", 0.0), ("▁", -1.0), ("a", -1.0), ("b", -1.0), ("c", -2.0), ("ab", -2.0), ("bc", -3.0), ("abc", -4.0), ("▁a", -2.0)]
    ours, theirs = piece_counts.PieceCounter(pieces), Tokenizer(models.Unigram(pieces, 0, False))
    theirs.pre_tokenizer = pre_tokenizers.Metaspace(replacement="▁", prepend_scheme="always", split=True)
    rng = random.Random(6)
    for _ in range(200):
        text = "".join(rng.choice("abc ") for _ in range(12))
        assert ours(text)[1] == len(theirs.encode(text).ids), text


# -- licences -----------------------------------------------------------------------------------------------------


def test_licences_as_by_brute_force(spark, docs, no_docs):
    scanner = licence_scan.Scanner()
    mit = "Copyright (c) 2020 Someone\n\n" + licence_scan.TEMPLATES["MIT"].replace("\n", " ").replace("sublicense", "relicense")
    rows = ["Prose here.\nReleased under the MIT License.\nMore prose.", mit, licence_scan.TEMPLATES["ISC"], "Nothing", None, "", "x " * 5000]
    frame = spark.createDataFrame([row(i, t) for i, t in enumerate(rows)], DOCS)
    got = {r["doc_id"]: r["m"] for r in clash(frame).select("doc_id", licence_scan.licences("text").alias("m")).collect()}
    assert [m["licence"] for m in got[0]] == ["MIT notice"]
    assert (got[0][0]["start"], got[0][0]["length"]) == (12, 31)
    assert got[1][0]["licence"] == "MIT"
    assert got[2][0] ["dice"] == 1.0
    assert not any(got[i] for i in (3, 4, 5, 6))
    for text in [t for t in rows if t] + list(licence_scan.TEMPLATES.values()):
        own = licence_scan.bigrams(licence_scan.words(text))
        scores = [2 * len(own & b) / (len(own) + n) for n, _, b in scanner.templates]
        found = scanner.match(licence_scan.words(text))
        assert (found[0] if found else 0) == (max(scores) if max(scores) >= scanner.least else 0)
    assert no_docs.select(licence_scan.licences("text")).count() == 0


# -- sharding -----------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", list(licence_scan.TEMPLATES))
def test_licences_over_several_lines_and_paragraphs(name):
    rng, scanner = random.Random(4), licence_scan.Scanner()
    ws = licence_scan.TEMPLATES[name].split()
    third = max(1, len(ws) // 3)
    for parts in ([" ".join(ws[:third]), " ".join(ws[third : 2 * third]), " ".join(ws[2 * third :])], [" ".join(ws[i : i + 9]) for i in range(0, len(ws), 9)]):
        for gap in ("\n", "\n\n"):
            body = gap.join(parts)
            text = prose(rng, 400) + "\n\n" + body + "\n\n" + prose(rng, 400)
            found = [m for m in scanner(text) if m["licence"] == name]
            assert any(m["dice"] > 0.99 and text[m["start"] : m["start"] + m["length"]] == body for m in found), (name, gap)


def test_a_notice_after_a_copyright_statement():
    scanner = licence_scan.Scanner()
    for text in ("Copyright 2024 X. Licensed under the MIT License.", "(c) 2020 Some One Inc. All rights reserved. Licensed under the MIT License."):
        assert [m["licence"] for m in scanner(text)] == ["MIT notice, licensed"], text


def test_every_licence_of_a_document_is_returned(spark, tmp_path):
    text = "Released under the MIT License.\nProse between the notices, long enough to keep them apart.\nLicensed under CC BY 4.0."
    rows = [row(1, text), row(2, None), row(2, None), row(3, "No notice here.")]
    spark.createDataFrame(rows, DOCS).write.parquet(f"{tmp_path}/documents.parquet")
    got = sorted(licence_scan.op9_licence_dice(spark, str(tmp_path)).collect(), key=lambda r: r["doc_id"])
    assert [r["doc_id"] for r in got] == [1, 2, 2, 3]
    assert [(text[m["start"] : m["start"] + m["length"]], m["licence"]) for m in got[0]["matches"]] == [("Released under the MIT License.", "MIT notice"), ("Licensed under CC BY 4.0.", "CC-BY-4.0 notice")]
    assert (got[0]["licence"], got[0]["n_matches"]) == ("MIT notice", 2)
    assert [(r["n_matches"], r["licence"], r["matches"]) for r in got[1:]] == [(0, None, [])] * 3


def test_shards_are_contiguous_and_balanced(docs, no_docs, corpus):
    out = sharding.byte_shards(clash(docs), 5, extra={"crc": F.crc32(F.coalesce("text", F.lit("")).cast("binary"))}).collect()
    assert collections.Counter((r["doc_id"], r["size"], r["crc"]) for r in out) == collections.Counter((r[0], len((r[1] or "").encode()) + 8, zlib.crc32((r[1] or "").encode())) for r in corpus)
    by_shard = collections.defaultdict(list)
    for r in out:
        by_shard[r["shard"]].append(r)
    for rows in by_shard.values():
        assert sorted(r["slot"] for r in rows) == list(range(len(rows)))
    order = sorted(out, key=lambda r: (r["shard"], r["slot"]))
    assert [r["doc_id"] for r in order] == sorted((r["doc_id"] for r in out), key=lambda x: (x is not None, x or 0))
    total, at = sum(r["size"] for r in out), 0
    for r in order:
        assert r["shard"] == min(4, (2 * at + r["size"]) * 5 // (2 * total))
        at += r["size"]
    assert sharding.byte_shards(no_docs, 5).count() == 0


def test_unlabelled_documents_are_joined_alike_at_any_size(spark):
    """Few labels are not sent out whole either, so a small table moves its share of what a large one does."""
    featured = spark.createDataFrame([(1, 5), (2, 6), (2, 7), (3, 8)], "_id long, t int")
    found = cotraining._unlabelled(featured, spark.createDataFrame([(1, 1), (9, 0)], "_id long, quality int"))
    assert sorted(tuple(r) for r in found.collect()) == [(2, 6), (2, 7), (3, 8)]
    assert "Broadcast" not in found._jdf.queryExecution().executedPlan().toString()
