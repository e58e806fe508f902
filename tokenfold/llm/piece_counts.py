"""Token counts of unigram vocabularies without their tokens, and a model's own counts beside them.

An Aho-Corasick automaton names all vocabulary pieces that end at each character;
dynamic programming carries the best score and the number of pieces on that path.
Where two paths score the same, the last piece that starts earlier wins, as in the
tokenizers library's unigram model: it goes through the starts in order and only a
strictly higher score replaces a path. A character without a piece of its own costs
the lowest score less UNKNOWN_PENALTY and counts one token for each of its bytes.

Pieces hold the word mark only at their start, and pre-tokenization cuts before
each mark, so words are scored alone and remembered.

No shipped model is a unigram one: piece_bpe_32k.model merges pairs by rank (BPE), and
its scores are minus those ranks. The counts of a unigram tokenizer with these pieces
and scores are therefore not the model's; op8 returns both, each under its own name.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pandas as pd
import public_tokenizers
import sentencepiece
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import MEMO_WORDS, table, texts

MARK = "▁"
UNKNOWN_PENALTY = 10.0
NO_SCORE = float("-inf")


def vocabulary(path: str) -> list[tuple[str, float]]:
    """Pieces and scores of a sentencepiece file, in the order of their ids."""
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    return [(sp.id_to_piece(i), sp.get_score(i)) for i in range(sp.get_piece_size())]


class PieceCounter:
    def __init__(self, pieces: list[tuple[str, float]], unknown: int = 0, most: int = MEMO_WORDS):
        self.automaton = ahocorasick.Automaton()
        for piece, score in pieces:
            if piece:
                self.automaton.add_word(piece, (len(piece), float(score)))
        self.automaton.make_automaton()
        self.unknown_score = min(s for _, s in pieces) - UNKNOWN_PENALTY
        self.single = {p for p, _ in pieces if len(p) == 1}
        self.memo: dict[str, tuple[float, int]] = {}
        self.old: dict[str, tuple[float, int]] = {}
        self.most = most // 2

    def word(self, word: str) -> tuple[float, int]:
        """Score and pieces of the best path through a word."""
        n = len(word)
        best, count = [NO_SCORE] * (n + 1), [0] * (n + 1)
        best[0] = 0.0
        done = -1
        single, unknown = self.single, self.unknown_score
        for end, (length, score) in self.automaton.iter(word):
            while done < end - 1:  # ends that no piece reaches, or that wait for their unknown step
                done += 1
                self._step(word, done, best, count, single, unknown)
            at = end + 1 - length
            s = best[at] + score
            if s > best[end + 1]:
                best[end + 1], count[end + 1] = s, count[at] + 1
        while done < n - 1:
            done += 1
            self._step(word, done, best, count, single, unknown)
        return best[n], count[n]

    @staticmethod
    def _step(word, i, best, count, single, unknown) -> None:
        """The unknown step over character i, the last start that can end there."""
        if word[i] not in single:
            s = best[i] + unknown
            if s > best[i + 1]:
                best[i + 1], count[i + 1] = s, count[i] + len(word[i].encode("utf-8", "surrogatepass"))

    def __call__(self, text: str) -> tuple[float, int]:
        """Score and number of tokens of a text; (0, 0) for the empty text."""
        if not text:
            return 0.0, 0
        memo, one = self.memo, self.word
        if len(memo) > self.most:  # words that are still in use come back from the old memo
            self.old, self.memo = memo, {}
            memo = self.memo
        old = self.old
        score, tokens = 0.0, 0
        marked = text.replace(MARK, " ")
        words = marked.split(" ")
        if not words[0] and len(words) > 1:  # the text starts with a mark of its own
            words = words[1:]
        for w in words:
            got = memo.get(w)
            if got is None:
                got = memo[w] = old.get(w) or one(MARK + w)
            score += got[0]
            tokens += got[1]
        return score, tokens


@lru_cache(1)
def _counter(path: str) -> PieceCounter:
    return PieceCounter(vocabulary(path))


def piece_count(text: str | Column, path: str | None = None, own: bool = False) -> Column:
    """Struct of tokens and score of one text under a unigram reading of the vocabulary; null texts count as empty.

    Whole texts are counted, whatever their length. own adds model_tokens, the number of
    tokens by the model's own method.
    """
    path = path or public_tokenizers.path("piece_bpe_32k.model")

    def count(column: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        counter, sp = _counter(path), _tokenizer(path)[0]
        for series in column:
            whole = texts(series)
            got = [counter(t) for t in whole]
            found = {"n_tokens": [n for _, n in got], "score": [s for s, _ in got]}
            yield pd.DataFrame(found | ({"model_tokens": [len(sp.encode(t)) for t in whole]} if own else {}))

    count.__annotations__ = {"column": Iterator[pd.Series], "return": Iterator[pd.DataFrame]}
    return F.pandas_udf(count, "n_tokens long, score double" + (", model_tokens long" if own else "")).asNondeterministic()(text)


@lru_cache(1)
def _tokenizer(path: str) -> tuple[sentencepiece.SentencePieceProcessor, np.ndarray]:
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    return sp, np.array([sp.get_score(i) for i in range(sp.get_piece_size())])


def token_count(text: str | Column, path: str | None = None) -> Column:
    """Struct of the tokenizer's own number of tokens and the sum of their scores in the model file; null texts count as empty.

    Whole texts are segmented by the model's method. In a BPE model scores are minus
    merge ranks, and control and byte pieces score 0; control pieces are never matched.
    """
    path = path or public_tokenizers.path("piece_bpe_32k.model")

    def count(column: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        sp, scores = _tokenizer(path)
        for series in column:
            n, total = [], []
            for t in texts(series):
                ids = sp.encode(t)
                n.append(len(ids))
                total.append(float(scores[ids].sum()) if ids else 0.0)
            yield pd.DataFrame({"n_tokens": n, "score": total})

    count.__annotations__ = {"column": Iterator[pd.Series], "return": Iterator[pd.DataFrame]}
    return F.pandas_udf(count, "n_tokens long, score double").asNondeterministic()(text)


def op8_viterbi_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Viterbi counts and scores over the pieces of piece_bpe_32k.model, and that BPE model's own counts."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return docs.select("doc_id", piece_count("text", own=True).alias("c")).select("doc_id", "c.n_tokens", "c.score", "c.model_tokens")
