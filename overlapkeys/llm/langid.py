"""Operator 8: language identification by segmentation-marginalised unigrams.

Each language has a probability for every piece of a fixed public vocabulary. A word's likelihood is
the sum over all its segmentations into pieces, by the forward recursion; a text's is the product over its
words. The probabilities come from expectation-maximisation on words of labelled documents.
"""

from __future__ import annotations

import re
import sys
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, lean

UNKNOWN = 1e-6  # probability of a letter that no piece has, alike for every language
TRAIN_DOCS = 600  # labelled documents for each language, about; a bounded sample fits the classifier
KEPT_WORDS = 400_000  # bound of a task's memory of words, unless the caller sets its own
CELLS = 60_000  # letters of words that are scored at once
RESCALE = 8  # letters after which the forward sums are scaled anew


_RUN = re.compile(r"[^\W\d_]+")  # letters, and numerals of other kinds than digits


@lru_cache(1)
def _letters() -> re.Pattern:
    numerals = "".join(c for c in map(chr, range(128, sys.maxunicode + 1)) if c.isalnum() and not c.isalpha() and not c.isdecimal())
    return re.compile(rf"[^\W\d_{numerals}]+")


def words_of(text: str) -> list[str]:
    """Runs of letters, Unicode's category L; the slower pattern is asked only where a text has numerals among them."""
    words = _RUN.findall(text.lower())
    return words if not words or "".join(words).isalpha() else _letters().findall(text.lower())


def load_pieces(path: str) -> dict[str, int]:
    """Lower-case letter pieces of a public sentencepiece vocabulary, numbered anew from 0."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    names = {model.id_to_piece(i).replace("▁", "_").lower() for i in range(model.get_piece_size())}
    fit = sorted(p for p in names if p == "_" or p.lstrip("_").isalpha())
    return {p: k for k, p in enumerate(fit)}


class _Table:
    """Numbers of pieces by a hash that grows letter by letter to the left; a hit is checked by the whole hash."""

    BASE, BITS = 0x9E3779B97F4A7C15, 21

    def __init__(self, pieces: dict[str, int]):
        self.none, self.longest = len(pieces), max(map(len, pieces), default=1)
        self.power = np.array([pow(self.BASE, k, 1 << 64) for k in range(self.longest)], np.uint64)
        self.hash = np.zeros(len(pieces) + 1, np.uint64)
        for p, k in pieces.items():
            codes = np.array([[ord(c) for c in reversed(p)]], np.uint64) + np.uint64(1)
            self.hash[k] = self._mixed((codes * self.power[: len(p)]).sum(1), len(p))[0]
        slot = (self.hash[:-1] >> np.uint64(64 - self.BITS)).astype(np.int64)
        self.slots = np.full(1 << self.BITS, self.none, np.int32)
        self.slots[slot] = np.arange(len(pieces))
        # pieces that lost their slot to another, a few, in a list sorted by hash
        lost = np.flatnonzero(self.slots[slot] != np.arange(len(pieces)))
        self.rest = lost[np.argsort(self.hash[lost])]
        self.shared = np.zeros(1 << self.BITS, bool)
        self.shared[slot[lost]] = True

    @staticmethod
    def _mixed(h: np.ndarray, size: int) -> np.ndarray:
        h = (h ^ np.uint64(size * 0x632BE59BD9B4E019 % (1 << 64))) * np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(31)
        return h * np.uint64(0x94D049BB133111EB)

    def lattice(self, words: list[str]) -> list[np.ndarray]:
        """For words of one length: a (words, starts) array of piece numbers for each size of piece, ``none`` where there is none."""
        codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), "<u4").reshape(len(words), -1).astype(np.uint64) + np.uint64(1)
        n, out = codes.shape[1], []
        h = np.zeros((len(words), n + 1), np.uint64)
        for m in range(1, min(self.longest, n) + 1):
            h = h[:, 1:] + self.power[m - 1] * codes[:, : n - m + 1]
            x = self._mixed(h, m)
            slot = (x >> np.uint64(64 - self.BITS)).astype(np.int64)
            ids = self.slots[slot]
            ids[self.hash[ids] != x] = self.none
            more = np.nonzero(self.shared[slot])
            if len(more[0]):
                own = x[more]
                at = np.minimum(np.searchsorted(self.hash[self.rest], own), len(self.rest) - 1)
                ids[more] = np.where(self.hash[self.rest[at]] == own, self.rest[at], ids[more])
            out.append(ids)
        return out


class Unigrams:
    def __init__(self, langs: list[str], pieces: dict[str, int], logp: np.ndarray):
        """logp: (pieces + 1, languages); the last row, of no piece, is -inf."""
        self.langs, self.table = langs, _Table(pieces)
        self.set_logp(logp)

    def set_logp(self, logp: np.ndarray) -> None:
        self.logp, self.p = logp, np.exp(logp)

    def _sums(self, lattice: list[np.ndarray], n: int, forward: bool = True, keep: bool = False) -> np.ndarray:
        """Log of the sum over all segmentations of the first letters (forward) or the last ones.

        (words, languages) for whole words, or (letters + 1, words, languages) if all are to be kept. The sums are
        scaled every RESCALE letters, so no length of word is out of range.
        """
        none, width = self.table.none, len(lattice)
        words = lattice[0].shape[0]
        sums = [np.ones((words, len(self.langs)))]  # of the last ``width`` places
        scale = np.zeros((words, len(self.langs)))
        kept = [scale.copy()] if keep else None
        for j in range(1, n + 1):
            total = np.zeros_like(scale)
            for m in range(1, min(j, width) + 1):
                ids = lattice[m - 1][:, j - m if forward else n - j]
                if m == 1:
                    total += sums[-1] * np.where((ids == none)[:, None], UNKNOWN, self.p[ids])
                    continue
                hit = np.flatnonzero(ids != none)
                if len(hit):
                    total[hit] += sums[-m][hit] * self.p[ids[hit]]
            sums.append(total)
            if len(sums) > width:
                del sums[0]
            if j % RESCALE == 0:
                scale += np.log(total)
                sums = [x / total for x in sums]
            if keep:
                kept.append(scale + np.log(sums[-1]))
        return np.array(kept) if keep else scale + np.log(sums[-1])

    @staticmethod
    def _groups(words: list[str]) -> Iterator[list[int]]:
        """Numbers of words of one length, as many as have about CELLS letters."""
        of_length: dict[int, list[int]] = {}
        for k, w in enumerate(words):
            of_length.setdefault(len(w), []).append(k)
        for n, own in of_length.items():
            step = max(1, CELLS // (n + 1))
            yield from (own[at : at + step] for at in range(0, len(own), step))

    def score_words(self, words: list[str]) -> np.ndarray:
        """(words, languages) log-likelihood: the sum over all segmentations of "_" and the word."""
        out = np.zeros((len(words), len(self.langs)))
        for own in self._groups(words):
            out[own] = self._sums(self.table.lattice(["_" + words[k] for k in own]), len(words[own[0]]) + 1)
        return out

    @classmethod
    def fit(cls, counts: dict[str, Counter], pieces: dict[str, int], rounds: int = 3) -> Unigrams:
        """EM from an even start; counts: words of each language. Smoothed, so every piece stays possible."""
        langs, none = sorted(counts), len(pieces)
        logp = np.full((none + 1, len(langs)), -np.log(none))
        logp[none] = -np.inf
        model = cls(langs, pieces, logp)
        if not langs:
            return model
        vocabulary = sorted(set().union(*counts.values()))
        weight = np.array([[counts[g][w] for g in langs] for w in vocabulary], float).reshape(-1, len(langs))
        for _ in range(rounds):
            seen = np.full((none + 1, len(langs)), 0.05)
            for own in model._groups(vocabulary):
                n = len(vocabulary[own[0]]) + 1
                lattice = model.table.lattice(["_" + vocabulary[k] for k in own])
                before, after = model._sums(lattice, n, True, True), model._sums(lattice, n, False, True)
                for m, ids in enumerate(lattice, 1):
                    row, start = np.nonzero(ids != none)
                    if not len(row):
                        continue
                    found = ids[row, start]
                    share = np.exp(before[start, row] + model.logp[found] + after[n - start - m, row] - before[n, row])
                    share *= weight[own][row]
                    for k in range(len(langs)):
                        seen[:, k] += np.bincount(found, share[:, k], none + 1)
            seen[none] = 0
            with np.errstate(divide="ignore"):
                model.set_logp(np.log(seen / seen.sum(0)))
        return model


def train(docs: DataFrame, vocabulary: str, per_language: int = TRAIN_DOCS) -> Unigrams:
    """Fit on documents that have a lang and whose crc32(doc_id) mod 3 is not 1, some ``per_language`` each.

    The sample is drawn by a hash of doc_id and is bounded; word counts are summed on the executors.
    """
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3
    labelled = docs.filter(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.coalesce(held, F.lit(1)) != 1))
    sizes = {r["lang"]: r["n"] for r in labelled.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # one row a language
    coin = F.pmod(F.xxhash64(F.lit("langid"), "doc_id"), F.lit(1 << 30)) / float(1 << 30)
    share = F.lit(1.0)
    for lang, n in sizes.items():
        share = F.when(F.col("lang") == lang, F.lit(min(1.0, per_language / n))).otherwise(share)

    @lean
    def words(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            got: Counter = Counter()
            for lang, text in zip(f["lang"], f["text"]):
                got.update((lang, w) for w in words_of(text))
            yield pd.DataFrame([(g, w, n) for (g, w), n in got.items()], columns=["lang", "word", "n"])

    counted = labelled.filter(coin < share).select("lang", "text").mapInPandas(words, "lang string, word string, n long")
    rows = counted.groupBy("lang", "word").agg(F.sum("n").alias("n")).toPandas()  # bounded by the sample
    counts: dict[str, Counter] = {g: Counter() for g in sizes}
    for lang, word, n in rows.itertuples(index=False):
        counts[lang][word] = n
    return Unigrams.fit({g: c for g, c in counts.items() if c}, load_pieces(vocabulary))


def language_of(model: Unigrams, kept_words: int = KEPT_WORDS):
    """A column function: text -> struct of lang_pred and score.

    ``und`` and 0 if the text is null or has no letter, or nothing was learnt. score is the posterior of
    the chosen language, tempered by the square root of the number of words. Ties go to the language
    that comes first by name. It reads the text alone, so other columns may have any names; repeated rows get
    repeated results, an empty table none, and a word's length has no bound.
    """
    langs = model.langs

    @F.pandas_udf("struct<lang_pred: string, score: double>")
    @lean
    def of(columns: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        number: dict[str, int] = {}
        scores = np.zeros((0, len(langs)))
        for column in columns:
            best, sure, texts = [], [], column.tolist()
            for at in range(0, len(texts), 500):  # a part of the batch at a time, for memory
                split = [words_of(t) if isinstance(t, str) else [] for t in texts[at : at + 500]]
                if len(number) > kept_words:
                    number, scores = {}, np.zeros((0, len(langs)))
                fresh = list(set().union(*split).difference(number))
                if fresh and langs:
                    number.update(zip(fresh, range(len(number), len(number) + len(fresh))))
                    scores = np.concatenate([scores, model.score_words(fresh)])
                for words in split:
                    if not words or not langs:
                        best.append("und")
                        sure.append(0.0)
                        continue
                    total = scores[np.fromiter(map(number.__getitem__, words), np.int64, len(words))].sum(0)
                    k = int(total.argmax())
                    best.append(langs[k])
                    sure.append(float(1 / np.exp((total - total[k]) / np.sqrt(len(words))).sum()))
            yield pd.DataFrame({"lang_pred": best, "score": sure})

    return of


def op8_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = documents(spark, sf_dir)
    model = train(docs, public_tokenizers.path("piece_bpe_32k.model"))
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(held, F.lit(False)).alias("held_out"), language_of(model)("text").alias("r"))
    return found.select("doc_id", "held_out", "r.lang_pred", "r.score")
