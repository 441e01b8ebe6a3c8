"""Operator 1: repeated runs of sentences.

Texts are cut into sentences at marks (full-width ones, too) and line ends; commas and colons count as marks, so a
passage that was set into another sentence still has whole sentences. Sentences of over LONG words are parted after
words chosen by their hash, so a passage inside them is parted alike wherever it stands; the parts count as sentences.
From each sentence on, the shortest run of at least SENTENCES sentences and WORDS words is hashed, and the shortest
such run that ends with the text; a text too short for one is a run by itself from LEAST_WORDS words on. A run whose
hash occurs earlier, in the order of (doc_id, place), has its sentences removed.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_rows, documents, in_told, join_by_share, settle

MARKS = ".!?;:,\u3002\uff01\uff1f\uff1b\uff1a\uff0c\u3001\uff0e\uff61\uff64"
SENTENCE = re.compile(rf"[^{MARKS}\n]*(?:[{MARKS}]+|\n|\Z)\s*")
SENTENCES, WORDS = 3, 25
LEAST_WORDS = 12  # of a text that is a run by itself
LONG, PART = 24, 8  # words of a sentence that stays whole, and of a part on average
_BARE = "\u0e00-\u0eff\u1000-\u109f\u1780-\u17ff\u3040-\u30ff\u3400-\u4dbf\u4e00-\u9fff\uf900-\ufaff\U00020000-\U0003ffff"
BARE = re.compile(f"[{_BARE}]")  # of scripts without white space between words: each character counts as a word
WORD = re.compile(rf"\s*(?:[{_BARE}]|[^\s{_BARE}]+)\s*")


def _words(sentence: str) -> int:
    return len(sentence.split()) if sentence.isascii() or not BARE.search(sentence) else len(WORD.findall(sentence))


def _parts(sentence: str) -> Iterator[str]:
    """Ends after a word by its hash alone, else after LONG words."""
    held: list[str] = []
    for word in WORD.findall(sentence):
        held.append(word)
        if len(held) == LONG or zlib.crc32(word.strip().encode("utf-8", "surrogatepass")) % PART == 0:
            yield "".join(held)
            held = []
    if held:
        yield "".join(held)


def cut(text: str) -> list[str]:
    """Sentences with the marks and white space that follow them; joined they are the text."""
    out = []
    for s in SENTENCE.findall(text):
        if len(s) > LONG and _words(s) > LONG:
            out += _parts(s)
        elif s:
            out.append(s)
    return out


def run_hashes(sentences: list[str]) -> list[tuple[int, int, int]]:
    """(first sentence, number of sentences, hash) of the runs from each sentence on."""
    flat = [" ".join(s.split()) for s in sentences]
    count = np.array([_words(s) for s in sentences], np.int64)
    upto = np.cumsum(count)
    before = upto - count
    last = len(flat) - 1
    ends = np.maximum(np.searchsorted(upto, before + WORDS), np.arange(len(flat)) + SENTENCES - 1)
    runs = [(i, j) for i, j in enumerate(ends.tolist()) if j <= last]
    if not runs and len(flat) and upto[-1] >= LEAST_WORDS:
        runs.append((0, last))
    elif runs and runs[-1][1] < last:  # the last sentences are too short for a run of their own
        runs.append((min(int(np.searchsorted(before, upto[-1] - WORDS, "right")) - 1, last + 1 - SENTENCES), last))
    digest = xxhash.xxh3_64_intdigest
    return [(i, j - i + 1, digest(" ".join([f for f in flat[i : j + 1] if f]).encode("utf-8", "surrogatepass")) - (1 << 63)) for i, j in runs if upto[j] > before[i]]


def _runs(numbered: DataFrame, places: bool) -> DataFrame:
    """The hashes of all runs, with their places if asked for."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            ids, ths, texts = f["doc_id"].to_numpy(), f["th"].to_numpy(), f["text"].tolist()
            for at in range(0, len(f), 500):
                got = [run_hashes(cut(t)) for t in texts[at : at + 500]]
                flat = np.array([x for g in got for x in g], np.int64).reshape(-1, 3)
                out = {"h": flat[:, 2]}
                if places:
                    size = [len(g) for g in got]
                    out |= {"doc_id": np.repeat(ids[at : at + 500], size), "th": np.repeat(ths[at : at + 500], size), "i": flat[:, 0].astype(np.int32), "n": flat[:, 1].astype(np.int32)}
                yield pd.DataFrame(out)

    return numbered.mapInPandas(run, "h long, doc_id long, th long, i int, n int" if places else "h long")


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, n_sentences, n_removed, kept (the text without repeated sentences); a row for each row.

    A null text counts as empty. White space is not compared. Rows with equal doc_id and text are one
    document read twice: their runs have one place, so none of them is a repeat of the other. The
    first occurrence of a run, in the order of (doc_id, place), stays.
    """
    slim = docs.select(F.col("doc_id").cast("long"), "text")
    key = F.xxhash64(F.coalesce("text", F.lit("")))
    # a null doc_id comes after all others
    numbered = slim.select(F.coalesce("doc_id", F.lit((1 << 63) - 1)).alias("doc_id"), key.alias("th"), F.coalesce("text", F.lit("")).alias("text"))
    # bare hashes first, which the map side counts; only runs whose hash repeats are kept with their places
    repeated = settle(_runs(numbered, False).groupBy("h").agg(F.count("*").alias("n")).filter("n > 1"), "repeated")
    total = repeated.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    runs = settle(in_told(_runs(numbered, True), repeated, "h", ["doc_id", "th", "i"], total), "runs")
    place = F.struct("doc_id", "th", "i")
    first = runs.groupBy("h").agg(F.min(place).alias("first"), F.max(place).alias("last"), F.count("*").alias("n")).filter("first <> last")
    first = settle(first.select("h", "first", "n"), "firsts")
    hits = join_by_share(runs.withColumnRenamed("n", "size"), first, ["h"], total)
    repeats = hits.filter(place != F.col("first")).select("doc_id", "th", "i", F.col("size").alias("n"))
    marks = repeats.groupBy("doc_id", "th").agg(F.collect_set(F.struct("i", "n")).alias("marks"))

    def cleaned(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            rows = []
            for text, own in zip(f["text"].tolist(), f["marks"].tolist()):
                sentences = cut(text)
                covered = np.zeros(len(sentences) + 1, np.int64)
                for m in own if own is not None else ():
                    covered[m["i"]] += 1
                    covered[m["i"] + m["n"]] -= 1
                out = np.cumsum(covered[:-1]) > 0
                rows.append((len(sentences), int(out.sum()), text if not out.any() else "".join(s for s, o in zip(sentences, out) if not o)))
            made = pd.DataFrame(rows, columns=["n_sentences", "n_removed", "kept"])
            made.insert(0, "doc_id", f["doc_id"].to_numpy())
            yield made

    whole = numbered.join(marks, ["doc_id", "th"], "left").select("doc_id", "text", "marks")
    result = whole.mapInPandas(cleaned, "doc_id long, n_sentences long, n_removed long, kept string")
    return result.withColumn("doc_id", F.when(F.col("doc_id") != (1 << 63) - 1, F.col("doc_id")))


def op1_sentence_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    arrow_rows(spark, 1_000)
    return remove_repeats(documents(spark, sf_dir))
