"""Operator 2: SpotSigs fingerprints.

A spot is an anchor, a very common word, with the chain of content words that follow it. The beginning of a text
and that of each sentence are anchors, too, and its end stands in where words run out, so one rule holds for
texts of any length. A document's fingerprint is its set of spots. Likeness is the Jaccard similarity of two sets, cut short where
the sizes alone keep it below the threshold; the join deals sets by length, so that sets whose lengths are
too unlike never meet.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_rows, documents, filled_id, unfilled, with_next

TOKEN = re.compile(r"[^\W_]+|[.!?\u3002\uff01\uff1f](?!\S)")  # words, and marks that end a sentence
# Anchors, and further common words that no chain counts as content.
ANCHORS = frozenset("the a an is was of to and le la les un une des der die das ein eine ist el los las una es".split())
STOPS = ANCHORS | frozenset("in that it for on with as by this be are from at or et de du que qui en au pour dans par sur und von mit zu den dem auf für y del por con para se lo al su".split())
CHAIN = 2  # content words in a spot
LEAST = 0.05  # a likeness below counts as none
KEPT_WORDS = 1_000_000  # bound of a worker's memory of words


BEGIN, END = np.uint64(0x5851F42D4C957F2D), np.uint64(0x14057B7EF767814F)  # hashes of a text's beginning and end


class _Words:
    """Per worker: each word's number, hash and kind (0 content, 1 common, 2 anchor, 3 the end of a sentence)."""

    def __init__(self) -> None:
        self.number: dict[str, int] = {}
        self.hashes, self.kinds = np.zeros(1 << 16, np.uint64), np.zeros(1 << 16, np.int8)

    def ids(self, words: list[str]) -> np.ndarray:
        try:
            return np.fromiter(map(self.number.__getitem__, words), np.int64, len(words))
        except KeyError:
            if len(self.number) > KEPT_WORDS:
                self.number.clear()
            for w in words:
                if w not in self.number:
                    k = self.number[w] = len(self.number)
                    if k == len(self.hashes):
                        self.hashes, self.kinds = np.r_[self.hashes, np.zeros_like(self.hashes)], np.r_[self.kinds, np.zeros_like(self.kinds)]
                    self.hashes[k] = xxhash.xxh3_64_intdigest(w.encode())
                    self.kinds[k] = 2 if w in ANCHORS else 1 if w in STOPS else 0 if w[0].isalnum() else 3
            return np.fromiter(map(self.number.__getitem__, words), np.int64, len(words))


_words = _Words()


def spots(text: str | None) -> np.ndarray:
    """Sorted distinct 32-bit spots of a text; of one without words, a spot of the text itself.

    Equal texts have equal spots. A null text counts as empty, and the empty text has one spot.
    """
    text = text or ""
    words = TOKEN.findall(text.lower())
    ids = _words.ids(words)
    kind, h = _words.kinds[ids], _words.hashes[ids]
    if not (kind < 3).any():
        return np.frombuffer(hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=4).digest(), "<u4").copy()
    # the text's beginning is an anchor before all words; ends of the text are content behind all of them
    kind, h = np.r_[np.int8(2), kind, np.zeros(CHAIN, np.int8)], np.r_[BEGIN, h, np.full(CHAIN, END, np.uint64)]
    content = np.flatnonzero(kind == 0)
    rank = np.cumsum(kind == 0)
    anchors = np.flatnonzero(kind >= 2)
    anchors = anchors[rank[anchors] + CHAIN <= len(content)]
    made = h[anchors] * np.uint64(0x9E3779B97F4A7C15)
    for k in range(CHAIN):
        made = (made ^ h[content[rank[anchors] + k]]) * np.uint64(0xBF58476D1CE4E5B9)
        made ^= made >> np.uint64(31)
    return np.unique((made >> np.uint64(32)).astype(np.uint32))


def likeness(a: np.ndarray, b: np.ndarray, least: float = LEAST) -> float:
    """Jaccard similarity of two sorted sets, 0 where it is below ``least``.

    Sets whose lengths lie more than one band apart, or whose sizes alone keep them below, are never compared.
    """
    small, large = (a, b) if len(a) <= len(b) else (b, a)
    if not len(small) or len(small) < least * len(large):
        return 0.0
    if least and band(len(large), least) - band(len(small), least) > 1:
        return 0.0
    wanted = math.ceil(least * (len(a) + len(b)) / (1 + least) - 1e-9)  # common spots
    # one of the first len - wanted + 1 spots of either set is common, or too few are
    head = small[: len(small) - max(1, wanted) + 1]
    at = np.searchsorted(large, head)
    if not (large[np.minimum(at, len(large) - 1)] == head).any():
        return 0.0
    shared = len(np.intersect1d(a, b, assume_unique=True))
    found = shared / (len(a) + len(b) - shared)
    return found if found >= least else 0.0


def band(n: int, least: float) -> int:
    """Sets of one band, or of two neighbouring ones, may reach ``least``; sets farther apart can't."""
    return int(math.log(n) / -math.log(least) + 1e-9)


def compare_edited(docs: DataFrame) -> DataFrame:
    """Each document with the fingerprints of its own and its edited text, and their likeness.

    The next document is the one with the next lower doc_id, by a hash of the text among equal ids; after the last
    comes the first. Null texts are empty. A table of one document is its own next one.
    """

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ahead = ("", spots(""))  # neighbours mostly follow each other: a next text's spots serve its own row
        for f in frames:
            rows = []
            for text, after in zip(f["text"].tolist(), f["next_text"].tolist()):
                half = len(text) // 2
                edited = text[: len(text) - half] + after[:half]
                own, changed, other = ahead[1] if ahead[0] == text else spots(text), spots(edited), spots(after)
                ahead = (after, other)
                rows.append((len(text), hashlib.sha256(edited.encode()).hexdigest(), own.astype(">u4").tobytes().hex(), changed.astype(">u4").tobytes().hex(), likeness(own, changed), likeness(own, other)))
            made = pd.DataFrame(rows, columns=["n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])
            made.insert(0, "doc_id", f["doc_id"].to_numpy())
            yield made

    slim = docs.select(filled_id(), F.coalesce("text", F.lit("")).alias("text"))
    paired = with_next(slim, "doc_id", "text", "next_text").select("doc_id", "text", "next_text")
    return unfilled(paired.mapInPandas(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"))


def fingerprint_sets(docs: DataFrame) -> DataFrame:
    """doc_id, spots array<long> for each row."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield pd.DataFrame({"doc_id": f["doc_id"], "spots": [spots(t).astype(np.int64) for t in f["text"].tolist()]})

    return unfilled(docs.select(filled_id(), "text").mapInPandas(run, "doc_id long, spots array<long>"))


def near_pairs(docs: DataFrame, least: float = 0.8) -> tuple[DataFrame, DataFrame]:
    """(membership: doc_id, class_id; pairs of classes: a, b, likeness >= ``least``). Exact.

    Equal spot sets form a class, so copies never meet. Sets are dealt by a band of lengths; a set also
    probes the next band, where its greatest partner may lie. Only a set's rarest spots, enough that
    any partner shares one, are join keys.
    """
    sets = fingerprint_sets(docs)
    classes = sets.groupBy("spots").agg(F.min("doc_id").alias("class_id"))
    membership = sets.join(classes, "spots").select("doc_id", "class_id")
    width = -math.log(least)
    sized = classes.select("class_id", "spots", F.size("spots").alias("n"))
    token = sized.select("class_id", F.explode("spots").alias("t"))
    rarity = token.groupBy("t").agg(F.count("*").alias("df"))
    ranked = token.join(rarity, "t").groupBy("class_id").agg(F.sort_array(F.collect_list(F.struct("df", "t"))).alias("o"))
    prefix = F.col("n") - F.ceil(F.col("n") * F.lit(least) - 1e-9) + 1
    keys = ranked.join(sized, "class_id").select(
        "class_id", "spots", "n", F.floor(F.log("n") / width + 1e-9).alias("band"), F.explode(F.expr("transform(slice(o, 1, n), x -> x.t)")).alias("t"), prefix.alias("p"), F.col("o")
    )
    keys = keys.filter(F.expr("array_position(transform(slice(o, 1, cast(p as int)), x -> x.t), t) > 0")).drop("o", "p")
    probes = keys.withColumn("band", F.explode(F.array("band", F.col("band") + 1)))
    a, b = keys.alias("a"), probes.alias("b")
    met = a.join(b, (F.col("a.t") == F.col("b.t")) & (F.col("a.band") == F.col("b.band")))
    met = met.filter("(a.n > b.n or (a.n = b.n and a.class_id < b.class_id)) and b.n >= a.n * " + repr(least - 1e-9))
    met = met.select(F.col("a.class_id").alias("x"), F.col("b.class_id").alias("y"), F.col("a.spots").alias("s"), F.col("b.spots").alias("u")).dropDuplicates(["x", "y"])
    shared = F.size(F.array_intersect("s", "u"))
    pairs = met.withColumn("likeness", shared / (F.size("s") + F.size("u") - shared)).filter(F.col("likeness") >= least)
    return membership, pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "likeness")


def op2_spotsigs(spark: SparkSession, sf_dir: str) -> DataFrame:
    arrow_rows(spark, 1_000)
    return compare_edited(documents(spark, sf_dir))
