"""Operator 10: benchmark decontamination by latent semantic retrieval.

Documents are cut into overlapping passages of words. Passages are weighted by TF-IDF over the terms of
the benchmark, whose document frequencies are counted over the whole corpus, and projected to the
leading right singular vectors of the matrix of all passages, found by a randomised decomposition whose
row sketch is made distributed, in one pass. Items are cut alike. Passages whose cosine with a part of a benchmark item is high
are candidates; the longest common subsequence with the item, and its rarest terms (its answer), decide.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_rows, documents, filled_id, lean, settle, unfilled

WINDOW, STRIDE = 40, 20  # words of a passage, words between two starts
ITEMS_AT_ONCE = 1_000  # items searched in one pass over the corpus; more go in blocks
COMMON = 0.05  # terms in a larger share of passages have no weight
KEPT = 0.5  # share of its length, squared, that a part of an item keeps in the projection at least
FAN = 16  # partial sketches that one task adds
RANK, SKETCH = 128, 1024  # singular vectors; rows of the sketch that all passages are added up in
RARE = 1e-4  # terms in no larger share of passages are equally rare
LEAST_HITS = 3  # weighted terms that a candidate passage has at least
COSINE, LCS, ANSWER = 0.35, 0.6, 0.5
ANSWER_TERMS = 6
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    """Lower-case words; ASCII marks and spaces part them."""
    return (text or "").lower().encode("utf-8", "surrogatepass").translate(_TABLE).split()


def _passages(pos: np.ndarray, term: np.ndarray, n_words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(passage, term, count) of the terms at word places ``pos``, sorted by passage; number of passages."""
    n = max(1, -(-max(0, n_words - (WINDOW - STRIDE)) // STRIDE))
    own = pos // STRIDE
    first = np.minimum(own, n - 1)
    twice = (first > 0) & (own == first)
    where = np.concatenate([first, first[twice] - 1])
    both, count = np.unique(where.astype(np.int64) << 32 | np.concatenate([term, term[twice]]), return_counts=True)
    return both >> 32, both & 0xFFFFFFFF, count, n


class Block:
    """A block of benchmark items: its vocabulary and, once counted, its weights and projection."""

    def __init__(self, items: list[tuple[int, str]]):
        self.ids = [i for i, _ in items]
        self.words = [words_of(t) for _, t in items]
        self.number = {w: k for k, w in enumerate(sorted(set().union(*self.words)))}

    def hits(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Places of the words that are terms, and their numbers."""
        number = np.fromiter(map(self.number.get, words, repeat(-1)), np.int32, len(words))
        pos = np.flatnonzero(number >= 0)
        return pos, number[pos]

    def numbers(self, words: list[bytes]) -> np.ndarray:
        return self.hits(words)[1]

    def weigh(self, df: np.ndarray, passages: int) -> None:
        idf = np.log(1 + passages / (1 + df))  # above zero even where every passage has the term
        self.idf = np.where(df > max(COMMON * passages, 5), 0.0, idf)
        # an item of common words only keeps them all
        for w in self.words:
            k = self.numbers(w)
            if len(k) and np.count_nonzero(self.idf[np.unique(k)]) < LEAST_HITS:
                self.idf[k] = idf[k]
        # rare terms count alike: one that a leak has replaced must not be taken because it is rarer for that
        rarity, self.answers = np.maximum(df, max(5, RARE * passages)), []
        for w in self.words:
            k = np.unique(self.numbers(w)) if w else np.zeros(0, np.int64)
            self.answers.append(set(k[np.argsort(rarity[k], kind="stable")][:ANSWER_TERMS].tolist()))

        # which items each term answers for, as runs of one list
        told = sorted((t, k) for k, a in enumerate(self.answers) for t in a)
        self.told_item = np.array([k for _, k in told], np.int64)
        self.told_count = np.bincount(np.array([t for t, _ in told], np.int64), minlength=len(idf))
        self.told_start = np.cumsum(self.told_count) - self.told_count
        self.enough = np.array([max(1, math.ceil(ANSWER * len(a) - 1e-9)) for a in self.answers])

    def answered(self, ids: np.ndarray) -> np.ndarray:
        """Items of whose answers the document has enough terms; no other item can be decided for it."""
        terms = np.unique(ids)
        terms = terms[self.told_count[terms] > 0]
        size = self.told_count[terms]
        if not len(terms):
            return terms
        ends = np.cumsum(size)
        items = self.told_item[np.repeat(self.told_start[terms] - ends + size, size) + np.arange(int(ends[-1]))]
        items, n = np.unique(items, return_counts=True)
        return items[n >= self.enough[items]]

    def rows(self, pos: np.ndarray, term: np.ndarray, n_words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(passage, term, weight) of the passages with enough weighted terms."""
        live = self.idf[term] > 0
        where, term, count, n = _passages(pos[live], term[live], n_words)
        weight = (1 + np.log(count)) * self.idf[term]
        enough = np.bincount(where, minlength=n)[where] >= LEAST_HITS
        return where[enough], term[enough], weight[enough]

    def project(self, where: np.ndarray, term: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Distinct passages and their unit latent vectors."""
        starts = np.flatnonzero(np.r_[True, where[1:] != where[:-1]]) if len(where) else np.zeros(0, np.int64)
        if not len(starts):
            return starts, np.zeros((0, self.axes.shape[1]), np.float32)
        latent = np.add.reduceat(self.axes[term] * weight[:, None].astype(np.float32), starts)
        return where[starts], latent / np.maximum(np.linalg.norm(latent, axis=1, keepdims=True), 1e-9)

    def item_parts(self) -> list[tuple[int, int, np.ndarray, np.ndarray]]:
        """(item, first word, terms, weights) of the passages of each item, cut as documents are."""
        out = []
        for k, w in enumerate(self.words):
            where, term, count, _ = _passages(*self.hits(w), len(w))
            for part in np.split(np.arange(len(where)), np.flatnonzero(np.diff(where)) + 1):
                if len(part):
                    out.append((k, int(where[part[0]]) * STRIDE, term[part], (1 + np.log(count[part])) * self.idf[term[part]]))
        return out

    def hold_items(self) -> None:
        """Add axes for the parts of items that the leading ones hold badly, so that none is lost in the projection."""
        parts = self.item_parts()
        rows = np.zeros((len(parts), len(self.number)), np.float32)
        for row, (_, _, term, weight) in zip(rows, parts):
            row[term] = weight / max(np.linalg.norm(weight), 1e-9)
        kept = rows @ self.axes
        poor = np.flatnonzero((kept**2).sum(1) < KEPT)
        if len(poor):
            _, size, more = np.linalg.svd(rows[poor] - kept[poor] @ self.axes.T, full_matrices=False)
            self.axes = np.ascontiguousarray(np.concatenate([self.axes, more[size > 1e-3].T], axis=1))

    def fold_items(self) -> None:
        parts = self.item_parts()
        self.part_item, self.part_start = np.array([p[0] for p in parts], np.int64), np.array([p[1] for p in parts], np.int64)
        latent = np.array([weight @ self.axes[term] for _, _, term, weight in parts], np.float32).reshape(len(parts), self.axes.shape[1])
        self.latent = latent / np.maximum(np.linalg.norm(latent, axis=1, keepdims=True), 1e-9)


def find_terms(docs: DataFrame, block: Block) -> DataFrame:
    """(doc_id, th, n_words, pos, term): where the block's terms stand in each text, written once; texts are read no more."""

    @lean
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            words = [words_of(t) for t in f["text"].tolist()]
            found = [block.hits(w) for w in words]
            made = pd.DataFrame({"n_words": [len(w) for w in words], "pos": [p.astype(np.int32) for p, _ in found], "term": [t for _, t in found]})
            yield pd.concat([f[["doc_id", "th"]].reset_index(drop=True), made], axis=1)

    slim = docs.select(filled_id(), F.xxhash64(F.coalesce("text", F.lit(""))).alias("th"), "text")
    return settle(slim.mapInPandas(run, "doc_id long, th long, n_words int, pos array<int>, term array<int>"), "terms")


def count_terms(found: DataFrame, block: Block) -> tuple[np.ndarray, int]:
    """Passages with each term, and all passages, over the whole corpus; as many rows as terms come back."""

    @lean
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        df, passages = np.zeros(len(block.number), np.int64), 0
        for f in frames:
            for pos, term, words in zip(f["pos"].tolist(), f["term"].tolist(), f["n_words"].tolist()):
                _, term, _, n = _passages(pos, term, words)
                df += np.bincount(term, minlength=len(df))
                passages += n
        at = np.flatnonzero(df)
        yield pd.DataFrame({"term": np.r_[at, -1], "df": np.r_[df[at], passages]})

    got = found.select("pos", "term", "n_words").mapInPandas(run, "term long, df long").groupBy("term").agg(F.sum("df").alias("df")).toPandas()
    df = np.zeros(len(block.number))
    own = got[got["term"] >= 0]
    df[own["term"].to_numpy()] = own["df"].to_numpy()
    return df, int(got.loc[got["term"] < 0, "df"].sum())


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def sketch_rows(seed: np.ndarray, pos: list[np.ndarray], term: list[np.ndarray], n_words: np.ndarray, idf: np.ndarray, out: np.ndarray) -> None:
    """Add the passages of some texts to ``out``, each with a random sign to a random row of it.

    Sign and row come from the text's ``seed`` and the passage's number. A term weighs its idf each time it stands there.
    """
    size = np.array([len(p) for p in pos])
    if not size.sum():
        return
    place, number, doc = np.concatenate(pos), np.concatenate(term), np.repeat(np.arange(len(size)), size)
    live = idf[number] > 0
    place, number, doc = place[live], number[live], doc[live]
    n = np.maximum(1, -(-np.maximum(0, n_words - (WINDOW - STRIDE)) // STRIDE))
    own = place // STRIDE
    first = np.minimum(own, n[doc] - 1)
    twice = (first > 0) & (own == first)
    base = np.cumsum(n) - n
    where = np.concatenate([base[doc] + first, (base[doc] + first)[twice] - 1])
    number, doc = np.concatenate([number, number[twice]]), np.concatenate([doc, doc[twice]])
    enough = np.bincount(where, minlength=int(n.sum()))[where] >= LEAST_HITS
    where, number, doc = where[enough], number[enough], doc[enough]
    h = _mixed(seed[doc] + (where - base[doc]).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    key = (h % np.uint64(len(out))).astype(np.int64) * out.shape[1] + number
    sign = np.where(h >> np.uint64(63), -1.0, 1.0)
    out += np.bincount(key, sign * idf[number], out.size).reshape(out.shape).astype(out.dtype)


def fit_axes(found: DataFrame, block: Block) -> np.ndarray:
    """Right singular vectors of a random sketch of all passages with enough weighted terms, and of the items' own rows.

    One pass: a task adds its passages up in a sketch of SKETCH rows, tasks add FAN sketches each, and the driver adds
    their few sums one after the other. The sketch's leading singular vectors are close to those of the passages.
    """
    spark, idf = found.sparkSession, block.idf
    shape = (SKETCH, len(block.number))

    @lean
    def sketch(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        out = np.zeros(shape, np.float32)
        for f in frames:
            sketch_rows(f["th"].to_numpy().astype(np.int64).view(np.uint64), f["pos"].tolist(), f["term"].tolist(), f["n_words"].to_numpy(), idf, out)
        yield pd.DataFrame({"slot": [TaskContext.get().partitionId() // FAN], "part": [out.tobytes()]})

    def add(f: pd.DataFrame) -> pd.DataFrame:
        total = np.zeros(shape, np.float32)
        for part in f["part"]:
            total += np.frombuffer(part, np.float32).reshape(shape)
        return pd.DataFrame({"part": [total.tobytes()]})

    items = np.zeros((len(block.words), shape[1]), np.float32)
    for k, _, term, weight in block.item_parts():
        items[k, term] += weight
    total = np.zeros(shape, np.float32)
    few = found.select("th", "pos", "term", "n_words").coalesce(max(1, spark.sparkContext.defaultParallelism))  # as many sketches
    for r in few.mapInPandas(sketch, "slot int, part binary").groupBy("slot").applyInPandas(add, "part binary").toLocalIterator():
        total += np.frombuffer(r["part"], np.float32).reshape(shape)
    rows = np.concatenate([total, items])
    values, vectors = np.linalg.eigh(rows @ rows.T if len(rows) < shape[1] else rows.T @ rows)
    lead = vectors[:, ::-1][:, :RANK]
    if len(rows) < shape[1]:
        lead = rows.T @ (lead[:, values[::-1][:RANK] > 1e-6 * max(values[-1], 1e-30)])
    return np.ascontiguousarray(np.linalg.qr(lead)[0].astype(np.float32))


def lcs_length(item: list, words: list) -> int:
    """Longest common subsequence, a machine word of the item's places at a time."""
    places: dict = {}
    for k, w in enumerate(item):
        places[w] = places.get(w, 0) | 1 << k
    full = (1 << len(item)) - 1
    v = full
    for w in words:
        m = places.get(w)
        if m is not None:
            u = v & m
            v = (v + u | v - u) & full
    return len(item) - v.bit_count()


def search(found: DataFrame, block: Block) -> DataFrame:
    wanted = [block.numbers(w).tolist() for w in block.words]

    @lean
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            out = []
            for doc, th, n_words, pos, term in zip(f["doc_id"].tolist(), f["th"].tolist(), f["n_words"].tolist(), f["pos"].tolist(), f["term"].tolist()):
                items = block.answered(term)
                if not len(items):
                    continue
                where, latent = block.project(*block.rows(pos, term, n_words))
                parts = np.flatnonzero(np.isin(block.part_item, items))
                cosine = latent @ block.latent[parts].T
                best: dict[int, tuple[float, float, float]] = {}
                for row, col in zip(*np.nonzero(cosine >= COSINE)):
                    item = int(block.part_item[parts[col]])
                    size = len(wanted[item])
                    reach = size // 2 + 2
                    begin = int(block.part_start[parts[col]])  # of the part in the item
                    start = int(where[row]) * STRIDE
                    lo, hi = np.searchsorted(pos, (start - begin - reach, start + max(WINDOW, size - begin) + reach))
                    near = term[lo:hi].tolist()  # words that are no terms match nothing
                    answer = block.answers[item]
                    there = len(answer.intersection(near)) / max(1, len(answer))
                    if there < ANSWER:
                        continue
                    lcs = lcs_length(wanted[item], near) / size
                    if lcs >= LCS:
                        best[item] = max(best.get(item, (0.0, 0.0, 0.0)), (lcs, float(cosine[row, col]), there))
                out += [(doc, th, block.ids[i], c, lcs, a) for i, (lcs, c, a) in best.items()]
            yield pd.DataFrame(out, columns=["doc_id", "th", "item_id", "cosine", "lcs_share", "answer_share"])

    return unfilled(found.mapInPandas(run, "doc_id long, th long, item_id long, cosine double, lcs_share double, answer_share double"))


def leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, th, item_id, cosine, lcs_share, answer_share): one row for each document row and item that it holds.

    th is the hash of the text. Null texts and items without words match nothing; repeated items or rows give repeated rows;
    an empty benchmark gives an empty table. Items are searched in blocks of ITEMS_AT_ONCE, so what a
    task is sent stays bounded however large the benchmark is.
    """
    spark = docs.sparkSession
    n_items = benchmark.count()
    blocks = max(1, -(-n_items // ITEMS_AT_ONCE))
    found = None
    for b in range(blocks):
        own = benchmark.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == b)
        items = [(r["item_id"], r["text"]) for r in own.select("item_id", "text").collect()]  # one block
        block = Block([(i, t) for i, t in items if words_of(t)])
        if not block.ids:
            continue
        terms = find_terms(docs, block)
        block.weigh(*count_terms(terms, block))
        block.axes = fit_axes(terms, block)
        block.hold_items()
        block.fold_items()
        got = search(terms, block)
        found = got if found is None else found.union(got)
    if found is None:
        return spark.createDataFrame([], "doc_id long, th long, item_id long, cosine double, lcs_share double, answer_share double")
    return found


def op10_latent_decontam(spark: SparkSession, sf_dir: str) -> DataFrame:
    arrow_rows(spark, 1_000)
    return leaks(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet")).drop("th")
