"""Operator 3: token ids in Simple-8b words.

A 64-bit word has a selector in its top four bits and as many ids as fit, all of one width, in the
other sixty. Ids wider than sixty bits cannot occur; ids of over ESCAPE_BITS bits are escaped: the
word holds the all-ones code and the ids follow in a list of their own. A block holds the words of
neighbouring documents with offsets, so a reader decodes all of a block at once, or a part of it,
without walking from the start.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator
from itertools import chain, repeat

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import documents, filled_id, scratch, settle, unfilled
from .word_split import is_plain

# Fixed values of the format: ids in a word, bits of each; selector = place in the list.
COUNTS = (60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1)
WIDTHS = (1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60)
ESCAPE_BITS = 20  # wider ids are escaped, so that one of them doesn't waste its neighbours' bits
ESCAPE = (1 << ESCAPE_BITS) - 1
KEPT_WORDS = 1_200_000  # bound of a worker's memory of words
BLOCK_IDS = 1 << 19


_BITS = np.maximum(np.frexp(np.arange(ESCAPE + 1, dtype=np.float64))[1], 1).astype(np.int8)  # of each id up to the escape


def pack(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words and escaped ids of one document's ids (unsigned 64-bit)."""
    ids = np.asarray(ids, np.uint64)
    wide = ids >= ESCAPE
    escaped = ids[wide]
    v = np.where(wide, np.uint64(ESCAPE), ids)
    n = len(v)
    if not n:
        return np.zeros(0, np.uint64), escaped
    bits = _BITS[np.minimum(v, ESCAPE).astype(np.int64)]
    least = int(bits.min())
    # a selector fits where all of its count of ids have its width or less; a fuller one fits nowhere else,
    # so the number of selectors that fit gives the fullest
    pick = np.full(n, len(COUNTS), np.int8)
    for s in range(len(COUNTS) - 1, -1, -1):
        c, w = COUNTS[s], WIDTHS[s]
        if w < least or c > n:
            break
        fits, span = bits <= w, 1
        while span < c:  # all of the next c ids, by doubling
            more = min(span, c - span)
            fits, span = fits[: len(fits) - more] & fits[more:], span + more
        if not fits.any():
            break
        pick[: n + 1 - c] -= fits
    step = np.array(COUNTS)[pick].tolist()
    at, heads = 0, []
    while at < n:
        heads.append(at)
        at += step[at]
    heads = np.array(heads)
    chosen = pick[heads]
    words = chosen.astype(np.uint64) << np.uint64(60)
    for s in np.unique(chosen):
        rows = np.flatnonzero(chosen == s)
        c, w = COUNTS[s], WIDTHS[s]
        got = v[heads[rows][:, None] + np.arange(c)]
        words[rows] |= np.bitwise_or.reduce(got << (np.arange(c, dtype=np.uint64) * np.uint64(w)), axis=1)
    return words, escaped


def unpack(words: np.ndarray, escaped: np.ndarray) -> np.ndarray:
    """All ids of a run of words, selector by selector."""
    s = (words >> np.uint64(60)).astype(np.int64)
    counts = np.array(COUNTS)[s]
    ends = np.cumsum(counts)
    out = np.empty(int(ends[-1]) if len(ends) else 0, np.uint64)
    for k in np.unique(s):
        rows = np.flatnonzero(s == k)
        c, w = COUNTS[k], WIDTHS[k]
        shift = np.arange(c, dtype=np.uint64) * np.uint64(w)
        got = (words[rows][:, None] >> shift) & np.uint64((1 << w) - 1)
        out[(ends[rows] - c)[:, None] + np.arange(c)] = got
    out[out == ESCAPE] = escaped
    return out


_LETTER, _DIGIT, _MARK, _SPACE, _END = range(5)
_CLASS = np.full(256, _LETTER, np.int8)  # of a byte of plain text; beyond ASCII all are letters there
_CLASS[0x21:0x7F] = _MARK
_CLASS[ord("0") : ord("9") + 1] = _DIGIT
_CLASS[ord("A") : ord("Z") + 1] = _CLASS[ord("a") : ord("z") + 1] = _LETTER
_CLASS[[*range(0x09, 0x0E), 0x20]] = _SPACE
_CLASS[0] = _END


def word_starts(raw: np.ndarray) -> np.ndarray:
    """Where the pre-tokens of plain UTF-8 texts begin; a zero byte ends each text and is a word itself.

    A word is a run of one class with a blank before it, if there is one; of a longer white run that a word
    follows, the last character stands apart. Clitics after an apostrophe are words where no blank or mark is
    before them.
    """
    kind = _CLASS[raw]
    blank = raw == 0x20
    turn = np.r_[True, kind[1:] != kind[:-1]]
    begins = turn | (kind == _END)
    begins[1:] &= ~(blank[:-1] & (kind[1:] < _SPACE))
    last = (kind[:-1] == _SPACE) & (kind[1:] < _SPACE)
    begins[:-1] |= last
    at = np.flatnonzero(begins & (raw == ord("'")))
    at = at[at + 2 < len(raw)]
    one, two = raw[at + 1], raw[at + 2]
    short = np.isin(one, np.frombuffer(b"stmd", np.uint8))
    long = ((two == ord("e")) & ((one == ord("r")) | (one == ord("v")))) | ((one == ord("l")) & (two == ord("l")))
    begins[at[short] + 1] = begins[at[long] + 1] = False
    begins[at[short] + 2] = begins[at[long] + 3] = True
    return np.flatnonzero(begins)


class WordIds:
    """Per worker: a pre-token's ids, from the tokenizers library; whole texts where the split isn't plain.

    The string of one of the vocabulary's special tokens in a text is that token, as in a plain call of the
    library, unless ``special_as_text`` asks for it as ordinary text.
    """

    _of_path: dict[tuple[str, bool], WordIds] = {}

    def __init__(self, path: str, special_as_text: bool = False):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = special_as_text
        self.special = [] if special_as_text else [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.of_words = Tokenizer.from_file(path)  # for words that are split already: parts at blanks only
        self.of_words.encode_special_tokens = True
        parts = [pre_tokenizers.Split(" ", "merged_with_next"), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)]
        self.of_words.pre_tokenizer = pre_tokenizers.Sequence(parts)
        self.spaced = np.zeros(self.tokenizer.get_vocab_size(), np.int64)
        for piece, k in self.tokenizer.get_vocab().items():
            self.spaced[k] = piece.startswith("Ġ")
        self._forget()

    def _forget(self) -> None:
        """word -> its number; the ids of word k are flat[start[k] : start[k] + length[k]]. Word 0 ends a text."""
        self.number: dict[str, int] = {"\0": 0}
        self.flat, self.start, self.length = np.zeros(1, np.uint64), np.zeros(1, np.int64), np.ones(1, np.int64)

    @classmethod
    def at(cls, path: str, special_as_text: bool = False) -> WordIds:
        if (path, special_as_text) not in cls._of_path:
            cls._of_path[path, special_as_text] = cls(path, special_as_text)
        return cls._of_path[path, special_as_text]

    def _whole(self, text: str) -> bool:
        """Is the text for the library as it stands?"""
        return not is_plain(text) or any(t in text for t in self.special)

    def _learn(self, words: list[str]) -> None:
        """Words that begin with a space and go on with letters stay apart when joined: one call for many of them."""
        apart, rest = [], []
        for w in words:
            (apart if w[0] == " " and w[1:].isalpha() else rest).append(w)
        flat, lengths = [self.flat], [self.length]
        joined = ["".join(apart[at : at + 2000]) for at in range(0, len(apart), 2000)]
        for got in self.of_words.encode_batch_fast(joined, add_special_tokens=False):
            own = np.array(got.ids, np.uint64)
            flat.append(own)
            lengths.append(np.bincount(np.cumsum(self.spaced[own]) - 1))  # a word's first token alone begins with the space
        ids = [e.ids for e in self.tokenizer.encode_batch_fast(rest, add_special_tokens=False)]
        flat.append(np.array(list(chain.from_iterable(ids)), np.uint64))
        lengths.append(np.array([len(i) for i in ids], np.int64))
        self.number.update(zip(apart + rest, range(len(self.number), len(self.number) + len(words))))
        self.flat, self.length = np.concatenate(flat), np.concatenate(lengths)
        self.start = np.cumsum(self.length) - self.length

    def encode_all(self, texts: list[str], end_id: int) -> tuple[np.ndarray, list[int]]:
        """The ids of all texts in a row, each with ``end_id`` after it, and how many each has.

        Words are split and told apart in bulk; the memory is asked once for each different word.
        """
        if not texts:
            return np.zeros(0, np.uint64), []
        odd = {k: np.array(self.tokenizer.encode(t, add_special_tokens=False).ids, np.uint64) for k, t in enumerate(texts) if self._whole(t)}
        raw = np.frombuffer("\0".join(["" if k in odd else t for k, t in enumerate(texts)] + [""]).encode(), np.uint8)
        starts = word_starts(raw)
        bounds = pa.py_buffer(np.append(starts, len(raw)).astype(np.int64))
        coded = pa.LargeStringArray.from_buffers(len(starts), bounds, pa.py_buffer(raw)).dictionary_encode()
        words = coded.dictionary.to_pylist()
        if len(self.number) > KEPT_WORDS:
            self._forget()
        known = np.fromiter(map(self.number.get, words, repeat(-1)), np.int64, len(words))
        missed = np.flatnonzero(known < 0)
        if len(missed):
            new = [words[i] for i in missed.tolist()]
            self._learn(new)
            known[missed] = np.fromiter(map(self.number.__getitem__, new), np.int64, len(new))
        k = known[coded.indices.to_numpy()]
        length = self.length[k]
        ends = np.cumsum(length)
        flat = self.flat[np.repeat(self.start[k] - ends + length, length) + np.arange(int(ends[-1]))]
        close = ends[k == 0]  # of each text
        flat[close - 1] = end_id
        counts = np.diff(close, prepend=0)
        if odd:
            cuts = [int(close[k]) - 1 for k in odd]
            pieces = np.split(flat, cuts)
            flat = np.concatenate([pieces[0], *chain.from_iterable(zip(odd.values(), pieces[1:]))])
            counts[list(odd)] += [len(x) for x in odd.values()]
        return flat, counts.tolist()


BLOCK = "shard int, block int, doc_ids array<long>, n_tokens array<long>, every array<int>, words binary, escapes binary"
EVERY = 1024  # words between two kept offsets


def write_token_file(docs: DataFrame, path: str, vocabulary: str, end_id: int = 0, special_as_text: bool = False) -> None:
    """Encode ``docs`` and write the file: Parquet rows, each one block, in ascending doc_id order.

    Rows are dealt by ranges of doc_id and sorted inside a range; the shard number is the range's.
    A block packs the ids of neighbouring documents as one run of words; ``every`` has the number of
    ids before each EVERY-th word, so a reader can begin inside a block. A null text counts as empty
    (only the end id), a null doc_id sorts first, equal ids sort by text, an empty table gives no block.
    """

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        coder, shard, block = WordIds.at(vocabulary, special_as_text), TaskContext.get().partitionId(), 0
        doc_ids: list = []
        counts: list[int] = []
        parts: list[np.ndarray] = []

        def close() -> pd.DataFrame:
            nonlocal block
            words, escaped = pack(np.concatenate(parts))
            held = np.array(COUNTS)[(words >> np.uint64(60)).astype(np.int64)]
            every = (np.cumsum(held) - held)[::EVERY]
            row = (shard, block, doc_ids[:], counts[:], every, words.astype("<u8").tobytes(), escaped.astype("<u8").tobytes())
            block += 1
            for x in (doc_ids, counts, parts):
                x.clear()
            return pd.DataFrame([row], columns=[c.split()[0] for c in BLOCK.split(", ")])

        for frame in frames:
            texts = frame["text"].fillna("").tolist()
            ids_of = frame["doc_id"].tolist()
            at = 0
            while at < len(texts):
                upto, chars = at, 0
                while upto < len(texts) and chars < 3_000_000:
                    chars, upto = chars + len(texts[upto]), upto + 1
                ids, own = coder.encode_all(texts[at:upto], end_id)
                doc_ids += ids_of[at:upto]
                counts += own
                parts.append(ids)
                at = upto
                if sum(map(len, parts)) >= BLOCK_IDS or len(doc_ids) >= 4096:
                    yield close()
        if doc_ids:
            yield close()

    (
        docs.select(filled_id(), "text")  # the file, too, has the least long for none
        .repartitionByRange(F.col("doc_id"))
        .sortWithinPartitions("doc_id", "text")
        .mapInPandas(run, BLOCK)
        .write.option("compression", "zstd")
        .parquet(path)
    )


def read_token_file(spark: SparkSession, path: str) -> DataFrame:
    """Blocks with ``start``, the number of ids in all blocks before; shards first, then inside a shard."""
    blocks = spark.read.schema(BLOCK).parquet(path)
    sizes = blocks.select("shard", "block", F.aggregate("n_tokens", F.lit(0).cast("long"), lambda a, x: a + x).alias("n"))
    shards = sizes.groupBy("shard").agg(F.sum("n").alias("n"))  # one row a shard: a bounded window
    shards = shards.select("shard", (F.sum("n").over(W.orderBy("shard")) - F.col("n")).alias("before"))
    inside = F.sum("n").over(W.partitionBy("shard").orderBy("block")) - F.col("n")
    starts = sizes.withColumn("inside", inside).join(shards, "shard")
    starts = settle(starts.select("shard", "block", (F.col("before") + F.col("inside")).alias("start")), "starts")
    return blocks.join(starts, ["shard", "block"])  # written first: while its size is small, blocks aren't shuffled


def decode_documents(blocks: DataFrame, with_ids: bool = False) -> DataFrame:
    """One row per document of the file: doc_id, start, n_tokens, ids_crc32 (and the ids if asked for)."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for b in frame.itertuples(index=False):
                ids = unpack(np.frombuffer(b.words, "<u8"), np.frombuffer(b.escapes, "<u8")).astype("<u4")
                ends = np.cumsum(b.n_tokens)
                starts = ends - np.asarray(b.n_tokens)
                made = {
                    "doc_id": b.doc_ids,
                    "start": b.start + starts,
                    "n_tokens": np.asarray(b.n_tokens),
                    "ids_crc32": [zlib.crc32(ids[i:j]) for i, j in zip(starts, ends)],
                }
                if with_ids:
                    made["ids"] = [ids[i:j].astype(np.int64) for i, j in zip(starts, ends)]
                yield pd.DataFrame(made)

    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids
    return unfilled(blocks.drop("every").mapInPandas(run, schema))


def op3_simple8b(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = scratch(spark, "simple8b")
    write_token_file(documents(spark, sf_dir), path, public_tokenizers.path("byte_bpe_50k.json"))
    return decode_documents(read_token_file(spark, path))
