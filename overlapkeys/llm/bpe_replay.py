"""Operator 5: byte-level BPE by corpus-level merge replay.

All words that a batch of texts has and that are not known yet are laid out as one array of tokens.
An inverted index gives the positions of each token pair; the merges present are applied in rank
order, each at all its positions at once, and only the pairs that touch a merged position are
indexed anew. Results are kept per word, so a text costs one look-up a word.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterable, Iterator
from itertools import islice

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from .common import documents, filled_id, lean, unfilled
from .word_split import pretokens

KEPT_WORDS = 450_000  # bound of a worker's memory of words
FIRST_WORDS = 120_000  # the words learnt first, the most frequent ones, stay beyond it and between tasks


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class MergeReplay:
    def __init__(self, ranks: dict[bytes, int]):
        self.piece = {i: b for b, i in ranks.items()}
        self.single = [ranks[bytes([i])] for i in range(256)]
        self.rank_of = ranks
        self.whole = ranks.get
        self.byte = np.array(self.single, np.int32)
        self.pairs: dict[tuple[int, int], int | None] = {}
        self.first = np.array([[self._merged(a, b) or -1 for b in self.single] for a in self.single], np.int32)

    def _merged(self, a: int, b: int) -> int | None:
        """The token that a and b make; its id is the merge's rank."""
        try:
            return self.pairs[a, b]
        except KeyError:
            made = self.pairs[a, b] = self.rank_of.get(self.piece[a] + self.piece[b])
            return made

    def encode_words(self, words: list[bytes]) -> list[list[int]]:
        """Token ids of each word; words are independent of each other."""
        pairs, merged = self.pairs, self._merged
        out: list = [None] * len(words)
        left_over, starts, n = [], [], 0
        for k, w in enumerate(words):
            known = self.whole(w)
            if known is not None:  # a word of the vocabulary is one token
                out[k] = [known]
                continue
            starts.append((k, n, len(w)))
            left_over.append(w)
            n += len(w) + 1
        if not starts:
            return out
        raw = np.frombuffer(b" ".join([*left_over, b""]), np.uint8)
        walls = np.cumsum([len(w) + 1 for w in left_over]) - 1
        # the index of the first pairs: by byte, then sorted by the merge and the position
        made_of = self.first[raw[:-1], raw[1:]]
        made_of[walls[:-1]] = made_of[walls - 1] = -1
        at_all = np.flatnonzero(made_of >= 0)
        at_all = at_all[np.argsort(made_of[at_all], kind="stable")]
        cuts = np.flatnonzero(np.diff(made_of[at_all])) + 1
        index: dict[int, list[int]] = {}
        if len(at_all):
            index = {int(made_of[run[0]]): run.tolist() for run in np.split(at_all, cuts)}
        tokens = self.byte[raw]
        tokens[walls] = -1  # between words
        token: list[int] = tokens.tolist()
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        queue = list(index)
        heapq.heapify(queue)
        while queue:
            made = heapq.heappop(queue)
            places = index.pop(made, None)
            if places is None:
                continue
            places.sort()  # left to right, as overlapping places need
            for k, at in enumerate(places):
                if queue and queue[0] < made:  # a new pair outranks this merge: it goes first
                    index[made] = places[k:] + index.get(made, [])
                    heapq.heappush(queue, made)
                    break
                left, nxt = token[at], after[at]
                if left < 0:
                    continue
                right = token[nxt]
                if right < 0 or pairs.get((left, right)) != made:
                    continue  # a neighbour was merged away meanwhile
                token[at] = made
                token[nxt] = -2
                nxt = after[at] = after[nxt]
                before[nxt if nxt < n else -1] = at
                # only the two pairs that touch the merged place are indexed anew
                t = token[nxt]
                if t >= 0:
                    try:
                        new = pairs[made, t]
                    except KeyError:
                        new = merged(made, t)
                    if new is not None:
                        if new in index:
                            index[new].append(at)
                        else:
                            index[new] = [at]
                            heapq.heappush(queue, new)
                prev = before[at]
                if prev >= 0 and (t := token[prev]) >= 0:
                    try:
                        new = pairs[t, made]
                    except KeyError:
                        new = merged(t, made)
                    if new is not None:
                        if new in index:
                            index[new].append(prev)
                        else:
                            index[new] = [prev]
                            heapq.heappush(queue, new)
        for k, start, length in starts:
            out[k] = [t for t in token[start : start + length] if t >= 0]
        return out

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.piece.__getitem__, ids))


class WordMemory:
    """Per worker: word -> (ids as text, number of ids, decoded bytes)."""

    _of_path: dict[str, WordMemory] = {}

    def __init__(self, path: str):
        self.replay = MergeReplay(load_ranks(path))
        self.known: dict[str, tuple[str, int, bytes]] = {}

    @classmethod
    def at(cls, path: str) -> WordMemory:
        if path not in cls._of_path:
            cls._of_path[path] = cls(path)
        return cls._of_path[path]

    def trim(self, first_words: int = FIRST_WORDS) -> None:
        if len(self.known) > first_words:
            self.known = dict(islice(self.known.items(), first_words))

    def learn(self, split: list[list[str]], kept_words: int = KEPT_WORDS) -> None:
        if len(self.known) > kept_words:
            self.trim(min(FIRST_WORDS, kept_words // 3))
        fresh = list(set().union(*split).difference(self.known)) if split else []
        decode = self.replay.decode
        for w, ids in zip(fresh, self.replay.encode_words([w.encode() for w in fresh])):
            self.known[w] = ",".join(map(str, ids)), len(ids), decode(ids)


def _batches(texts: list[str], chars: int = 4_000_000) -> Iterator[list[str]]:
    """Runs of whole texts of about so many characters, which bounds what a replay holds."""
    run, held = [], 0
    for t in texts:
        run.append(t)
        held += len(t)
        if held >= chars:
            yield run
            run, held = [], 0
    if run:
        yield run


def encode_documents(docs: DataFrame, path: str, with_ids: bool = False, kept_words: int = KEPT_WORDS) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids if asked for).

    A null text counts as empty: no ids, the digest of nothing. Repeated rows give repeated rows, an
    empty table an empty one. Texts are independent, so there is no shuffle.
    """

    @lean
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        memory = WordMemory.at(path)
        for frame in frames:
            rows = []
            for texts in _batches(frame["text"].fillna("").tolist()):
                split = [pretokens(t) for t in texts]
                memory.learn(split, kept_words)
                get = memory.known.__getitem__
                for words in split:
                    got = list(map(get, words))
                    ids = ",".join([g[0] for g in got])
                    row = (
                        sum([g[1] for g in got]),
                        hashlib.sha256(ids.encode()).hexdigest(),
                        hashlib.sha256(b"".join([g[2] for g in got])).hexdigest(),
                    )
                    rows.append((*row, list(map(int, ids.split(","))) if ids else []) if with_ids else row)
            names = ["n_tokens", "ids_sha256", "decoded_sha256"] + ["ids"] * with_ids
            made = pd.DataFrame(rows, columns=names)
            made.insert(0, "doc_id", frame["doc_id"].to_numpy())
            yield made
        memory.trim(min(FIRST_WORDS, kept_words // 3))  # a worker goes on to other stages

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return unfilled(docs.select(filled_id(), "text").mapInPandas(run, schema))


def op5_bpe_merge_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return encode_documents(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
