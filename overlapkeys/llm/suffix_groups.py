"""Operator 4: removal of bytes covered by repeated 400-byte strings, with suffix arrays by linear grouping.

Candidates. Of every 400-byte string some 192-byte gram is the least by hash (its anchor), and equal
strings have the same one at the same place. Only anchors whose hash repeats matter. An anchor and what
may lie around it inside such strings is its segment. Equal segments are counted, never paired. The least grams
of 320-byte strings are looked up alike, but only counted: they tell of repeats too short to be removed.

Decision. Different segments of one anchor go to suffix arrays: the bytes around the anchor are named by
blocks of sixteen, aligned to it, and the arrays of the names bring together all segments that share
eight blocks and the anchor. Within such a class the last sixteen bytes decide, for each place where a string may start.
"""

from __future__ import annotations

import gc
import hashlib
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_rows, documents, in_told, join_by_share, settle

LENGTH, GRAM = 400, 192
SHORT = 320  # bytes of a string that has a counted gram
SIDE = LENGTH - GRAM  # bytes that a string can have on either side of its anchor
BLOCK = 16
BLOCKS = SIDE // BLOCK
SPLIT_OVER = 1000  # anchors with more different segments are dealt by what follows and precedes them


# ---- suffix arrays ----
def suffix_array(text: list[int]) -> list[int]:
    """Start positions of the sorted suffixes of ``text``.

    Suffixes first share a group if they share the first symbol. Groups are taken from the greatest
    down: a member's previous-smaller pointer leads to the suffix that its group's prefix continues,
    and suffixes move to a greater group by how many members point at them, which leaves one group
    for each Lyndon prefix. The order inside a group follows from the suffixes after those prefixes,
    which are smaller and so come out earlier.
    """
    n = len(text)
    if not n:
        return []
    first: dict[int, list[int]] = {}
    for i, c in enumerate(text):
        first.setdefault(c, []).append(i)
    members: list[list[int]] = [first[c] for c in sorted(first)]
    above = [*range(1, len(members)), -1]
    below = [-1, *range(len(members) - 1)]
    group = [0] * n
    for g, own in enumerate(members):
        for i in own:
            group[i] = g
    done, back = bytearray(n), [-1] * n
    g = len(members) - 1
    while g >= 0:
        own = sorted(i for i in members[g] if group[i] == g)  # moved ones are left behind lazily
        members[g] = own
        for i in own:
            done[i] = 1
        pointed: dict[int, int] = {}
        for i in own:
            p = i - 1
            while p >= 0 and done[p]:
                p = back[p]
            back[i] = p
            if p >= 0:
                pointed[p] = pointed.get(p, 0) + 1
        if pointed:
            by_count: dict[int, dict[int, list[int]]] = {}
            for p, k in pointed.items():
                by_count.setdefault(k, {}).setdefault(group[p], []).append(p)
            for k in sorted(by_count, reverse=True):
                for old, movers in by_count[k].items():
                    new = len(members)
                    members.append(movers)
                    over = above[old]
                    above.append(over)
                    below.append(old)
                    above[old] = new
                    if over >= 0:
                        below[over] = new
                    for p in movers:
                        group[p] = new
        g = below[g]
    # the least group is at the end of the chain below; free[g] is the next free place of a group
    chain, g = [], 0
    while below[g] >= 0:
        g = below[g]
    while g >= 0:
        chain.append(g)
        g = above[g]
    free, at = {}, 1
    for g in chain:
        free[g] = at
        at += len(members[g])
    out, placed = [-1] * (n + 1), bytearray(n)
    out[0] = n  # the empty suffix
    for k in range(n + 1):
        s = out[k] - 1
        while s >= 0 and not placed[s]:
            placed[s] = 1
            g = group[s]
            out[free[g]] = s
            free[g] += 1
            s = back[s]
    return out[1:]


# ---- anchors ----
def _gram_hashes(b: np.ndarray) -> np.ndarray:
    """A hash of the GRAM bytes from each place on, joined from those of 64 and 128 bytes."""
    h, base, span = b.astype(np.uint64) + np.uint64(1), np.uint64(0x9E3779B97F4A7C15), 1
    with np.errstate(over="ignore"):
        while span < 64:
            h = h[:-span] * base + h[span:]
            base, span = base * base, span * 2
        half = h
        h = h[:-span] * base + h[span:]
        h = h[:-span] * base + half[2 * span :]
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def _over_windows(x: np.ndarray, width: int, pick: np.ufunc) -> np.ndarray:
    span = 1
    while span < width:
        more = min(span, width - span)
        x, span = pick(x[:-more], x[more:]), span + more
    return x


def _least(h: np.ndarray, width: int) -> np.ndarray:
    """Which of ``h`` are least (ties included) in some window of ``width``."""
    if len(h) < width:
        return np.zeros(len(h), bool)
    least = _over_windows(h, width, np.minimum)
    reach = np.zeros(len(h) + width - 1, np.uint64)
    reach[width - 1 : width - 1 + len(least)] = least
    return _over_windows(reach, width, np.maximum)[: len(h)] == h


def anchors(b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Positions and hashes of the grams that are least in some SHORT-byte string; which are in one of LENGTH bytes, too."""
    if len(b) < SHORT:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, bool)
    h = _gram_hashes(b)
    at = np.flatnonzero(_least(h, SHORT - GRAM + 1))
    return at, h[at], _least(h, SIDE + 1)[at]


def segment(raw: bytes, at: int) -> tuple[bytes, int]:
    left = min(at, SIDE)
    return raw[at - left : at + LENGTH], left


# ---- classes of segments ----
@contextmanager
def _uncollected() -> Iterator[None]:
    """No search for garbage cycles: the many lists of a suffix array make none, but each search walks them."""
    on = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if on:
            gc.enable()


def _hopeful(group: np.ndarray, sides: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Rows that share half of what a class shares, on one side of the anchor, with another row of their group.

    Strings of a class have BLOCKS - 1 whole blocks around the anchor in common, so at least half of them on one side.
    """
    span = BLOCK * (BLOCKS // 2)
    odd = np.random.default_rng(0).integers(0, 1 << 62, span // 8).astype(np.uint64) * np.uint64(2) + np.uint64(1)
    keep = np.zeros(len(group), bool)
    for own, near in ((left, sides[:, SIDE - span : SIDE]), (right, sides[:, SIDE : SIDE + span])):
        at = np.flatnonzero(own >= span)
        h = (np.ascontiguousarray(near[at]).view("<u8") * odd).sum(1, dtype=np.uint64)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) ^ group[at].view(np.uint64)
        order = np.argsort(h)
        same = h[order][1:] == h[order][:-1]
        keep[at[order[np.r_[False, same] | np.r_[same, False]]]] = True
    return keep


def repeated_places(rows: list[tuple[int, bytes, int, int]]) -> tuple[np.ndarray, np.ndarray]:
    """For each (group, segment, left, window): least and greatest number of bytes before the anchor of
    the 400-byte strings that another row of the group has too; (1, 0) if there is none.

    window: -1 for all, else only strings with that many whole blocks before the anchor.
    """
    n = len(rows)
    least, most = np.ones(n, np.int64), np.zeros(n, np.int64)
    left = np.array([r[2] for r in rows], np.int64)
    right = np.array([len(r[1]) - r[2] - GRAM for r in rows], np.int64)
    sides = np.frombuffer(b"".join(r[1][: r[2]].rjust(SIDE, b"\0") + r[1][r[2] + GRAM :].ljust(SIDE, b"\0") for r in rows), np.uint8).reshape(n, 2 * SIDE)
    own = np.flatnonzero(_hopeful(np.array([r[0] for r in rows], np.int64), sides, left, right))
    if len(own):
        least[own], most[own] = _by_suffixes([rows[k] for k in own.tolist()], sides[own], left[own], right[own])
    return least, most


def _by_suffixes(rows: list[tuple[int, bytes, int, int]], sides: np.ndarray, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    n = len(rows)
    least, most = np.full(n, SIDE + 1), np.full(n, -1)
    # fixed places: SIDE bytes before the anchor, SIDE after, nearest first in blocks
    sides = sides.reshape(n, 2 * BLOCKS, BLOCK)
    before, after = sides[:, :BLOCKS][:, ::-1], sides[:, BLOCKS:]
    named = np.ascontiguousarray(sides).view(f"V{BLOCK}").reshape(n, 2 * BLOCKS)
    name = np.unique(named, return_inverse=True)[1].reshape(n, 2 * BLOCKS).astype(np.int64)
    whole = np.concatenate([(left[:, None] >= BLOCK * np.arange(BLOCKS, 0, -1)), (right[:, None] >= BLOCK * np.arange(1, BLOCKS + 1))], axis=1)
    spare = name.max() + 1 + np.arange(name.size).reshape(name.shape)  # blocks that are cut off match nothing
    name = np.where(whole, name, spare)
    gram = [(r[0], xxhash.xxh3_128_digest(r[1][r[2] : r[2] + GRAM])) for r in rows]
    of_gram = {g: k for k, g in enumerate(dict.fromkeys(gram))}
    top = int(spare.max()) + 1
    middle = np.array([of_gram[g] for g in gram])[:, None] + top
    end = (top + len(of_gram) + np.arange(n))[:, None]
    line = np.concatenate([name[:, :BLOCKS], middle, name[:, BLOCKS:], end], axis=1)
    width = line.shape[1]
    with _uncollected():
        order = np.array(suffix_array(line.ravel().tolist()))
    row, col = order // width, order % width
    blocks = BLOCKS - col  # whole blocks before the anchor of the string class that begins here
    window = np.array([r[3] for r in rows])
    fit = (col >= 1) & (col <= BLOCKS) & ((window[row] < 0) | (window[row] == blocks))
    fit &= (left[row] >= BLOCK * blocks) & (right[row] >= BLOCK * (BLOCKS - 1 - blocks))
    row, blocks, col = row[fit], blocks[fit], col[fit]
    if not len(row):
        return least, most
    shape = line[row[:, None], col[:, None] + np.arange(BLOCKS)]
    new = np.r_[True, (shape[1:] != shape[:-1]).any(axis=1)]
    kind = np.cumsum(new) - 1
    several = np.bincount(kind)[kind] > 1
    row, blocks, kind = row[several], blocks[several], kind[several]
    edge = np.concatenate([before[row, blocks], after[row, BLOCKS - 1 - blocks]], axis=1)
    for b in range(BLOCK + 1):
        t = BLOCK * blocks + b
        ok = np.flatnonzero((t <= left[row]) & (SIDE - t <= right[row]))
        if not len(ok):
            continue
        piece = np.ascontiguousarray(edge[ok, BLOCK - b : 2 * BLOCK - b]).view("<u8")
        rank = np.lexsort((piece[:, 1], piece[:, 0], kind[ok]))
        k, p = kind[ok][rank], piece[rank]
        same = (k[1:] == k[:-1]) & (p[1:] == p[:-1]).all(axis=1)
        hit = ok[rank[np.r_[False, same] | np.r_[same, False]]]
        np.minimum.at(least, row[hit], t[hit])
        np.maximum.at(most, row[hit], t[hit])
    return np.where(most < 0, 1, least), np.maximum(most, 0)


# ---- the distributed flow ----
def _numbered(docs: DataFrame) -> DataFrame:
    """doc_id (null: the least id), th (32 bits that part equal ids of other texts), text."""
    text = F.coalesce("text", F.lit(""))
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("doc_id"), F.hash(text).alias("th"), text.alias("text"))


def _occurrences(docs: DataFrame, places: bool) -> DataFrame:
    """The hashes of all anchors, with their places if asked for; ``at`` is ~place for grams that are only counted."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            ids, ths, texts = f["doc_id"].to_numpy(), f["th"].to_numpy(), f["text"].tolist()
            for lo in range(0, len(f), 500):
                got, digests = [], []
                for text in texts[lo : lo + 500]:
                    raw = text.encode("utf-8", "surrogatepass")
                    at, h, long = anchors(np.frombuffer(raw, np.uint8))
                    got.append((np.where(long, at, ~at), h))
                    if places:
                        digests += [xxhash.xxh3_64_intdigest(raw[max(0, p - SIDE) : p + LENGTH], min(p, SIDE)) if far else 0 for p, far in zip(at.tolist(), long.tolist())]
                size = [len(a) for a, _ in got]
                out = {"h": np.concatenate([h for _, h in got]).view(np.int64)}
                if places:
                    out |= {"sh": np.array(digests, np.uint64).view(np.int64), "doc_id": np.repeat(ids[lo : lo + 500], size), "th": np.repeat(ths[lo : lo + 500], size), "at": np.concatenate([a for a, _ in got]).astype(np.int32)}
                yield pd.DataFrame(out)

    return docs.mapInPandas(run, "h long, sh long, doc_id long, th int, at int" if places else "h long")


def _decide(rows: DataFrame) -> DataFrame:
    """(h, sh, least, most) from (g, h, sh, left, window, seg), dealt by g."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = None

        def decided(part: pd.DataFrame) -> pd.DataFrame:
            part = part.drop_duplicates(["g", "h", "sh", "window"])
            low, high = repeated_places(list(zip(part["g"].tolist(), part["seg"].tolist(), part["left"].tolist(), part["window"].tolist())))
            out = pd.DataFrame({"h": part["h"].to_numpy(), "sh": part["sh"].to_numpy(), "least": low.astype(np.int32), "most": high.astype(np.int32)})
            return out[low <= high]

        for f in frames:
            held = f if held is None else pd.concat([held, f])
            if len(held) < 2000:
                continue
            cut = int(np.searchsorted(held["g"].to_numpy(), held["g"].iloc[-1]))  # the last group may go on
            if cut:
                yield decided(held.iloc[:cut])
                held = held.iloc[cut:]
        if held is not None and len(held):
            yield decided(held)

    found = rows.repartition("g").sortWithinPartitions("g").mapInPandas(run, "h long, sh long, least int, most int")
    return found.groupBy("h", "sh").agg(F.min("least").alias("least"), F.max("most").alias("most"))


def _segments(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """Rows for _decide: the segments of ``wanted`` (doc_id, th, at, h, sh, kinds), read from the texts."""
    lists = wanted.groupBy("doc_id", "th").agg(F.collect_list(F.struct("at", "h", "sh", "kinds")).alias("own"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            out: list[tuple] = []
            for text, own in zip(f["text"].tolist(), f["own"].tolist()):
                raw = text.encode("utf-8", "surrogatepass")
                for w in own:
                    seg, left = segment(raw, w["at"])
                    if w["kinds"] <= SPLIT_OVER:
                        out.append((w["h"], w["h"], w["sh"], left, -1, seg))
                        continue
                    for a in range(BLOCKS):  # a hot anchor: rows meet only by the blocks that a class shares
                        lo, hi = left - BLOCK * a, left + GRAM + BLOCK * (BLOCKS - 1 - a)
                        if lo >= 0 and hi <= len(seg):
                            g = xxhash.xxh3_64_intdigest(seg[lo:hi], a + 1)
                            out.append((g - (1 << 63), w["h"], w["sh"], left, a, seg))
                if len(out) > 20_000:
                    yield pd.DataFrame(out, columns=["g", "h", "sh", "left", "window", "seg"])
                    out = []
            yield pd.DataFrame(out, columns=["g", "h", "sh", "left", "window", "seg"])

    return docs.join(lists, ["doc_id", "th"]).select("text", "own").mapInPandas(run, "g long, h long, sh long, left int, window int, seg binary")


def remove_repeated_bytes(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, n_shared, kept (binary): one row for each row of ``docs``.

    A byte goes if a 400-byte string that covers it starts anywhere else too, judged on the input. A null
    text counts as empty, texts of under 400 bytes stay, repeated rows repeat each other's strings. An
    empty table gives an empty one. No pairs are made: equal segments are counted, different ones
    of an anchor meet in bounded groups, those of a hot anchor by what they share.

    n_shared tells of shorter repeats, too: of the 192-byte strings that are least by hash in some 320 bytes of
    the text, those that also start elsewhere. A text that shares 320 bytes or more has one at least.
    """
    slim = _numbered(docs)
    repeated = settle(_occurrences(slim, False).groupBy("h").agg(F.count("*").alias("n")).filter("n > 1"), "repeated")
    total = repeated.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    shared = settle(in_told(_occurrences(slim, True), repeated, "h", ["doc_id", "th", "at"], total), "anchors")
    counts = shared.groupBy("doc_id", "th").agg(F.size(F.collect_set("at")).cast("long").alias("n_shared"))
    places = shared.filter("at >= 0")
    kinds = places.groupBy("h", "sh").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "th", "at")).alias("first"))
    kinds = settle(kinds, "segments")
    per_anchor = kinds.groupBy("h").agg(F.count("*").alias("kinds"), F.min("n").alias("fewest")).filter("kinds > 1 and fewest = 1")
    per_anchor = settle(per_anchor.select("h", "kinds", F.col("kinds").alias("n")), "open")
    open_kinds = join_by_share(kinds.select("first.*", "h", "sh"), per_anchor, ["h"], kinds.count())
    partial = _decide(_segments(slim, open_kinds))
    whole = kinds.filter("n > 1").select("h", "sh", F.lit(-1).alias("least"), F.lit(-1).alias("most"), "n")
    single = kinds.filter("n = 1").select("h", "sh")
    decisions = whole.union(partial.join(single, ["h", "sh"], "left_semi").withColumn("n", F.lit(1).cast("long")))
    decisions = settle(decisions, "decisions")
    marks = join_by_share(places, decisions, ["h", "sh"], total).groupBy("doc_id", "th").agg(F.collect_list(F.struct("at", "least", "most")).alias("marks"))
    marks = counts.join(marks, ["doc_id", "th"], "left")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            rows = []
            for text, own in zip(f["text"].tolist(), f["marks"].tolist()):
                raw = text.encode("utf-8", "surrogatepass")
                n = len(raw)
                if own is None or not len(own):
                    rows.append((n, 0, 0, hashlib.sha256(raw).hexdigest(), raw))
                    continue
                at, low, high = (np.array([m[k] for m in own], np.int64) for k in ("at", "least", "most"))
                start = np.where(low < 0, np.maximum(at - SIDE, 0), at - high)
                stop = np.where(low < 0, np.minimum(at + LENGTH, n), at - low + LENGTH)
                depth = np.cumsum(np.bincount(start, minlength=n + 1) - np.bincount(stop, minlength=n + 1))[:n]
                gone = depth > 0
                kept = np.frombuffer(raw, np.uint8)[~gone].tobytes()
                spans = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum())
                rows.append((n, int(gone.sum()), spans, hashlib.sha256(kept).hexdigest(), kept))
            made = pd.DataFrame(rows, columns=["n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])
            made.insert(0, "doc_id", f["doc_id"].to_numpy())
            made["n_shared"] = f["n_shared"].to_numpy()
            yield made

    joined = slim.join(marks, ["doc_id", "th"], "left").select("doc_id", "text", "marks", F.coalesce("n_shared", F.lit(0).cast("long")).alias("n_shared"))
    result = joined.mapInPandas(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, n_shared long, kept binary")
    return result.withColumn("doc_id", F.when(F.col("doc_id") != -(1 << 63), F.col("doc_id")))


def op4_suffix_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    arrow_rows(spark, 1_000)
    return remove_repeated_bytes(documents(spark, sf_dir)).drop("kept")
