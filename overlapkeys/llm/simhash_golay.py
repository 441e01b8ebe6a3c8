"""Operator 6: SimHash near-duplicates through the perfect Golay code.

A fingerprint's 64 bits are cut into segments of 23, 23 and 18 bits. Any two fingerprints that differ
in at most four bits have two segments with at most two errors each. All code words within four
bits of a segment are its indices: two segments at distance two or less always share one, as the word
midway decodes to it. So a pair of segments gives some 28 keys of 24 bits, three pairs give all, and
fingerprints that share a key are compared exactly.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import lru_cache
from itertools import combinations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from overlapkeys.operators.components import component_labels

from .common import arrow_rows, documents, drop, filled_id, lean, settle, sweep, unfilled

GENERATOR = 0b110001110101  # fixed value: generator polynomial of the (23, 12) code
SEGMENTS = ((0, 23), (23, 23), (46, 18))  # first bit, bits
NULL_ID = -(1 << 63)
TEXTS = 500  # rows of an Arrow batch of whole texts
RUN = 48  # runs of a key up to here are compared at once, longer ones by intact blocks


def shingle_hashes(text: str | None, words: int = 4) -> np.ndarray:
    """XXH64 of each run of so many words, repeats included; of the whole sequence if it is shorter, of none if empty."""
    own = (text or "").encode("utf-8", "surrogatepass").lower().split()
    digest = xxhash.xxh64_intdigest
    if len(own) < words:
        return np.array([digest(b" ".join(own), 42)] if own else [], np.uint64)
    size = np.fromiter(map(len, own), np.int64, len(own)) + 1
    ends = np.cumsum(size)
    line = b" ".join(own)
    return np.array([digest(line[i:j], 42) for i, j in zip((ends - size)[: len(own) - words + 1].tolist(), (ends - 1)[words - 1 :].tolist())], np.uint64)


def _print_of(hashes: np.ndarray) -> int:
    if not len(hashes):
        return 0
    bits = np.unpackbits(hashes.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    over = bits.sum(0, dtype=np.int64) * 2 > len(hashes)
    return int(np.packbits(over, bitorder="little").view("<u8")[0])


def fingerprint(text: str | None) -> int:
    return _print_of(shingle_hashes(text))


@lru_cache(1)
def _golay() -> tuple[np.ndarray, np.ndarray]:
    """Syndrome of each 23-bit word's bits; error patterns of weight four or less of each syndrome."""

    def remainder(x: int) -> int:
        for k in range(22, 10, -1):
            if x >> k & 1:
                x ^= GENERATOR << (k - 11)
        return x

    unit = np.array([remainder(1 << k) for k in range(23)], np.int64)
    errors = np.full((2048, 6), -1, np.int64)
    filled = [0] * 2048
    for weight in range(5):
        for bits in combinations(range(23), weight):
            s = int(np.bitwise_xor.reduce(unit[list(bits)])) if bits else 0
            if weight < 4 or filled[s] < 6:
                errors[s, filled[s]] = sum(1 << b for b in bits)
                filled[s] += 1
    return unit, errors


def nearby_indices(word: np.ndarray) -> np.ndarray:
    """(n, 6) indices of the code words within four bits of 23-bit words, -1 where there are fewer."""
    unit, errors = _golay()
    syndrome = np.zeros(len(word), np.int64)
    for k in range(23):
        syndrome ^= np.where(word >> k & 1, unit[k], 0)
    e = errors[syndrome]
    return np.where(e >= 0, (word[:, None] ^ e) >> 11, -1)


def golay_keys(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, key) of all keys of unsigned 64-bit fingerprints."""
    near = [nearby_indices(((fp >> np.uint64(at)) & np.uint64((1 << n) - 1)).astype(np.int64)) for at, n in SEGMENTS]
    rows, keys = [], []
    for p, (a, b) in enumerate(combinations(range(3), 2)):
        x, y = near[a][:, :, None], near[b][:, None, :]
        key = np.where((x >= 0) & (y >= 0), (p << 24) | (x << 12) | y, -1).reshape(len(fp), -1)
        at, col = np.nonzero(key >= 0)
        rows.append(at)
        keys.append(key[at, col])
    return np.concatenate(rows), np.concatenate(keys)


def _close_in_runs(group: np.ndarray, fp: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions (i, j) of equal ``group`` (sorted) within ``most`` bits."""
    left, right = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    live = np.arange(len(fp) - 1)
    lag = 1
    while len(live):
        live = live[live + lag < len(fp)]
        live = live[group[live] == group[live + lag]]
        hit = live[np.bitwise_count(fp[live] ^ fp[live + lag]) <= most]
        left.append(hit)
        right.append(hit + lag)
        lag += 1
    return np.concatenate(left), np.concatenate(right)


def _forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A star for each component of the edges: as many edges as nodes at most."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        np.minimum.at(new, label[x], low)
        np.minimum.at(new, label[y], low)
        new = new[new]
        if (new == label).all():
            break
        label = new
    keep = label != np.arange(len(nodes))
    return nodes[label[keep]], nodes[keep]


def links_of_run(key: np.ndarray, fp: np.ndarray, rep: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links between rows of equal key (sorted by key)."""
    size = np.diff(np.flatnonzero(np.r_[True, key[1:] != key[:-1], True])) if len(key) else np.zeros(0, np.int64)
    long = np.repeat(size > RUN, size)
    short = np.flatnonzero(~long)
    i, j = _close_in_runs(key[short], fp[short], most)
    left, right = [rep[short[i]]], [rep[short[j]]]
    at = np.flatnonzero(long)
    for k in range(most + 1):  # of most + 1 blocks of bits one is intact
        lo, hi = 64 * k // (most + 1), 64 * (k + 1) // (most + 1)
        block = (fp[at] >> np.uint64(lo)) & np.uint64((1 << (hi - lo)) - 1)
        order = np.lexsort((block, key[at]))
        g = key[at][order].astype(np.int64) << 20 | block[order].astype(np.int64)
        i, j = _close_in_runs(g, fp[at][order], most)
        if len(i):
            a, b = _forest(rep[at][order][i], rep[at][order][j])
            left.append(a)
            right.append(b)
    a, b = np.concatenate(left), np.concatenate(right)
    return _forest(a, b) if len(a) else (a, b)


def fingerprints(docs: DataFrame) -> DataFrame:
    @lean
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            fp = np.array([fingerprint(t) for t in f["text"].tolist()], np.uint64)
            yield pd.DataFrame({"doc_id": f["doc_id"], "fp": fp.view(np.int64)})

    return unfilled(docs.select(filled_id(), "text").mapInPandas(run, "doc_id long, fp long"))


def _by_key(keys: DataFrame, links, schema: str, size: int = 50_000) -> DataFrame:
    """``links`` over whole runs of rows of one key, about ``size`` rows at a time."""

    @lean
    def meet(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = None
        for f in frames:
            held = f if held is None else pd.concat([held, f])
            if len(held) < size:
                continue
            cut = int(np.searchsorted(held["key"].to_numpy(), held["key"].iloc[-1]))  # the last key may go on
            yield from links(held.iloc[:cut], False)
            held = held.iloc[cut:]
        yield from links(held, True)

    return keys.repartition("key").sortWithinPartitions("key").mapInPandas(meet, schema)


def _spread(classes: DataFrame, prints: list[str]) -> DataFrame:
    """(key, fp, rep): the Golay keys of each fingerprint column; keys of different columns never meet."""

    @lean
    def spread(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for at in range(0, len(f), 4000):
                part = f.iloc[at : at + 4000]
                for k, name in enumerate(prints):
                    fp = part[name].to_numpy()
                    rows, keys = golay_keys(fp.view(np.uint64))
                    yield pd.DataFrame({"key": (keys + k * (3 << 24)).astype(np.int32), "fp": fp[rows], "rep": part["rep"].to_numpy()[rows]})

    return classes.select(*prints, "rep").mapInPandas(spread, "key int, fp long, rep long")


def _forest_edges(keys: DataFrame, links: Callable) -> DataFrame:
    """(a, b) edges that connect the reps of ``keys`` as ``links`` (key, fp, rep of whole runs) does; forests are merged on the way."""
    found: list = [[], []]

    def merged(part: pd.DataFrame | None, end: bool) -> Iterator[pd.DataFrame]:
        if part is not None:
            a, b = links(part["key"].to_numpy(), part["fp"].to_numpy().view(np.uint64), part["rep"].to_numpy())
            found[0].append(a)
            found[1].append(b)
        if found[0] and (end or sum(map(len, found[0])) > 200_000):
            a, b = np.concatenate(found[0]), np.concatenate(found[1])
            if len(a):
                a, b = _forest(a, b)
            found[:] = [[a], [b]]
            if len(a) > 100_000 or end and len(a):
                yield pd.DataFrame({"a": a, "b": b})
                found[:] = [[], []]

    return _by_key(keys, merged, "a long, b long")


def link_edges(classes: DataFrame, most: int = 4) -> DataFrame:
    """(a, b) edges between the reps of ``classes`` (fp, rep; one row a fingerprint) that link them as all pairs would."""
    return _forest_edges(_spread(classes, ["fp"]), lambda key, fp, rep: links_of_run(key, fp, rep, most))


def near_duplicates(docs: DataFrame, most: int = 4) -> DataFrame:
    """doc_id, fp, component: one row per row of ``docs``.

    Equal fingerprints form a class first, so copies never meet in pairs. A null or wordless text has
    fingerprint zero; repeated rows share a component; a null doc_id counts as the least id while
    components are built and gives a null component where it leads one. An empty table gives none.
    """
    prints = settle(fingerprints(docs), "fingerprints")
    filled = F.coalesce("doc_id", F.lit(NULL_ID))
    classes = settle(prints.groupBy("fp").agg(F.min(filled).alias("rep")), "classes")
    labels = component_labels(link_edges(classes, most)).withColumnRenamed("node", "rep")
    whole = classes.join(labels, "rep", "left").select("fp", F.coalesce("label", "rep").alias("component"))
    return prints.join(whole, "fp").withColumn("component", F.when(F.col("component") != NULL_ID, F.col("component")))


# of near_copies: words of a shingle, least similarity, differing bits of one fingerprint and of all, fingerprints
NEAR_WORDS, NEAR_LEAST, NEAR_BITS, NEAR_TOTAL, NEAR_PRINTS = 5, 0.8, 10, 40, 3


def _close_rows(key: np.ndarray, fp: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Of rows sorted by (key, fp), each with the nearest of up to RUN rows of its key before it, if that is close."""
    n = len(key)
    near, dist = np.full(n, -1), np.full(n, most + 1)
    live, lag = np.arange(n), 1
    while len(live) and lag <= RUN:
        live = live[live >= lag]
        live = live[key[live] == key[live - lag]]
        d = np.bitwise_count(fp[live] ^ fp[live - lag])
        better = d < dist[live]
        near[live[better]], dist[live[better]] = live[better] - lag, d[better]
        lag += 1
    j = np.flatnonzero(near >= 0)
    return near[j], j


PAIRS = 1_000_000  # compared at a time


def _apart_rows(key: np.ndarray, home: np.ndarray, fp: np.ndarray, most: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Of rows sorted by (key, home), all positions (i, j) of one key, different homes and within ``most`` bits."""
    n = len(key)
    turns = np.flatnonzero(np.r_[True, key[1:] != key[:-1], True])
    end = np.repeat(turns[1:], np.diff(turns))
    turns = np.flatnonzero(np.r_[True, (key[1:] != key[:-1]) | (home[1:] != home[:-1]), True])
    other = np.repeat(turns[1:], np.diff(turns))  # the first row of the key's next home
    total = np.r_[0, np.cumsum(end - other)]
    at = 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(total, total[at] + PAIRS, "right")) - 1)
        size = (end - other)[at:to]
        i = np.repeat(np.arange(at, to), size)
        j = other[i] + np.arange(len(i)) - (total[i] - total[at])
        close = np.bitwise_count(fp[i] ^ fp[j]) <= most
        yield i[close], j[close]
        at = to


def _kept(hashes: np.ndarray) -> np.ndarray:
    """The set of shingles that is compared: 32 bits of each hash, in order."""
    return np.unique((hashes >> np.uint64(32)).astype(np.uint32))


def candidates_of_run(key: np.ndarray, fp: np.ndarray, rep: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """A forest that connects all rows of equal key within ``most`` bits; those that the nearest few connect aren't compared."""
    order = np.lexsort((fp, key))
    key, fp, rep = key[order], fp[order], rep[order]
    i, j = _close_rows(key, fp, most)
    left, right = _forest(rep[i], rep[j]) if len(i) else (rep[:0], rep[:0])
    home = rep.copy()
    if len(right):
        by = np.argsort(right)
        at = np.minimum(np.searchsorted(right[by], rep), len(by) - 1)
        home = np.where(right[by][at] == rep, left[by][at], rep)
    order = np.lexsort((home, key))
    key, fp, home = key[order], fp[order], home[order]
    for i, j in _apart_rows(key, home, fp, most):
        if len(i):
            left, right = _forest(np.r_[left, home[i]], np.r_[right, home[j]])
    return left, right


CHUNK, CHUNKS = 2_000, 16  # rows of a group that are compared together, about, and its parts at most


def _in_chunks(members: DataFrame) -> DataFrame:
    """Rows of ``members`` (u, home, n: rows of home, more) with ``p``, ``q`` and ``side`` of the parts that they meet in, and a ``key`` of these.

    A group of up to CHUNK rows is one part. A greater one has more, each pair of which meets; but never over CHUNKS, so a
    row goes to so many places at most, however large its group is.
    """
    parts = F.least(F.ceil(F.col("n") / CHUNK), F.lit(CHUNKS)).cast("int")
    own = members.withColumn("side", F.pmod(F.xxhash64("u"), parts).cast("int"))
    each = own.withColumn("other", F.explode(F.sequence(F.lit(0), parts - 1)))
    met = each.withColumn("p", F.least("side", "other")).withColumn("q", F.greatest("side", "other")).drop("other", "n")
    return met.withColumn("key", F.xxhash64("home", "p", "q"))


def similar_rows(fp: np.ndarray, sets: list[np.ndarray], right: np.ndarray | None, least: float, total: int) -> list[tuple[int, int]]:
    """A forest of the links among rows: ``total`` differing bits of ``fp`` (n, prints) at most, a Jaccard similarity of ``least``.

    ``right``: which rows meet only the others, which meet only them; None if all meet. Rows that are connected aren't compared again.
    """
    n, edges = len(sets), []
    size = np.array([len(x) for x in sets], np.int64)
    start = np.cumsum(size) - size
    words, of = np.unique(np.concatenate(sets), return_inverse=True)
    mark, label = np.zeros(len(words), bool), np.arange(n)
    turns = range(n - 1) if right is None else np.flatnonzero(~right).tolist()
    opposite = None if right is None else np.flatnonzero(right)
    for i in turns:
        j = np.arange(i + 1, n) if opposite is None else opposite
        j = j[label[j] != label[i]]
        j = j[np.bitwise_count(fp[j] ^ fp[i]).sum(1, dtype=np.int64) <= total]
        j = j[np.minimum(size[j], size[i]) >= least * np.maximum(size[j], size[i]) - 1e-9]
        if not len(j):
            continue
        own = of[start[i] : start[i] + size[i]]
        mark[own] = True
        while len(j):
            some = j[: max(1, int(np.searchsorted(np.cumsum(size[j]), PAIRS)))]
            ends = np.cumsum(size[some])
            at = np.repeat(start[some] - (ends - size[some]), size[some]) + np.arange(ends[-1])
            hits = np.r_[0, np.cumsum(mark[of[at]])]
            both = hits[ends] - hits[ends - size[some]]
            like = some[both >= least * (size[i] + size[some] - both) - 1e-9]
            if len(like):
                homes, first = np.unique(label[like], return_index=True)
                edges += [(i, int(k)) for k in like[first]]
                label[np.isin(label, homes)] = label[i]
            j = j[len(some) :]
            j = j[label[j] != label[i]]
        mark[own] = False
    return edges


def near_copies(docs: DataFrame, words: int = NEAR_WORDS, least: float = NEAR_LEAST, most: int = NEAR_BITS, prints: int = NEAR_PRINTS) -> DataFrame:
    """doc_id, u, component, keep: near copies by shingles; u is a hash of doc_id and text, one row a row of ``docs``.

    Several independent fingerprints of the shingles give Golay keys. Rows that share a key and differ in ``most`` bits at
    most there are candidates; chains of candidates make groups, by forests, so no pair is listed. Inside a group all rows that
    differ in NEAR_TOTAL bits at most over all fingerprints are held against each other, and those with a Jaccard similarity
    of at least ``least`` over the sets of shingles are linked, but for pairs that are connected by then: no link is lost, and
    what is shuffled grows with the rows, as a row goes to a bounded number of places. Equal texts are
    one class and always linked. That two rows share a key is a matter of chance, the surer the more alike (recall is
    measured in the tests). ``keep`` is true for one row of a component, of the least doc_id (nulls last). What is joined
    to the texts grows with them, so it is shuffled at every size and never broadcast.
    """
    spark = docs.sparkSession
    batch = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")

    @lean
    def printed(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            rows = []
            for text in f["text"].tolist():
                h = shingle_hashes(text, words)
                rows.append([_print_of(h if k == 0 else (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15 + 2 * k * 0x632BE59BD9B4E019 & (1 << 64) - 1)) for k in range(prints)])
            made = pd.DataFrame(np.array(rows, np.uint64).reshape(-1, prints).view(np.int64), columns=names)
            made.insert(0, "u", f["u"].to_numpy())
            made.insert(0, "doc_id", f["doc_id"].to_numpy())
            yield made

    names = [f"f{k}" for k in range(prints)]
    u = F.xxhash64(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")))
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit((1 << 63) - 1)).alias("doc_id"), u.alias("u"), "text")
    arrow_rows(spark, TEXTS)
    told = settle(rows.mapInPandas(printed, "doc_id long, u long, " + ", ".join(f"{n} long" for n in names)), "prints")
    arrow_rows(spark, int(batch))
    classes = settle(told.groupBy(*names).agg(F.min("u").alias("rep")), "classes")

    @lean
    def shingled(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            f["s"] = [_kept(shingle_hashes(t, words)).view(np.int32) for t in f["text"].tolist()]
            yield f[["u", "home", "n", *names, "s"]]

    def similar(part: pd.DataFrame | None, end: bool) -> Iterator[pd.DataFrame]:
        if part is not None and len(part):
            edges = []
            for (_, p, q), f in part.groupby(["home", "p", "q"], sort=False):
                u, right = f["u"].to_numpy(), None if p == q else f["side"].to_numpy() == q
                edges += [(u[i], u[j]) for i, j in similar_rows(f[names].to_numpy().view(np.uint64), f["s"].tolist(), right, least, NEAR_TOTAL)]
            yield pd.DataFrame(np.array(edges, np.int64).reshape(-1, 2), columns=["a", "b"])

    met = settle(_forest_edges(_spread(classes, names), lambda key, fp, rep: candidates_of_run(key, fp, rep, most)), "met")
    groups = settle(component_labels(met), "groups")
    drop(met)
    sweep(spark)  # the keys' shuffle goes before texts are shuffled
    sized = groups.join(groups.groupBy("label").agg(F.count("*").alias("n")), "label")
    asked = classes.join(sized, classes["rep"] == sized["node"]).select(F.col("rep").alias("u"), F.col("label").alias("home"), "n", *names)
    arrow_rows(spark, TEXTS)
    form = "u long, home long, n long, " + ", ".join(f"{n} long" for n in names) + ", s array<int>"
    sets = settle(rows.select("u", "text").join(asked.hint("merge"), "u").mapInPandas(shingled, form).dropDuplicates(["u"]), "shingles")
    sweep(spark)
    near = settle(_by_key(_in_chunks(sets), similar, "a long, b long", 2 * CHUNK), "near")
    arrow_rows(spark, int(batch))
    drop(sets, groups)
    sweep(spark)
    labels = component_labels(near).withColumnRenamed("node", "rep")
    whole = classes.join(labels, "rep", "left").select(*names, F.coalesce("label", "rep").alias("component"))
    placed = settle(told.join(whole, names).select("doc_id", "u", "component"), "placed")
    drop(told, classes, near)
    sweep(spark)
    best = placed.groupBy("component").agg(F.min(F.struct("doc_id", "u")).alias("best"))
    kept = placed.join(best, "component").withColumn("keep", F.struct("doc_id", "u") == F.col("best"))
    return kept.select(F.when(F.col("doc_id") != (1 << 63) - 1, F.col("doc_id")).alias("doc_id"), "u", "component", "keep")


def op6_simhash_golay(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(documents(spark, sf_dir))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("component").alias("component_id"))
