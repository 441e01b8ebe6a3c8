"""What the key method is compared with: all pairs, inverted index, prefix filter, MinHash, k-means, blocking."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from overlapkeys.plans.overlap_plan import OverlapPlan
from overlapkeys.plans.rules import SimilarityRule
from overlapkeys.session import settle

from .keys import element_codes, encoded, expanded, mark_keys, probe_keys
from .retrieve import classes_of, expand, links_by, side, similar_pairs, verify


def bruteforce_pairs(sigs: DataFrame, rule: SimilarityRule) -> DataFrame:
    """Every pair compared: quadratic on purpose, as the baseline is."""
    a, b = sigs.alias("a"), sigs.alias("b")
    o = F.size(F.array_intersect("a.sig", "b.sig"))
    met = a.crossJoin(b).filter("a.ordinal < b.ordinal").select(F.col("a.ordinal").alias("earlier"), F.col("b.ordinal").alias("later"), o.alias("overlap"), F.col("a.size").alias("x"), F.col("b.size").alias("y"))
    return met.filter((F.col("overlap") > 0) & rule.holds_col(F.col("overlap"), F.col("y"), F.col("x"))).select("earlier", "later", "overlap", rule.score_col(F.col("overlap"), F.col("y"), F.col("x")).alias("score"))


BLOCK = 1024  # signatures on either side of one product of incidence matrices
LINKS = "marker bigint, prober bigint, overlap int, x int, y int"


def _met(pdf: pd.DataFrame, rule: SimilarityRule) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(marker's row, prober's row, overlap) of the similar pairs among rows (ordinal, size, sig), rising by ordinal; all are compared."""
    size = pdf["size"].to_numpy()
    most = int(size.max())
    holds = np.zeros((most + 1,) * 3, dtype=bool)
    present = sorted(set(size.tolist()))
    for x in present:
        for y in present:
            for o in range(1, min(x, y) + 1):
                holds[o, x, y] = rule.holds(o, x, y)
    codes, _ = pd.factorize(pdf["sig"].explode())
    row = np.repeat(np.arange(len(pdf)), pdf["sig"].str.len())

    def incidence(start: int) -> np.ndarray:
        lo, hi = np.searchsorted(row, [start, start + BLOCK])
        out = np.zeros((min(BLOCK, len(pdf) - start), codes.max() + 1), dtype=np.float32)
        out[row[lo:hi] - start, codes[lo:hi]] = 1
        return out

    for i in range(0, len(pdf), BLOCK):
        a = incidence(i)
        for j in range(i, len(pdf), BLOCK):
            o = (a @ incidence(j).T).astype(np.int64)
            m, p = np.nonzero(holds[o, size[None, j : j + BLOCK], size[i : i + BLOCK, None]])
            keep = m + i < p + j
            yield m[keep] + i, p[keep] + j, o[m[keep], p[keep]]


def _linked(found: DataFrame, rule: SimilarityRule) -> DataFrame:
    return found.select("marker", "prober", "overlap", rule.score_col(F.col("overlap"), F.col("x"), F.col("y")).alias("score"))


def bruteforce_classes(sigs: DataFrame, rule: SimilarityRule) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Links of distinct signatures (marker the earlier), their classes, membership: all pairs of these are compared, by blocks."""
    classes, members = classes_of(sigs)
    n = max(1, -(-classes.count() // BLOCK))
    dealt = classes.select("ordinal", "size", "sig", F.expr(f"cast(pmod(xxhash64(ordinal), {n}) as int)").alias("b"))
    every = F.sequence(F.lit(0), F.lit(n - 1))
    dealt = dealt.withColumn("o", F.explode(every)).withColumn("i", F.least("b", "o")).withColumn("j", F.greatest("b", "o"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("ordinal", ignore_index=True)
        size, ordinal, b, apart = pdf["size"].to_numpy(), pdf["ordinal"].to_numpy(), pdf["b"].to_numpy(), pdf["i"][0] != pdf["j"][0]
        out = []
        for m, p, o in _met(pdf, rule):
            if apart:  # pairs of one block meet in that block's own group
                across = b[m] != b[p]
                m, p, o = m[across], p[across], o[across]
            out.append(pd.DataFrame({"marker": ordinal[m], "prober": ordinal[p], "overlap": o, "x": size[p], "y": size[m]}))
        return pd.concat(out)

    return _linked(dealt.groupBy("i", "j").applyInPandas(run, LINKS), rule), classes, members


CELL = 4 * BLOCK  # rows of a key on either side that one call compares


class _Rows:
    """Classes of a cell, sorted by key and ordinal: elements as codes, the place of the key among them, hashes of bands.

    ``before`` has the elements in front of the key, ``flat`` those from it on; ``bounds`` parts ``flat`` by rows.
    """

    def __init__(self, t: pa.Table, on: list[str]) -> None:
        t = t.sort_by([(c, "ascending") for c in ("b", *on, "ordinal")])
        els, self.n = t["els"].combine_chunks(), len(t)
        self.ordinal, self.hi, self.at = (t[c].to_numpy() for c in ("ordinal", "hi", "at"))
        keys = [t[c].combine_chunks().dictionary_encode().indices.to_numpy() for c in on]
        self.run = np.cumsum(np.any([np.diff(k, prepend=k[:1]) != 0 for k in keys], axis=0))
        self.size = np.diff(els.offsets.to_numpy())
        row = np.repeat(np.arange(self.n), self.size)
        place = np.arange(len(row)) - np.repeat(np.cumsum(self.size) - self.size, self.size)
        codes = els.flatten().dictionary_encode().indices.to_numpy()
        late = place >= self.at[row]
        self.before = np.full((self.n, max(1, int(self.at.max()))), -1, dtype=np.int32)
        self.before[row[~late], place[~late]] = codes[~late]
        self.flat, self.row, self.width = codes[late], row[late], int(codes.max()) + 1
        self.bounds = np.searchsorted(self.row, np.arange(self.n + 1))
        if "hashes" in t.column_names:
            hashes = t["hashes"].combine_chunks()
            self.hashes = hashes.flatten().to_numpy().reshape(self.n, -1)
            self.band = t["band"].to_numpy()
        else:
            self.hashes = None

    def once(self, m: np.ndarray, p: np.ndarray) -> np.ndarray:
        """Whether the key is the first that both have."""
        if self.hashes is not None:
            return (self.hashes[m] == self.hashes[p]).argmax(axis=1) == self.band[m]
        out = np.ones(len(m), dtype=bool)
        some = np.flatnonzero((self.at[m] > 0) & (self.at[p] > 0))
        a, b = self.before[m[some]], self.before[p[some]]
        for k in range(a.shape[1]):
            out[some] &= ~((a[:, k, None] == b) & (a[:, k, None] >= 0)).any(axis=1)
        return out

    def overlaps(self, s: slice, t: slice) -> np.ndarray:
        """Common elements from the key on of the rows of one range with those of another."""
        a, b = (slice(self.bounds[x.start], self.bounds[x.stop]) for x in (s, t))
        here = np.zeros((2, self.width), dtype=bool)
        here[0, self.flat[a]], here[1, self.flat[b]] = True, True
        common = here.all(axis=0)
        column = np.where(common, np.cumsum(common) - 1, -1)

        def incidence(rows: slice, at: slice) -> np.ndarray:
            out, c = np.zeros((rows.stop - rows.start, int(common.sum())), dtype=np.float32), column[self.flat[at]]
            out[self.row[at][c >= 0] - rows.start, c[c >= 0]] = 1
            return out

        return incidence(s, a) @ incidence(t, b).T


def _ranges(r: _Rows, apart: int, block: int) -> Iterator[tuple[slice, slice]]:
    """Pairs of ranges that hold all rows of equal keys, once; rows before ``apart``, if there are, meet those after it only."""
    ends = np.searchsorted(r.run, r.run, side="right")
    for i in range(0, apart or r.n, block):
        s = slice(i, min(i + block, apart or r.n))
        start, stop = (apart, r.n) if apart else (i, ends[s.stop - 1])
        for j in range(start, stop, block):
            yield s, slice(j, min(j + block, stop))


def _holds(r: _Rows, rule: SimilarityRule) -> tuple[np.ndarray, np.ndarray]:
    """(whether the rule holds for [overlap, prober's size, marker's size], least overlap at which it does either way)."""
    most, present = int(r.size.max()), sorted(set(r.size.tolist()))
    holds, least = np.zeros((most + 1,) * 3, dtype=bool), np.full((most + 1,) * 2, np.inf, dtype=np.float32)
    for x in present:
        for y in present:
            for o in range(1, min(x, y) + 1):
                if rule.holds(o, x, y):
                    holds[o, x, y] = True
                    least[x, y], least[y, x] = min(o, least[x, y]), min(o, least[y, x])
    return holds, least


def links_of_keys(keyed: DataFrame, on: list[str], rule: SimilarityRule, both: bool) -> DataFrame:
    """``links_by`` for keys that many classes have: rows (ordinal, hi, els, at, .., keys ``on``) are compared in blocks.

    Keys of up to CELL rows are dealt to cells together; the rows of others go to parts and each two parts to a
    cell. ``at`` is the key's place among ``els``: what lies in front is passed over, as a pair counts at its first
    common key. With ``hashes``, a pair counts at the first ``band`` of equal ones. The marker is the earlier class;
    with ``both`` a later class marks for copies of an earlier one, too.
    """
    counts = settle(keyed.groupBy(*on).agg(F.count("*").alias("n")).filter("n > 1"), "counts")
    rows, block = counts.agg(F.sum("n")).first()[0] or 0, BLOCK
    cells = max(int(keyed.sparkSession.conf.get("spark.sql.shuffle.partitions")), rows // CELL)
    dealt = keyed.join(counts, on).withColumn("parts", F.expr(f"cast(ceil(n / {CELL}) as int)"))
    dealt = dealt.withColumn("b", F.expr("cast(pmod(xxhash64(ordinal), parts) as int)")).withColumn("o", F.explode(F.expr("sequence(0, parts - 1)")))
    cell = F.when(F.col("parts") > 1, F.xxhash64(*on)).otherwise(F.pmod(F.xxhash64(*on), F.lit(cells)))
    dealt = dealt.withColumn("cell", cell).withColumn("i", F.least("b", "o")).withColumn("j", F.greatest("b", "o")).drop("n", "parts", "o")

    def run(t: pa.Table) -> pa.Table:
        apart = int((t["b"].to_numpy() == t["i"][0].as_py()).sum()) if t["i"][0].as_py() != t["j"][0].as_py() else 0
        r, out = _Rows(t, on), []
        holds, least = _holds(r, rule)
        for s, t_ in _ranges(r, apart, block):
            found = r.overlaps(s, t_)
            m, p = np.nonzero(found >= least[r.size[s]][:, r.size[t_]])
            o = found[m, p].astype(np.int32)
            m, p = m + s.start, p + t_.start
            keep = (r.run[m] == r.run[p]) & ((m < p) | (apart > 0))
            m, p, o = m[keep], p[keep], o[keep]
            keep = r.once(m, p)
            m, p, o = m[keep], p[keep], o[keep]
            late = r.ordinal[m] > r.ordinal[p]
            m, p = np.where(late, p, m), np.where(late, m, p)
            for a, b, fits in ((m, p, True), (p, m, r.ordinal[p] < r.hi[m]))[: 1 + both]:
                keep = fits & holds[o, r.size[b], r.size[a]]
                out.append((r.ordinal[a[keep]], r.ordinal[b[keep]], o[keep], r.size[b[keep]], r.size[a[keep]]))
        columns = [np.concatenate(c) for c in zip(*out, strict=True)]
        return pa.table([pa.array(c, kind) for c, kind in zip(columns, (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32()), strict=True)], ["marker", "prober", "overlap", "x", "y"])

    return _linked(dealt.groupBy("cell", "i", "j").applyInArrow(run, LINKS), rule)


def element_join_pairs(sigs: DataFrame, rule: SimilarityRule) -> DataFrame:
    return expand(*element_join_classes(sigs, rule, both=True), rule)


def element_join_classes(sigs: DataFrame, rule: SimilarityRule, both: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Join on every element; a pair counts at its first common one. Links of distinct signatures, their classes, membership."""
    classes, members = classes_of(sigs)
    flat = classes.select("ordinal", "hi", F.col("sig").alias("els"), F.posexplode("sig").alias("at", "e"))
    return links_of_keys(flat, ["e"], rule, both), classes, members


def coded_classes(sigs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Distinct signatures with their elements' codes, rarest first, and the membership of the items."""
    classes, members = classes_of(sigs)
    flat = classes.select("ordinal", F.explode("sig").alias("text")).join(element_codes(sigs).select("text", "code"), "text")
    codes = flat.groupBy("ordinal").agg(F.sort_array(F.collect_list("code"), asc=False).alias("codes"))
    return settle(classes.join(codes, "ordinal"), "coded"), members


def prefix_pairs(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    return expand(*prefix_classes(sigs, plan, both=True), plan.rule)


def prefix_classes(sigs: DataFrame, plan: OverlapPlan, both: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Join on each item's rarest elements only, as many as any partner must share one of.

    The codes travel with the key: sizes that can't be similar and places with too few elements left are
    passed over, and a pair counts at its rarest common element. Links of distinct signatures, their classes,
    membership.
    """
    classes, members = coded_classes(sigs)
    least = {x: min(plan.need(x, y) for y in plan.partner_sizes(x)) for x in plan.sizes}
    prefix = F.create_map(*[F.lit(v) for x, m in least.items() for v in (x, x - m + 1)])
    keys = classes.select("ordinal", "hi", F.col("codes").alias("els"), F.posexplode(F.slice("codes", F.lit(1), prefix[F.col("size")])).alias("at", "code"))
    return links_of_keys(keys, ["code"], plan.rule, both), classes, members


def rare_classes(sigs: DataFrame, plan: OverlapPlan, depth: int = 3) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Links of distinct signatures that share ``depth`` elements among their rarest, their classes, membership.

    Of two sets that share m elements the l rarest common ones are among the first x - m + l of either, so
    each l of those make a key; l is ``depth``, or the need of the two sizes if that is less. A set of ten
    has 35 such keys at a threshold of 3/5, where it reads 540 sub-signatures. A pair counts at its rarest common
    elements. For symmetric rules.
    """
    if not plan.rule.symmetric:
        raise ValueError("a directed rule has no one need for two sizes")
    classes, members = coded_classes(sigs.filter(F.col("size").isin(*plan.sizes)))
    rows = []
    for x in plan.sizes:
        needs = [plan.need(x, y) for y in plan.partner_sizes(x)]
        for l in sorted({min(depth, m) for m in needs}):  # noqa: E741
            length = x - min(m for m in needs if min(depth, m) == l) + l
            rows.append((x, [list(c) for c in combinations(range(1, length + 1), l)]))
    table = F.broadcast(sigs.sparkSession.createDataFrame(rows, "size int, at array<array<int>>"))  # some rows a size
    keyed = classes.join(table, "size").select(*classes.columns, F.explode("at").alias("at"))
    keyed = keyed.withColumn("sub", F.transform("at", lambda i: F.element_at(F.col("codes"), i))).withColumn("key", F.xxhash64("sub"))
    tiers = F.create_map(*[F.lit(v) for x in plan.sizes for y in plan.partner_sizes(x) for v in (x * 1000 + y, min(depth, plan.need(x, y)))])
    tier = tiers[F.size("p_els") * 1000 + F.size("m_els")]
    once = (tier == F.size("sub")) & (F.slice("both", 1, F.size("sub")) == F.col("sub"))
    return links_by(side(keyed, "p", "key", "sub", els="codes"), side(keyed, "m", "key", els="codes"), ["key"], plan.rule, once), classes, members


MODULUS = 2_147_483_647


def minhash_params(n: int) -> list[tuple[int, int, int]]:
    return [(k, (k * 7_368_787 + 12_345) % MODULUS, (k * 9_176_263 + 6_789) % MODULUS) for k in range(1, n + 1)]


def minhash_pairs(sigs: DataFrame, rule: SimilarityRule, bands: int, rows: int) -> DataFrame:
    return expand(*minhash_classes(sigs, rule, bands, rows, both=True), rule)


def minhash_classes(sigs: DataFrame, rule: SimilarityRule, bands: int, rows: int, both: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Links of distinct signatures, their classes, membership. Banded MinHash with modular hashes of element codes, verified: exact precision, recall below one.

    A signature's hashes are made in its own row, with no shuffle before the bands; a pair counts at the
    first band that it shares.
    """
    classes, members = coded_classes(sigs)
    params = minhash_params(bands * rows)

    def least(a: int, b: int) -> Column:
        return F.array_min(F.transform("codes", lambda c: (c * F.lit(a) + F.lit(b)) % F.lit(MODULUS)))

    low = [least(a, b) for _, a, b in params]
    hashed = classes.select("ordinal", "hi", F.col("codes").alias("els"), F.lit(0).alias("at"), F.array(*[F.xxhash64(F.lit(k), *low[k * rows : (k + 1) * rows]) for k in range(bands)]).alias("hashes"))
    hashed = settle(hashed, "bands")
    return links_of_keys(hashed.select("*", F.posexplode("hashes").alias("band", "key")), ["band", "key"], rule, both), classes, members


def _vectors(sigs: DataFrame, name: str, of: DataFrame | None = None) -> DataFrame:
    """A binary vector of each signature (of those in ``of``) over all elements that there are: none is cut from the vocabulary."""
    from pyspark.ml.feature import CountVectorizer

    elements = sigs.select(F.explode("sig").alias("e")).agg(F.count_distinct("e")).first()[0]
    return CountVectorizer(inputCol="sig", outputCol=name, binary=True, vocabSize=max(1, elements)).fit(sigs).transform(sigs if of is None else of)


def minhash_mllib(sigs: DataFrame, theta: float, tables: int = 20, seed: int = 1) -> DataFrame:
    """The library's MinHash join. It keeps distances strictly below the bound, so the bound is nudged up."""
    from pyspark.ml.feature import MinHashLSH

    vectors = _vectors(sigs, "v").select("ordinal", "v")
    model = MinHashLSH(inputCol="v", outputCol="h", numHashTables=tables, seed=seed).fit(vectors)
    joined = model.approxSimilarityJoin(vectors, vectors, 1 - theta + 1e-7, "distance")
    return joined.select(F.col("datasetA.ordinal").alias("earlier"), F.col("datasetB.ordinal").alias("later"), (1 - F.col("distance")).alias("score")).filter("earlier < later")


def minhash_mllib_classes(sigs: DataFrame, rule: SimilarityRule, tables: int = 20, seed: int = 1) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Links of distinct signatures (marker the earlier) that share one of the library's hashes, their classes, membership.

    The library's own join carries both vectors and all hashes with each candidate, and broadcasts them while
    the table looks small. Here signatures meet by (table, hash), are compared in blocks, and count at the
    first table that they share.
    """
    from pyspark.ml.feature import MinHashLSH
    from pyspark.ml.functions import vector_to_array

    classes, members = classes_of(sigs)
    vectors = _vectors(sigs, "v", classes)
    hashed = MinHashLSH(inputCol="v", outputCol="h", numHashTables=tables, seed=seed).fit(vectors).transform(vectors)
    hashes = F.array(*[vector_to_array(F.col("h")[k])[0].cast("bigint") for k in range(tables)])
    hashed = settle(hashed.select("ordinal", "size", "sig", hashes.alias("hashes")), "hashes")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("ordinal", ignore_index=True)
        size, ordinal, h, table = pdf["size"].to_numpy(), pdf["ordinal"].to_numpy(), np.stack(pdf["hashes"].to_list()), pdf["table"][0]
        out = []
        for m, p, o in _met(pdf, rule):
            here = (h[m] == h[p]).argmax(axis=1) == table
            m, p, o = m[here], p[here], o[here]
            out.append(pd.DataFrame({"marker": ordinal[m], "prober": ordinal[p], "overlap": o, "x": size[p], "y": size[m]}))
        return pd.concat(out)

    met = hashed.select("*", F.posexplode("hashes").alias("table", "hash")).groupBy("table", "hash").applyInPandas(run, LINKS)
    return _linked(met, rule), classes, members


def kmeans_clusters(sigs: DataFrame, k: int, seed: int = 1) -> DataFrame:
    from pyspark.ml.clustering import KMeans

    vectors = _vectors(sigs, "features")
    return KMeans(k=k, seed=seed, maxIter=10).fit(vectors).transform(vectors).select("ordinal", F.col("prediction").cast("bigint").alias("cluster_id"))


def blocked_pairs(sigs: DataFrame, blocks: DataFrame, plan: OverlapPlan) -> DataFrame:
    """Similar pairs inside a block only; (ordinal, block)."""
    marks = mark_keys(sigs, plan).join(blocks, "ordinal").select("key", "block", F.col("ordinal").alias("earlier"))
    probes = probe_keys(sigs, plan).join(blocks, "ordinal").select("key", "block", F.col("ordinal").alias("later"))
    return verify(probes.join(marks, ["key", "block"]).filter("earlier < later").select("earlier", "later").distinct(), sigs, plan.rule)


def blocked_classes(sigs: DataFrame, blocks: DataFrame, plan: OverlapPlan) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Links of the distinct signatures of each block, their classes, membership: the same join without listing copies."""
    dealt = settle(sigs.join(blocks, "ordinal"), "dealt")
    classes = dealt.groupBy("block", "sig", "size").agg(F.min("ordinal").alias("ordinal"), F.max("ordinal").alias("hi"))
    classes = settle(classes.select("ordinal", F.col("ordinal").alias("lo"), "hi", "size", "sig", "block"), "classes")
    members = dealt.select("ordinal", "sig", "block").join(classes.select(F.col("ordinal").alias("cls"), "sig", "block"), ["sig", "block"]).select("cls", "ordinal")
    probes, marks = (expanded(classes, plan, r).withColumn("key", encoded(F.col("tag"), F.col("sub"), "text")) for r in ("probe", "mark"))
    first = F.col("sub") == F.slice("both", 1, F.size("sub"))
    return links_by(side(probes, "p", "block", "key", "sub"), side(marks, "m", "block", "key"), ["block", "key"], plan.rule, first), classes, members


def salted_pairs(sigs: DataFrame, plan: OverlapPlan, salts: int = 4) -> DataFrame:
    """Hot keys spread: probes are dealt over salts, marks are copied to each."""
    marks = mark_keys(sigs, plan).select("key", F.col("ordinal").alias("earlier"), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    probes = probe_keys(sigs, plan).select("key", F.col("ordinal").alias("later"), (F.col("ordinal") % salts).cast("int").alias("salt"))
    return verify(probes.join(marks, ["key", "salt"]).filter("earlier < later").select("earlier", "later").distinct(), sigs, plan.rule)


def generated_pairs(sigs: DataFrame, plan: OverlapPlan, most_keys: int = 600) -> DataFrame:
    """Sub-signature keys while an item's stay manageable, else the prefix filter: the same pairs."""
    few = max(plan.probe_count(x) for x in plan.sizes) <= most_keys
    return similar_pairs(sigs, plan) if few else prefix_pairs(sigs, plan)
