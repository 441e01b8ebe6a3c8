"""Leader clustering: the first item of a cluster is its fixed leader; an item joins the earliest similar leader.

Item i leads iff no earlier similar item leads. Rounds decide it: an undecided item without undecided
earlier neighbours and without earlier leading neighbours leads, one with a leading neighbour is a
member. A key's least undecided and least leading writer are all that its readers need, so a round is two
aggregations of key rows, with map-side combining, and never lists pairs.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import TYPE_CHECKING

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapkeys.plans.overlap_plan import OverlapPlan
from overlapkeys.plans.rules import SimilarityRule
from overlapkeys.session import scratch, settle
from overlapkeys.sources.signatures import with_ordinal

from .keys import collapse_identical, role_keys
from .trace import Engine, whole

if TYPE_CHECKING:
    from overlapkeys.sources.io import KeyStore

CHOICES = ("earliest", "latest", "overlap", "score", "votes")


def _round(live: DataFrame, plan: OverlapPlan) -> DataFrame:
    """(ordinal, size, sig, s) after a round; s: 0 undecided, 1 has just become a leader."""
    marked = role_keys(live.withColumnRenamed("ordinal", "o").withColumn("ordinal", F.struct("o", "s")), plan, "mark")
    per_key = marked.groupBy("key").agg(
        F.min(F.when(F.col("ordinal.s") == 0, F.col("ordinal.o"))).alias("waiting"), F.min(F.when(F.col("ordinal.s") == 1, F.col("ordinal.o"))).alias("leading")
    )
    probes = role_keys(live.filter("s = 0"), plan, "probe").select("key", "ordinal")
    seen = probes.join(per_key, "key", "left").groupBy("ordinal").agg(F.max(F.coalesce(F.expr("leading < ordinal"), F.lit(False))).alias("hit"), F.max(F.coalesce(F.expr("waiting < ordinal"), F.lit(False))).alias("held"))
    waiting = live.filter("s = 0").join(seen, "ordinal").filter("not hit")
    return waiting.select("ordinal", "size", "sig", F.when(F.col("held"), 0).otherwise(1).alias("s"))


LAST_KEYS = 1_000_000  # mark keys of what is left, up to which one task ends the rounds


def _end(live: DataFrame, plan: OverlapPlan) -> DataFrame:
    """The leaders among what is left, one item at a time over a dictionary: the same answer as more rounds give."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        engine, out = Engine(plan), []
        for r in whole(frames).itertuples(index=False):
            sig = list(r.sig)
            if r.s == 1:
                engine.lead(r.ordinal, sig)
            elif engine.assign(r.ordinal, sig, engine.keys(sig)) == r.ordinal:
                out.append((r.ordinal, r.size, sig))
        yield pd.DataFrame(out, columns=["ordinal", "size", "sig"])

    return live.select("ordinal", "size", "sig", "s").coalesce(1).mapInPandas(run, "ordinal bigint, size int, sig array<string>")


def leaders(sigs: DataFrame, plan: OverlapPlan, max_rounds: int = 10_000, last_keys: int = LAST_KEYS) -> DataFrame:
    """(ordinal, size, sig) of the leaders. Each round writes what is undecided and the new leaders, and counts it by size.

    Once the keys of what is left are few, by that count, one task decides the rest: long tails of small rounds go.
    """
    some = sigs.filter(F.col("size").isin(*plan.sizes))  # others have no keys
    now = settle(collapse_identical(some).select("ordinal", "size", "sig", F.lit(0).alias("s")), "live")
    found = None
    for _ in range(max_rounds):
        left = {(r["size"], r["s"]): r["count"] for r in now.groupBy("size", "s").count().collect()}  # two rows a size
        if not any(s == 0 for _, s in left):
            return now.select("ordinal", "size", "sig") if found is None else found
        if sum(n * plan.mark_count(x) for (x, _), n in left.items()) <= last_keys:
            rest = settle(_end(now, plan), "leaders")
            return rest if found is None else found.union(rest)
        now = settle(_round(now, plan), "live")
        new = now.filter("s = 1").select("ordinal", "size", "sig")
        found = new if found is None else found.union(new)
    raise RuntimeError("rounds did not end")


def candidates(sigs: DataFrame, led: DataFrame, plan: OverlapPlan) -> DataFrame:
    """(ordinal, leader, votes): every similar leader at or before an item, and how many keys match; a leader has itself."""
    marks = role_keys(led, plan, "mark").select("key", F.col("ordinal").alias("leader"))
    probes = role_keys(sigs, plan, "probe").select("key", "ordinal")
    return probes.join(marks, "key").filter("leader <= ordinal").groupBy("ordinal", "leader").agg(F.count("*").alias("votes"))


def scored(found: DataFrame, sigs: DataFrame, led: DataFrame, plan: OverlapPlan) -> DataFrame:
    a = sigs.select("ordinal", F.col("sig").alias("__a"))
    b = led.select(F.col("ordinal").alias("leader"), F.col("sig").alias("__b"))
    met = found.join(a, "ordinal").join(b, "leader").withColumn("overlap", F.size(F.array_intersect("__a", "__b")))
    return met.select("ordinal", "leader", "votes", "overlap", plan.rule.score_col(F.col("overlap"), F.size("__a"), F.size("__b")).alias("score"))


def leader(sigs: DataFrame, plan: OverlapPlan, choice: str = "earliest", led: DataFrame | None = None) -> DataFrame:
    """(cluster_id, ordinal, elements); the id is the leader's ordinal. Ties of a choice go to the earliest.

    The leaders don't depend on the choice; a leader always stays in its own cluster.
    """
    led = leaders(sigs, plan) if led is None else led
    if choice == "earliest":  # a copy's earliest leader is its first copy's; other choices may fall on later leaders
        distinct = settle(collapse_identical(sigs).select("ordinal", "size", "sig"), "distinct")
        marks = role_keys(led, plan, "mark").groupBy("key").agg(F.min("ordinal").alias("leader"))
        probes = role_keys(distinct, plan, "probe").select("key", "ordinal")
        best = probes.join(marks, "key").groupBy("ordinal").agg(F.min("leader").alias("cluster_id"))
    else:
        found = scored(candidates(sigs, led, plan), sigs, led, plan)
        own = F.col("leader") == F.col("ordinal")
        rank = {
            "latest": F.struct(own.alias("own"), F.col("leader").alias("a")),
            "overlap": F.struct(own.alias("own"), F.col("overlap").alias("a"), (-F.col("leader")).alias("b")),
            "score": F.struct(own.alias("own"), F.col("score").alias("a"), (-F.col("leader")).alias("b")),
            "votes": F.struct(own.alias("own"), F.col("votes").alias("a"), (-F.col("leader")).alias("b")),
        }[choice]
        best = found.groupBy("ordinal").agg(F.max_by("leader", rank).alias("cluster_id"))
        return sigs.join(best, "ordinal").select("cluster_id", "ordinal", F.col("sig").alias("elements"))
    of_sig = distinct.join(best, "ordinal").select("sig", "cluster_id")
    return sigs.join(of_sig, "sig").select("cluster_id", "ordinal", F.col("sig").alias("elements"))


LAST_LINKS = 1_000_000  # links of what is undecided, up to which one task ends the rounds


def _members_of(links: DataFrame) -> DataFrame:
    """Items of (j, i) links, j < i, that join another: one after another, in one task."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        parts = list(frames)
        joined: set[int] = set()
        for j, i in pd.concat(parts).sort_values("i").itertuples(index=False) if parts else ():
            if j not in joined:
                joined.add(i)
        yield pd.DataFrame({"i": sorted(joined)}, dtype="int64")

    return links.select("j", "i").coalesce(1).mapInPandas(run, "i bigint")


def leader_by_links(sigs: DataFrame, plan: OverlapPlan, last_links: int = LAST_LINKS) -> DataFrame:
    """The earliest-leader clusters from links of distinct signatures by their rarest elements: for long signatures, with many keys.

    An item with no undecided earlier neighbour leads, its later neighbours join; both go with their links.
    """
    from .baselines import rare_classes

    links, classes, members = rare_classes(sigs, plan)
    near = settle(links.filter("marker < prober").select(F.col("marker").alias("j"), F.col("prober").alias("i")), "links")
    left, joined = near, None
    while True:
        few = left.count() <= last_links
        if few:
            new = settle(_members_of(left), "joined")
        else:
            heads = left.select("j").distinct().join(left.select(F.col("i").alias("j")), "j", "left_anti")
            new = settle(left.join(heads, "j", "left_semi").select("i").distinct(), "joined")
        joined = new if joined is None else joined.union(new)
        if few:
            break
        left = settle(left.join(new, "i", "left_anti").join(new.withColumnRenamed("i", "j"), "j", "left_anti").select("j", "i"), "links")
    # links to items that joined don't count, those to leaders do; a leader has none to another
    best = near.join(joined.withColumnRenamed("i", "j"), "j", "left_anti").groupBy("i").agg(F.min("j").alias("cluster_id"))
    home = classes.select(F.col("ordinal").alias("cls"), "sig").join(best.withColumnRenamed("i", "cls"), "cls", "left")
    home = home.select("sig", F.coalesce("cluster_id", "cls").alias("cluster_id"))
    return sigs.join(home, "sig").select("cluster_id", "ordinal", F.col("sig").alias("elements"))


def leader_multi(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """(ordinal, cluster_id, score): every cluster whose leader is similar."""
    led = leaders(sigs, plan)
    return scored(candidates(sigs, led, plan), sigs, led, plan).select("ordinal", F.col("leader").alias("cluster_id"), "score")


def _numbered(sigs: DataFrame) -> tuple[DataFrame, int]:
    """(place, ordinal, size, sig): the distinct signatures in the order of their first arrivals; and how many there are."""
    first = collapse_identical(sigs).select(F.col("ordinal").alias("first"), "size", "sig")
    placed = with_ordinal(first, F.floor(F.col("first") / 65536), "first")
    distinct = settle(placed.select(F.col("ordinal").alias("place"), F.col("first").alias("ordinal"), "size", "sig"), "distinct")
    return distinct, distinct.count()


def leader_step(batch: DataFrame, plan: OverlapPlan, store: KeyStore, batch_id: int) -> DataFrame:
    """Assignments of one batch of arrivals, written: stored leaders come first, the rest goes through rounds.

    The keys of the new leaders are appended to the store, so a step costs what its batch does.
    """
    distinct = settle(collapse_identical(batch).select("ordinal", "size", "sig"), "distinct")
    known = store.probe(role_keys(distinct, plan, "probe"), batch_id)
    known = settle(distinct.join(known, "ordinal", "left"), "known")
    rest = known.filter("leader is null").select("ordinal", "size", "sig")
    new = settle(leaders(rest, plan).select("ordinal", "size", "sig"), "leaders")
    store.append(new, batch_id)
    own = leader(rest, plan, led=new).select(F.col("elements").alias("sig"), "cluster_id")
    home = known.filter("leader is not null").select("sig", F.col("leader").alias("cluster_id")).union(own)
    return settle(batch.join(home, "sig").select("cluster_id", "ordinal", F.col("sig").alias("elements")), "assigned")


HOMES = "ordinal bigint, size int, sig array<string>, cluster_id bigint"


def _small_step(distinct: DataFrame, plan: OverlapPlan, store: KeyStore, batch_id: int) -> str:
    """The same for a batch of distinct signatures with few keys: what no stored leader takes is decided in one task.

    Returns the path of HOMES rows.
    """

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        engine, out = Engine(plan), []
        for r in whole(frames).itertuples(index=False):
            sig = list(r.sig)
            out.append((r.ordinal, r.size, sig, engine.assign(r.ordinal, sig, engine.keys(sig)) if pd.isna(r.leader) else int(r.leader)))
        yield pd.DataFrame(out, columns=["ordinal", "size", "sig", "cluster_id"])

    known = store.probe(role_keys(distinct, plan, "probe"), batch_id)
    home = settle(distinct.join(known, "ordinal", "left").coalesce(1).mapInPandas(run, HOMES), "homes")
    store.append(home.filter("cluster_id = ordinal"), batch_id)
    return home.settled_at


def leader_batched(sigs: DataFrame, plan: OverlapPlan, batch_rows: int, store: KeyStore | None = None) -> DataFrame:
    """The same clusters, arrivals in batches, over a key store that may hold earlier leaders.

    A copy's leader is its first item's, so batches are of ``batch_rows`` distinct signatures. Where stored leaders
    expire, copies can outlive theirs: then batches are of ``batch_rows`` ordinals, copies included.
    """
    from overlapkeys.sources.io import KeyStore

    spark = sigs.sparkSession
    store = store or KeyStore(spark, scratch(spark, "keys"), plan)
    if store.keep is not None or batch_rows * max(map(plan.mark_count, plan.sizes)) > LAST_KEYS:
        return _by_ordinals(sigs, plan, batch_rows, store)
    distinct, top = _numbered(sigs.filter(F.col("size").isin(*plan.sizes)))  # others have no keys
    paths, first = [], store.next_batch()
    for start in range(0, top, batch_rows):
        batch = distinct.filter((F.col("place") > start) & (F.col("place") <= start + batch_rows)).drop("place")
        paths.append(_small_step(batch, plan, store, first + len(paths)))
    if not paths:
        return leader(sigs, plan)
    home = spark.read.schema(HOMES).parquet(*paths).select("sig", "cluster_id")
    return sigs.join(home, "sig").select("cluster_id", "ordinal", F.col("sig").alias("elements"))


def _by_ordinals(sigs: DataFrame, plan: OverlapPlan, batch_rows: int, store: KeyStore) -> DataFrame:
    out = None
    first, top = sigs.agg(F.min("ordinal"), F.max("ordinal")).first()
    for start in range((first or 1) - 1, top or 0, batch_rows):
        batch = sigs.filter((F.col("ordinal") > start) & (F.col("ordinal") <= start + batch_rows))
        part = leader_step(batch, plan, store, store.next_batch())
        out = part if out is None else out.union(part)
    return out if out is not None else leader(sigs, plan)


def leader_reference(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """One item at a time over a dictionary, in one task: for tests and small comparisons only."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        store: dict[tuple, int] = {}
        rows = []
        for r in whole(frames).itertuples(index=False):
            sig = list(r.sig)
            hits = [store[k] for t, pos in plan.combos(len(sig), "probe") if (k := (t, *(sig[p - 1] for p in pos))) in store]
            cluster = min(hits) if hits else r.ordinal
            if not hits:
                for t, pos in plan.combos(len(sig), "mark"):
                    store.setdefault((t, *(sig[p - 1] for p in pos)), r.ordinal)
            rows.append((cluster, r.ordinal, sig))
        yield pd.DataFrame(rows, columns=["cluster_id", "ordinal", "elements"])

    return sigs.select("ordinal", "sig").coalesce(1).mapInPandas(run, "cluster_id bigint, ordinal bigint, elements array<string>")


def centroid_scan_reference(sigs: DataFrame, plan: OverlapPlan) -> DataFrame:
    """The control: each arrival is compared with every leader in turn, the earliest similar one wins; one task.

    It walks the distinct signatures: a copy finds its first item's leader, after as many comparisons as that one's place.
    """

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pdf = whole(frames)
        led: list[tuple[int, frozenset]] = []
        rows = []
        for r in pdf.itertuples(index=False):
            sig, done, home = frozenset(r.sig), 0, None
            for i, other in led:
                done += 1
                if plan.rule.holds(len(sig & other), len(sig), len(other)):
                    home = i
                    break
            again = done
            if home is None:
                led.append((r.ordinal, sig))
                home, again = r.ordinal, done + 1
            rows.append((home, r.ordinal, done, again))
        yield pd.DataFrame(rows, columns=["cluster_id", "first", "done", "again"])

    distinct = settle(collapse_identical(sigs).select("ordinal", "sig"), "distinct")
    walked = distinct.coalesce(1).mapInPandas(run, "cluster_id bigint, first bigint, done bigint, again bigint")
    walked = distinct.withColumnRenamed("ordinal", "first").join(walked, "first").select("sig", "cluster_id", "first", "done", "again")
    comparisons = F.when(F.col("ordinal") == F.col("first"), F.col("done")).otherwise(F.col("again"))
    return sigs.select("ordinal", "sig").join(walked, "sig").select("cluster_id", "ordinal", comparisons.alias("comparisons"))


BLOCK = 2048  # leaders, or arrivals of a batch, on one side of a product of incidence matrices


def _similar(items: list, others: list, rule: SimilarityRule) -> np.ndarray:
    """Is each of ``items`` similar to each of ``others``? Overlaps from incidence matrices, the rule on integers."""
    codes = {e: k for k, e in enumerate({e for sig in items for e in sig})}

    def incidence(sigs: list) -> np.ndarray:
        out = np.zeros((len(sigs), max(1, len(codes))), np.float32)
        for k, sig in enumerate(sigs):
            out[k, [c for e in sig if (c := codes.get(e)) is not None]] = 1
        return out

    x, y = (np.array([len(sig) for sig in s], np.int64) for s in (items, others))
    return rule.holds_each((incidence(items) @ incidence(others).T).astype(np.int64), x[:, None], y[None, :])


def _scan(items: list, led: list[tuple[int, list]], rule: SimilarityRule) -> list[int | None]:
    """The earliest similar one of ``led``, rising by ordinal, for each of ``items``: those without one go on to the next block."""
    home: list[int | None] = [None] * len(items)
    open_ = list(range(len(items)))
    for lo in range(0, len(led), BLOCK):
        near = _similar([items[k] for k in open_], [sig for _, sig in led[lo : lo + BLOCK]], rule)
        for k, hit, at in zip(open_, near.any(1).tolist(), near.argmax(1).tolist()):
            if hit:
                home[k] = led[lo + at][0]
        open_ = [k for k in open_ if home[k] is None]
        if not open_:
            break
    return home


def _walk(ordinals: list[int], sigs: list, rule: SimilarityRule) -> list[int]:
    """Leaders of arrivals that no earlier leader takes, one after another."""
    led: list[tuple[int, list]] = []
    out = []
    for lo in range(0, len(sigs), BLOCK):
        own = sigs[lo : lo + BLOCK]
        home, near = _scan(own, led, rule), _similar(own, own, rule)
        fresh: list[int] = []
        for k in range(len(own)):
            if home[k] is None:
                hits = near[k, fresh]
                home[k] = ordinals[lo + (fresh[int(hits.argmax())] if hits.any() else k)]
                if home[k] == ordinals[lo + k]:
                    fresh.append(k)
        led += [(ordinals[lo + k], own[k]) for k in fresh]
        out += home
    return out


def centroid_scan(sigs: DataFrame, plan: OverlapPlan, batch_rows: int = 2000) -> DataFrame:
    """The control for Spark: distinct signatures in batches of arrivals; a batch meets all leaders so far, then itself.

    Leaders are dealt in blocks over the tasks, and each block takes the whole batch. What no block takes goes one
    after another in one task. A copy's earliest similar leader is its first item's.
    """
    spark, rule, paths = sigs.sparkSession, plan.rule, []
    distinct, top = _numbered(sigs)

    def nearest(pdf: pd.DataFrame) -> pd.DataFrame:
        led = pdf[pdf["led"]].sort_values("ordinal")
        own = pdf[~pdf["led"]]
        home = _scan(own["sig"].tolist(), list(zip(led["ordinal"].tolist(), led["sig"].tolist())), rule)
        met = [(o, h) for o, h in zip(own["ordinal"].tolist(), home) if h is not None]
        return pd.DataFrame(met, columns=["ordinal", "home"]).astype("int64")

    def rest(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pdf = whole(frames)
        left = pdf[pdf["home"].isna()]
        own = dict(zip(left["ordinal"], _walk(left["ordinal"].tolist(), left["sig"].tolist(), rule)))
        pdf["cluster_id"] = [own[o] if o in own else int(h) for o, h in zip(pdf["ordinal"], pdf["home"])]
        yield pdf[["place", "ordinal", "sig", "cluster_id"]]

    schema = "place bigint, ordinal bigint, sig array<string>, cluster_id bigint"
    for start in range(0, top, batch_rows):
        batch = distinct.filter((F.col("place") > start) & (F.col("place") <= start + batch_rows)).select("place", "ordinal", "sig")
        if paths:
            led = spark.read.schema(schema).parquet(*paths).filter("cluster_id = ordinal")
            blocks = F.sequence(F.lit(0), F.lit(start // BLOCK))
            met = led.select(F.expr(f"place div {BLOCK}").cast("int").alias("block"), "ordinal", "sig", F.lit(True).alias("led"))
            met = met.union(batch.select(F.explode(blocks), "ordinal", "sig", F.lit(False)))
            known = met.groupBy("block").applyInPandas(nearest, "ordinal bigint, home bigint").groupBy("ordinal").agg(F.min("home").alias("home"))
            batch = batch.join(known, "ordinal", "left").select("place", "ordinal", "sig", "home")
        else:
            batch = batch.withColumn("home", F.lit(None).cast("bigint"))
        paths.append(settle(batch.coalesce(1).mapInPandas(rest, schema), "homes").settled_at)
    if not paths:
        return sigs.select(F.col("ordinal").alias("cluster_id"), "ordinal", F.col("sig").alias("elements"))
    home = spark.read.schema(schema).parquet(*paths).select("sig", "cluster_id")
    return sigs.join(home, "sig").select("cluster_id", "ordinal", F.col("sig").alias("elements"))
