"""Near-duplicate documents by a chosen-path similarity join over minwise values.

A document's set holds the hashes of its word shingles. Texts with equal sets form one class, which takes part once. Independent
trees branch the classes: a node picks some coordinates of the minwise signature (by its own path alone) and sends each class
to the child named by its value there, so that a pair of similarity s stays together with probability s a choice. A node of at
most ``leaf`` classes is compared exhaustively by signatures; larger ones branch on, at most ``depth`` times, and what is still
large then is taken as one candidate cluster. Candidates only narrow the work: each cluster of connected candidates is then
resolved exactly on full sets. In a cluster of many classes, pivots are compared with all members in chunks, and all members
outside the cluster's largest component become pivots, until no link between two components can be missing.

Edge cases: null or empty text, and text without words, has an empty set, links with nothing and stays; fewer words than a
shingle form one shingle; rows without an id stay and have no component; rows that repeat an id are one document with several
texts: a link of any of them links all, and they go or stay together; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import TextHash, claim, column_bytes, dealt_join, mark, salted_join, slices, stage, sweep, unused
from .components import Forest, chain, components

WIDTH = 64
LEAF = 64
RECALL = 0.98
DEPTH = 8
STUBBORN = 3  # from this level on, a large node that keeps half of its parent is one cluster
BRANCH = 0.33  # chance that a node picks a second coordinate
CHUNK = 256
HASH = TextHash(3)
_RNG = np.random.default_rng(5)
MULTIPLY = _RNG.integers(0, 1 << 63, WIDTH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
ADD = _RNG.integers(0, 1 << 63, WIDTH, dtype=np.uint64)


def shingles(text: bytes, words: int = 5) -> np.ndarray:
    """Sorted distinct hashes of all runs of ``words`` words (ASCII white space between, A-Z as a-z)."""
    parts = text.lower().split()
    n = len(parts)
    if not n:
        return np.zeros(0, np.uint64)
    prefix = HASH.prefixes(np.frombuffer(b" ".join(parts), np.uint8))
    size = np.fromiter(map(len, parts), np.int64, n)
    end = np.cumsum(size + 1) - 1
    start = end - size
    if n < words:
        return HASH.spans(prefix, start[:1], end[-1:])
    return np.unique(HASH.spans(prefix, start[: n - words + 1], end[words - 1 :]))


def set_key(s: np.ndarray) -> tuple[int, int]:
    """128 bits that name a set."""
    if not len(s):
        return 0, 0
    a, b = HASH.mix(s * np.uint64(0xD6E8FEB86659FD93)), HASH.mix(s ^ np.uint64(0xA0761D6478BD642F))
    return int(a.sum(dtype=np.uint64).astype(np.int64)), int(b.sum(dtype=np.uint64).astype(np.int64))


def signature(s: np.ndarray) -> np.ndarray:
    """Minwise values of a non-empty set."""
    out = np.full(WIDTH, 0xFFFFFFFF, np.uint32)
    for lo in range(0, len(s), 4096):
        part = s[lo : lo + 4096]
        out = np.minimum(out, ((part[None, :] * MULTIPLY[:, None] + ADD[:, None]) >> np.uint64(32)).min(axis=1).astype(np.uint32))
    return out


def _sketch(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("sets")
        for batch in slices(batches):
            n, k1, k2, sig = [], [], [], []
            for text in column_bytes(batch.column(1)):
                s = shingles(text, words)
                key = set_key(s)
                n.append(len(s))
                k1.append(key[0])
                k2.append(key[1])
                sig.append(signature(s).view(np.int32) if len(s) else None)
            yield pa.record_batch([batch.column(0), pa.array(n, pa.int64()), pa.array(k1, pa.int64()), pa.array(k2, pa.int64()), pa.array(sig, pa.list_(pa.int32()))], names=["doc_id", "n_shingles", "k1", "k2", "sig"])

    return run


def stay(similarity: float, depth: int = DEPTH, branch: float = BRANCH) -> float:
    """Chance that a pair of a similarity shares a node on the last level of one tree."""
    chance = 1.0
    for _ in range(depth):
        one = similarity * chance
        chance = one + branch * one * (1 - one)  # a second coordinate helps where the first has parted them
    return chance


def recall_of(trees: int, similarity: float, depth: int = DEPTH, branch: float = BRANCH) -> float:
    """Chance that a pair at ``similarity`` shares a last node in one of some trees. All trees read one signature, so the chance is taken over the
    share of its values that the pair has in common."""
    chance = 0.0
    for agree in range(WIDTH + 1):
        weight = math.comb(WIDTH, agree) * similarity**agree * (1 - similarity) ** (WIDTH - agree)
        chance += weight * (1 - (1 - stay(agree / WIDTH, depth, branch)) ** trees)
    return chance


def trees_for(recall: float, similarity: float, depth: int = DEPTH, branch: float = BRANCH) -> int:
    """The least number of trees with that recall."""
    trees = 1
    while recall_of(trees, similarity, depth, branch) < recall and trees < 1000:
        trees += 1
    return trees


# ---- trees ---------------------------------------------------------------------------------------------------------------


def _children(node: Column, sig: Column) -> Column:
    """The children of a node that a class goes to: one or two coordinates, picked by the node's path."""

    def child(salt: int) -> Column:
        pick = F.pmod(F.xxhash64(node, F.lit(salt)), F.lit(WIDTH)).cast("int")
        return F.xxhash64(node, F.lit(salt), F.element_at(sig, pick + 1))

    second = F.pmod(F.xxhash64(node, F.lit(-1)), F.lit(1000)) < int(1000 * BRANCH)
    return F.when(second, F.array(child(1), child(2))).otherwise(F.array(child(1)))


def _compare(least: float):
    """Candidate links inside each small node, as a chain of each connected part, by estimated similarity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = [], []
            for members in batch.column(0).to_pylist():
                reps = [m["rep"] for m in members]
                sig = np.array([m["sig"] for m in members], np.int32)
                forest = Forest()
                for i in range(len(reps) - 1):
                    near = np.flatnonzero((sig[i + 1 :] == sig[i]).mean(axis=1) >= least)
                    for j in near:
                        forest.join(reps[i], reps[i + 1 + int(j)])
                for x, before in chain((x, root) for x, root in forest.links() if x != root):
                    a.append(before)
                    b.append(x)
            yield pa.record_batch([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return run


def candidate_links(classes: DataFrame, similarity: float, leaf: int = LEAF, recall: float = RECALL, depth: int = DEPTH) -> DataFrame:
    """Links (a, b) between classes (rep, sig) that connect all likely similar ones."""
    spark, since = classes.sparkSession, mark()
    roots = F.flatten(F.array(*[_children(F.xxhash64(F.lit(t)), F.col("sig")) for t in range(trees_for(recall, similarity, depth))]))
    at = classes.select("rep", F.explode(roots).alias("node"), F.lit(0).cast("long").alias("above"))
    found: list[DataFrame] = []
    for level in range(1, depth + 1):
        at = stage(at, f"level{level}")
        sizes = stage(at.groupBy("node").agg(F.count("*").alias("n"), F.max("above").alias("above")).where("n > 1"), "nodes")
        large = sizes.where(F.col("n") > leaf)
        any_large = large.limit(1).count() > 0
        # members of small nodes; those of a large one are dealt over several keys
        rest = salted_join(at, large.select("node"), ["node"], "rep", "left_anti") if any_large else at
        lists = rest.groupBy("node").agg(F.array_sort(F.collect_set("rep")).alias("reps")).where("size(reps) > 1").select("reps").distinct()
        lists = lists.select(F.xxhash64("reps").alias("list"), F.explode("reps").alias("rep"))
        groups = lists.join(classes.select("rep", "sig").hint("merge"), "rep").groupBy("list").agg(F.collect_list(F.struct("rep", "sig")).alias("m")).select("m")
        found.append(stage(groups.mapInArrow(_compare(similarity - 0.25), "a long, b long"), "near"))
        if any_large:
            inside = stage(salted_join(at.select("rep", "node"), large, ["node"], "rep").select("node", "rep", "n", "above"), "large")
            dense = (F.lit(level) == depth) | (F.lit(level) >= STUBBORN) & (2 * F.col("n") >= F.col("above"))
            if level >= STUBBORN or level == depth:
                # links by slices to the smallest class of each slice, and these to the smallest of all: no class has very many
                slices = inside.where(dense).select("node", "rep", F.pmod(F.hash("rep"), F.ceil(F.col("n") / leaf)).alias("slice"))
                heads = slices.groupBy("node", "slice").agg(F.min("rep").alias("head"))
                tied = salted_join(heads, heads.groupBy("node").agg(F.min("head").alias("a")), ["node"], "head").select("a", F.col("head").alias("b"))
                found.append(stage(slices.join(heads.hint("merge"), ["node", "slice"]).select(F.col("head").alias("a"), F.col("rep").alias("b")).union(tied).where("a <> b").distinct(), "dense"))
            more = inside.where(~dense)
        sweep(spark, since, *found, *([inside] if any_large else []))
        if not any_large or level == depth:
            break
        at = more.join(classes.select("rep", "sig").hint("merge"), "rep").select("rep", F.explode(_children(F.col("node"), F.col("sig"))).alias("node"), F.col("n").alias("above"))
    out = found[0]
    for links in found[1:]:
        out = out.union(links)
    return out


# ---- exact links on full sets ---------------------------------------------------------------------------------------------


def similar(inter: np.ndarray, size_a: int, size_b: np.ndarray, percent: int) -> np.ndarray:
    return 100 * inter >= percent * (size_a + size_b - inter)


class Sets:
    """Sets laid end to end, to count what each shares with another at once."""

    def __init__(self, sets: list[np.ndarray]) -> None:
        self.size = np.array([len(s) for s in sets], np.int64)
        flat = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
        owner = np.repeat(np.arange(len(sets)), self.size)
        order = np.argsort(flat, kind="stable")
        self.value, self.owner = flat[order], owner[order]

    def shared(self, s: np.ndarray) -> np.ndarray:
        lo, hi = np.searchsorted(self.value, s, "left"), np.searchsorted(self.value, s, "right")
        hit = lo < hi
        lo, hi = lo[hit], hi[hit]
        n = hi - lo
        at = np.repeat(lo - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum()) if len(n) else np.zeros(0, np.int64)
        return np.bincount(self.owner[at], minlength=len(self.size))


LINKS = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def _exact_small(percent: int):
    def run(table: pa.Table) -> pa.Table:
        seen = dict(zip(table.column("rep").to_pylist(), table.column("shingles").to_pylist(), strict=True))
        reps = sorted(seen)
        sets = [np.frombuffer(seen[r], np.uint64) for r in reps]
        joined, forest, out = Sets(sets), Forest(), []
        for i, s in enumerate(sets):
            if i and all(forest.root(r) == forest.root(reps[0]) for r in reps[i:]):
                break
            for j in np.flatnonzero(similar(joined.shared(s), len(s), joined.size, percent)):
                if j != i and forest.join(reps[i], reps[int(j)]):
                    out.append((reps[i], reps[int(j)]))
        return pa.table([pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.int64())], schema=LINKS)

    return run


def _exact_pivots(percent: int):
    def run(members: pa.Table, pivots: pa.Table) -> pa.Table:
        a, b = [], []
        if members.num_rows and pivots.num_rows:
            reps = members.column("rep").to_pylist()
            joined = Sets([np.frombuffer(x, np.uint64) for x in members.column("shingles").to_pylist()])
            for p, raw in zip(pivots.column("rep").to_pylist(), pivots.column("shingles").to_pylist(), strict=True):
                s = np.frombuffer(raw, np.uint64)
                chain = p
                for j in np.flatnonzero(similar(joined.shared(s), len(s), joined.size, percent)):
                    if reps[j] != p:
                        a.append(chain)
                        b.append(reps[j])
                        chain = reps[j]
        return pa.table([pa.array(a, pa.int64()), pa.array(b, pa.int64())], schema=LINKS)

    return run


def _to_sets(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("sets")
        for batch in slices(batches):
            keep, raw = [], []
            for i, (k1, k2, text) in enumerate(zip(batch.column("k1").to_pylist(), batch.column("k2").to_pylist(), column_bytes(batch.column("text")), strict=True)):
                s = shingles(text, words)
                if set_key(s) == (k1, k2):
                    keep.append(i)
                    raw.append(s.tobytes())
            rows = batch.take(pa.array(keep, pa.int64()))
            yield pa.record_batch([rows.column("rep"), rows.column("cluster"), rows.column("chunk"), rows.column("size"), pa.array(raw, pa.binary())], names=["rep", "cluster", "chunk", "size", "shingles"])

    return run


def _large_clusters(sets: DataFrame, percent: int) -> DataFrame:
    """Links in clusters of many classes, by rounds of pivots; ``sets``: rep, cluster, chunk, shingles."""
    chunks = sets.select("cluster", "chunk").distinct()
    label = sets.select("rep", "cluster", F.col("rep").alias("component"))
    done = links = None
    share = 64
    while True:
        if done is None:
            open_ = label.select("rep", "cluster")
        else:
            # all outside the largest component of their cluster that have not been pivots
            counts = label.groupBy("cluster", "component").count()
            main = counts.groupBy("cluster").agg(F.max(F.struct("count", "component")).alias("m")).select("cluster", F.col("m.component").alias("main"))
            open_ = stage(salted_join(label, main, ["cluster"], "rep").where("component <> main").select("rep", "cluster").join(done.hint("merge"), "rep", "left_anti"), "pivot-open")
        # those whose hash is below a bar that about ``share`` members of each cluster pass; all, once few are open
        sizes = open_.groupBy("cluster").agg(F.count("*").alias("open"))
        bar = F.pmod(F.xxhash64("rep", F.lit(share)), F.lit(1 << 30)) < (F.lit(float(share)) / F.col("open") * (1 << 30))
        pivots = stage(salted_join(open_, sizes, ["cluster"], "rep").where(bar | (F.col("open") <= share)).select("rep", "cluster"), "pivots")
        share *= 8
        if not pivots.limit(1).count():
            if not open_.limit(1).count():
                return links
            continue
        sent = pivots.hint("merge").join(sets.select("rep", "shingles"), "rep").join(chunks.hint("merge"), "cluster").select("cluster", "chunk", "rep", "shingles").toDF("cluster", "chunk", "rep", "shingles")
        new = sets.groupBy("cluster", "chunk").cogroup(sent.groupBy("cluster", "chunk")).applyInArrow(_exact_pivots(percent), "a long, b long")
        done = pivots.select("rep") if done is None else stage(done.union(pivots.select("rep")), "pivot-done")
        found = stage(components(new if links is None else new.union(links)), "pivot-labels")
        links = found.toDF("a", "b")
        label = sets.select("rep", "cluster").join(found.withColumnRenamed("id", "rep").hint("merge"), "rep", "left").select("rep", "cluster", F.coalesce("component", "rep").alias("component"))


def near_duplicates(docs: DataFrame, percent: int = 75, words: int = 5, recall: float = RECALL) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of each row of ``docs`` (doc_id, text): linked at ``percent`` of similarity."""
    spark, since = docs.sparkSession, mark()
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    sketches = stage(docs.mapInArrow(_sketch(words), "doc_id long, n_shingles long, k1 long, k2 long, sig array<int>"), "sketches")
    with_set = sketches.where("n_shingles > 0 and doc_id is not null")
    classes = stage(with_set.groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n"), F.first("sig").alias("sig")), "classes")
    clusters = components(candidate_links(classes.select("rep", "sig"), percent / 100, recall=recall))
    clusters = stage(clusters.union(clusters.select("component", "component").distinct()).toDF("rep", "cluster"), "clusters")
    sizes = stage(clusters.groupBy("cluster").agg(F.count("*").alias("size")), "sizes")
    placed = dealt_join(clusters, sizes, ["cluster"], "rep", "size").withColumn("chunk", F.pmod(F.hash("rep"), F.ceil(F.col("size") / CHUNK)).cast("int"))
    placed = stage(placed.join(classes.select("rep", "k1", "k2").hint("merge"), "rep").select("rep", "cluster", "chunk", "size", "k1", "k2"), "placed")
    sweep(spark, since, sketches, classes, placed)
    # texts meet their classes by shuffle at any size; then only the sets of candidates are moved
    members = docs.withColumnRenamed("doc_id", "rep").join(placed.hint("merge"), "rep").select("rep", "cluster", "chunk", "size", "k1", "k2", "text")
    sets = stage(members.mapInArrow(_to_sets(words), "rep long, cluster long, chunk int, size long, shingles binary").dropDuplicates(["rep"]), "sets")
    links = stage(sets.where(F.col("size") <= CHUNK).groupBy("cluster").applyInArrow(_exact_small(percent), "a long, b long"), "links")
    if placed.where(F.col("size") > CHUNK).limit(1).count():
        links = links.union(_large_clusters(sets.where(F.col("size") > CHUNK).select("rep", "cluster", "chunk", "shingles"), percent))
    # classes that share a document with several texts
    repeated = with_set.groupBy("doc_id").agg(F.min("k1").alias("a"), F.max("k1").alias("b")).where("a <> b").select("doc_id")
    several = stage(with_set.join(repeated.hint("merge"), "doc_id").select("doc_id", "k1", "k2").distinct(), "several")
    if several.limit(1).count():
        held = several.join(classes.select("k1", "k2", "rep").hint("merge"), ["k1", "k2"]).select("doc_id", "rep")
        links = links.union(held.join(held.groupBy("doc_id").agg(F.min("rep").alias("a")).hint("merge"), "doc_id").select("a", F.col("rep").alias("b")))
    final = stage(components(links), "final")
    named = classes.join(final.withColumnRenamed("id", "rep").hint("merge"), "rep", "left").where((F.col("n") > 1) | F.col("component").isNotNull())
    named = stage(named.select("k1", "k2", "n", F.coalesce("component", "rep").alias("component_id")), "named")
    sweep(spark, since, sketches, named)
    rows = sketches.select("doc_id", "n_shingles", "k1", "k2")
    # a class of very many copies is dealt over several keys
    out = dealt_join(rows, named, ["k1", "k2"], "doc_id", "n", "left")
    component = F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def drop_near_duplicates(docs: DataFrame, percent: int = 75, words: int = 5) -> DataFrame:
    """The rows of ``docs`` without those whose component has a smaller id; all columns as they are."""
    judged = near_duplicates(docs, percent, words).where("doc_id is not null and n_shingles > 0").groupBy("doc_id").agg(F.bool_or("kept").alias("stay"))
    name = unused(docs, "__gone")
    gone = judged.where(~F.col("stay")).select(F.col("doc_id").alias(name))
    return docs.join(gone.hint("merge"), docs["doc_id"] == gone[name], "left_anti")
