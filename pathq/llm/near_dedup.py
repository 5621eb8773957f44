"""Near duplicates of documents by a chosen-path set similarity join.

A document is the set of its distinct word shingles. Documents with equal sets are one class from the start.
The classes are branched recursively: a node of a tree picks, by its own hash, one or two of the minwise
positions, and its documents go to children by their minwise token there. Two sets of similarity s stay together
with probability s per step, and on average 1.25 positions are picked, so that pairs at the threshold are not
thinned out as they descend. Nodes that have become small are compared exhaustively; independent trees are
repeated until the target recall is met for pairs at the threshold. Compared pairs pass a test of 512-bit sketches,
which keeps 4.5 standard deviations, and are then confirmed on full sets read again from the texts. In all but tiny
nodes this takes two passes: the most similar pairs that span the node first, then, within the node's task, all whose
ends are not in one component by then. So a group of copies is confirmed by about as many pairs as it has members.

Nodes that stay large after a few steps hold many mutually similar sets. There a pivot is compared with all
members on full sets. Jaccard distance is a metric, so a member that is nearer to the pivot than
``d_min - (1 - threshold)``, with ``d_min`` the smallest distance of a member that did not link, can link
with nothing that the pivot's links do not already connect; it leaves the node. The others branch on. No node is
capped or sampled, and a group of copies costs comparisons in proportion to its size.

The number of trees follows from the depth at which nodes are compared, as a pair at the threshold survives fewer of
more steps. The first trees suffice for the first steps. Classes that go deeper get further trees among themselves, until
they have as many as their own depth asks for; a pair of which one end never went so deep has met already.

Edge cases: null, empty and blank texts have an empty set and link with nothing. Texts with fewer words than a
shingle are one shingle. Repeated rows are copies of each other. A row whose doc_id is null takes no part: it gets a
null component and kept = false. An empty table gives an empty result. Extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.llm.common import Workspace, prefilter
from pathq.llm.graph import components
from pathq.llm.shingles import document_sets, minhash, mix

POSITIONS = 64  # minwise values that branching picks from
SKETCHED = 256  # minwise values of which a sketch keeps two bits
SHALLOW = 3  # steps without pivots
HEAVY = 2_000_000  # shingles that a task holds of one node
TINY = 4  # nodes up to this size give all their pairs at once
SKETCH_SCHEMA = "doc_id long, n_shingles long, f1 long, f2 long, sketch binary, sig binary"


def _prints(h: np.ndarray) -> tuple[int, int]:
    """128 bits that name a set."""
    if not len(h):
        return 0, 0
    return int(np.sum(mix(h), dtype=np.uint64).view(np.int64)), int(np.bitwise_xor.reduce(mix(h + np.uint64(0x51ED270B))).view(np.int64))


def _sketches(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, f1, f2, sketch, sig = [], [], [], [], []
            for h in document_sets(batch["text"], k):
                low = minhash(h, SKETCHED)
                n.append(len(h))
                both = _prints(h)
                f1.append(both[0])
                f2.append(both[1])
                spread = mix(low.astype(np.uint64))
                sketch.append(np.packbits(((spread[None, :] >> np.array([[0], [1]], np.uint64)) & np.uint64(1)).astype(bool), axis=None).tobytes())
                sig.append(low[:POSITIONS].tobytes())
            yield pa.RecordBatch.from_arrays([batch["doc_id"].cast(pa.int64()), pa.array(n, pa.int64()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64()), pa.array(sketch, pa.binary()), pa.array(sig, pa.binary())], names=["doc_id", "n_shingles", "f1", "f2", "sketch", "sig"])

    return run


def _sets(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = list(document_sets(batch["text"], k))
            prints = [_prints(h) for h in sets]
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in prints], pa.int64()), pa.array([x[1] for x in prints], pa.int64()), pa.array([h.tobytes() for h in sets], pa.binary())], names=["f1", "f2", "set"])

    return run


def _overlaps(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(a, b, set_a, set_b) -> (a, b, both, either)."""
    for batch in batches:
        both, either = [], []
        for x, y in zip(batch["set_a"], batch["set_b"], strict=True):
            p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
            if len(p) > len(q):
                p, q = q, p
            at = np.searchsorted(q, p)
            at[at == len(q)] = 0
            same = int(np.count_nonzero(q[at] == p))
            both.append(same)
            either.append(len(p) + len(q) - same)
        yield pa.RecordBatch.from_arrays([batch["a"], batch["b"], pa.array(both, pa.int64()), pa.array(either, pa.int64())], names=["a", "b", "both", "either"])


def _nodes(batches: Iterator[pa.RecordBatch], columns: tuple[str, ...]) -> Iterator[list[np.ndarray]]:
    """Columns of one node after the other, from rows sorted by node."""
    held: list[list[np.ndarray]] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        node = batch["node"].to_numpy()
        # a sketch becomes a row of 64-bit words
        data = [np.frombuffer(b"".join(batch[c].to_pylist()), np.uint64).reshape(len(node), -1) if c == "sketch" else batch[c].to_numpy(zero_copy_only=False) for c in columns]
        edges = [0, *(np.flatnonzero(np.diff(node)) + 1).tolist(), len(node)]
        for lo, hi in zip(edges[:-1], edges[1:], strict=True):
            if node[lo] != last:
                if held:
                    yield [np.concatenate(c) for c in zip(*held, strict=True)] if len(held) > 1 else held[0]
                held, last = [], node[lo]
            held.append([c[lo:hi] for c in data])
    if held:
        yield [np.concatenate(c) for c in zip(*held, strict=True)] if len(held) > 1 else held[0]


def _gaps(n: np.ndarray, sketch: np.ndarray, threshold: int, most: int) -> np.ndarray:
    """Positions in which sketches differ, for all pairs of a node; 255 where sizes or sketches rule a link out."""
    m = len(n)
    gap = np.empty((m, m), np.uint8)
    half = sketch.shape[1] // 2
    for at in range(0, m, 128):  # in strips, so that no matrix of wide numbers is held
        part = sketch[at : at + 128]
        own = np.zeros((len(part), m), np.int16)
        for w in range(half):
            own += np.bitwise_count((part[:, w, None] ^ sketch[None, :, w]) | (part[:, half + w, None] ^ sketch[None, :, half + w]))
        a, b = n[at : at + 128, None], n[None, :]
        own[(own > most) | (np.minimum(a, b) * 100 < np.maximum(a, b) * threshold)] = 255
        gap[at : at + 128] = own
    np.fill_diagonal(gap, 255)
    return gap


def _spanning(gap: np.ndarray) -> tuple[list[int], list[int]]:
    """The most similar pairs that span each part of a node, grown one member at a time."""
    m = len(gap)
    best, by, out = gap[0].copy(), np.zeros(m, np.int64), np.ones(m, bool)
    out[0] = False
    a, b = [], []
    for _ in range(m - 1):
        j = int(np.argmin(np.where(out, best, 255)))
        if not out[j] or best[j] == 255:  # a new part
            j = int(np.argmax(out))
        else:
            a.append(int(by[j]))
            b.append(j)
        out[j] = False
        closer = gap[j] < best
        best = np.where(closer, gap[j], best)
        by[closer] = j
    return a, b


def _pair_batch(found: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    a, b = np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])
    return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["a", "b"])


def _near_pairs(threshold: int, most: int):
    """First pass over small nodes: all likely pairs of tiny ones, spanning pairs of the others."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, n_found = [], 0
        for rep, n, sketch in _nodes(batches, ("rep", "n", "sketch")):
            gap = _gaps(n, sketch, threshold, most)
            p, q = np.nonzero(np.triu(gap < 255)) if len(rep) <= TINY else _spanning(gap)
            if len(p):
                found.append((rep[p], rep[q]))
                n_found += len(p)
            if n_found > 50_000:
                yield _pair_batch(found)
                found, n_found = [], 0
        if found:
            yield _pair_batch(found)

    return run


def _cross_members(threshold: int, most: int):
    """Second pass: members with a likely partner in another component; what is in one component is settled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for node, rep, n, sketch, part in _nodes(batches, ("node", "rep", "n", "sketch", "part")):
            if (part == part[0]).all():
                continue
            gap = _gaps(n, sketch, threshold, most)
            open_ = ((gap < 255) & (part[:, None] != part[None, :])).any(axis=1)
            if open_.any():
                yield pa.RecordBatch.from_arrays([pa.array(c[open_]) for c in (node, rep, part)], names=["node", "rep", "part"])

    return run


def _cross_links(threshold: int):
    """Links across components among a node's members, from full sets: one for each two components that touch.

    An index from shingles to members counts a member's overlaps with all others at once.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rep, part, packed in _nodes(batches, ("rep", "part", "set")):
            sets = [np.frombuffer(x, np.uint64) for x in packed]
            sizes = np.array([len(x) for x in sets])
            owner = np.repeat(np.arange(len(sets)), sizes)
            _, token = np.unique(np.concatenate(sets), return_inverse=True)
            members = owner[np.argsort(token, kind="stable")]
            n_of = np.bincount(token)
            starts = np.concatenate(([0], np.cumsum(n_of)))
            at = np.concatenate(([0], np.cumsum(sizes)))
            a, b = [], []
            for i in range(len(sets)):
                own = token[at[i] : at[i + 1]]
                own = own[n_of[own] > 1]
                n = n_of[own]
                if not len(own):
                    continue
                spots = np.repeat(starts[own] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum())
                both = np.bincount(members[spots], minlength=len(sets))
                hit = np.flatnonzero((100 * both >= threshold * (sizes[i] + sizes - both)) & (part != part[i]))
                if len(hit):
                    hit = hit[np.unique(part[hit], return_index=True)[1]]
                    a.append(np.full(len(hit), rep[i]))
                    b.append(rep[hit])
            if a:
                yield _pair_batch([(np.concatenate(a), np.concatenate(b))])

    return run


def trees_for(depth: int, similarity: float, recall: float) -> int:
    """Trees after which a pair of that similarity has met with probability ``recall``, if its nodes are compared at that depth.

    All trees pick from the same positions, so the chance is taken over the number of positions in which the pair agrees.
    """
    agree = np.arange(POSITIONS + 1) / POSITIONS
    weight = np.array([math.comb(POSITIONS, i) * similarity**i * (1 - similarity) ** (POSITIONS - i) for i in range(POSITIONS + 1)])
    meets = np.ones(POSITIONS + 1)
    for _ in range(depth):
        meets = 0.75 * agree * meets + 0.25 * (1 - (1 - agree * meets) ** 2)
    n = 2
    while float(weight @ (1 - meets) ** n) > 1 - recall:
        n += 1
    return n


class Join:
    """One run of the join over (doc_id, text)."""

    def __init__(self, docs: DataFrame, k: int, threshold: int, recall: float, small: int):
        self.docs, self.k, self.threshold, self.small = docs.select("doc_id", "text"), k, threshold, small
        self.work = Workspace(docs.sparkSession, "near-dedup")
        s = threshold / 100
        self.needed = lru_cache(maxsize=None)(lambda depth: trees_for(depth, s, recall))
        self.trees = self.needed(SHALLOW)
        self.planted = 0  # trees so far; each has a root of its own
        off = (1 - s) * 0.75  # two bits agree by chance once in four
        self.most_bits = min(254, math.ceil(SKETCHED * off + 4.5 * math.sqrt(SKETCHED * off * (1 - off))))

    def branch(self, rows: DataFrame, to: list | None = None) -> DataFrame:
        """(node, rep, n, sketch, sig) -> children, without sig. A node's picks depend on its own hash alone."""
        picks = lambda node: F.when(
            F.pmod(F.xxhash64(node, F.lit(5)), F.lit(4)) == 0,
            F.array(F.pmod(F.xxhash64(node, F.lit(1)), F.lit(POSITIONS)), F.pmod(F.xxhash64(node, F.lit(2)), F.lit(POSITIONS))),
        ).otherwise(F.array(F.pmod(F.xxhash64(node, F.lit(1)), F.lit(POSITIONS))))
        picked = rows.withColumn("pick", F.explode(F.array_distinct(picks(F.col("node")))))
        token = F.substring(F.col("sig"), (F.col("pick") * 4 + 1).cast("int"), F.lit(4))
        return picked.select(F.xxhash64("node", "pick", token).alias("node"), "rep", "n", "sketch")

    def sets_of(self, reps: DataFrame, name: str) -> DataFrame:
        """(rep, set) of some classes, read again from a text of each, dealt by rep. ``reps``: distinct column ``rep``."""
        wanted = self.work.table(self.signed.select("rep", "doc_id").join(reps, "rep", "left_semi"), f"{name}-wanted")
        texts = prefilter(self.docs, wanted, "doc_id").join(wanted.select("doc_id").distinct(), "doc_id")  # a semi join would be pushed below the filter
        found = texts.mapInArrow(_sets(self.k), "f1 long, f2 long, set binary").withColumn("rep", F.xxhash64("f1", "f2"))
        # rows may repeat, and rows of one id may differ in text: a class needs one set
        return found.join(wanted.select("rep"), "rep", "left_semi").groupBy("rep").agg(F.first("set").alias("set"))

    def overlaps(self, pairs: DataFrame, sets: DataFrame) -> DataFrame:
        """(a, b, both, either) for distinct pairs of classes in ``sets``."""
        a, b = sets.select(F.col("rep").alias("a"), F.col("set").alias("set_a")), sets.select(F.col("rep").alias("b"), F.col("set").alias("set_b"))
        return pairs.join(a, "a").join(b, "b").select("a", "b", "set_a", "set_b").mapInArrow(_overlaps, "a long, b long, both long, either long")

    def settle(self, rows: DataFrame, name: str) -> tuple[DataFrame, DataFrame]:
        """(rows of small nodes, rows of large nodes), with their node's size. Nodes of one document end here.

        Small nodes are compared exhaustively, so of nodes with the same members, which independent trees often have, one is
        enough: 128 bits over the members name them. Only rows of nodes that are left are shuffled.
        """
        members = [F.bit_xor(F.xxhash64(F.col("rep"), F.lit(seed))).alias(f"m{seed}") for seed in (1, 2)]
        sizes = rows.groupBy("node").agg(F.count(F.lit(1)).alias("size"), F.sum("n").alias("weight"), *members)
        fits = (F.col("size") <= self.small) & ((F.col("weight") <= HEAVY) | (F.col("size") <= 2))
        counts = self.work.table(sizes.filter("size > 1").select("node", "size", "m1", "m2", fits.alias("fits")), f"{name}-counts")
        once = counts.filter("fits").groupBy("size", "m1", "m2").agg(F.min("node").alias("node")).select("node", "size", F.lit(True).alias("fits"))
        live = self.work.table(once.unionByName(counts.filter("not fits").select("node", "size", "fits")), f"{name}-live")
        sized = self.work.table(prefilter(rows, live, "node").join(live, "node"), f"{name}-sized")
        return sized.filter("fits").drop("fits"), sized.filter("not fits").drop("fits", "size")

    def confirm(self, pairs: DataFrame, name: str) -> DataFrame:
        """(a, b, linked) of distinct pairs, on full sets."""
        wanted = pairs.select(F.explode(F.array("a", "b")).alias("rep")).distinct()
        measured = self.overlaps(pairs, self.sets_of(wanted, name))  # the sets are dealt by rep once, for both joins
        return self.work.table(measured.select("a", "b", (F.col("both") * 100 >= F.col("either") * self.threshold).alias("linked")), name)

    def pivot_round(self, large: DataFrame, sets: DataFrame, i: str, seed: int) -> tuple[DataFrame, DataFrame]:
        """(links with pivots, rows that stay)."""
        order = F.xxhash64(F.lit(seed), F.col("rep"))
        pivots = self.work.table(large.groupBy("node").agg(F.min_by("rep", F.struct(order, "rep")).alias("pivot")), f"pivots-{i}")
        starred = self.work.table(large.join(pivots, "node").filter("rep <> pivot"), f"starred-{i}")
        pairs = starred.select(F.col("pivot").alias("b"), F.col("rep").alias("a")).distinct()
        star = self.work.table(self.overlaps(pairs, sets), f"star-{i}")
        linked = F.col("both") * 100 >= F.col("either") * self.threshold
        measured = starred.join(star.select(F.col("a").alias("rep"), F.col("b").alias("pivot"), "both", "either"), ["rep", "pivot"])
        distance = 1 - F.col("both") / F.col("either")
        measured = self.work.table(measured.select("node", "rep", "n", "sketch", linked.alias("linked"), distance.alias("d")), f"measured-{i}")
        shell = self.work.table(measured.filter("not linked").groupBy("node").agg(F.min("d").alias("d_min")), f"shell-{i}")
        reach = F.col("d_min") - (1 - self.threshold / 100) - 1e-9
        stay = measured.join(shell, "node").filter(~F.col("linked") | (F.col("d") >= reach))
        return star.filter(linked).select("a", "b"), stay.select("node", "rep", "n", "sketch")

    def grow(self, classes: DataFrame, trees: int, nodes: list[DataFrame], links: list[DataFrame]) -> DataFrame | None:
        """Branch classes down new trees; adds to small nodes and links, and returns (rep, depth) of those beyond the first steps."""
        name = f"{self.planted}-"
        roots = F.explode(F.array(*[F.lit(1_000_003 * (self.planted + j + 1)).cast("long") for j in range(trees)]))
        self.planted += trees
        small, large = self.settle(self.branch(classes.withColumn("node", roots)), f"{name}step-1")
        nodes.append(small)
        depth, sets, deep = 1, None, None
        while not large.isEmpty():
            if depth >= SHALLOW:
                if sets is None:
                    sets = self.work.table(self.sets_of(large.select("rep").distinct(), f"{name}large"), f"{name}large-sets")
                found, large = self.pivot_round(large, sets, f"{name}{depth}", self.planted * 1000 + depth)
                links.append(found)
            depth += 1
            if depth > SHALLOW:
                reached = self.work.table(large.select("rep").distinct(), f"{name}deep-{depth}").withColumn("depth", F.lit(depth))
                deep = reached if deep is None else deep.union(reached)
            signed = prefilter(self.signed.select("rep", "sig"), large, "rep")
            small, large = self.settle(self.branch(large.join(signed, "rep")), f"{name}step-{depth}")
            nodes.append(small)
        return deep

    def run(self) -> tuple[DataFrame, DataFrame]:
        """(sketches of all documents, links that connect all linked classes). ``signed`` then holds the classes."""
        work = self.work
        sketches = work.table(self.docs.mapInArrow(_sketches(self.k), SKETCH_SCHEMA).withColumn("rep", F.xxhash64("f1", "f2")), "sketches")
        filled = sketches.filter("n_shingles > 0 and doc_id is not null")
        one = filled.groupBy("rep", F.col("n_shingles").alias("n")).agg(F.min("doc_id").alias("doc_id"), F.first("sketch").alias("sketch"), F.first("sig").alias("sig"))
        signed = self.signed = work.table(one, "classes")
        nodes: list[DataFrame] = []
        links: list[DataFrame] = []
        deep = self.grow(signed, self.trees, nodes, links)
        # a class that needs more trees has been in all so far, or it would not have gone so deep
        while deep is not None:
            deepest = work.table(deep.groupBy("rep").agg(F.max("depth").alias("depth")), f"{self.planted}-deepest")
            depths = [r[0] for r in deepest.select("depth").distinct().collect() if self.needed(r[0]) > self.planted]  # as many as steps
            if not depths:
                break
            more = min(max(self.needed(d) for d in depths), 2 * self.planted) - self.planted
            again = self.grow(signed.join(deepest.filter(F.col("depth").isin(depths)).select("rep"), "rep", "left_semi"), more, nodes, links)
            deep = deepest if again is None else deepest.select("rep", "depth").union(again)
        small = nodes[0]
        for more in nodes[1:]:
            small = small.union(more)
        test = (self.threshold, self.most_bits)
        by_node = small.repartition("node").sortWithinPartitions("node")
        pairs = work.table(by_node.select("node", "rep", "n", "sketch").mapInArrow(_near_pairs(*test), "a long, b long").distinct(), "pairs-1")
        first = self.confirm(pairs, "confirmed-1")
        linked = first.filter("linked").select("a", "b")
        for found in links:
            linked = linked.union(found)
        linked = work.table(linked, "links-1")
        part = components(linked, work).select(F.col("id").alias("rep"), F.col("component").alias("part"))
        middle = small.filter(F.col("size") > TINY).join(part, "rep", "left").withColumn("part", F.coalesce("part", "rep"))
        sorted_ = lambda df: df.repartition("node").sortWithinPartitions("node")
        open_ = sorted_(middle).select("node", "rep", "n", "sketch", "part").mapInArrow(_cross_members(*test), "node long, rep long, part long")
        open_ = work.table(open_, "open")
        if open_.isEmpty():
            return sketches, linked
        sets = self.sets_of(open_.select("rep").distinct(), "open")
        crossing = sorted_(open_.join(sets, "rep")).select("node", "rep", "part", "set").mapInArrow(_cross_links(self.threshold), "a long, b long")
        return sketches, linked.union(work.table(crossing.distinct(), "links-2"))


def near_duplicates(docs: DataFrame, k: int = 5, threshold: int = 80, recall: float = 0.9995, small: int = 2048) -> DataFrame:
    """Per row of ``docs``: doc_id, n_shingles, component_id (smallest id reachable over links), kept.

    ``threshold`` is in hundredths: sets link if 100 * |both| >= threshold * |either|.
    """
    join = Join(docs, k, threshold, recall, small)
    sketches, links = join.run()
    found = components(links, join.work)
    ids = join.signed.select("rep", "doc_id")
    # a component is named by the smallest document id of its classes
    linked = found.join(ids, F.col("id") == F.col("rep"))
    least = linked.groupBy("component").agg(F.min("doc_id").alias("smallest"))
    named = join.work.table(linked.select("rep", "component").join(least, "component").select("rep", "smallest"), "named")
    smallest = join.work.table(ids.join(named, "rep", "left").select("rep", F.coalesce("smallest", "doc_id").alias("smallest")), "smallest")
    rows = sketches.select("doc_id", "n_shingles", "rep").join(smallest, "rep", "left")
    component = F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("smallest")).otherwise(F.col("doc_id"))
    return join.work.finish(rows.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(False)).alias("kept")))


def op10_near_dedup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), k=4, threshold=80)
