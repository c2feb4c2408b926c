"""Near copies: covering SimHash proposes links, and each link is confirmed by exact Jaccard similarity.

A document is the set of its five-word shingles (64-bit hashes); equal sets are one node. Links that simhash finds by its
covering tables between five-word fingerprints come first: they join most copies, and large groups by few pairs. But sets
of similarity 0.8 lie up to some 16 bits apart, far beyond any radius that covering tables can pay for, so an exact way
finds the rest: two sets of similarity t or more share an element among the first n - ceil(t n) + 1 of each, in any order
that is the same for all sets. So every such pair meets under one of these prefix shingles, and none is lost. The order puts
shingles that a task sees often last, so that prefixes hold rare ones; it only saves work and never changes a result.

What stands before the first shingle that two sets share is in one of them only, which bounds their similarity. Pairs within
this bound, with prints (SimHash over the sets) no more than FAR_BITS apart (a pair of similarity 0.8 lies beyond about once in a
million, one of a few shingles once in ten thousand; every other step is exact) and still in different components are held against each other's bit sketches (a shingle whose bit the other set
lacks is not shared: again a bound, never a guess), and what passes is confirmed on the whole sets. Nodes of confirmed pairs
form components (single links). All this happens where the rows of a shingle stand, and pairs leave it in two passes: first only a
forest of them (no more than rows went in), which joins most copies, then every pair that passes the bounds and still lies in
different components. A shingle of many rows is dealt in blocks, a cell for each two of them, so no task holds it whole.

Defined cases: words and case as in simhash; fewer than five words give one shingle of all of them; texts without words
are equal to each other; rows with null doc_id count, but name no component (null if no row with an id is in it).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutlearn.llm import simhash
from cutlearn.llm import textblocks as tb
from cutlearn.llm.components import star_components
from cutlearn.llm.session import broadcast_if_small, cut, shuffle_parts

SHINGLE_WORDS = 5
#: Least similarity of a link, as a fraction.
OVER, UNDER = 4, 5
#: Slots in which a task counts shingles, the count from which it reports a slot, and how many slots are kept.
SLOTS, OFTEN, KEPT_SLOTS = 1 << 22, 8, 1 << 16
#: Rows under one shingle that are compared in one piece.
BLOCK = 1024
#: Most differing bits of the prints of a pair that is looked at. Sets of similarity 0.8 differ in 10 of 64
#: bits on average (12 for sets of a few shingles), unlike ones in 32.
FAR_BITS = 25
#: Rows under one shingle up to which all their pairs are looked at when rows without partner are left out.
SMALL = 64
#: Bits of a sketch for each shingle of a set, at least (a power of two in all), and its most bits: a larger set's
#: sketch is fuller, which only leaves more pairs to the whole sets.
SKETCH_BITS, MOST_BITS = 4, 1 << 13

MET_NAMES = ["key", "node", "n", "rest", "print"]
MET = "key long, node long, n long, rest long, print long"
MARKED = "doc_id long, node long, fp long, n int, bits binary"


def shingles_of(data: np.ndarray, offsets: np.ndarray, n: int = SHINGLE_WORDS) -> tuple[np.ndarray, np.ndarray]:
    """(shingle hashes, sorted and distinct in each text; where each text's begin)."""
    s, e, first = tb.words_of(data, offsets)
    h = tb.hashes_of(tb.LOWER[data], s, e)
    ok, doc = tb.within(first, n, len(h))
    values, owner = [tb.ngrams(h, n)[ok]], [doc[ok]]
    words = np.diff(first)
    for k in range(1, n):
        short = np.flatnonzero(words == k)
        values.append(tb.sequence_hash(h, first[short], k))
        owner.append(short)
    v, who = np.concatenate(values), np.concatenate(owner)
    order = np.lexsort((v, who))
    v, who = v[order], who[order]
    new = np.ones(len(v), bool)
    new[1:] = (v[1:] != v[:-1]) | (who[1:] != who[:-1])
    v, who = v[new], who[new]
    return v, np.searchsorted(who, np.arange(len(offsets)))


def nodes_of(v: np.ndarray, first: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each set."""
    size = np.diff(first).astype(np.uint64)
    return tb.mix(tb.sums_by(tb.mix(v + tb.MIX_A), first) ^ tb.mix(tb.sums_by(tb.mix(v ^ tb.MIX_B), first) + size))


def _slot(v: np.ndarray) -> np.ndarray:
    return (v & np.uint64(SLOTS - 1)).astype(np.int64)


def _often(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.zeros(SLOTS, np.int32)
    for batch in batches:
        for _lo, _hi, data, offsets in tb.slices(batch.column(0)):
            np.add.at(total, _slot(shingles_of(data, offsets)[0]), np.int32(1))
    seen = np.flatnonzero(total >= OFTEN)
    yield pa.RecordBatch.from_arrays([pa.array(seen.astype(np.int32)), pa.array(total[seen].astype(np.int64))], ["slot", "n"])


def frequent_slots(docs: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(sorted slots, their counts) of the KEPT_SLOTS most frequent ones."""
    got = docs.select("text").mapInArrow(_often, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n"))
    got = got.orderBy(F.col("n").desc(), "slot").limit(KEPT_SLOTS).toArrow()
    slot, n = (np.asarray(got.column(c).combine_chunks()).astype(np.int64) for c in ("slot", "n"))
    order = np.argsort(slot)
    return slot[order], n[order]


def prefixes(v: np.ndarray, first: np.ndarray, slots: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(prefix shingles, the text of each, how many of the text's shingles stand from it on)."""
    size = np.diff(first)
    rank = np.zeros(len(v), np.int64)
    if len(slots):
        mine = _slot(v)
        k = np.minimum(np.searchsorted(slots, mine), len(slots) - 1)
        rank = np.where(slots[k] == mine, counts[k], 0)
    who = np.repeat(np.arange(len(size)), size)
    order = np.lexsort((v, rank, who))
    length = np.where(size > 0, size - -(-OVER * size // UNDER) + 1, 0)
    turn = np.arange(len(v)) - first[who]
    take = turn < length[who]
    return v[order][take], who[take], (size[who] - turn)[take]


def sketches(v: np.ndarray, first: np.ndarray) -> pa.Array:
    """A bitmap of each set, with the bit of each shingle set; its size is a power of two from 64 to MOST_BITS."""
    size = np.diff(first)
    width = np.int64(1) << np.ceil(np.log2(np.clip(SKETCH_BITS * size, 64, MOST_BITS))).astype(np.int64)
    begin = np.concatenate([[0], np.cumsum(width)])
    who = np.repeat(np.arange(len(size)), size)
    bits = np.zeros(begin[-1], bool)
    bits[begin[who] + (v & (width[who] - 1).astype(np.uint64)).astype(np.int64)] = True
    packed = np.packbits(bits, bitorder="little")
    return pa.Array.from_buffers(pa.binary(), len(size), [None, pa.py_buffer((begin // 8).astype(np.int32)), pa.py_buffer(packed)])


def most_common(n: int, bits: np.ndarray, other_n: int, other_bits: np.ndarray) -> int:
    """How many shingles two sets can share at most by their bitmaps; the wider one is folded to the narrower."""
    while len(bits) > len(other_bits):
        bits = bits[: len(bits) // 2] | bits[len(bits) // 2 :]
    while len(other_bits) > len(bits):
        other_bits = other_bits[: len(other_bits) // 2] | other_bits[len(other_bits) // 2 :]
    alone, other_alone = (int(np.bitwise_count(x).sum()) for x in (bits & ~other_bits, other_bits & ~bits))
    return min(n - alone, other_n - other_alone)


def _marker(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lo, hi, data, offsets in tb.slices(batch.column(1)):
            v, first = shingles_of(data, offsets)
            fp = simhash.fingerprints_of(data, offsets, SHINGLE_WORDS)
            cols = [pa.array(nodes_of(v, first).view(np.int64)), pa.array(fp.view(np.int64)), pa.array(np.diff(first).astype(np.int32)), sketches(v, first)]
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), *cols], ["doc_id", "node", "fp", "n", "bits"])


def _sketched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows a, b, n_a, n_b, bits_a, bits_b the pairs that can be similar enough."""
    for batch in batches:
        n_a, n_b = (batch.column(k).to_pylist() for k in (2, 3))
        bits = [[np.frombuffer(x, np.uint8) for x in batch.column(k).to_pylist()] for k in (4, 5)]
        keep = [(OVER + UNDER) * most_common(n, x, m, y) >= OVER * (n + m) for n, m, x, y in zip(n_a, n_b, *bits, strict=True)]
        yield pa.RecordBatch.from_arrays([c.filter(pa.array(keep, pa.bool_())) for c in batch.columns[:2]], ["a", "b"])


def _meeter(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The prefixes of each node that the task has not met before."""
        known: set[int] = set()
        for batch in batches:
            for _lo, _hi, data, offsets in tb.slices(batch.column(0)):
                v, first = shingles_of(data, offsets)
                node = nodes_of(v, first).view(np.int64)
                fresh = np.zeros(len(node), bool)
                for i, x in enumerate(node.tolist()):
                    if x not in known:
                        known.add(x)
                        fresh[i] = True
                keys, who, left = prefixes(v, first, *shared.value)
                take = fresh[who]
                print_ = simhash.majority(tb.mix(v), first).view(np.int64)
                cols = (keys[take].view(np.int64), node[who[take]], np.diff(first)[who[take]], left[take], print_[who[take]])
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], MET_NAMES)

    return run


def fit(n: np.ndarray, rest: np.ndarray, other_n: np.ndarray, other_rest: np.ndarray) -> np.ndarray:
    """Whether sets of these sizes can be similar enough if the shingle with so many from it on is the first they share."""
    return (OVER + UNDER) * np.minimum(rest, other_rest) >= OVER * (n + other_n)


def near(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count((a ^ b).view(np.uint64)) <= FAR_BITS


def _partnered(key: np.ndarray, node: np.ndarray, n: np.ndarray, rest: np.ndarray, prints: np.ndarray) -> np.ndarray:
    """Rows (sorted by key, n and node) that have a row of another node under their key that fits and is near; in a
    bucket of over SMALL rows, those whose nearest in size may fit."""
    keep = np.zeros(len(key), bool)
    edge = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1], [True]]))
    size = np.diff(edge)
    twos = edge[:-1][size == 2]
    good = twos[fit(n[twos], rest[twos], n[twos + 1], rest[twos + 1]) & near(prints[twos], prints[twos + 1])]
    keep[good] = keep[good + 1] = True
    for i in np.flatnonzero(size > 2):
        a, z = edge[i], edge[i + 1]
        if z - a <= SMALL:
            ok = fit(n[a:z, None], rest[a:z, None], n[None, a:z], rest[None, a:z]) & near(prints[a:z, None], prints[None, a:z])
            np.fill_diagonal(ok, False)
            keep[a:z] = ok.any(axis=1)
        else:
            alike = UNDER * n[a : z - 1] >= OVER * n[a + 1 : z]
            keep[a : z - 1] |= alike
            keep[a + 1 : z] |= alike
    return keep


def _partners(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows arrive sorted by key, n and node; a key that goes on in the next batch is carried over."""
    held = (np.zeros(0, np.int64),) * len(MET_NAMES)

    def out(rows: list[np.ndarray]) -> pa.RecordBatch:
        key, node = rows[:2]
        new = np.ones(len(key), bool)
        new[1:] = (key[1:] != key[:-1]) | (node[1:] != node[:-1])
        rows = [r[new] for r in rows]
        keep = _partnered(*rows)
        return pa.RecordBatch.from_arrays([pa.array(r[keep]) for r in rows], MET_NAMES)

    for batch in batches:
        rows = [np.concatenate([h, np.asarray(batch.column(i)).astype(np.int64)]) for i, h in enumerate(held)]
        if not len(rows[0]):
            continue
        last = np.flatnonzero(rows[0] != rows[0][-1])
        k = last[-1] + 1 if len(last) else 0
        held = tuple(r[k:] for r in rows)
        if k:
            yield out([r[:k] for r in rows])
    if len(held[0]):
        yield out(list(held))


class Cell:
    """Rows that meet under one shingle, compared with one of them at a time."""

    def __init__(self, cols: dict[str, np.ndarray], bits: list[bytes]):
        self.n, self.rest, self.prints, self.block = (cols[c] for c in ("n", "rest", "print", "block"))
        self.across = cols["lo"][0] != cols["hi"][0]
        width = np.array([len(x) // 8 for x in bits])
        self.width, self.at, self.rows = width, np.zeros(len(bits), np.int64), {}
        for w in np.unique(width).tolist():
            own = np.flatnonzero(width == w)
            self.at[own] = np.arange(len(own))
            self.rows[w] = np.frombuffer(b"".join(bits[k] for k in own), np.uint64).reshape(len(own), w)

    def common(self, i: int, others: np.ndarray) -> np.ndarray:
        """How many shingles row i can share with each of the others, at most."""
        out = np.zeros(len(others), np.int64)
        for w, rows in self.rows.items():
            some = np.flatnonzero(self.width[others] == w)
            if not len(some):
                continue
            x, y = self.rows[self.width[i]][self.at[i]], rows[self.at[others[some]]]
            least = min(len(x), w)
            x = np.bitwise_or.reduce(x.reshape(-1, least), axis=0)
            y = np.bitwise_or.reduce(y.reshape(len(y), -1, least), axis=1)
            ones = lambda z: np.bitwise_count(z).sum(axis=-1, dtype=np.int64)
            both = ones(x & y)
            out[some] = np.minimum(self.n[i] - ones(x) + both, self.n[others[some]] - ones(y) + both)
        return out

    def alike(self, i: int, others: np.ndarray) -> np.ndarray:
        """Those of the others that may be similar enough to row i."""
        if self.across:
            others = others[self.block[others] != self.block[i]]
        others = others[fit(self.n[i], self.rest[i], self.n[others], self.rest[others]) & near(self.prints[i], self.prints[others])]
        if not len(others):
            return others
        return others[(OVER + UNDER) * self.common(i, others) >= OVER * (self.n[i] + self.n[others])]

    def pairs(self, root: np.ndarray, forest: bool) -> Iterator[tuple[int, int]]:
        """Pairs of different roots that may be similar enough: all of them, or of those only a forest."""
        label = root.copy()
        for i in range(len(label) - 1):
            others = np.flatnonzero(label != label[i])
            if not len(others):
                if forest:
                    return
                continue
            hits = self.alike(i, others if forest else others[others > i])
            if forest and len(hits):
                found, first = np.unique(label[hits], return_index=True)
                hits = hits[first]
                label[np.isin(label, found)] = label[i]
            yield from ((i, int(j)) for j in hits)


CELL = ["key", "lo", "hi", "block", "node", "n", "rest", "print", "root"]


def _comparer(forest: bool):
    def found(rows: pa.Table) -> pa.RecordBatch:
        cols = {c: rows.column(c).to_numpy() for c in CELL}
        edge = np.flatnonzero(np.concatenate([[True], _new_cell(cols), [True]]))
        size, out = np.diff(edge), [np.zeros((0, 2), np.int64)]
        open_ = size > 1
        twos = edge[:-1][size == 2]
        far = ~(fit(cols["n"][twos], cols["rest"][twos], cols["n"][twos + 1], cols["rest"][twos + 1]) & near(cols["print"][twos], cols["print"][twos + 1]))
        open_[np.flatnonzero(size == 2)[far]] = False
        bits = rows.column("bits").combine_chunks()
        for k in np.flatnonzero(open_):
            a, z = edge[k], edge[k + 1]
            root = cols["root"][a:z]
            if (root == root[0]).all():
                continue
            cell = Cell({c: cols[c][a:z] for c in CELL}, bits.slice(a, z - a).to_pylist())
            hits = np.array(list(cell.pairs(root, forest)), np.int64).reshape(-1, 2)
            out.append(np.sort(cols["node"][a:z][hits], axis=1))
        pairs = np.unique(np.concatenate(out), axis=0)
        return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0].copy()), pa.array(pairs[:, 1].copy())], ["a", "b"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows arrive sorted by key, lo and hi; a cell that goes on in the next batch is carried over."""
        held = None
        for batch in batches:
            rows = pa.Table.from_batches([batch])
            rows = pa.concat_tables([held, rows]) if held is not None else rows
            ends = np.flatnonzero(_new_cell({c: rows.column(c).to_numpy() for c in CELL[:3]})) + 1
            k = int(ends[-1]) if len(ends) else 0
            held = rows.slice(k)
            if k:
                yield found(rows.slice(0, k))
        if held is not None and held.num_rows:
            yield found(held)

    return compare


def _new_cell(cols: dict[str, np.ndarray]) -> np.ndarray:
    """For each row but the first whether it stands in another cell than the one before."""
    key, lo, hi = (cols[c] for c in CELL[:3])
    return (key[1:] != key[:-1]) | (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])


def met_pairs(met: DataFrame, roots: DataFrame, nodes: DataFrame, forest: bool, block: int) -> DataFrame:
    """a, b: pairs of nodes that meet under a shingle, lie in different components and pass all bounds."""
    placed = met.join(roots, "node", "left").select(*MET_NAMES, F.coalesce("root", "node").alias("root"))
    keys = placed.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.count("*").alias("c"))
    keys = keys.where("low <> high").select("key", F.ceil(F.col("c") / block).cast("int").alias("blocks"))
    rows = placed.join(keys, "key").join(nodes.select("node", "bits"), "node")
    rows = rows.withColumn("block", F.pmod(F.xxhash64("node", F.lit(block)), F.col("blocks")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.withColumn("lo", F.least("block", "other")).withColumn("hi", F.greatest("block", "other")).select(*CELL, "bits")
    rows = rows.repartition(shuffle_parts(met.sparkSession), "key", "lo", "hi").sortWithinPartitions("key", "lo", "hi", "node")
    return rows.mapInArrow(_comparer(forest), "a long, b long").distinct()


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for _lo, _hi, data, offsets in tb.slices(batch.column(0)):
            v, first = shingles_of(data, offsets)
            lists = pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(v.view(np.int64)))
            yield pa.RecordBatch.from_arrays([pa.array(nodes_of(v, first).view(np.int64)), lists], ["node", "v"])


def sketched(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """The pairs (a, b) that can be similar enough by the sketches of their nodes. nodes: node, n, bits."""
    one, two = (nodes.select(F.col("node").alias(c), F.col("n").alias(f"n_{c}"), F.col("bits").alias(f"bits_{c}")) for c in "ab")
    open_ = pairs.join(one, "a").join(two, "b").select("a", "b", "n_a", "n_b", "bits_a", "bits_b")
    return open_.mapInArrow(_sketched, "a long, b long")


def confirmed(pairs: DataFrame, docs: DataFrame) -> DataFrame:
    """The pairs (a, b) of nodes whose sets are similar enough, exactly. Only the sets in these pairs travel."""
    open_ = cut(pairs)
    if open_.isEmpty():
        return open_
    wanted = cut(open_.select(F.col("a").alias("node")).union(open_.select("b")).distinct())
    sets = docs.select("text").mapInArrow(_sets, "node long, v array<long>")
    sets = cut(sets.join(broadcast_if_small(wanted, wanted.count()), "node", "left_semi").dropDuplicates(["node"]))
    one, two = (sets.select(F.col("node").alias(c), F.col("v").alias(f"v_{c}")) for c in "ab")
    both = F.size(F.array_intersect("v_a", "v_b"))
    return open_.join(one, "a").join(two, "b").where(both * (OVER + UNDER) >= (F.size("v_a") + F.size("v_b")) * OVER).select("a", "b")


def covered_pairs(nodes: DataFrame, radius: int = simhash.RADIUS) -> DataFrame:
    """a, b: links between nodes whose fingerprints are equal, or that simhash's covering tables connect."""
    heads = cut(nodes.groupBy("fp").agg(F.min("node").alias("head")))
    same = nodes.join(heads, "fp").select(F.col("node").alias("a"), F.col("head").alias("b"))
    found = simhash.links(heads.select("fp"), radius)
    one, two = (heads.select(F.col("fp").alias(c), F.col("head").alias(f"head_{c}")) for c in "ab")
    near = found.join(one, "a").join(two, "b").select(F.col("head_a").alias("a"), F.col("head_b").alias("b"))
    every = same.union(near).where("a <> b")
    return every.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def components(docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """doc_id, node, component_id (the smallest doc_id that links reach) for each row of docs."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(frequent_slots(docs))
    marked = cut(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_marker, MARKED))
    nodes = cut(marked.select("node", "fp", "n", "bits").dropDuplicates(["node"]))
    found = cut(confirmed(sketched(covered_pairs(nodes), nodes), docs))
    met = docs.select("text").mapInArrow(_meeter(shared), MET)
    met = met.repartition(shuffle_parts(spark), "key").sortWithinPartitions("key", "n", "node")
    met = cut(met.mapInArrow(_partners, MET))
    roots = star_components(found)
    for forest in (True, False):
        found = cut(found.unionByName(confirmed(met_pairs(met, roots, nodes, forest, block), docs)))
        roots = star_components(found)
    roots = roots.select(F.col("node").alias("at"), "root")
    kept = marked.select("doc_id", "node")
    least = kept.groupBy("node").agg(F.min("doc_id").alias("least"))
    joined = least.join(roots, least.node == roots["at"], "left").select("node", "least", F.coalesce("root", "node").alias("root"))
    named = joined.groupBy("root").agg(F.min("least").alias("component_id"))
    return kept.join(joined.join(named, "root").select("node", "component_id"), "node")
