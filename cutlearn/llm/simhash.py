"""SimHash near-duplicates with covering locality-sensitive hashing.

A fingerprint bit is the majority over the XXH64 values of a document's word triples. Covering hashing makes every
pair within the radius meet: each of the 64 bits gets a random vector of radius + 1 bits, and table v (any non-zero
vector) keeps the bits whose vector has an odd scalar product with v. At most `radius` differing bits leave a vector v
orthogonal to all of theirs, and in that table the two fingerprints are equal. So no linked pair is lost.

Documents are first grouped by fingerprint (partial aggregation), so a group of exact copies is one row. A bucket
of more than HOT fingerprints is divided by the pigeonhole rule: its free bits are cut into radius + 1 blocks, and a
linked pair agrees in one of them; what is still hot is divided once more. Fingerprints of a bucket are distinct, so
each division bounds its parts by the number of bits left. Inside a bucket pairs are compared in memory and only a
forest of links comes out. Components are found by rounds of star contraction on the links.

Defined cases: a null, empty or blank text has fingerprint zero, which links like any other; fewer than three words
give one shingle of all of them; a row with null doc_id keeps its fingerprint and gets the component of its
fingerprint (null if no row with an id has it); repeated rows get equal results.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutlearn.llm import textblocks as tb
from cutlearn.llm.components import star_components
from cutlearn.llm.session import broadcast_if_small, cut, shuffle_parts

RADIUS, SEED, SHINGLE_WORDS, MASK_SEED = 3, 42, 3, 20_240_229
#: Fingerprints of a bucket that are compared in one piece.
HOT = 4096


def masks(radius: int = RADIUS, seed: int = MASK_SEED) -> np.ndarray:
    """One 64-bit mask for each of the 2^(radius + 1) - 1 tables."""
    vectors = np.random.default_rng(seed).integers(0, 1 << (radius + 1), 64)
    odd = lambda v: [bin(int(x) & v).count("1") & 1 for x in vectors]
    return np.array([sum(b << i for i, b in enumerate(odd(v))) for v in range(1, 1 << (radius + 1))], np.uint64)


def free_blocks(mask: int, parts: int) -> list[int]:
    """The bits outside mask, cut into `parts` blocks of nearly equal size."""
    free = [i for i in range(64) if not mask >> i & 1]
    return [sum(1 << int(i) for i in chunk) for chunk in np.array_split(free, parts)]


def fingerprints_of(data: np.ndarray, offsets: np.ndarray, n: int = SHINGLE_WORDS) -> np.ndarray:
    """uint64 fingerprint of each text of a slice."""
    s, e, first = tb.words_of(data, offsets)
    docs, words = len(offsets) - 1, np.diff(first)
    low = tb.LOWER[data]
    # one space between words, so that a shingle is one piece of bytes
    lengths = e - s
    start = np.concatenate([[0], np.cumsum(lengths + 1)])
    inner = np.arange(lengths.sum()) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    joined = np.full(start[-1], 0x20, np.uint8)
    joined[np.repeat(start[:-1], lengths) + inner] = low[np.repeat(s, lengths) + inner]
    text = joined.tobytes()
    ok, doc = tb.within(first, n, len(s))
    at = np.flatnonzero(ok)
    short = np.flatnonzero((words > 0) & (words < n))
    begins = np.concatenate([start[at], start[first[short]]])
    ends = np.concatenate([start[at + n], start[first[short + 1]]]) - 1
    owner = np.concatenate([doc[at], short])
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(text[a:b], SEED) for a, b in zip(begins.tolist(), ends.tolist(), strict=True)), np.uint64, len(owner))
    order = np.argsort(owner, kind="stable")
    return majority(h[order], np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=docs))]))


def majority(h: np.ndarray, edge: np.ndarray) -> np.ndarray:
    """For each run of hashes between two edges the 64 bits that are set in over half of them."""
    total = np.diff(edge)
    out = np.zeros(len(total), np.uint64)
    lanes = np.uint64(0x0101010101010101)
    for j in range(8):
        part = ((h >> np.uint64(j)) & lanes).view(np.uint8).reshape(-1, 8)
        ones = tb.sums_by(part.astype(np.int32), edge)
        bit = (2 * ones > total[:, None]).astype(np.uint64)
        for byte in range(8):
            out |= bit[:, byte] << np.uint64(8 * byte + j)
    return out


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lo, hi, data, offsets in tb.slices(batch.column(1)):
            fp = fingerprints_of(data, offsets).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(fp)], ["doc_id", "fp"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long)."""
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_fingerprints, "doc_id long, fp long")


def _forest(fp: np.ndarray, radius: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Links that connect what is within the radius in one bucket: each round takes the unlabelled fingerprints
    around one more of them, so no more links come out than fingerprints go in."""
    out, left = [], np.arange(len(fp))
    while len(left) > 1:
        front, left = left[:1], left[1:]
        while len(front) and len(left):
            near = np.full(len(left), -1)
            for f in front:
                hit = (near < 0) & (np.bitwise_count(fp[left] ^ fp[f]) <= radius)
                near[hit] = f
            got = near >= 0
            if not got.any():
                break
            out.append((fp[left[got]], fp[near[got]]))
            front, left = left[got], left[~got]
    return out


def _linker(radius: int):
    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows arrive sorted by bucket; a bucket that goes on in the next batch is carried over."""
        rest = (np.zeros(0, np.int64),) * 3

        def links(v: np.ndarray, key: np.ndarray, fp: np.ndarray) -> pa.RecordBatch | None:
            edge = np.flatnonzero(np.concatenate([[True], (v[1:] != v[:-1]) | (key[1:] != key[:-1]), [True]]))
            found = []
            u = fp.view(np.uint64)
            size = np.diff(edge)
            twos = edge[:-1][size == 2]
            near = twos[np.bitwise_count(u[twos] ^ u[twos + 1]) <= radius]
            found.append((u[near], u[near + 1]))
            for i in np.flatnonzero(size > 2):
                found += _forest(u[edge[i] : edge[i + 1]], radius)
            a, b = (np.concatenate(x).view(np.int64) for x in zip(*found, strict=True))
            return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"]) if len(a) else None

        for batch in batches:
            rows = [np.concatenate([r, np.asarray(batch.column(i))]) for i, r in enumerate(rest)]
            v, key, fp = rows
            if not len(v):
                continue
            last = np.flatnonzero((v != v[-1]) | (key != key[-1]))
            k = last[-1] + 1 if len(last) else 0
            rest = (v[k:], key[k:], fp[k:])
            if k and (out := links(v[:k], key[:k], fp[:k])):
                yield out
        if len(rest[0]) and (out := links(*rest)):
            yield out

    return link


def links(distinct: DataFrame, radius: int = RADIUS, hot: int = HOT) -> DataFrame:
    """a, b: links that connect all fingerprints within the radius. distinct: column fp, no value twice."""
    parts = radius + 1
    tables = [int(m) for m in masks(radius)]
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    rows = distinct.select(
        "fp", F.explode(F.array(*[F.struct(F.lit(i).cast("long").alias("v"), F.col("fp").bitwiseAND(F.lit(signed(m))).alias("key"), F.lit(signed(m)).alias("mask")) for i, m in enumerate(tables)])).alias("t")
    ).select("t.v", "t.key", "fp", "t.mask")
    done, known = [], tables
    for level in (1, 2):
        crowded = cut(rows.groupBy("v", "key").agg(F.count("*").alias("n")).where(F.col("n") > hot).select("v", "key"))
        if crowded.isEmpty():
            break
        done.append(rows.join(crowded, ["v", "key"], "left_anti"))
        blocks = {m: free_blocks(m, parts) for m in known}
        entries = [x for m, b in blocks.items() for x in (F.lit(signed(m)), F.array(*(F.lit(signed(y)) for y in b)))]
        rows = rows.join(crowded, ["v", "key"]).select("v", "fp", "mask", F.posexplode(F.create_map(*entries)[F.col("mask")]).alias("k", "block"))
        wider = F.col("mask").bitwiseOR(F.col("block"))
        rows = rows.select((F.col("v") * parts + F.col("k") + 1000 * level).alias("v"), F.col("fp").bitwiseAND(wider).alias("key"), "fp", wider.alias("mask"))
        known = sorted({m | y for m, b in blocks.items() for y in b})
    for x in done:
        rows = rows.unionByName(x)
    n = shuffle_parts(distinct.sparkSession)
    dealt = rows.select("v", "key", "fp").repartition(n, "v", "key").sortWithinPartitions("v", "key", "fp")
    return dealt.mapInArrow(_linker(radius), "a long, b long")


def near_duplicates(docs: DataFrame, radius: int = RADIUS, hot: int = HOT) -> DataFrame:
    """doc_id, fingerprint, component_id (the smallest doc_id that links reach), n_same (rows with this fingerprint)."""
    marked = cut(fingerprints(docs))
    same = cut(marked.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("n_same")))
    found = star_components(links(same.select("fp"), radius, hot))
    joined = same.join(found, same.fp == found.node, "left").select("fp", "least", "n_same", F.coalesce("root", "fp").alias("root"))
    roots = joined.groupBy("root").agg(F.min("least").alias("component_id"))
    class_of = joined.join(roots, "root").select("fp", "component_id", "n_same")
    return marked.join(class_of, "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "n_same"
    )


def representatives(docs: DataFrame, radius: int = RADIUS, found: DataFrame | None = None) -> DataFrame:
    """docs with one document of each component left, the one with the smallest doc_id. Of repeated rows with that
    doc_id the least row stays; rows with null doc_id can't be told apart from others and stay. found: doc_id and
    component_id, those of near_duplicates if None."""
    found = near_duplicates(docs, radius) if found is None else found
    found = cut(
        found.where("doc_id is not null").groupBy("doc_id").agg(
            F.max(F.col("doc_id") == F.col("component_id")).alias("stay"), F.count("*").alias("times")
        ).where("not stay or times > 1")
    )
    # only ids that go travel; few are broadcast, and texts are shuffled only beside many
    gone = found.where("not stay").select("doc_id")
    left = docs.join(broadcast_if_small(gone, gone.count()), "doc_id", "left_anti").select(*docs.columns)
    again = found.where("stay").select("doc_id")
    times = again.count()
    if not times:
        return left
    again = broadcast_if_small(again, times)
    rows = left.join(again, "doc_id", "left_semi").select(F.col("doc_id").alias("id"), F.struct(*docs.columns).alias("row"))
    return left.join(again, "doc_id", "left_anti").select(*docs.columns).unionByName(rows.groupBy("id").agg(F.min("row").alias("row")).select("row.*"))
