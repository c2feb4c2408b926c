"""Exact substring dedup with per-shard suffix arrays.

Every string of SPAN bytes that starts at two places or more is removed at all of them. Equal strings are brought
together by anchors: in each window of SPAN bytes the ANCHOR-byte string with the least hash (the leftmost of equals)
is the window's anchor; equal windows have equal anchors at equal places, so their segments (the windows that share an
anchor occurrence, with the bytes they cover) carry one anchor hash. Anchors that occur once drop out at once, equal
segments are counted before any text moves, and only different segments of one anchor go on to a shard.

A shard joins the segments of its anchors into one text and sorts its suffixes by Larsson-Sadakane refinement: ranks
by the first bytes, then by pairs of ranks, doubling the depth, only in groups that are still tied. Common prefixes
come from Kasai's rule, all segments advancing together. Neighbours with SPAN bytes in common are repeats.

An anchor with more different segments than a shard holds is dealt to several shards by segment; windows that stay
single there are merged across shards: their 128-bit hashes are range-dealt, sorted, and looked up by binary search
in the other shards' sorted lists.

Defined cases: a null text is empty; texts under SPAN bytes lose nothing; repeated rows repeat each other and lose
all they can; rows with one doc_id are documents of their own unless their texts are equal as well; a null doc_id is
a value like any other; other columns are ignored. Equality of segments rests on two 64-bit hashes of different kinds: a
polynomial one of the anchor and XXH3 of all bytes. A text over LONG_BYTES is read in pieces that overlap by a window, so
a very long one needs no more memory for its hashes than a short one; the removal itself takes some 10 bytes a byte.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutlearn.llm import textblocks as tb
from cutlearn.llm.session import cut, drop_path, shared_dir, shuffle_parts

SPAN, ANCHOR = 400, 128
#: Bytes of text that a shard sorts at once, and segments of one anchor that stay in one shard.
SHARD_BYTES = 1_000_000
SHARD_SEGMENTS = 4_000
#: Bytes of one text whose windows are hashed at once.
LONG_BYTES = 4 << 20

ANCHORS = "doc_id long, th int, pos int, nwin int, ah long, sh long"
REMOVED = "doc_id long, th int, s int, e int"


def sliding_argmin(h: np.ndarray, width: int) -> np.ndarray:
    """Place of the least of each `width` consecutive hashes, the leftmost of equals by their high bits: as many for
    every length of h, so that equal windows choose equally wherever they stand."""
    bits = np.uint64(32)
    low = (np.uint64(1) << bits) - np.uint64(1)
    key = (h & ~low) | np.arange(len(h), dtype=np.uint64)
    reach = 1
    while reach * 2 <= width:
        key = np.minimum(key[:-reach], key[reach:])
        reach *= 2
    if reach < width:
        key = np.minimum(key[: len(key) - (width - reach)], key[width - reach :])
    return (key & low).astype(np.int64)


def anchors_of(data: np.ndarray, offsets: np.ndarray, span: int = SPAN, anchor: int = ANCHOR) -> tuple[np.ndarray, ...]:
    """(text, first window, windows, anchor hash, segment hash) of each segment of a slice; windows are counted from
    the begin of the slice."""
    m = len(data) - span + 1
    if m <= 0:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),) * 2
    ranges = tb.RangeHash(data)
    n = len(data) - anchor + 1
    h = tb.mix((ranges.sums[anchor:] - ranges.sums[:n]) * ranges.down[:n])
    pick = sliding_argmin(h, span - anchor + 1)
    doc = np.repeat(np.arange(len(offsets) - 1, dtype=np.int32), np.diff(offsets))
    inside = doc[:m] == doc[span - 1 :]
    new = np.ones(m, bool)
    new[1:] = (pick[1:] != pick[:-1]) | (doc[1:m] != doc[: m - 1]) | (inside[1:] != inside[:-1])
    start = np.flatnonzero(new)
    count = np.diff(np.append(start, m))
    good = inside[start]
    start, count = start[good], count[good]
    raw, digest = data.tobytes(), xxhash.xxh3_64_intdigest
    sh = np.fromiter((digest(raw[a:z]) for a, z in zip(start.tolist(), (start + count + span - 1).tolist(), strict=True)), np.uint64, len(start))
    return doc[start].astype(np.int64), start, count, h[pick[start]], sh


def pieces(data: np.ndarray, offsets: np.ndarray, span: int = SPAN, long: int = LONG_BYTES) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first byte, bytes, offsets): the slice itself, or overlapping pieces of a single long text. Each window lies in
    exactly one piece."""
    if len(offsets) > 2 or len(data) < long + span:
        yield 0, data, offsets
        return
    for at in range(0, len(data) - span + 1, long):
        part = data[at : at + long + span - 1]
        yield at, part, np.array([0, len(part)])


def _anchor_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lo, hi, whole, every in tb.slices(batch.column(2)):
            for at, data, offsets in pieces(whole, every):
                doc, start, count, ah, sh = anchors_of(data, offsets)
                rows = pa.array(doc)
                cols = [batch.column(k).slice(lo, hi - lo).take(rows) for k in (0, 1)]
                cols += [pa.array(x.astype(np.int32)) for x in (start - offsets[doc] + at, count)] + [pa.array(x.view(np.int64)) for x in (ah, sh)]
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "th", "pos", "nwin", "ah", "sh"])


def suffix_ranks(text: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(suffix array, ranks) by the first `depth` entries or more; entries are under 512, ties keep equal ranks.
    Larsson-Sadakane refinement: only groups that are still tied are sorted again."""
    n = len(text)
    bits = np.uint64(max(1, (n - 1).bit_length()))
    low = (np.uint64(1) << bits) - np.uint64(1)
    padded = np.concatenate([text.astype(np.uint64), np.zeros(3, np.uint64)])
    key = padded[:n]
    for k in range(1, 4):
        key = (key << np.uint64(9)) | padded[k : k + n]
    if bits <= 28:
        order = np.sort((key << bits) | np.arange(n, dtype=np.uint64))
        sa = (order & low).astype(np.int64)
        key = order >> bits
    else:
        sa = np.argsort(key, kind="stable")
        key = key[sa]
    new = np.ones(n, bool)
    new[1:] = key[1:] != key[:-1]
    rank = np.zeros(n + 1, np.int64)  # the place past the end ranks below all
    rank[sa] = np.flatnonzero(new)[np.cumsum(new) - 1] + 1
    reach = 4
    while reach < depth:
        tied = ~new
        tied[:-1] |= ~new[1:]
        at = np.flatnonzero(tied)
        if not len(at):
            break
        who = sa[at]
        group, second = rank[who], rank[np.minimum(who + reach, n)]
        if 3 * int(bits) + 2 <= 64:
            b1 = bits + np.uint64(1)
            packed = np.sort((group.astype(np.uint64) << (bits + b1)) | (second.astype(np.uint64) << bits) | who.astype(np.uint64))
            who, pair = (packed & low).astype(np.int64), packed >> bits
        else:
            pair = (group.astype(np.uint64) << np.uint64(32)) | second.astype(np.uint64)
            order = np.argsort(pair, kind="stable")
            who, pair = who[order], pair[order]
        sa[at] = who
        fresh = np.ones(len(at), bool)
        fresh[1:] = pair[1:] != pair[:-1]
        new[at] |= fresh
        rank[who] = at[np.maximum.accumulate(np.where(fresh, np.arange(len(at)), 0))] + 1
        reach *= 2
    return sa, rank[:n]


def kasai(data: np.ndarray, first: np.ndarray, sa: np.ndarray, most: int) -> np.ndarray:
    """Common prefix of each suffix (by its place in the text) with the one before it in the array, at most `most`
    and never past the end of a segment. first: where segments begin (one more than there are); each ends with a mark
    that matches nothing. Kasai's rule keeps
    all but one entry from one suffix to the next; each segment is a lane and lanes advance together."""
    n = len(data)
    before = np.full(n, -1, np.int64)
    before[sa[1:]] = sa[:-1]
    stop = np.repeat(first[1:] - 1, np.diff(first))
    words = np.concatenate([data, np.zeros(8, np.uint8)])
    eight = np.lib.stride_tricks.as_strided(words, (n, 8), (1, 1)).copy().view(np.uint64)[:, 0]
    out = np.zeros(n, np.int32)
    length = np.diff(first)
    lanes = np.argsort(-length, kind="stable")
    have = np.zeros(len(lanes), np.int64)
    begin = first[:-1][lanes]
    active = len(lanes)
    sizes = length[lanes]
    for t in range(int(sizes[0]) if len(sizes) else 0):
        while active and sizes[active - 1] <= t:
            active -= 1
        i = begin[:active] + t
        j = before[i]
        l = np.maximum(have[:active] - 1, 0)
        limit = np.where(j >= 0, np.minimum(np.minimum(stop[i] - i, stop[j] - j), most), 0)
        l = np.minimum(l, limit)
        go = np.flatnonzero(l < limit)
        while len(go):
            a, b = i[go] + l[go], j[go] + l[go]
            x = eight[a] ^ eight[b]
            same = np.where(x == 0, 8, np.bitwise_count((x & -x) - np.uint64(1)).astype(np.int64) >> 3)
            l[go] = np.minimum(l[go] + same, limit[go])
            go = go[(same == 8) & (l[go] < limit[go])]
        have[:active] = l
        out[i] = l
    return out


def repeats_in_shard(segments: list[np.ndarray], windows: np.ndarray, span: int = SPAN) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For all windows of all segments, one after the other: (segment, offset, class). Windows of one class hold the
    same bytes; classes are numbered from 0."""
    sizes = np.array([len(s) for s in segments])
    first = np.concatenate([[0], np.cumsum(sizes + 1)])
    data = np.zeros(first[-1], np.uint8)
    text = np.zeros(first[-1], np.uint16)
    for a, s in zip(first[:-1], segments, strict=True):
        data[a : a + len(s)] = s
        text[a : a + len(s)] = s.astype(np.uint16) + 1
    sa, _ = suffix_ranks(text, len(text))  # Kasai's rule needs the full order
    lcp = kasai(data, first, sa, span)
    wanted = np.full(len(text), -1, np.int64)
    segment = np.repeat(np.arange(len(segments)), windows)
    offset = np.arange(windows.sum()) - np.repeat(np.cumsum(windows) - windows, windows)
    wanted[first[:-1][segment] + offset] = np.arange(len(offset))
    which = wanted[sa]
    at = np.flatnonzero(which >= 0)
    if not len(at):
        return segment, offset, np.zeros(0, np.int64)
    # the prefix that two neighbours among the wanted suffixes share is the least of those between them
    share = np.minimum.reduceat(lcp[sa][: at[-1] + 1], at[:-1] + 1) if len(at) > 1 else np.zeros(0, np.int32)
    classes = np.zeros(len(offset), np.int64)
    classes[which[at]] = np.concatenate([[0], np.cumsum(share < span)])
    return segment, offset, classes


SHARD_OUT = "kind string, doc_id long, th int, s int, e int, wh long, wh2 long, shard int"


def _sorter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows: ah, salt, split, n, doc_id, th, pos, nwin, body; those of an (ah, salt) are together. Gives ranges of
    bytes to remove, and for anchors dealt to several shards a hash for each class of windows."""
    names = [c.split()[0] for c in SHARD_OUT.split(", ")]
    held: list[pa.RecordBatch] = []

    def ranges(doc, pos, segment, offset):
        """Maximal runs of consecutive windows of a segment as byte ranges."""
        if not len(segment):
            return None
        new = np.ones(len(segment), bool)
        new[1:] = (segment[1:] != segment[:-1]) | (offset[1:] != offset[:-1] + 1)
        a = np.flatnonzero(new)
        z = np.append(a[1:], len(segment)) - 1
        row = segment[a]
        k = len(a)
        return pa.RecordBatch.from_arrays(
            [pa.array(["range"] * k), doc[0].take(pa.array(row)), doc[1].take(pa.array(row)), pa.array((pos[row] + offset[a]).astype(np.int32)), pa.array((pos[row] + offset[z] + SPAN).astype(np.int32)), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int32())], names)

    def work(t: pa.Table) -> Iterator[pa.RecordBatch]:
        doc = [t[c].combine_chunks() for c in ("doc_id", "th")]
        salt, pos, nwin, n = (t[c].to_numpy() for c in ("salt", "pos", "nwin", "n"))
        split = t["split"].to_numpy(zero_copy_only=False).astype(bool)
        body, offs = tb.column_bytes(t["body"])
        segments = [body[a:z] for a, z in zip(offs[:-1], offs[1:], strict=True)]
        segment, offset, classes = repeats_in_shard(segments, nwin.astype(np.int64))
        times = np.bincount(classes, n[segment])
        single = n[segment] == 1
        again = single & (times[classes] > 1)
        if (out := ranges(doc, pos, segment[again], offset[again])) is not None:
            yield out
        if split.any():
            # one window for each class, with whether it still needs a partner
            cand = np.flatnonzero(split[segment])
            _, one = np.unique(classes[cand], return_index=True)
            cand = cand[one]
            hashes = tb.RangeHash(body)
            a = offs[segment[cand]] + offset[cand]
            wh = hashes.of(a, a + SPAN)
            raw = body.tobytes()
            wh2 = np.fromiter((xxhash.xxh3_64_intdigest(raw[x : x + SPAN]) for x in a.tolist()), np.uint64, len(a))
            open_ = single[cand] & (times[classes[cand]] == 1)
            row = segment[cand]
            k = len(cand)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.where(open_, "open", "known")), doc[0].take(pa.array(row)), doc[1].take(pa.array(row)), pa.array((pos[row] + offset[cand]).astype(np.int32)), pa.array((pos[row] + offset[cand] + SPAN).astype(np.int32)), pa.array(wh.view(np.int64)), pa.array(wh2.view(np.int64)), pa.array(salt[row].astype(np.int32))], names)

    def drain(last: bool) -> Iterator[pa.RecordBatch]:
        nonlocal held
        t = pa.Table.from_batches(held)
        ah, salt = t["ah"].to_numpy(), t["salt"].to_numpy()
        size = t["nwin"].to_numpy().astype(np.int64) + SPAN
        new = np.ones(len(ah), bool)
        new[1:] = (ah[1:] != ah[:-1]) | (salt[1:] != salt[:-1])
        edge = np.append(np.flatnonzero(new), len(ah))
        total = np.concatenate([[0], np.cumsum(size)])
        k, stop = 0, len(edge) - 1 if last else len(edge) - 2
        while k < stop:
            z = k + 1
            while z < stop and total[edge[z + 1]] - total[edge[k]] <= SHARD_BYTES:
                z += 1
            yield from work(t.slice(edge[k], edge[z] - edge[k]))
            k = z
        held = t.slice(edge[max(stop, 0)]).combine_chunks().to_batches() if not last else []

    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            if sum(b.nbytes for b in held) > 4 * SHARD_BYTES:
                yield from drain(False)
    if held:
        yield from drain(True)


def _merger(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (wh, wh2), equal ones in one partition. Each open window is looked up by binary search among
    all the partition's sorted hashes; a window that two shards hold is a repeat."""
    rest: pa.Table | None = None

    def work(t: pa.Table) -> pa.RecordBatch:
        wh, wh2 = t["wh"].to_numpy(), t["wh2"].to_numpy()
        new = np.ones(len(wh), np.int64)
        new[1:] = (wh[1:] != wh[:-1]) | (wh2[1:] != wh2[:-1])
        rank = np.cumsum(new)  # the place of each pair of hashes among the different ones, in sorted order
        open_ = np.flatnonzero(t["kind"].to_numpy(zero_copy_only=False) == "open")
        found = np.searchsorted(rank, rank[open_], "right") - np.searchsorted(rank, rank[open_], "left")
        rows = pa.array(open_[found > 1])
        return pa.RecordBatch.from_arrays([t[c].combine_chunks().take(rows) for c in ("doc_id", "th", "s", "e")], ["doc_id", "th", "s", "e"])

    for batch in batches:
        t = pa.Table.from_batches([batch])
        t = pa.concat_tables([rest, t]).combine_chunks() if rest is not None else t
        if not t.num_rows:
            continue
        wh = t["wh"].to_numpy()
        k = int(np.searchsorted(wh, wh[-1], "left"))
        if k:
            yield work(t.slice(0, k))
        rest = t.slice(k)
    if rest is not None and rest.num_rows:
        yield work(rest)


def _with_hash(docs: DataFrame) -> DataFrame:
    text = F.coalesce("text", F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.hash(text).alias("th"), text.alias("text"))


def _same_doc(a: DataFrame, b: DataFrame):
    return a.doc_id.eqNullSafe(b.doc_id) & (a.th == b.th)


def _bodies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Cuts the wanted segments out of each text."""
    for batch in batches:
        data, offsets = tb.column_bytes(batch.column(2))
        wanted = batch.column(3)
        flat = wanted.flatten()
        row = np.repeat(np.arange(batch.num_rows), wanted.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64))
        cols = {f.name: flat.field(f.name) for f in flat.type}
        a = offsets[row] + cols["pos"].to_numpy()
        z = a + cols["nwin"].to_numpy() + SPAN - 1
        rows = pa.array(row)
        body = pa.array([data[x:y].tobytes() for x, y in zip(a, z, strict=True)], pa.binary())
        yield pa.RecordBatch.from_arrays([cols["ah"], cols["salt"], cols["split"], cols["n"], batch.column(0).take(rows), batch.column(1).take(rows), cols["pos"], cols["nwin"], body], ["ah", "salt", "split", "n", "doc_id", "th", "pos", "nwin", "body"])


SEGMENT_ROWS = "ah long, salt int, split boolean, n long, doc_id long, th int, pos int, nwin int, body binary"


def removed_ranges(docs: DataFrame, shard_segments: int = SHARD_SEGMENTS) -> DataFrame:
    """doc_id, th (hash of the text), s, e: byte ranges to remove, which may overlap."""
    spark = docs.sparkSession
    rows, parts = _with_hash(docs), shuffle_parts(spark)
    path = f"{shared_dir(spark)}/anchors-{uuid.uuid4().hex}"
    rows.mapInArrow(_anchor_rows, ANCHORS).write.parquet(path)
    every = spark.read.schema(ANCHORS).parquet(path)
    seen = every.groupBy("ah").agg(F.count("*").alias("c"), F.min("sh").alias("lo"), F.max("sh").alias("hi")).where("c > 1")
    # both sides of the join have exchanges of their own, so Spark can split an anchor that very many windows share
    seen = cut(seen.select("ah", (F.col("lo") != F.col("hi")).alias("differ")))
    again = cut(every.join(seen, "ah"))
    drop_path(spark, path)
    segs = cut(
        again.groupBy("ah", "sh", "differ").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "th", "pos", "nwin")).alias("rep"))
    )
    copies = again.join(segs.where("n > 1").select("ah", "sh"), ["ah", "sh"]).select("doc_id", "th", F.col("pos").alias("s"), (F.col("pos") + F.col("nwin") + SPAN - 1).alias("e"))
    # anchors with a single segment left to judge beside others
    open_ = cut(segs.where("differ").groupBy("ah").agg(F.count("*").alias("d"), F.min("n").alias("least")).where("d > 1 and least = 1"))
    shards = F.ceil(F.col("d") / shard_segments).cast("int")
    todo = segs.join(open_, "ah").select("ah", "n", "rep.*", F.pmod(F.xxhash64("sh"), shards).cast("int").alias("salt"), (shards > 1).alias("split"))
    wanted = todo.groupBy("doc_id", "th").agg(F.collect_list(F.struct("ah", "salt", "split", "n", "pos", "nwin")).alias("wanted"))
    once = rows.join(wanted, _same_doc(rows, wanted)).select(rows.doc_id, rows.th, "text", "wanted")
    dealt = once.mapInArrow(_bodies, SEGMENT_ROWS).repartition(parts, "ah", "salt").sortWithinPartitions("ah", "salt", "doc_id", "th", "pos")
    sorted_ = cut(dealt.mapInArrow(_sorter, SHARD_OUT))
    found = sorted_.where("kind = 'range'").select("doc_id", "th", "s", "e")
    split = sorted_.where("kind <> 'range'")
    merged = split.repartitionByRange(parts, "wh").sortWithinPartitions("wh", "wh2").mapInArrow(_merger, REMOVED)
    return copies.union(found).union(merged)


def _applier(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Merges ranges and removes them from the bytes of each text."""
    for batch in batches:
        for lo, hi, data, offsets in tb.slices(batch.column(1)):
            ids, ranges = batch.column(0).slice(lo, hi - lo), batch.column(2).slice(lo, hi - lo)
            out = []
            for k in range(hi - lo):
                raw = data[offsets[k] : offsets[k + 1]]
                own = ranges[k].values
                if own is None or not len(own):
                    out.append((len(raw), 0, 0, hashlib.sha256(raw).hexdigest(), raw.tobytes()))
                    continue
                change = np.zeros(len(raw) + 1, np.int32)
                np.add.at(change, own.field("s").to_numpy(), 1)
                np.add.at(change, own.field("e").to_numpy(), -1)
                gone = np.cumsum(change[:-1], dtype=np.int32) > 0
                spans = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum())
                left = raw[~gone].tobytes()
                out.append((len(raw), int(gone.sum()), spans, hashlib.sha256(left).hexdigest(), left))
            n, r, s, h, left = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([ids, *(pa.array(x, pa.int64()) for x in (n, r, s)), pa.array(h), pa.array(left, pa.binary())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])


KEPT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"


def remove_repeats(docs: DataFrame, shard_segments: int = SHARD_SEGMENTS) -> DataFrame:
    """Columns of KEPT for each row of docs; kept has the bytes left, which may begin or end inside a character."""
    ranges = removed_ranges(docs, shard_segments).groupBy("doc_id", "th").agg(F.collect_list(F.struct("s", "e")).alias("ranges"))
    rows = _with_hash(docs)
    joined = rows.join(ranges, _same_doc(rows, ranges), "left").select(rows.doc_id, "text", "ranges")
    return joined.mapInArrow(_applier, KEPT)
