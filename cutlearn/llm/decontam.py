"""Benchmark decontamination: rare n-gram seeds find where an item may stand, Smith-Waterman alignment decides.

Words are runs of letters, digits and non-ASCII bytes; all letters are taken in lower case. Word triples of an item are its seeds. One
pass over all documents counts in how many documents each seed occurs; a seed is rare for an item beside the item's
own rarest quarter. A second pass looks all seeds up in every document. Each hit names a document, an item and a
diagonal; the words around the diagonal are aligned with the item (match 2, mismatch and gap -1), and a document is
contaminated where the best local alignment reaches THRESHOLD of a perfect copy's score. Candidates of common seeds
alone are aligned unless too few of the item's words stand in the window to reach THRESHOLD in any order, so how often
a leak occurs, whole, edited or shortened, changes no verdict; only the score of clean documents leaves those out.

Seeds that more than ITEMS_PER_SEED places of the benchmark share belong to templates. Items that are equal but for the
words outside templates answer alike to a document that holds the template only, so of such a class one item (the smallest
item_id) is looked up by template seeds, and each item by its other seeds: what a document expands to doesn't grow with the
number of items that share a phrase.

An item of fewer than MIN_ITEM_WORDS words has no seeds to speak of and would stand in clean prose by chance; it is matched
exactly instead: a document is contaminated if one of its lines has the item's words and no others.

The benchmark is taken in blocks of at most ITEMS_PER_BLOCK items and some BLOCK_BYTES bytes (a longer item by itself), so
what is broadcast is bounded whatever its size; all documents meet every block, and nothing but seed counts reaches the
driver.

Defined cases: null, empty and word-less texts are clean; items without words are skipped; ties between items go to the smallest item_id; repeated rows get equal results; a null
item_id is skipped; an empty benchmark leaves every document clean.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cutlearn.llm import textblocks as tb

SEED_WORDS = 3
MIN_ITEM_WORDS = 5
THRESHOLD = 0.5
ITEMS_PER_BLOCK, BLOCK_BYTES = 20_000, 64 << 20
#: Places of the benchmark that may share a seed before it counts as a template's.
ITEMS_PER_SEED = 64
#: A seed is rare if it occurs in no more than so many times the documents of the item's rarest quarter.
COMMON_TIMES = 10
ALIGN_BATCH = 256
#: Places of seeds that are looked at in one piece.
PLACES = 200_000
MATCH, MISMATCH, GAP = 2, -1, -1

ADDED = ("contaminated", "item_id", "score")

IN_WORD = np.zeros(256, bool)
IN_WORD[0x80:] = True
for _a, _z in (("0", "9"), ("A", "Z"), ("a", "z")):
    IN_WORD[ord(_a) : ord(_z) + 1] = True


class Items(NamedTuple):
    """Items of a block. words: hashes of all words, item k's at first[k]:first[k + 1]; seeds: sorted distinct seed
    hashes; at, item, pos: for seed i the places at[i]:at[i + 1] give the item and the word where it begins; short,
    short_ids: sorted hashes of the items that are matched exactly, and their smallest ids."""

    ids: np.ndarray
    words: np.ndarray
    first: np.ndarray
    seeds: np.ndarray
    at: np.ndarray
    item: np.ndarray
    pos: np.ndarray
    short: np.ndarray
    short_ids: np.ndarray


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    s, e = tb.runs_of(IN_WORD[data], offsets)
    return tb.hashes_of(data, s, e), np.searchsorted(s, offsets)


def short_lines(data: np.ndarray, offsets: np.ndarray, words: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(text, hash of its words) of each line of one to MIN_ITEM_WORDS - 1 words."""
    if not len(words):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    s, _ = tb.runs_of(IN_WORD[data], offsets)
    line = np.searchsorted(np.flatnonzero(data == 10), s)
    doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
    begin = np.flatnonzero(np.concatenate([[True], (line[1:] != line[:-1]) | (doc[1:] != doc[:-1])]))
    size = np.diff(np.append(begin, len(words)))
    parts = [(doc[begin[size == n]], tb.sequence_hash(words, begin[size == n], n)) for n in range(1, MIN_ITEM_WORDS)]
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def _without_templates(ids: np.ndarray, words: np.ndarray, first: np.ndarray, at: np.ndarray, item: np.ndarray, pos: np.ndarray, most: int) -> np.ndarray:
    """Which places stay: those of seeds with at most `most` places, and of others one item of each class."""
    times = np.diff(at)
    common = np.repeat(times > most, times)
    if not common.any():
        return np.ones(len(item), bool)
    covered = np.zeros(len(words), bool)
    for k in range(SEED_WORDS):
        covered[first[item[common]] + pos[common] + k] = True
    who = np.repeat(np.arange(len(ids)), np.diff(first))
    turn = (np.arange(len(words)) - first[who]).astype(np.uint64)
    key = tb.sums_by(tb.mix(np.where(covered, words, np.uint64(0)) + turn * tb.MIX_A), first) + tb.mix(np.diff(first).astype(np.uint64))
    order = np.lexsort((ids, key))
    head = np.zeros(len(ids), bool)
    head[order[np.concatenate([[True], key[order][1:] != key[order][:-1]])]] = True
    return ~common | head[item]


def index_items(ids: list[int], texts: list[str], most: int = ITEMS_PER_SEED) -> Items:
    data, offsets = tb.column_bytes(pc.utf8_lower(pa.array(texts, pa.string())))
    words, first = word_hashes(data, offsets)
    ok, item = tb.within(first, SEED_WORDS, len(words))
    ok = ok & (np.diff(first)[item] >= MIN_ITEM_WORDS)
    pos = np.flatnonzero(ok)
    seed, item = tb.ngrams(words, SEED_WORDS)[pos], item[pos]
    order = np.argsort(seed, kind="stable")
    seeds, at = np.unique(seed[order], return_index=True)
    names, at, item, pos = np.array(ids, np.int64), np.append(at, len(order)), item[order], (pos - first[item])[order]
    stay = _without_templates(names, words, first, at, item, pos, most)
    at = np.concatenate([[0], np.cumsum(stay)])[at]
    n = np.diff(first)
    brief = np.flatnonzero((n > 0) & (n < MIN_ITEM_WORDS))
    h = np.array([tb.sequence_hash(words, first[k : k + 1], n[k])[0] for k in brief], np.uint64)
    order = np.lexsort((names[brief], h))
    short, one = np.unique(h[order], return_index=True)
    return Items(names, words, first, seeds, at, item[stay], pos[stay], short, names[brief][order][one])


def _hits(index: Items, filter_bits: np.ndarray, words: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(window, its text, number of its seed) of each seed occurrence in a slice."""
    ok, doc = tb.within(first, SEED_WORDS, len(words))
    g = tb.ngrams(words, SEED_WORDS)
    maybe = np.flatnonzero(filter_bits[(g & np.uint64(len(filter_bits) - 1)).astype(np.int64)] & ok)
    k = np.minimum(np.searchsorted(index.seeds, g[maybe]), max(len(index.seeds) - 1, 0))
    sure = index.seeds[k] == g[maybe] if len(index.seeds) else np.zeros(0, bool)
    return maybe[sure], doc[maybe[sure]], k[sure]


def _filter_bits(index: Items) -> np.ndarray:
    bits = np.zeros(1 << 20, bool)
    bits[(index.seeds & np.uint64(len(bits) - 1)).astype(np.int64)] = True
    return bits


def _frequency_counter(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index: Items = shared.value
        bits, total = _filter_bits(index), np.zeros(len(index.seeds), np.int64)
        for batch in batches:
            for _lo, _hi, data, offsets in tb.slices(pc.utf8_lower(batch.column(0))):
                _, doc, k = _hits(index, bits, *word_hashes(data, offsets))
                pairs = np.unique(doc.astype(np.int64) * len(index.seeds) + k)
                total += np.bincount(pairs % len(index.seeds), minlength=len(total)) if len(pairs) else 0
        seen = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(seen.astype(np.int64)), pa.array(total[seen])], ["seed", "docs"])

    return run


def rare_seeds(index: Items, frequency: np.ndarray) -> np.ndarray:
    """For each seed, whether it is rare for at least one of its items."""
    seed_of = np.repeat(np.arange(len(index.seeds)), np.diff(index.at))
    keep = np.zeros(len(index.seeds), bool)
    order = np.argsort(index.item, kind="stable")
    edge = np.flatnonzero(np.diff(index.item[order], prepend=-1, append=-1))
    for a, z in zip(edge[:-1], edge[1:], strict=True):
        own = seed_of[order[a:z]]
        f = frequency[own]
        keep[own[f <= COMMON_TIMES * (1 + np.quantile(f, 0.25, method="lower"))]] = True
    return keep


def align(items: list[np.ndarray], windows: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(best local alignment score, words of the item) of each item with its window. All pairs of a batch advance
    together, a row of the score table at a time; a row's gaps along the window are a running maximum."""
    n, width = len(items), max(map(len, windows))
    height = max(map(len, items))
    a = np.zeros((n, height), np.uint64)
    b = np.ones((n, width), np.uint64)
    a_len = np.array([len(x) for x in items])
    b_in = np.zeros((n, width), bool)
    for k, (x, y) in enumerate(zip(items, windows, strict=True)):
        a[k, : len(x)], b[k, : len(y)] = x, y
        b_in[k, : len(y)] = True
    slope = np.arange(width + 1, dtype=np.int32) * -GAP
    row = np.zeros((n, width + 1), np.int32)
    best = np.zeros(n, np.int32)
    for i in range(height):
        live = (i < a_len)[:, None] & b_in
        gain = np.where((b == a[:, i : i + 1]) & live, MATCH, MISMATCH).astype(np.int32)
        new = np.zeros_like(row)
        np.maximum(row[:, :-1] + gain, row[:, 1:] + GAP, out=new[:, 1:])
        np.maximum(new, 0, out=new)
        row = np.maximum.accumulate(new + slope, axis=1) - slope
        row[:, 1:][~live] = 0
        best = np.maximum(best, row.max(axis=1))
    return best, a_len


def _words_met(index: Items, item: np.ndarray, words: np.ndarray, a: np.ndarray, z: np.ndarray) -> np.ndarray:
    """For each candidate the number of the item's words that stand anywhere in words[a:z]: no alignment has more matches."""
    def keyed(values: np.ndarray, begin: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        who = np.repeat(np.arange(len(size)), size)
        turn = np.arange(len(who)) - np.repeat(np.cumsum(size) - size, size)
        return tb.mix(values[np.repeat(begin, size) + turn] + who.astype(np.uint64) * tb.GOLDEN), who

    own, who = keyed(index.words, index.first[item], index.first[item + 1] - index.first[item])
    there, _ = keyed(words, a, np.maximum(z - a, 0))
    return np.bincount(who[np.isin(own, there)], minlength=len(item))


def _candidates(index: Items, rare: np.ndarray, words: np.ndarray, first: np.ndarray, hits: tuple) -> Iterator[tuple[np.ndarray, ...]]:
    """(text, item, first and last word of the window) of what has to be aligned, ALIGN_BATCH at a time."""
    lengths = np.diff(index.first)
    window, doc, k = hits
    every = index.at[k + 1] - index.at[k]
    piece = np.cumsum(every) // PLACES
    for part in np.split(np.arange(len(k)), np.flatnonzero(np.diff(piece)) + 1):
        places = every[part]
        turn = np.arange(places.sum()) - np.repeat(np.cumsum(places) - places, places)
        place = np.repeat(index.at[k[part]], places) + turn
        if not len(place):
            continue
        item, d = index.item[place], np.repeat(doc[part], places)
        s = lengths[item] // 4 + 4
        # hits near one diagonal are one candidate
        diagonal = (np.repeat(window[part], places) - index.pos[place]) // s
        order = np.lexsort((diagonal, item, d))
        d, item, diagonal, s = d[order], item[order], diagonal[order], s[order]
        new = np.flatnonzero(np.concatenate([[True], (np.diff(d) != 0) | (np.diff(item) != 0) | (np.diff(diagonal) != 0)]))
        sure = np.logical_or.reduceat(np.repeat(rare[k[part]], places)[order], new)
        d, item, diagonal, s = d[new], item[new], diagonal[new], s[new]
        a = np.maximum(diagonal * s - s, first[d])
        z = np.minimum((diagonal + 1) * s + lengths[item] + s, first[d + 1])
        left = np.flatnonzero(~sure)
        for c in range(0, len(left), 16 * ALIGN_BATCH):
            i = left[c : c + 16 * ALIGN_BATCH]
            sure[i] = _words_met(index, item[i], words, a[i], z[i]) >= THRESHOLD * lengths[item[i]]
        d, item, a, z = d[sure], item[sure], a[sure], z[sure]
        for c in range(0, len(d), ALIGN_BATCH):
            yield tuple(x[c : c + ALIGN_BATCH] for x in (d, item, a, z))


def _matcher(shared, text: int, names: list[str]):
    """Appends contaminated, item_id and score to the columns of each batch; column number `text` is judged."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, rare = shared.value
        bits = _filter_bits(index)
        for batch in batches:
            for lo, hi, data, offsets in tb.slices(pc.utf8_lower(batch.column(text))):
                words, first = word_hashes(data, offsets)
                score, owner = np.zeros(hi - lo), np.full(hi - lo, -1, np.int64)
                if len(index.short):
                    d, h = short_lines(data, offsets, words, first)
                    k = np.minimum(np.searchsorted(index.short, h), len(index.short) - 1)
                    for row, which_id in zip(d[index.short[k] == h].tolist(), index.short_ids[k[index.short[k] == h]].tolist(), strict=True):
                        owner[row] = which_id if not score[row] else min(owner[row], which_id)
                        score[row] = 1
                for d, it, a, z in _candidates(index, rare, words, first, _hits(index, bits, words, first)):
                    got, full = align([index.words[index.first[x] : index.first[x + 1]] for x in it], [words[x:y] for x, y in zip(a, z, strict=True)])
                    for row, value, which_id in sorted(zip(d.tolist(), (got / (MATCH * full)).tolist(), index.ids[it].tolist(), strict=True), key=lambda x: (x[0], -x[1], x[2])):
                        if value > score[row] or value == score[row] and value and which_id < owner[row]:
                            score[row], owner[row] = value, which_id
                yield pa.RecordBatch.from_arrays(
                    [*(c.slice(lo, hi - lo) for c in batch.columns), pa.array(score >= THRESHOLD), pa.array(owner, mask=owner < 0), pa.array(score)], names
                )

    return run


def item_blocks(benchmark: DataFrame, size: int = ITEMS_PER_BLOCK) -> Iterator[tuple[list[int], list[str]]]:
    """Blocks by a hash of id and text, so rows that share an id spread as well; repeated rows are one."""
    rows = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("long").alias("item_id"), "text").distinct()
    count, length = rows.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    n = max(1, -(-count // size), -(-length // BLOCK_BYTES))
    for k in range(n):
        part = rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k).orderBy("item_id", "text").collect() if n > 1 else rows.orderBy("item_id", "text").collect()
        if part:
            yield [r.item_id for r in part], [r.text for r in part]


def decontaminate(docs: DataFrame, benchmark: DataFrame, items_per_block: int = ITEMS_PER_BLOCK, prefix: str = "") -> DataFrame:
    """docs with ADDED (replacing columns of these names): the best item and its score, null and 0 without any candidate.
    The prefix stands before the names added. Every further block of items is a further pass that keeps the better of its own and the former item."""
    added_names = tuple(prefix + c for c in ADDED)
    sc = docs.sparkSession.sparkContext
    texts_only, rows = docs.select("text"), docs.drop(*added_names)
    kinds = (F.lit(False), F.lit(None).cast("long"), F.lit(0.0))
    names, at = docs.drop(*added_names).columns, docs.drop(*added_names).columns.index("text")
    rows, done = rows.select("*", *(k.alias(c) for k, c in zip(kinds, added_names, strict=True))), False
    for ids, texts in item_blocks(benchmark, items_per_block):
        index = index_items(ids, texts)
        counted = texts_only.mapInArrow(_frequency_counter(sc.broadcast(index)), "seed long, docs long").groupBy("seed").agg(F.sum("docs").alias("docs"))
        frequency = np.zeros(len(index.seeds), np.int64)
        for seed, n in counted.collect():
            frequency[seed] = n
        rare = rare_seeds(index, frequency)
        before = rows if done else rows.select(*names)
        own = [f"_new_{c}" for c in ADDED]
        added = zip(own if done else added_names, (T.BooleanType(), T.LongType(), T.DoubleType()), strict=True)
        fields = T.StructType([*before.schema.fields, *(T.StructField(c, kind) for c, kind in added)])
        rows = before.mapInArrow(_matcher(sc.broadcast((index, rare)), at, fields.names), fields)
        if done:
            score, item = F.col(added_names[2]), F.coalesce(added_names[1], F.lit((1 << 63) - 1))
            better = (F.col("_new_score") > score) | (F.col("_new_score") == score) & (F.col("_new_item_id") < item)
            rows = rows.select(*names, *(F.when(better, F.col(o)).otherwise(F.col(c)).alias(c) for o, c in zip(own, added_names, strict=True)))
        done = True
    return rows


def clean_documents(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without the contaminated rows; no join."""
    return decontaminate(docs, benchmark, prefix="_found_").where("not _found_contaminated").select(*docs.columns)
