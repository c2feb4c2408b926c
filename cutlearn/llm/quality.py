"""Quality rules: base rules on words, lines and symbols, then a hashed n-gram log-likelihood ratio.

Two multinomials over hashed n-grams are counted over every document: one over the trusted target (documents that
``labels`` marks as good), one over the raw corpus. The n-grams are single words, word pairs and runs of four bytes,
all with their case, hashed into one table. A document's verdict is the sum of log(target / raw) over its n-grams
divided by their number. Weights are whole micro-nats, so the sum, the mean and the threshold give the same verdict
whatever the batches, the partitions or the order of rows.

Defined cases: a null or empty text has no words and fails the base rules; a null doc_id stays null and belongs to
no target; repeated rows count as often as they occur and get the same verdict; without any target row or any row at
all every weight is 0, so every document that passes the base rules is kept; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutlearn.llm import textblocks as tb
from cutlearn.llm.session import broadcast_if_small

BUCKETS = 1 << 17
#: Log-ratio per n-gram, in micro-nats, under which a document goes.
THRESHOLD = -500_000
#: Labelled rows up to this number are broadcast (some 100 bytes each); more are joined by a shuffle.
LABEL_ROWS = 200_000
SMOOTHING = 0.5
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50

COUNTS = "bucket int, raw long, target long"
SCORES = (
    "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, "
    "n_grams long, llr_micro long"
)

SYMBOL = np.zeros(256, bool)
SYMBOL[list(b"#*$%&|<>")] = True


def _grams(data: np.ndarray, offsets: np.ndarray, h: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bucket of every n-gram, text of every n-gram)."""
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(first))
    ok, doc2 = tb.within(first, 2, len(h))
    m = max(0, len(data) - 3)
    quad = np.zeros(m, np.uint64)
    for k in range(4):
        quad = (quad << np.uint64(8)) | data[k : k + m]
    at = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    whole = at[:m] == at[3 : 3 + m]
    pair = tb.ngrams(h, 2)[ok]
    shift = np.uint64(64 - (BUCKETS.bit_length() - 1))
    all_h = np.concatenate([h * tb.GOLDEN, pair, tb.mix(quad[whole] + tb.GOLDEN)])
    return (all_h >> shift).astype(np.int64), np.concatenate([doc, doc2[ok], at[:m][whole]])


def _counter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    raw, target = np.zeros(BUCKETS, np.int64), np.zeros(BUCKETS, np.int64)
    for batch in batches:
        good = np.asarray(batch.column(1))
        for lo, _, data, offsets in tb.slices(batch.column(0)):
            s, e, first = tb.words_of(data, offsets)
            bucket, doc = _grams(data, offsets, tb.hashes_of(data, s, e), first)
            raw += np.bincount(bucket, minlength=BUCKETS)
            target += np.bincount(bucket[good[lo + doc]], minlength=BUCKETS)
    seen = np.flatnonzero(raw)
    yield pa.RecordBatch.from_arrays([pa.array(seen.astype(np.int32)), pa.array(raw[seen]), pa.array(target[seen])], ["bucket", "raw", "target"])


def fit_weights(docs: DataFrame, labels: DataFrame) -> np.ndarray:
    """Micro-nats per bucket, from counts over all documents. What reaches the driver is one row per bucket."""
    good = labels.where("quality = 1 and doc_id is not null").select("doc_id").distinct()
    rows = docs.select("doc_id", "text").join(
        broadcast_if_small(good.withColumn("good", F.lit(True)), good.count(), LABEL_ROWS), "doc_id", "left"
    )
    flagged = rows.select("text", F.coalesce("good", F.lit(False)).alias("good"))
    counts = flagged.mapInArrow(_counter, COUNTS).groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target"))
    raw, target = np.zeros(BUCKETS), np.zeros(BUCKETS)
    for bucket, r, t in counts.collect():
        raw[bucket], target[bucket] = r, t
    if not target.sum():
        return np.zeros(BUCKETS, np.int64)
    p = (target + SMOOTHING) / (target.sum() + SMOOTHING * BUCKETS)
    q = (raw + SMOOTHING) / (raw.sum() + SMOOTHING * BUCKETS)
    return np.rint(np.log(p / q) * 1e6).astype(np.int64)


def _repeats(keys: np.ndarray) -> np.ndarray:
    """True where a key occurs more than once."""
    order = np.sort(keys)
    twice = order[1:][order[1:] == order[:-1]]
    if not len(twice):
        return np.zeros(len(keys), bool)
    return twice[np.minimum(np.searchsorted(twice, keys), len(twice) - 1)] == keys


def _later(keys: np.ndarray) -> np.ndarray:
    """True where a key has occurred before."""
    out = np.ones(len(keys), bool)
    out[np.unique(keys, return_index=True)[1]] = False
    return out


def measure(data: np.ndarray, offsets: np.ndarray, weights: np.ndarray | None = None) -> list[np.ndarray]:
    """The columns of SCORES after doc_id for each text of a slice."""
    s, e, first = tb.words_of(data, offsets)
    h, n = tb.hashes_of(data, s, e), len(offsets) - 1
    whole = tb.NOT_SPACE[data]
    chars = tb.sums_by((whole & ((data & 0xC0) != 0x80)).astype(np.int64), offsets)
    symbols = tb.sums_by(SYMBOL[data].astype(np.int64), offsets)
    ls, le = tb.runs_of(data != 10, offsets)
    filled = np.concatenate([[0], np.cumsum(whole)])
    ls, le = (x[filled[le] > filled[ls]] for x in (ls, le))
    line_first = np.searchsorted(ls, offsets)
    line_doc = np.repeat(np.arange(n), np.diff(line_first))
    dup = _later(tb.mix(tb.hashes_of(data, ls, le) + line_doc.astype(np.uint64) * tb.MIX_A))
    ok, doc3 = tb.within(first, 3, len(h))
    at = np.flatnonzero(ok)
    at = at[_repeats(tb.mix(tb.ngrams(h, 3)[at] + doc3[at].astype(np.uint64) * tb.MIX_A))]
    covered = np.zeros(len(h), np.int64)
    for k in range(3):
        covered[at + k] = 1
    out = [np.diff(first), chars, symbols, tb.sums_by(dup.astype(np.int64), line_first), tb.sums_by(covered, first)]
    if weights is not None:
        bucket, doc = _grams(data, offsets, h, first)
        total = np.zeros(n, np.int64)
        # the three kinds stand one after the other, each in the order of texts: exact whole-number sums per text
        order = np.argsort(doc, kind="stable")
        per = np.bincount(doc, minlength=n)
        total = tb.sums_by(weights[bucket[order]], np.concatenate([[0], np.cumsum(per)]))
        out += [per, total]
    return out


def score(docs: DataFrame, weights: np.ndarray) -> DataFrame:
    """One row per document with its measures and the summed log ratio; one scan, no shuffle."""
    shared = docs.sparkSession.sparkContext.broadcast(weights)

    def scorer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, offsets in tb.slices(batch.column(1)):
                ids = batch.column(0).slice(lo, hi - lo)
                cols = [pa.array(x.astype(np.int64)) for x in measure(data, offsets, shared.value)]
                yield pa.RecordBatch.from_arrays([ids, *cols], [c.split()[0] for c in SCORES.split(", ")])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(scorer, SCORES)


def judge(scored: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """Adds base_failed and kept. The mean is compared without dividing, so it is exact."""
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    return scored.withColumn("base_failed", failed).withColumn(
        "kept", ~failed & (F.col("llr_micro") >= F.lit(threshold) * F.col("n_grams"))
    )


def quality_rules(docs: DataFrame, labels: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    return judge(score(docs, fit_weights(docs, labels)), threshold)
