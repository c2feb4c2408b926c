"""Language identification in two steps: the family first, then the language within it.

A text's features are hashed counts of its byte runs of two to four bytes (letters in lower case, all else one
blank), each count divided by their sum, square root taken, so every text is a vector of length 1. Linear support
vector machines (squared hinge loss) tell each family from the others; inside a family one machine for each pair of
languages votes, and ties go to the larger sum of margins, then to the smaller code.

Machines are fitted on the driver from at most SAMPLE_PER_LANGUAGE labelled rows of each language, those with the
least hashes of doc_id among training rows (of rows with one doc_id and language the least text counts, so equal ids
can't swell the sample); everything else covers all rows. Features of the sample are computed on
the executors.

Defined cases: `und` with score 0 if the text is null, has no letter, or nothing could be learned; one learned
language is predicted for every text with letters; a null doc_id counts as training row only for its hash, that is,
never; languages missing from FAMILIES are families of their own; repeated rows get equal predictions.
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

DIMENSIONS = 1 << 12
RUNS = (2, 3, 4)
SAMPLE_PER_LANGUAGE = 300
FOLDS, HELD_OUT = 5, 0
ROWS_PER_SLICE = 256
UNKNOWN = "und"

#: Families of languages by code.
FAMILIES = {
    "germanic": ("en", "de", "nl", "sv", "da", "no", "nb", "nn", "is", "af"),
    "romance": ("fr", "es", "it", "pt", "ro", "ca", "gl"),
    "slavic": ("ru", "uk", "be", "bg", "pl", "cs", "sk", "sl", "hr", "sr", "mk"),
    "uralic": ("fi", "et", "hu"),
    "turkic": ("tr", "az", "kk"),
}
FAMILY = {code: name for name, codes in FAMILIES.items() for code in codes}

#: Bytes that may be part of a letter keep their (lower-case) value; others become a blank.
FOLD = np.where((np.arange(256) >= 0x80) | ((tb.LOWER >= ord("a")) & (tb.LOWER <= ord("z"))), tb.LOWER, 0x20).astype(np.uint8)


class Model(NamedTuple):
    families: list[str]
    family_weights: np.ndarray  # dimensions + 1 by families
    languages: dict[str, list[str]]
    pairs: dict[str, tuple[list[tuple[int, int]], np.ndarray]]


def features(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """A row of DIMENSIONS + 1 (the last is 1) for each text."""
    n = len(offsets) - 1
    folded = FOLD[data].astype(np.uint64)
    at = np.repeat(np.arange(n), np.diff(offsets))
    counts = np.zeros((n, DIMENSIONS))
    run = folded.copy()
    for k in range(1, max(RUNS)):
        m = len(data) - k
        if m <= 0:
            break
        run = (run[:m] << np.uint64(8)) | folded[k:]
        if k + 1 in RUNS:
            bucket = (((run + np.uint64(k)) * tb.GOLDEN) >> np.uint64(64 - DIMENSIONS.bit_length() + 1)).astype(np.int64)
            whole = at[:m] == at[k:]
            counts += np.bincount((at[:m] * DIMENSIONS + bucket)[whole], minlength=n * DIMENSIONS).reshape(n, DIMENSIONS)
    total = counts.sum(axis=1, keepdims=True)
    x = np.sqrt(counts / np.maximum(total, 1))
    return np.hstack([x, np.ones((n, 1))])


def fit_svm(x: np.ndarray, y: np.ndarray, penalty: float = 1e-3, steps: int = 150) -> np.ndarray:
    """Weights of linear machines (a column for each column of y, entries 1 or -1) by accelerated gradient descent on
    the mean squared hinge loss, rows of either side weighing the same in sum."""
    weight = np.where(y > 0, 0.5 / np.maximum((y > 0).sum(axis=0), 1), 0.5 / np.maximum((y < 0).sum(axis=0), 1))
    w = np.zeros((x.shape[1], y.shape[1]))
    look, t = w, 1.0
    step = 1 / (2 * 2 + penalty)  # rows have squared length 2
    for _ in range(steps):
        slack = np.maximum(0, 1 - y * (x @ look))
        new = look - step * (penalty * look - 2 * x.T @ (weight * y * slack))
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        look, w, t = new + (t - 1) / t2 * (new - w), new, t2
    return w


def fit(x: np.ndarray, lang: list[str]) -> Model | None:
    known = sorted(set(lang))
    if not known:
        return None
    family_of = {code: FAMILY.get(code, code) for code in known}
    families = sorted(set(family_of.values()))
    names = np.array(lang)
    own = np.array([family_of[c] for c in lang])
    sign = lambda on: np.where(on, 1.0, -1.0)
    weights = fit_svm(x, sign(own[:, None] == np.array(families)[None, :])) if len(families) > 1 else np.zeros((x.shape[1], 1))
    languages = {f: [c for c in known if family_of[c] == f] for f in families}
    pairs = {}
    for f, codes in languages.items():
        duels = [(i, j) for i in range(len(codes)) for j in range(i + 1, len(codes))]
        columns = []
        for i, j in duels:
            rows = np.isin(names, [codes[i], codes[j]])
            columns.append(fit_svm(x[rows], sign(names[rows] == codes[i])[:, None])[:, 0])
        pairs[f] = (duels, np.array(columns).T if columns else np.zeros((x.shape[1], 0)))
    return Model(families, weights, languages, pairs)


def predict(model: Model, x: np.ndarray) -> tuple[list[str], np.ndarray]:
    chance = lambda m: 1 / (1 + np.exp(-3 * np.clip(m, -20, 20)))
    margin = x @ model.family_weights
    pick = margin.argmax(axis=1)
    score = chance(margin[np.arange(len(x)), pick]) if len(model.families) > 1 else np.ones(len(x))
    out = np.empty(len(x), object)
    for k, f in enumerate(model.families):
        rows = np.flatnonzero(pick == k)
        codes, (duels, weights) = model.languages[f], model.pairs[f]
        if not len(rows):
            continue
        if not duels:
            out[rows] = codes[0]
            continue
        m = x[rows] @ weights
        votes, sums = np.zeros((len(rows), len(codes))), np.zeros((len(rows), len(codes)))
        for c, (i, j) in enumerate(duels):
            votes[:, i] += m[:, c] >= 0
            votes[:, j] += m[:, c] < 0
            sums[:, i] += m[:, c]
            sums[:, j] -= m[:, c]
        best = (votes + 0.5 * np.tanh(sums) / (len(codes) + 1)).argmax(axis=1)
        out[rows] = np.array(codes, object)[best]
        score[rows] *= chance(sums[np.arange(len(rows)), best] / (len(codes) - 1))
    return out.tolist(), score


def fold_of(doc_id: str = "doc_id"):
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % FOLDS


def _vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, ROWS_PER_SLICE):
            part = batch.slice(at, ROWS_PER_SLICE)
            for lo, hi, data, offsets in tb.slices(pc.utf8_lower(part.column(1))):
                x = features(data, offsets)[:, :-1].astype(np.float32)
                yield pa.RecordBatch.from_arrays([part.column(0).slice(lo, hi - lo), pa.array([r.tobytes() for r in x], pa.binary())], ["lang", "x"])


def learn(docs: DataFrame, sample: int = SAMPLE_PER_LANGUAGE) -> Model | None:
    """Reads ids and labels of all rows, and the texts of the sample."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang").where("doc_id is not null and lang is not null")
    rows = rows.where(fold_of() != HELD_OUT).withColumn("draw", F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40)))
    counts = {r.lang: r.n for r in rows.groupBy("lang").agg(F.approx_count_distinct("draw").alias("n")).collect()}
    if not counts:
        return None
    # twice the wanted share of the hash space, then exactly the least hashes of each language
    share = F.create_map(*[v for lang, n in sorted(counts.items()) for v in (F.lit(lang), F.lit(int(min(1.0, 2 * (sample + 50) / n) * (1 << 40))))])
    near = rows.where(F.col("draw") <= share[F.col("lang")])
    cuts = near.groupBy("lang").agg(F.sort_array(F.collect_set("draw")).alias("d")).select("lang", F.element_at("d", F.least(F.size("d"), F.lit(sample))).alias("last")).collect()
    last = F.create_map(*[v for r in sorted(cuts) for v in (F.lit(r.lang), F.lit(r["last"]))])
    chosen = near.where(F.col("draw") <= last[F.col("lang")]).groupBy("lang", "draw").agg(F.min("text").alias("text")).select("lang", "text")
    got = sorted((r.lang, bytes(r.x)) for r in chosen.mapInArrow(_vectors, "lang string, x binary").collect())
    x = np.array([np.frombuffer(v, np.float32) for _, v in got], np.float64).reshape(-1, DIMENSIONS)
    return fit(np.hstack([x, np.ones((len(x), 1))]), [c for c, _ in got])


def _predictor(shared, text: int, names: list[str]):
    """Appends lang_pred and score to the columns of each batch; column number `text` is judged."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model: Model | None = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS_PER_SLICE):
                part = batch.slice(at, ROWS_PER_SLICE)
                letters = pc.fill_null(pc.match_substring_regex(part.column(text), r"\p{L}"), False).to_numpy(zero_copy_only=False)
                for lo, hi, data, offsets in tb.slices(pc.utf8_lower(part.column(text))):
                    n, good = hi - lo, letters[lo:hi]
                    if model is None:
                        lang, score = [UNKNOWN] * n, np.zeros(n)
                    else:
                        lang, score = predict(model, features(data, offsets))
                        lang = [c if g else UNKNOWN for c, g in zip(lang, good, strict=True)]
                        score = np.where(good, score, 0.0)
                    yield pa.RecordBatch.from_arrays([*(c.slice(lo, n) for c in part.columns), pa.array(lang, pa.string()), pa.array(score)], names)

    return run


def identify(docs: DataFrame, model: Model | None, prefix: str = "") -> DataFrame:
    """docs with lang_pred and score added (replaced, if there are such columns); one scan, no shuffle or join. The
    prefix stands before both names."""
    docs = docs.drop(f"{prefix}lang_pred", f"{prefix}score")
    shared = docs.sparkSession.sparkContext.broadcast(model)
    fields = T.StructType([*docs.schema.fields, T.StructField(f"{prefix}lang_pred", T.StringType()), T.StructField(f"{prefix}score", T.DoubleType())])
    return docs.mapInArrow(_predictor(shared, docs.columns.index("text"), fields.names), fields)
