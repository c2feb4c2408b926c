"""Line dedup with DataFrame operations only.

A line's key is hashed to 128 bits. Hashes are range-partitioned with a secondary sort by document and position; a
running window then streams each key's first document past the later lines, which are marked. The marks come back
as one compressed bitmap for each document, not as text: pairs (word, bits) for those 62-bit words that lose a line.

A key that holds a large share of all lines would fill one range. A mergeable frequent-items sketch over all lines
names such keys (at most FREQUENT_KEYS, so they can be broadcast); their first document is a pre-aggregated minimum,
and their lines are marked where they are read. Both ways are exact, so the sketch decides only who does the work.

Defined cases: a null or empty text is one empty line; a key needs ten code points; a row with null doc_id neither
holds nor loses lines; repeated rows with one doc_id count as one document and get equal bitmaps; other columns are
ignored. Hashes decide equality: a wrong match of two 128-bit hashes is less likely than a disk error.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from cutlearn.llm.session import cut, shuffle_parts

MIN_POINTS = 10
FREQUENT_KEYS, TRACKED = 64, 10_000
#: A key with more than this share of all lines leaves the range partitioning.
HOT_SHARE = 1 / 1000
HOT_LINES = 2_000
BITS = 62

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
STRIP = " \t\n\x0b\x0c\r"


def line_key(line: Column) -> Column:
    return F.translate(F.btrim(line, F.lit(STRIP)), UPPER, LOWER)


def _text(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


def keyed_lines(docs: DataFrame) -> DataFrame:
    """doc_id, text_hash, pos, h1, h2 for each line whose key is long enough."""
    lines = docs.where("doc_id is not null").select(
        "doc_id", F.xxhash64(_text()).alias("text_hash"), F.posexplode(F.split(_text(), "\n", -1)).alias("pos", "line")
    )
    keys = lines.select("doc_id", "text_hash", "pos", line_key(F.col("line")).alias("key"))
    return keys.where(F.length("key") >= MIN_POINTS).select(
        "doc_id", "text_hash", "pos", F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(MIN_POINTS), F.col("key")).alias("h2")
    )


def frequent_keys(lines: DataFrame) -> DataFrame:
    """h1 of keys that hold a large share of the lines; at most FREQUENT_KEYS rows."""
    top = lines.agg(F.expr(f"approx_top_k(h1, {FREQUENT_KEYS}, {TRACKED})").alias("top"), F.count("*").alias("n"))
    return (
        top.select(F.explode("top").alias("t"), "n")
        .where((F.col("t.count") > F.col("n") * HOT_SHARE) & (F.col("t.count") > HOT_LINES))
        .select(F.col("t.item").alias("h1"))
    )


def dropped_lines(docs: DataFrame) -> DataFrame:
    """doc_id, text_hash, pos of each line that a smaller doc_id holds as well."""
    spark = docs.sparkSession
    lines = cut(keyed_lines(docs))
    hot = cut(frequent_keys(lines))
    rest = lines.join(F.broadcast(hot), "h1", "left_anti")
    dealt = rest.repartitionByRange(shuffle_parts(spark), "h1", "h2").sortWithinPartitions("h1", "h2", "doc_id", "pos")
    first = F.first("doc_id").over(Window.partitionBy("h1", "h2").orderBy("doc_id", "pos").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    late = dealt.withColumn("holder", first).where("doc_id > holder").select("doc_id", "text_hash", "pos")
    busy = lines.join(F.broadcast(hot), "h1")
    holders = busy.groupBy("h1", "h2").agg(F.min("doc_id").alias("holder"))
    late_busy = busy.join(F.broadcast(holders), ["h1", "h2"]).where("doc_id > holder").select("doc_id", "text_hash", "pos")
    return late.union(late_busy)


def keep_bitmaps(docs: DataFrame) -> DataFrame:
    """doc_id, text_hash, dropped (map from word number to bits, a set bit for each line that goes), n_dropped.
    Documents that lose nothing have no row."""
    words = dropped_lines(docs).groupBy("doc_id", "text_hash", F.floor(F.col("pos") / BITS).cast("int").alias("word")).agg(
        F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("pos") % BITS)).alias("bits")
    )
    return words.groupBy("doc_id", "text_hash").agg(
        F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("dropped"),
        F.sum(F.bit_count("bits")).alias("n_dropped"),
    )


def _judged(docs: DataFrame) -> tuple[DataFrame, Column, Column, Column]:
    """docs joined with their bitmaps, and the text left, the lines and the lines lost. Names added begin with _ld."""
    bitmaps = keep_bitmaps(docs).toDF("_ld_id", "_ld_hash", "_ld_dropped", "_ld_n")
    rows = docs.join(bitmaps, (docs.doc_id == bitmaps["_ld_id"]) & (F.xxhash64(F.coalesce(docs.text, F.lit(""))) == bitmaps["_ld_hash"]), "left")
    stays = lambda line, i: (
        F.call_function("shiftright", F.coalesce(F.element_at("_ld_dropped", F.floor(i / BITS).cast("int")), F.lit(0).cast("long")), i % BITS).bitwiseAND(F.lit(1).cast("long")) == 0
    )
    kept = F.when(F.col("_ld_dropped").isNull(), _text()).otherwise(F.array_join(F.filter(F.split(_text(), "\n", -1), stays), "\n"))
    n_lines = F.length(_text()) - F.length(F.translate(_text(), "\n", "")) + 1
    return rows, kept, n_lines.cast("long"), F.coalesce(F.col("_ld_n"), F.lit(0)).cast("long")


def dedup_lines(docs: DataFrame) -> DataFrame:
    """The rows of docs with kept (the text left), n_lines and n_dropped added; columns of these names are replaced."""
    rows, kept, n_lines, n_dropped = _judged(docs)
    own = [c for c in docs.columns if c not in ("kept", "n_lines", "n_dropped")]
    return rows.select(*own, kept.alias("kept"), n_lines.alias("n_lines"), n_dropped.alias("n_dropped"))


def dedup_text(docs: DataFrame) -> DataFrame:
    """The rows and columns of docs; text has the lines left, and n_chars (if there is one) its length."""
    rows, kept, _, _ = _judged(docs)
    new = {"text": kept, "n_chars": F.length(kept).cast("long")}
    return rows.select(*(new[c].alias(c) if c in new else docs[c] for c in docs.columns))
