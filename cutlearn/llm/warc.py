"""WARC archives: writing pages as records, reading them back, and reassembling segmented records.

Payloads travel in chunked transfer framing. A block over SEGMENT_BYTES is cut into a first record and continuation
records that name it as their origin, number themselves and, in the last one, tell the whole length. Reading groups
continuations by origin, orders them by number, checks that none is missing and that the length is the one told, and
takes off the framing. Records repeat a payload as a revisit when another page's response holds it.

Archives are text of Spark's own writer (gzip) with the record end as line separator, so they lie in any store that
Spark reaches and are written again by themselves if an executor is lost. They are read back by the version line, which
nothing before it can overlap with; chunks break the version string apart wherever a payload has it, so no payload holds
that line. Bytes beyond a record's length are a problem of the record, and a round trip that reads more or fewer records
than it wrote pages raises. `parse_archive` reads foreign archives.

Defined cases: a null html is an empty payload; a null url leaves out its field; a page with null page_id is written
under the id `null` and gives its payload to nobody else's revisit unless all equal ones have null ids; repeated rows
are records of their own; an empty table gives empty archives; broken or missing segments give a row with `problem`.
"""

from __future__ import annotations

import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutlearn.llm.session import broadcast_if_small, cut, drop_path, shared_dir
from cutlearn.llm.textblocks import slices

SEGMENT_BYTES, CHUNK_BYTES = 32_768, 8_192
REVISIT_BYTES = 1000
RECORDS_PER_FILE = 20_000

#: Fixed values of the format.
VERSION = b"WARC/1.1\r\n"
END = b"\r\n\r\n"
DATE = "2024-01-01T00:00:00Z"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
ID = "urn:page"

PARSED = (
    "record_id string, record_type string, origin string, segment long, total long, refers string, digest string, "
    "payload_bytes long, payload_digest string, url string, block binary, problem string"
)


def chunked(payload: bytes, size: int = CHUNK_BYTES) -> bytes:
    """Chunked framing; no chunk holds the version string and none cuts a character in two."""
    out = []
    for piece in re.split(rb"(?<=WARC/)(?=1\.1)", payload):
        at = 0
        while at < len(piece):
            z = min(at + size, len(piece))
            while z < len(piece) and z > at + 1 and piece[z] & 0xC0 == 0x80:
                z -= 1
            out += [b"%x\r\n" % (z - at), piece[at:z], b"\r\n"]
            at = z
    return b"".join([*out, b"0\r\n\r\n"])


def dechunk(body: bytes) -> bytes:
    """Takes chunked framing off; ValueError if it is broken."""
    out, at = [], 0
    while True:
        z = body.index(b"\r\n", at)
        n = int(body[at:z].split(b";")[0], 16)
        if n == 0:
            return b"".join(out)
        piece = body[z + 2 : z + 2 + n]
        if len(piece) != n or body[z + 2 + n : z + 4 + n] != b"\r\n":
            raise ValueError("broken chunk")
        out.append(piece)
        at = z + 4 + n


def _record(fields: list[tuple[str, str | None]], block: bytes) -> bytes:
    safe = lambda v: re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", v)
    # a blank keeps an address that ends in the version from making a version line
    lines = [f"{k}: {safe(str(v)) + ' ' * str(v).endswith(VERSION[:-2].decode()) if k == 'WARC-Target-URI' else v}\r\n" for k, v in fields if v is not None]
    return VERSION + "".join(lines).encode() + b"Content-Length: %d\r\n\r\n" % len(block) + block


def page_records(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: str | None, segment: int = SEGMENT_BYTES) -> list[bytes]:
    """The records of one page, without the record end."""
    name = f"<{ID}:{'null' if page_id is None else page_id}:{digest}>"
    common = [("WARC-Date", DATE), ("WARC-Target-URI", url), ("WARC-Payload-Digest", f"sha1:{digest}")]
    http = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n"
    if refers_to is not None:
        head = [("WARC-Type", "revisit"), ("WARC-Record-ID", name), *common, ("WARC-Profile", REVISIT_PROFILE), ("WARC-Refers-To", f"<{ID}:{refers_to}:{digest}>"), ("Content-Type", "application/http;msgtype=response")]
        return [_record(head, f"{http}Content-Length: {len(payload)}\r\n\r\n".encode())]
    block = f"{http}Transfer-Encoding: chunked\r\n\r\n".encode() + chunked(payload)
    cuts, at = [], 0
    while at < len(block):
        z = min(at + segment, len(block))
        while z < len(block) and z > at + 1 and (block[z] & 0xC0 == 0x80):
            z -= 1
        cuts.append((at, z))
        at = z
    out = []
    for n, (a, z) in enumerate(cuts, 1):
        head = [("WARC-Type", "response" if n == 1 else "continuation"), ("WARC-Record-ID", name if n == 1 else f"{name[:-1]}:{n}>"), *common]
        if len(cuts) > 1:
            head += [("WARC-Segment-Number", str(n)), ("WARC-Segment-Origin-ID", name if n > 1 else None), ("WARC-Segment-Total-Length", str(len(block)) if n == len(cuts) else None)]
        out.append(_record([*head, ("Content-Type", "application/http;msgtype=response") if n == 1 else ("Content-Type", None)], block[a:z]))
    return out


def parse_record(data: bytes) -> tuple[dict[str, str], bytes]:
    """(fields by lower-case name, block) of one record, with or without its version line."""
    return split_record(data)[:2]


def split_record(data: bytes) -> tuple[dict[str, str], bytes, bytes]:
    """(fields by lower-case name, block, what stands behind the block)."""
    if data.startswith(b"WARC/"):
        data = data[data.index(b"\r\n") + 2 :]
    head, _, rest = data.partition(END)
    fields = {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in head.decode("utf-8", "replace").split("\r\n")) if k}
    n = int(fields.get("content-length", len(rest)))
    return fields, rest[:n], rest[n:]


def parse_archive(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Records of a whole archive, plain or made of gzip members, by their Content-Length."""
    if data[:2] == b"\x1f\x8b":
        out = []
        while data:
            d = zlib.decompressobj(31)
            out.append(d.decompress(data) + d.flush())
            data = d.unused_data
        data = b"".join(out)
    at = 0
    while (at := data.find(b"WARC/", at)) >= 0:
        head = data.index(END, at)
        n = re.search(rb"(?im)^content-length:\s*(\d+)", data[at:head])
        stop = head + 4 + int(n[1] if n else 0)
        yield parse_record(data[at:stop])
        at = stop


def payload_of(fields: dict[str, str], block: bytes) -> bytes:
    """The HTTP body of a whole response block, without framing."""
    head, _, body = block.partition(END)
    return dechunk(body) if re.search(rb"(?im)^transfer-encoding:.*chunked", head) else body


def assemble(segments: list[tuple[int, int | None, bytes]]) -> bytes:
    """One block from (number, told total length, piece) in any order; repeats of a number are taken once."""
    pieces = {n: (total, piece) for n, total, piece in segments}
    if sorted(pieces) != list(range(1, len(pieces) + 1)):
        raise ValueError("a segment is missing")
    block = b"".join(pieces[n][1] for n in sorted(pieces))
    if pieces[len(pieces)][0] != len(block):
        raise ValueError("the length differs from the one told")
    return block


def with_revisits(pages: DataFrame) -> DataFrame:
    """page_id, url, html, digest, refers (page id of the response as a string, null for responses). Equal payloads
    are counted before anything is joined; few groups are broadcast, many are joined by a shuffle of digests."""
    html = F.coalesce("html", F.lit(""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", html.alias("html"))
    keyed = rows.select("page_id", F.sha1(html.cast("binary")).alias("digest"), F.octet_length("html").alias("n")).where(F.col("n") >= REVISIT_BYTES)
    groups = cut(keyed.groupBy("digest", "n").agg(F.max("page_id").alias("chosen"), F.count("*").alias("times")).where("times > 1 and chosen is not null").select("digest", "n", "chosen"))
    marked = rows.withColumns({"digest": F.sha1(F.col("html").cast("binary")), "n": F.octet_length("html")})
    joined = marked.join(broadcast_if_small(groups, groups.count()), ["digest", "n"], "left")
    other = F.col("chosen").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("chosen"))
    return joined.select("page_id", "url", "html", "digest", F.when(other, F.col("chosen").cast("string")).alias("refers"))


def _writer(segment: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, urls, digests, refers = (batch.column(k).to_pylist() for k in (0, 1, 3, 4))
            for lo, hi, data, offsets in slices(batch.column(2)):
                raw = data.tobytes()
                out = [r for i in range(lo, hi) for r in page_records(ids[i], urls[i], raw[offsets[i - lo] : offsets[i - lo + 1]], digests[i], refers[i], segment)]
                yield pa.RecordBatch.from_arrays([pa.array([x.decode("utf-8", "replace") for x in out])], ["value"])

    return run


def write_pages(pages: DataFrame, path: str, segment: int = SEGMENT_BYTES) -> None:
    with_revisits(pages).mapInArrow(_writer(segment), "value string").write.options(
        lineSep=END.decode(), compression="gzip", maxRecordsPerFile=RECORDS_PER_FILE
    ).text(path)


def _id(value: str | None) -> str | None:
    return value.strip("<>") if value else None


def _parser(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = [c.split()[0] for c in PARSED.split(", ")]
    kinds = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}
    types = [kinds[c.split()[1]] for c in PARSED.split(", ")]
    for batch in batches:
        for _lo, _hi, data, offsets in slices(batch.column(0)):
            raw, rows = data.tobytes(), []
            for a, z in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
                if not raw[a:z].strip():
                    continue
                f, block, beyond = split_record(raw[a:z])
                number, kind = int(f.get("warc-segment-number", 0)), f.get("warc-type")
                origin = _id(f.get("warc-segment-origin-id")) or _id(f.get("warc-record-id"))
                size = digest = problem = None
                if len(block) != int(f.get("content-length", -1)):
                    problem = "the record is cut off"
                elif beyond not in (b"", END):
                    problem = f"{len(beyond)} bytes beyond the record"
                elif kind == "revisit":
                    n = re.search(rb"(?im)^content-length:\s*(\d+)", block)
                    size, digest = int(n[1]) if n else None, f.get("warc-payload-digest", "").removeprefix("sha1:")
                elif not number:
                    try:
                        payload = payload_of(f, block)
                        size, digest = len(payload), hashlib.sha1(payload).hexdigest()
                    except ValueError as e:
                        problem = str(e)
                total = f.get("warc-segment-total-length")
                rows.append((_id(f.get("warc-record-id")), kind, origin, number or None, int(total) if total else None, _id(f.get("warc-refers-to")), f.get("warc-payload-digest", "").removeprefix("sha1:"), size, digest, f.get("warc-target-uri"), block if number and not problem else None, problem))
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(types)], names)


ASSEMBLED = "record_id string, record_type string, refers string, digest string, payload_bytes long, payload_digest string, url string, copies long, payload binary, problem string"


def _assembler(with_payload: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for r in (batch.slice(i, 1).to_pylist()[0] for i in range(batch.num_rows)):
                payload = problem = None
                try:
                    payload = payload_of({}, assemble([(s["segment"], s["total"], s["block"]) for s in r["segments"]]))
                except (ValueError, KeyError) as e:
                    problem = str(e)
                rows.append((r["origin"], "response", None, r["digest"], len(payload) if payload is not None else None, hashlib.sha1(payload).hexdigest() if payload is not None else None, r["url"], r["copies"] or 1, payload if with_payload else None, problem))
            kinds = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}
            cols = ASSEMBLED.split(", ")
            yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in rows], kinds[c.split()[1]]) for k, c in enumerate(cols)], [c.split()[0] for c in cols])

    return run


def read_pages(spark: SparkSession, path: str, with_payload: bool = False) -> DataFrame:
    """Columns of ASSEMBLED for each record; segmented ones are whole again. Only segments are shuffled."""
    lines = spark.read.option("lineSep", VERSION.decode()).text(path)
    parsed = cut(lines.mapInArrow(_parser, PARSED))
    whole = parsed.where("segment is null").select("record_id", "record_type", "refers", "digest", "payload_bytes", "payload_digest", "url", F.lit(1).cast("long").alias("copies"), F.lit(None).cast("binary").alias("payload"), "problem")
    # equal segments of repeated records are one, so a group is never larger than its record
    once = parsed.where("segment is not null").groupBy("origin", "segment", "total", "block").agg(F.max("digest").alias("digest"), F.max("url").alias("url"), F.count("*").alias("times"))
    groups = once.groupBy("origin").agg(
        F.max("digest").alias("digest"), F.max("url").alias("url"), F.collect_list(F.struct("segment", "total", "block")).alias("segments"),
        F.max(F.when(F.col("segment") == 1, F.col("times"))).alias("copies"),
    )
    return whole.unionByName(groups.mapInArrow(_assembler(with_payload), ASSEMBLED))


def round_trip(pages: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to, url: read from archives just written to the shared folder."""
    spark = pages.sparkSession
    path = f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}"
    write_pages(pages, path)
    read = cut(read_pages(spark, path))
    drop_path(spark, path)
    wrote, got = pages.count(), read.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0]
    if wrote != got:
        raise RuntimeError(f"{wrote} pages were written and {got} records read back")
    number = lambda c: F.regexp_extract(c, rf"^{ID}:(-?\d+):", 1).try_cast("long")
    rows = read.withColumn("page_id", number(F.col("record_id"))).withColumn("refers_to", number(F.col("refers")))
    once = rows.withColumn("nth", F.explode(F.sequence(F.lit(1).cast("long"), "copies")))
    return once.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "problem")

