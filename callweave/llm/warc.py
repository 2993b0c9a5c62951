"""WARC archives: a deduplicating writer and a salvage reader.

Records are built as SQL strings and gathered in each task into archives of
bounded bytes, plain or with a gzip member for each record. An archive is a row
of Spark's text sink and a file of its own, so the commit protocol covers
archives as any other table; the sink's line separator is the last byte of the
archive itself. The reader checks every record (framing, length, digest); after a
failed check it looks for the next version line or gzip member that holds a
sound record, goes on there and reports the bytes between as a gap. Of a broken
gzip member, what inflates before the damage is searched for records as well.
"""

from __future__ import annotations

import hashlib
import re
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from callweave.llm.common import cut, scratch

END = b"\r\n\r\n"
URN = "urn:callweave:page:"
LEAST_SHARED = 100


def _payload(html_col: str):
    return F.coalesce(F.col(html_col).cast("string"), F.lit(""))


def plan_records(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least: int = LEAST_SHARED) -> DataFrame:
    """page_id, url, payload, digest, record_type and refers_to of each page.

    Of pages with equal payloads of at least `least` bytes the smallest page_id
    is the response and the others revisit it; rows that repeat the smallest
    page_id are responses too, and so is a page without an id. Only digests that
    occur twice join back, so hot payloads are counted before they shuffle.
    """
    base = pages.select(
        F.col(id_col).cast("long").alias("page_id"),
        F.col(url_col).cast("string").alias("url"),
        _payload(html_col).alias("payload"),
        F.sha2(_payload(html_col), 256).alias("digest"),
    )
    shared = (
        base.where((F.octet_length("payload") >= least) & F.col("page_id").isNotNull())
        .groupBy("digest")
        .agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n"))
        .where("n > 1")
        .select("digest", "first_id")
    )
    again = F.col("page_id") != F.col("first_id")
    return base.join(cut(shared), "digest", "left").select(
        "page_id", "url", "payload", "digest",
        F.when(again, "revisit").otherwise("response").alias("record_type"),
        F.when(again, F.col("first_id")).alias("refers_to"),
    )


FILE_BYTES = 32 << 20


def write_archives(records: DataFrame, path: str, date: str = "2024-01-01T00:00:00Z", file_bytes: int = FILE_BYTES, gzip: bool = False) -> None:
    """Write `records` of plan_records() as WARC/1.1 files below `path`; `gzip` makes each record a gzip member.

    A file ends with the record that brings it to `file_bytes` (before
    compression), so it is that and one record long at most.
    """
    eol = "\r\n"
    urn = lambda c: F.concat(F.lit(f"<{URN}"), F.coalesce(F.col(c).cast("string"), F.lit("")), F.lit(">"))
    uri = F.regexp_replace(F.coalesce("url", F.lit("")), r"[\x00-\x20]", "%20")
    http = F.concat(
        F.lit(f"HTTP/1.1 200 OK{eol}Content-Type: text/html; charset=utf-8{eol}Content-Length: "),
        F.octet_length("payload").cast("string"), F.lit(eol + eol),
    )
    block = F.when(F.col("record_type") == "response", F.concat(http, "payload")).otherwise(http)
    record = F.concat(
        F.lit(f"WARC/1.1{eol}WARC-Type: "), "record_type",
        F.lit(f"{eol}WARC-Record-ID: "), urn("page_id"),
        F.lit(f"{eol}WARC-Date: {date}{eol}WARC-Target-URI: "), uri,
        F.lit(f"{eol}WARC-Payload-Digest: sha256:"), "digest",
        F.when(F.col("refers_to").isNotNull(), F.concat(
            F.lit(f"{eol}WARC-Refers-To: "), urn("refers_to"),
            F.lit(f"{eol}WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"),
        )).otherwise(""),
        F.lit(f"{eol}Content-Type: application/http; msgtype=response{eol}Content-Length: "),
        F.octet_length("block").cast("string"), F.lit(eol + eol), "block",
    )
    whole = records.withColumn("block", block).select(F.concat(record, F.lit(END.decode())).alias("record"))

    def gather(batches):
        """Archives without their last byte, which the sink writes."""
        parts, size = [], 0
        for b in batches:
            for text in b.column(0):
                data = text.as_buffer().to_pybytes()
                parts.append(member(data) if gzip else data)
                size += len(data)
                if size >= file_bytes:
                    yield pa.RecordBatch.from_arrays([pa.array([b"".join(parts)[:-1]], pa.binary())], ["value"])
                    parts, size = [], 0
        if parts:
            yield pa.RecordBatch.from_arrays([pa.array([b"".join(parts)[:-1]], pa.binary())], ["value"])

    files = whole.mapInArrow(gather, "value binary").select(F.col("value").cast("string").alias("value"))
    files.write.option("lineSep", "\x00" if gzip else "\n").option("maxRecordsPerFile", 1).option("compression", "none").text(path)


def member(data: bytes) -> bytes:
    """A gzip member that ends in a zero byte: the length's highest, or that of an empty member behind one of 16 MB or more."""
    out = zlib.compressobj(wbits=31)
    packed = out.compress(data) + out.flush()
    return packed if packed.endswith(b"\0") else packed + member(b"")


def _record(data: bytes, at: int) -> tuple[dict, int] | str:
    """The record at `at` and where it ends, or why there is none."""
    if not data.startswith(b"WARC/1.", at):
        return "no version line"
    top = data.find(END, at)
    if top < 0:
        return "header without end"
    lines = data[at:top].split(b"\r\n")[1:]
    if not all(b":" in x for x in lines):
        return "broken header"
    head = {k.strip().lower().decode("latin-1"): v.strip().decode("utf-8", "replace") for k, v in (x.split(b":", 1) for x in lines)}
    single = [x.split(b":", 1)[0].strip().lower() for x in lines]
    if len({x for x in single if x != b"warc-concurrent-to"}) != sum(x != b"warc-concurrent-to" for x in single):
        return "repeated header field"  # two headers that a tear has run together
    if not re.fullmatch(r"\d{1,15}", head.get("content-length", "")):
        return "no length"
    start = top + 4
    stop = start + int(head["content-length"])
    if stop + 4 > len(data) or data[stop : stop + 4] != END:
        return "wrong length"
    block = data[start:stop]
    out = {"record_type": head.get("warc-type"), "url": head.get("warc-target-uri"), "digest": None, "payload": None, "payload_bytes": None}
    out |= {"page_id": _number(head.get("warc-record-id")), "refers_to": _number(head.get("warc-refers-to"))}
    if out["record_type"] in ("response", "revisit"):
        cut_at = block.find(END)
        size = re.search(rb"(?im)^content-length:\s*(\d+)\s*$", block[: max(cut_at, 0)])
        if cut_at < 0 or not size:
            return "no http header"
        out["payload_bytes"], digest = int(size[1]), head.get("warc-payload-digest", "").removeprefix("sha256:").lower()
        if out["record_type"] == "response":
            out["payload"] = block[cut_at + 4 :]
            if len(out["payload"]) != out["payload_bytes"] or hashlib.sha256(out["payload"]).hexdigest() != digest:
                return "wrong digest"
        elif len(block) != cut_at + 4 or not re.fullmatch("[0-9a-f]{64}", digest):
            return "broken revisit"
        out["digest"] = digest
    return out, stop + 4


def _number(uri: str | None) -> int | None:
    m = re.fullmatch(rf"<{URN}(-?\d+)>", uri or "")
    return int(m[1]) if m else None


def _member(data: bytes, at: int, step: int = 1 << 16) -> tuple[bytes, int, str]:
    """What inflates of the gzip member at `at`, where it ends or breaks, and why it isn't sound (empty if it is)."""
    unzip, out, why = zlib.decompressobj(wbits=31), [], ""
    view, to = memoryview(data), at
    while to < len(data) and not unzip.eof:
        try:
            out.append(unzip.decompress(view[to : to + step]))
        except zlib.error as e:
            why = f"broken member: {e}"
            break
        to = min(len(data), to + step)
    if unzip.eof:
        return b"".join(out), to - len(unzip.unused_data), ""
    return b"".join(out), to, why or "member without end"


def salvage(data: bytes, inside: bool = False):
    """Yield ("record", fields) and ("gap", start, end, reason) of an archive's bytes, in order; gaps count bytes of `data`.

    A broken gzip member is a gap up to the next sound member or record, but for
    the records found in what inflates of it. A member within 64 KB of damage
    is found again by its magic bytes.
    """
    at, gap, why = 0, None, ""
    mark = re.compile(rb"WARC/1\." if inside else rb"WARC/1\.|\x1f\x8b\x08")  # a tear may leave no line end before it
    while at < len(data):
        found, saved = None, []
        if not inside and data.startswith(b"\x1f\x8b\x08", at):
            inner, end, got = _member(data, at)
            parts = list(salvage(inner, True)) if inner else []
            records = [p for p in parts if p[0] == "record"]
            if not got and not inner:
                found = ([], end)  # an empty member
            elif not got and records:
                found = ([p if p[0] == "record" else ("gap", at, end, f"in member: {p[3]}") for p in parts], end)
            elif not got:
                got = "member without record"
            else:
                saved = records
        else:
            got = _record(data, at)
            if not isinstance(got, str):
                found = ([("record", got[0])], got[1])
        if found:
            if gap is not None:
                yield "gap", gap, at, why
                gap = None
            yield from found[0]
            at = found[1]
            continue
        yield from saved
        if gap is None:
            gap, why = at, got
        m = mark.search(data, at + 1)
        at = m.start() if m else len(data)
    if gap is not None:
        yield "gap", gap, len(data), why


SCHEMA = "file string, page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary, gap_start long, gap_end long, gap_reason string"


def read_archives(spark: SparkSession, path: str, payloads: bool = True, pattern: str = "*.txt*") -> DataFrame:
    """A row per sound record, and per quarantined gap (gap_reason not null, other record columns null).

    A file is one task's unit and held in memory: write_archives bounds its
    bytes, archives of other writers can have 2 GB at most (Spark refuses longer
    binary files). Files without any record give one gap, empty files nothing.
    """
    names = [c.strip().split()[0] for c in SCHEMA.split(",")]
    types = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}
    kinds = [types[c.strip().split()[1]] for c in SCHEMA.split(",")]

    def batch(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names)

    def run(batches):
        rows = []
        for b in batches:
            for file, content in zip(b.column(0), b.column(1)):
                name, data = file.as_py(), content.as_py()
                for part in salvage(data or b""):
                    if part[0] == "gap":
                        rows.append((name, *[None] * 7, *part[1:]))
                    else:
                        r = part[1]
                        rows.append((name, r["page_id"], r["url"], r["record_type"], r["refers_to"], r["payload_bytes"], r["digest"], r["payload"] if payloads else None, None, None, None))
                    if len(rows) >= 512:
                        yield batch(rows)
                        rows = []
        if rows:
            yield batch(rows)

    files = spark.read.format("binaryFile").option("pathGlobFilter", pattern).load(path)
    return files.select(F.col("path").alias("file"), "content").mapInArrow(run, SCHEMA)


def archive_roundtrip(pages: DataFrame) -> DataFrame:
    """Write all pages as archives in the shared folder and read them back: the records, without payloads.

    Null html is an empty payload, null url an empty URI, null page_id stays
    null; repeated rows stay repeated; an empty table gives no records. Any gap,
    or another number of records than of pages, raises an error.
    """
    spark, path = pages.sparkSession, scratch(pages.sparkSession)
    write_archives(plan_records(pages), path)
    read = cut(read_archives(spark, path, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "gap_reason"))
    gone = F.col("gap_reason").isNotNull()
    sound, gaps = read.agg(F.count(F.when(~gone, 1)), F.count(F.when(gone, 1))).first()
    if gaps or sound != (written := pages.count()):
        raise RuntimeError(f"{sound} records and {gaps} gaps read back, {written} pages written")
    return read.drop("gap_reason")
