"""WARC archives: a writer that deduplicates payloads and a reader that salvages damage.

Writing. Each page becomes one gzip member. Pages whose payload (of at least ``MIN_REVISIT``
bytes) equals that of a page with a larger id become revisits of it. Only digests take part in
the search for equals; payloads are not shuffled while the repeated digests fit a checked
broadcast. Spark's text writer lays the members end to end with an empty member as separator,
so archives go to any file system Spark knows, through its commit protocol. A new archive is
begun when one holds ``max_bytes``, so an archive has at most that and one record more.

Reading. Archives come as whole files, whose bytes are bounded when written here; members are
inflated one by one and records handed on in bounded batches. Members and plain records are checked: gzip checksum, version line, length, trailing
line ends, block and payload digests. After a failed check the reader looks for the next
valid member or version line, goes on from there, and logs the bytes between as a gap.

Defined results: null html is an empty payload; a null url becomes a urn; a null page_id is
never referred to if an equal page has an id; rows that repeat both the largest id and its
payload are all responses; empty tables give no records; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from navspark.llm.common import checked, scratch, written

MIN_REVISIT = 1000  #: bytes from which equal payloads are stored once
MAX_BYTES = 32 << 20  #: compressed bytes after which a new archive is begun
LEVEL = 4  #: of compression
DATE = "1970-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

_EMPTY_MEMBER = "1f8b08000000000000030300000000000000000000"[:40]
_STEP = 1 << 16
_MAGIC, _VERSION = b"\x1f\x8b\x08", b"WARC/1."
_UNSAFE = re.compile(rb"[\x00-\x20\x7f-\xff<>]")


def _b32(hex_digest: str) -> str:
    return base64.b32encode(bytes.fromhex(hex_digest)).decode()


def member(data: bytes, level: int = LEVEL) -> bytes:
    c = zlib.compressobj(level, zlib.DEFLATED, 31)
    return c.compress(data) + c.flush()


def record(kind: str, page_id, url: str | None, payload: bytes, digest: str, refers_to=None, date: str = DATE) -> bytes:
    """One record: the full HTTP message for a response, its header alone for a revisit."""
    name = f"urn:x-page:{'null' if page_id is None else page_id}"
    uri = _UNSAFE.sub(lambda m: b"%%%02X" % m[0][0], (url or name).encode()).decode()
    block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <{name}>", f"WARC-Date: {date}", f"WARC-Target-URI: {uri}", "Content-Type: application/http; msgtype=response"]
    if kind == "revisit":
        head += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:x-page:{refers_to}>"]
    else:
        block += payload
    head += [f"WARC-Payload-Digest: sha1:{_b32(digest)}", f"WARC-Block-Digest: sha1:{_b32(hashlib.sha1(block).hexdigest())}", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def plan_revisits(pages: DataFrame, min_bytes: int = MIN_REVISIT) -> DataFrame:
    """page_id, url, payload (binary), digest (hex) and refers_to of each page."""
    base = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary").alias("payload"))
    base = base.withColumn("digest", F.sha1("payload"))
    large = base.where(F.octet_length("payload") >= min_bytes)
    again = written(large.groupBy("digest").agg(F.max("page_id").alias("keeper"), F.count("*").alias("n")).where("n > 1").select("digest", "keeper"), "digests")
    refers = F.when(~F.col("page_id").eqNullSafe(F.col("keeper")), F.col("keeper"))
    return base.join(checked(again, 96), "digest", "left").select("page_id", "url", "payload", "digest", refers.alias("refers_to"))


def write_warc(pages: DataFrame, path: str, min_bytes: int = MIN_REVISIT, level: int = LEVEL, date: str = DATE, max_bytes: int = MAX_BYTES) -> None:
    """Archives below ``path``/archive=n; a task numbers its own from 0."""

    def run(batches):
        archive, size = 0, 0
        for b in batches:
            out, where = [], []
            for page_id, url, payload, digest, refers in zip(*(b.column(c) for c in ("page_id", "url", "payload", "digest", "refers_to")), strict=True):
                to = refers.as_py()
                out.append(member(record("response" if to is None else "revisit", page_id.as_py(), url.as_py(), payload.as_py(), digest.as_py(), to, date), level))
                if size >= max_bytes:
                    archive, size = archive + 1, 0
                where.append(archive)
                size += len(out[-1])
            yield pa.RecordBatch.from_arrays([pa.array(where, pa.int32()), pa.array(out, pa.binary())], ["archive", "value"])

    members = plan_revisits(pages, min_bytes).mapInArrow(run, "archive int, value binary")
    separator = bytes.fromhex(_EMPTY_MEMBER).decode("latin-1")
    members.select("archive", F.col("value").cast("string").alias("value")).write.option("lineSep", separator).option("encoding", "ISO-8859-1").partitionBy("archive").text(path)


class Broken(Exception):
    """Why bytes at a place are no record."""


def _inflate(buf: memoryview, at: int) -> tuple[bytes, int]:
    """Content and end of the gzip member at ``at``; fed in steps, so that nothing behind it is copied."""
    z, out, pos = zlib.decompressobj(31), [], at
    try:
        while not z.eof:
            if pos >= len(buf):
                raise Broken("member cut short")
            out.append(z.decompress(buf[pos : pos + _STEP]))
            pos = min(len(buf), pos + _STEP)
    except zlib.error as e:
        raise Broken(f"member: {str(e)[:60]}") from e
    return b"".join(out), pos - len(z.unused_data)


def _digest_hex(value: str) -> str | None:
    name, _, digest = value.partition(":")
    if name.lower() != "sha1":
        return None
    return digest.lower() if len(digest) == 40 else base64.b32decode(digest.upper()).hex()


def _parse(data: bytes, at: int) -> tuple[dict, int]:
    """The record at ``at`` and its end; raises ``Broken`` when a check fails."""
    head = data.find(b"\r\n\r\n", at, at + (1 << 20))
    if not data.startswith(_VERSION, at) or head < 0:
        raise Broken("no version line or header end")
    fields = {}
    for line in data[at:head].split(b"\r\n")[1:]:
        k, colon, v = line.partition(b":")
        if not colon:
            raise Broken("header line without colon")
        fields[k.strip().lower().decode("latin-1")] = v.strip().decode("utf-8", "replace")
    try:
        n = int(fields["content-length"])
        block, end = data[head + 4 : head + 4 + n], head + 4 + n
        if n < 0 or len(block) < n or data[end : end + 4] != b"\r\n\r\n":
            raise Broken("length doesn't lead to a record end")
        want = _digest_hex(fields["warc-block-digest"]) if "warc-block-digest" in fields else None
        if want and hashlib.sha1(block).hexdigest() != want:
            raise Broken("block digest")
        got = {"type": fields["warc-type"], "id": fields.get("warc-record-id", ""), "uri": fields.get("warc-target-uri"), "refers_to": fields.get("warc-refers-to"), "payload": block, "size": n, "digest": None}
        told = _digest_hex(fields["warc-payload-digest"]) if "warc-payload-digest" in fields else None
    except (KeyError, ValueError) as e:
        raise Broken(f"header: {e!r}"[:80]) from e
    if fields.get("content-type", "").startswith("application/http"):
        split = block.find(b"\r\n\r\n")
        if split < 0:
            raise Broken("no HTTP header end")
        got["payload"] = block[split + 4 :]
        size = re.search(rb"(?i)\r\ncontent-length:[ \t]*([0-9]+)", block[:split])
        got["size"] = int(size[1]) if got["type"] == "revisit" and size else len(got["payload"])
    got["digest"] = told if got["type"] == "revisit" else hashlib.sha1(got["payload"]).hexdigest()
    if told and got["digest"] != told:
        raise Broken("payload digest")
    return got, end + 4


def _plain(data: bytes, base: int) -> Iterator[tuple[int, int, dict | str]]:
    """Records and gaps of plain bytes."""
    at, gap, why = 0, None, ""
    while at < len(data):
        try:
            got, end = _parse(data, at)
        except Broken as e:
            if gap is None:
                gap, why = at, str(e)
            nxt = data.find(_VERSION, at + 1)
            at = len(data) if nxt < 0 else nxt
            continue
        if gap is not None:
            yield base + gap, base + at, why
            gap = None
        yield base + at, base + end, got
        at = end
    if gap is not None:
        yield base + gap, base + len(data), why


def salvage(data: bytes) -> Iterator[tuple[int, int, dict | str]]:
    """(start, end, record or reason of a gap) over the bytes of an archive, in order.

    Offsets of records in a compressed member are those of the member. A member that holds
    damaged records gives a gap with the member's offsets for each damaged stretch.
    """
    buf = memoryview(data)
    at, gap, why = 0, None, ""
    while at < len(data):
        found: list[tuple[int, int, dict | str]] = []
        try:
            if data.startswith(_MAGIC, at):
                content, end = _inflate(buf, at)
                found = [(at, end, x) for _, _, x in _plain(content, 0)]
                if content and all(isinstance(x[2], str) for x in found):
                    raise Broken(found[0][2])
            elif data.startswith(_VERSION, at):
                got, end = _parse(data, at)
                found = [(at, end, got)]
            elif data[at] in b"\r\n\0":
                end = at + 1
            else:
                raise Broken("neither member nor version line")
        except Broken as e:
            if gap is None:
                gap, why = at, str(e)
            nxt = [x for x in (data.find(_MAGIC, at + 1), data.find(_VERSION, at + 1)) if x >= 0]
            at = min(nxt, default=len(data))
            continue
        if gap is not None and found:
            yield gap, at, why
            gap = None
        yield from found
        at = end
    if gap is not None:
        yield gap, len(data), why


_READ = "archive string, start long, end long, record_type string, record_id string, uri string, refers_to string, payload_bytes long, payload_digest string, payload binary, gap string"


def read_warc(spark: SparkSession, path: str, with_payload: bool = True) -> DataFrame:
    """All records of the archives below ``path``; rows with record_type 'gap' log what was lost."""

    def run(batches):
        for b in batches:
            for name, content in zip(b.column("path"), b.column("content"), strict=True):
                rows, size = [], 0
                for start, end, x in salvage(content.as_py()):
                    row = {"archive": name.as_py(), "start": start, "end": end, "record_type": "gap", "gap": x if isinstance(x, str) else None}
                    if isinstance(x, dict):
                        row |= {"record_type": x["type"], "record_id": x["id"], "uri": x["uri"], "refers_to": x["refers_to"], "payload_bytes": x["size"], "payload_digest": x["digest"]}
                        if with_payload:
                            row["payload"], size = x["payload"], size + len(x["payload"])
                    rows.append(row)
                    if len(rows) >= 10_000 or size > 1 << 24:
                        yield batch(rows)
                        rows, size = [], 0
                if rows:
                    yield batch(rows)

    def batch(rows):
        names = [f.split()[0] for f in _READ.split(", ")]
        kinds = [{"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}[f.split()[1]] for f in _READ.split(", ")]
        return pa.RecordBatch.from_arrays([pa.array([r.get(n) for r in rows], k) for n, k in zip(names, kinds, strict=True)], names)

    return spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("path", "content").mapInArrow(run, _READ)


def op1_result(spark: SparkSession, pages: DataFrame) -> DataFrame:
    path = scratch(spark, "warc")
    write_warc(pages, path)
    got = read_warc(spark, path, with_payload=False)

    def page(c):
        return F.try_to_number(F.regexp_extract(c, r"^<urn:x-page:(-?[0-9]+)>$", 1), F.lit("S9999999999999999999")).cast("long")

    return got.select(page("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", page("refers_to").alias("refers_to"), "gap")


OP1_SQL = """
SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest,
  CASE WHEN strlen(coalesce(html, '')) >= 1000 AND page_id IS DISTINCT FROM m THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN strlen(coalesce(html, '')) >= 1000 AND page_id IS DISTINCT FROM m THEN m END AS refers_to, CAST(NULL AS VARCHAR) AS gap
FROM (SELECT *, max(page_id) OVER (PARTITION BY coalesce(html, '')) AS m FROM pages)
"""
