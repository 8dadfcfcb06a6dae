"""WARC archives: a writer, and a reader that salvages what damaged archives still hold.

The writer makes one gzip member for each record, or plain records, in archives under a folder that every
executor can write. Each task attempt writes files under names of its own and returns them; only files named in
the manifest are read, so a task that is run again leaves nothing behind that counts.

The reader checks each record: the member's checksum, the version line, the header block, the block length, the
closing blank lines, and the payload digest where there is a payload. After a failed check it searches for the
next valid member (compressed) or version line (plain), goes on from there, and logs the bytes between as a
quarantined gap. As any offset can serve as a start in that way, archives are also read in byte ranges in
parallel: a range owns the records that begin in it. It also tells where its first good record starts and its last
one ends; the gaps between ranges, and at the ends of an archive, are derived from those.

Defined cases: a null payload is empty; a null page id is written as such and never becomes what others refer
to; of repeated rows of the smallest id all are responses; an empty table gives no archives and an empty result;
line ends in addresses are escaped; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from memojoin.llm.common import read, scratch

#: Payloads below this size are never replaced by a reference.
MIN_REVISIT_BYTES = 100
ARCHIVE_BYTES = 256 << 20
RANGE_BYTES = 32 << 20
CHUNK = 1 << 20
#: Fixed values of the format.
VERSION, END, MAGIC = b"WARC/1.1\r\n", b"\r\n\r\n", b"\x1f\x8b\x08"
PROFILE = b"http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
MANIFEST = "path string, bytes long, records long"
RECORDS = "kind string, path string, offset long, length long, reason string, page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary"


def _urn(page_id: int | None) -> bytes:
    return f"<urn:page:{'null' if page_id is None else page_id}>".encode()


def record(page_id, url, payload: bytes, digest: str, refers_to=None) -> bytes:
    """One response record, or a revisit record (HTTP header without its payload) where refers_to is given."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if refers_to is not None else http + payload
    fields = [(b"WARC-Type", b"response" if refers_to is None else b"revisit"), (b"WARC-Record-ID", _urn(page_id)), (b"WARC-Date", b"1970-01-01T00:00:00Z"), (b"Content-Type", b"application/http; msgtype=response"), (b"WARC-Payload-Digest", b"sha256:" + digest.encode())]
    if url is not None:
        fields.append((b"WARC-Target-URI", url.replace("\r", "%0D").replace("\n", "%0A").encode()))
    if refers_to is not None:
        fields += [(b"WARC-Refers-To", _urn(refers_to)), (b"WARC-Profile", PROFILE)]
    fields.append((b"Content-Length", b"%d" % len(block)))
    return VERSION + b"".join(k + b": " + v + b"\r\n" for k, v in fields) + b"\r\n" + block + END


def with_roles(pages: DataFrame) -> DataFrame:
    """page_id, url, payload, digest, refers_to: which rows revisit an equal payload of a smaller id."""
    payload = F.coalesce(F.col("html").cast("binary"), F.lit(b""))
    rows = pages.select("page_id", "url", payload.alias("payload"), F.sha2(payload, 256).alias("digest"))
    keys = pages.select("page_id", F.sha2(payload, 256).alias("digest"), F.octet_length(payload).alias("n")).where(F.col("n") >= MIN_REVISIT_BYTES)
    firsts = keys.groupBy("digest").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1 AND first IS NOT NULL").drop("n")
    refers = F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first"))
    return rows.join(firsts, "digest", "left").withColumn("refers_to", refers).select("page_id", "url", "payload", "digest", "refers_to")


def write(roles: DataFrame, folder: str, compressed: bool = True) -> DataFrame:
    """Write the rows of with_roles(); returns the manifest, read back from the folder."""
    spark = roles.sparkSession

    def run(batches):
        fs, root = pafs.FileSystem.from_uri(folder)
        fs.create_dir(root, recursive=True)
        sink, path, size, count, done = None, "", 0, 0, []
        for batch in batches:
            for r in batch.to_pylist():
                if sink is None:
                    path, size, count = f"{root}/{uuid.uuid4().hex}.warc" + ".gz" * compressed, 0, 0
                    sink = fs.open_output_stream(path, compression=None)
                data = record(r["page_id"], r["url"], r["payload"], r["digest"], r["refers_to"])
                if compressed:
                    z = zlib.compressobj(6, zlib.DEFLATED, 31)
                    data = z.compress(data) + z.flush()
                sink.write(data)
                size, count = size + len(data), count + 1
                if size >= ARCHIVE_BYTES:
                    sink.close()
                    done.append((path, size, count))
                    sink = None
        if sink is not None:
            sink.close()
            done.append((path, size, count))
        yield pa.RecordBatch.from_arrays([pa.array([d[k] for d in done], t) for k, t in enumerate((pa.string(), pa.int64(), pa.int64()))], ["path", "bytes", "records"])

    at = folder.rstrip("/") + "-manifest"
    roles.mapInArrow(run, MANIFEST).write.parquet(at)
    return spark.read.schema(MANIFEST).parquet(at)


class Damaged(ValueError):
    """A record that fails a check."""


def parse(data: bytes) -> dict:
    """The fields of one whole record, after all checks."""
    head, found, rest = data.partition(END)
    lines = head.split(b"\r\n")
    if not found or not re.fullmatch(rb"WARC/1\.\d", lines[0]):
        raise Damaged("no version line or header end")
    fields = {}
    for line in lines[1:]:
        name, colon, value = line.partition(b":")
        if not colon:
            raise Damaged("header line without a colon")
        fields[name.strip().lower()] = value.strip()
    if not fields.get(b"content-length", b"").isdigit() or b"warc-type" not in fields:
        raise Damaged("no length or type")
    n = int(fields[b"content-length"])
    if len(rest) != n + len(END) or rest[n:] != END:
        raise Damaged("block length does not match")
    http, _, payload = rest[:n].partition(END)
    kind = fields[b"warc-type"].decode("latin-1")
    said = re.search(rb"(?i)\ncontent-length: *(\d+)", http)
    digest = fields.get(b"warc-payload-digest", b"").removeprefix(b"sha256:").decode("latin-1")
    if kind != "revisit" and digest and hashlib.sha256(payload).hexdigest() != digest:
        raise Damaged("payload digest does not match")
    number = lambda k: int(m[1]) if (m := re.fullmatch(rb"<urn:page:(-?\d+)>", fields.get(k, b""))) else None
    url = fields.get(b"warc-target-uri")
    return {
        "page_id": number(b"warc-record-id"), "url": url.decode("utf-8", "replace") if url is not None else None, "record_type": kind, "refers_to": number(b"warc-refers-to"),
        "payload_bytes": int(said[1]) if kind == "revisit" and said else len(payload), "payload_digest": digest or hashlib.sha256(payload).hexdigest(), "payload": payload if kind != "revisit" else None,
    }


#: Fixed value: how a record begins.
MARK = b"WARC/1."


class Bytes:
    """A forward window over a file: keeps only what lies at or behind the position in use."""

    def __init__(self, f, start: int):
        self.f, self.start, self.data, self.ended = f, start, b"", False
        f.seek(start)

    def more(self) -> bool:
        if not self.ended:
            got = self.f.read(max(CHUNK, len(self.data)))  # twice as much each time
            self.ended = not got
            self.data += got
        return not self.ended

    def peek(self, offset: int, n: int) -> bytes:
        """n bytes from an offset on, without reading what lies before."""
        self.f.seek(offset)
        got = self.f.read(n)
        self.f.seek(self.start + len(self.data))
        return got

    def drop_to(self, offset: int) -> None:
        self.data = self.data[offset - self.start :]
        self.start = offset


def _member(w: Bytes, at: int) -> tuple[bytes, int]:
    """The content of the gzip member at an offset, and the offset behind it."""
    z, k, out = zlib.decompressobj(31), at - w.start, []
    while not z.eof:
        if k >= len(w.data) and not w.more():
            raise Damaged("member cut short")
        try:
            out.append(z.decompress(w.data[k:]))
        except zlib.error as e:
            raise Damaged(f"member: {str(e)[:60]}") from None
        k = len(w.data) - len(z.unused_data)
        if out and len(out) == 1 and out[0] and not out[0].startswith(MARK[: len(out[0])]):
            raise Damaged("member holds no record")
    return b"".join(out), w.start + k


def _plain(w: Bytes, at: int) -> tuple[bytes, int]:
    """The plain record at an offset, and the offset behind it."""
    k = at - w.start
    while (e := w.data.find(END, k)) < 0:
        if e < 0 and (len(w.data) - k > CHUNK or not w.more()):
            raise Damaged("no header end")
    m = re.search(rb"(?i)\r\ncontent-length: *(\d+)(?=\r\n|$)", w.data[k:e])
    if not m or not w.data.startswith(MARK, k):
        raise Damaged("no version line or length")
    end = e + len(END) + int(m[1]) + len(END)
    # a length is believed, and read, only if a record's end stands there, and the file's or another record behind
    edge = w.peek(w.start + end - len(END), len(END) + len(MARK))
    if len(edge) < len(END):
        raise Damaged("record cut short")
    if not edge.startswith(END) or not MARK.startswith(edge[len(END) :]):
        raise Damaged("block length does not match")
    while len(w.data) < end and w.more():
        pass
    return w.data[k:end], w.start + end


def salvage_range(f, path: str, start: int, end: int, span: bool = False) -> Iterator[dict]:
    """Records that begin in [start, end), and gaps of bytes that no record covers.

    With span, only gaps between records of the range are given, and at the end a row of kind span: where the first
    record starts (offset) and the last one ends (length), both null without any, and why a record behind the last
    one failed ("" if none did).
    """
    f.seek(0)
    compressed = path.endswith(".gz") or f.read(2) == MAGIC[:2]
    mark, take = (MAGIC, _member) if compressed else (MARK, _plain)
    w, at, gap, why = Bytes(f, start), start, None, ""
    searching, first, last = start > 0, None, None
    while True:
        if searching:
            while (k := w.data.find(mark, max(0, at - w.start))) < 0:
                at = max(at, w.start + len(w.data) - len(mark) + 1)
                w.drop_to(min(at, w.start + len(w.data)))
                if at >= end or not w.more():
                    k = -1
                    break
            if k < 0:
                break
            at = w.start + k
        elif at - w.start >= len(w.data) and not w.more():
            break
        if at >= end:
            break
        w.drop_to(at)
        try:
            data, after = take(w, at)
            fields = parse(data)
        except Damaged as e:
            if gap is None and ((start == 0 and not span) or not searching):
                gap, why = at, str(e)
            at, searching = at + 1, True
            continue
        if gap is not None:
            if last is not None or not span:
                yield {"kind": "gap", "path": path, "offset": gap, "length": at - gap, "reason": why}
            gap = None
        first, last = at if first is None else first, after
        yield {"kind": "record", "path": path, "offset": at, "length": after - at} | fields
        at, searching = after, False
    if span:
        yield {"kind": "span", "path": path, "offset": first, "length": last, "reason": why if gap is not None else ""}
    elif gap is not None:
        stop = min(end, w.start + len(w.data)) if not w.ended else w.start + len(w.data)
        yield {"kind": "gap", "path": path, "offset": gap, "length": max(stop, gap + 1) - gap, "reason": why}


def _scan(manifest: DataFrame, folder: str, payloads: bool, range_bytes: int, spans: bool) -> DataFrame:
    """Records and inner gaps of all ranges, or the spans of the ranges: with start in page_id, file size in payload_bytes."""
    names = [c.split()[0] for c in RECORDS.split(", ")]

    def run(batches):
        fs, _ = pafs.FileSystem.from_uri(folder)
        schema = pa.schema([(c, {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}[t]) for c, t in (x.split() for x in RECORDS.split(", "))])
        rows, held = [], 0
        for batch in batches:
            for part in batch.to_pylist():
                with fs.open_input_file(part["path"]) as f:
                    for r in salvage_range(f, part["path"], part["start"], part["start"] + range_bytes, span=True):
                        if (r["kind"] == "span") != spans:
                            continue
                        row = dict.fromkeys(names) | r
                        if spans:
                            row |= {"page_id": part["start"], "payload_bytes": f.size()}
                        held += len(row["payload"] or b"")
                        if not payloads:
                            row["payload"] = None
                        rows.append(row)
                        if len(rows) >= 2000 or held > 16 << 20:
                            yield pa.RecordBatch.from_pylist(rows, schema)
                            rows, held = [], 0
        if rows:
            yield pa.RecordBatch.from_pylist(rows, schema)

    starts = F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.col("bytes") - 1, F.lit(0)), F.lit(range_bytes).cast("long")))
    spark: SparkSession = manifest.sparkSession
    parts = manifest.select("path", starts.alias("start"))
    return parts.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "path", "start").mapInArrow(run, RECORDS)


def salvage(manifest: DataFrame, folder: str, payloads: bool = True, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """Records and quarantined gaps (kind) of all archives in the manifest, read in byte ranges.

    Gaps that touch a range's border come from a second reading, which a plan that asks for records only leaves out.
    """
    spans = _scan(manifest, folder, False, range_bytes, True).selectExpr("path", "page_id AS start", "offset AS first", "length AS last", "reason", "payload_bytes AS size")
    # behind the last range stands one that starts where the archive ends
    ends = spans.join(manifest.select("path", "bytes"), "path").groupBy("path").agg(F.min(F.least("bytes", "size")).alias("first"))
    spans = spans.where("first IS NOT NULL").drop("size").unionByName(ends.select("path", F.lit((1 << 63) - 1).alias("start"), "first", F.lit(None).cast("long").alias("last"), F.lit("").alias("reason")))
    before = Window.partitionBy("path").orderBy("start").rowsBetween(Window.unboundedPreceding, -1)
    spans = spans.withColumn("from", F.coalesce(F.max("last").over(before), F.lit(0))).withColumn("why", F.last("reason").over(before))
    columns = {"kind": F.lit("gap"), "path": F.col("path"), "offset": F.col("from"), "length": F.col("first") - F.col("from"), "reason": F.coalesce(F.expr("nullif(why, '')"), F.lit("no record at a range's start"))}
    gaps = spans.where(F.col("first") > F.col("from"))
    rest = [F.lit(None).cast(t).alias(c) for c, t in (x.split() for x in RECORDS.split(", ")[len(columns) :])]
    gaps = gaps.select(*[v.alias(c) for c, v in columns.items()], *rest)
    return _scan(manifest, folder, payloads, range_bytes, False).unionByName(gaps)


def op3_warc(spark, sf_dir: str) -> DataFrame:
    folder = scratch(spark, "warc")
    manifest = write(with_roles(read(spark, sf_dir, "pages")), folder)
    found = salvage(manifest, folder, payloads=False).where("kind = 'record'")
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP3_SQL = f"""
WITH p AS (SELECT page_id, strlen(coalesce(html, ''))::BIGINT AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
f AS (SELECT payload_digest, min(page_id) AS first FROM p WHERE payload_bytes >= {MIN_REVISIT_BYTES} GROUP BY payload_digest)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN first IS NOT NULL AND page_id IS DISTINCT FROM first THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN page_id IS DISTINCT FROM first THEN first END AS refers_to
FROM p LEFT JOIN f USING (payload_digest)"""
