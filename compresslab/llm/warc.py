"""WARC archives: write pages as segmented records, read them back and reassemble.

Writing. Of pages with equal payloads the one with the smallest page_id becomes a response, the others
become revisit records that name it. A response's HTTP message carries the payload in chunked transfer
framing; if the message is longer than `segment` bytes it is cut into a response record and continuation
records. The archives are gzip files in the shared folder, written by Spark's own text sink (the four
bytes that end every record are the sink's line separator), so any Hadoop store can hold them.

Reading. Files come in as binary rows of a bounded size and are parsed record by record. Whole records are
decoded where they are; segments are grouped by origin identifier, ordered by segment number, checked to
be gapless and of the stated total length, and then decoded. A digest that does not match raises an error.

Each file is one gzip member, as Spark's sink writes it: whole files are read, records cannot be sought by offset. Revisits
name their response by page (Refers-To-Page-Id) and by its target and payload digest, as the standard's revisit profile asks.

A null html is an empty payload; a null url is written as an empty target. Rows that share a page_id and the smallest payload
are all responses. A null page_id is kept as such. Very long pages become as many segments as they need; a task must hold
the longest. Empty tables give no rows; columns other than page_id, url and html are not read.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

END = b"\r\n\r\n"
SEGMENT, FRAME, FILE_RECORDS, SALTS = 16 << 10, 4 << 10, 4000, 16
DATE = "2024-01-01T00:00:00Z"
NAMESPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def chunked(payload: bytes, frame: int = FRAME) -> bytes:
    """Chunked transfer framing: sizes in hex, a zero chunk at the end."""
    parts = []
    for i in range(0, len(payload), frame):
        piece = payload[i : i + frame]
        parts += [b"%x\r\n" % len(piece), piece, b"\r\n"]
    return b"".join([*parts, b"0\r\n\r\n"])


def unchunked(body: bytes) -> bytes:
    parts, at = [], 0
    while True:
        line = body.index(b"\r\n", at)
        n = int(body[at:line].split(b";")[0], 16)
        at = line + 2
        if n == 0:
            return b"".join(parts)
        if body[at + n : at + n + 2] != b"\r\n":
            raise ValueError("broken chunk framing")
        parts.append(body[at : at + n])
        at += n + 2


def record(kind: str, record_id: str, block: bytes, fields: dict) -> bytes:
    """A record without the four bytes that end it."""
    head = {"WARC-Type": kind, "WARC-Record-ID": f"<urn:uuid:{record_id}>", "WARC-Date": DATE, "WARC-Block-Digest": f"sha1:{digest(block)}", "Content-Length": len(block)} | fields
    return b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head.items() if v is not None).encode() + b"\r\n" + block


def _one_line(url: str | None) -> str:
    return "".join(c for c in url or "" if c not in "\r\n")


def page_records(page_id, row: int, url, payload: bytes, payload_digest: str, original, segment: int = SEGMENT, frame: int = FRAME, original_url=None) -> list[bytes]:
    """All records of one page. original: the response's page_id if this is a revisit, else None."""
    name = str(uuid.uuid5(NAMESPACE, f"{page_id}:{row}"))
    fields = {"WARC-Target-URI": _one_line(url), "Page-Id": page_id, "WARC-Payload-Digest": f"sha1:{payload_digest}"}
    if original is not None:
        block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
        profile = {"WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", "Refers-To-Page-Id": original, "WARC-Refers-To-Target-URI": _one_line(original_url), "WARC-Refers-To-Date": DATE, "Content-Type": "application/http;msgtype=response"}
        return [record("revisit", name, block, fields | profile)]
    message = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n" + chunked(payload, frame)
    fields["Content-Type"] = "application/http;msgtype=response"
    if len(message) <= segment:
        return [record("response", name, message, fields)]
    cuts = range(0, len(message), segment)
    out = []
    for n, at in enumerate(cuts, 1):
        own = {"WARC-Segment-Number": n}
        if n > 1:
            own["WARC-Segment-Origin-ID"] = f"<urn:uuid:{name}>"
        if n == len(cuts):
            own["WARC-Segment-Total-Length"] = len(message)
        part = str(uuid.uuid5(NAMESPACE, f"{name}:{n}"))
        out.append(record("response" if n == 1 else "continuation", name if n == 1 else part, message[at : at + segment], own | (fields if n == 1 else {})))
    return out


def write(pages: DataFrame, path: str, segment: int = SEGMENT, frame: int = FRAME, least: int = 0) -> None:
    """Write archives under path. Payloads of at least `least` bytes are stored once."""
    html = F.coalesce(F.col("html"), F.lit(""))
    named = pages.select("page_id", "url", "html", F.sha1(html).alias("sha"), F.octet_length(html).alias("n"))
    # only payloads that occur more than once need a look at the others
    repeated = (
        named.where(F.col("n") >= least).groupBy("sha", "n").agg(F.min("page_id").alias("first_id"), F.min_by("url", F.struct("page_id", "url")).alias("first_url"), F.count("*").alias("copies"))
        .where("copies > 1").select("sha", "n", "first_id", "first_url")
    )
    # a payload that very many pages share (the empty one, say) is spread over SALTS keys
    salted = named.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int"))
    met = salted.join(repeated.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), ["sha", "n", "salt"], "left")
    other = ~F.col("page_id").eqNullSafe(F.col("first_id"))
    rows = met.select("page_id", "url", "html", "sha", F.when(other, F.col("first_id")).alias("original"), F.when(other, F.col("first_url")).alias("original_url"), F.monotonically_increasing_id().alias("row"))

    def run(batches):
        for b in batches:
            for piece in C.small_batches(b, "html", 4 << 20):
                out = []
                for r in piece.to_pylist():
                    payload = (r["html"] or "").encode("utf-8")
                    sha = base64.b32encode(bytes.fromhex(r["sha"])).decode()
                    out += page_records(r["page_id"], r["row"], r["url"], payload, sha, r["original"], segment, frame, r["original_url"])
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], names=["record"])

    records = rows.mapInArrow(run, C.schema(record=C.BINARY))
    records.select(F.col("record").cast("string").alias("value")).write.option("lineSep", END.decode()).option("compression", "gzip").option("maxRecordsPerFile", FILE_RECORDS).text(path)


def parse(data: bytes):
    """(fields, block) of every record of an archive's bytes."""
    at = 0
    while at < len(data):
        if data[at : at + 5] != b"WARC/":
            raise ValueError(f"no record at byte {at}")
        stop = data.index(END, at)
        lines = data[at:stop].split(b"\r\n")[1:]
        fields = {k.decode().lower(): v.strip().decode() for k, _, v in (line.partition(b":") for line in lines)}
        n = int(fields["content-length"])
        block = data[stop + 4 : stop + 4 + n]
        if len(block) != n or data[stop + 4 + n : stop + 8 + n] != END:
            raise ValueError("record's length does not hold")
        if fields.get("warc-block-digest", "").removeprefix("sha1:") not in ("", digest(block)):
            raise ValueError("block digest does not hold")
        yield fields, block
        at = stop + 8 + n


def decode_message(message: bytes) -> bytes:
    head, _, body = message.partition(END)
    return unchunked(body) if b"transfer-encoding: chunked" in head.lower() else body


_PAGE = [("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())]
_PART = [("origin", pa.string()), ("number", pa.int32()), ("total", pa.int64()), ("block", pa.binary()), ("stated", pa.string())]


def _number(text):
    return None if text in (None, "None") else int(text)


def _checked(payload: bytes, stated: str) -> str:
    found = digest(payload)
    if found != stated.removeprefix("sha1:"):
        raise ValueError(f"payload digest {found} is not {stated}")
    return found


def read(spark: SparkSession, path: str, payloads: bool = True) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to and payload (null for revisits) of all archives under path."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").load(path).select("content")

    def run(batches):
        names = [n for n, _ in _PAGE + _PART]
        types = [t for _, t in _PAGE + _PART]
        for b in batches:
            for item in b.column("content"):
                rows, held = [], 0
                for f, block in parse(gzip.decompress(item.as_py())):
                    page = _number(f.get("page-id"))
                    if f["warc-type"] == "revisit":
                        http = dict(line.split(b": ", 1) for line in block.split(b"\r\n") if b": " in line)
                        rows.append((page, int(http[b"Content-Length"]), f["warc-payload-digest"].removeprefix("sha1:"), "revisit", _number(f["refers-to-page-id"]), None, None, None, None, None, None))
                    elif "warc-segment-number" in f:
                        rows.append((page, None, None, None, None, None, f.get("warc-segment-origin-id", f["warc-record-id"]), int(f["warc-segment-number"]), _number(f.get("warc-segment-total-length")), block, f.get("warc-payload-digest")))
                    else:
                        payload = decode_message(block)
                        rows.append((page, len(payload), _checked(payload, f["warc-payload-digest"]), "response", None, payload if payloads else None, None, None, None, None, None))
                    held += len(block)
                    if held > 4 << 20:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=names)
                        rows, held = [], 0
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=names)

    page_schema = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"
    parsed = C.materialize(files.mapInArrow(run, page_schema + ", origin string, number int, total long, block binary, stated string"), "warc-parsed")
    names = [n for n, _ in _PAGE]
    whole = parsed.where("origin is null").select(*names)
    parts = (
        parsed.where("origin is not null").groupBy("origin")
        .agg(F.max("page_id").alias("page_id"), F.max("total").alias("total"), F.max("stated").alias("stated"), F.sort_array(F.collect_list(F.struct("number", "block"))).alias("parts"))
        .select("page_id", "total", "stated", "parts")
    )

    def reassemble(batches):
        for b in batches:
            rows = []
            for r in b.to_pylist():
                if [p["number"] for p in r["parts"]] != list(range(1, len(r["parts"]) + 1)):
                    raise ValueError("a segment is missing or there twice")
                message = b"".join(p["block"] for p in r["parts"])
                if len(message) != r["total"]:
                    raise ValueError(f"segments hold {len(message)} bytes, not {r['total']}")
                payload = decode_message(message)
                rows.append((r["page_id"], len(payload), _checked(payload, r["stated"]), "response", None, payload if payloads else None))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*rows), _PAGE)], names=names)

    return whole.unionByName(parts.mapInArrow(reassemble, page_schema))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = C.scratch_path(spark, "warc")
    write(C.table(spark, sf_dir, "pages"), path)
    return read(spark, path, payloads=False).drop("payload")
