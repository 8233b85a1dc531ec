"""Content-addressed web archive.

Payload bytes are written once under their SHA-256 (length and SHA-1 beside it), exact
record headers in a table of their own. Records come back through a join on the digest and are exported as WARC files
(whole-file gzip), which are read back by a parser of their own that checks every payload digest.
Of equal payloads of at least `min_revisit` bytes, the record with the largest page_id is
the response and the others revisit it; shorter payloads are responses all, yet stored once.

Defined results: null html is an empty payload; a null url becomes an empty target; a null
page_id is never a revisit; repeated rows give repeated records, each with an id of its own (equal ids are all
responses if theirs is the largest); an empty table gives an empty archive; other columns
of the input are ignored whatever their names; a page of any length is one record.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import stored

CRLF = "\r\n"
HTTP_HEAD = f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}{CRLF}"
#: A file takes records until it holds this many bytes before compression; SPLIT records of one payload go to a task.
FILE_BYTES, SPLIT = 16 << 20, 4096


def _record_id() -> Column:
    """An id for each row, however many are equal: from the page's number and the row's place."""
    h = F.md5(F.concat_ws(":", F.coalesce(F.col("page_id").cast("string"), F.lit("null")), F.monotonically_increasing_id()))
    part = lambda a, n: F.substring(h, a, n)
    return F.concat(F.lit("urn:uuid:"), part(1, 8), F.lit("-"), part(9, 4), F.lit("-"), part(13, 4), F.lit("-"), part(17, 4), F.lit("-"), part(21, 12))


def write_archive(pages: DataFrame, path: str, min_revisit: int = 1000, date: str = "2024-01-01T00:00:00Z") -> None:
    """Writes {path}/payloads and {path}/headers. Equal payloads merge map-side first, so a
    payload that a third of all pages share moves once per map task."""
    spark = pages.sparkSession
    payload = F.coalesce(F.encode(F.col("html"), "UTF-8"), F.lit(b""))
    rec = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce("url", F.lit("")).alias("url"), payload.alias("payload"))
    rec = rec.select("page_id", "url", "payload", F.sha2("payload", 256).alias("sha256"), F.octet_length("payload").cast("long").alias("n"))
    # Ids depend on the row's place: written once, so that whoever refers to a record sees the same id.
    stub = stored(rec.select("page_id", "url", "sha256", "n", _record_id().alias("record_id")), "records")
    (
        rec.groupBy("sha256", "n").agg(F.first("payload").alias("payload"))
        .select("sha256", "n", F.sha1("payload").alias("sha1"), "payload")
        .write.option("compression", "zstd").parquet(f"{path}/payloads")
    )
    kept = stub.groupBy("sha256", "n").agg(F.max(F.struct("page_id", "record_id")).alias("k"))
    kept = kept.join(spark.read.parquet(f"{path}/payloads").select("sha256", "n", "sha1"), ["sha256", "n"])
    h = stub.join(kept, ["sha256", "n"])
    revisit = F.coalesce((F.col("n") >= min_revisit) & (F.col("page_id") < F.col("k.page_id")), F.lit(False))
    line = lambda k, v: F.concat(F.lit(f"{k}: "), v, F.lit(CRLF))
    size = F.lit(len(HTTP_HEAD)) + F.when(revisit, F.lit(0)).otherwise(F.col("n"))
    header = F.concat(
        F.lit(f"WARC/1.1{CRLF}"),
        line("WARC-Type", F.when(revisit, F.lit("revisit")).otherwise(F.lit("response"))),
        line("WARC-Record-ID", F.concat(F.lit("<"), F.col("record_id"), F.lit(">"))),
        line("WARC-Date", F.lit(date)),
        line("WARC-Target-URI", F.regexp_replace("url", r"[\r\n]", "")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("sha1"))),
        F.when(F.col("page_id").isNotNull(), line("WARC-Page-ID", F.col("page_id").cast("string"))).otherwise(F.lit("")),
        line("Content-Type", F.lit("application/http; msgtype=response")),
        F.when(revisit, F.concat(
            line("WARC-Profile", F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
            line("WARC-Refers-To", F.concat(F.lit("<"), F.col("k.record_id"), F.lit(">"))),
        )).otherwise(F.lit("")),
        line("Content-Length", size.cast("string")),
        F.lit(CRLF),
    )
    h.select("page_id", "record_id", header.alias("header"), revisit.alias("revisit"), "sha256", "n").write.option("compression", "zstd").parquet(f"{path}/headers")


def read_payloads(spark: SparkSession, path: str) -> DataFrame:
    """(sha256, n, sha1, payload, good): good says that bytes, digests and length agree again."""
    p = spark.read.parquet(f"{path}/payloads")
    sha1, n = F.sha1("payload"), F.octet_length("payload").cast("long")
    good = (F.sha2("payload", 256) == F.col("sha256")) & (sha1 == F.col("sha1")) & (n == F.col("n"))
    return p.select("sha256", n.alias("n"), sha1.alias("sha1"), "payload", good.alias("good"))


def reconstruct(spark: SparkSession, path: str) -> DataFrame:
    """(page_id, record_id, record): the original record bytes, header to closing blank lines. Only responses need their payload;
    a payload of many responses is dealt to several tasks."""
    h = spark.read.parquet(f"{path}/headers")
    p = spark.read.parquet(f"{path}/payloads").select("sha256", "n", "payload")
    full = h.where(~F.col("revisit"))
    often = F.broadcast(full.groupBy("sha256", "n").agg(F.count("*").alias("c")).where(F.col("c") > SPLIT)
                        .select("sha256", "n", F.ceil(F.col("c") / SPLIT).cast("int").alias("cuts")).withColumnsRenamed({"sha256": "os", "n": "on"}))  # at most a row for SPLIT records
    same = lambda d: (d["sha256"] == F.col("os")) & (d["n"] == F.col("on"))
    full = full.join(often, same(full), "left").withColumn("cut", F.pmod(F.xxhash64("record_id"), F.coalesce("cuts", F.lit(1))).cast("int")).drop("os", "on", "cuts")
    p = p.join(often, same(p), "left").withColumn("cut", F.explode(F.sequence(F.lit(0), F.coalesce("cuts", F.lit(1)) - 1))).drop("os", "on", "cuts")
    end = F.lit(f"{CRLF}{CRLF}".encode())
    record = lambda body: F.concat(F.encode("header", "UTF-8"), F.lit(HTTP_HEAD.encode()), *body, end).alias("record")
    again = h.where("revisit").select("page_id", "record_id", record([]))
    return full.join(p, ["sha256", "n", "cut"]).select("page_id", "record_id", record([F.col("payload")])).unionByName(again)


def export_warc(spark: SparkSession, path: str, out: str, file_bytes: int = FILE_BYTES, tasks: int | None = None) -> None:
    """WARC files, through Spark's own text writer: a row of the table written is a file, which begins with a warcinfo record
    and takes records until it holds file_bytes, so that a reader needs no more than that and one record at once."""

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[bytes] = []
        size = 0

        def whole() -> pa.RecordBatch:
            about = f"software: content-addressed archive{CRLF}format: WARC File Format 1.1{CRLF}".encode()
            name = hashlib.md5(held[0]).hexdigest()
            head = f"WARC/1.1{CRLF}WARC-Type: warcinfo{CRLF}WARC-Record-ID: <urn:uuid:{name[:8]}-{name[8:12]}-{name[12:16]}-{name[16:20]}-{name[20:]}>{CRLF}WARC-Date: 2024-01-01T00:00:00Z{CRLF}Content-Type: application/warc-fields{CRLF}Content-Length: {len(about)}{CRLF}{CRLF}"
            data = b"".join([head.encode(), about, b"\r\n\r\n", *held])
            return pa.RecordBatch.from_arrays([pa.array([data[:-4]], pa.binary())], ["value"])  # the writer ends each row so

        for b in batches:
            for x in b.column(0):
                r = x.as_py()
                if held and size + len(r) > file_bytes:
                    yield whole()
                    held, size = [], 0
                held.append(r)
                size += len(r)
        if held:
            yield whole()

    files = reconstruct(spark, path).select("record").mapInArrow(fill, "value binary").select(F.col("value").cast("string").alias("value"))
    files.write.option("lineSep", f"{CRLF}{CRLF}").option("maxRecordsPerFile", 1).option("compression", "gzip").text(out)


def _members(data: bytes) -> bytes:
    """The bytes of a gzip file of any number of members; other bytes as they are."""
    if data[:2] != b"\x1f\x8b":
        return data
    out = []
    while data[:2] == b"\x1f\x8b":
        z = zlib.decompressobj(31)
        out.append(z.decompress(data))
        if not z.eof:
            raise ValueError("a compressed archive file ends too early")
        data = z.unused_data.lstrip(b"\0")
    return b"".join(out)


def _digest_holds(said: str, payload: bytes) -> bool | None:
    """Whether `algorithm:value` (hexadecimal or base 32) is the payload's; None where the algorithm is not known."""
    kind, _, value = said.partition(":")
    try:
        d = hashlib.new(kind.strip().lower().replace("-", ""), payload)
    except (ValueError, TypeError):
        return None
    value = value.strip()
    return value.lower() == d.hexdigest() or value.upper().rstrip("=") == base64.b32encode(d.digest()).decode().rstrip("=")


RECORD = "record_id string, record_type string, uri string, payload_digest string, refers_to string, page_id long, payload binary, digest_holds boolean"
_TYPES = [pa.string()] * 5 + [pa.int64(), pa.binary(), pa.bool_()]


def parse(data: bytes) -> Iterator[tuple]:
    """Records of one file, as RECORD: header names in any case, values with any space about them and folded over lines, lines
    ended by CRLF or LF, any number of blank lines between records. What breaks the framing raises."""
    data, at = _members(data), 0
    head_end = re.compile(rb"\r?\n\r?\n")
    while True:
        while data[at : at + 1] in (b"\r", b"\n"):
            at += 1
        if at >= len(data):
            return
        end = head_end.search(data, at)
        if not data.startswith(b"WARC/", at) or end is None:
            raise ValueError(f"no record begins at byte {at}")
        head: dict[str, str] = {}
        key = None
        for line in data[at : end.start()].decode("utf-8", "replace").replace("\r\n", "\n").split("\n")[1:]:
            if line[:1] in " \t" and key:
                head[key] += " " + line.strip()
                continue
            name, colon, value = line.partition(":")
            if colon:  # other lines say nothing
                key = name.strip().lower()
                head[key] = value.strip()
        size = int(head["content-length"])
        block = data[end.end() : end.end() + size]
        if len(block) != size:
            raise ValueError(f"the record at byte {at} ends too early")
        at = end.end() + size
        kind = head.get("warc-type", "").lower()
        http = head.get("content-type", "").lower().startswith("application/http")
        first = head_end.search(block) if http else None
        payload = block[first.end() :] if first else block
        said = head.get("warc-payload-digest")
        bare = lambda x: x.strip("<>") if x is not None else None
        holds = None if said is None or kind == "revisit" else _digest_holds(said, payload)
        page = head.get("warc-page-id", "")
        yield bare(head.get("warc-record-id")), kind, head.get("warc-target-uri"), said, bare(head.get("warc-refers-to")), int(page) if re.fullmatch(r"-?\d+", page) else None, payload, holds


def _parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for content in batch.column(0):
            rows: list[tuple] = []
            held = 0
            for r in parse(content.as_py()):
                rows.append(r)
                held += len(r[6])
                if held > 4 << 20 or len(rows) >= 500:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _TYPES)], [x.split()[0] for x in RECORD.split(", ")])
                    rows, held = [], 0
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _TYPES)], [x.split()[0] for x in RECORD.split(", ")])


def read_warc(spark: SparkSession, out: str) -> DataFrame:
    """Records (RECORD) of WARC files, plain or gzip, whatever their names: a file at a time per task. digest_holds is null for
    revisits, whose payload is elsewhere, and where no known digest is given."""
    raw = spark.read.format("binaryFile").load(out).select("content")
    return raw.mapInArrow(_parse, RECORD)


def read_pages(spark: SparkSession, out: str) -> DataFrame:
    """One row per response or revisit of the files at `out`, from the parsed records alone: page_id, payload_bytes, payload_digest,
    record_type, refers_to, uri. A revisit has its length from the record it refers to. A payload that
    differs from its digest raises, and so does a revisit whose record is missing or has another digest."""
    r = read_warc(spark, out).where("record_type in ('response', 'revisit')")
    wrong = F.raise_error(F.concat(F.lit("payload differs from its digest: "), F.coalesce("record_id", F.lit("?"))))
    sha1 = F.regexp_replace(F.lower("payload_digest"), "^sha1:", "")
    index = stored(r.select("record_id", "record_type", "uri", "page_id", F.col("refers_to").alias("to"), F.octet_length("payload").cast("long").alias("n"),
                            F.when((F.col("record_type") == "revisit") | F.col("digest_holds"), sha1).otherwise(wrong).alias("sha1")), "index")
    # A record that many revisit is sent once for each salt.
    wanted = index.where("record_type = 'revisit'").withColumn("z", F.pmod(F.xxhash64("record_id"), F.lit(16)).cast("int"))
    known = index.where("record_type = 'response'").join(wanted.select(F.col("to").alias("record_id")).distinct(), "record_id", "left_semi")
    known = known.select(F.col("record_id").alias("to"), F.col("page_id").alias("of"), F.col("n").alias("m"), F.col("sha1").alias("d")).withColumn("z", F.explode(F.sequence(F.lit(0), F.lit(15))))
    lost = F.raise_error(F.concat(F.lit("no record of this digest to refer to: "), F.coalesce("record_id", F.lit("?"))))
    again = wanted.join(known, ["to", "z"], "left").select(
        "page_id", F.col("m").alias("payload_bytes"), F.when(F.col("d") == F.col("sha1"), F.col("sha1")).otherwise(lost).alias("payload_digest"), "record_type", F.col("of").alias("refers_to"), "uri")
    whole = index.where("record_type = 'response'").select(
        "page_id", F.col("n").alias("payload_bytes"), F.col("sha1").alias("payload_digest"), "record_type", F.lit(None).cast("long").alias("refers_to"), "uri")
    return whole.unionByName(again)
