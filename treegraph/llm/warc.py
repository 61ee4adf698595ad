"""WARC archives: gzip members of one record each, a strict reader, and a salvage reader that recovers after damage.

Tasks write whole files: under a name of their own, renamed when complete, so that an attempt that dies leaves nothing that
is read. Files live in the shared folder and are opened through pyarrow's file systems, by URI.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from dataclasses import dataclass, field
from urllib.parse import quote

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import delete, materialise, scratch_root, table, unused

#: A file is closed beyond so many bytes; readers hold one file and one record in memory.
FILE_BYTES = 32 << 20
DATE = "2024-01-01T00:00:00Z"
_VERSION = re.compile(rb"WARC/1\.[01]\r\n")
_MAGIC = b"\x1f\x8b\x08"


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(kind: str, page_id: int | None, url: str, payload: bytes, sha: str, refers_to: int | None, refers_url: str | None) -> bytes:
    """One record. A revisit has no payload; it names the response that has the same."""
    name = f"urn:page:{page_id}" if page_id is not None else f"urn:uuid:{uuid.uuid4()}"
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <{name}>", f"WARC-Date: {DATE}", f"WARC-Target-URI: {quote(url, safe=':/?#[]@!$&()*+,;=%~-._')}", f"WARC-Payload-Digest: sha1:{sha}", f"X-Payload-Length: {len(payload)}"]
    if page_id is not None:
        head.append(f"X-Page-ID: {page_id}")
    if kind == "revisit":
        head += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
        body = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    else:
        body = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload) + payload
    head += ["Content-Type: application/http; msgtype=response", f"WARC-Block-Digest: sha1:{digest(body)}", f"Content-Length: {len(body)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def member(data: bytes, level: int = 1) -> bytes:
    c = zlib.compressobj(level, zlib.DEFLATED, 31)
    return c.compress(data) + c.flush()


def file_system(uri: str):
    """The file system and path of a URI or plain path."""
    return pafs.FileSystem.from_uri(uri) if re.match(r"[a-z][a-z0-9+.-]*:", uri) else (pafs.LocalFileSystem(), uri)


@dataclass
class Read:
    """What a file gave: records (headers, block) with their offset, and gaps (offset, length, reason)."""

    records: list[tuple[int, dict[str, str], bytes]] = field(default_factory=list)
    gaps: list[tuple[int, int, str]] = field(default_factory=list)


class Damaged(ValueError):
    pass


def parse(data: bytes, at: int = 0) -> tuple[dict[str, str], bytes, int]:
    """The record at an offset of plain bytes and where it ends; raises Damaged unless all checks hold."""
    if not _VERSION.match(data, at):
        raise Damaged("no version line")
    stop = data.find(b"\r\n\r\n", at)
    if stop < 0:
        raise Damaged("headers don't end")
    headers = {}
    for line in data[at:stop].split(b"\r\n")[1:]:
        name, colon, value = line.partition(b":")
        if not colon:
            raise Damaged("header without a colon")
        headers[name.decode("utf-8", "replace").strip().lower()] = value.decode("utf-8", "replace").strip()
    try:
        length = int(headers["content-length"])
    except (KeyError, ValueError):
        raise Damaged("no length") from None
    begin = stop + 4
    block = data[begin : begin + length]
    if length < 0 or len(block) < length or data[begin + length : begin + length + 4] != b"\r\n\r\n":
        raise Damaged("block is cut or not closed")
    if "warc-block-digest" in headers and headers["warc-block-digest"] != f"sha1:{digest(block)}":
        raise Damaged("block digest differs")
    return headers, block, begin + length + 4


def inflate(data: bytes, at: int, piece: int = 1 << 14) -> tuple[bytes, int]:
    """The gzip member at an offset and where it ends; length and checksum are checked. Fed in pieces, of which the last may hold more."""
    d, out = zlib.decompressobj(31), []
    try:
        while not d.eof:
            if at >= len(data):
                raise Damaged("member is cut")
            out.append(d.decompress(data[at : at + piece]))
            at = min(at + piece, len(data))
    except zlib.error as e:
        raise Damaged(f"member: {e}") from None
    return b"".join(out), at - len(d.unused_data)


def salvage(data: bytes) -> Read:
    """All records of an archive, compressed or plain, that pass their checks.

    After a failed check the search goes on one byte further for the next gzip member or version line that starts a whole
    record; the bytes between are logged as one gap. An empty archive has neither records nor gaps. The next places of both
    marks are kept until they are passed, so that no byte is searched twice.
    """
    out, at, bad, why = Read(), 0, None, ""
    magic = version = -1
    while at < len(data):
        try:
            if data.startswith(_MAGIC, at):
                plain, end = inflate(data, at)
                inner, found = 0, []
                while inner < len(plain):
                    headers, block, inner = parse(plain, inner)
                    found.append((at, headers, block))
            else:
                headers, block, end = parse(data, at)
                found = [(at, headers, block)]
        except Damaged as e:
            if bad is None:
                bad, why = at, str(e)
            if magic <= at:
                magic = data.find(_MAGIC, at + 1)
                magic = len(data) if magic < 0 else magic
            if version <= at:
                m = _VERSION.search(data, at + 1)
                version = m.start() if m else len(data)
            at = min(magic, version)
            continue
        if bad is not None:
            out.gaps.append((bad, at - bad, why))
            bad = None
        out.records += found
        at = end
    if bad is not None:
        out.gaps.append((bad, len(data) - bad, why))
    return out


def with_types(pages: DataFrame, *, id_col: str = "page_id", html_col: str = "html", least: int = 0) -> DataFrame:
    """pages with refers_to: for payloads of at least `least` bytes, the smallest other page id with the same; else null.

    A row is told by its id and its payload, so that an id may have several payloads; rows that repeat both are alike. A null
    id refers to the smallest id of its payload, if there is one. The narrow table of ids and digests is grouped with partial
    sums; only digests that repeat are joined back, over salted keys, so that a payload that a third of all pages share is
    spread over many tasks.
    """
    id_, sha, n, first, salt, back = unused(pages, "__id", "__sha", "__n", "__first", "__salt", "__refers")
    payload = F.coalesce(F.col(html_col), F.lit("")).cast("binary")
    narrow = pages.select(F.col(id_col).alias(id_), F.sha1(payload).alias(sha), F.octet_length(payload).alias(n)).where(F.col(n) >= least)
    found = narrow.groupBy(sha).agg(F.min(id_).alias(first), F.count(F.lit(1)).alias(n)).where(F.col(n) > 1).select(sha, first)
    salts = 64
    found = found.select(sha, first, F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias(salt))
    salted = narrow.withColumn(salt, F.pmod(F.xxhash64(id_), F.lit(salts)).cast("int"))
    again = salted.join(found, [sha, salt]).where(F.col(id_).isNull() | (F.col(id_) > F.col(first))).where(F.col(first).isNotNull())
    again = materialise(again.select(id_, sha, F.col(first).alias(back)).distinct(), "revisits")
    own = [c for c in pages.columns if c != "refers_to"]
    tagged = pages.select(*own, F.sha1(payload).alias(salt))
    return tagged.join(again, F.col(id_col).eqNullSafe(F.col(id_)) & (F.col(salt) == F.col(sha)), "left").select(*own, F.col(back).alias("refers_to"))


def write_archives(pages: DataFrame, folder: str, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Write a record per page (see with_types) as .warc.gz files into folder: (path, records, bytes) of each file.

    A null html is an empty payload, a null url an empty one, a null id leaves its header out. Run once: the result is a
    written table. Other columns are ignored; an empty table writes no file.
    """

    def run(it):
        fs, root = file_system(folder)
        fs.create_dir(root, recursive=True)
        buffer: list[bytes] = []
        size, n = 0, 0

        def close():
            name = f"{root}/{uuid.uuid4().hex}.warc.gz"
            with fs.open_output_stream(name + ".part", compression=None) as f:
                for b in buffer:
                    f.write(b)
            fs.move(name + ".part", name)
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([n], pa.int64()), pa.array([size], pa.int64())], ["path", "records", "bytes"])

        for batch in it:
            for page, url, text, refers in zip(*[batch.column(i) for i in range(4)]):
                payload = (text.as_py() or "").encode("utf-8", "replace")
                to = refers.as_py()
                key = page.as_py()
                data = member(record("response" if to is None else "revisit", key, url.as_py() or "", payload, digest(payload), to, None))
                buffer.append(data)
                size, n = size + len(data), n + 1
                if size >= FILE_BYTES:
                    yield close()
                    buffer.clear()
                    size = n = 0
        if n:
            yield close()

    rows = with_types(pages, id_col=id_col, html_col=html_col).select(F.col(id_col).cast("long"), F.col(url_col).cast("string"), F.col(html_col).cast("string"), F.col("refers_to").cast("long"))
    return materialise(rows.mapInArrow(run, "path string, records long, bytes long"), "archives")


_ROW = "path string, at long, gap_bytes long, reason string, page_id long, record_type string, refers_to long, payload_bytes long, payload_digest string, checked boolean, url string, payload binary"


def read_archives(files: DataFrame, folder: str) -> DataFrame:
    """Records and quarantined gaps of the archives named in files(path): one row each, gaps with gap_bytes and reason set.

    checked tells whether a response's payload has the length and digest that its headers state (revisits have none).
    """

    def run(it):
        fs, _ = file_system(folder)
        for batch in it:
            for path in batch.column(0).to_pylist():
                with fs.open_input_stream(path, compression=None) as f:
                    got = salvage(f.read())
                rows = [{"path": path, "at": a, "gap_bytes": n, "reason": why} for a, n, why in got.gaps]
                for a, h, block in got.records:
                    kind = h.get("warc-type")
                    payload = block.partition(b"\r\n\r\n")[2]
                    stated, size = h.get("warc-payload-digest", "").removeprefix("sha1:"), int(h.get("x-payload-length", -1))
                    refers = h.get("warc-refers-to", "").removeprefix("<urn:page:").removesuffix(">")
                    fine = kind == "revisit" or digest(payload) == stated and len(payload) == size
                    rows.append({"path": path, "at": a, "page_id": int(h["x-page-id"]) if "x-page-id" in h else None, "record_type": kind, "refers_to": int(refers) if refers else None, "payload_bytes": size, "payload_digest": stated, "checked": fine, "url": h.get("warc-target-uri"), "payload": payload if kind != "revisit" else None})
                for k in range(0, len(rows), 200):
                    yield pa.RecordBatch.from_pylist(rows[k : k + 200], schema=_schema)

    _schema = pa.schema([(n, {"string": pa.string(), "long": pa.int64(), "boolean": pa.bool_(), "binary": pa.binary()}[t]) for n, t in (x.split() for x in _ROW.split(", "))])
    few = files.select("path")
    return few.repartition(max(1, min(10_000, few.count()))).mapInArrow(run, _ROW)


def verified(files: DataFrame, folder: str) -> DataFrame:
    """The records of the archives without their payloads, as a written table; raises if any is damaged, lost, or not what its headers say."""
    found = materialise(read_archives(files, folder).drop("payload"), "records")
    wrote = files.agg(F.coalesce(F.sum("records"), F.lit(0))).first()[0]
    gaps, whole = found.agg(F.count_if(F.col("gap_bytes").isNotNull()), F.count_if(F.coalesce("checked", F.lit(False)))).first()
    if gaps or whole != wrote:
        raise ValueError(f"{wrote} records were written, {whole} came back whole, with {gaps} gaps")
    return found


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = f"{scratch_root(spark)}/warc-{uuid.uuid4().hex}"
    files = write_archives(table(spark, sf_dir, "pages").select("page_id", "url", "html"), folder)
    found = verified(files, folder)
    delete(spark, folder)
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


QUERIES = {"op3_warc": op3_warc}
ORACLES = {
    "op3_warc": """
      WITH p AS (SELECT page_id, coalesce(html, '') AS payload FROM pages), h AS (SELECT page_id, payload, sha1(payload) AS sha, min(page_id) OVER (PARTITION BY payload) AS least FROM p)
      SELECT page_id, CAST(octet_length(encode(payload)) AS BIGINT) AS payload_bytes,
        array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST(1 + ((CAST('0x' || substr(sha, CAST(i * 5 // 4 + 1 AS BIGINT), 2) AS INTEGER) >> CAST(3 - i * 5 % 4 AS INTEGER)) & 31) AS BIGINT), 1)), '') AS payload_digest,
        CASE WHEN page_id > least THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN page_id > least THEN least END AS refers_to FROM h"""
}
