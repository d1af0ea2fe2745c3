"""WARC archives: a writer with revisit records and a splittable reader.

Writing: every record is a gzip member of its own. Of records with equal payloads of at
least ``least`` bytes, that with the smallest page_id is a response and the others revisit
it. Which payloads are shared is found on digests and ids alone; the few digests that many
rows share are broadcast (at most ``2 ** HOT_BITS`` of them, by their definition), so these rows meet
nowhere and are written by the tasks that read them, and so are payloads below ``least``. Revisits are
written without the payload, which they never need. Each task writes one archive under a name
of its own and moves it into place when it is whole, so a task that runs again replaces its own work. Files go
to the shared folder through its own file system.

Reading: tasks get byte ranges. A task scans its range for the gzip magic, takes a hit as
the start of a record only if the member there decodes to a WARC version line, and owns
every record that starts inside its range, reading past the end to finish the last one.
From a valid record on it follows the members one by one, so that bytes within a member
that look like the magic are never considered.

Defined cases: a null html is an empty payload; a null url is written as an empty target;
a null page_id is kept as null and is a response; rows that repeat the smallest page_id are all responses;
an empty table gives no archive and an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import urllib.parse
import uuid
import zlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded, release, shared_dir, slices, table, written

MAGIC = b"\x1f\x8b\x08"
VERSION = b"WARC/1.1\r\n"
SPLIT = 8 << 20
READ = 1 << 20
HOT_BITS = 14  # digests of more rows than a share of 2 ** -HOT_BITS are broadcast
HOT_ROWS = 1024  # and at least of so many rows
READERS = 100_000  # tasks that read ranges at most; each then takes several


def _fs(uri: str):
    from pyarrow import fs

    if "://" not in uri:
        uri = "file://" + re.sub("^file:", "", uri)
    return fs.FileSystem.from_uri(uri)


def _name(page_id) -> str:
    return "<urn:x-page:" + ("null" if page_id is None or pd.isna(page_id) else str(int(page_id))) + ">"


def _page(name: str) -> int | None:
    found = name.strip().removeprefix("<urn:x-page:").removesuffix(">")
    return None if found in ("null", "") else int(found)


def record(page_id, url: str | None, payload: bytes, digest: str, first, size: int | None = None) -> bytes:
    """One gzip member: a response with its payload, or a revisit of page ``first`` with the HTTP header alone, for a payload of ``size`` bytes."""
    revisit = first is not None and not pd.isna(first)
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload) if size is None else size}\r\n\r\n".encode()
    block = http if revisit else http + payload
    head = [
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: {_name(page_id)}",
        f"WARC-Target-URI: {urllib.parse.quote(url or '', safe=':/?#[]@!$&()*+,;=%~-._')}",
        "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Payload-Digest: sha256:{digest}",
    ]
    if revisit:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {_name(first)}"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    return packer.compress(VERSION + "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n") + packer.flush()


def with_first(pages: DataFrame, least: int = 100) -> DataFrame:
    """``pages`` (page_id, url, html) with ``digest``, ``size`` and ``first``: the page that the row revisits, null for responses.

    Revisits of widely shared payloads come without html.
    """
    html = F.coalesce("html", F.lit(""))
    p = pages.select("page_id", "url", html.alias("html"), F.octet_length(html).cast("long").alias("size")).withColumn("digest", F.sha2("html", 256))
    groups = p.where(F.col("size") >= least).groupBy("digest").agg(F.min("page_id").alias("least_id"), F.count("*").alias("n")).where(F.col("n") > 1)
    groups = written(groups, "shared-payloads")
    widely = F.col("n") > max(HOT_ROWS, pages.count() >> HOT_BITS)
    columns = ["page_id", "url", "html", "size", "digest"]
    first = F.when(F.col("page_id") > F.col("least_id"), F.col("least_id")).alias("first")
    marked = p.join(F.broadcast(groups.where(widely).select("digest", "least_id", F.lit(True).alias("wide"))), "digest", "left")  # 2 ** HOT_BITS rows at most
    alone = F.col("wide").isNotNull() | (F.col("size") < least)
    here = marked.where(alone).select(*columns, first).withColumn("html", F.when(F.col("first").isNull(), F.col("html")))
    rest = marked.where(~alone).select(*columns).join(groups.where(~widely).select("digest", "least_id"), "digest", "left").select(*columns, first)
    return here.unionByName(rest)


def write_archives(pages: DataFrame, folder: str, least: int = 100) -> DataFrame:
    """Writes ``pages`` as archives under ``folder``; (file, bytes, records) of each."""

    def put(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        fs, base = _fs(folder)
        name = f"{base}/part-{TaskContext.get().partitionId():06d}.warc.gz"
        draft = f"{name}.{uuid.uuid4().hex}.tmp"
        n = size = 0
        out = None
        for pdf in (part for batch in batches for part in slices(batch, "html", READ)):
            for page_id, url, html, payload_bytes, digest, first in zip(pdf["page_id"], pdf["url"], pdf["html"], pdf["size"], pdf["digest"], pdf["first"]):
                if out is None:
                    fs.create_dir(base, recursive=True)
                    out = fs.open_output_stream(draft)
                data = record(page_id, url, (html or "").encode("utf-8", "surrogatepass"), digest, first, payload_bytes)
                out.write(data)
                n, size = n + 1, size + len(data)
        if out is not None:
            out.close()
            fs.move(draft, name)
            yield pd.DataFrame({"file": [name], "bytes": [size], "records": [n]})
        release()

    return with_first(bounded(pages), least).mapInPandas(put, "file string, bytes long, records long")


class _Source:
    """Sequential bytes of a file from an offset on, read in blocks."""

    def __init__(self, file, at: int):
        self.file, self.at, self.held = file, at, b""
        file.seek(at)

    def fill(self) -> bool:
        got = self.file.read(READ)
        self.held += got
        return bool(got)

    def skip(self, n: int) -> None:
        self.held, self.at = self.held[n:], self.at + n


def _member(src: _Source, header_only: bool) -> tuple[bytes, int] | None:
    """The member at ``src``: its content and its length in the file; None if it isn't a WARC record."""
    unpack, used, parts, head = zlib.decompressobj(31), 0, [], b""
    while True:
        if used == len(src.held) and not src.fill():
            return None
        try:
            got = unpack.decompress(src.held[used:])
        except zlib.error:
            return None
        used = len(src.held) - len(unpack.unused_data)
        if len(head) < len(VERSION):
            head += got
            if not VERSION.startswith(head[: len(VERSION)]):
                return None
            if header_only and len(head) >= len(VERSION):
                return b"", 0
        parts.append(got)
        if unpack.eof:
            return (b"".join(parts), used) if len(head) >= len(VERSION) else None


def read_range(fs, path: str, start: int, end: int) -> Iterator[bytes]:
    """Contents of the records of ``path`` that start in ``start`` up to ``end``."""
    with fs.open_input_file(path) as file:
        src = _Source(file, start)
        synced = False
        while src.at < end:
            if len(src.held) < len(MAGIC) and not src.fill():
                return
            if not src.held.startswith(MAGIC):
                if synced:  # padding or damage: look for the next member
                    synced = False
                hit = src.held.find(MAGIC, 1)
                src.skip(hit if hit > 0 else max(1, len(src.held) - len(MAGIC) + 1))
                continue
            got = _member(src, False)
            if got is None:
                src.skip(1)
                continue
            synced = True
            yield got[0]
            src.skip(got[1])


def parse(content: bytes) -> dict:
    """Fields of a record; the digest of a response is taken from its payload and checked against the header."""
    head, _, block = content.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode("utf-8").split("\r\n")[1:] if ": " in line)
    http, _, payload = block[: int(fields["Content-Length"])].partition(b"\r\n\r\n")
    told = fields["WARC-Payload-Digest"].removeprefix("sha256:")
    if fields["WARC-Type"] == "response":
        size, found = len(payload), hashlib.sha256(payload).hexdigest()
        if found != told:
            raise ValueError(f"payload of {fields['WARC-Record-ID']} doesn't have its digest")
    else:
        size = int(re.search(rb"(?i)\r\ncontent-length: *(\d+)", http)[1])
    return {
        "page_id": _page(fields["WARC-Record-ID"]), "url": urllib.parse.unquote(fields.get("WARC-Target-URI", "")), "payload": payload if fields["WARC-Type"] == "response" else None,
        "payload_bytes": size, "payload_digest": told, "record_type": fields["WARC-Type"], "refers_to": _page(fields.get("WARC-Refers-To", "")),
    }


def read_archives(files: DataFrame, folder: str, split: int = SPLIT, payloads: bool = False, readers: int = READERS) -> DataFrame:
    """Records of ``files`` (file, bytes), read by byte ranges of ``split`` bytes, in ``readers`` tasks at most."""
    ranges = files.select("file", "bytes", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.col("bytes") - 1, F.lit(0)), F.lit(split).cast("long"))).alias("start"))
    ranges = ranges.withColumn("end", F.least(F.col("start") + split, F.col("bytes"))).select("file", "start", "end")
    count = files.agg(F.sum(F.greatest(F.ceil(F.col("bytes") / split), F.lit(1)))).first()[0] or 1
    ranges = ranges.repartition(int(min(count, readers)))  # a stated number: tiny range rows would be coalesced into one task
    kind = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long" + ", url string, payload binary" * payloads
    names = [x.split()[0] for x in kind.split(", ")]

    def get(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        fs, _ = _fs(folder)

        def frame(rows: list[dict]) -> pd.DataFrame:
            out = pd.DataFrame(rows, columns=names)
            return out.assign(page_id=out["page_id"].astype("Int64"), refers_to=out["refers_to"].astype("Int64"))

        for pdf in batches:
            for file, start, end in zip(pdf["file"], pdf["start"], pdf["end"]):
                rows: list[dict] = []
                held = 0
                for content in read_range(fs, file, int(start), int(end)):
                    rows.append({k: v for k, v in parse(content).items() if k in names})
                    held += len(content)
                    if held > READ:
                        yield frame(rows)
                        rows, held = [], 0
                if rows:
                    yield frame(rows)
        release()

    return ranges.mapInPandas(get, kind)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = f"{shared_dir(spark)}/llm-warc-{uuid.uuid4().hex}"
    files = write_archives(table(spark, sf_dir, "pages"), folder)
    files.write.parquet(f"{folder}/manifest")
    return read_archives(spark.read.parquet(f"{folder}/manifest"), folder)


ORACLE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
d AS (SELECT page_id, octet_length(encode(html)) AS payload_bytes, sha256(html) AS payload_digest FROM p),
f AS (SELECT payload_digest, min(page_id) AS first FROM d WHERE payload_bytes >= 100 GROUP BY 1)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes, payload_digest,
  CASE WHEN page_id > first THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN page_id > first THEN first END AS refers_to
FROM d LEFT JOIN f USING (payload_digest)
"""
