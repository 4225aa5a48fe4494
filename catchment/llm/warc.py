"""WARC archives with a two-level capture index.

Archives: one gzip member a record (warcinfo first in each file), response records with the whole payload and
revisit records for payloads that a response holds already. Index: capture lines sorted by reversed-host URL
key lie in compressed blocks of ``block_lines``; a sparse directory keeps each block's first key, place and length,
and a list of directory files keeps each file's first key. A look-up is two binary searches, one
range read of a block and one range read of the record. Reading everything back goes the same way, block by
block, then in file order.

A page is a revisit when a page with a smaller id has an equal payload of at least ``least`` bytes; it refers to the
smallest such id. Odd input: null html is an empty payload; a null url gets a URN of its id as target; rows
with a null page id are responses (nothing can refer to them); rows that repeat the smallest id with the same payload are
responses all; an empty table gives no archive and an empty result; other columns are ignored.
"""

from __future__ import annotations

import bisect
import hashlib
import json
import zlib
from urllib.parse import quote, urlsplit

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bitmap_bits, file_system, fresh_path, id_slots, in_batches, materialize, slot_hit

_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_GZIP = 31


def url_key(url: str | None) -> str:
    """Reversed host, then path and query: blog.example.org/a?b -> org,example,blog)/a?b."""
    url = (url or "").strip()
    try:
        parts = urlsplit(url if "://" in url or url.startswith("urn:") else "http://" + url)
        host, port = (parts.hostname or "").lower(), parts.port
    except ValueError:
        return quote(url, safe="")
    if not host:
        return quote(url, safe=":/?=&%")
    key = ",".join(reversed(host.split("."))) + (f":{port}" if port and port not in (80, 443) else "")
    tail = (parts.path or "/") + (f"?{parts.query}" if parts.query else "")
    return quote(f"{key}){tail}", safe="%/:=&?#[]@!$()*+,;~'")


def gz(data: bytes) -> bytes:
    packer = zlib.compressobj(6, zlib.DEFLATED, _GZIP)
    return packer.compress(data) + packer.flush()


def _record(kind: str, fields: list[tuple[str, str]], body: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in fields)
    return f"WARC/1.1\r\nWARC-Type: {kind}\r\n{head}Content-Length: {len(body)}\r\n\r\n".encode() + body + b"\r\n\r\n"


def page_record(page, url, payload: bytes, digest: str, refers_to, date: str) -> bytes:
    """An uncompressed response or revisit record."""
    target = quote(url, safe="%/:=&?#[]@!$()*+,;~'") if url else f"urn:x-page:{page}"
    fields = [("WARC-Record-ID", f"<urn:x-page:{page}>"), ("WARC-Target-URI", target), ("WARC-Date", date), ("WARC-Payload-Digest", f"sha256:{digest}"), ("Content-Type", "application/http; msgtype=response")]
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    if refers_to is None:
        return _record("response", fields, http + payload)
    return _record("revisit", [*fields, ("WARC-Refers-To", f"<urn:x-page:{refers_to}>"), ("WARC-Profile", _PROFILE)], http)


def parse_record(data: bytes) -> tuple[dict, dict, bytes]:
    """WARC headers (lower-cased names, plus ``type``), HTTP headers, payload of an uncompressed record."""

    def headers(block: bytes):
        lines = block.decode("utf-8").split("\r\n")
        return lines[0], {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}

    head, _, rest = data.partition(b"\r\n\r\n")
    first, fields = headers(head)
    if not first.startswith("WARC/"):
        raise ValueError("not a WARC record")
    body = rest[: int(fields["content-length"])]
    http, _, payload = body.partition(b"\r\n\r\n")
    return fields, headers(http)[1] if http else {}, payload


def _archive(root: str, date: str):
    schema = pa.schema([("page_id", pa.int64()), ("key", pa.string()), ("line", pa.string())])

    def run(batches):
        context = TaskContext.get()
        name, out, at = f"pages-{context.partitionId():06d}-{context.taskAttemptId()}.warc.gz", None, 0
        fs, base = file_system(root)
        try:
            for batch in batches:
                if not batch.num_rows:
                    continue
                if out is None:
                    fs.create_dir(base, recursive=True)
                    out = fs.open_output_stream(f"{base}/{name}", compression=None)
                    info = gz(_record("warcinfo", [("WARC-Record-ID", f"<urn:x-archive:{name}>"), ("WARC-Date", date), ("Content-Type", "application/warc-fields")], b"format: WARC File Format 1.1\r\n"))
                    out.write(info)
                    at = len(info)
                pages, urls, digests, refers = (batch.column(c).to_pylist() for c in (0, 1, 3, 4))
                keys, lines = [], []
                for page, url, payload, digest, refer in zip(pages, urls, batch.column(2).cast(pa.binary()).to_pylist(), digests, refers):
                    data = gz(page_record(page, url, payload or b"", digest, refer, date))
                    out.write(data)
                    key = url_key(url)
                    keys.append(key)
                    lines.append(key + " " + date + " " + json.dumps({"page": page, "digest": digest, "type": "response" if refer is None else "revisit", "file": name, "offset": at, "length": len(data)}))
                    at += len(data)
                yield pa.RecordBatch.from_arrays([pa.array(pages, pa.int64()), pa.array(keys), pa.array(lines)], schema=schema)
        finally:
            if out is not None:
                out.close()

    return run


def _blocks(root: str, block_lines: int):
    """Sorted capture lines to one block file and one directory file a task."""
    schema = pa.schema([("shard", pa.int64()), ("first_key", pa.string()), ("block_file", pa.string()), ("directory", pa.string()), ("offset", pa.int64()), ("length", pa.int64()), ("lines", pa.int64())])

    def run(batches):
        context = TaskContext.get()
        shard = context.partitionId()
        name = f"index-{shard:06d}-{context.taskAttemptId()}"
        fs, base = file_system(root)
        out, at, held, rows = None, 0, [], []

        def flush():
            nonlocal out, at, held
            if out is None:
                fs.create_dir(base, recursive=True)
                out = fs.open_output_stream(f"{base}/{name}.cdx.gz", compression=None)
            data = gz("\n".join(held).encode())
            out.write(data)
            rows.append((held[0].split(" ", 1)[0], at, len(data), len(held)))
            at += len(data)
            held = []

        for batch in batches:
            for line in batch.column(1).to_pylist():
                held.append(line)
                if len(held) == block_lines:
                    flush()
        if held:
            flush()
        if out is not None:
            out.close()
            with fs.open_output_stream(f"{base}/{name}.dir", compression=None) as d:
                d.write("\n".join("\t".join(map(str, r)) for r in rows).encode())
            n = len(rows)
            yield pa.RecordBatch.from_arrays([pa.array([shard] * n, pa.int64()), pa.array([r[0] for r in rows]), pa.array([f"{name}.cdx.gz"] * n), pa.array([f"{name}.dir"] * n), *[pa.array([r[k] for r in rows], pa.int64()) for k in (1, 2, 3)]], schema=schema)

    return run


def read_range(fs, path: str, offset: int, length: int) -> bytes:
    with fs.open_input_file(path) as f:
        f.seek(offset)
        return f.read(length)


class CaptureIndex:
    """Archives and index under ``root``; ``blocks`` is the directory as a table, ``shards`` its files by first key."""

    def __init__(self, root: str, blocks: DataFrame):
        self.root, self.blocks = root, blocks
        found = blocks.groupBy("shard", "directory", "block_file").agg(F.min("first_key").alias("k")).orderBy("shard").collect()
        self.shards = [(r["k"], r["directory"], r["block_file"]) for r in found]

    def lookup(self, url: str) -> list[tuple[dict, dict, dict, bytes]]:
        """All captures of a URL: (index entry, WARC headers, HTTP headers, payload), by binary search and range reads."""
        fs, base = file_system(self.root)
        key = url_key(url)
        out = []
        first = max(0, bisect.bisect_left([s[0] for s in self.shards], key) - 1)
        for start, directory, block_file in self.shards[first:]:
            if start > key:
                break
            with fs.open_input_file(f"{base}/{directory}") as f:
                rows = [r.split("\t") for r in f.read().decode().split("\n")]
            at = max(0, bisect.bisect_left([r[0] for r in rows], key) - 1)
            for row in rows[at:]:
                if row[0] > key:
                    break
                lines = zlib.decompress(read_range(fs, f"{base}/{block_file}", int(row[1]), int(row[2])), _GZIP).decode().split("\n")
                keys = [x.split(" ", 1)[0] for x in lines]
                for line in lines[bisect.bisect_left(keys, key) : bisect.bisect_right(keys, key)]:
                    entry = json.loads(line.split(" ", 2)[2])
                    data = zlib.decompress(read_range(fs, f"{base}/{entry['file']}", entry["offset"], entry["length"]), _GZIP)
                    out.append((entry, *parse_record(data)))
        return out

    def read_all(self) -> DataFrame:
        """Every record through the index: page_id, payload_bytes, payload_digest, record_type, refers_to, url_key."""
        root = self.root
        line_schema = pa.schema([("url_key", pa.string()), ("file", pa.string()), ("offset", pa.int64()), ("length", pa.int64())])

        def expand(batches):
            fs, base = file_system(root)
            for batch in batches:
                for name, offset, length in zip(*(batch.column(c).to_pylist() for c in range(3))):
                    lines = zlib.decompress(read_range(fs, f"{base}/{name}", offset, length), _GZIP).decode().split("\n")
                    cut = [x.split(" ", 2) for x in lines]
                    entries = [json.loads(x[2]) for x in cut]
                    yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in cut]), pa.array([e["file"] for e in entries]), pa.array([e["offset"] for e in entries], pa.int64()), pa.array([e["length"] for e in entries], pa.int64())], schema=line_schema)

        out_schema = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("url_key", pa.string())])

        def read(batches):
            fs, base = file_system(root)
            held, f = None, None
            number = lambda urn: None if urn is None or urn.endswith(":None>") else int(urn.rpartition(":")[2].rstrip(">"))
            for batch in batches:
                rows: list[tuple] = []
                for key, name, offset, length in zip(*(batch.column(c).to_pylist() for c in range(4))):
                    if name != held:
                        if f is not None:
                            f.close()
                        held, f = name, fs.open_input_file(f"{base}/{name}")
                    f.seek(offset)
                    warc, http, payload = parse_record(zlib.decompress(f.read(length), _GZIP))
                    page = number(warc["warc-record-id"])
                    if warc["warc-type"] == "response":
                        rows.append((page, len(payload), hashlib.sha256(payload).hexdigest(), "response", None, key))
                    else:
                        rows.append((page, int(http["content-length"]), warc["warc-payload-digest"].partition(":")[2], "revisit", number(warc["warc-refers-to"]), key))
                yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*rows), out_schema)] if rows else [pa.nulls(0, t.type) for t in out_schema], schema=out_schema)
            if f is not None:
                f.close()

        blocks = self.blocks.select("block_file", "offset", "length")
        lines = blocks.repartition("block_file", "offset").mapInArrow(expand, "url_key string, file string, offset long, length long")
        ordered = lines.repartition("file").sortWithinPartitions("file", "offset")
        return ordered.mapInArrow(read, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url_key string")


def write_archives(pages: DataFrame, root: str | None = None, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least: int = 100, block_lines: int = 3000, date: str = "2024-01-01T00:00:00Z") -> CaptureIndex:
    """Write every page to an archive and index it; ``root`` defaults to the shared folder."""
    spark = pages.sparkSession
    root = root or fresh_path(spark, "warc")
    rows = in_batches(pages).select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.coalesce(F.col(html_col).cast("string"), F.lit("")).alias("html"))
    rows = rows.withColumn("digest", F.sha2(F.col("html").cast("binary"), 256))
    facts = rows.filter((F.octet_length("html") >= least) & F.col("page_id").isNotNull()).select("page_id", "digest")
    firsts = facts.groupBy("digest").agg(F.min("page_id").alias("refers_to"), F.max("page_id").alias("last")).filter("refers_to != last").select("digest", "refers_to")
    revisits = materialize(facts.join(firsts, "digest").filter("page_id != refers_to").distinct(), "revisits")
    bits = bitmap_bits(revisits.count())
    hit = slot_hit(rows, id_slots(revisits, bits, "page_id"), bits, "page_id").select("page_id", "url", "html", "digest", "_hit")
    # only pages that may be revisits move to their rows
    marked = hit.filter("not _hit").drop("_hit").withColumn("refers_to", F.lit(None).cast("long")).unionByName(hit.filter("_hit").drop("_hit").join(revisits, ["page_id", "digest"], "left").select("page_id", "url", "html", "digest", "refers_to"))
    lines = materialize(marked.mapInArrow(_archive(root, date), "page_id long, key string, line string"), "captures")
    ordered = lines.repartitionByRange("key").sortWithinPartitions("key", "page_id").select("key", "line")
    blocks = materialize(ordered.mapInArrow(_blocks(root, block_lines), "shard long, first_key string, block_file string, directory string, offset long, length long, lines long"), "blocks")
    return CaptureIndex(root, blocks)


def op3_warc(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    return write_archives(pages).read_all().select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


SQL = {
    "op3_warc": """
WITH p AS (SELECT page_id, coalesce(html, '') AS h, sha256(coalesce(html, '')) AS d, strlen(coalesce(html, ''))::BIGINT AS b FROM pages),
f AS (SELECT d, min(page_id) AS first FROM p WHERE b >= 100 GROUP BY d)
SELECT page_id, b AS payload_bytes, p.d AS payload_digest,
  CASE WHEN b >= 100 AND page_id > first THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN b >= 100 AND page_id > first THEN first END AS refers_to
FROM p LEFT JOIN f ON p.d = f.d
""",
}
