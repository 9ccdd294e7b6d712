"""WARC archives with a two-level capture index (operator 1).

Every page becomes one gzip member of a WARC file: a response with its payload, or a revisit
that refers to the response of an equal payload. Index entries are range-sorted by key, the
URL with its host reversed, and compressed in blocks of ``BLOCK_ENTRIES``; at the end of each
index file stands a sparse directory with the first and last key and the place of each block. One
row for each index file, so no more than there are range partitions, is loaded. A look-up searches
these rows, the file's directory and the block by bisection, each read by range, and reads the
records by range. Many look-ups at once are dealt by block, so a URL with many captures is too.
A revisit names the URL of its response, by which its payload is looked up.

Files go to a folder that driver and executors share; a name is used by one attempt of one
task only, and what a lost task left behind is in no index.

Defined cases: a null payload is empty; payloads under ``MIN_REVISIT`` bytes are responses;
of equal payloads the smallest page_id is the response (rows that repeat that id with that
payload are responses too, and so are all where no id is there); a null URL is an empty one,
with an empty key; URLs are percent-encoded before all else; an empty table gives an empty index; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import re
import zlib
from bisect import bisect_left, bisect_right
from functools import lru_cache
from itertools import groupby
from urllib.parse import quote, urlsplit

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import files
from .common import bound_batches, materialize, scratch_dir

MIN_REVISIT = 100
FILE_BYTES = 64 << 20
BLOCK_ENTRIES = 512
LEVEL = 4
#: Fixed values of the format.
DATE = "1970-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"

ENTRY = "key string, url string, page_id long, file string, offset long, length long, record_type string"
RECORD = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long"


def url_key(url: str) -> str:
    """Sort key of a URL: host labels reversed, port, path and query; no scheme, no fragment."""
    try:
        u = urlsplit(url.strip())
        host, port = u.hostname or "", u.port
    except ValueError:
        return url
    rest = (u.path or "/") + (f"?{u.query}" if u.query else "")
    return ",".join(reversed(host.split("."))) + (f":{port}" if port else "") + ")" + rest if host else url


def _header(url: str) -> str:
    return quote(url, safe="!#$%&'()*+,/:;=?@[]~-._")


def write_record(page_id: int | None, url: str, payload: bytes, size: int, digest: str, refers_to: int | None, refers_url: str | None = None) -> bytes:
    """One record as a gzip member; with ``refers_to`` a revisit, without payload."""
    kind = "response" if refers_to is None else "revisit"
    block = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", f"WARC-Date: {DATE}", f"WARC-Target-URI: {_header(url)}", f"WARC-Payload-Digest: sha256:{digest}"]
    if refers_to is None:
        block += payload
    else:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:page:{refers_to}>", f"WARC-Refers-To-Target-URI: {_header(refers_url or '')}"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}", "", ""]
    packer = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
    return packer.compress("\r\n".join(lines).encode() + block + b"\r\n\r\n") + packer.flush()


def read_record(member: bytes) -> dict:
    """Fields of a record; the digest of a response is taken from its payload anew."""
    data = zlib.decompress(member, 31)
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if lines[0] != "WARC/1.1":
        raise ValueError("not a WARC record")
    fields = dict(line.split(": ", 1) for line in lines[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    number = lambda k: int(m[1]) if (m := re.fullmatch(r"<urn:page:(-?\d+)>", fields.get(k, ""))) else None
    said = fields["WARC-Payload-Digest"].removeprefix("sha256:")
    size = int(re.search(rb"Content-Length: (\d+)", http)[1])
    if fields["WARC-Type"] == "response":
        if hashlib.sha256(payload).hexdigest() != said or len(payload) != size:
            raise ValueError(f"damaged record {fields['WARC-Record-ID']}")
    return {"page_id": number("WARC-Record-ID"), "payload": payload, "payload_bytes": size, "payload_digest": said, "record_type": fields["WARC-Type"], "refers_to": number("WARC-Refers-To"), "refers_url": fields.get("WARC-Refers-To-Target-URI")}


def write_archives(pages: DataFrame, base: str, min_revisit: int = MIN_REVISIT, file_bytes: int = FILE_BYTES) -> DataFrame:
    """Write the WARC files; their index entries (see ``ENTRY``) as a written table."""
    bound_batches(pages.sparkSession, rows=500, mb=16)
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce("url", F.lit("")).alias("url"), payload.alias("payload"))
    rows = rows.withColumn("digest", F.sha2("payload", 256))
    equal = rows.where(F.length("payload") >= min_revisit).groupBy("digest").agg(F.min(F.when(F.col("page_id").isNotNull(), F.struct("page_id", "url"))).alias("first"), F.count(F.lit(1)).alias("n"))
    equal = materialize(equal.where("n > 1").select("digest", "first"), "equal")
    other = ~F.col("page_id").eqNullSafe(F.col("first.page_id"))
    rows = rows.join(equal, "digest", "left").select("page_id", "url", "payload", "digest", F.when(other, F.col("first.page_id")).alias("refers"), F.when(other, F.col("first.url")).alias("refers_url"))

    def run(batches):
        part, nth = TaskContext.get().partitionId(), 0
        held, entries, size = [], [], 0

        def close():
            name = files.create(base, f"pages-{part:06d}-{nth:06d}", ".warc.gz", b"".join(held))
            k, u, p, o, n, t = map(list, zip(*entries, strict=True))
            cols = [pa.array(k, pa.string()), pa.array(u, pa.string()), pa.array(p, pa.int64()), pa.array([name] * len(k), pa.string()), pa.array(o, pa.int64()), pa.array(n, pa.int64()), pa.array(t, pa.string())]
            return pa.RecordBatch.from_arrays(cols, names=["key", "url", "page_id", "file", "offset", "length", "record_type"])

        for b in batches:
            for page, url, body, digest, refers, refers_url in zip(*(c.to_pylist() for c in b.columns), strict=True):
                member = write_record(page, url, body, len(body), digest, refers, refers_url)
                entries.append((url_key(_header(url)), url, page, size, len(member), "response" if refers is None else "revisit"))
                held.append(member)
                size += len(member)
                if size >= file_bytes:
                    yield close()
                    held, entries, size, nth = [], [], 0, nth + 1
        if held:
            yield close()

    return materialize(rows.mapInArrow(run, ENTRY), "entries")


def write_index(entries: DataFrame, base: str, block_entries: int = BLOCK_ENTRIES) -> DataFrame:
    """Write the sorted, compressed blocks and their directories; ``first_key, last_key, file,
    offset, length, n_blocks`` of each index file's directory as a written table."""
    rows = entries.repartitionByRange("key", "page_id").sortWithinPartitions("key", "page_id", "file", "offset")

    def run(batches):
        part, held, blocks, made, size = TaskContext.get().partitionId(), [], [], [], 0

        def pack():
            lines = "\n".join(json.dumps(list(e), ensure_ascii=False) for e in held)
            blocks.append(zlib.compress(lines.encode(), LEVEL))
            return (held[0][0], held[-1][0], size, len(blocks[-1]))

        for b in batches:
            for e in zip(*(c.to_pylist() for c in b.columns), strict=True):
                held.append(e)
                if len(held) == block_entries:
                    made.append(pack())
                    size += made[-1][3]
                    held = []
        if held:
            made.append(pack())
            size += made[-1][3]
        if made:
            tail = zlib.compress("\n".join(json.dumps(m, ensure_ascii=False) for m in made).encode(), LEVEL)
            name = files.create(base, f"index-{part:06d}", ".cdx.z", b"".join([*blocks, tail]))
            row = {"first_key": [made[0][0]], "last_key": [made[-1][1]], "file": [name], "offset": [size], "length": [len(tail)], "n_blocks": [len(made)]}
            text, number = pa.string(), pa.int64()
            yield pa.RecordBatch.from_pydict(row, schema=pa.schema(list(zip(row, (text, text, text, number, number, number), strict=True))))

    return materialize(rows.mapInArrow(run, "first_key string, last_key string, file string, offset long, length long, n_blocks long"), "directory")


def read_block(base: str, file: str, offset: int, length: int) -> list[list]:
    """Entries of a block, or rows of a directory, read by range."""
    return [json.loads(x) for x in zlib.decompress(files.read_range(base, file, offset, length)).decode().split("\n")]


class CaptureIndex:
    """Looks URLs up; loads one row for each index file."""

    def __init__(self, directory: DataFrame, base: str) -> None:
        self._load(sorted(map(tuple, directory.select("last_key", "first_key", "file", "offset", "length").collect())), base)

    def _load(self, rows: list[tuple], base: str) -> None:
        self.rows, self.base, self.last = rows, base, [r[0] for r in rows]
        self._blocks = lru_cache(4)(lambda file, offset, length: read_block(base, file, offset, length))

    def __getstate__(self):
        return self.rows, self.base

    def __setstate__(self, state) -> None:
        self._load(*state)

    def blocks(self, key: str):
        """``file, offset, length`` of the blocks that may hold the key, by two bisections."""
        for last, first, file, offset, length in self.rows[bisect_left(self.last, key) :]:
            if first > key:
                return
            own = self._blocks(file, offset, length)
            for m in own[bisect_left(own, key, key=lambda m: m[1]) :]:
                if m[0] > key:
                    return
                yield file, m[2], m[3]

    def entries(self, key: str):
        for place in self.blocks(key):
            yield from _of_key(read_block(self.base, *place), key)

    def lookup(self, url: str) -> list[dict]:
        """The records of a URL, payloads of revisits from the responses they refer to."""
        found = []
        for e in self.entries(url_key(_header(url))):
            r = read_record(files.read_range(self.base, e[3], e[4], e[5]))
            if r["record_type"] == "revisit":
                for o in self.entries(url_key(r["refers_url"])):
                    if o[2] == r["refers_to"] and o[6] == "response":
                        first = read_record(files.read_range(self.base, o[3], o[4], o[5]))
                        if first["payload_digest"] == r["payload_digest"]:
                            r["payload"] = first["payload"]
                            break
                else:
                    raise ValueError(f"no response to the revisit of page {r['page_id']}")
            found.append({"url": e[1]} | r)
        return found


def _of_key(entries: list[list], key: str) -> list[list]:
    own = lambda e: e[0]
    return entries[bisect_left(entries, key, key=own) : bisect_right(entries, key, key=own)]


def look_up(keys: DataFrame, directory: DataFrame, base: str) -> DataFrame:
    """All records (see ``RECORD``) of the distinct keys in ``key``. The keys go through the
    directory in their order; what is then read is dealt by block among the tasks."""
    index = CaptureIndex(directory, base)

    def find(batches):
        for b in batches:
            found = [(k, *place) for k in b.column(0).to_pylist() for place in index.blocks(k)]
            if found:
                k, f, o, n = map(list, zip(*found, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(f), pa.array(o, pa.int64()), pa.array(n, pa.int64())], names=["key", "file", "offset", "length"])

    def read(batches):
        rows = (r for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True))
        for place, own in groupby(rows, key=lambda r: r[1:]):
            block, out, opened, now = read_block(base, *place), [], None, None
            todo = [e for k, *_ in own for e in _of_key(block, k)]
            for _, url, page, name, at, n, _ in sorted(todo, key=lambda e: (e[3], e[4])):
                if name != now:
                    if opened:
                        opened.close()
                    opened, now = files.open_file(base, name), name
                opened.seek(at)
                r = read_record(opened.read(n))
                if r["page_id"] != page:
                    raise ValueError(f"the index and {name} differ at {at}")
                out.append((page, url, r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]))
            if opened:
                opened.close()
                cols = [pa.array(c, t) for c, t in zip(map(list, zip(*out, strict=True)), (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64()), strict=True)]
                yield pa.RecordBatch.from_arrays(cols, names=["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to"])

    count = directory.agg(F.sum("n_blocks")).first()[0] or 1
    places = keys.select("key").distinct().repartitionByRange("key").sortWithinPartitions("key").mapInArrow(find, "key string, file string, offset long, length long")
    places = places.repartition(min(count, 20_000), "file", "offset").sortWithinPartitions("file", "offset", "key")
    return places.mapInArrow(read, RECORD)


def op1_warc_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = f"{scratch_dir(spark)}/warc"
    entries = write_archives(spark.read.parquet(f"{sf_dir}/pages.parquet"), base)
    found = look_up(entries.select("key"), write_index(entries, base), base)
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h, sha256(coalesce(html, '')) AS d, octet_length(encode(coalesce(html, ''))) AS n FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY d) AS first FROM p)
SELECT page_id, n AS payload_bytes, d AS payload_digest,
       CASE WHEN n >= 100 AND page_id <> first THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 100 AND page_id <> first THEN first END AS refers_to
FROM f
"""
