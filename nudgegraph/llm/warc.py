"""WARC archives: a writer and a salvage reader.

The writer makes one gzip member a record and rolls to a new file at a target
size, so that a file, which the reader holds whole, stays small. A file's name
holds its task attempt; only files named in the manifest, which is a table
that successful tasks alone write, belong to the archive.

The reader walks members (or bare records). Where a check fails it looks for
the next gzip magic or version line from which a whole record can be read and
reports the bytes between as a gap.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.llm.text import need
from nudgegraph.session import Scratch, scratch_path

_START = re.compile(rb"\x1f\x8b\x08|WARC/1\.")


def _record(kind: str, page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    head = [f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'none' if page_id is None else page_id}:{kind}>", "WARC-Date: 2024-01-01T00:00:00Z"]
    if url is not None:
        head.append("WARC-Target-URI: " + re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url))
    if page_id is not None:
        head.append(f"X-Page-ID: {page_id}")
    head += [f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}"]
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}:response>"]
        body = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    else:
        body = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload) + payload
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}"]
    return b"WARC/1.1\r\n" + "\r\n".join(head).encode("utf-8", "surrogatepass") + b"\r\n\r\n" + body + b"\r\n\r\n"


def gzip_member(data: bytes, level: int = 4) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def _parsed(data: bytes, at: int) -> tuple[int, dict[str, str], bytes] | None:
    """(end, headers, payload) of the bare record at ``at``, if all checks hold."""
    if data[at : at + 7] != b"WARC/1.":
        return None
    stop = data.find(b"\r\n\r\n", at)
    if stop < 0:
        return None
    headers = {}
    for line in data[at:stop].split(b"\r\n")[1:]:
        name, colon, value = line.partition(b":")
        if not colon:
            return None
        headers[name.strip().lower().decode("latin-1")] = value.strip().decode("utf-8", "replace")
    size = headers.get("content-length", "")
    if not size.isdigit():
        return None
    begin, end = stop + 4, stop + 4 + int(size)
    if data[end : end + 4] != b"\r\n\r\n":
        return None
    _, blank, payload = data[begin:end].partition(b"\r\n\r\n")
    if not blank:
        return None
    if headers.get("warc-type") == "response" and headers.get("warc-payload-digest") != "sha1:" + hashlib.sha1(payload).hexdigest():
        return None
    return end + 4, headers, payload


def _unit(data: bytes, at: int) -> tuple[int, list[tuple[dict[str, str], bytes]]] | None:
    """End and records of the gzip member or bare record at ``at``; None if a check fails."""
    if data[at : at + 3] == b"\x1f\x8b\x08":
        z = zlib.decompressobj(31)
        try:
            # fed in steps, so that a false start costs little
            out, pos, step = [], at, 1 << 16
            while not z.eof:
                piece = data[pos : pos + step]
                if not piece:
                    return None
                out.append(z.decompress(piece))
                pos += len(piece)
            plain, end = b"".join(out), pos - len(z.unused_data)
        except zlib.error:
            return None
        records, inner = [], 0
        while inner < len(plain):
            one = _parsed(plain, inner)
            if one is None:
                return None
            inner = one[0]
            records.append(one[1:])
        return end, records
    one = _parsed(data, at)
    return None if one is None else (one[0], [one[1:]])


def salvage(data: bytes) -> Iterator[tuple[int, int, dict[str, str] | None, bytes]]:
    """(start, end, headers, payload) of records in order; headers are None for a gap."""
    at, n = 0, len(data)
    while at < n:
        unit = _unit(data, at)
        if unit is None:
            start = at
            for m in _START.finditer(data, at + 1):
                if (unit := _unit(data, m.start())) is not None:
                    at = m.start()
                    break
            else:
                at = n
            yield start, at, None, b""
            if unit is None:
                return
        end, records = unit
        for headers, payload in records:
            yield at, end, headers, payload
        at = end


def _store(path: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(re.sub(r"^file:/(?!/)", "file:///", path))


def write_archives(pages: DataFrame, folder: str, *, least_revisit: int = 1000, roll_bytes: int = 16 << 20) -> DataFrame:
    """Write a record for every row of (page_id, url, html); the manifest as a lazy frame.

    Equal payloads of at least ``least_revisit`` bytes are stored once, under
    the largest page id; the rest become revisit records. Manifest: (path,
    n_records, n_bytes). The caller keeps the manifest as a table before use.
    """
    own = need(pages, "page_id", "url", "html").withColumn("payload", F.encode(F.coalesce("html", F.lit("")), "UTF-8"))
    own = own.withColumn("n", F.octet_length("payload")).withColumn("digest", F.sha1("payload")).drop("html")
    found = own.where(F.col("n") >= least_revisit).groupBy("digest").agg(F.max("page_id").alias("winner"), F.count("*").alias("copies")).where("copies > 1 and winner is not null")
    found = found.select(F.col("digest").alias("of"), "winner").hint("shuffle_hash")
    marked = own.join(found, F.col("digest") == F.col("of"), "left")
    marked = marked.select("page_id", "url", "payload", "digest", F.expr("case when winner is not null and not (winner <=> page_id) then winner end").alias("refers_to"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, root = _store(folder)
        store.create_dir(root, recursive=True)
        attempt = TaskContext.get().taskAttemptId()
        done, part, out, n, size = [], 0, None, 0, 0
        for batch in batches:
            for page_id, url, payload, digest, refers_to in zip(*batch.columns, strict=True):
                if out is None:
                    path = f"{root}/part-{attempt}-{part}.warc.gz"
                    out, n, size, part = store.open_output_stream(path, compression=None), 0, 0, part + 1
                target = refers_to.as_py()
                member = gzip_member(_record("response" if target is None else "revisit", page_id.as_py(), url.as_py(), payload.as_py(), digest.as_py(), target))
                out.write(member)
                n, size = n + 1, size + len(member)
                if size >= roll_bytes:
                    out.close()
                    done.append((path, n, size))
                    out = None
        if out is not None:
            out.close()
            done.append((path, n, size))
        paths, counts, sizes = zip(*done, strict=True) if done else ((), (), ())
        prefix = folder[: len(folder) - len(root)] if folder.endswith(root) else ""
        yield pa.RecordBatch.from_arrays([pa.array([prefix + p for p in paths], pa.string()), pa.array(counts, pa.int64()), pa.array(sizes, pa.int64())], ["path", "n_records", "n_bytes"])

    return marked.mapInArrow(run, "path string, n_records long, n_bytes long")


def read_archives(manifest: DataFrame) -> DataFrame:
    """Every record and gap of the archives at ``manifest.path``.

    (path, start, end, gap, page_id, url, payload_bytes, payload_digest,
    record_type, refers_to, payload); a gap has nulls from page_id on. A
    revisit's payload is null, its digest and length come from its headers.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["path", "start", "end", "gap", "page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]
        kinds = [pa.string(), pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]

        def out(rows):
            columns = list(zip(*rows, strict=True)) if rows else [()] * len(names)
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)

        for batch in batches:
            for path in batch.column(0).to_pylist():
                store, inner = _store(path)
                with store.open_input_file(inner) as f:
                    data = f.readall()
                rows, held = [], 0
                for start, end, headers, payload in salvage(data):
                    if headers is None:
                        rows.append((path, start, end, True, *[None] * 7))
                        continue
                    number = lambda x: int(x) if x is not None and x.lstrip("-").isdigit() else None
                    kind = headers.get("warc-type")
                    revisit = kind == "revisit"
                    target = re.fullmatch(r"<urn:page:(-?\d+):response>", headers.get("warc-refers-to", ""))
                    digest = headers.get("warc-payload-digest", "").removeprefix("sha1:") if revisit else hashlib.sha1(payload).hexdigest()
                    size = number(headers.get("x-payload-length")) if revisit else len(payload)
                    rows.append((path, start, end, False, number(headers.get("x-page-id")), headers.get("warc-target-uri"), size, digest, kind, int(target[1]) if target else None, None if revisit else payload))
                    held += len(payload)
                    if held > 8 << 20:
                        yield out(rows)
                        rows, held = [], 0
                yield out(rows)

    schema = "path string, start long, end long, gap boolean, page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"
    return manifest.select("path").repartition(max(1, manifest.count())).mapInArrow(run, schema)


def warc_round_trip(pages: DataFrame, *, least_revisit: int = 1000) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to) per row, from archives written and read back.

    A null html is an empty payload, a null url has no target header, a null
    page id comes back as null and is never the one that others refer to. Rows
    that repeat both page id and payload are all what the first of them is. An
    empty table writes no archive.
    """
    spark = pages.sparkSession
    scratch = Scratch(spark, "warc")
    manifest = scratch.keep(write_archives(pages, scratch_path(spark, "warc-files"), least_revisit=least_revisit), "manifest")
    return read_archives(manifest).where("not gap").select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE = """
with p as (select page_id, encode(coalesce(html, '')) as payload from pages),
q as (select page_id, octet_length(payload)::bigint as n, sha1(payload) as digest from p),
w as (select digest, max(page_id) as winner from q where n >= 1000 group by digest)
select q.page_id, q.n as payload_bytes, q.digest as payload_digest,
       case when w.winner is null or w.winner = q.page_id then 'response' else 'revisit' end as record_type,
       case when w.winner is null or w.winner = q.page_id then null else w.winner end as refers_to
from q left join w on w.digest = q.digest and q.n >= 1000
"""
