"""Deterministic, sharded WARC writer and reader.

Records are dealt into ranges of ``(page_id, payload digest)`` of about equal payload size,
sorted inside a range, and written to files that roll at a compressed size. Range bounds are
weighted quantiles of keys that a hash of the key picks in proportion to their bytes, so they
depend on the data alone, neither on gaps between ids nor on partitions; a ``page_id`` with many
payloads is split. Every record is its own gzip member; headers and digests are made anew. Of records with equal payloads the one with the
smallest ``page_id`` is a ``response``, the others are ``revisit`` records that refer to it.

Tasks write under temporary names that hold the attempt, so lost or repeated attempts do no
harm; only the files of successful attempts are renamed, and the manifest, written last and
renamed in one step, makes an archive valid. Files go through a file-system URI, so any store
that the workers can reach serves.
"""

from __future__ import annotations

import base64
import hashlib
import json
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyarrow.fs import FileSelector
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetspark.llm.store import discard, fresh_path, ship, written

END = b"\r\n\r\n"


@dataclass(frozen=True)
class WarcParams:
    """``least_bytes``: smaller payloads are always responses. Times are fixed for determinism.

    A range holds about ``shard_bytes``, more where that would make over ``max_shards`` ranges;
    about ``bound_keys`` keys come to the driver to set the bounds.
    """

    shard_bytes: int = 24_000_000
    roll_bytes: int = 8_000_000
    max_shards: int = 4096
    bound_keys: int = 60_000
    least_bytes: int = 0
    date: str = "2024-01-01T00:00:00Z"
    level: int = 6


def file_system(uri: str):
    """A pyarrow file system and the path inside it."""
    from pyarrow import fs

    if uri.startswith("file:/"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_bytes(page_id: int, url: str | None, payload: bytes, digest: str, refers_to: int | None, p: WarcParams) -> bytes:
    """One WARC record, uncompressed. Its id is a name-based UUID of ``page_id``."""
    clean = lambda u: " ".join((u or "about:blank").split())
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: " + str(len(payload)).encode() + END
    block = http if refers_to is not None else http + payload
    lines = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_OID, f'page:{page_id}')}>",
        f"WARC-Date: {p.date}",
        f"WARC-Target-URI: {clean(url)}",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"WARC-Block-Digest: sha1:{payload_digest(block)}",
        f"X-Page-ID: {page_id}",
    ]
    if refers_to is not None:
        lines += [
            "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest",
            f"WARC-Refers-To: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_OID, f'page:{refers_to}')}>",
            f"X-Refers-To-Page-ID: {refers_to}",
        ]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + END + block + END


def gzip_member(data: bytes, level: int) -> bytes:
    packer = zlib.compressobj(level, zlib.DEFLATED, 31)  # no name, no time: equal bytes on every run
    return packer.compress(data) + packer.flush()


def read_records(data: Iterator[bytes]) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of every record of a WARC file of gzip members."""
    rest, out, unpack = b"", b"", zlib.decompressobj(31)
    for chunk in data:
        rest += chunk
        while rest:
            out += unpack.decompress(rest)
            rest = unpack.unused_data
            if not unpack.eof:
                rest = b""
                break
            head, _, tail = out.partition(END)
            headers = dict(x.split(": ", 1) for x in head.decode().split("\r\n")[1:])
            size = int(headers["Content-Length"])
            if len(tail) != size + len(END) or not tail.endswith(END):
                raise ValueError("broken record")
            yield headers, tail[:size]
            out, unpack = b"", zlib.decompressobj(31)
    if out:
        raise ValueError("the file ends inside a record")


def _told(chunks: Iterator[bytes], total) -> Iterator[bytes]:
    """The chunks as they are, each added to a running digest."""
    for chunk in chunks:
        total.update(chunk)
        yield chunk


WRITTEN = "shard int, part int, temporary string, records long, bytes long, sha256 string"


def _writer(folder: str, p: WarcParams):
    names = [x.split()[0] for x in WRITTEN.split(", ")]

    def run(batches):
        files, handle, size = [], None, 0
        fs, root = file_system(folder)
        attempt = f"{TaskContext.get().taskAttemptId()}-{uuid.uuid4().hex}"
        shard, part, count, total = None, 0, 0, None

        def close():
            nonlocal handle
            if handle is not None:
                handle.close()
                files.append((shard, part, name, count, size, total.hexdigest()))
                handle = None

        def put(row):
            nonlocal handle, size, shard, part, count, total, name
            page_shard, page_id, url, html, digest, refers_to = row
            if page_shard != shard:
                close()
                shard, part = page_shard, 0
            elif handle is not None and size >= p.roll_bytes:
                close()
                part += 1
            if handle is None:
                name = f"{root}/_temporary-{shard:06d}-{part:05d}-{attempt}"
                handle, size, count, total = fs.open_output_stream(name), 0, 0, hashlib.sha256()
            data = gzip_member(record_bytes(page_id, url, html, digest, refers_to, p), p.level)
            handle.write(data)
            total.update(data)
            size += len(data)
            count += 1

        name = None
        told: tuple = (None, None)  # the rows of a payload are preceded by one that says to what it refers
        for batch in batches:
            for s, page_id, kind, url, html, digest, size_of, refers_to in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                key = page_id, digest, size_of
                if kind == 0:
                    told = (key, refers_to)
                else:
                    put((s, page_id, url, (html or "").encode(), base64.b32encode(digest).decode(), told[1] if told[0] == key else None))
        close()
        kinds = [pa.int32(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.string()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*files, strict=True) if files else [[]] * 6, kinds, strict=True)], names)

    return run


#: The leading bits of a payload's digest: orders the payloads of one page.
TIE = "cast(conv(substring(hex(digest), 1, 15), 16, 10) as long)"


def _bounds(keys: DataFrame, p: WarcParams) -> list[tuple[int, int]]:
    """First keys of all ranges but the lowest: quantiles of ``(page_id, TIE)`` weighted by bytes.

    A key of weight w stands for max(w, step) bytes and is picked with probability min(1, w / step),
    by its hash; step is the total over ``bound_keys``.
    """
    weight = (F.col("size") + 400) * F.col("n")
    total = int(keys.agg(F.sum(weight)).first()[0] or 0)
    share = max(p.shard_bytes, -(-total // p.max_shards))
    if total <= share:
        return []
    step = max(1, total // p.bound_keys)
    draw = F.pmod(F.xxhash64("page_id", "digest", "size"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    picked = keys.select("page_id", F.expr(TIE).alias("tie"), weight.alias("weight"), draw.alias("draw")).where(F.col("draw") * step < F.col("weight"))
    bounds, filled = [], 0
    for page_id, tie, w in sorted(tuple(r) for r in picked.select("page_id", "tie", "weight").collect()):
        w = max(w, step)
        if filled and filled + w > share and (page_id, tie) not in bounds[-1:]:
            bounds.append((page_id, tie))
            filled = 0
        filled += w
    return bounds


def _shard_of(bounds: list[tuple[int, int]]):
    """The number of bounds at or below a key."""
    ids, ties = (np.array([b[i] for b in bounds], dtype=np.int64) for i in (0, 1))

    def place(page_id: pd.Series, tie: pd.Series) -> pd.Series:
        page, rest = page_id.to_numpy(), tie.to_numpy()
        low, high = np.searchsorted(ids, page, "left"), np.searchsorted(ids, page, "right")
        out = low.copy()
        inside = np.flatnonzero(low < high)
        for start in np.unique(low[inside]):  # ids that bounds split
            own = inside[low[inside] == start]
            out[own] += np.searchsorted(ties[start : high[own[0]]], rest[own], "right")
        return pd.Series(out.astype(np.int32))

    return F.pandas_udf(place, "int")


def write_archive(pages: DataFrame, folder: str, p: WarcParams = WarcParams()) -> str:
    """Write ``page_id, url, html`` rows as WARC files under ``folder``; returns the manifest's path.

    A null html is an empty payload, a null url is written as ``about:blank``. Rows without
    ``page_id`` cannot be named and are left out; rows that repeat a ``page_id`` are all
    written, and refer only to a smaller page's equal payload. An empty table gives a manifest
    without files; other columns are not looked at. What failed attempts left is removed.
    """
    spark = pages.sparkSession
    ship(spark)
    fs, root = file_system(folder)
    fs.create_dir(root, recursive=True)
    html = F.coalesce(F.col("html").cast("string"), F.lit(""))
    rows = pages.where("page_id is not null").select(
        F.col("page_id").cast("long").alias("page_id"),
        F.col("url").cast("string").alias("url"),
        html.alias("html"),
        F.unhex(F.sha1(html.cast("binary"))).alias("digest"),
        F.octet_length(html).cast("long").alias("size"),
    )
    keys = written(rows.groupBy("page_id", "digest", "size").agg(F.count("*").alias("n")), "warc-keys")
    bounds = _bounds(keys, p)

    # what each payload refers to: equal payloads are found by digest and size, without their text
    firsts = keys.where(F.col("size") >= p.least_bytes).groupBy("digest", "size").agg(F.min("page_id").alias("first"), F.count("*").alias("pages")).where("pages > 1")
    refers = keys.join(firsts, ["digest", "size"]).where("page_id <> first").select("page_id", "digest", "size", F.col("first").alias("refers_to"))
    # records and what they refer to travel in one shuffle and meet in the writer
    null = F.lit(None).cast("string")
    both = rows.select("page_id", F.lit(1).alias("kind"), "url", "html", "digest", "size", F.lit(None).cast("long").alias("refers_to")).unionByName(
        refers.select("page_id", F.lit(0).alias("kind"), null.alias("url"), null.alias("html"), "digest", "size", "refers_to")
    )
    placed = both.select(_shard_of(bounds)("page_id", F.expr(TIE)).alias("shard"), "page_id", "kind", "url", "html", "digest", "size", "refers_to")
    sorted_rows = placed.repartitionById(len(bounds) + 1, F.col("shard")).sortWithinPartitions("shard", "page_id", "digest", "size", "kind", "url")
    done = sorted(sorted_rows.mapInArrow(_writer(folder, p), WRITTEN).collect())  # one row per file
    discard(keys)
    files = []
    for f in done:
        final = f"part-{f['shard']:06d}-{f['part']:05d}.warc.gz"
        fs.move(f["temporary"], f"{root}/{final}")
        files.append({"name": final, "shard": f["shard"], "records": f["records"], "bytes": f["bytes"], "sha256": f["sha256"]})
    manifest = json.dumps({"format": "WARC/1.1", "files": files, "records": sum(f["records"] for f in files)}, indent=1)
    with fs.open_output_stream(f"{root}/_manifest.tmp") as out:
        out.write(manifest.encode())
    fs.move(f"{root}/_manifest.tmp", f"{root}/manifest.json")
    for left in fs.get_file_info(FileSelector(root)):
        if left.base_name.startswith("_temporary-"):
            fs.delete_file(left.path)
    return f"{folder}/manifest.json"


RECORDS = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long"


def read_archive(spark: SparkSession, folder: str) -> DataFrame:
    """Every record of a committed archive; files are checked against the manifest, blocks and responses against their digests.

    A revisit's size and digest are those of the full payload, which its headers hold.
    """
    ship(spark)
    fs, root = file_system(folder)
    with fs.open_input_stream(f"{root}/manifest.json") as f:
        files = [(x["name"], x["sha256"]) for x in json.loads(f.read())["files"]]
    names = [x.split()[0] for x in RECORDS.split(", ")]
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64()]

    def parse(headers, block):
        head, _, payload = block.partition(END)
        size = int(dict(x.split(": ", 1) for x in head.decode().split("\r\n")[1:])["Content-Length"])
        digest = headers["WARC-Payload-Digest"].removeprefix("sha1:")
        if headers["WARC-Block-Digest"] != f"sha1:{payload_digest(block)}":
            raise ValueError("block digest differs")
        if headers["WARC-Type"] == "response" and (payload_digest(payload) != digest or len(payload) != size):
            raise ValueError("payload digest differs")
        refers = headers.get("X-Refers-To-Page-ID")
        return int(headers["X-Page-ID"]), headers["WARC-Target-URI"], size, digest, headers["WARC-Type"], None if refers is None else int(refers)

    def run(batches):
        fs, root = file_system(folder)
        for batch in batches:
            for name, sha256 in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows, total = [], hashlib.sha256()
                with fs.open_input_stream(f"{root}/{name}", compression=None) as f:
                    for headers, block in read_records(_told(iter(lambda: f.read(1 << 20), b""), total)):
                        rows.append(parse(headers, block))
                        if len(rows) == 5000:
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)
                            rows = []
                if total.hexdigest() != sha256:
                    raise ValueError(f"{name} differs from the manifest")
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    listed = spark.createDataFrame(files, "name string, sha256 string")
    return listed.repartition(max(1, len(files)), "name").mapInArrow(run, RECORDS)


def archive_and_read(pages: DataFrame, p: WarcParams = WarcParams()) -> DataFrame:
    """Write the pages into a fresh archive of the shared folder and read it back."""
    folder = fresh_path(pages.sparkSession, "warc")
    write_archive(pages, folder, p)
    return read_archive(pages.sparkSession, folder)
