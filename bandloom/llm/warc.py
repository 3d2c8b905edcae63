"""WARC: a deterministic sharded writer and its reader.

Records are dealt to shards by ranges of (page_id, payload hash) whose bounds come from a hash-chosen sample of keys, so
they do not depend on how the input is partitioned; inside a shard they are sorted, and a shard rolls to a new file when
the compressed size reaches ROLL_BYTES. Every record is a gzip member of its own with regenerated headers and digests.
Files start with a warcinfo record, are written under temporary names and renamed when complete; each task returns the
lines of the manifest, which is written last and is the only list that readers follow. A retried task has the same bytes for
the same name: a finished file of that size stays, any other is replaced. Temporaries of lost tasks are removed at the end.

Of records with equal payloads of at least MIN_DUPLICATE bytes, that with the largest page_id is a response and the
others are revisit records that refer to it, by its record id, target URI and date (and by page id, in a field of ours).
Payloads cross one shuffle; the decisions are made on (page_id, digest, size, url) rows, and join the payloads in the writer
as marker rows that sort before their records; a digest that very many pages share is one side's hot key, which adaptive
execution splits.

Defined results: null html is an empty payload; a null page_id sorts first, is written without that header and is a
response unless its payload has a response with an id; rows that repeat the chosen page_id and payload are all
responses, and revisits name the one with the least URL; ties are sorted by URL; an empty table writes an empty manifest; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import itertools
import uuid
import zlib
from urllib.parse import quote

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandloom.runtime import scratch, ship

ROLL_BYTES = 8 << 20
SHARD_BYTES = 64 << 20
SMALL_SHARD_ROWS = 2000
MIN_DUPLICATE = 0
SAMPLE = 20_000
DATE = "2024-01-01T00:00:00Z"
MANIFEST = "shard int, file string, n_records long, n_bytes long, sha256 string"
READ = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string, file string"
NULL_ID = -(1 << 63)


def sha1_base32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_id(page_id: int | None, digest: str, url: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{page_id} {digest} {url}')}>"


def target_of(url: str | None) -> str:
    return quote(url or "", safe=":/?#[]@!$&'()*+,;=%-._~")


def info_record(name: str, date: str = DATE) -> bytes:
    """The warcinfo record at the head of a file."""
    block = b"software: bandloom\r\nformat: WARC File Format 1.1\r\n"
    lines = ["WARC/1.1", "WARC-Type: warcinfo", f"WARC-Record-ID: {record_id(None, sha1_base32(block), name)}", f"WARC-Date: {date}", f"WARC-Filename: {name}"]
    lines += [f"WARC-Block-Digest: sha1:{sha1_base32(block)}", "Content-Type: application/warc-fields", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, date: str = DATE, refers_url: str | None = None) -> bytes:
    """One record's bytes, not yet compressed; refers_to (a page and its url) makes it a revisit."""
    digest, target = sha1_base32(payload), target_of(url)
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = head if refers_to is not None else head + payload
    kind = "response" if refers_to is None else "revisit"
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {record_id(page_id, digest, target)}", f"WARC-Date: {date}", f"WARC-Target-URI: {target}"]
    if page_id is not None:
        lines.append(f"Page-ID: {page_id}")
    if refers_to is not None:
        first = target_of(refers_url)
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(refers_to, digest, first)}"]
        lines += [f"WARC-Refers-To-Target-URI: {first}", f"WARC-Refers-To-Date: {date}", f"Refers-To-Page-ID: {refers_to}"]
    lines += [f"Payload-Length: {len(payload)}", f"WARC-Payload-Digest: sha1:{digest}", f"WARC-Block-Digest: sha1:{sha1_base32(block)}"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def gzip_member(data: bytes) -> bytes:
    """A gzip member without time or name: equal input, equal bytes."""
    c = zlib.compressobj(6, zlib.DEFLATED, 31)
    return c.compress(data) + c.flush()


def read_records(raw: bytes):
    """(headers, block) of each record of an archive; checks lengths and digests."""
    while raw:
        d = zlib.decompressobj(31)
        data = d.decompress(raw) + d.flush()
        raw = d.unused_data
        head, _, rest = data.partition(b"\r\n\r\n")
        version, *lines = head.decode().split("\r\n")
        headers = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in lines)
        block = rest[: int(headers["Content-Length"])]
        if not version.startswith("WARC/") or len(rest) != len(block) + 4 or headers["WARC-Block-Digest"] != f"sha1:{sha1_base32(block)}":
            raise ValueError(f"damaged record {headers.get('WARC-Record-ID')}")
        yield headers, block


def store(folder: str) -> tuple[pyarrow.fs.FileSystem, str]:
    return pyarrow.fs.FileSystem.from_uri(folder if "://" in folder or folder.startswith("file:") else f"file://{folder}")


class ShardWriter:
    """Rolls the files of one shard; complete files get their names, unfinished ones never do."""

    def __init__(self, folder: str, shard: int, roll: int, date: str = DATE):
        self.fs, self.path = store(folder)
        self.shard, self.roll, self.seq, self.lines, self.date = shard, roll, 0, [], date
        self.buffer, self.size, self.n = [], 0, 0

    @property
    def name(self) -> str:
        return f"shard-{self.shard:05d}-{self.seq:05d}.warc.gz"

    def add(self, data: bytes) -> None:
        if not self.n:
            self.buffer.append(gzip_member(info_record(self.name, self.date)))
        member = gzip_member(data)
        self.buffer.append(member)
        self.size += len(member)
        self.n += 1
        if self.size >= self.roll:
            self.close()

    def close(self) -> None:
        if not self.n:
            return
        name, raw = self.name, b"".join(self.buffer)
        temporary, final = f"{self.path}/.{name}.{uuid.uuid4().hex}", f"{self.path}/{name}"
        with self.fs.open_output_stream(temporary, compression=None) as f:
            f.write(raw)
        there = self.fs.get_file_info(final)
        if there.type == pyarrow.fs.FileType.File and there.size == len(raw):
            self.fs.delete_file(temporary)  # an earlier attempt of this task got here
        else:
            if there.type == pyarrow.fs.FileType.File:
                self.fs.delete_file(final)
            self.fs.move(temporary, final)
        self.lines.append((self.shard, name, self.n, len(raw), hashlib.sha256(raw).hexdigest()))
        self.seq += 1
        self.buffer, self.size, self.n = [], 0, 0


def revisits(keys: DataFrame, least: int) -> DataFrame:
    """digest, response and response_url: the page that represents each payload that occurs more than once."""
    # ~ reverses the order of longs: the largest page, and of its rows the least url.
    first = F.min(F.when(F.col("page_id").isNotNull(), F.struct(F.bitwise_not("page_id").alias("p"), F.coalesce("url", F.lit("")).alias("u")))).alias("first")
    groups = keys.where(F.col("n_bytes") >= least).groupBy("digest").agg(first, F.count("*").alias("n")).where("n > 1 and first is not null")
    return groups.select("digest", F.bitwise_not("first.p").alias("response"), F.col("first.u").alias("response_url"))


def write_warc(pages: DataFrame, folder: str, least: int = MIN_DUPLICATE, roll: int = ROLL_BYTES, shard_bytes: int = SHARD_BYTES, date: str = DATE) -> DataFrame:
    """Write the archives; returns the manifest (MANIFEST), which is also at folder/manifest."""
    spark = pages.sparkSession
    ship(spark)
    html = F.coalesce("html", F.lit(""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", html.alias("html"), F.sha1(html.cast("binary")).alias("digest"), F.octet_length(html).cast("long").alias("n_bytes"))
    keys = rows.select("page_id", "digest", "n_bytes", "url")
    order = F.coalesce("page_id", F.lit(NULL_ID))
    total, n_rows = keys.agg(F.coalesce(F.sum("n_bytes"), F.lit(0)), F.count("*")).first()
    n_shards = max(1, -(-total // shard_bytes), min(64, n_rows // SMALL_SHARD_ROWS))
    # Bounds from a sample by hash: the same for every partitioning of the input; it places rows and drops none.
    chosen = keys.where(F.pmod(F.xxhash64("page_id", "digest"), F.lit(1 << 20)) < max(1, min(1.0, SAMPLE / max(n_rows, 1)) * (1 << 20)))
    rows_seen = sorted({tuple(r) for r in chosen.select(order, F.xxhash64("digest"), "n_bytes").limit(8 * SAMPLE).collect()})
    sample = np.array(rows_seen, np.int64).reshape(-1, 3)
    load = np.cumsum(sample[:, 2] + 512)
    cuts = sample[np.searchsorted(load, [load[-1] * i // n_shards for i in range(1, n_shards)]), :2] if len(sample) else sample[:, :2]
    cut_keys = [tuple(c) for c in cuts.tolist()]

    @F.pandas_udf("int")
    def shard_of(page: pd.Series, spread: pd.Series) -> pd.Series:
        first = np.array([c[0] for c in cut_keys], np.int64)
        lo, hi = np.searchsorted(first, page.to_numpy(), "left"), np.searchsorted(first, page.to_numpy(), "right")
        out = hi.copy()
        for k in np.flatnonzero(hi > lo):  # only where a bound has the same page_id
            own = page.iat[k], spread.iat[k]
            out[k] = lo[k] + sum(c <= own for c in cut_keys[lo[k] : hi[k]])
        return pd.Series(out, dtype="int32")

    def dealt(df: DataFrame) -> DataFrame:
        return df.withColumn("shard", shard_of(order, F.xxhash64("digest")))

    markers = keys.join(revisits(keys, least), "digest").where(~F.col("page_id").eqNullSafe(F.col("response"))).select("page_id", "digest", "response", "response_url").distinct()
    both = dealt(rows.select("page_id", "url", "html", "digest", F.lit(None).cast("long").alias("response"))).unionByName(
        dealt(markers.select("page_id", F.col("response_url").alias("url"), F.lit(None).cast("string").alias("html"), "digest", "response"))
    )
    sorted_rows = both.repartitionById(n_shards, F.col("shard")).sortWithinPartitions("shard", "page_id", "digest", F.col("html").isNotNull(), "url")

    def run(it):
        rows = ((r["shard"], r["page_id"], r["url"], r["html"], r["digest"], r["response"]) for b in it for s in range(0, b.num_rows, 256) for r in b.slice(s, 256).to_pylist())
        for shard, own in itertools.groupby(rows, key=lambda r: r[0]):
            out, key, response, its_url = ShardWriter(folder, shard, roll, date), None, None, None
            for _, page_id, url, text, digest, marked in own:
                if key != (page_id, digest):
                    key, response = (page_id, digest), None
                if text is None:
                    response, its_url = marked, url
                    continue
                out.add(record(page_id, url, text.encode(), response, date, its_url))
            out.close()
            cols = list(zip(*out.lines, strict=True)) or [[]] * 5
            kinds = [pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["shard", "file", "n_records", "n_bytes", "sha256"])

    fs, path = store(folder)
    fs.create_dir(path, recursive=True)
    sorted_rows.mapInArrow(run, MANIFEST).write.parquet(f"{folder}/manifest")
    for f in fs.get_file_info(pyarrow.fs.FileSelector(path)):
        if f.base_name.startswith(".shard-"):
            fs.delete_file(f.path)
    return spark.read.schema(MANIFEST).parquet(f"{folder}/manifest")


def read_warc(manifest: DataFrame, folder: str) -> DataFrame:
    """READ rows of every record in the files that the manifest lists; digests are recomputed and compared."""
    spark = manifest.sparkSession
    ship(spark)

    def run(it):
        fs, path = store(folder)
        for batch in it:
            for name, want in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                with fs.open_input_stream(f"{path}/{name}", compression=None) as f:
                    raw = f.read()
                if hashlib.sha256(raw).hexdigest() != want:
                    raise ValueError(f"{name} differs from its manifest line")
                out = []
                for h, block in read_records(raw):
                    if h["WARC-Type"] == "warcinfo":
                        continue
                    payload = block.partition(b"\r\n\r\n")[2]
                    digest = h["WARC-Payload-Digest"].removeprefix("sha1:")
                    if h["WARC-Type"] == "response" and (sha1_base32(payload) != digest or len(payload) != int(h["Payload-Length"])):
                        raise ValueError(f"{name}: payload of {h['WARC-Record-ID']} is damaged")
                    number = lambda k, h=h: int(h[k]) if k in h else None
                    out.append((number("Page-ID"), int(h["Payload-Length"]), digest, h["WARC-Type"], number("Refers-To-Page-ID"), h["WARC-Target-URI"], name))
                kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string()]
                cols = list(zip(*out, strict=True)) or [[]] * len(kinds)
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "file"])

    files = manifest.select("file", "sha256")
    return files.repartition(max(1, files.count())).mapInArrow(run, READ)


def warc_round_trip(pages: DataFrame) -> DataFrame:
    folder = scratch(pages.sparkSession, "warc")
    return read_warc(write_warc(pages, folder), folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
