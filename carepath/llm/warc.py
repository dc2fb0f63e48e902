"""A deterministic, sharded WARC writer and its reader.

Records are sorted by page id over ranges that depend on the rows alone: bytes are counted in bins of the id range, a bin that holds
more than a shard is parted again until it fits, one id (or none) by the digests of its payloads, and the parts are packed into
shards in order. Within a shard files are rolled where the running compressed size passes ``roll_bytes``,
so the same rows give the same files whatever the cluster. Every record is a gzip member of its own; headers, record
ids and digests are made anew from the payload. Of equal payloads one is stored, the others are revisit records.

Files are written by Spark's text writer through whatever file system the folder is in, under a temporary folder; then
they get their names by renaming, and the manifest (names and sizes) is renamed into place last. Readers open what the
manifest lists and nothing else, so a lost job leaves no half archive behind.

A text writer ends each row with a separator. A gzip member of less than 16 MiB of data ends with a zero byte, the top of
its length; that byte is left to the separator, and longer members are followed by an empty one that ends alike.

Defined cases: a null html is the empty payload; a null url leaves its header out; rows without an id come first and are
never referred to; rows that repeat the smallest id of their payload are all responses; rows with one id and one payload share a
shard however many they are; an empty table gives an archive
without files and an empty result; other columns are ignored.
"""

from __future__ import annotations

import base64
import gzip
import uuid
import zlib
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass
from hashlib import sha256
from urllib.parse import quote

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from carepath.llm._shared import if_small, written

#: Fixed values of the format.
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
END = b"\r\n\r\n"
NAMES = uuid.UUID("6f0a8a4c-7a0c-5d1e-9a57-2f6d1c0b9e31")
PIECE = 1 << 13
_EMPTY = gzip.compress(b"", mtime=0)


@dataclass(frozen=True)
class ArchiveSpec:
    #: Bytes of payload in a shard, which one task sorts; bytes of a file.
    shard_bytes: int = 64 << 20
    roll_bytes: int = 16 << 20
    #: Payloads of fewer bytes are always stored.
    least_shared: int = 100
    level: int = 6
    date: str = "2024-01-01T00:00:00Z"
    prefix: str = "pages"
    bins: int = 4096


#: Shared payloads are broadcast up to this many (under 100 bytes each), and joined beyond.
BROADCAST_ROWS = 500_000


def record_id(page_id: int | None, digest: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(NAMES, f'{page_id}/{digest}')}>"


def _sha(data: bytes) -> str:
    return "sha256:" + base64.b32encode(sha256(data).digest()).decode().rstrip("=")


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, spec: ArchiveSpec) -> bytes:
    """A compressed record: a response, or a revisit of the page ``refers_to``."""
    digest = sha256(payload).hexdigest()
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if refers_to is not None else http + payload
    head = [("WARC-Type", "response" if refers_to is None else "revisit"), ("WARC-Record-ID", record_id(page_id, digest)), ("WARC-Date", spec.date)]
    if url is not None:
        head.append(("WARC-Target-URI", quote(url, safe="!#$%&'()*+,/:;=?@[]~")))
    if page_id is not None:
        head.append(("Page-Id", str(page_id)))
    if refers_to is not None:
        head += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(refers_to, digest)), ("Refers-To-Page-Id", str(refers_to))]
    head += [("WARC-Payload-Digest", _sha(payload)), ("WARC-Block-Digest", _sha(block)), ("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(block)))]
    plain = b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head).encode() + b"\r\n" + block + END
    packed = gzip.compress(plain, spec.level, mtime=0)
    return packed if packed[-1] == 0 else packed + _EMPTY


def records(content: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and payload of each record of a file; digests are checked."""
    at, view = 0, memoryview(content)
    while at < len(content):
        unpack, parts = zlib.decompressobj(31), []
        while not unpack.eof and at < len(content):
            # In pieces: what a member leaves over is copied.
            piece = view[at : at + PIECE]
            parts.append(unpack.decompress(piece))
            at += len(piece)
        at -= len(unpack.unused_data)
        plain = b"".join(parts)
        if not unpack.eof:
            raise ValueError("a record is cut short")
        if not plain:
            continue
        head, _, rest = plain.partition(END)
        first, *lines = head.decode().split("\r\n")
        fields = dict(line.split(": ", 1) for line in lines)
        block = rest[: int(fields["Content-Length"])]
        if first != "WARC/1.1" or rest[len(block) :] != END or _sha(block) != fields["WARC-Block-Digest"]:
            raise ValueError(f"damaged record {fields.get('WARC-Record-ID')}")
        http, _, payload = block.partition(END)
        fields["Payload-Length"] = http.rpartition(b"Content-Length: ")[2].decode()
        if fields["WARC-Type"] == "response" and _sha(payload) != fields["WARC-Payload-Digest"]:
            raise ValueError(f"damaged payload {fields['WARC-Record-ID']}")
        yield fields, payload


#: Where rows without an id begin.
NO_ID = -(1 << 63) - 1
#: A bin that holds more than a shard is parted into this power of two.
PART_BITS = 8

_Leaf = tuple[int, int, int]  # first id, first of 256 parts of its digests, bytes


def _block(bits: int) -> Column:
    """Number of an id's block of 2^bits ids, in order of ids."""
    return F.shiftrightunsigned(F.col("page_id").bitwiseXOR(F.lit(-(1 << 63))), bits)


def _leaves(light: DataFrame, spec: ArchiveSpec) -> list[_Leaf]:
    """Ranges of (id, part of digests) that have rows, with their bytes, from counts alone; only single parts of single ids may exceed a shard."""
    size = F.sum(F.col("n") + 512).alias("size")
    low, high, nothing = light.agg(F.min("page_id"), F.max("page_id"), F.sum(F.when(F.col("page_id").isNull(), F.col("n") + 512))).first()
    out: list[_Leaf] = [] if nothing is None or nothing > spec.shard_bytes else [(NO_ID, 0, nothing)]
    whole: list[int] = []
    rows, bits = light.filter("page_id IS NOT NULL"), 64
    if low is not None:
        bits = next(b for b in range(65) if ((high + (1 << 63)) >> b) - ((low + (1 << 63)) >> b) < spec.bins)
    while low is not None:
        found = [((r["b"] & ((1 << 64) - 1)) << bits, r["b"], r["size"]) for r in rows.groupBy(_block(bits).alias("b")).agg(size).collect()]
        out += [(u - (1 << 63), 0, n) for u, _, n in found if n <= spec.shard_bytes]
        large = [(u, b) for u, b, n in found if n > spec.shard_bytes]
        if not large or bits == 0:
            whole = [u - (1 << 63) for u, _ in large]
            break
        some = light.sparkSession.createDataFrame([(b,) for _, b in large], "_b long")
        rows = rows.join(F.broadcast(some), _block(bits) == F.col("_b"), "left_semi")
        bits = max(0, bits - PART_BITS)
    digest = F.conv(F.substring("digest", 1, 2), 16, 10).cast("int").alias("d")
    if whole:
        ids = light.sparkSession.createDataFrame([(i,) for i in whole], "_i long")
        out += [(r["page_id"], r["d"], r["size"]) for r in light.join(F.broadcast(ids), F.col("page_id") == F.col("_i"), "left_semi").groupBy("page_id", digest).agg(size).collect()]
    if nothing is not None and nothing > spec.shard_bytes:
        out += [(NO_ID, r["d"], r["size"]) for r in light.filter("page_id IS NULL").groupBy(digest).agg(size).collect()]
    return sorted(out)


def _shards(light: DataFrame, spec: ArchiveSpec) -> list[tuple[int, int]]:
    """Where each shard begins, as (id, part of digests); a list of as many entries as there are shards."""
    starts, filled = [], 0
    for first, part, n in _leaves(light, spec):
        if not starts or filled + n > spec.shard_bytes:
            starts.append((first, part))
            filled = 0
        filled += n
    return starts


def write(pages: DataFrame, folder: str, spec: ArchiveSpec = ArchiveSpec()) -> None:
    """Archive ``pages`` (page_id, url, html) under ``folder``, which must hold no archive yet."""
    spark = pages.sparkSession
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html")
    payload = F.coalesce("html", F.lit("")).cast("binary")
    light = written(pages.select("page_id", F.sha2(payload, 256).alias("digest"), F.length(payload).alias("n")), "warc-light")
    starts = _shards(light, spec)
    shared = light.filter(F.col("n") >= spec.least_shared).groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count("*").alias("c")).filter("c > 1 AND first_id IS NOT NULL").drop("c")
    own = pages.select("page_id", "url", payload.alias("payload"), F.sha2(payload, 256).alias("digest"))
    own = own.join(if_small(written(shared, "warc-shared"), BROADCAST_ROWS), "digest", "left")
    refers = F.when(~F.col("first_id").eqNullSafe(F.col("page_id")), F.col("first_id"))
    known = spark.sparkContext.broadcast(starts)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        begins = known.value
        for batch in batches:
            packed, shards, ids = [], [], batch.column(0).to_pylist()
            for page, url, data, to, digest in zip(ids, *(batch.column(i) for i in range(1, 5)), strict=True):
                packed.append(record(page, url.as_py(), data.as_py(), to.as_py(), spec)[:-1])
                shards.append(bisect_right(begins, (NO_ID if page is None else page, int(digest.as_py()[:2], 16))) - 1)
            yield pa.RecordBatch.from_arrays([pa.array(shards, pa.int32()), batch.column(0), batch.column(4), pa.array(packed, pa.binary())], names=["shard", "page_id", "digest", "packed"])

    made = own.select("page_id", "url", "payload", refers.alias("refers_to"), "digest").mapInArrow(pack, "shard int, page_id long, digest string, packed binary")
    order = Window.partitionBy("shard").orderBy(F.col("page_id").asc_nulls_first(), "digest", "packed")
    before = F.coalesce(F.sum(F.length("packed") + 1).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rolled = made.withColumns({"file": F.floor(before / spec.roll_bytes).cast("int"), "at": F.row_number().over(order)})
    staging = f"{folder}/_staging-{uuid.uuid4().hex}"
    # The writer asks for rows in order of shard and file and would sort by these alone; this order begins with both and is kept.
    rolled = rolled.sortWithinPartitions("shard", "file", "at").select("shard", "file", F.col("packed").cast("string").alias("value"))
    rolled.write.partitionBy("shard", "file").option("lineSep", "\0").text(staging)
    _commit(spark, folder, staging, spec)


def _commit(spark: SparkSession, folder: str, staging: str, spec: ArchiveSpec) -> None:
    """Rename the finished files to their names, then the manifest into place."""
    path = spark._jvm.org.apache.hadoop.fs.Path
    fs = path(folder).getFileSystem(spark._jsc.hadoopConfiguration())
    if fs.exists(path(f"{folder}/manifest.json")):
        raise FileExistsError(f"{folder} holds an archive")
    fs.mkdirs(path(f"{folder}/data"))
    listed, names = fs.listFiles(path(staging), True), []
    while listed.hasNext():
        f = listed.next()
        where = f.getPath()
        if not where.getName().startswith("part-"):
            continue
        file, shard = (int(p.getName().partition("=")[2]) for p in (where.getParent(), where.getParent().getParent()))
        name = f"{spec.prefix}-{shard:06d}-{file:06d}.warc.gz"
        if not fs.rename(where, path(f"{folder}/data/{name}")):
            raise OSError(f"{where} can't be renamed")
        names.append((name, f.getLen()))
    fs.delete(path(staging), True)
    made = f"{folder}/_manifest-{uuid.uuid4().hex}"
    spark.createDataFrame(sorted(names), "name string, bytes long").coalesce(1).write.json(made)
    if not fs.rename(path(made), path(f"{folder}/manifest.json")):
        raise OSError("the manifest can't be renamed")


def read(spark: SparkSession, folder: str) -> DataFrame:
    """One row per record: page_id, record_id, url, record_type, payload_bytes, payload_digest (hex), refers_to, payload (null for revisits)."""
    manifest = spark.read.schema("name string, bytes long").json(f"{folder}/manifest.json")
    files = spark.read.format("binaryFile").load(f"{folder}/data").withColumn("name", F.element_at(F.split("path", "/"), -1))
    files = files.join(manifest.withColumnRenamed("bytes", "length"), ["name", "length"], "left_semi").select("content")
    schema = "page_id long, record_id string, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, payload binary"

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.binary()]
        names = ["page_id", "record_id", "url", "record_type", "payload_bytes", "payload_digest", "refers_to", "payload"]
        out = lambda rows: pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True) if rows else [()] * 8, kinds, strict=True)], names=names)
        for batch in batches:
            for content in batch.column(0):
                rows = []
                for f, payload in records(content.as_py()):
                    number = lambda k, f=f: int(f[k]) if k in f else None
                    digest = f["WARC-Payload-Digest"].removeprefix("sha256:")
                    plain = base64.b32decode(digest + "=" * (-len(digest) % 8)).hex()
                    stored = payload if f["WARC-Type"] == "response" else None
                    rows.append((number("Page-Id"), f["WARC-Record-ID"], f.get("WARC-Target-URI"), f["WARC-Type"], number("Payload-Length"), plain, number("Refers-To-Page-Id"), stored))
                    if len(rows) >= 500:
                        yield out(rows)
                        rows = []
                yield out(rows)

    return files.mapInArrow(unpack, schema)


def exists(spark: SparkSession, folder: str) -> bool:
    path = spark._jvm.org.apache.hadoop.fs.Path
    return path(folder).getFileSystem(spark._jsc.hadoopConfiguration()).exists(path(f"{folder}/manifest.json"))
