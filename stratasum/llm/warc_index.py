"""WARC archives with a two-level capture index.

Writing: a row becomes a WARC/1.1 record. Of records with equal payloads (by SHA-1, of at least
`least_bytes` bytes) the one with the smallest page_id is a response with the payload; the others are
revisits that name it. Which is which follows from page_id, digest and length alone. Payloads are
deflated before anything is shuffled, and of equal ones in a batch only those that may be the response
go along. A record is one gzip member, so it can be read alone; archives have about `archive_bytes`
bytes each and end in an empty member. Spark's committed writer puts them in place, so a retried task
leaves nothing half done.

Index: archives are read back member by member, in one pass of bounded memory, and digests are taken
anew. Captures are sorted by their key, the URL with its host reversed (com,example)/path, then by
page_id, range-partitioned, and cut into blocks of `block_lines` lines, each a gzip member. An index
file holds the blocks of one range of keys and, at its end, the sparse directory of them: first and
last key, place and length of each block. The table `files` has the first and last key of each file.

Lookup: a binary search among the files, one in the directory of the file, a range read of the block, a
binary search in its lines, and a range read of the record in its archive. `lookup` does it for one URL on
the driver, `lookup_all` for a table of captures, dealt by file and sorted, so that no block is read
twice. Memory is bounded by a block, a file's directory and the `files` table, which has a row for
`file_bytes` of compressed index.

Range reads go through pyarrow's file systems (local, HDFS, S3, Google, Azure); `shared_dir` must be in
one of them.

Defined results: a null html is the empty payload; a null url is empty; rows that repeat the smallest
page_id are all responses; a null page_id is a response if all of its group are null, else a revisit;
line ends in URLs are percent-encoded; page_id must be a whole number (a text that is none raises);
rows that repeat page_id and url are all in the index, and found together; an empty table gives an empty
archive and index.
"""

from __future__ import annotations

import base64
import bisect
import hashlib
import json
import re
import struct
import zlib
from collections.abc import Callable, Iterator
from urllib.parse import urlsplit

import pyarrow as pa
import pyarrow.fs  # noqa: F401
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, kept_in_worker, map_texts, shared_dir, table

LEAST_BYTES, BLOCK_LINES = 0, 2000
ARCHIVE_BYTES, FILE_BYTES = 32 << 20, 8 << 20
READ_BYTES = 1 << 16
CRLF = b"\r\n"
DATE = b"2024-01-01T00:00:00Z"
PROFILE = b"http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
CAPTURE = "urlkey string, page_id bigint, url string, file string, offset bigint, length bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint"
LINE = [f.split()[0] for f in CAPTURE.split(", ")]
KINDS = [pa.int64() if f.endswith("bigint") else pa.string() for f in CAPTURE.split(", ")]
LEAST_ID = -(1 << 63)
GZIP_HEAD = b"\x1f\x8b\x08\x00\x00\x00\x00\x00\x00\xff"
#: A member without content.
GZIP_END = GZIP_HEAD + b"\x03\x00" + bytes(8)
#: An index file ends in the place of its directory, in so many digits, and a line end.
PLACE_DIGITS = 20

Key = tuple[str, int]


# ---- bytes of records


def _deflate(data: bytes, last: bool) -> bytes:
    """Raw deflated data that ends at a byte, so that more may follow unless it is the last."""
    packer = zlib.compressobj(6, zlib.DEFLATED, -15)
    return packer.compress(data) + packer.flush(zlib.Z_FINISH if last else zlib.Z_FULL_FLUSH)


def _member(head: bytes, deflated: bytes, payload: bytes) -> bytes:
    """One gzip member of a record's head, its payload (deflated before) and the two line ends."""
    tail = CRLF + CRLF
    crc = zlib.crc32(tail, zlib.crc32(payload, zlib.crc32(head)))
    size = len(head) + len(payload) + len(tail)
    return GZIP_HEAD + _deflate(head, False) + deflated + _deflate(tail, True) + struct.pack("<II", crc, size & 0xFFFFFFFF)


def _head(page_id: int | None, url: str, sha: bytes, n_bytes: int, refers_to: int | None) -> bytes:
    """WARC headers and the HTTP head of a record; refers_to: the response that a revisit names."""
    revisit = refers_to is not None
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % n_bytes
    lines = [
        b"WARC/1.1",
        b"WARC-Type: " + (b"revisit" if revisit else b"response"),
        b"WARC-Target-URI: " + url.encode(),
        b"WARC-Date: " + DATE,
        b"WARC-Record-ID: <urn:page:%s>" % (b"none" if page_id is None else b"%d" % page_id),
        b"WARC-Payload-Digest: sha1:" + base64.b32encode(sha),
        *([b"WARC-Profile: " + PROFILE, b"WARC-Refers-To: <urn:page:%d>" % refers_to] if revisit else []),
        b"Content-Type: application/http; msgtype=response",
        b"Content-Length: %d" % (len(http) + (0 if revisit else n_bytes)),
    ]
    return CRLF.join(lines) + CRLF + CRLF + http


def _plain(pages: DataFrame) -> DataFrame:
    """page_id, url and html as records have them."""
    url = F.coalesce("url", F.lit(""))
    url = F.replace(F.replace(url, F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A"))
    return pages.select(F.col("page_id").cast("bigint").alias("page_id"), url.alias("url"), F.coalesce("html", F.lit("")).alias("html"))


def _deflated(own: DataFrame, least_bytes: int) -> DataFrame:
    """page_id, url, sha, bytes, body: the deflated payload, null where a smaller page_id of the same slice has the same one."""

    def make():
        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            ids = part.column("page_id").to_pylist()
            texts = part.column("html").cast(pa.binary()).to_pylist()
            shas = [hashlib.sha1(t).digest() for t in texts]
            first: dict[bytes, int] = {}
            for i, s in zip(ids, shas, strict=True):
                if i is not None:
                    first[s] = min(i, first.get(s, i))
            bodies = [_deflate(t, False) if len(t) < least_bytes or first.get(s) == i else None for i, s, t in zip(ids, shas, texts, strict=True)]
            columns = [part.column("page_id"), part.column("url"), pa.array(shas, pa.binary()), pa.array([len(t) for t in texts], pa.int64()), pa.array(bodies, pa.binary())]
            return pa.RecordBatch.from_arrays(columns, ["page_id", "url", "sha", "bytes", "body"])

        return one

    return map_texts(own, "page_id bigint, url string, sha binary, bytes bigint, body binary", make, "html")


def archives(pages: DataFrame, least_bytes: int = LEAST_BYTES, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """value: the bytes of one archive a row, of about archive_bytes, or of one record that is longer."""
    own = _plain(pages)
    narrow = own.select("page_id", F.unhex(F.sha1("html")).alias("sha"), F.octet_length("html").alias("bytes")).filter(F.col("bytes") >= least_bytes)
    groups = narrow.groupBy("sha").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("sha", "first")
    typed = _deflated(own, least_bytes).join(groups, "sha", "left")
    revisit = F.col("first").isNotNull() & ~F.col("first").eqNullSafe(F.col("page_id"))
    typed = typed.select("page_id", "url", "sha", "bytes", F.when(revisit, F.col("first")).alias("refers_to"), F.when(~revisit, F.col("body")).alias("body"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_in_worker(None)
        held: list[bytes] = []
        size = 0

        def archive() -> pa.RecordBatch:
            out = pa.RecordBatch.from_pydict({"value": pa.array([b"".join(held)], pa.binary())})
            held.clear()
            return out

        nothing = _deflate(b"", False)
        for batch in batches:
            for page_id, url, sha, n, refers_to, body in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                payload = b"" if refers_to is not None else zlib.decompressobj(-15).decompress(body)
                member = _member(_head(page_id, url, sha, n, refers_to), nothing if refers_to is not None else body, payload)
                if held and size + len(member) > archive_bytes:
                    yield archive()
                    size = 0
                held.append(member)
                size += len(member)
        if held:
            yield archive()

    return typed.mapInArrow(run, "value binary")


def _write_blobs(df: DataFrame, path: str, end: bytes) -> None:
    """A file for each row of `value`, with `end` after it. Spark's text writer passes bytes on as they are."""
    writer = df.select(F.col("value").cast("string").alias("value")).write
    writer.option("lineSep", end.decode("latin-1")).option("encoding", "ISO-8859-1").option("maxRecordsPerFile", 1).text(path)


def write_archives(pages: DataFrame, path: str, least_bytes: int = LEAST_BYTES, archive_bytes: int = ARCHIVE_BYTES) -> None:
    _write_blobs(archives(pages, least_bytes, archive_bytes), path, GZIP_END)


# ---- reading archives back


def open_input(path: str) -> pa.NativeFile:
    """A file of the shared folder, to seek and read in."""
    scheme, _, rest = path.partition(":")
    if "/" in scheme or not rest:
        return pa.fs.LocalFileSystem().open_input_file(path)
    if scheme == "file":  # Spark writes file:/a and file:///a
        return pa.fs.LocalFileSystem().open_input_file("/" + rest.lstrip("/"))
    store, place = pa.fs.FileSystem.from_uri({"s3a": "s3", "s3n": "s3"}.get(scheme, scheme) + ":" + rest)
    return store.open_input_file(place)


def members(source: pa.NativeFile) -> Iterator[tuple[int, int, bytes]]:
    """Offset, length and content of each gzip member of a file that is not empty, read in order."""
    at, data = 0, b""
    while True:
        unpacker, parts, length = zlib.decompressobj(31), [], 0
        while not unpacker.eof:
            if not data and not (data := source.read(READ_BYTES)):
                if length:
                    raise ValueError(f"a member at {at} has no end")
                return
            # pieces, since what follows the member is copied each time
            piece, data = data[: READ_BYTES // 8], data[READ_BYTES // 8 :]
            parts.append(unpacker.decompress(piece))
            length += len(piece) - len(unpacker.unused_data)
            data = unpacker.unused_data + data
        if any(parts):
            yield at, length, b"".join(parts)
        at += length


def parse(record: bytes) -> tuple[dict[bytes, bytes], bytes]:
    """Headers and block of a record."""
    lines, _, rest = record.partition(CRLF + CRLF)
    first, *lines = lines.split(CRLF)
    if not first.startswith(b"WARC/"):
        raise ValueError("no record")
    head = {k.lower(): v for k, _, v in (line.partition(b": ") for line in lines)}
    return head, rest[: int(head[b"content-length"])]


def url_key(url: str) -> str:
    """Reversed host, then the rest: com,example)/path?query. Port, user and a leading www do not count."""
    try:
        parts = urlsplit(url.strip())
        host = (parts.hostname or "").removeprefix("www.")
    except ValueError:
        return ")" + url.lower()
    rest = (parts.path or "/") + ("?" + parts.query if parts.query else "")
    return ",".join(reversed(host.split("."))) + ")" + rest.lower()


def _number(name: bytes | None) -> int | None:
    found = re.fullmatch(rb"<urn:page:(-?\d+)>", name or b"")
    return int(found[1]) if found else None


def _capture(file: str, offset: int, length: int, record: bytes) -> tuple:
    head, block = parse(record)
    http, _, payload = block.partition(CRLF + CRLF)
    kind = head[b"warc-type"].decode()
    url = head[b"warc-target-uri"].decode()
    if kind == "response":
        size, digest = len(payload), base64.b32encode(hashlib.sha1(payload).digest()).decode()
        if "sha1:" + digest != head[b"warc-payload-digest"].decode():
            raise ValueError(f"payload of {file} at {offset} does not have its digest")
    else:
        size = int(re.search(rb"Content-Length: (\d+)", http)[1])
        digest = head[b"warc-payload-digest"].decode().removeprefix("sha1:")
    return url_key(url), _number(head[b"warc-record-id"]), url, file, offset, length, size, digest, kind, _number(head.get(b"warc-refers-to"))


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), KINDS, strict=True)], LINE)


def _files(spark: SparkSession, path: str) -> DataFrame:
    """path of each file in a folder; Spark deals them by their lengths, contents are not read."""
    return spark.read.format("binaryFile").load(path).select("path", "length")


def captures(spark: SparkSession, path: str) -> DataFrame:
    """A row for each record of the archives at path, read back from them; digests are taken anew from payloads."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_in_worker(None)
        for batch in batches:
            for file in batch.column("path").to_pylist():
                held = []
                with open_input(file) as source:
                    for member in members(source):
                        held.append(_capture(file, *member))
                        if len(held) == 1000:
                            yield _rows(held)
                            held = []
                if held:
                    yield _rows(held)

    return _files(spark, path).mapInArrow(run, CAPTURE)


# ---- the index


def _key(urlkey: str, page_id: int | None) -> Key:
    return urlkey, LEAST_ID if page_id is None else page_id


def _pack_lines(rows: list[tuple]) -> bytes:
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    return packer.compress("\n".join(json.dumps(r) for r in rows).encode()) + packer.flush()


def _unpack_lines(data: bytes) -> list[list]:
    return [json.loads(line) for line in zlib.decompress(data, 31).decode().split("\n")]


def write_index(found: DataFrame, path: str, block_lines: int = BLOCK_LINES, file_bytes: int = FILE_BYTES) -> None:
    """Files of blocks and of their directory at path/blocks, and what keys each has at path/files."""
    spark = found.sparkSession

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_in_worker(None)
        lines: list[tuple] = []
        blocks: list[bytes] = []
        directory: list[tuple] = []  # first key, last key, place, length
        at = 0

        def block() -> None:
            nonlocal at
            blocks.append(_pack_lines(lines))
            directory.append((*_key(*lines[0][:2]), *_key(*lines[-1][:2]), at, len(blocks[-1])))
            at += len(blocks[-1])
            lines.clear()

        def file() -> pa.RecordBatch:
            nonlocal at
            data = b"".join(blocks) + _pack_lines(directory) + b"%0*d" % (PLACE_DIGITS, at)
            blocks.clear()
            directory.clear()
            at = 0
            return pa.RecordBatch.from_pydict({"value": pa.array([data], pa.binary())})

        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in LINE), strict=True):
                lines.append(row)
                if len(lines) == block_lines:
                    block()
                    if at >= file_bytes:
                        yield file()
        if lines:
            block()
        if blocks:
            yield file()

    parts = max(1, spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    order = ["urlkey", F.coalesce("page_id", F.lit(LEAST_ID)), "file", "offset"]
    ordered = found.select(*LINE).repartitionByRange(parts, *order).sortWithinPartitions(*order)
    _write_blobs(ordered.mapInArrow(run, "value binary"), f"{path}/blocks", b"\n")

    def ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name in batch.column("path").to_pylist():
                with open_input(name) as source:
                    own = read_directory(source)
                yield pa.RecordBatch.from_pydict({"file": [name], "first_key": [own[0][0]], "first_id": pa.array([own[0][1]], pa.int64()), "last_key": [own[-1][2]], "last_id": pa.array([own[-1][3]], pa.int64())})

    _files(spark, f"{path}/blocks").mapInArrow(ends, "file string, first_key string, first_id bigint, last_key string, last_id bigint").coalesce(1).sortWithinPartitions("first_key", "first_id", "last_key", "last_id", "file").write.parquet(f"{path}/files")


def read_directory(source: pa.NativeFile) -> list[list]:
    """The directory at the end of an index file, by two range reads."""
    size = source.size()
    end = size - PLACE_DIGITS - 1
    source.seek(end)
    place = int(source.read(PLACE_DIGITS))
    source.seek(place)
    return _unpack_lines(source.read(end - place))


class IndexFiles:
    """The keys of all index files, in order, and the file that is open with its directory and last block."""

    def __init__(self, files: list[tuple[str, Key, Key]], opener: Callable[[str], object] = open_input):
        self.files = sorted(files, key=lambda f: (f[1], f[2], f[0]))
        self.firsts = [f[1] for f in self.files]
        self.lasts = [f[2] for f in self.files]
        self.opener, self.at, self.block_at, self.blocks_read = opener, -1, -1, 0

    def _open(self, number: int) -> None:
        if self.at != number:
            self.at, self.block_at = number, -1
            self.source = self.opener(self.files[number][0])
            self.directory = read_directory(self.source)
            self.block_firsts = [(d[0], d[1]) for d in self.directory]
            self.block_lasts = [(d[2], d[3]) for d in self.directory]

    def _load(self, number: int) -> None:
        if self.block_at != number:
            _, _, _, _, place, length = self.directory[number]
            self.source.seek(place)
            self.lines = _unpack_lines(self.source.read(length))
            self.keys = [_key(*line[:2]) for line in self.lines]
            self.block_at = number
            self.blocks_read += 1

    def place(self, low: Key) -> int:
        """The first file that may hold a key of at least `low`."""
        return bisect.bisect_left(self.lasts, low)

    def find(self, low: Key, high: Key) -> Iterator[list]:
        """Lines with keys from low to high."""
        for number in range(self.place(low), len(self.files)):
            if self.firsts[number] > high:
                return
            self._open(number)
            for k in range(bisect.bisect_left(self.block_lasts, low), len(self.directory)):
                if self.block_firsts[k] > high:
                    return
                self._load(k)
                yield from self.lines[bisect.bisect_left(self.keys, low) : bisect.bisect_right(self.keys, high)]


def _file_keys(spark: SparkSession, path: str) -> list[tuple[str, Key, Key]]:
    """A row for each index file, of some file_bytes compressed."""
    return [(r["file"], (r["first_key"], r["first_id"]), (r["last_key"], r["last_id"])) for r in spark.read.parquet(f"{path}/files").toLocalIterator()]


class HadoopInput:
    """A file to seek and read in, through the store that Spark itself uses; on the driver."""

    def __init__(self, spark: SparkSession, file: str):
        place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(file)
        store = place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        self._size, self._stream = store.getFileStatus(place).getLen(), store.open(place)

    def size(self) -> int:
        return self._size

    def seek(self, at: int) -> None:
        self._stream.seek(at)

    def read(self, n: int) -> bytes:
        return bytes(self._stream.readNBytes(n))


def lookup(spark: SparkSession, path: str, url: str) -> list[dict]:
    """Captures of a URL: binary searches among files, in the directory and in the lines of the blocks that may hold its key."""
    key = url_key(url.replace("\r", "%0D").replace("\n", "%0A"))
    index = IndexFiles(_file_keys(spark, path), lambda file: HadoopInput(spark, file))
    return [dict(zip(LINE, line, strict=True)) for line in index.find((key, LEAST_ID), (key, -LEAST_ID))]


def read_record(spark: SparkSession, file: str, offset: int, length: int) -> tuple[dict[bytes, bytes], bytes]:
    """Headers and block of one record, by a range read in whatever store holds the archive."""
    source = HadoopInput(spark, file)
    source.seek(offset)
    return parse(zlib.decompress(source.read(length), 31))


def lookup_all(spark: SparkSession, path: str, pages: DataFrame) -> DataFrame:
    """Captures of all rows of (page_id, url), each found by binary searches and range reads of blocks.

    Wanted keys are dealt by the index file that holds them and sorted, so a task opens a file once
    and reads a block once. Keys that the index lacks give no row; repeated ones count once.
    """
    keys = _file_keys(spark, path)
    shared = spark.sparkContext.broadcast(keys)  # a row for file_bytes of compressed index
    url = F.replace(F.replace(F.coalesce("url", F.lit("")), F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A"))
    wanted = pages.select(F.coalesce(F.col("page_id").cast("bigint"), F.lit(LEAST_ID)).alias("page_id"), url.alias("url")).distinct()

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_in_worker(None)
        index = IndexFiles(shared.value)
        for batch in batches:
            own = [url_key(u) for u in batch.column("url").to_pylist()]
            file = [index.place(k) for k in zip(own, batch.column("page_id").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(file, pa.int32()), pa.array(own, pa.string()), batch.column("page_id")], ["file", "urlkey", "page_id"])

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_in_worker(None)
        index, last = IndexFiles(shared.value), None
        for batch in batches:
            held = []
            for key in zip(batch.column("urlkey").to_pylist(), batch.column("page_id").to_pylist(), strict=True):
                if key != last:  # two URLs may have one key
                    held += index.find(key, key)
                    last = key
            if held:
                yield _rows(held)

    dealt = wanted.mapInArrow(deal, "file int, urlkey string, page_id bigint").repartition("file").sortWithinPartitions("file", "urlkey", "page_id")
    return dealt.mapInArrow(find, CAPTURE)


def op5_warc_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    place, pages = shared_dir(spark), table(spark, sf_dir, "pages")
    write_archives(pages, f"{place}/warc")
    write_index(cut(captures(spark, f"{place}/warc")), f"{place}/index")
    return lookup_all(spark, f"{place}/index", pages.select("page_id", "url")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "offset", "length")
