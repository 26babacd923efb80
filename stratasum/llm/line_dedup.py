"""Dropping lines that many documents share, by a sharded minimal perfect hash over line hashes.

A line's key is the line without white space at its ends and with A-Z in lower case. Keys of at least
`min_chars` code points that at least `min_docs` documents hold lose all their lines, except in the
largest doc_id that holds them. Each document gives its distinct keys once, as 128-bit hashes, whose
documents are counted with pre-aggregation. All distinct hashes but those of a single document, which
no threshold asks for, are dealt to shards of bounded size. A task builds for each shard a minimal
perfect hash (levels of bit arrays; keys that collide go one level down) and, in its order, arrays of
64-bit fingerprints, of counts and of largest doc_ids. Documents probe the arrays for the counts of their
lines and decide by them; their lines are never joined or shuffled.

The arrays are broadcast while they take at most `broadcast_bytes`, by default a share of an executor's
memory. Beyond, they are probed in rounds of shard groups of that size, with the marks kept in a written
table between rounds, so that neither an executor nor the driver ever holds more than one group. Each
further round reads and writes the texts once, so rounds should be as large as memory lets them be.

Defined results: a null or empty text is one empty line and is returned as the empty text; a document
is a row, so repeated rows count each; a null doc_id counts as the smallest; in rows that repeat the
largest doc_id all keep their lines; doc_id must be a whole number, since the largest is asked for (a type
that is none raises a ValueError); an empty table gives no rows. Other columns than doc_id and text stay as
they are.
"""

from __future__ import annotations

import hashlib
import itertools
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import as_bytes, cut, drop, kept_in_worker, map_texts, table

MIN_CHARS, MIN_DOCS = 40, 5
#: Documents that a key must have to be indexed: what a single one holds is never shared.
INDEXED_DOCS = 2
#: Keys of a shard, about.
SHARD_KEYS = 200_000
#: Bytes of a key in the arrays: fingerprint, count, doc_id, and its share of the bit arrays with their ranks.
KEY_BYTES = 25
#: Bytes of arrays that are broadcast at once, at least, and as a share of an executor's memory.
BROADCAST_BYTES, BROADCAST_SHARE = 64 << 20, 1 / 48
LEAST_ID = -(1 << 63)
#: Positions of a level per key of it.
ROOM = 2.0


def round_bytes(spark: SparkSession) -> int:
    """What may be broadcast at once: a fixed share of an executor's memory, BROADCAST_BYTES at least."""
    unit = {"": 1, "b": 1, "k": 1 << 10, "m": 1 << 20, "g": 1 << 30, "t": 1 << 40}
    found = re.fullmatch(r"(\d+)([bkmgt]?)b?", spark.conf.get("spark.executor.memory", "1g").lower())
    return max(BROADCAST_BYTES, int(int(found[1]) * unit[found[2]] * BROADCAST_SHARE) if found else 0)


def line_key(line: bytes, min_chars: int) -> bytes | None:
    key = line.strip().lower()
    if len(key) < min_chars or (len(key) < 4 * min_chars and len(key.decode()) < min_chars):
        return None
    return key


def _mix(h: np.ndarray, level: int) -> np.ndarray:
    x = h ^ np.uint64((level + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _Bits:
    """A bit array of which the number of ones before a place is known from a count every 64 places."""

    def __init__(self, words: np.ndarray, size: int, base: int):
        self.words, self.size = words, size
        ones = np.bitwise_count(words)
        self.before = (np.cumsum(ones, dtype=np.int64) - ones + base).astype(np.int32)
        self.after = base + int(ones.sum())

    @classmethod
    def of(cls, bits: np.ndarray, base: int) -> _Bits:
        padded = np.zeros(-(-len(bits) // 64) * 64, bool)
        padded[: len(bits)] = bits
        return cls(np.packbits(padded, bitorder="little").view(np.uint64), len(bits), base)

    def get(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether the bits are set, and the number of ones before them."""
        word, bit = self.words[at >> 6], (at & 63).astype(np.uint64)
        below = word & ((np.uint64(1) << bit) - np.uint64(1))
        return (word >> bit & np.uint64(1)).astype(bool), self.before[at >> 6] + np.bitwise_count(below)


class PerfectHash:
    """Minimal perfect hash of distinct pairs (hash, fingerprint), with an array of values for each name.

    A probe gives the position of a member; anything else gives -1, but for a chance of 2^-64.
    """

    def __init__(self, high: np.ndarray, low: np.ndarray, **values: np.ndarray):
        self.levels: list[_Bits] = []
        left, base = np.arange(len(high)), 0
        place = np.zeros(len(high), np.int64)
        while len(left):
            size = max(8, int(ROOM * len(left)) + 1)
            at = self._at(high[left], low[left], len(self.levels), size)
            bits = _Bits.of(np.bincount(at, minlength=size) == 1, base)
            mine, rank = bits.get(at)
            place[left[mine]] = rank[mine]
            self.levels.append(bits)
            base, left = bits.after, left[~mine]
        order = np.empty(len(high), np.int64)
        order[place] = np.arange(len(high))
        self.low = low[order]
        self.values = {k: v[order] for k, v in values.items()}

    @staticmethod
    def _at(high: np.ndarray, low: np.ndarray, level: int, size: int) -> np.ndarray:
        return (_mix(high ^ low * np.uint64(level & 1), level) % np.uint64(size)).astype(np.int64)

    def probe(self, high: np.ndarray, low: np.ndarray) -> np.ndarray:
        out = np.full(len(high), -1, np.int64)
        left = np.arange(len(high))
        for level, bits in enumerate(self.levels):
            if not len(left):
                break
            found, rank = bits.get(self._at(high[left], low[left], level, bits.size))
            out[left[found]] = rank[found]
            left = left[~found]
        if len(self.low):
            out[(out >= 0) & (self.low[out] != low)] = -1
        return out

    def pack(self) -> bytes:
        head = np.array([len(self.levels), len(self.low), *(b.size for b in self.levels)], np.int64).tobytes()
        return head + b"".join(b.words.tobytes() for b in self.levels) + self.low.tobytes() + b"".join(v.tobytes() for _, v in sorted(self.values.items()))

    @classmethod
    def unpack(cls, data: bytes, kinds: dict[str, type]) -> PerfectHash:
        """The packed arrays, as views of data; kinds: the type of each array of values."""
        self = cls.__new__(cls)
        n_levels, n = (int(x) for x in np.frombuffer(data, np.int64, 2))
        at, base, self.levels = 16 + 8 * n_levels, 0, []
        for size in np.frombuffer(data, np.int64, n_levels, 16).tolist():
            bits = _Bits(np.frombuffer(data, np.uint64, -(-size // 64), at), size, base)
            self.levels.append(bits)
            at, base = at + bits.words.nbytes, bits.after
        self.low = np.frombuffer(data, np.uint64, n, at)
        at += self.low.nbytes
        self.values = {}
        for name, kind in sorted(kinds.items()):
            self.values[name] = np.frombuffer(data, kind, n, at)
            at += self.values[name].nbytes
        return self


def keys_of(df: DataFrame, min_chars: int) -> DataFrame:
    """doc_id and each distinct key hash (two longs) of each row."""

    def make():
        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            ids, digests = [], []
            for doc_id, text in zip(part.column("doc_id").to_pylist(), as_bytes(part.column("text")), strict=True):
                if text and len(text) >= min_chars:
                    own = {xxhash.xxh3_128_digest(k) for line in text.split(b"\n") if (k := line_key(line, min_chars)) is not None}
                    digests.extend(own)
                    ids.extend([doc_id] * len(own))
            both = np.frombuffer(b"".join(digests), np.int64).reshape(-1, 2)
            return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(both[:, 0].copy()), pa.array(both[:, 1].copy())], ["doc_id", "high", "low"])

        return one

    return map_texts(df.select(F.coalesce(F.col("doc_id").cast("bigint"), F.lit(LEAST_ID)).alias("doc_id"), "text"), "doc_id bigint, high bigint, low bigint", make)


def counted_keys(df: DataFrame, min_chars: int, indexed_docs: int = INDEXED_DOCS) -> DataFrame:
    """high, low, n_docs, last_id of each key that at least indexed_docs rows hold."""
    counted = keys_of(df, min_chars).groupBy("high", "low").agg(F.count(F.lit(1)).alias("n_docs"), F.max("doc_id").alias("last_id"))
    return counted.filter(F.col("n_docs") >= indexed_docs)


#: Counts saturate at the largest number that their array holds.
VALUES = {"last_id": np.int64, "n_docs": np.int32}


def build_shards(counted: DataFrame, n_shards: int) -> DataFrame:
    """shard, n_keys, packed arrays: one row for each shard that has keys. A task holds one shard at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_in_worker(None)
        held: list[pa.RecordBatch] = []

        def one() -> pa.RecordBatch:
            rows = pa.Table.from_batches(held)
            held.clear()
            column = lambda c: rows.column(c).to_numpy()
            n_docs = np.minimum(column("n_docs"), np.iinfo(np.int32).max).astype(np.int32)
            built = PerfectHash(column("high").view(np.uint64), column("low").view(np.uint64), n_docs=n_docs, last_id=column("last_id"))
            return pa.RecordBatch.from_pydict({"shard": pa.array([rows.column("shard")[0].as_py()], pa.int32()), "n_keys": pa.array([rows.num_rows], pa.int64()), "packed": pa.array([built.pack()], pa.binary())})

        for batch in batches:
            number = batch.column("shard").to_numpy()
            edges = [0, *(np.flatnonzero(np.diff(number)) + 1).tolist(), len(number)]
            for a, b in itertools.pairwise(edges):
                if held and held[0].column("shard")[0].as_py() != number[a]:
                    yield one()
                if b > a:
                    held.append(batch.slice(a, b - a))
        if held:
            yield one()

    dealt = counted.withColumn("shard", F.pmod(F.col("high"), F.lit(n_shards)).cast("int")).repartition("shard").sortWithinPartitions("shard")
    return dealt.mapInArrow(run, "shard int, n_keys bigint, packed binary")


class LineIndex:
    """Shards of one round, as they are broadcast."""

    def __init__(self, rows: list, n_shards: int):
        self.n_shards = n_shards
        self.shards = {r["shard"]: PerfectHash.unpack(r["packed"], VALUES) for r in rows}

    def counts(self, high: np.ndarray, low: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each hash the number of documents that hold it (0: not indexed here), and the largest doc_id."""
        number, last = np.zeros(len(high), np.int64), np.zeros(len(high), np.int64)
        shard = np.mod(high, self.n_shards)
        for k in np.unique(shard):
            if (own := self.shards.get(int(k))) is not None:
                at = np.flatnonzero(shard == k)
                hit = own.probe(high[at].view(np.uint64), low[at].view(np.uint64))
                ok = hit >= 0
                number[at[ok]] = own.values["n_docs"][hit[ok]]
                last[at[ok]] = own.values["last_id"][hit[ok]]
        return number, last


def _prober(df: DataFrame, rows: list, n_shards: int, min_chars: int, min_docs: int):
    """Maker of the function that gives the rows of a batch, their __drop marks (a byte for each line, in order; null: none yet) with those of these shards added."""
    packed = df.sparkSession.sparkContext.broadcast([{"shard": r["shard"], "packed": bytes(r["packed"])} for r in rows])

    def make():
        index = LineIndex(packed.value, n_shards)

        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            before = part.column("__drop").to_pylist()
            lines = [(text or b"").split(b"\n") for text in as_bytes(part.column("text"))]
            place, digests, owner = [], [], []
            ids = [LEAST_ID if d is None else d for d in part.column("doc_id").cast(pa.int64()).to_pylist()]
            for d, own in enumerate(lines):
                for i, line in enumerate(own):
                    if (k := line_key(line, min_chars)) is not None:
                        place.append((d, i))
                        digests.append(xxhash.xxh3_128_digest(k))
                        owner.append(ids[d])
            both = np.frombuffer(b"".join(digests), np.int64).reshape(-1, 2)
            number, last = index.counts(both[:, 0].copy(), both[:, 1].copy())
            marks = [bytearray(m) if m is not None else bytearray(len(own)) for m, own in zip(before, lines, strict=True)]
            for k in np.flatnonzero((number >= min_docs) & (last != np.array(owner, np.int64))):
                d, i = place[k]
                marks[d][i] = 1
            at = part.schema.get_field_index("__drop")
            return part.set_column(at, "__drop", pa.array([bytes(m) for m in marks], pa.binary()))

        return one

    return make


def _finisher(df: DataFrame, digest_only: bool):
    """Schema, and maker of the function that drops the marked lines of a batch."""
    kind = dict(df.dtypes)["doc_id"]

    def make():
        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            total, dropped, kept = [], [], []
            for text, marks in zip(as_bytes(part.column("text")), part.column("__drop").to_pylist(), strict=True):
                lines = (text or b"").split(b"\n")
                total.append(len(lines))
                dropped.append(sum(marks))
                kept.append(b"\n".join(line for line, m in zip(lines, marks, strict=True) if not m) if any(marks) else text or b"")
            if digest_only:
                return pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(total, pa.int64()), pa.array(dropped, pa.int64()), pa.array([hashlib.sha256(k).hexdigest() for k in kept])], ["doc_id", "n_lines", "n_dropped", "kept_sha256"])
            at = part.schema.get_field_index("text")
            out = part.set_column(at, "text", pa.array(kept, pa.binary()).cast(pa.string()))
            out = out.append_column("__lines", pa.array(total, pa.int64())).append_column("__dropped", pa.array(dropped, pa.int64()))
            return out.drop_columns(["__drop"])

        return one

    if digest_only:
        return f"doc_id {kind}, n_lines bigint, n_dropped bigint, kept_sha256 string", make
    fields = [f for f in df.schema.fields if f.name != "__drop"]
    schema = T.StructType([*fields, T.StructField("__lines", T.LongType()), T.StructField("__dropped", T.LongType())])
    return schema, make


def dedup_lines(df: DataFrame, min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS, broadcast_bytes: int | None = None, shard_keys: int = SHARD_KEYS, digest_only: bool = False) -> DataFrame:
    """The rows of df with their kept texts and the columns __lines and __dropped; digest_only: doc_id, n_lines, n_dropped, kept_sha256.

    Builds the index when called (jobs over all documents), then returns a lazy frame.
    """
    if not isinstance(df.schema["doc_id"].dataType, T.IntegralType):
        raise ValueError("doc_id must be a whole number")
    if digest_only:
        df = df.select("doc_id", "text")
    counted = cut(counted_keys(df, min_chars, min(min_docs, INDEXED_DOCS)))
    n_keys = counted.count()
    n_shards = max(1, math.ceil(n_keys / shard_keys))
    shards = cut(build_shards(counted, n_shards))
    drop(counted)
    per_round = max(1, (broadcast_bytes or round_bytes(df.sparkSession)) // (KEY_BYTES * shard_keys))
    marked, before = df.withColumn("__drop", F.lit(None).cast("binary")), None
    for first in range(0, n_shards, per_round):
        rows = shards.filter(F.col("shard").between(first, first + per_round - 1)).collect()  # at most broadcast_bytes
        probe = _prober(marked, rows, n_shards, min_chars, min_docs)
        if first + per_round < n_shards:
            marked = cut(map_texts(marked, marked.schema, probe))
            if before is not None:
                drop(before)
            before = marked
    schema, finish = _finisher(marked, digest_only)

    def both():  # one pass of Python, so a task has one worker
        first_step, second_step = probe(), finish()
        return lambda part: second_step(first_step(part))

    return map_texts(marked, schema, both)


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_lines(table(spark, sf_dir, "documents"), digest_only=True)


ORACLE_SQL = """
WITH base AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents),
flat AS (SELECT doc_id, unnest(lines) AS line, generate_subscripts(lines, 1) AS pos, len(lines) AS n FROM base),
keyed AS (
  SELECT doc_id, pos, n, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
  FROM flat),
freq AS (
  SELECT k, max(doc_id) AS last_id FROM (SELECT DISTINCT k, doc_id FROM keyed WHERE length(k) >= 40)
  GROUP BY k HAVING count(*) >= 5),
marked AS (
  SELECT keyed.doc_id, pos, n, line, freq.k IS NOT NULL AND freq.last_id <> keyed.doc_id AS gone
  FROM keyed LEFT JOIN freq ON keyed.k = freq.k)
SELECT doc_id, CAST(max(n) AS BIGINT) AS n_lines, CAST(sum(CASE WHEN gone THEN 1 ELSE 0 END) AS BIGINT) AS n_dropped,
       sha256(coalesce(string_agg(CASE WHEN gone THEN NULL ELSE line END, chr(10) ORDER BY pos), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
