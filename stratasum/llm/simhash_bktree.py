"""Near-duplicates by SimHash fingerprints and broadcast BK-trees.

A fingerprint has 64 bits or several words of 64. Bit j is 1 if it is set in over half of the hashes
of the text's word shingles. Texts are nodes: equal fingerprints (or equal shingle sets) are one node,
so copies, however many, cost one row.

Each node names the shards that it stands in; nodes that may link share one. Shards of one node are
left out. A shard is a BK-tree: the first member is the root, a child's key is its Hamming distance to
its parent, and a search with radius r follows only edges whose keys lie within r of the query's
distance to the node. A shard of more than `chunk` members is several trees, so no task holds a whole
shard. Trees are built on the executors, packed, and broadcast in rounds of at most `round_bytes`;
nodes search the trees of their shards, wherever they are, level by level, in blocks of bounded size.
Each batch of searches gives the links of a spanning forest, never all pairs. Components follow by
contraction.

`near_duplicates` links fingerprints of 64 bits within 3 bits. Shards are pairs out of five parts of
the bits: 3 differing bits leave two parts alike, so no pair is missed, and a shard has 25 or 26 bits.

`similar_documents` finds texts whose shingle sets have a Jaccard similarity. Its shards are minima of
the shingle hashes (`bands` times `rows` of them), whose number does not depend on the input, and in
which texts meet by their similarity, not by chance. Trees then make candidate groups: fingerprints of
the sets within the expected number of differing bits and `spread` standard deviations. Each group is
verified exactly: its texts meet in blocks of bounded size, an inverted list of their shingles gives all
intersections, and links are pairs that have the similarity.

At radius 3 of 64 the trees prune; at the radius that similarity 0.8 needs they hardly can, since nearly
all distances lie within it of each other: README has figures. There, shards do the pruning.

Defined results: null and empty texts have the fingerprint zero and link like others; repeated rows
get equal results; a null doc_id belongs to its component but never names it, unless all are null; an
empty table gives no rows; other columns than doc_id and text are not read.
"""

from __future__ import annotations

import hashlib
import itertools
import math
from collections.abc import Iterator
from functools import cache, partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, cut, drop, kept_in_worker, map_texts, shared_dir, table
from .graph import components

WORDS, RADIUS, PARTS, SEED = 3, 3, 5, 42
#: Minima of shingle hashes: two texts of similarity s share a shard with the chance 1 - (1 - s^ROWS)^BANDS, 0.9993 at 0.8.
BANDS, ROWS = 14, 4
#: Members of a tree, at most; pairs of query and node that a task looks at in one step.
CHUNK, BLOCK_PAIRS = 2000, 2_000_000
#: Bytes of trees that are broadcast at once; of those that are built and packed together, about.
ROUND_BYTES, BIN_BYTES = 32 << 20, 1 << 20
#: Texts, and bytes of text, that are verified together, about.
GROUP_TEXTS, GROUP_BYTES = 256, 8 << 20
#: Sets of more shingles differ in as many bits as the angle between them says.
LARGE_SET = 60


# ---- fingerprints and shards


def text_hashes(text: bytes | None, words: int) -> np.ndarray:
    """XXH64 of each word shingle, repeats included; of the whole sequence if it is shorter; none for no words."""
    own = (text or b"").lower().split()
    if not own:
        return np.empty(0, np.uint64)
    if len(own) <= words:
        shingles = [b" ".join(own)]
    else:
        shingles = map(b" ".join, zip(*(own[i:] for i in range(words)), strict=False))
    return np.frombuffer(b"".join(map(partial(xxhash.xxh64_digest, seed=SEED), shingles)), ">u8").astype(np.uint64)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _words_of(hashes: np.ndarray, n: int) -> np.ndarray:
    """n words of bits of each hash; the first is the hash itself."""
    if n == 1:
        return hashes[:, None]
    y = _mixed(hashes[:, None] + np.arange(n, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    y[:, 0] = hashes
    return y


def fingerprint(hashes: np.ndarray, n: int = 1) -> bytes:
    """8 n bytes, most significant first."""
    if not len(hashes):
        return bytes(8 * n)
    total = np.zeros(64 * n, np.int64)
    for first in range(0, len(hashes), 255):  # sums of so many bits fit a byte
        part = _words_of(hashes[first : first + 255], n).astype(">u8")
        bits = np.unpackbits(part.view(np.uint8).reshape(len(part), -1), axis=1)
        total += np.add.reduce(bits, axis=0, dtype=np.uint8)
    return np.packbits(2 * total > len(hashes)).tobytes()


def fingerprints(df: DataFrame, words: int = WORDS, n: int = 1) -> DataFrame:
    """doc_id, fp (binary) of each row."""
    kind = dict(df.dtypes)["doc_id"]

    def make():
        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            fps = [fingerprint(text_hashes(text, words), n) for text in as_bytes(part.column("text"))]
            return pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(fps, pa.binary())], ["doc_id", "fp"])

        return one

    return map_texts(df.select("doc_id", "text"), f"doc_id {kind}, fp binary", make)


def part_shards(fps: np.ndarray, parts: int = PARTS, radius: int = RADIUS) -> np.ndarray:
    """Shards of 64-bit fingerprints, a row each: every choice of as many parts as the radius leaves alike."""
    if radius >= parts:
        raise ValueError(f"{parts} parts need a radius below their number")
    edges = [64 * k // parts for k in range(parts + 1)]
    own = np.stack([(fps >> np.uint64(a)) & np.uint64((1 << b - a) - 1) for a, b in itertools.pairwise(edges)], 1)
    out = []
    for t, chosen in enumerate(itertools.combinations(range(parts), parts - radius)):
        code = np.full(len(fps), t + 1, np.uint64)
        for k in chosen:
            code = _mixed(code * np.uint64(0x9E3779B97F4A7C15) + own[:, k])
        out.append(code)
    return np.stack(out, 1).view(np.int64)


@cache
def _multipliers(n: int) -> np.ndarray:
    return np.random.default_rng(SEED).integers(0, 1 << 64, n, dtype=np.uint64) | np.uint64(1)


def band_shards(hashes: np.ndarray, bands: int = BANDS, rows: int = ROWS) -> np.ndarray:
    """A shard for each band: its number and the least of the hashes under each of its orders."""
    by = _multipliers(bands * rows)
    least = np.full(len(by), np.iinfo(np.uint64).max, np.uint64)
    for first in range(0, len(hashes), 1024):
        least = np.minimum(least, (hashes[first : first + 1024, None] * by).min(0))
    least = least.reshape(bands, rows)
    code = np.arange(1, bands + 1, dtype=np.uint64)
    for k in range(rows):
        code = _mixed(code * np.uint64(0x9E3779B97F4A7C15) + least[:, k])
    return code.view(np.int64)


# ---- trees


class TreeSet:
    """BK-trees of many shards. points: (n, words) of uint64; shard: a number for each point, equal ones adjacent and in order."""

    def __init__(self, points: np.ndarray, shard: np.ndarray):
        n = len(points)
        self.points = points
        starts = np.flatnonzero(np.diff(shard, prepend=shard[0] - 1)) if n else np.empty(0, np.int64)
        self.roots, self.shards = starts, shard[starts]
        parent, key = np.full(n, -1, np.int64), np.zeros(n, np.int64)
        left = np.setdiff1d(np.arange(n), starts, assume_unique=True)
        at = np.repeat(starts, np.diff(np.append(starts, n)))[left] if n else left
        while len(left):  # all points wait at a node; the first of each distance becomes its child, the others go down to it
            d = np.bitwise_count(points[left] ^ points[at]).sum(1).astype(np.int64)
            order = np.lexsort((left, d, at))
            left, at, d = left[order], at[order], d[order]
            new = np.empty(len(left), bool)
            new[0] = True
            new[1:] = (at[1:] != at[:-1]) | (d[1:] != d[:-1])
            child = left[new]
            parent[child], key[child] = at[new], d[new]
            at = np.repeat(child, np.diff(np.append(np.flatnonzero(new), len(left))))[~new]
            left = left[~new]
        order = np.lexsort((key, parent))
        order = order[parent[order] >= 0]
        self._index(order, parent[order], key[order])

    def _index(self, child: np.ndarray, parent: np.ndarray, key: np.ndarray) -> None:
        self.child, self.parent, self.key = child, parent, key
        self.width = 64 * self.points.shape[1] + 2
        self.place = parent * self.width + key  # sorted: children of a node, by key

    def pack(self) -> bytes:
        head = np.array([*self.points.shape, len(self.roots), len(self.child)], np.int64).tobytes()
        return head + b"".join(x.tobytes() for x in (self.points, self.shards, self.roots.astype(np.int32), self.child.astype(np.int32), self.parent.astype(np.int32), self.key.astype(np.int16)))

    @classmethod
    def unpack(cls, packed: list[bytes]) -> TreeSet:
        """All trees of several packed sets, as one set."""
        kinds = (np.uint64, np.int64, np.int32, np.int32, np.int32, np.int16)
        found: list[list[np.ndarray]] = [[] for _ in kinds]
        before = 0
        for data in packed:
            n, words, n_roots, n_child = (int(x) for x in np.frombuffer(data, np.int64, 4))
            at = 32
            for k, (kind, size) in enumerate(zip(kinds, (n * words, n_roots, n_roots, n_child, n_child, n_child), strict=True)):
                own = np.frombuffer(data, kind, size, at)
                at += own.nbytes
                found[k].append(own.reshape(n, words) if k == 0 else own if k in (1, 5) else own.astype(np.int64) + before)
            before += n
        self = cls.__new__(cls)
        points, shards, roots, child, parent, key = (np.concatenate(x) if x else np.empty((0, 1) if k == 0 else 0, kinds[k]) for k, x in enumerate(found))
        order = np.argsort(shards, kind="stable")
        self.points, self.shards, self.roots = points, shards[order], roots[order]
        self._index(child, parent, key.astype(np.int64))
        return self

    def root_of(self, shard: np.ndarray) -> np.ndarray:
        """The root of each shard's tree, which must be here."""
        at = np.minimum(np.searchsorted(self.shards, shard), len(self.shards) - 1)
        if not np.array_equal(self.shards[at], shard):
            raise KeyError("a query's tree is not among those of its round")
        return self.roots[at]

    def search(self, queries: np.ndarray, roots: np.ndarray, radius: np.ndarray | int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs (query number, point number) within the radius, which may differ by query. roots: of the tree that each query searches."""
        reach = np.broadcast_to(np.asarray(radius, np.int64), len(queries))
        stack = [(np.arange(len(queries)), np.asarray(roots))]
        while stack:
            who, node = stack.pop()
            if len(who) > BLOCK_PAIRS:
                half = len(who) // 2
                stack += [(who[:half], node[:half]), (who[half:], node[half:])]
                continue
            d = np.bitwise_count(queries[who] ^ self.points[node]).sum(1).astype(np.int64)
            hit = d <= reach[who]
            if hit.any():
                yield who[hit], node[hit]
            base = node * self.width
            low = np.searchsorted(self.place, base + np.maximum(d - reach[who], 0))
            high = np.searchsorted(self.place, base + np.minimum(d + reach[who], self.width - 1), "right")
            n = high - low
            more = n > 0
            if more.any():
                low, n, who = low[more], n[more], who[more]
                edge = np.repeat(low - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(n.sum())
                stack.append((np.repeat(who, n), self.child[edge]))


def _least_labels(a: np.ndarray, b: np.ndarray, label: np.ndarray) -> np.ndarray:
    """Labels (each at most its own number) so that points linked by a, b or by earlier labels share the least."""
    while True:
        low = np.minimum(label[a], label[b])
        before = label.copy()
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        label = label[label]
        if np.array_equal(label, before):
            return label


def _numbers(column: pa.Array, n_words: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), ">u8").reshape(-1, n_words).astype(np.uint64)


def _build(batches: Iterator[pa.RecordBatch], n_words: int) -> Iterator[pa.RecordBatch]:
    """Packed trees of each bin, and their keys in the order of points. Rows come sorted by bin and tree."""
    kept_in_worker(None)
    held: list[pa.RecordBatch] = []

    def trees() -> pa.RecordBatch:
        rows = pa.Table.from_batches(held)
        held.clear()
        points = _numbers(rows.column("fp"), n_words)
        tree = rows.column("tree").to_numpy()
        packed = TreeSet(points, tree).pack()
        keys = b"".join(rows.column("key").to_pylist())
        return pa.RecordBatch.from_pydict({"bin": pa.array([rows.column("bin")[0].as_py()], pa.int32()), "packed": pa.array([packed], pa.binary()), "keys": pa.array([keys], pa.binary())})

    for batch in batches:
        number = batch.column("bin").to_numpy()
        edges = [0, *(np.flatnonzero(np.diff(number)) + 1).tolist(), len(number)]
        for a, b in itertools.pairwise(edges):
            if held and held[0].column("bin")[0].as_py() != number[a]:
                yield trees()
            if b > a:
                held.append(batch.slice(a, b - a))
    if held:
        yield trees()


def _probe(batches: Iterator[pa.RecordBatch], name: tuple, shared, n_words: int, key_bytes: int) -> Iterator[pa.RecordBatch]:
    """Links (a, b) of a spanning forest of what each batch finds in the broadcast trees."""

    def load() -> tuple[TreeSet, np.ndarray]:
        rows = shared.value
        return TreeSet.unpack([p for p, _ in rows]), np.frombuffer(b"".join(k for _, k in rows), f"S{key_bytes}") if rows else np.empty(0, f"S{key_bytes}")

    forest, keys = kept_in_worker(name, load)
    for batch in batches:
        roots = forest.root_of(batch.column("tree").to_numpy())
        queries = _numbers(batch.column("fp"), n_words)
        own = np.frombuffer(b"".join(batch.column("key").to_pylist()), keys.dtype)
        reach = batch.column("reach").to_numpy()
        apart_who, apart_node = [], []
        step = max(1, BLOCK_PAIRS // 64)
        for first in range(0, len(queries), step):
            part = slice(first, first + step)
            for who, node in forest.search(queries[part], roots[part], reach[part]):
                who = who + first
                differ = own[who] != keys[node]
                apart_who.append(who[differ])
                apart_node.append(node[differ])
                if sum(map(len, apart_who)) > BLOCK_PAIRS:
                    yield from _forest(apart_who, apart_node, own, keys)
        yield from _forest(apart_who, apart_node, own, keys)


def _forest(apart_who: list[np.ndarray], apart_node: list[np.ndarray], own: np.ndarray, keys: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Each node and each query with hits, linked to the least node of its component; forgets the hits."""
    if not sum(map(len, apart_who)):
        return
    who, node = np.concatenate(apart_who), np.concatenate(apart_node)
    apart_who.clear()
    apart_node.clear()
    asked, who = np.unique(who, return_inverse=True)
    touched, node = np.unique(node, return_inverse=True)
    linked = _least_labels(node, len(touched) + who, np.arange(len(touched) + len(asked)))
    names = np.concatenate([keys[touched], own[asked]])
    end = names[linked]
    left = names != end
    width = names.dtype.itemsize
    both = [pa.FixedSizeBinaryArray.from_buffers(pa.binary(width), int(left.sum()), [None, pa.py_buffer(np.ascontiguousarray(x[left]).tobytes())]).cast(pa.binary()) for x in (names, end)]
    if left.any():
        yield pa.RecordBatch.from_arrays(both, ["a", "b"])


def links(nodes: DataFrame, n_words: int, key_bytes: int, chunk: int = CHUNK, round_bytes: int = ROUND_BYTES, bin_bytes: int = BIN_BYTES) -> DataFrame:
    """Links (a, b) between keys that join all nodes of a shard whose fingerprints differ in as many bits as they reach.

    nodes: key (binary of key_bytes), fp (binary), reach (int), shards (array of bigint), a row for each
    key. A shard of one node costs a count. What the driver holds is one round of trees.
    """
    spark = nodes.sparkSession
    members = nodes.select(F.explode("shards").alias("shard"), "key", "fp", "reach")
    sizes = cut(members.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"))
    total = sizes.agg(F.sum("n")).first()[0] or 0
    if not total:
        return spark.createDataFrame([], "a binary, b binary")
    n_bins = max(1, math.ceil(total * (8 * n_words + key_bytes + 10) / bin_bytes))
    n_rounds = math.ceil(n_bins * bin_bytes / round_bytes)
    chunks = F.ceil(F.col("n") / chunk).cast("int")
    live = members.join(sizes, "shard").withColumn("own", F.pmod(F.xxhash64("key"), chunks).cast("int"))
    # a query searches the trees up to its own: each pair of trees meets once
    live = live.withColumn("target", F.explode(F.sequence(F.lit(0), F.col("own")))).withColumn("tree", F.xxhash64("shard", "target"))
    live = live.withColumn("bin", F.pmod(F.col("tree"), F.lit(n_bins)).cast("int")).withColumn("round", F.pmod(F.col("bin"), F.lit(n_rounds)).cast("int"))
    place = shared_dir(spark)
    live.select("round", "bin", "tree", (F.col("target") == F.col("own")).alias("member"), "key", "fp", "reach").write.partitionBy("round").parquet(f"{place}/live")
    live = spark.read.schema("bin int, tree bigint, member boolean, key binary, fp binary, reach int, round int").parquet(f"{place}/live")
    dealt = live.filter("member").select("bin", "tree", "fp", "key").repartition("bin").sortWithinPartitions("bin", "tree", "key")
    trees = cut(dealt.mapInArrow(lambda b: _build(b, n_words), "bin int, packed binary, keys binary").withColumn("round", F.pmod(F.col("bin"), F.lit(n_rounds)).cast("int")))
    for r in range(n_rounds):
        rows = [(bytes(x["packed"]), bytes(x["keys"])) for x in trees.filter(F.col("round") == r).select("packed", "keys").collect()]  # at most round_bytes, about
        shared = spark.sparkContext.broadcast(rows)
        name = ("trees", place, r)
        found = live.filter(F.col("round") == r).select("tree", "key", "fp", "reach").mapInArrow(lambda b, s=shared, m=name: _probe(b, m, s, n_words, key_bytes), "a binary, b binary")
        found.distinct().write.mode("append").parquet(f"{place}/links")
        shared.unpersist()
    drop(sizes, trees, f"{place}/live")
    return spark.read.schema("a binary, b binary").parquet(f"{place}/links")


# ---- fingerprints within a radius


def near_duplicates(df: DataFrame, words: int = WORDS, radius: int = RADIUS, parts: int = PARTS, **options) -> DataFrame:
    """doc_id, fp (binary), component_id of each row: the smallest doc_id reachable through links."""
    own = cut(fingerprints(df, words))
    nodes = cut(own.groupBy("fp").agg(F.min("doc_id").alias("least")))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                shards = part_shards(_numbers(batch.column("fp"), 1)[:, 0], parts, radius)
                fp = batch.column("fp")
                yield pa.RecordBatch.from_arrays([fp, fp, pa.array(np.full(len(fp), radius, np.int32)), pa.array(list(shards), pa.list_(pa.int64()))], ["key", "fp", "reach", "shards"])

    found = links(nodes.select("fp").mapInArrow(place, "key binary, fp binary, reach int, shards array<bigint>"), 1, 8, **options)
    roots = cut(components(found).withColumnRenamed("node", "fp"))
    of = nodes.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    named = of.groupBy("root").agg(F.min("least").alias("component_id"))
    by_fp = cut(of.join(named, "root").select("fp", "component_id"))
    return own.join(by_fp, "fp").select("doc_id", "fp", "component_id")


# ---- texts with a similarity


def differing_bits(common: int, left: int, right: int) -> float:
    """Chance that a bit differs between two sets with so many common and own shingles; exact."""

    def above(own: int, rest: int, n: int) -> float:
        return sum(math.comb(own, k) for k in range(own + 1) if 2 * (k + rest) > n) / 2**own

    total = 0.0
    for k in range(common + 1):
        a, b = above(left, k, common + left), above(right, k, common + right)
        total += math.comb(common, k) / 2**common * (a * (1 - b) + b * (1 - a))
    return total


@cache
def reaches(similarity: float, bits: int, spread: float) -> tuple[int, ...]:
    """By the number of shingles of a set (the last for all larger ones): the bits that differ at the similarity, and `spread` standard deviations more."""

    def reach(p: float) -> int:
        return math.ceil(bits * p + spread * math.sqrt(bits * p * (1 - p)))

    usual = math.acos(2 * similarity / (1 + similarity)) / math.pi
    worst = [0.0]
    for common in range(1, LARGE_SET + 1):
        own = math.floor(common / similarity + 1e-9) - common  # shingles that only one of both has
        worst.append(max(differing_bits(common, left, own - left) for left in range(own // 2 + 1)))
    out = [reach(max(usual, *worst[math.ceil(similarity * n - 1e-9) : n + 1])) if n else 0 for n in range(LARGE_SET + 1)]
    return (*out, reach(usual))


def sketches(df: DataFrame, words: int, similarity: float, n_words: int, bands: int, rows: int, spread: float) -> DataFrame:
    """doc_id, text_key (MD5 of the text), n (distinct shingles), key (of the set of them), fp, reach and shards of each row."""
    kind = dict(df.dtypes)["doc_id"]
    schema = f"doc_id {kind}, text_key binary, n int, key binary, fp binary, reach int, shards array<bigint>"

    def make():
        reach = reaches(similarity, 64 * n_words, spread)

        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            out: list[list] = [[] for _ in range(6)]
            for text in as_bytes(part.column("text")):
                own = np.unique(text_hashes(text, words))
                values = (hashlib.md5(text or b"").digest(), len(own), xxhash.xxh3_128_digest(own.tobytes()), fingerprint(own, n_words), reach[min(len(own), len(reach) - 1)], band_shards(own, bands, rows) if len(own) else [])
                for column, value in zip(out, values, strict=True):
                    column.append(value)
            kinds = (pa.binary(), pa.int32(), pa.binary(), pa.binary(), pa.int32(), pa.list_(pa.int64()))
            return pa.RecordBatch.from_arrays([part.column("doc_id"), *(pa.array(c, k) for c, k in zip(out, kinds, strict=True))], ["doc_id", "text_key", "n", "key", "fp", "reach", "shards"])

        return one

    return map_texts(df.select("doc_id", "text"), schema, make)


def _alike(sets: list[np.ndarray], left: int, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of sets with the similarity: of any two if left is all of them, else of one of the first `left` and one of the others."""
    if not left:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    length = np.array([len(s) for s in sets], np.int64)
    owner = np.repeat(np.arange(len(sets)), length)
    _, code, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    order = np.argsort(code, kind="stable")  # owners of each shingle, one list after the other
    lists, start = owner[order], np.cumsum(count) - count
    ends = np.cumsum(length)
    a, b = [], []
    for i in range(left):
        own = code[ends[i] - length[i] : ends[i]]
        own = own[count[own] > 1]
        n = count[own]
        at = np.repeat(start[own] - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(n.sum()) if len(own) else own
        both = np.bincount(lists[at], minlength=len(sets))
        both[: i + 1 if left == len(sets) else left] = 0
        hit = np.flatnonzero((both > 0) & (both >= similarity * (length + length[i] - both) - 1e-9))
        a.append(np.full(len(hit), i))
        b.append(hit)
    return np.concatenate(a), np.concatenate(b)


def _verify(batches: Iterator[pa.RecordBatch], words: int, similarity: float) -> Iterator[pa.RecordBatch]:
    """Links (a, b) of a spanning forest of the pairs in each block that have the similarity. Rows come sorted by block, its first part first."""
    kept_in_worker(None)
    keys: list[bytes] = []
    sets: list[np.ndarray] = []
    at, left = None, 0
    out: tuple[list, list] = ([], [])

    def block() -> None:
        n = left if at[1] != at[2] else len(keys)
        a, b = _alike(sets, n, similarity)
        label = _least_labels(a, b, np.arange(len(keys)))
        moved = np.flatnonzero(label != np.arange(len(keys)))
        out[0].extend(keys[x] for x in moved)
        out[1].extend(keys[label[x]] for x in moved)

    for batch in batches:
        for root, i, j, part, key, text in zip(*(batch.column(c).to_pylist() for c in ("root", "i", "j", "part")), batch.column("key").to_pylist(), as_bytes(batch.column("text")), strict=True):
            if (root, i, j) != at:
                if len(keys) > 1:
                    block()
                keys, sets, at, left = [], [], (root, i, j), 0
            keys.append(key)
            sets.append(np.unique(text_hashes(text, words)))
            left += part == i
        if out[0]:
            yield pa.RecordBatch.from_pydict({"a": pa.array(out[0], pa.binary()), "b": pa.array(out[1], pa.binary())})
            out = ([], [])
    if len(keys) > 1:
        block()
    if out[0]:
        yield pa.RecordBatch.from_pydict({"a": pa.array(out[0], pa.binary()), "b": pa.array(out[1], pa.binary())})


def verified(df: DataFrame, nodes: DataFrame, groups: DataFrame, words: int, similarity: float, group_texts: int = GROUP_TEXTS, group_bytes: int = GROUP_BYTES) -> DataFrame:
    """Links (a, b) between keys of one group whose texts have the similarity. nodes: key, text_key; groups: node, root.

    A text is taken once, whatever the number of its copies. A group of many texts is cut into parts,
    and every two parts meet in a block of their own.
    """
    texts = df.select(F.unhex(F.md5(F.coalesce("text", F.lit("")))).alias("text_key"), F.coalesce("text", F.lit("")).alias("text")).groupBy("text_key").agg(F.first("text").alias("text"))
    wanted = groups.select(F.col("node").alias("key"), "root").join(nodes.select("key", "text_key"), "key")
    held = cut(wanted.join(texts, "text_key").select("key", "root", "text"))
    sizes = held.groupBy("root").agg(F.greatest(F.ceil(F.count(F.lit(1)) / group_texts), F.ceil(F.sum(F.octet_length("text")) / group_bytes)).cast("int").alias("parts")).filter("parts > 1")
    held = held.join(sizes, "root", "left").withColumn("parts", F.coalesce("parts", F.lit(1))).withColumn("part", F.pmod(F.xxhash64("key"), F.col("parts")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("parts") - 1))
    held = held.withColumn("other", other).withColumn("i", F.least("part", "other")).withColumn("j", F.greatest("part", "other"))
    dealt = held.select("root", "i", "j", "part", "key", "text").repartition("root", "i", "j").sortWithinPartitions("root", "i", "j", "part")
    return dealt.mapInArrow(lambda b: _verify(b, words, similarity), "a binary, b binary")


def similar_documents(df: DataFrame, words: int = 5, similarity: float = 0.8, n_words: int = 4, bands: int = BANDS, rows: int = ROWS, spread: float = 4.0, **options) -> DataFrame:
    """doc_id, text_key, n, fp, component_id, stays of each row: texts link if their shingle sets have that Jaccard similarity or more.

    component_id is the smallest doc_id of those reachable through links; stays is true for the rows of
    one (doc_id, text) of each component, the smallest. Fingerprints are of the sets, so a passage that
    recurs in one text counts once. Of pairs at the similarity itself about one in a thousand may share no
    shard or lie beyond the radius, fewer above it; no pair below it links.
    """
    own = cut(sketches(df, words, similarity, n_words, bands, rows, spread))
    first = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_key")
    nodes = cut(own.groupBy("key").agg(F.min(first).alias("least"), F.first("fp").alias("fp"), F.first("reach").alias("reach"), F.first("shards").alias("shards")))
    found = links(nodes.select("key", "fp", "reach", "shards"), n_words, 16, **options)
    groups = cut(components(found))
    found = cut(verified(df, nodes.select("key", F.col("least.text_key").alias("text_key")), groups, words, similarity))
    roots = cut(components(found).withColumnRenamed("node", "key"))
    of = nodes.select("key", "least").join(roots, "key", "left").withColumn("root", F.coalesce("root", "key"))
    named = of.groupBy("root").agg(F.min("least").alias("chosen"))
    by_key = cut(of.join(named, "root").select("key", "chosen"))
    return own.join(by_key, "key").select("doc_id", "text_key", "n", "fp", F.col("chosen.doc_id").alias("component_id"), first.eqNullSafe(F.col("chosen")).alias("stays"))


def op6_simhash_bktree(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.hex("fp")).alias("fingerprint"), "component_id")
