"""Language identification by prediction by partial matching.

For each language a context tree counts which byte follows each context of up to `order` bytes in
its training texts. A text's code length under a tree is exact: at the longest known context the byte
is coded by its share, or an escape leads to the next shorter context, where bytes already excluded
no longer count; the escape is given as many counts as the context has distinct bytes. Below the
empty context all bytes are alike. The trees are frozen: reading a text does not change them.

Frozen trees make the cost of a byte a function of its context alone. So the trees are merged into
one of all contexts, and for each of its nodes the costs of every byte under every language are laid
out beforehand. A text is read by walking that tree backwards from each position, all positions at
once, and adding up costs. The language with the shortest code wins.

Training takes about `train_docs` texts of each language, chosen by a hash of their doc_id (the bound
on what the driver trains on); predictions cover all rows and whole texts.

Defined results: `und` with score 0 for null texts and texts without a letter, or if nothing could be
learned; ties go to the language that sorts first; a null lang is not learned from; a null doc_id
counts as the empty text in the split. Score: the share of the winner's likelihood, per byte, tempered.
"""

from __future__ import annotations

import pickle
import zlib

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, map_texts, remainder, table

ORDER = 4
#: Training texts of a language, about, and counts below which a context is not kept.
TRAIN_DOCS, LEAST_COUNT = 300, 3
LETTER = regex.compile(r"\p{L}")
#: Bytes that are walked at once.
WALK_BYTES = 1 << 19
UND = "und"


def _context_counts(texts: list[bytes], order: int, least: int) -> dict[tuple[int, ...], dict[int, int]]:
    """context (nearest byte first) -> following byte -> count. Texts are preceded by line feeds."""
    data = np.frombuffer(b"".join(b"\n" * order + t for t in texts), np.uint8).astype(np.uint64)
    own = np.concatenate([np.arange(len(t)) + order for t in texts]) if texts else np.empty(0, np.int64)
    begin = np.repeat(np.cumsum([0, *(len(t) + order for t in texts[:-1])]), [len(t) for t in texts]) if texts else own
    at = own + begin
    out: dict[tuple[int, ...], dict[int, int]] = {}
    for k in range(order + 1):
        code = data[at]
        for j in range(1, k + 1):
            code = code | data[at - j] << np.uint64(8 * j)
        value, count = np.unique(code, return_counts=True)
        context = value >> np.uint64(8)
        first = np.flatnonzero(np.diff(context, prepend=context[0] + np.uint64(1) if len(context) else 0)) if len(context) else []
        for a, b in zip(first, [*first[1:], len(context)], strict=True):
            if k and count[a:b].sum() < least:
                continue
            c = int(context[a])
            name = tuple(c >> 8 * j & 255 for j in range(k))
            if k and name[:-1] not in out:
                continue
            out[name] = dict(zip((value[a:b] & np.uint64(255)).astype(int).tolist(), count[a:b].tolist(), strict=True))
    out.setdefault((), {})
    return out


def tree_costs(counts: dict[tuple[int, ...], dict[int, int]], column: dict[int, int], kinds: int) -> tuple[list[tuple[int, ...]], np.ndarray]:
    """The tree's contexts and, in their order, the bits of each byte class after them, by escapes with exclusion.

    column: byte -> class; the last class stands for all bytes that were never seen.
    """
    contexts = sorted(counts, key=lambda c: (len(c), c))
    number = {c: i for i, c in enumerate(contexts)}
    table = np.zeros((len(contexts), kinds), np.float32)
    for i, c in enumerate(contexts):
        for s, n in counts[c].items():
            table[i, column[s]] = n
    alike = np.ones(kinds)
    alike[-1] = 256 - len(column)
    cost = np.zeros((len(contexts), kinds))
    depth = np.array([len(c) for c in contexts])
    for d in range(int(depth.max()) + 1):
        own = np.flatnonzero(depth == d)
        at = own.copy()
        open_, spent = np.ones((len(own), kinds), bool), np.zeros(len(own))
        bits = np.zeros((len(own), kinds))
        for level in range(d, -1, -1):
            seen = table[at] * open_
            total, distinct = seen.sum(1), (seen > 0).sum(1)
            whole = np.maximum(total + distinct, 1)
            here = seen > 0
            with np.errstate(divide="ignore"):
                bits = np.where(here, spent[:, None] - np.log2(seen / whole[:, None]), bits)
            open_ &= ~here
            left = open_ @ alike > 0
            spent = spent + np.where((distinct > 0) & left, -np.log2(np.maximum(distinct, 1) / whole), 0.0)
            if level:
                at = np.array([number[contexts[i][: level - 1]] for i in own])
        rest = np.maximum(open_ @ alike, 1)
        cost[own] = np.where(open_, (spent + np.log2(rest))[:, None], bits)
    return contexts, cost


class LanguageModel:
    """The merged tree: `next[node, byte class]` (a longer context, or that node's stop) and costs by node, byte class, language."""

    def __init__(self, texts: dict[str, list[bytes]], order: int = ORDER, least: int = LEAST_COUNT):
        self._build(sorted(texts), order, [_context_counts(texts[name], order, least) for name in sorted(texts)])

    def __getstate__(self) -> bytes:
        """What is sent is the counts; each worker lays the costs out for itself."""
        return zlib.compress(pickle.dumps((self.names, self.order, self.counts)), 6)

    def __setstate__(self, state: bytes) -> None:
        self._build(*pickle.loads(zlib.decompress(state)))
        self.counts = []

    def _build(self, names: list[str], order: int, counts: list[dict]) -> None:
        self.names, self.order, self.counts = names, order, counts
        nodes = sorted(set().union(*counts) if counts else {()}, key=lambda c: (len(c), c))
        number = {c: i for i, c in enumerate(nodes)}
        used = sorted({s for tree in counts for c, seen in tree.items() for s in (*c, *seen)})
        self.kind = np.full(256, len(used), np.int64)  # bytes that occur nowhere are one class
        self.kind[used] = np.arange(len(used))
        self.kinds = len(used) + 1
        column = {s: i for i, s in enumerate(used)}
        costs = np.zeros((len(nodes), self.kinds, len(self.names)), np.float32)
        for k, tree in enumerate(counts):
            contexts, bits = tree_costs(tree, column, self.kinds)
            row = {c: i for i, c in enumerate(contexts)}
            of = np.zeros(len(nodes), np.int64)  # a context that a tree lacks costs what its longest known suffix does
            for c, i in number.items():
                of[i] = row[c] if c in row else of[number[c[:-1]]]
            costs[:, :, k] = bits.astype(np.float32)[of]
        self.costs = costs.reshape(len(nodes) * self.kinds, len(self.names))
        # nodes from n on are stops: the walk has left the tree and stays where it was
        n = len(nodes)
        self.nodes = n
        self.next = np.empty((n, self.kinds), np.int32)
        self.next[:] = np.arange(n, dtype=np.int32)[:, None] + n
        for c, i in number.items():
            if c:
                self.next[number[c[:-1]], self.kind[c[-1]]] = i

    def code_lengths(self, texts: list[bytes]) -> np.ndarray:
        """Bits of each text (rows) under each language (columns)."""
        out = np.zeros((len(texts), len(self.names)))
        pad = b"\n" * self.order
        group, size = [], 0
        for i, t in enumerate(texts):
            for a in range(0, len(t), WALK_BYTES):
                piece = (t[a - self.order : a] if a else pad) + t[a : a + WALK_BYTES]
                if size + len(piece) > WALK_BYTES and group:
                    self._walk(group, out)
                    group, size = [], 0
                group.append((i, piece))
                size += len(piece)
        if group:
            self._walk(group, out)
        return out

    def _walk(self, group: list[tuple[int, bytes]], out: np.ndarray) -> None:
        data = self.kind[np.frombuffer(b"".join(p for _, p in group), np.uint8)]
        n, order = len(data), self.order
        node = np.zeros(n - order, np.int32)
        flat = self.next.reshape(-1)
        for k in range(1, order + 1):
            there = node < self.nodes
            moved = flat[np.where(there, node, 0).astype(np.int64) * self.kinds + data[order - k : n - k]]
            node = np.where(there, moved, node)
        node = np.where(node < self.nodes, node, node - self.nodes)
        cost = self.costs[node.astype(np.int64) * self.kinds + data[order:]]
        at = 0
        for i, p in group:
            out[i] += cost[at : at + len(p) - order].sum(0, dtype=np.float64)
            at += len(p)

    def predict(self, texts: list[bytes | None]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, score, bits a byte under it."""
        plain = [t or b"" for t in texts]
        wordy = np.array([bool(self.names) and LETTER.search(t.decode()) is not None for t in plain], bool)
        if not self.names:
            return [UND] * len(plain), np.zeros(len(plain)), np.full(len(plain), 8.0)
        bits = self.code_lengths(plain)
        best = bits.argmin(1)
        least = bits[np.arange(len(plain)), best]
        length = np.maximum(1, np.array([len(t) for t in plain]))
        share = 1 / np.exp2(-(bits - least[:, None]) / np.sqrt(length)[:, None]).sum(1)
        return [self.names[b] if w else UND for b, w in zip(best, wordy, strict=True)], np.where(wordy, share, 0.0), least / length


def train(docs: DataFrame, train_docs: int = TRAIN_DOCS, order: int = ORDER) -> LanguageModel:
    """From (doc_id, text, lang) rows of the learning fold, about train_docs of each language, chosen by hash."""
    rows = docs.filter("lang is not null and text is not null").filter(remainder("doc_id", 4) != 2)
    sizes = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row a language
    if not sizes:
        return LanguageModel({})
    u = F.pmod(F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit("train")), F.lit(1 << 40)) / F.lit(float(1 << 40))
    share = F.lit(0.0)
    for lang, n in sizes.items():
        share = F.when(F.col("lang") == lang, min(1.0, train_docs / n)).otherwise(share)
    texts: dict[str, list[bytes]] = {lang: [] for lang in sizes}
    for r in sorted(rows.filter(u < share).select("lang", "text").collect()):
        texts[r["lang"]].append(r["text"].encode())
    return LanguageModel({k: v for k, v in texts.items() if v}, order)


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """The rows of docs with lang_pred, score and bits_per_byte."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    from pyspark.sql import types as T

    names = ("__lang", "__score", "__bits")
    schema = T.StructType([*docs.schema.fields, T.StructField(names[0], T.StringType()), T.StructField(names[1], T.DoubleType()), T.StructField(names[2], T.DoubleType())])

    def make():
        own = shared.value

        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            lang, score, bits = own.predict(as_bytes(part.column("text")))
            for name, values in zip(names, (pa.array(lang, pa.string()), pa.array(score), pa.array(bits)), strict=True):
                part = part.append_column(name, values)
            return part

        return one

    return map_texts(docs, schema, make)


def op2_ppm_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = identify(docs.select("doc_id", "text"), train(docs))
    return found.select("doc_id", (remainder("doc_id", 4) == 2).alias("held_out"), F.col("__lang").alias("lang_pred"), F.col("__score").alias("score"))
