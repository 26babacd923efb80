"""Benchmark decontamination: rare seeds, then Smith-Waterman alignment.

A local alignment scores matches, replaced, missing and added words, so paraphrased and edited copies
still score; a pair is reported if its score is at least `similarity` of what the whole item would
score. Every such pair is found:

- A pair at the similarity matches at least that share of the item's words. So the seeds of an item
  are its words, rarest first, until those left are one too few for that: each pair holds a seed,
  whichever words an edit has replaced. Rarity, the number of documents with each word, only makes
  candidates few.
- A candidate's words gain what a match does if the item has them, and lose what another word does
  if not. No alignment scores more than the sum over its passage, so only passages whose sum can
  reach the similarity are aligned.

A seed is an n-gram of one word: longer ones would lose pairs whose every second or third word is
replaced, which still score above the similarity.

The test set is the small side: it is cut into blocks of at most `block_bytes`, and each block is
broadcast and run against all documents. The driver holds one block and a row for each of its words.

Defined results: words are runs of letters and digits in lower case; null and empty texts and items
without words match nothing; repeated rows give repeated pairs; a null doc_id or item_id is kept, of
whatever type; empty tables give no pairs, and nothing is taken away.
"""

from __future__ import annotations

import math
import re
from collections.abc import Collection, Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, map_texts, table

SIMILARITY = 0.5
MATCH, REPLACED, GAP = 2, -1, -1
#: Bytes of the items that are indexed and broadcast at once.
BLOCK_BYTES = 16 << 20
#: Items times words of a text that are tested at once.
CELLS = 1 << 20
WORD = re.compile(r"[^\W_]+")
#: Bytes of UTF-8 to themselves, those of ASCII that are in no word to spaces.
SPACES = bytes(b if b > 127 or chr(b).isalnum() else 32 for b in range(256))
#: Distinct characters beyond ASCII that are replaced one by one; texts with more are searched.
FEW_SYMBOLS = 16


def words_of(text: str | None) -> list[str]:
    """The runs of letters and digits in lower case, as WORD finds them; cutting at spaces is quicker."""
    text = (text or "").lower()
    if not text.isascii():
        symbols = [c for c in set(text) if c > "\x7f" and not c.isalnum()]
        if len(symbols) > FEW_SYMBOLS:
            return WORD.findall(text)
        for c in symbols:
            text = text.replace(c, " ")
    return text.encode("utf-8", "surrogatepass").translate(SPACES).decode("utf-8", "surrogatepass").split()


def align(item: np.ndarray, passage: np.ndarray) -> tuple[float, int, int]:
    """Best local alignment: share of the item's full score, and where it ends in item and passage (exclusive)."""
    best, at = 0, (0, 0)
    steps = np.arange(len(passage) + 1) * -GAP
    row = np.zeros(len(passage) + 1, np.int64)
    for i, word in enumerate(item):
        new = np.zeros_like(row)
        new[1:] = np.maximum(row[:-1] + np.where(passage == word, MATCH, REPLACED), row[1:] + GAP)
        np.maximum(new, 0, out=new)
        new = np.maximum.accumulate(new + steps) - steps  # runs of added words
        row = np.maximum(new, 0)
        j = int(row.argmax())
        if row[j] > best:
            best, at = int(row[j]), (i + 1, j)
    return best / (MATCH * max(1, len(item))), *at


def _ranges(start: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The numbers from each start on, n of them, one range after the other."""
    return np.repeat(start - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(n.sum())


class ItemIndex:
    """Vocabulary and items of one block of the test set, and the seeds of the items."""

    def __init__(self, items: list[tuple[int | None, str | None]]):
        self.ids, self.items = [], []
        self.vocabulary: dict[str, int] = {}
        for item_id, text in items:
            own = [self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words_of(text)]
            if own:
                self.ids.append(item_id)
                self.items.append(np.array(own, np.int64))
        self.length = np.array([len(item) for item in self.items], np.int64)
        self.words = np.concatenate(self.items) if self.items else np.empty(0, np.int64)
        self.start = np.cumsum(self.length) - self.length
        self.of_text, self.of_item = np.zeros((2, len(self.vocabulary) + 1), bool)
        self.place = np.zeros(len(self.vocabulary) + 1, np.int64)

    def numbers(self, words: Collection[str]) -> np.ndarray:
        """The word numbers of a text, or of its distinct words (0: not in the vocabulary)."""
        return np.fromiter(map(self.vocabulary.get, words, repeat(0)), np.int64, len(words))

    def keep_rare(self, count: dict[int, int], similarity: float = SIMILARITY) -> None:
        """Seeds: of each item the words in the fewest documents, so many that those left alone cannot reach the similarity."""
        seeds = []
        for i, item in enumerate(self.items):
            least = max(1, math.ceil(similarity * len(item) - 1e-9))  # words that a pair matches
            ranked = sorted((count.get(w, 0), w) for w in item.tolist())
            seeds += [(w, i) for w in {w for _, w in ranked[: max(1, len(item) - least + 1)]}]
        word, self.seeded = np.array(sorted(seeds), np.int64).reshape(-1, 2).T
        self.first = np.searchsorted(word, np.arange(len(self.vocabulary) + 2))

    def candidates(self, present: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
        """Items with a seed among the distinct word numbers of a text, and enough words in it; how many seeds each has."""
        seeds = np.bincount(self.seeded[_ranges(self.first[present], self.first[present + 1] - self.first[present])])
        items = np.flatnonzero(seeds)
        n_seeds = seeds[items]
        if not len(items):
            return items, n_seeds
        length = self.length[items]
        self.of_text[present] = True
        found = self.of_text[self.words[_ranges(self.start[items], length)]]
        self.of_text[present] = False
        enough = np.add.reduceat(found, np.cumsum(length) - length, dtype=np.int64) >= similarity * length - 1e-9
        return items[enough], n_seeds[enough]

    def matches(self, text: str | None, similarity: float, first_only: bool = False) -> list[tuple[int | None, float, int, int, int]]:
        """item_id, score, seeds found, first and last word (exclusive) of the aligned passage; first_only: one item is enough."""
        own = self.numbers(words_of(text))
        at = np.flatnonzero(own)
        if not len(at):
            return []
        known = own[at]
        self.of_text[known] = True
        present = np.flatnonzero(self.of_text)
        self.of_text[present] = False
        out = []
        for i, n_seeds in self._reaching(at, known, present, *self.candidates(present, similarity), similarity):
            item = self.items[i]
            best = (0.0, 0, 0)
            for a, b in self._passages(at, known, item, MATCH * similarity * len(item) - 1e-9):
                score, _, end = align(item, own[a:b])
                best = max(best, (score, a + end - min(end, len(item)), a + end))
            if best[0] > 0 and best[0] >= similarity:
                out.append((self.ids[i], best[0], n_seeds, best[1], best[2]))
                if first_only:
                    break
        return out

    def _reaching(self, at: np.ndarray, known: np.ndarray, present: np.ndarray, items: np.ndarray, n_seeds: np.ndarray, similarity: float) -> Iterator[tuple[int, int]]:
        """The candidates for which `_passages` finds any, with their seeds: its first test, for many items at once."""
        loss = -max(REPLACED, GAP)
        apart = 2 * (MATCH + loss) * len(known) + loss * int(at[-1]) + 1  # more than the sums of two items differ by
        self.place[present] = np.arange(len(present))
        column = self.place[known]
        many = max(1, CELLS // len(known))
        for first in range(0, len(items), many):
            some = items[first : first + many]
            length = self.length[some]
            words = self.words[_ranges(self.start[some], length)]
            self.of_text[present] = True
            held = self.of_text[words]
            self.of_text[present] = False
            has = np.zeros((len(some), len(present)), bool)
            has[np.repeat(np.arange(len(some)), length)[held], self.place[words[held]]] = True
            row, k = np.divmod(np.flatnonzero(has[:, column]), len(column))  # the words of each item in the text, item by item; each has a seed there
            before = (MATCH + loss) * np.arange(len(row)) - loss * at[k] - apart * row  # below those of earlier items, so that minima begin anew
            ending = before + MATCH - np.minimum.accumulate(before)
            best = np.maximum.reduceat(ending, np.searchsorted(row, np.arange(len(some))))
            for j in np.flatnonzero(best >= MATCH * similarity * length - 1e-9).tolist():
                yield int(some[j]), int(n_seeds[first + j])

    def _passages(self, at: np.ndarray, known: np.ndarray, item: np.ndarray, need: float) -> list[tuple[int, int]]:
        """The parts of a text, given as places and numbers of its known words, that hold every passage whose alignment may score `need`."""
        self.of_item[item] = True
        p = at[self.of_item[known]]
        self.of_item[item] = False
        loss = -max(REPLACED, GAP)
        before = (MATCH + loss) * np.arange(len(p)) - loss * p  # sum of all words before each word of the item
        after = before + MATCH
        ending = after - np.minimum.accumulate(before)  # largest sum of a passage that ends here
        if not len(p) or ending.max() < need:
            return []
        starting = np.maximum.accumulate(after[::-1])[::-1] - before
        whole = np.flatnonzero(ending + starting - MATCH >= need)
        apart = ending[whole[:-1]] + starting[whole[1:]] - loss * (np.diff(p[whole]) - 1) < need
        apart |= np.diff(whole) > 1
        first, last = p[whole[np.append(True, apart)]], p[whole[np.append(apart, True)]]
        return list(zip(first.tolist(), (last + 1).tolist(), strict=True))


def blocks(benchmark: DataFrame, block_bytes: int = BLOCK_BYTES) -> Iterator[list[tuple]]:
    """The test set in blocks of about so many bytes of text, read row by row; the driver holds one block."""
    out, size = [], 0
    for r in benchmark.select("item_id", "text").orderBy("item_id", "text").toLocalIterator():
        n = len((r["text"] or "").encode()) + 16
        if out and size + n > block_bytes:
            yield out
            out, size = [], 0
        out.append((r["item_id"], r["text"]))
        size += n
    if out:
        yield out


def word_counts(docs: DataFrame, shared) -> DataFrame:
    """word, n: documents that hold each word of a block, over all documents."""

    def make():
        index = shared.value

        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            total = np.zeros(len(index.vocabulary) + 1, np.int64)
            for text in part.column("text").to_pylist():
                if text:
                    total[index.numbers(set(words_of(text)))] += 1
            total[0] = 0
            k = np.flatnonzero(total)
            return pa.RecordBatch.from_arrays([pa.array(k), pa.array(total[k])], ["word", "n"])

        return one

    return map_texts(docs.select("text"), "word bigint, n bigint", make).groupBy("word").agg(F.sum("n").alias("n"))


def _indexes(docs: DataFrame, benchmark: DataFrame, similarity: float, block_bytes: int) -> Iterator:
    """The index of each block of the test set, broadcast, with seeds chosen by the counts of all documents."""
    spark = docs.sparkSession
    for rows in blocks(benchmark, block_bytes):
        index = ItemIndex(rows)
        if not index.items:
            continue
        counts = {r["word"]: r["n"] for r in word_counts(docs, spark.sparkContext.broadcast(index)).collect()}  # a row for each word of the block
        index.keep_rare(counts, similarity)
        yield spark.sparkContext.broadcast(index)


def contaminated(docs: DataFrame, benchmark: DataFrame, similarity: float = SIMILARITY, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, item_id, score, n_seeds, first_word, last_word of each document and item that align."""
    kind, item_kind = dict(docs.dtypes)["doc_id"], dict(benchmark.dtypes)["item_id"]
    schema = f"doc_id {kind}, item_id {item_kind}, score double, n_seeds bigint, first_word bigint, last_word bigint"
    found = None
    for shared in _indexes(docs, benchmark, similarity, block_bytes):

        def make(shared=shared):
            own = shared.value

            def one(part: pa.RecordBatch) -> pa.RecordBatch:
                got, at = [], []
                for k, text in enumerate(part.column("text").to_pylist()):
                    if text and (hits := own.matches(text, similarity)):
                        got.extend(hits)
                        at.extend([k] * len(hits))
                ids = part.column("doc_id").take(pa.array(at, pa.int64()))
                items = pa.array([g[0] for g in got]) if got else pa.array([], pa.null())
                kinds = (pa.float64(), pa.int64(), pa.int64(), pa.int64())
                columns = [pa.array([g[c] for g in got], t) for c, t in enumerate(kinds, 1)]
                return pa.RecordBatch.from_arrays([ids, items, *columns], ["doc_id", "item_id", "score", "n_seeds", "first_word", "last_word"])

            return one

        part = map_texts(docs.select("doc_id", "text"), schema, make)
        found = part if found is None else cut(found.unionByName(part))
    return docs.sparkSession.createDataFrame([], schema) if found is None else found


def clean(docs: DataFrame, benchmark: DataFrame, similarity: float = SIMILARITY, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """The rows of docs, with all their columns, whose text aligns with no item. Each row is judged by its own text, whatever its doc_id; nothing is joined."""
    for shared in _indexes(docs, benchmark, similarity, block_bytes):

        def make(shared=shared):
            own = shared.value

            def one(part: pa.RecordBatch) -> pa.RecordBatch:
                return part.filter(pa.array([not (text and own.matches(text, similarity, True)) for text in part.column("text").to_pylist()], pa.bool_()))

            return one

        docs = map_texts(docs, docs.schema, make)
    return docs


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
