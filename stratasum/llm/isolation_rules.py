"""Quality rules by an isolation forest over rule statistics.

Each text gets the statistics of common rules: counts of words, of their characters, of symbols, of
repeated lines and of words in repeated windows. Fixed base rules reject first. The rest is judged by
an isolation forest: trees split a sample at random features and random cuts, and rows that few cuts
set apart are anomalies. The forest grows on samples of labelled rows of good quality; the threshold
is the one that tells the labelled rows apart best.

Labelled rows are taken by the smallest hashes of their doc_id, `label_rows` at most. That bounds
what the driver trains on; statistics and verdicts cover all rows and whole texts.

Defined results: null and empty texts have no words and fail the base; repeated rows get equal rows;
a doc_id may be of any type that sorts; without labels of both kinds there is no threshold, and the base alone decides.
"""

from __future__ import annotations

import math
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, map_texts, table

SYMBOLS = b"#*$%&|<>"
#: Labelled rows to learn from, at most.
LABEL_ROWS = 20_000
TREES, TREE_ROWS, DEEPEST = 100, 256, 20
#: Cuts are drawn from the range of a node's rows and so much on both sides, in spreads: what lies where no good row does is set apart at once.
MARGIN = 1.0
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Statistics beyond the base.
MORE = ("n_lines", "n_upper", "n_digits", "n_stops", "n_distinct")


def _count(text: bytes, chars: bytes) -> int:
    return len(text) - len(text.translate(None, chars))


UPPER, DIGITS, STOPS, SPACES = bytes(range(65, 91)), bytes(range(48, 58)), b".!?", b" \t\n\v\f\r"


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a window of three which the text has twice or more."""
    windows = list(zip(words, words[1:], words[2:], strict=False))
    if len(set(windows)) == len(windows):
        return 0
    seen = Counter(windows)
    total, covered = 0, 0
    for i, w in enumerate(windows):
        if seen[w] > 1:
            total += i + 3 - max(covered, i)
            covered = i + 3
    return total


def statistics(text: bytes | None) -> tuple[int, ...]:
    """BASE and MORE of a text."""
    text = text or b""
    words = text.split()
    lines = [line for line in text.split(b"\n") if line and not line.isspace()] if b"\n" in text else []
    chars = len(text.decode()) - _count(text, SPACES)
    return (len(words), chars, _count(text, SYMBOLS), len(lines) - len(set(lines)), repeated_words(words), text.count(b"\n") + 1, _count(text, UPPER), _count(text, DIGITS), _count(text, STOPS), len(set(words)))


def features(stats: np.ndarray) -> np.ndarray:
    """Shares and means of the statistics, one row a text."""
    s = dict(zip(BASE + MORE, np.asarray(stats, float).T, strict=True))
    words, chars, lines = np.maximum(s["n_words"], 1), np.maximum(s["word_chars"], 1), np.maximum(s["n_lines"], 1)
    return np.column_stack([
        s["word_chars"] / words,
        s["n_symbols"] / words,
        s["n_dup_lines"] / lines,
        s["n_repeat_words"] / words,
        s["n_upper"] / chars,
        s["n_digits"] / chars,
        s["n_stops"] / words,
        s["n_distinct"] / np.sqrt(words),
    ])


def _mean_path(n: float) -> float:
    """Mean depth at which a search in a random tree of n rows ends without success."""
    return 0.0 if n <= 1 else 1.0 if n == 2 else 2 * (math.log(n - 1) + 0.5772156649015329) - 2 * (n - 1) / n


class IsolationForest:
    """Trees as arrays: feature (-1: leaf), cut, left child (the right one is next), depth with the mean path of a leaf's rows."""

    def __init__(self, rows: np.ndarray, trees: int = TREES, tree_rows: int = TREE_ROWS, seed: int = 11):
        rng = np.random.default_rng(seed)
        self.sample = min(tree_rows, len(rows))
        deepest = DEEPEST
        self.trees = [self._grow(rows[rng.choice(len(rows), self.sample, replace=False)], deepest, rng) for _ in range(trees)]

    @staticmethod
    def _grow(rows: np.ndarray, deepest: int, rng: np.random.Generator) -> tuple[np.ndarray, ...]:
        feature, cut, left, path = [-1], [0.0], [0], [0.0]
        todo = [(0, rows, 0)]
        while todo:
            node, own, depth = todo.pop()
            if depth == deepest or len(own) < 2:
                path[node] = depth + _mean_path(len(own))
                continue
            low, high = own.min(0) - MARGIN, own.max(0) + MARGIN
            f = int(rng.integers(own.shape[1]))
            c = rng.uniform(low[f], high[f])
            under = own[:, f] <= c
            feature[node], cut[node], left[node] = f, c, len(feature)
            for part in (own[under], own[~under]):
                todo.append((len(feature), part, depth + 1))
                feature.append(-1)
                cut.append(0.0)
                left.append(0)
                path.append(0.0)
        return np.array(feature), np.array(cut), np.array(left), np.array(path)

    def scores(self, rows: np.ndarray) -> np.ndarray:
        """0 to 1; near 1 for rows that few cuts set apart."""
        total = np.zeros(len(rows))
        number = np.arange(len(rows))
        for feature, cut, left, path in self.trees:
            at = np.zeros(len(rows), np.int64)
            while True:
                f = feature[at]
                if (f < 0).all():
                    break
                above = rows[number, np.maximum(f, 0)] > cut[at]
                at = np.where(f < 0, at, left[at] + above)
            total += path[at]
        return 2.0 ** (-total / len(self.trees) / max(_mean_path(self.sample), 1e-9))


class _Standard:
    """A forest sees features spread by their quantiles among good rows, so a far tail stays apart but does not hide the rest."""

    def __init__(self, good: np.ndarray):
        self.middle = np.median(good, 0)
        spread = np.quantile(good, 0.95, 0) - np.quantile(good, 0.05, 0)
        self.spread = np.maximum(spread, 0.02)

    def __call__(self, rows: np.ndarray) -> np.ndarray:
        return np.arcsinh((rows - self.middle) / self.spread)


class Judge:
    """Forest and threshold, learned from statistics and labels."""

    def __init__(self, stats: np.ndarray, quality: np.ndarray, seed: int = 11):
        self.threshold = math.inf
        keep = ~base_failed(stats)
        rows, good = features(stats)[keep], quality[keep] > 0
        if not good.any() or good.all():
            return
        self.standard = _Standard(rows[good])
        shown = self.standard(rows)
        self.forest = IsolationForest(shown[good], seed=seed)
        score = self.forest.scores(shown)
        order = np.argsort(-score, kind="stable")
        bad_caught = np.cumsum(~good[order])
        good_lost = np.cumsum(good[order])
        gain = bad_caught / max(1, (~good).sum()) - GOOD_WEIGHT * good_lost / good.sum()
        last = np.append(score[order][1:] < score[order][:-1], True)
        best = int(np.argmax(np.where(last, gain, -np.inf)))
        if gain[best] > 0:
            after = score[order][best + 1] if best + 1 < len(order) else 0.0
            self.threshold = (score[order][best] + after) / 2

    def scores(self, stats: np.ndarray) -> np.ndarray:
        if self.threshold == math.inf or not len(stats):
            return np.zeros(len(stats))
        return self.forest.scores(self.standard(features(stats)))


#: A good row lost weighs as much as so many bad rows kept (as shares of their kinds).
GOOD_WEIGHT = 10.0


def base_failed(stats: np.ndarray) -> np.ndarray:
    stats = np.asarray(stats, np.int64).reshape(-1, len(BASE + MORE))
    return (stats[:, 0] < 50) | (100 * stats[:, 4] > 50 * stats[:, 0])


def labelled_statistics(docs: DataFrame, labels: DataFrame, label_rows: int = LABEL_ROWS) -> tuple[np.ndarray, np.ndarray]:
    """Statistics and quality of at most label_rows labelled rows; collected, as the bound allows."""
    chosen = labels.filter("quality is not null and doc_id is not null").select("doc_id", "quality").orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(label_rows)
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")  # bounded by label_rows

    def make():
        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            stats = [statistics(t) for t in as_bytes(part.column("text"))]
            return pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("quality").cast(pa.int32()), pa.array(stats, pa.list_(pa.int64()))], ["doc_id", "quality", "stats"])

        return one

    kind = dict(docs.dtypes)["doc_id"]
    got = map_texts(rows.select("doc_id", F.col("quality").cast("int").alias("quality"), "text"), f"doc_id {kind}, quality int, stats array<bigint>", make).collect()
    got.sort(key=lambda r: (r[0], r[1], r[2]))
    return np.array([r[2] for r in got], np.int64).reshape(-1, len(BASE + MORE)), np.array([r[1] for r in got], np.int64)


def judge(docs: DataFrame, learned: Judge) -> DataFrame:
    """doc_id, the base statistics, base_failed, kept, anomaly of each row of docs."""
    shared = docs.sparkSession.sparkContext.broadcast(learned)
    kind = dict(docs.dtypes)["doc_id"]

    def make():
        model = shared.value

        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            stats = np.array([statistics(t) for t in as_bytes(part.column("text"))], np.int64).reshape(-1, len(BASE + MORE))
            failed, score = base_failed(stats), model.scores(stats)
            kept = ~failed & ~(score >= model.threshold)
            columns = [part.column("doc_id"), *(pa.array(stats[:, k]) for k in range(len(BASE))), pa.array(failed), pa.array(kept), pa.array(score)]
            return pa.RecordBatch.from_arrays(columns, ["doc_id", *BASE, "base_failed", "kept", "anomaly"])

        return one

    return map_texts(docs.select("doc_id", "text"), f"doc_id {kind}, " + ", ".join(f"{b} bigint" for b in BASE) + ", base_failed boolean, kept boolean, anomaly double", make)


def op4_isolation_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return judge(docs, Judge(*labelled_statistics(docs, labels)))
