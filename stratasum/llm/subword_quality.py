"""Quality classifier with supervised subword embeddings.

Words, pairs of neighbouring words, and n-grams of characters (code points) of a text are hashed to
buckets, each with a learned vector. All pairs of a word with itself share a bucket, so that repetition
is learned for words never seen. The mean of a text's vectors goes through a softmax over the two labels.
Vectors and output are trained by stochastic gradient descent in numpy.

Training takes at most `train_rows` labelled rows outside of the held-out fold, those with the
smallest hashes of their doc_id; that is what the driver holds. Scores cover all rows and whole texts.
Since output and mean are linear, a frozen model needs only one number for each bucket when scoring.

Defined results: null and empty texts have no features but the n-grams of their margins, and get the score of the bias; repeated rows
get equal scores; with no labelled rows every score is 0.5; other columns than doc_id and text are
not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, map_texts, remainder, table

BUCKET_BITS, DIMS, GRAMS = 18, 8, (3, 4)
TRAIN_ROWS, EPOCHS, RATE = 4000, 6, 0.8
THRESHOLD = 0.3
#: Texts are hashed in groups of about so many bytes.
GROUP_BYTES = 1 << 19
#: White space between words, as code points.
SPACES = np.array([9, 10, 11, 12, 13, 32], np.uint64)
_ODD = np.uint64(0x9E3779B97F4A7C15)
_BASE = 0x100000001B3
_INVERSE = pow(_BASE, -1, 1 << 64)
#: Kinds of features, so that a word and an n-gram of one number are apart; n-grams have their length.
WORD, PAIR = 101, 102


def _bucket(code: np.ndarray, kind: int, bits: int) -> np.ndarray:
    x = (code + np.uint64(kind)) * _ODD
    x ^= x >> np.uint64(29)
    return ((x * _ODD) >> np.uint64(64 - bits)).astype(np.int64)


def features(texts: list[bytes], bits: int = BUCKET_BITS) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all features of the texts, and the number of the text of each.

    A word's number is a polynomial in its characters. Prefix sums of all texts give it for every word
    at once: a difference of two sums, divided by the power at the word's start (odd, so it has an inverse).
    """
    plain = [" " + t.decode("utf-8", "replace") + " " for t in texts]
    chars = np.frombuffer("".join(plain).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    owner = np.repeat(np.arange(len(texts), dtype=np.int32), [len(t) for t in plain])
    buckets, owners = [], []
    code = chars
    for n in range(2, max(GRAMS) + 1):
        code = code[:-1] * np.uint64(_BASE) + chars[n - 1 :]
        if n in GRAMS:
            inside = owner[n - 1 :] == owner[: len(code)]
            buckets.append(_bucket(code[inside], n, bits))
            owners.append(owner[: len(code)][inside])
    blank = (chars <= 32) & np.isin(chars, SPACES)
    starts = np.flatnonzero(blank[:-1] & ~blank[1:]) + 1
    stops = np.flatnonzero(~blank[:-1] & blank[1:]) + 1
    if len(starts):
        power = np.cumprod(np.full(len(chars), np.uint64(_BASE)))
        upto = np.concatenate([np.zeros(1, np.uint64), np.cumsum((chars + np.uint64(1)) * power)])
        back = np.cumprod(np.full(len(chars), np.uint64(_INVERSE)))
        word = (upto[stops] - upto[starts]) * back[starts]
        of = owner[starts]
        buckets.append(_bucket(word, WORD, bits))
        owners.append(of)
        same = of[1:] == of[:-1]
        first, second = word[:-1][same], word[1:][same]
        buckets.append(_bucket(np.where(first == second, np.uint64(0), first * np.uint64(31) ^ second), PAIR, bits))
        owners.append(of[1:][same])
    return np.concatenate(buckets), np.concatenate(owners)


class SubwordModel:
    """bias and one number for each bucket: what its vector adds to the logit of label 1."""

    def __init__(self, texts: list[bytes], labels: np.ndarray, bits: int = BUCKET_BITS, dims: int = DIMS, epochs: int = EPOCHS, rate: float = RATE, seed: int = 5):
        self.bits, self.bias = bits, 0.0
        self.weight = np.zeros(1 << bits, np.float32)
        if not len(texts):
            return
        rng = np.random.default_rng(seed)
        rows = []
        for t in texts:
            bucket, _ = features([t], bits)
            own, count = np.unique(bucket, return_counts=True)
            rows.append((own, (count / max(1, len(bucket))).astype(np.float32)[:, None]))
        vectors = rng.uniform(-1 / dims, 1 / dims, (1 << bits, dims)).astype(np.float32)
        out, bias = np.zeros((2, dims), np.float32), np.zeros(2, np.float32)
        wanted = np.eye(2, dtype=np.float32)[labels]
        steps, done = epochs * len(rows), 0
        for _ in range(epochs):
            for i in rng.permutation(len(rows)):
                own, share = rows[i]
                lr = rate * (1 - done / steps)
                done += 1
                hidden = (vectors[own] * share).sum(0)
                logit = out @ hidden + bias
                p = np.exp(logit - logit.max())
                p /= p.sum()
                error = p - wanted[i]
                back = error @ out
                out -= lr * np.outer(error, hidden)
                bias -= 0.1 * lr * error
                vectors[own] -= (lr * LIFT) * share * back
        self.bias = float(bias[1] - bias[0])
        self.weight = vectors @ (out[1] - out[0])

    def scores(self, texts: list[bytes | None]) -> np.ndarray:
        """Chance of label 1 for each text."""
        plain = [t or b"" for t in texts]
        out, group, size = np.zeros(len(plain)), [], 0
        for i, t in enumerate(plain):
            group.append(i)
            size += len(t)
            if size >= GROUP_BYTES or i == len(plain) - 1:
                bucket, owner = features([plain[k] for k in group], self.bits)
                total = np.bincount(owner, self.weight[bucket], len(group))
                number = np.bincount(owner, minlength=len(group))
                out[group] = total / np.maximum(1, number)
                group, size = [], 0
        return 1 / (1 + np.exp(-(out + self.bias)))


#: Steps of the vectors are longer than those of the output by so much, since a mean spreads the error over all features.
LIFT = 40.0


def labelled_texts(docs: DataFrame, labels: DataFrame, train_rows: int = TRAIN_ROWS) -> tuple[list[bytes], np.ndarray]:
    """Texts and labels of at most train_rows rows of the learning fold; collected, as the bound allows."""
    chosen = labels.filter("quality in (0, 1) and doc_id is not null").filter(remainder("doc_id", 5) != 0).select("doc_id", "quality").orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(train_rows)
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").collect()  # bounded by train_rows
    rows.sort(key=lambda r: (r["doc_id"], r["text"] or "", r["quality"]))
    return [(r["text"] or "").encode() for r in rows], np.array([r["quality"] for r in rows], np.int64)


def score(docs: DataFrame, model: SubwordModel) -> DataFrame:
    """doc_id, score of each row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = dict(docs.dtypes)["doc_id"]

    def make():
        own = shared.value

        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(own.scores(as_bytes(part.column("text"))))], ["doc_id", "score"])

        return one

    return map_texts(docs.select("doc_id", "text"), f"doc_id {kind}, score double", make)


def op1_subword_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    found = score(docs, SubwordModel(*labelled_texts(docs, labels)))
    return found.select("doc_id", (remainder("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
