import base64
import gzip
import hashlib
import math
import random
import re

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from stratasum.llm import bpe_automaton as B
from stratasum.llm import chat_parts as C
from stratasum.llm import decontaminate as D
from stratasum.llm import isolation_rules as I
from stratasum.llm import line_dedup as LD
from stratasum.llm import ppm_language as P
from stratasum.llm import simhash_bktree as S
from stratasum.llm import splitter_shards as SS
from stratasum.llm import subword_quality as Q
from stratasum.llm import warc_index as W

SMALL = "/root/testdata/sf0.001"
DOCS = "doc_id bigint, text string"
LONG = "word " * 30_000
ODD = [(1, None), (2, ""), (3, " \n\t"), (4, "same line that is long enough to be counted as one\nx"), (4, "same line that is long enough to be counted as one\nx"), (None, "no id"), (5, LONG), (6, "日本語 ßü 😀 ** <|end|> \\<|"), (7, "123 456")]


def odd(spark):
    return spark.createDataFrame(ODD, DOCS).withColumn("score", F.lit("clash")).withColumn("fp", F.lit(1)).withColumn("h", F.lit(2)).withColumn("lang", F.lit("en"))


def documents(spark):
    return spark.read.parquet(f"{SMALL}/documents.parquet")


# ---- encoding


def test_tokens_equal_the_library():
    from tokenizers import Tokenizer

    library, own = Tokenizer.from_file(B.default_path()), B.Tokenizer(B.default_path())
    random.seed(1)
    parts = ["a", "b", "th", "e", " ", "  ", "\n", "'s", "é", "1", "23", "!", "<|endoftext|>", "՘", "中", "😀", "ing", "\x85", "\xa0", "\x1c", "Ж", "aaaa"]
    texts = ["".join(random.choices(parts, k=random.randint(0, 40))) for _ in range(3000)] + [t for _, t in ODD if t]
    for text in texts:
        want = library.encode(text, add_special_tokens=False).ids
        assert own.encode(text) == want
        assert own.decode(want) == library.decode(want, skip_special_tokens=False)


def test_documents_of_the_table_equal_the_library(spark):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(B.default_path())
    got = {r["doc_id"]: r for r in B.op9_bpe(spark, SMALL).collect()}
    for r in documents(spark).collect():
        ids = library.encode(r["text"] or "", add_special_tokens=False).ids
        back = library.decode(ids, skip_special_tokens=False)
        own = got[r["doc_id"]]
        assert (own["n_tokens"], own["ids_sha256"], own["decoded_sha256"]) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(back.encode()).hexdigest())


def test_automaton_on_small_merges():
    labels = {0: b"a", 1: b"b", 2: b"aa", 3: b"ab", 4: b"aab"}
    merges = [(0, 0, 2), (0, 1, 3), (2, 1, 4)]
    automaton = B.TokenAutomaton(labels, merges)

    def by_rank(word):
        own = [labels_inverse[bytes([c])] for c in word]
        while pairs := [(r, i) for i in range(len(own) - 1) for r, (x, y, _) in enumerate(merges) if own[i : i + 2] == [x, y]]:
            r, i = min(pairs)
            own[i : i + 2] = [merges[r][2]]
        return tuple(own)

    labels_inverse = {v: k for k, v in labels.items()}
    for n in range(1, 9):
        for k in range(2**n):
            word = bytes(b"ab"[k >> j & 1] for j in range(n))
            assert automaton.encode(word) == by_rank(word)


def test_encode_rows(spark):
    rows = B.encode(odd(spark)).collect()
    assert len(rows) == len(ODD)
    assert {r["n_tokens"] for r in rows if r["doc_id"] in (1, 2)} == {0}
    assert next(r for r in rows if r["doc_id"] == 5)["decoded_sha256"] == hashlib.sha256(LONG.encode()).hexdigest()


# ---- lines


def brute_lines(rows, min_chars, min_docs):
    held = {}
    keys = [[(line, k if (k := line.strip(" \t\n\v\f\r")).__len__() >= min_chars else None) for line in (t or "").split("\n")] for _, t in rows]
    for (doc_id, _), own in zip(rows, keys, strict=True):
        for k in {k.lower() for _, k in own if k is not None}:
            held.setdefault(k, []).append(LD.LEAST_ID if doc_id is None else doc_id)
    gone = {k: max(v) for k, v in held.items() if len(v) >= min_docs}
    out = []
    for (doc_id, _), own in zip(rows, keys, strict=True):
        kept = [line for line, k in own if k is None or k.lower() not in gone or gone[k.lower()] == doc_id]
        out.append((doc_id, len(own), len(own) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("rounds", [False, True])
def test_line_dedup_equals_brute_force(spark, rounds):
    rows = [(k, "\n".join(f"This line number {(k * j) % 7} is shared by some of the documents" for j in range(5)) + f"\nown {k}") for k in range(30)] + ODD[:7]
    df = spark.createDataFrame(rows, DOCS)
    options = {"shard_keys": 2, "broadcast_bytes": 60} if rounds else {}
    got = LD.dedup_lines(df, digest_only=True, **options).collect()
    assert sorted((tuple(r) for r in got), key=str) == brute_lines(rows, 40, 5)


def test_perfect_hash():
    rng = np.random.default_rng(0)
    high, low = (rng.integers(0, 1 << 64, 5000, dtype=np.uint64) for _ in range(2))
    packed = LD.PerfectHash(high, low, n=np.arange(5000)).pack()
    assert len(packed) < 5000 * (LD.KEY_BYTES - 4) and len(LD.PerfectHash(high[:0], low[:0], n=np.arange(0)).pack()) == 16
    again = LD.PerfectHash.unpack(packed, {"n": np.int64})
    at = again.probe(high, low)
    assert sorted(at) == list(range(5000)) and (again.values["n"][at] == np.arange(5000)).all()
    assert (again.probe(high, low + np.uint64(1)) == -1).all()


def test_counts_are_probed(spark):
    """Keys below the threshold are indexed, and stay by their count."""
    line = "a line that some documents share, and long enough to count"
    rows = [(k, f"{line} {j}") for j in (2, 4, 5) for k in range(10 * j, 10 * j + j)]
    df = spark.createDataFrame(rows, DOCS)
    assert sorted(r["n_docs"] for r in LD.counted_keys(df, 40).collect()) == [2, 4, 5]
    for least in (2, 3, 5, 6):
        got = LD.dedup_lines(df, min_docs=least, digest_only=True).collect()
        assert sorted((tuple(r) for r in got), key=str) == brute_lines(rows, 40, least)
    with pytest.raises(ValueError, match="whole number"):
        LD.dedup_lines(spark.createDataFrame([("a", "b")], "doc_id string, text string"))


def test_line_dedup_keeps_columns(spark):
    out = LD.dedup_lines(odd(spark))
    assert out.count() == len(ODD) and {"score", "fp", "h"} <= set(out.columns)
    assert LD.dedup_lines(spark.createDataFrame([], DOCS), digest_only=True).count() == 0


# ---- near-duplicates


def brute_components(fps, radius):
    parent = list(range(len(fps)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= radius:
                parent[find(i)] = find(j)
    return [find(i) for i in range(len(fps))]


@pytest.mark.parametrize("options", [{}, {"chunk": 2, "bin_bytes": 200, "round_bytes": 1000}])
def test_components_equal_brute_force(spark, options):
    rows = S.near_duplicates(documents(spark), **options).collect()
    ids, fps = [r["doc_id"] for r in rows], [int.from_bytes(r["fp"], "big") for r in rows]
    texts = {r["doc_id"]: (r["text"] or "").encode() for r in documents(spark).collect()}
    assert fps == [int.from_bytes(S.fingerprint(S.text_hashes(texts[i], 3)), "big") for i in ids]
    roots = brute_components(fps, 3)
    least = {}
    for i, r in zip(ids, roots, strict=True):
        least[r] = min(i, least.get(r, i))
    assert [r["component_id"] for r in rows] == [least[r] for r in roots]


def test_bk_trees_find_all_within_the_radius():
    rng = np.random.default_rng(2)
    base = rng.integers(0, 1 << 64, 40, dtype=np.uint64)
    points = np.unique(np.concatenate([base, *(base ^ (np.uint64(1) << rng.integers(0, 64, 40, dtype=np.uint64)) for _ in range(6))]))[:, None]
    shard = np.sort(rng.integers(-2, 2, len(points)))
    trees = S.TreeSet.unpack([S.TreeSet(points[a:b], shard[a:b]).pack() for a, b in ((0, int((shard < 0).sum())), (int((shard < 0).sum()), len(points)))])
    for reach in (3, rng.integers(0, 40, len(points))):
        got = {(int(a), int(b)) for who, node in trees.search(points, trees.root_of(shard), reach) for a, b in zip(who, node, strict=True)}
        want = {(i, j) for i in range(len(points)) for j in range(len(points)) if shard[i] == shard[j] and (int(points[i, 0]) ^ int(points[j, 0])).bit_count() <= np.broadcast_to(reach, len(points))[i]}
        assert got == want


def test_parts_leave_no_pair_apart():
    rng = np.random.default_rng(3)
    a = rng.integers(0, 1 << 64, 2000, dtype=np.uint64)
    b = a.copy()
    for _ in range(3):
        b ^= np.uint64(1) << rng.integers(0, 64, 2000, dtype=np.uint64)
    assert (S.part_shards(a) == S.part_shards(b)).any(1).all()


def test_fingerprint_uses_sparks_hash(spark):
    text = "One two THREE four two"
    shingles = ["one two three", "two three four", "three four two"]
    hashes = [r[0] & (1 << 64) - 1 for r in spark.createDataFrame([(s,) for s in shingles], "s string").select(F.xxhash64("s")).collect()]
    want = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > 3)
    assert int.from_bytes(S.fingerprint(S.text_hashes(text.encode(), 3)), "big") == want


def test_near_duplicates_of_odd_rows(spark):
    rows = S.near_duplicates(odd(spark)).collect()
    assert len(rows) == len(ODD)
    assert {r["component_id"] for r in rows if r["doc_id"] in (1, 2, 3)} == {1}
    assert S.near_duplicates(spark.createDataFrame([], DOCS)).count() == 0


def test_similar_documents(spark):
    random.seed(3)
    words = [f"w{k}" for k in range(5000)]
    base = [random.choices(words, k=300) for _ in range(40)]
    rows = []
    for k, b in enumerate(base):
        rows.append((2 * k, " ".join(b)))
        edited = list(b)
        for _ in range(5):
            edited[random.randrange(300)] = "new"
        rows.append((2 * k + 1, " ".join(edited)))
    got = {r["doc_id"]: r["component_id"] for r in S.similar_documents(spark.createDataFrame(rows, DOCS)).collect()}
    assert sum(got[2 * k + 1] == 2 * k for k in range(40)) >= 38
    assert all(got[2 * k] == 2 * k for k in range(40))


def brute_similar(rows, words=5, similarity=0.8):
    """doc_id -> smallest doc_id of its component, by the sets themselves."""
    sets = [frozenset(S.text_hashes((t or "").encode(), words).tolist()) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if len(a & b) >= similarity * len(a | b) - 1e-9:
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    least = {}
    for k, (d, _) in enumerate(rows):
        least[find(k)] = min(d, least.get(find(k), d))
    return {d: least[find(k)] for k, (d, _) in enumerate(rows)}


@pytest.mark.parametrize("options", [{}, {"chunk": 5, "bin_bytes": 2000, "round_bytes": 5000}])
def test_similar_documents_of_the_table(spark, options):
    rows = [(r["doc_id"], r["text"]) for r in documents(spark).collect()]
    got = {r["doc_id"]: r["component_id"] for r in S.similar_documents(documents(spark), **options).collect()}
    assert got == brute_similar(rows) and any(d != c for d, c in got.items())


def test_a_large_family_of_edits(spark):
    """One text and many edits of it, of any similarity to each other: what is compared in parts is as whole as in one."""
    rng = random.Random(12)
    base = [f"w{rng.randrange(10**6)}" for _ in range(120)]
    rows = []
    for k in range(150):
        share = rng.choice([0.005, 0.01, 0.03, 0.08])
        rows.append((k, " ".join(f"x{rng.randrange(10**6)}" if rng.random() < share else w for w in base)))
    df = spark.createDataFrame(rows, DOCS)
    want = brute_similar(rows)
    for parts in (1000, 20):
        own = S.sketches(df, 5, 0.8, 4, 14, 4, 4.0).collect()
        nodes = spark.createDataFrame([(bytes(r["key"]), bytes(r["text_key"])) for r in own], "key binary, text_key binary").distinct()
        groups = nodes.select(F.col("key").alias("node"), F.lit("one").alias("root"))
        found = S.components(S.verified(df, nodes, groups, 5, 0.8, group_texts=parts))
        of = {bytes(r["node"]): bytes(r["root"]) for r in found.collect()}
        family = {}
        for r in own:
            family.setdefault(of.get(bytes(r["key"]), bytes(r["key"])), []).append(r["doc_id"])
        assert {d: min(ds) for ds in family.values() for d in ds} == want


def test_which_row_stays(spark):
    text = " ".join(f"w{k}" for k in range(30))
    rows = [(5, text), (5, text), (5, text + " more"), (7, text), (None, text), (None, "alone"), (8, ""), (9, None)]
    got = S.similar_documents(spark.createDataFrame(rows, DOCS)).collect()
    assert len(got) == len(rows)
    assert sum(r["stays"] for r in got if r["doc_id"] == 5 or r["doc_id"] == 7) in (1, 2)  # the smaller of two texts, once or twice
    assert {r["component_id"] for r in got if r["n"] > 5} == {5}
    assert [r["stays"] for r in got if r["doc_id"] is None and r["n"] == 1] == [True]
    assert [r["stays"] for r in got if r["doc_id"] is None and r["n"] > 1] == [False]


def test_similar_documents_with_a_repeated_passage(spark):
    rng = random.Random(5)
    rows = []
    for k in range(20):
        base, passage = ([f"w{rng.randrange(10**6)}" for _ in range(n)] for n in (304, 19))
        rows += [(2 * k, " ".join(base + passage)), (2 * k + 1, " ".join(base + passage * 20))]
    got = {r["doc_id"]: r["component_id"] for r in S.similar_documents(spark.createDataFrame(rows, DOCS)).collect()}
    assert all(got[d] == d // 2 * 2 for d, _ in rows)


def test_similar_documents_near_the_threshold(spark):
    rng = random.Random(6)
    rows, want = [], {}
    for k in range(300):
        n = rng.choice([8, 9, 14, 60, 120, 300])
        base = [f"w{rng.randrange(10**6)}" for _ in range(n)]
        # an end that only one text has: similarity is common / whole, just at the threshold or just below
        whole = n - 4 if k % 2 == 0 else n - 3
        common = math.ceil(0.8 * whole) if k % 3 else math.ceil(0.8 * whole) - 1
        rows += [(2 * k, " ".join(base[: whole + 4])), (2 * k + 1, " ".join(base[: common + 4]))]
        a, b = (set(S.text_hashes(t.encode(), 5).tolist()) for _, t in rows[-2:])
        want[2 * k + 1] = 2 * k if len(a & b) >= 0.8 * len(a | b) else 2 * k + 1
    got = {r["doc_id"]: r["component_id"] for r in S.similar_documents(spark.createDataFrame(rows, DOCS)).collect()}
    assert not [d for d in want if want[d] == d and got[d] != d]  # none below the threshold links
    assert sum(got[d] != want[d] for d in want) <= 1  # one in a thousand at the threshold may be missed
    assert all(got[2 * k] == 2 * k for k in range(300))


# ---- language, quality, rules


def test_ppm_costs_are_a_code():
    texts = {"a": [b"the cat sat on the mat " * 20], "b": ["le chat était là ".encode() * 20]}
    model = P.LanguageModel(texts)
    alike = np.ones(model.kinds)
    alike[-1] = 256 - (model.kinds - 1)
    shares = (2.0 ** -model.costs.reshape(model.nodes, model.kinds, 2).astype(float) * alike[None, :, None]).sum(1)
    assert np.all(shares <= 1 + 1e-4) and np.all(shares > 0.99)
    counts = P._context_counts(texts["a"], 4, 3)

    def cost(context, byte):  # the definition, for one byte
        while context not in counts:
            context = context[:-1]
        spent, excluded = 0.0, set()
        while True:
            seen = {s: n for s, n in counts[context].items() if s not in excluded}
            if seen:
                whole = sum(seen.values()) + len(seen)
                if byte in seen:
                    return spent - np.log2(seen[byte] / whole)
                spent -= np.log2(len(seen) / whole)
                excluded |= set(seen)
            if not context:
                return spent + np.log2(256 - len(excluded))
            context = context[:-1]

    text = b"the mat sat\nzq"
    padded = b"\n" * 4 + text
    want = sum(cost(tuple(padded[i + 4 - k] for k in range(1, 5)), padded[i + 4]) for i in range(len(text)))
    assert abs(model.code_lengths([text])[0][0] - want) < 1e-2
    long = texts["a"][0] * 2000
    assert abs(model.code_lengths([long])[0][0] / model.code_lengths([long[: len(long) // 2]])[0][0] - 2) < 1e-3


def test_language_of_odd_rows(spark):
    got = {r["doc_id"]: r["__lang"] for r in P.identify(odd(spark), P.train(documents(spark))).collect()}
    assert got[1] == got[2] == got[3] == got[7] == "und" and got[5] != "und"
    assert {r["__lang"] for r in P.identify(odd(spark), P.LanguageModel({})).collect()} == {"und"}


def test_held_out_language(spark):
    rows = P.op2_ppm_language(spark, SMALL).join(documents(spark).select("doc_id", "lang"), "doc_id").filter("held_out").collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in rows]) > 0.95


def test_held_out_quality(spark):
    sf = "/root/testdata/sf0.01"
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    rows = Q.op1_subword_quality(spark, sf).join(labels, "doc_id").filter("held_out").collect()
    assert np.mean([r["predicted"] == r["quality"] for r in rows]) > 0.95
    assert Q.score(odd(spark), Q.SubwordModel([], np.array([], int))).filter("score = 0.5").count() == len(ODD)


def brute_features(text, bits):
    """Buckets of a text's features by their definition, in Python's integers."""
    mask, odd = (1 << 64) - 1, 0x9E3779B97F4A7C15

    def bucket(code, kind):
        x = (code + kind) * odd & mask
        x ^= x >> 29
        return (x * odd & mask) >> 64 - bits

    chars = [ord(c) for c in " " + text + " "]
    out = []
    for n in Q.GRAMS:
        for i in range(len(chars) - n + 1):
            code = 0
            for c in chars[i : i + n]:
                code = code * Q._BASE + c
            out.append(bucket(code & mask, n))
    words = [w for w in re.split("[\x20\x09-\x0d]+", text) if w]
    code = [sum((ord(c) + 1) * Q._BASE**k for k, c in enumerate(w)) & mask for w in words]
    out += [bucket(c, Q.WORD) for c in code]
    out += [bucket(0 if a == b else (a * 31 & mask) ^ b, Q.PAIR) for a, b in zip(code, code[1:], strict=False)]
    return sorted(out)


def test_quality_features_by_definition():
    texts = ["one two two\tTHREE\n", "", "é日本 😀 a", " x\x0b\x1cy ", "a" * 300]
    for group in (texts, texts[::-1], texts[2:3]):
        bucket, owner = Q.features([t.encode() for t in group], 18)
        for k, t in enumerate(group):
            assert sorted(bucket[owner == k].tolist()) == brute_features(t, 18)


def test_quality_learns_what_a_gradient_step_says():
    """One epoch over one text, against the step worked out in plain loops."""
    text, bits, dims, rate = "good words here", 12, 3, 0.5
    model = Q.SubwordModel([text.encode()], np.array([1]), bits, dims, epochs=1, rate=rate, seed=5)
    rng = np.random.default_rng(5)
    rng.permutation(1)
    rng = np.random.default_rng(5)
    vectors = rng.uniform(-1 / dims, 1 / dims, (1 << bits, dims)).astype(np.float32)
    own = brute_features(text, bits)
    hidden = [sum(vectors[b][d] for b in own) / len(own) for d in range(dims)]
    p = [0.5, 0.5]  # the output starts at zero
    out = [[-rate * (p[label] - (label == 1)) * h for h in hidden] for label in (0, 1)]
    bias = [-0.1 * rate * (p[label] - (label == 1)) for label in (0, 1)]
    assert abs(model.bias - (bias[1] - bias[0])) < 1e-6
    want = vectors @ (np.array(out[1]) - np.array(out[0]))
    assert np.abs(model.weight - want).max() < 1e-5
    score = model.scores([text.encode(), None])
    mean = sum(want[b] for b in own) / len(own)
    assert abs(score[0] - 1 / (1 + math.exp(-(mean + model.bias)))) < 1e-5


def brute_statistics(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    lines = [line for line in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", line)]
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    inside = {i + j for i, w in enumerate(windows) if windows.count(w) > 1 for j in range(3)}
    return len(words), sum(map(len, words)), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(inside)


def test_rule_statistics():
    texts = [t for _, t in ODD if t != LONG] + ["a b c a b c d", "x\nx\n \n \nx", "a a a a", "# b | c < d\vé\x0bé"]
    for text in texts:
        assert I.statistics(None if text is None else text.encode())[:5] == brute_statistics(text)


def test_base_statistics_of_the_table(spark):
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{SMALL}/documents.parquet'")
    want = con.sql(r"""
        WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
        w AS (SELECT doc_id, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS ws, list_filter(string_split(text, chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS ls FROM t),
        g AS (SELECT doc_id, list_transform(range(1, len(ws) - 1), lambda i: ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2]) AS gs FROM w),
        f AS (SELECT doc_id, unnest(gs) AS gram, generate_subscripts(gs, 1) AS i FROM g),
        r AS (SELECT doc_id, unnest([i, i + 1, i + 2]) AS place FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, gram) AS n FROM f) WHERE n > 1),
        c AS (SELECT doc_id, count(DISTINCT place) AS n FROM r GROUP BY doc_id)
        SELECT w.doc_id, len(ws), CAST(coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS BIGINT), length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')),
               len(ls) - len(list_distinct(ls)), coalesce(c.n, 0) FROM w LEFT JOIN c USING (doc_id)""").fetchall()
    labels = spark.read.parquet(f"{SMALL}/labels.parquet")
    got = I.judge(documents(spark), I.Judge(*I.labelled_statistics(documents(spark), labels))).select("doc_id", *I.BASE).collect()
    assert sorted(map(tuple, got)) == sorted(want)


def test_paths_of_a_small_forest():
    """Depths by a walk of each tree, node by node."""
    rng = np.random.default_rng(3)
    rows = rng.normal(size=(60, 3))
    forest = I.IsolationForest(rows, trees=7, tree_rows=20, seed=1)
    seen = np.vstack([rows[:10], [[9.0, 9, 9], [-50, 0, 0]]])
    got = forest.scores(seen)
    for row, score in zip(seen, got, strict=True):
        depths = []
        for feature, cut, left, path in forest.trees:
            at, depth = 0, 0
            while feature[at] >= 0:
                at, depth = left[at] + int(row[feature[at]] > cut[at]), depth + 1
            assert path[at] >= depth
            depths.append(path[at])
        assert abs(score - 2 ** (-np.mean(depths) / I._mean_path(20))) < 1e-12
    assert got[-1] > np.median(got[:10]) and got[-2] > np.median(got[:10])


def test_rules_take_any_ids(spark):
    docs = spark.createDataFrame([("a", "word " * 60), ("b", None), (None, "x")], "doc_id string, text string")
    labels = spark.createDataFrame([("a", 1), ("b", 0)], "doc_id string, quality int")
    got = I.judge(docs, I.Judge(*I.labelled_statistics(docs, labels))).collect()
    assert {r["doc_id"] for r in got} == {"a", "b", None}


def test_forest_keeps_good_rows(spark):
    sf = "/root/testdata/sf0.01"
    rows = I.op4_isolation_rules(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").filter("not base_failed").collect()
    good, bad = [r["kept"] for r in rows if r["quality"] == 1], [r["kept"] for r in rows if r["quality"] == 0]
    assert np.mean(good) > 0.97 and np.mean(bad) < 0.25
    assert I.judge(odd(spark), I.Judge(np.zeros((0, 10), int), np.zeros(0, int))).count() == len(ODD)


# ---- chat, archives, shards


def test_chat_round_trip(spark):
    parts = [("text", "a<|end|>\\<|b", None, None), ("image", None, "s3.png", 4), ("text", None, None, None), ("audio", None, "b.wav", None)]
    rows = [(1, 0, "user", parts), (1, 1, "assistant", [("text", "ok <\\| \\\\", None, None)]), (1, None, None, None), (2, 5, "assistant", [("image", None, "x", 1)])]
    turns = spark.createDataFrame(rows, f"conv_id bigint, turn bigint, role string, parts {C.PARTS}").withColumn("formatted", F.lit("clash"))
    made = C.format_chat(turns)
    back = {r["conv_id"]: r for r in C.read_chat(made).collect()}
    assert [(t["role"], t["text"]) for t in back[1]["read"]] == [("", ""), ("user", "a<|end|>\\<|b<|image:0|><|audio:1|>"), ("assistant", "ok <\\| \\\\")]
    assert back[1]["loss_text"] == "ok <\\| \\\\"
    assert [(a["number"], a["type"], a["ref"], a["tokens"]) for a in back[1]["attachments"]] == [(0, "image", "s3.png", 2 + 4 * 576), (1, "audio", "b.wav", 27)]
    assert back[1]["expanded_tokens"] == 2 + 4 * 576 + 27
    spans = {(r["conv_id"], back[r["conv_id"]]["formatted"][r["start"] : r["start"] + r["length"]]) for r in C.loss_spans(made).collect()}
    assert (1, C.escape and "ok <\\\\| \\\\\\\\") in spans
    assert C.format_chat(turns.limit(0)).count() == 0


def test_tied_turns_are_ordered_by_text(spark, tmp_path):
    rows = [(1, 0, "user", "ok thanks"), (1, 0, "user", "ok"), (1, 0, "user", None), (1, 0, "user", 'ok "so"'), (1, 0, "user", "ok"), (1, None, None, "é\\<|"), (None, 2, "assistant", "a"), (None, 2, "assistant", "A")]
    spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    con = duckdb.connect()
    con.execute(f"create view conversations as select * from '{tmp_path}/conversations.parquet/*.parquet'")
    want = con.sql(C.ORACLE_SQL)
    got = C.op3_chat_parts(spark, str(tmp_path)).select(*want.columns)
    assert sorted(map(tuple, got.collect()), key=str) == sorted(want.fetchall(), key=str)


def test_chat_equals_sql(spark):
    con = duckdb.connect()
    con.execute(f"create view conversations as select * from '{SMALL}/conversations.parquet'")
    got = C.op3_chat_parts(spark, SMALL)
    want = con.sql(C.ORACLE_SQL)
    key = lambda r: str(r)
    assert sorted((tuple(r) for r in got.select(*want.columns).collect()), key=key) == sorted(want.fetchall(), key=key)


PAGES = "page_id bigint, url string, html string"


def brute_pages(rows, least_bytes=0):
    """page_id, payload_bytes, payload_digest, record_type, refers_to by the definition."""
    first = {}
    for i, _, html in rows:
        key = (html or "").encode()
        first.setdefault(key, set()).add(i)
    out = []
    for i, _, html in rows:
        payload = (html or "").encode()
        named = [x for x in first[payload] if x is not None]
        least = min(named) if named else None
        answer = len(payload) < least_bytes or i == least
        out.append((i, len(payload), base64.b32encode(hashlib.sha1(payload).digest()).decode(), "response" if answer else "revisit", None if answer else least))
    return sorted(out, key=str)


def test_archives_and_index(spark, tmp_path):
    rows = [(1, "http://www.b.example.org/x?q=1", "<p>a\r\n\r\nb"), (2, "http://a.example.org/", "<p>a\r\n\r\nb"), (3, None, None), (4, "http://a.example.org/\r\nX: y", ""), (5, "https://a.example.org/é", "é" * 1000)]
    rows += [(5, "https://a.example.org/é", "é" * 1000), (None, "http://c.example.org", "é" * 1000), (None, "http://[", "own"), (None, None, "own"), (6, "http://a.example.org/", "x" * 3_000_000)]
    rows += [(k, f"http://h{k % 7}.example.org/{k}", f"<p>{k % 40}</p>") for k in range(10, 300)]
    df = spark.createDataFrame(rows, PAGES).withColumn("sha", F.lit("clash")).withColumn("first", F.lit(1)).repartition(3)
    place = f"file://{tmp_path}"
    W.write_archives(df, f"{place}/warc", archive_bytes=3000)
    files = [f for f in (tmp_path / "warc").iterdir() if f.name.startswith("part-")]
    assert len(files) > 5
    plain = b"".join(gzip.decompress(f.read_bytes()) for f in files)  # any reader of gzip takes them
    assert plain.count(b"WARC/1.1\r\n") == len(rows)
    W.write_index(W.captures(spark, f"{place}/warc"), f"{place}/index", block_lines=4, file_bytes=200)
    found = W.lookup_all(spark, f"{place}/index", df)
    got = found.collect()
    assert sorted(((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in got), key=str) == brute_pages(rows)
    assert spark.read.parquet(f"{place}/index/files").count() > 5
    assert [c["page_id"] for c in W.lookup(spark, f"{place}/index", "https://a.example.org/é")] == [5, 5]
    assert sorted(c["page_id"] for c in W.lookup(spark, f"{place}/index", "http://a.example.org/")) == [2, 6]
    assert W.lookup(spark, f"{place}/index", "http://nowhere.example/") == []
    texts = {i: html or "" for i, _, html in rows if i is not None}
    for r in got[::20]:
        head, block = W.read_record(spark, r["file"], r["offset"], r["length"])
        assert head[b"warc-type"].decode() == r["record_type"]
        if r["record_type"] == "response" and r["page_id"] is not None:
            assert block.partition(b"\r\n\r\n")[2].decode() == texts[r["page_id"]]


def test_small_payloads_are_all_responses(spark, tmp_path):
    rows = [(1, "u", "same"), (2, "u", "same"), (3, "u", "longer text"), (4, "u", "longer text")]
    W.write_archives(spark.createDataFrame(rows, PAGES), f"file://{tmp_path}/warc", least_bytes=5)
    got = [(r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in W.captures(spark, f"file://{tmp_path}/warc").collect()]
    assert sorted(got, key=str) == brute_pages(rows, 5)


def test_index_reads_few_blocks(tmp_path):
    lines = [(f"k{n:04}", n, *[None] * 8) for n in range(0, 2000, 2)]
    blocks = [lines[k : k + 50] for k in range(0, 1000, 50)]
    directory, data = [], b""
    for b in blocks:
        packed = W._pack_lines(b)
        directory.append((*W._key(*b[0][:2]), *W._key(*b[-1][:2]), len(data), len(packed)))
        data += packed
    (tmp_path / "one").write_bytes(data + W._pack_lines(directory) + b"%0*d" % (W.PLACE_DIGITS, len(data)) + b"\n")
    for key in (0, 98, 99, 100, 1998, 1999, 2500):
        index = W.IndexFiles([(f"{tmp_path}/one", ("k0000", 0), ("k1998", 1998))])
        got = [line[1] for line in index.find((f"k{key:04}", W.LEAST_ID), (f"k{key:04}", -W.LEAST_ID))]
        assert got == ([key] if key % 2 == 0 and key < 2000 else []) and index.blocks_read <= 1


def test_every_page_of_the_table(spark):
    rows = spark.read.parquet(f"{SMALL}/pages.parquet").select("page_id", "url", "html").collect()
    got = W.op5_warc_index(spark, SMALL).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to").collect()
    assert sorted((tuple(r) for r in got), key=str) == brute_pages(rows)


def test_no_pages(spark, tmp_path):
    none = spark.createDataFrame([], PAGES)
    W.write_archives(none, f"file://{tmp_path}/warc")
    W.write_index(W.captures(spark, f"file://{tmp_path}/warc"), f"file://{tmp_path}/index")
    assert W.lookup_all(spark, f"file://{tmp_path}/index", none).count() == 0
    assert W.lookup(spark, f"file://{tmp_path}/index", "http://a.example.org/") == []


def test_shards(spark):
    for law in ("bytes", "rows"):
        rows = SS.shard(documents(spark), 7, law, sample_keys=50, ranges=9).collect()
        by = {}
        for r in rows:
            by.setdefault(r["shard"], []).append(r)
        assert all(sorted(x["slot"] for x in own) == list(range(len(own))) for own in by.values())
        sizes = [sum(x["size"] for x in own) for own in by.values()]
        if law == "rows":
            assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
        else:
            assert max(sizes) - min(sizes) <= 2 * max(r["size"] for r in rows)
    assert SS.shard(odd(spark)).count() == len(ODD)
    same = spark.createDataFrame([(k, "same text") for k in range(400)], DOCS)
    assert {r["count"] for r in SS.shard(same, 4).groupBy("shard").count().collect()} == {100}
    assert SS.shard(spark.createDataFrame([], DOCS)).count() == 0
    names = spark.createDataFrame([("a", "x"), ("b", "x"), (None, None)], "doc_id string, text string")
    assert SS.shard(names, 2).count() == 3
    assert tuple(SS.torn_groups(SS.shard(same, 4)).first()) == (1, 1)


def test_ranges_do_not_change_the_shards(spark):
    """Boundaries inside one text, and ranges divided until none is overfull."""
    rows = [(k, "same text" if k % 2 else f"text {k} " * (k % 7)) for k in range(600)]
    df = spark.createDataFrame(rows, DOCS)
    made = [sorted(map(tuple, SS.shard(df, 5, sample_keys=n, ranges=r).select("doc_id", "shard", "slot").collect())) for n, r in ((20, 2), (40, 30), (600, 100))]
    assert made[0] == made[1] == made[2]


# ---- decontamination


def brute_align(item, passage):
    h = [[0] * (len(passage) + 1) for _ in range(len(item) + 1)]
    for i, a in enumerate(item, 1):
        for j, b in enumerate(passage, 1):
            h[i][j] = max(0, h[i - 1][j - 1] + (D.MATCH if a == b else D.REPLACED), h[i - 1][j] + D.GAP, h[i][j - 1] + D.GAP)
    return max(map(max, h)) / (D.MATCH * len(item))


def test_alignment_equals_the_full_table():
    rng = np.random.default_rng(4)
    for _ in range(100):
        a, b = rng.integers(0, 5, rng.integers(1, 12)), rng.integers(0, 5, rng.integers(0, 30))
        assert abs(D.align(a, b)[0] - brute_align(a.tolist(), b.tolist())) < 1e-12


def test_contaminated_equals_brute_force(spark):
    benchmark = spark.read.parquet(f"{SMALL}/benchmark.parquet")
    items, docs = benchmark.collect(), documents(spark).collect()
    got = {(r["doc_id"], r["item_id"]) for r in D.contaminated(documents(spark), benchmark).collect()}
    vocabulary = {}
    code = lambda t: np.array([vocabulary.setdefault(w, len(vocabulary)) for w in D.words_of(t)])
    coded = [(d["doc_id"], code(d["text"] or "")) for d in docs]
    want = {(i, x["item_id"]) for i, words in coded for x in items if len(words) and D.align(code(x["text"]), words)[0] >= D.SIMILARITY}
    assert got == want and want
    left = {r["doc_id"] for r in D.clean(documents(spark), benchmark, block_bytes=2000).collect()}
    assert left == {d["doc_id"] for d in docs} - {i for i, _ in want}


def test_every_third_word_replaced(spark):
    item = " ".join(f"w{k}" for k in range(20))
    copy = " ".join("other" if k % 3 == 2 else f"w{k}" for k in range(20))
    benchmark = spark.createDataFrame([("i", item)], "item_id string, text string")
    got = D.contaminated(spark.createDataFrame([("d", f"before {copy} after")], "doc_id string, text string"), benchmark).collect()
    assert [(r["doc_id"], r["item_id"]) for r in got] == [("d", "i")] and got[0]["score"] >= 0.5


def test_rows_are_cleaned_by_their_own_text(spark):
    item = " ".join(f"w{k}" for k in range(20))
    benchmark = spark.createDataFrame([(1, item)], "item_id bigint, text string")
    rows = [(None, item), (None, "clean"), (5, "clean too"), (5, item), (6, None), (7, "")]
    docs = spark.createDataFrame(rows, DOCS).withColumn("item_id", F.lit("clash"))
    got = D.clean(docs, benchmark)
    assert got.columns == docs.columns
    assert sorted(((r["doc_id"], r["text"]) for r in got.collect()), key=str) == sorted([(None, "clean"), (5, "clean too"), (6, None), (7, "")], key=str)
    assert D.clean(docs, benchmark.limit(0)).count() == 6 and D.clean(docs.limit(0), benchmark).count() == 0


def test_edited_and_hot_copies(spark):
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon"
    edited = item.replace("delta", "changed").replace("kappa ", "").replace("pi", "pi added")
    rows = [(k, f"before {edited} after") for k in range(50)] + [(100, "alpha beta gamma but nothing else here"), *ODD]
    benchmark = spark.createDataFrame([(9, item), (10, None), (11, "")], "item_id bigint, text string")
    got = D.contaminated(spark.createDataFrame(rows, DOCS), benchmark).collect()
    assert sorted(r["doc_id"] for r in got) == list(range(50)) and {r["item_id"] for r in got} == {9}
    assert D.contaminated(spark.createDataFrame(rows, DOCS), benchmark, block_bytes=1).count() == 50
    assert D.contaminated(spark.createDataFrame(rows, DOCS), benchmark.limit(0)).count() == 0


def test_single_edited_copies_equal_full_alignment(spark):
    rng = random.Random(8)
    words = [f"w{k}" for k in range(3000)]
    items, rows = [], []
    for k in range(60):
        item = rng.choices(words, k=39)
        share = (0.15, 0.2, 0.25, 0.3)[k % 4]
        copy = [f"new{k}x{j}" if (j % 3 == 2 if k < 4 else j % 6 == 3 if k < 8 else rng.random() < share) else w for j, w in enumerate(item)]
        items.append((k, " ".join(item)))
        rows.append((k, " ".join(rng.choices(words, k=60) + copy + rng.choices(words, k=60))))
    benchmark = spark.createDataFrame(items, "item_id bigint, text string")

    def want(rows):
        code = {}
        number = lambda t: np.array([code.setdefault(w, len(code)) for w in t.split()])
        return {(d, i): s for d, text in rows for i, item in items if (s := D.align(number(item), number(text))[0]) >= D.SIMILARITY}

    got = lambda rows: {(r["doc_id"], r["item_id"]): r["score"] for r in D.contaminated(spark.createDataFrame(rows, DOCS), benchmark).collect()}
    assert got(rows) == want(rows) and {(k, k) for k in range(8)} <= set(want(rows))
    beside = [*rows, *((100 + k, text) for k, text in items)]  # whole copies, which hold all that the edits replaced
    assert got(beside) == want(beside)


def test_a_worker_keeps_one_object():
    from stratasum.llm.common import kept_in_worker

    first = kept_in_worker(("a",), list)
    assert kept_in_worker(("a",), list) is first
    assert kept_in_worker(("b",), dict) == {}
    assert kept_in_worker(("a",), list) is not first
    assert kept_in_worker(None) is None


def test_decontaminate_cuts_words_as_its_pattern_does():
    texts = ["", "A_b-c9\n\tD", "Ça\u00a0l\u2019été\u2026 \u0130x\u0307y", "\u4f60\u597d\u3002ab\u00b2\u00bd\u2167", "".join(f"x{chr(c)}Y" for c in range(0x2000, 0x2100))]
    texts += ["".join(f"a{chr(c)}B" for c in range(k, k + 8)) for k in range(0, 0x3100, 8)]
    for text in texts:
        assert D.words_of(text) == D.WORD.findall(text.lower())


def test_decontaminate_looks_for_passages_only_where_some_are(monkeypatch):
    """Items whose words are all in a text, but far apart, are left after a test of all of them at once."""
    rng = np.random.default_rng(4)
    vocabulary = [f"w{k}" for k in range(60)]
    items = [(k, " ".join(rng.choice(vocabulary, 12))) for k in range(30)]
    index = D.ItemIndex(items)
    index.keep_rare({w: 1 for w in index.vocabulary.values()})
    asked = []
    passages = D.ItemIndex._passages
    monkeypatch.setattr(D.ItemIndex, "_passages", lambda *a: asked.append(found := passages(*a)) or found)
    monkeypatch.setattr(D, "CELLS", 200)  # several rounds a text
    apart = " ".join(f"{w} {'x ' * 40}" for w in vocabulary)
    assert index.matches(apart, 0.5) == [] and asked == []
    texts = [" ".join([*rng.choice([*vocabulary, "x", "y"], 80), *items[k][1].split()[:9]]) for k in range(20)]
    got = [index.matches(t, 0.5) for t in texts]
    assert all(asked) and sum(map(len, got))
    monkeypatch.setattr(D.ItemIndex, "_reaching", lambda self, at, known, present, items, n_seeds, similarity: zip(items.tolist(), n_seeds.tolist(), strict=True))
    assert got == [index.matches(t, 0.5) for t in texts]
