import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as CP
from stratasum.llm.common import cut
from test_operators import brute_lines

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"
ITEM = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon"
SHARED = "this sentence is the same in many of the documents here"


@pytest.fixture(scope="module")
def fixture(spark, tmp_path_factory):
    random.seed(9)
    words = ["".join(random.choices(["the", "ing", "ou", "er", "th", "an"], k=3)) for _ in range(400)]
    texts = [" ".join(random.choices(words, k=120)) for _ in range(30)]
    rows = [(k, t + ("\n" + SHARED if k < 8 else "")) for k, t in enumerate(texts)]
    edited = texts[3].split()
    edited[60] = "changed"
    other = [" ".join(random.choices(words, k=120)) for _ in range(4)]
    rows += [(40, texts[2]), (41, " ".join(edited)), (42, other[0] + " " + ITEM), (43, None), (44, ""), (45, "12 34"), (46, texts[5]), (46, texts[5]), (50, texts[6] * 40)]
    rows += [(51, other[1]), (51, other[1]), (51, other[2]), (52, other[3]), (52, "an " * 60 + ITEM), (None, "the " * 60 + ITEM)]
    full = [(i, t, "en", "s", len(t or "")) for i, t in rows]
    place = str(tmp_path_factory.mktemp("tables"))
    spark.createDataFrame(full, SCHEMA).withColumn("__extra", F.lit(1)).write.parquet(f"{place}/documents.parquet")
    spark.createDataFrame([(1, ITEM)], "item_id bigint, text string").write.parquet(f"{place}/benchmark.parquet")
    return place, rows


def test_stages(spark, fixture):
    place, rows = fixture
    docs = spark.read.parquet(f"{place}/documents.parquet")
    columns = docs.columns
    after = {}
    for name, stage in CP.STAGES:
        docs = cut(stage(spark, docs, place))
        after[name] = docs
        if name != "encoding":
            assert docs.columns == columns
    order = lambda i: (i is None, i)
    ids = {k: sorted((r["doc_id"] for r in d.select("doc_id").collect()), key=order) for k, d in after.items()}
    assert ids["language_id"] == sorted((i for i, _ in rows if i not in (43, 44, 45)), key=order)
    want = {(i, n - d) for i, n, d, _ in brute_lines([r for r in rows if r[0] not in (43, 44, 45)], 40, 5)}
    assert {(r["doc_id"], r["text"].count("\n") + 1) for r in after["line_dedup"].collect()} == want
    left = ids["near_dedup"]
    # rows alike in doc_id and text are one; those that only share their doc_id are not; 50 repeats the words of 6
    assert left == sorted([*range(30), 42, 51, 51, 52, 52, None], key=lambda i: (i is None, i))
    assert ids["decontamination"] == [*range(30), 51, 51, 52]
    assert ids["encoding"] == ids["decontamination"]
    got = CP.run(spark, place)
    assert sorted(map(str, got.select("doc_id", "ids_sha256").collect())) == sorted(map(str, after["encoding"].select("doc_id", "ids_sha256").collect()))


def test_empty_tables(spark, tmp_path):
    spark.createDataFrame([], "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    for name, stage in CP.STAGES:
        assert stage(spark, spark.createDataFrame([], SCHEMA), str(tmp_path)).count() == 0, name
    one = spark.createDataFrame([(1, "the only document there is", "en", "s", 26)], SCHEMA)
    assert CP.decontamination(spark, one, str(tmp_path)).count() == 1
    spark.createDataFrame([], SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    assert CP.run(spark, str(tmp_path)).count() == 0
