"""A corpus pipeline of five operators: language ID, line dedup, SimHash near-dedup, decontamination, encoding.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept. All but the last
return the columns of documents. `run` writes each stage's rows in the shared folder and reads them
again for the next.

Defined results: empty and null texts have no language and go in the first stage; later stages keep
rows whose text has become empty; rows that repeat doc_id and text are one document to the near-duplicate
stage, and one of them stays; columns that documents has besides its own stay as they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stratasum.llm import bpe_automaton, decontaminate, line_dedup, ppm_language, simhash_bktree
from stratasum.llm.common import cut, table

#: Bits a byte of text takes without a model. A text that no language codes in fewer is in none of them.
PLAIN_BITS = 8.0
#: A column that the near-duplicate stage adds for itself.
TEXT_KEY = "__text_md5"
#: Words that a worker of the last stage keeps, beside what earlier stages left in it.
WORDS_KEPT = 60_000


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps texts that have a language and sets lang to it."""
    found = ppm_language.identify(docs, ppm_language.train(docs))
    kept = found.filter((F.col("__lang") != ppm_language.UND) & (F.col("__bits") < PLAIN_BITS))
    return kept.withColumn("lang", F.col("__lang")).select(*docs.columns)


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops lines that many documents share; n_chars follows the text. Documents all stay."""
    return line_dedup.dedup_lines(docs).withColumn("n_chars", F.length("text").cast("bigint")).select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates (five words, similarity 0.8) the row with the smallest doc_id, then text, stays; a text without words is no duplicate.

    Rows are told apart by doc_id and text; of rows alike in both, one stays. A null doc_id is the largest.
    """
    found = cut(simhash_bktree.similar_documents(docs).filter("n > 0").select("doc_id", "text_key", "stays"))
    gone = cut(found.filter("not stays").select("doc_id", "text_key").distinct())
    keyed = docs.withColumn(TEXT_KEY, F.unhex(F.md5(F.coalesce("text", F.lit("")))))
    # texts are dealt by row at every size: the rows that go grow with the input, and are not to be broadcast while they are few
    left = keyed.join(gone.hint("merge"), _same_row(keyed, gone), "left_anti")
    twice = cut(found.filter("stays").groupBy("doc_id", "text_key").agg(F.count(F.lit(1)).alias("rows")).filter("rows > 1"))
    if twice.isEmpty():
        return left.select(*docs.columns)
    one = left.join(twice, _same_row(left, twice), "left_semi").dropDuplicates(["doc_id", TEXT_KEY])
    return left.join(twice, _same_row(left, twice), "left_anti").select(*docs.columns).unionByName(one.select(*docs.columns))


def _same_row(docs: DataFrame, other: DataFrame) -> Column:
    return docs["doc_id"].eqNullSafe(other["doc_id"]) & (docs[TEXT_KEY] == other["text_key"])


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that align with a benchmark item go, each by its own text."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids, and digests of the ids and of the text decoded from them."""
    return bpe_automaton.encode(docs, words_kept=WORDS_KEPT)


STAGES = [
    ("language_id", language_id),
    ("line_dedup", line_dedup_stage),
    ("near_dedup", near_dedup),
    ("decontamination", decontamination),
    ("encoding", encoding),
]

#: Learned trees, fingerprints and automata are not SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
