"""Corpus pipeline over documents: language, near copies, benchmark passages, secrets, tokens.

Each stage takes what its predecessor kept. A text that a stage changes gets a new
``n_chars``. A row's id and text identify a document, so different texts under one id, or
under none, are documents of their own; of rows that repeat an id and its text, the stage
on near copies keeps one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freshview.llm import byte_bpe, decontaminate, language, ngram_join, secrets
from freshview.llm.common import discard, materialise, table


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language that was learned; null texts and texts without a letter go."""
    model = language.train_on_documents(docs)
    rest = F.struct(*[c for c in docs.columns if c != "text"]).alias("row")
    named = language.identify(docs.select(rest, "text"), model).filter(F.col("lang_pred") != language.UNKNOWN)
    return named.select(*[F.col("text") if c == "text" else F.col("row").getField(c).alias(c) for c in docs.columns])


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one with the least id, ties by a digest of the text; null ids come last."""
    marked = docs.withColumn("__digest", F.md5("text"))
    key = F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", F.col("__digest").alias("digest"))
    found = materialise(ngram_join.similar_components(marked.select("text", key.alias("__key")), doc_id="__key"))
    # without an id, wordless texts are not known to repeat each other: each is its own group
    apart = F.col("doc_id.unnamed") & (F.col("n_shingles") == 0)
    kept = found.filter(F.col("doc_id") == F.col("component_id")).groupBy("doc_id").agg(F.count(F.when(~apart, F.lit(1))).alias("rows"))
    kept = kept.select(F.col("doc_id.doc_id").alias("__kept"), F.col("doc_id.digest").alias("__kept_digest"), "rows")
    same = F.col("doc_id").eqNullSafe(F.col("__kept")) & F.col("__digest").eqNullSafe(F.col("__kept_digest"))
    # the list grows with the corpus, so it is never broadcast, however small it is here
    single = marked.join(kept.filter("rows <= 1").hint("merge"), same, "left_semi")
    repeated = marked.join(kept.filter("rows > 1"), same, "left_semi").dropDuplicates(["doc_id", "__digest"])
    return single.unionByName(repeated).drop("__digest")


def without_benchmarks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Benchmark passages are cut out of the texts; a document that has no word left goes."""
    clean = decontaminate.remove_contamination(docs, table(spark, sf_dir, "benchmark"))
    left = F.col("text").rlike("[^\\x00-\\x2F\\x3A-\\x40\\x5B-\\x60\\x7B-\\x7F]")
    return clean.filter(left).withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)).select(*docs.columns)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark."""
    clean = secrets.redact(secrets.scan_secrets(docs, out="__secret_spans"), spans="__secret_spans")
    return clean.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)).select(*docs.columns)


def as_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids and of the decoded ids."""
    return byte_bpe.encode_digests(docs)


STAGES = [
    ("language", known_language),
    ("near_copies", one_of_each_group),
    ("benchmarks", without_benchmarks),
    ("secrets", without_secrets),
    ("tokens", as_tokens),
]

#: The stages on near copies and spans are beyond SQL; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        older, docs = docs, materialise(stage(spark, docs, sf_dir))
        discard(older)
    return STAGES[-1][1](spark, docs, sf_dir)
