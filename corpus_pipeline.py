"""A corpus from documents to tokens, in five stages.

Each stage takes (spark, docs, sf_dir) and works on all that the one before kept; its result is written as Parquet in
the shared folder and read again. All but the last return the columns of documents.

1. toxicity: documents that score 0.7 or more go.
2. line dedup: lines that five documents or more share stay in the one of largest doc_id only.
3. SimHash near-dedup: of documents linked by a Jaccard similarity of 0.8 or more over five-word shingles the one of
   smallest doc_id stays. SimHash finds links first, an exact search those that it misses (`near_copies`).
4. decontamination: documents that quote a benchmark item go.
5. byte-level BPE: the ids of each text and the text decoded from them.

A null text counts as an empty one (and is one after line dedup). Rows that repeat a doc_id are one document and share
its fate. Rows without a doc_id keep their lines; of near-duplicates with and without a doc_id those with one stand for
the group. Empty tables give empty tables.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkrank.llm import byte_bpe, common, decontamination, line_dedup, near_copies, toxicity

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    lexicon = toxicity.learned(docs, common.documents(spark, sf_dir, "labels"))
    return toxicity.accepted(docs.select(*COLUMNS), lexicon)


def without_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    kept = line_dedup.LineIndex.build(docs).deduped(docs, ("text",), ("lang", "source"))
    return kept.select("doc_id", "text", "lang", "source", F.char_length("text").cast("long").alias("n_chars"))


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    stay = near_copies.groups(docs).where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("_id")).distinct()
    return docs.select(*COLUMNS).join(stay, F.col("doc_id").eqNullSafe(F.col("_id")), "left_semi")


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.clean(docs.select(*COLUMNS), common.documents(spark, sf_dir, "benchmark"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return byte_bpe.encode_texts(docs, ["n_tokens", "token_ids", "text"], ("lang", "source"))


STAGES = [
    ("toxicity", without_toxic),
    ("line dedup", without_repeated_lines),
    ("SimHash near-dedup", without_near_copies),
    ("benchmark decontamination", without_benchmark),
    ("byte-level BPE", tokens),
]

#: SQL has no lexicon matching, Hamming search or BPE; tests hold the rows against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    for k, (_, stage) in enumerate(STAGES):
        before = docs
        with common.scratch(spark):  # what the stage wrote on its way goes when its result is there
            docs = common.keep(common.written(stage(spark, docs, sf_dir), f"stage-{k + 1}"))
        if k:
            common.discard(before)
    return docs
