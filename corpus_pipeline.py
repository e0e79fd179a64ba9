"""From raw documents to token ids in five stages, each an operator of ruleweave.llm.

STAGES lists (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and
read again as the next stage's docs. All but the last return the columns they get. ORACLE_SQL is None: SQL cannot express a
trained classifier; tests/llm compares run() with a plain Python version instead.

A row is a document: rows that share a doc_id, or have none, are kept or dropped each for its own text. Empty and null texts are
documents like others.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleweave.llm import decontaminate, near_dedup, piece_transducer, quality, secret_ledger
from ruleweave.llm.common import staged, table
from ruleweave.llm.queries import PIECE_MODEL, tokenizer_file

KEEP_SCORE = 0.7
ORACLE_SQL = None


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose quality score is at least KEEP_SCORE; the model is trained on these documents and the labels."""
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.scored(docs, model).filter(F.col("rw_score") >= KEEP_SCORE).select(docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest doc_id of each near-duplicate class, null after all others; a repeated row stays once."""
    first = staged(near_dedup.grouped(docs).filter("first").select("id", "exact"))
    own_id, own_text = near_dedup.row_key(docs)
    kept = docs.join(first, (own_id == first["id"]) & (own_text == first["exact"]), "left_semi")
    if not first.groupBy("id", "exact").count().filter("count > 1").isEmpty():
        kept = kept.dropDuplicates(["doc_id", "text"])
    return kept


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that contain a benchmark item; items without an id are items of their own."""
    row = F.xxhash64(docs["doc_id"], docs["text"])
    own = F.concat(F.lit("no id "), F.xxhash64("text").cast("string"))
    items = table(spark, sf_dir, "benchmark").select(F.coalesce(F.col("item_id").cast("string"), own).alias("item_id"), "text")
    found = decontaminate.leaks(docs.select(row.alias("rw_row"), "text"), items, id_col="rw_row").select(F.col("doc_id").alias("rw_row")).distinct()
    return docs.join(found, row == found["rw_row"], "left_anti")


def secret_masking(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Masks the secrets that the ledger finds; n_chars follows the text."""
    found = secret_ledger.Ledger(spark).scan(docs).findings(docs).filter(F.size("found") > 0)
    flagged = found.select(F.col("doc_id"), F.lit(True).alias("flag")).distinct()
    has, columns = flagged["flag"].isNotNull(), []
    text = F.when(has, secret_ledger.masked(docs["text"])).otherwise(docs["text"])
    for name, kind in docs.dtypes:
        if name == "text":
            columns.append(text.alias(name))
        elif name == "n_chars":
            columns.append(F.when(has, F.length(text).cast(kind)).otherwise(docs[name]).alias(name))
        else:
            columns.append(docs[name])
    return docs.join(flagged, docs["doc_id"].eqNullSafe(flagged["doc_id"]), "left").select(columns)


def piece_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document: doc_id, n_ids, ids, ids_crc32, decoded_ok."""
    return piece_transducer.encode(docs, tokenizer_file(PIECE_MODEL))


STAGES = [
    ("quality classifier", quality_classifier),
    ("near-duplicates", near_duplicates),
    ("benchmark decontamination", benchmark_decontamination),
    ("secret masking", secret_masking),
    ("piece encoding", piece_encoding),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies STAGES to documents, each result written and read again."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
