"""Token counts from an exact length histogram (op6).

Each text is encoded once and only its length is kept. One row for each distinct length, with suffix sums,
answers every question about totals: how many tokens there are, how many remain if texts are cut to a
context limit, and which length stands at a quantile. The suffix sums are taken in two levels (inside runs of
lengths, then over runs), so no single task has to sort the whole histogram: runs are ranges of about equally many lengths, one
a shuffle partition, and the driver adds up one pair of sums a run.

Null texts count as empty (length 0), repeated rows count each, a text of any length is encoded whole; an empty table gives an empty
histogram.
"""

from __future__ import annotations

import base64

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ruleweave.llm.common import shuffle_width, small_batches, staged


def byte_bpe(path: str, pattern: str):
    """A tiktoken encoding from a file of base64 tokens and ranks."""
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
    return tiktoken.Encoding("byte_bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


_ENCODINGS: dict = {}


def lengths(docs: DataFrame, path: str, pattern: str, text_col: str = "text") -> DataFrame:
    """n_tokens of every text, in a column of that name only."""

    def run(batches):
        if path not in _ENCODINGS:
            _ENCODINGS[path] = byte_bpe(path, pattern)
        encode = _ENCODINGS[path].encode_ordinary
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([len(encode(t)) if t else 0 for t in batch[0].to_pylist()], pa.int64())], ["n_tokens"])

    small_batches(docs.sparkSession)
    return docs.select(F.col(text_col).alias("rw_text")).mapInArrow(run, "n_tokens long")


def histogram(lengths: DataFrame, runs: int | None = None) -> DataFrame:
    """For each distinct n_tokens: n_docs, sum_tokens; docs_from and tokens_from (documents of this length or longer);
    truncated_total (tokens left if every text is cut to n_tokens) and share_to (share of documents up to this length)."""
    counts = lengths.groupBy("n_tokens").agg(F.count("*").alias("n_docs")).withColumn("sum_tokens", F.col("n_tokens") * F.col("n_docs"))
    counts = counts.repartitionByRange(runs or shuffle_width(lengths.sparkSession), "n_tokens")
    counts = staged(counts.withColumn("rw_run", F.spark_partition_id()))  # read twice; a row for each distinct length
    sums = sorted(counts.groupBy("rw_run").agg(F.sum("n_docs").alias("docs"), F.sum("sum_tokens").alias("tokens")).collect())  # a row a run
    later, docs_after, tokens_after = [], 0, 0
    for r in reversed(sums):
        later.append((r.rw_run, docs_after, tokens_after))
        docs_after, tokens_after = docs_after + r.docs, tokens_after + r.tokens
    later = lengths.sparkSession.createDataFrame(later, "rw_run int, rw_docs long, rw_tokens long")
    w = Window.partitionBy("rw_run").orderBy(F.desc("n_tokens"))
    out = counts.join(F.broadcast(later), "rw_run").withColumns({"rw_all": F.lit(docs_after).cast("long"), "rw_all_tokens": F.lit(tokens_after).cast("long")})
    out = out.withColumn("docs_from", F.sum("n_docs").over(w) + F.col("rw_docs")).withColumn("tokens_from", F.sum("sum_tokens").over(w) + F.col("rw_tokens"))
    below = F.col("rw_all_tokens") - F.col("tokens_from")
    return out.select(
        "n_tokens", "n_docs", "sum_tokens", "docs_from", "tokens_from",
        (below + F.col("n_tokens") * F.col("docs_from")).alias("truncated_total"),
        ((F.col("rw_all") - F.col("docs_from") + F.col("n_docs")) / F.col("rw_all")).alias("share_to"),
    )


def truncated_total(hist: DataFrame, limit: int) -> int:
    """Tokens left if every text is cut to `limit`: read off the suffix sums at the first length of at least `limit`."""
    row = hist.filter(F.col("n_tokens") >= limit).orderBy("n_tokens").first()
    if row is None:
        return hist.agg(F.coalesce(F.sum("sum_tokens"), F.lit(0))).first()[0]
    return row.truncated_total - (row.n_tokens - limit) * row.docs_from


def quantile(hist: DataFrame, q: float) -> int | None:
    """The smallest length that at least the share q of the documents does not exceed."""
    row = hist.filter(F.col("share_to") >= q).orderBy("n_tokens").first()
    return None if row is None else row.n_tokens
