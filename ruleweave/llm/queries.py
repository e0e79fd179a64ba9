"""The queries of this subpackage and the DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleweave.llm import decontaminate, near_dedup, page_text, piece_transducer, prefix_forest, quality, secret_ledger, substring_dedup, token_counts, token_files
from ruleweave.llm.common import table

TOKENIZER, BYTE_TOKENIZER, PIECE_MODEL = "word_bpe_49k.json", "byte_bpe_50k.tiktoken", "piece_bpe_32k.model"


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.encode_write_read(table(spark, sf_dir, "documents"), tokenizer_file(TOKENIZER))


def op2_prefix_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefix_forest.neighbours(table(spark, sf_dir, "embeddings"))


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.repeats(table(spark, sf_dir, "documents"), digest=True)


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.scores(docs, model).withColumn("predicted", F.when(F.col("score") >= 0.7, 1).otherwise(0))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = table(spark, sf_dir, "documents")
    return token_counts.histogram(token_counts.lengths(docs, tokenizer_file(BYTE_TOKENIZER), public_tokenizers.PATTERN))


def op7_piece_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_transducer.encode(table(spark, sf_dir, "documents"), tokenizer_file(PIECE_MODEL))


def op8_page_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return page_text.main_texts(table(spark, sf_dir, "pages"))


def op9_secret_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return secret_ledger.digest(secret_ledger.Ledger(spark).scan(docs).findings(docs))


def op10_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.classes(table(spark, sf_dir, "documents"))


OP3_SQL = """
with i as (select item_id, regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+') w from benchmark),
isg as (select distinct item_id, list_slice(w, k, k + 4) g from (select item_id, w, unnest(range(1, len(w) - 3)) k from i)),
n as (select item_id, count(*) n_item from isg group by item_id),
d as (select doc_id, regexp_extract_all(lower(text), '[\\p{L}\\p{N}]+') w from documents),
dsg as (select distinct doc_id, list_slice(w, k, k + 4) g from (select doc_id, w, unnest(range(1, len(w) - 3)) k from d)),
s as (select doc_id, item_id, count(*) n_shared from dsg join isg using (g) group by doc_id, item_id)
select doc_id, item_id, n_item, n_shared, n_shared / n_item containment from s join n using (item_id) where n_shared >= 0.8 * n_item - 1e-9
"""

OP4_SQL = """
with w as (select doc_id, regexp_extract_all(coalesce(text, ''), '[^ \\t\\n\\x0B\\f\\r]+') ws from documents),
p as (select doc_id, ws, unnest(range(1, len(ws) - 11)) i from w),
g as (select doc_id, i, list_slice(ws, i, i + 12) g from p),
m as (select g, min(doc_id) least from g group by g),
gone as (select distinct doc_id, unnest(range(i, i + 13)) k from g join m using (g) where least < doc_id),
k as (select doc_id, unnest(ws) word, unnest(range(1, len(ws) + 1)) k from w),
s as (select k.doc_id, string_agg(word, ' ' order by k.k) filter (gone.k is null) kept, count(gone.k) n from k left join gone on gone.doc_id = k.doc_id and gone.k = k.k group by k.doc_id)
select w.doc_id, cast(len(ws) as bigint) n_words, coalesce(n, 0) n_removed, sha256(coalesce(kept, '')) kept_sha256 from w left join s on s.doc_id = w.doc_id
"""

# A private key as SQL can say it: from its BEGIN to its END line (a key without an END line takes assertions that DuckDB's patterns lack).
KEY_LINES = "-----BEGIN [A-Z0-9 ]{0,40}PRIVATE KEY(?: BLOCK)?-----(?s:.*?)-----END [A-Z0-9 ]{0,40}PRIVATE KEY(?: BLOCK)?-----"


def _op9_sql() -> str:
    """Spans from the lengths of a rule's matches and of the gaps between them, rule by rule."""
    rules = []
    for number, rule in enumerate(secret_ledger.RULES):
        p = "'" + (KEY_LINES if rule.kind == "private_key" else rule.pattern).replace("'", "''") + "'"
        rules.append(
            f"select rid, '{rule.kind}' kind, {number} number, {rule.least} least, regexp_extract_all(t, {p}) hits, "
            f"regexp_extract_all(t, {p}, {rule.group}) grps, string_split_regex(t, {p}) gaps from d where regexp_matches(t, {p})"
        )
    counts = ", ".join(f"count(*) filter (kind = '{r.kind}') n_{r.kind}" for r in secret_ledger.BASE)
    shown = ", ".join(f"coalesce(n_{r.kind}, 0) n_{r.kind}" for r in secret_ledger.BASE)
    span = "string_agg(concat_ws(':', kind, till - length(hit), till), ',' order by till - length(hit), number)"
    return f"""
with d as (select row_number() over () rid, doc_id, coalesce(text, '') t from documents),
m as ({" union all ".join(rules)}),
h as (select rid, kind, number, least, unnest(hits) hit, unnest(grps) grp, unnest(gaps[1:len(hits)]) gap, unnest(range(1, len(hits) + 1)) k from m),
e as (select *, cast(sum(length(gap) + length(hit)) over (partition by rid, kind order by k) as bigint) till from h),
s as (select rid, {counts}, {span} filter (number < {len(secret_ledger.BASE)}) base, {span} spans from e where length(grp) >= least group by rid)
select doc_id, {shown}, sha256(coalesce(base, '')) base_sha256, coalesce(spans, '') spans from d left join s using (rid)
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = (op1_token_files, op2_prefix_forest, op3_decontaminate, op4_substring_dedup, op5_quality, op6_token_counts, op7_piece_transducer, op8_page_text, op9_secret_ledger, op10_near_dedup)
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op3_decontaminate": OP3_SQL, "op4_substring_dedup": OP4_SQL, "op9_secret_ledger": _op9_sql()}
