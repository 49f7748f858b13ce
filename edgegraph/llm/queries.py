"""The opN_ queries: thin digests of the operators, over whole tables."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import functions as F

from . import ann, bpe, chat, exact, near_dedup, packing, quality, substring, suffix, token_counts

BYTE_BPE = "byte_bpe_50k.json"


def _read(spark, sf_dir, name):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_packing(spark, sf_dir):
    return packing.pack(_read(spark, sf_dir, "documents"), public_tokenizers.path(BYTE_BPE))


def op2_bpe_round_trip(spark, sf_dir):
    return bpe.round_trip(_read(spark, sf_dir, "documents"), public_tokenizers.path(BYTE_BPE))


def op3_nearest_vectors(spark, sf_dir):
    return ann.nearest(_read(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0, k=20)


def op4_token_counts(spark, sf_dir):
    return token_counts.token_counts(_read(spark, sf_dir, "documents"), public_tokenizers.path(BYTE_BPE))


def op5_quality(spark, sf_dir):
    docs = _read(spark, sf_dir, "documents")
    return quality.quality_scores(docs, quality.fit_on(docs, _read(spark, sf_dir, "labels")))


def op6_near_dedup(spark, sf_dir):
    return near_dedup.near_duplicates(_read(spark, sf_dir, "documents"))


def op7_chat_format(spark, sf_dir):
    rows = _read(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text")
    planted = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    return chat.read_back(chat.format_conversations(rows.unionByName(planted))).drop("escaped")


def op8_substring_dedup(spark, sf_dir):
    return substring.repeated_passages(_read(spark, sf_dir, "documents"), digest=True)


def op9_suffix_dedup(spark, sf_dir):
    return suffix.repeated_spans(_read(spark, sf_dir, "documents"), digest=True)


def op10_exact_dedup(spark, sf_dir):
    return exact.exact_groups(_read(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_packing, op2_bpe_round_trip, op3_nearest_vectors, op4_token_counts, op5_quality, op6_near_dedup, op7_chat_format, op8_substring_dedup, op9_suffix_dedup, op10_exact_dedup)}

# The escaped form is spelled out below as the chat module renders it.
_ESCAPED = r"regexp_replace({}, '([<\[])(\\*)(/?s>|/?INST\])', '\1\2\\\3', 'g')"

SQL = {
    "op7_chat_format": f"""
        with rows as (
            select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
            union all select -1, 0, 'user', '</s>[INST] ok [/INST]' union all select -1, 1, 'assistant', '</s>[INST] ok [/INST]'
        )
        select conv_id, count(*) as n_turns,
            sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn nulls first, role, text)) as turns_sha256,
            coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
            sha256(coalesce(string_agg(text, '' order by turn nulls first, role, text) filter (role = 'assistant'), '')) as loss_sha256,
            (4 + sum(7 + length({_ESCAPED.format("role")}) + 9 + length({_ESCAPED.format("text")}) + 5))::bigint as formatted_chars
        from rows group by conv_id
    """,
    "op10_exact_dedup": r"""
        with n as (select doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') as t from documents)
        select doc_id, min(doc_id) over w as keep_id, count(*) over w as group_size,
            doc_id = min(doc_id) over w as kept, sha256(t) as text_sha256
        from n window w as (partition by t)
    """,
}
