"""The registered queries of the training-data operators, with production parameters over whole tables."""

from __future__ import annotations

from minlabel.llm import chat_formatting, context_trees, decontamination, language_id, mixing, near_duplicates, personal_data, quality_rules, repeated_passages
from minlabel.llm import token_counts as tc
from minlabel.session import table

SOURCE_COLUMNS = ("doc_id",)


def op1_mixing(spark, sf_dir):
    return mixing.mixed(table(spark, sf_dir, "documents"))


def op4_language_id(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return language_id.languages(docs, language_id.fit(docs))


def op2_quality_rules(spark, sf_dir):
    return quality_rules.quality_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_decontamination(spark, sf_dir):
    out = decontamination.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "longest_match", "spans", "contaminated")


def op5_repeated_passages(spark, sf_dir):
    return repeated_passages.repeated_passages(table(spark, sf_dir, "documents"))


def op6_context_trees(spark, sf_dir):
    return context_trees.scores(table(spark, sf_dir, "documents"))


def op7_near_duplicates(spark, sf_dir):
    return near_duplicates.classes(table(spark, sf_dir, "documents"))


def op8_token_counts(spark, sf_dir):
    import public_tokenizers

    return tc.token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op9_chat_formatting(spark, sf_dir):
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    trap = spark.createDataFrame([(chat_formatting.TRAP_ID, turn, role, chat_formatting.TRAP) for turn, role in ((0, "user"), (1, "assistant"))], rows.schema)
    return chat_formatting.digests(chat_formatting.conversations(chat_formatting.linear_messages(rows.unionByName(trap)), repeated=False))


def op10_personal_data(spark, sf_dir):
    return personal_data.personal_data(table(spark, sf_dir, "documents"))


QUERIES = (
    op1_mixing, op2_quality_rules, op3_decontamination, op4_language_id, op5_repeated_passages,
    op6_context_trees, op7_near_duplicates, op8_token_counts, op9_chat_formatting, op10_personal_data,
)


def queries():
    return {f.__name__: f for f in QUERIES}


def oracle_sql():
    return {"op1_mixing": mixing.oracle(), "op2_quality_rules": quality_rules.oracle(), "op9_chat_formatting": chat_formatting.ORACLE}
