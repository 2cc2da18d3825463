"""The thin queries of the training-data operators, with their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import functions as F

from .bpe import vocabulary
from .chat import DIGEST_SQL, digest, format_turns, probe_rows
from .common import table, written
from .langid import language_report
from .media import text_media
from .mixing import REPORT_SQL, mix_report
from .near_dup import REPORT_SQL as NEAR_SQL
from .near_dup import near_duplicates
from .neighbours import nearest
from .packing import pack
from .sharding import byte_shards
from .token_output import token_table
from .toxicity import toxicity_report


def op1_best_fit_packing(spark, sf_dir):
    return pack(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"), end_id=1, capacity=4096)


def op2_token_output(spark, sf_dir):
    return token_table(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"), end_id=2)


def op3_sharding(spark, sf_dir):
    return byte_shards(table(spark, sf_dir, "documents"), shards=40)


def op4_toxicity(spark, sf_dir):
    return toxicity_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_chat_formatting(spark, sf_dir):
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    formatted = written(format_turns(turns.unionByName(probe_rows(turns))), "chat")
    return digest(formatted)


def op6_media_columns(spark, sf_dir):
    return text_media(table(spark, sf_dir, "documents"))


def op7_mixing(spark, sf_dir):
    return mix_report(table(spark, sf_dir, "documents"), share=1.5, most=2.0)


def op8_nearest_neighbours(spark, sf_dir):
    return nearest(table(spark, sf_dir, "embeddings"), "vec_id", "embedding", lambda i: F.pmod(i, F.lit(20)) == 0, k=20)


def op9_language_id(spark, sf_dir):
    return language_report(table(spark, sf_dir, "documents"))


def op10_minhash_near_dedup(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "documents"), words=4, percent=80)


QUERIES = {
    f.__name__: f
    for f in (op1_best_fit_packing, op2_token_output, op3_sharding, op4_toxicity, op5_chat_formatting, op6_media_columns, op7_mixing, op8_nearest_neighbours, op9_language_id, op10_minhash_near_dedup)
}

ORACLES = {"op5_chat_formatting": DIGEST_SQL, "op7_mixing": REPORT_SQL, "op10_minhash_near_dedup": NEAR_SQL}
