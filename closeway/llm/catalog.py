"""The subpackage's named queries, each over its whole table, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import small, table
from . import decontam, hmm, langid, merge_replay, planes, projection_forest, secrets, setsketch, sharding, toxicity
from .common import fold


#: Labelled ids that are sent to the executors; more are joined by shuffling.
LABEL_ROWS = 500_000


def op1_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = fold("doc_id", 3) == 1
    profiles = langid.learn(docs.where(~held_out).select("lang", "text"))
    return langid.predict(docs, profiles).select("doc_id", held_out.alias("held_out"), "lang_pred", "score")


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    hits = decontam.find_hits(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    ids = F.array_join(F.array_sort(F.transform("items", lambda x: x.cast("string"))), ",")
    return hits.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(ids, 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op3_projection_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return projection_forest.near_vectors(table(spark, sf_dir, "embeddings"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    held_out = fold("doc_id", 5) == 0
    marked = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("label"))
    rows = docs.where(~held_out).select("doc_id", "text").join(small(marked, LABEL_ROWS), "doc_id")
    model = toxicity.learn(rows.select(F.col("doc_id").alias("id"), "text", "label"))
    return toxicity.score(docs, model).select("doc_id", held_out.alias("held_out"), "score", "predicted")


def op5_hmm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", (fold("doc_id", 10) == 0).alias("held_out"), "text")
    return hmm.Trained(docs).scores()


def op6_planes(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    with open(public_tokenizers.path("byte_bpe_50k.json")) as f:
        spec = f.read()
    files = planes.write_files(table(spark, sf_dir, "documents"), spec, public_tokenizers.PATTERN)
    return planes.read_files(files.df)


def op7_setsketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return setsketch.NearDuplicates(table(spark, sf_dir, "documents")).result()


def op8_merge_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    ranks = merge_replay.read_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    return merge_replay.encode_and_decode(table(spark, sf_dir, "documents"), ranks, public_tokenizers.PATTERN)


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan_secrets(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("base_spans", 256).alias("base_sha256"), "spans")


def op10_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_by_bytes(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_language, op2_decontaminate, op3_projection_forest, op4_toxicity, op5_hmm, op6_planes, op7_setsketch, op8_merge_replay, op9_secrets, op10_shards)}


def oracle_sql() -> dict[str, str]:
    return {"op2_decontaminate": decontam.ORACLE, "op3_projection_forest": projection_forest.ORACLE, "op7_setsketch": setsketch.ORACLE, "op10_shards": sharding.ORACLE}
