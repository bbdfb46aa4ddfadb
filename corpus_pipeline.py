"""The corpus pipeline: language, near duplicates, benchmark passages, secrets, token ids.

``STAGES`` lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame, which is written
as Parquet and read back as the next stage's ``docs``. All but the last return the columns of ``documents``.

Defined results for all stages: further columns pass through whatever their names; rows with null ids stay and are linked
with nothing; texts are read whole at any length; an empty table gives an empty one. Null texts and texts without a letter
go in the first stage.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from closeway.llm import decontam, langid, merge_replay, secrets, setsketch
from closeway.llm.common import fold, steady
from closeway.session import Stored, table


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents in which no profile recognises a language: null texts and texts without a letter.

    Repeated rows are judged each; where no language can be learned, texts with a letter stay.
    """
    steady(spark)
    profiles = langid.learn(docs.where(fold("doc_id", 3) != 1).select("lang", "text"))
    return langid.recognised(docs, profiles)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document of the smallest id of each group of near copies: word shingles alike by 0.8 or more.

    Of rows that repeat id and text one stays; rows that repeat an id with other texts go or stay by their own text.
    """
    steady(spark)
    return setsketch.deduplicated(docs, percent=80)


def drop_benchmark_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold ten words of a benchmark item in a row (all words of a shorter item).

    Null and wordless items match nothing; with no items all documents stay.
    """
    steady(spark)
    return decontam.uncontaminated(docs, table(spark, sf_dir, "benchmark"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps all documents and replaces the secrets in their texts; n_chars follows. A null text stays null."""
    steady(spark)
    return secrets.redacted(docs).withColumn("n_chars", F.char_length("text").cast("long"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Encodes and decodes every text: its token ids, their number, and digests of the ids and of the decoded bytes.

    A null text has no ids; of equal pairs in a word the leftmost is merged first.
    """
    steady(spark)
    ranks = merge_replay.read_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    return merge_replay.encode_and_decode(docs, ranks, public_tokenizers.PATTERN, with_ids=True, forget=True)


STAGES = [
    ("language_id", identify_language),
    ("near_dedup", drop_near_duplicates),
    ("decontamination", drop_benchmark_passages),
    ("secret_scan", redact_secrets),
    ("bpe", encode),
]

#: Profiles, sketches and merges are beyond SQL; the tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = Stored(stage(spark, docs, sf_dir), f"stage-{name}").df
    return STAGES[-1][1](spark, docs, sf_dir)
