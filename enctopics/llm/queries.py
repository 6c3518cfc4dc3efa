"""The registered queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

import corpus_pipeline
from enctopics.llm import audio, chat, decontaminate, langid, packing, sharding, simhash, suffixes, token_counts, toxicity
from enctopics.llm.common import cut, documents, narrow, remainder, save, word_bpe


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = langid.learn(docs.where(remainder(4) != 2))
    held_out = (remainder(4) == 2).alias("held_out")
    return langid.predict(docs, model).select("doc_id", held_out, "lang_pred", "score", "rejected")


def op3_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contamination(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.digest(suffixes.repeats(narrow(documents(spark, sf_dir), doc_id="doc_id", text="text")))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trees of all documents, kept, then a batch of three edits a document, at places and of kinds that its id and their number give."""
    import public_tokenizers

    vocabulary = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
    kept = save(token_counts.trees(documents(spark, sf_dir), *vocabulary), "zstd")
    draw = lambda what, k, n: F.pmod(F.xxhash64("doc_id", F.lit(what), F.lit(k)), n)
    said = F.array(*map(F.lit, ["", " edited", "\n\n", "x", "  two  spaces ", "'s 12,5 %"]))
    edits = F.array(*[F.struct(F.lit(k).alias("seq"), draw("start", k, F.col("n_chars") + 1).alias("start"), draw("n_delete", k, F.lit(40)).alias("n_delete"), F.element_at(said, (draw("said", k, F.lit(6)) + 1).cast("int")).alias("inserted")) for k in range(3)])
    after = token_counts.edited(kept.withColumn("edits", edits), *vocabulary)
    return after.select("doc_id", F.col("n_tokens_before").alias("n_tokens"), F.col("n_tokens").alias("n_tokens_after"), F.col("n_chars").alias("n_chars_after"), F.size("leaf_tokens").alias("n_leaves"), "chars_reencoded")


def op6_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recordings of all vectors; those whose id is divisible by 100 are looked up among all."""
    media = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    prints = cut(audio.fingerprints(media, "vec_id", "embedding", audio.melody))
    asked = audio.class_of(prints).where("id % 100 = 0")
    found = audio.align(prints, asked.select("class_id").distinct())
    return asked.join(found, F.col("query_id") == asked["class_id"], "left").select(
        asked["id"].alias("vec_id"), asked["class_id"].alias("own_class"), asked["copies"].alias("own_copies"), found["class_id"].alias("match_class"), found["copies"].alias("match_copies"), "offset", "votes", "bit_error", "n_frames"
    )


def op7_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    said = "</s>[INST] ok [/INST]"
    probe = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    return chat.digest(chat.format_chats(turns.unionByName(probe)))


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), word_bpe())


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(remainder(3) != 1)
    scored = toxicity.score(docs, toxicity.learn(docs, labels))
    return scored.select("doc_id", (remainder(3) == 1).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(documents(spark, sf_dir))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "pipeline": corpus_pipeline.run,
        "op1_simhash_near_dedup": op1_simhash_near_dedup,
        "op2_language_id": op2_language_id,
        "op3_benchmark_decontamination": op3_benchmark_decontamination,
        "op4_suffix_dedup": op4_suffix_dedup,
        "op5_token_counts": op5_token_counts,
        "op6_media_columns": op6_media_columns,
        "op7_chat_formatting": op7_chat_formatting,
        "op8_best_fit_packing": op8_best_fit_packing,
        "op9_toxicity": op9_toxicity,
        "op10_sharding": op10_sharding,
    }


ORACLE_SQL: dict[str, str] = {
    "op7_chat_formatting": """
        WITH t AS (
            SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
            UNION ALL VALUES (-7, 0, 'user', '</s>[INST] ok [/INST]'), (-7, 1, 'assistant', '</s>[INST] ok [/INST]')
        ), m AS (
            SELECT *, coalesce(lag(role) OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) <> role, true) AS opens,
                replace(replace(text, '&', '&amp;'), '<|', '&lt;|') AS et,
                replace(replace(replace(role, '&', '&amp;'), '<|', '&lt;|'), chr(10), '&nl;') AS er
            FROM t
        ), c AS (
            SELECT conv_id, count(*) AS n_turns,
                string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text) AS said,
                coalesce(string_agg(CASE WHEN role = 'assistant' THEN text END, '' ORDER BY turn NULLS FIRST, role, text), '') AS loss,
                sum(length(et) + CASE WHEN opens THEN length(er) + 13 + 11 ELSE 10 END) AS formatted_chars
            FROM m GROUP BY conv_id
        )
        SELECT conv_id, CAST(n_turns AS BIGINT) AS n_turns, sha256(said) AS turns_sha256, CAST(length(loss) AS BIGINT) AS loss_chars,
            sha256(loss) AS loss_sha256, CAST(formatted_chars AS BIGINT) AS formatted_chars FROM c""",
}

if corpus_pipeline.ORACLE_SQL:
    ORACLE_SQL["pipeline"] = corpus_pipeline.ORACLE_SQL
