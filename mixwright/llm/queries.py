"""One registered query per operator, each over its whole table."""

from __future__ import annotations

import corpus_pipeline
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kneser_ney, mpeg_audio, oracles, packing, pfair, quality_rules, reply_trees, sharding, simhash, suffix_dedup, token_store


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op2_kneser_ney(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    held_out = kneser_ney.fold(F.col("doc_id")) == 2
    model = kneser_ney.fit(docs.filter(~held_out), order=3)
    return kneser_ney.score(docs, model).select(
        "doc_id", held_out.alias("held_out"), "n_tokens", "n_known", F.lit(model.tokens).cast("long").alias("train_tokens"), "base_score", "score"
    )


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    m = F.col("measures")
    failed = (m["n_words"] < 20) | (100 * m["n_repeat_words"] > 30 * m["n_words"])
    return quality_rules.measure(docs).select(
        "doc_id",
        *[m[c].alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")],
        failed.alias("base_failed"),
        (~failed & quality_rules.passes(m)).alias("kept"),
    )


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(_table(spark, sf_dir, "documents").select("doc_id", "text"))


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_groups(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", simhash.hex_digits(F.col("fp")).alias("fingerprint"), F.col("component").alias("component_id"))


def op5_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    index = token_store.write_tokens(_table(spark, sf_dir, "documents").select("doc_id", "text"), public_tokenizers.path("word_bpe_49k.json"))
    return token_store.read_digests(index)


def op6_mpeg_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mpeg_audio.describe(mpeg_audio.with_media(_table(spark, sf_dir, "documents").select("doc_id", "text"), replace=True))


def op7_reply_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    probe = "</s>[INST] ok [/INST]"
    rows = _table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    rows = rows.unionByName(spark.createDataFrame([(-1, 0, "user", probe), (-1, 1, "assistant", probe)], "conv_id long, turn long, role string, text string"))
    nodes = reply_trees.chains(rows)
    out = reply_trees.format_paths(nodes, reply_trees.branch_paths(nodes))
    turns, learnt = reply_trees.read_back(F.col("formatted")), F.array_join(reply_trees.read_loss(F.col("formatted"), F.col("loss")), "")
    out = out.select("tree", "formatted", turns.alias("turns"), learnt.alias("learnt"))
    whole = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return out.select(
        F.col("tree").alias("conv_id"),
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(whole.cast("binary"), 256).alias("turns_sha256"),
        F.length("learnt").cast("long").alias("loss_chars"),
        F.sha2(F.col("learnt").cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


def op8_pfair_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "source", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"))
    return pfair.mix(pfair.stored(docs, "mix-sizes"), size=F.col("n_bytes"))


def _words(text: str):
    return F.size(F.array_remove(F.split(F.coalesce(F.col(text), F.lit("")), quality_rules.SPACE), ""))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    near = simhash.near_groups(docs.select("doc_id", "text")).groupBy("doc_id").agg(F.min("component").alias("cluster"))
    docs = docs.select(F.col("doc_id").alias("id"), "source", _words("text").alias("n_words")).join(near, F.col("id").eqNullSafe(F.col("doc_id")))
    return packing.pack(packing.stored(docs.drop("id"), "pack-sizes"), F.col("n_words"), F.col("cluster"))


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.digests(_table(spark, sf_dir, "documents").select("doc_id", "text"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_sharding, op2_kneser_ney, op3_quality_rules, op4_simhash, op5_token_store, op6_mpeg_audio, op7_reply_trees, op8_pfair_mixing, op9_best_fit_packing, op10_suffix_dedup)} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {"op3_quality_rules": oracles.quality_rules_sql(), "op7_reply_trees": oracles.reply_trees_sql()} | ({"pipeline": corpus_pipeline.ORACLE_SQL} if corpus_pipeline.ORACLE_SQL else {})
