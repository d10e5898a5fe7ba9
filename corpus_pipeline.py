"""From raw documents to packed training bins, in five stages of the operators in ``mixwright.llm``.

Each stage takes (spark, docs, sf_dir); what it returns is written as Parquet and reread as the next one's docs. All but
the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mixwright.functions import storage
from mixwright.llm import packing, pfair, quality_rules, shared, simhash, suffix_dedup

#: Five-word shingles and the least Jaccard similarity of near-copies.
NEAR_WIDTH, NEAR_SIMILARITY = 5, 0.8


def drop_bad(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that break a quality rule go."""
    return quality_rules.keep_good(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near copies stays, the one of least id: SimHash groups, each checked exactly, and the exact links between them."""
    return simhash.keep_one(docs, found=simhash.near_texts(docs, width=NEAR_WIDTH, threshold=NEAR_SIMILARITY))


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Strings of 100 bytes that occur earlier are cut out of the texts; documents with no word left go."""
    return suffix_dedup.clean(docs).filter(F.col("text").rlike(r"[^\x20\x09-\x0D]"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, scheduled at its source's natural share: files and the rows in them follow the slots of the schedule, and bins are packed along them."""
    sizes = shared.stored(docs.select("doc_id", "source", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes")), "mix-sizes")
    slot, key = shared.free_names(docs, "_p_slot", "_p_id")
    chosen = shared.stored(pfair.mix(sizes, size=F.col("n_bytes"), ceiling=1.0).groupBy(F.col("doc_id").alias(key)).agg(F.min("slot").alias(slot)), "mix-slots")
    placed = docs.join(shared.sized(chosen), F.col("doc_id").eqNullSafe(F.col(key)))
    return placed.repartitionByRange(slot).sortWithinPartitions(slot, "doc_id").select(*[F.col(f"`{c}`") for c in docs.columns])


def pack_bins(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bins of 2048 words along the schedule of the mixture, without two near copies (of a SimHash group) or three documents of a source in one bin."""
    words = F.size(F.array_remove(F.split(F.coalesce(F.col("text"), F.lit("")), quality_rules.SPACE), ""))
    near = simhash.near_groups(docs.select("doc_id", "text")).groupBy(F.col("doc_id").alias("id")).agg(F.min("component").alias("cluster"))
    sizes = shared.numbered(docs).select("doc_id", "source", words.alias("n_words"), shared.PLACE).join(near, F.col("doc_id").eqNullSafe(F.col("id"))).drop("id")
    return packing.pack(shared.stored(sizes, "pack-sizes"), F.col("n_words"), F.col("cluster"), place=F.col(shared.PLACE))


STAGES = [
    ("quality_rules", drop_bad),
    ("near_dedup", drop_near_copies),
    ("suffix_array_dedup", cut_repeats),
    ("mix_sources", mix_sources),
    ("best_fit_packing", pack_bins),
]

#: Verified set joins, suffix arrays and best fit are beyond SQL; tests/llm compares the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, last = spark.read.parquet(f"{sf_dir}/documents.parquet"), []
    for name, stage in STAGES:
        keep: list[str] = []
        with storage.tidied(spark, keep):  # what a stage has written on its way goes when its result is written
            docs = storage.kept(stage(spark, docs, sf_dir), f"stage-{name}")
            keep.append(docs.stored_at)
        storage.removed(spark, *last)
        last = keep
    return docs
