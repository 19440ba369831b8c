"""The ten operators as registered queries, with oracle SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from qacurate.llm import compression, line_alignment, mixing, packing, quality_crf, radix_exact, simhash_cover, substring_cover, toxicity_chain, warc
from qacurate.registry import Registry, read
from qacurate.staging import fresh_path

LLM = Registry()


#: Target weights of the given sources; a source that is not named has the least of them.
TARGETS = {f"src{k}": float(1 + k % 4) for k in range(20)}


@LLM.add("op1_mix_pfair")
def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read(spark, sf_dir, "documents"), TARGETS)


@LLM.add("op2_warc_segments", warc.round_trip_sql())
def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = fresh_path(spark, "warc")
    warc.write_warc(read(spark, sf_dir, "pages"), path)
    found = warc.read_warc(spark, path, with_payload=False)
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


@LLM.add("op3_line_alignment")
def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_alignment.align_lines(read(spark, sf_dir, "documents"))
    return found.withColumn("removed", F.array_join("removed", ","))


@LLM.add("op4_pack_nnls")
def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return packing.pack(read(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


@LLM.add("op5_quality_crf")
def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    return quality_crf.score(docs, quality_crf.fit(docs, read(spark, sf_dir, "labels")))


@LLM.add("op6_substring_cover", substring_cover.ORACLE)
def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_cover.remove_repeats(read(spark, sf_dir, "documents")).drop("cut_from", "cut_to")


@LLM.add("op7_compression_bands")
def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compression.compression_bands(read(spark, sf_dir, "documents"))


@LLM.add("op8_radix_exact", radix_exact.ORACLE)
def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return radix_exact.exact_classes(read(spark, sf_dir, "documents"))


@LLM.add("op9_simhash_cover")
def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_cover.near_classes(read(spark, sf_dir, "documents"))


@LLM.add("op10_toxicity_chain")
def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The label table names two categories: unfit text comes first in the chain, abuse second."""
    docs, kinds = read(spark, sf_dir, "documents"), ("unfit", "toxic")
    labels = read(spark, sf_dir, "labels").select("doc_id", (1 - F.col("quality")).alias("unfit"), "toxic")
    return toxicity_chain.score(docs, toxicity_chain.fit(docs, labels, kinds), kinds, "toxic")
