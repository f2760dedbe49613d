"""One query for each training-data operator, over its whole table."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import fingerprints, flac, licences, mixing, mixing_sql, neardup, pieces, quality, sharding, tokenfile, toxicity
from .common import table

#: Where the public vocabularies lie; parameters of the operators.
BYTE_BPE = public_tokenizers.path("byte_bpe_50k.json")
PIECE_BPE = public_tokenizers.path("piece_bpe_32k.model")


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.words_taken(table(spark, sf_dir, "documents"))


def op2_quality_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.resample(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.edited_pairs(table(spark, sf_dir, "documents"))


def simhash_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The block tables of op3: all fingerprints within three bits of each other."""
    return fingerprints.near_fingerprints(table(spark, sf_dir, "documents"))


def op4_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_components(table(spark, sf_dir, "documents"), percent=85)


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfile.token_file_digests(table(spark, sf_dir, "documents"), BYTE_BPE, end_id=0)


def op7_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.piece_digests(table(spark, sf_dir, "documents"), PIECE_BPE)


def op8_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan(table(spark, sf_dir, "documents"))


def op9_extendible_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents"))


def op10_flac_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flac.media_digests(flac.encode_column(table(spark, sf_dir, "documents").select("doc_id", "text")))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_mix_sources, op2_quality_resampling, op3_simhash, simhash_search, op4_minhash_near_dedup, op5_toxicity, op6_token_files, op7_pieces, op8_licence_scan, op9_extendible_shards, op10_flac_media)
}

ORACLE_SQL: dict[str, str] = {
    "op1_mix_sources": mixing_sql.words_taken_sql(),
    "op4_minhash_near_dedup": neardup.near_components_sql(),
    "op8_licence_scan": licences.scan_sql(),
    "op9_extendible_shards": sharding.shards_sql(),
}
