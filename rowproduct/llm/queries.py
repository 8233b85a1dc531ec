"""Queries of the training-data operators: (spark, sf_dir) -> DataFrame, with SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .oracles import ORACLES


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


PIECES = "piece_bpe_32k.model"


def op1_sentencepiece(spark, sf_dir):
    """Every text's ids as a digest, and whether they decode to the text again."""
    from .pieces import decode, encode

    path = tokenizer_file(PIECES)
    both = decode(encode(_table(spark, sf_dir, "documents"), path), path)
    return both.select("doc_id", "n_tokens", "ids_crc32", F.element_at("ids", 1).alias("first_id"), (F.col("decoded") == F.coalesce("text", F.lit(""))).alias("restored"))


def op2_nearest_neighbours(spark, sf_dir):
    from .ann import neighbours

    return neighbours(_table(spark, sf_dir, "embeddings"))


def op3_simhash_near_dedup(spark, sf_dir):
    from .simhash import near_duplicates

    return near_duplicates(_table(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id")


def op4_toxicity(spark, sf_dir):
    from .toxicity import held_out, score, train

    docs = _table(spark, sf_dir, "documents")
    out = score(docs, train(docs, _table(spark, sf_dir, "labels")))
    return out.select("doc_id", held_out("doc_id").alias("held_out"), "score", "predicted")


def op5_packing(spark, sf_dir):
    from .packing import TOKENIZER, pack

    return pack(_table(spark, sf_dir, "documents"), tokenizer_file(TOKENIZER))


def op6_license_scan(spark, sf_dir):
    from .licenses import scan

    return scan(_table(spark, sf_dir, "documents"))


def op7_token_counts(spark, sf_dir):
    from .pieces import token_counts

    return token_counts(_table(spark, sf_dir, "documents"), tokenizer_file(PIECES))


def op8_line_dedup(spark, sf_dir):
    from .lines import dedup_lines

    out = dedup_lines(_table(spark, sf_dir, "documents"), counts=True)
    return out.select("doc_id", "dropped_lines", "dropped_words", F.length("text").cast("long").alias("kept_chars"), F.crc32(F.encode("text", "UTF-8")).alias("kept_crc32"))


def op9_quality_rules(spark, sf_dir):
    from .quality import measure

    return measure(_table(spark, sf_dir, "documents"))


def op10_warc(spark, sf_dir):
    """Archive, records put together again, WARC files, and what their parser reads."""
    from .scratch import new_path
    from .warc import export_warc, read_pages, write_archive

    path, files = new_path(spark, "archive"), new_path(spark, "warc")
    write_archive(_table(spark, sf_dir, "pages"), path)
    export_warc(spark, path, files)
    return read_pages(spark, files)


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (
    op1_sentencepiece, op2_nearest_neighbours, op3_simhash_near_dedup, op4_toxicity, op5_packing, op6_license_scan,
    op7_token_counts, op8_line_dedup, op9_quality_rules, op10_warc, pipeline)}

__all__ = ["ORACLES", "QUERIES"]
