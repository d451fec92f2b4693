"""The driver's queries of this subpackage: each applies an operator to its whole table and derives a digest."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import storage


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from . import chat_format as chat

    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = "</s>[INST] ok [/INST]"
    planted = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    made = chat.formatted(chat.turns_of_table(rows.unionByName(planted)))
    back = made.select("conv_id", "formatted", chat.read_back(F.col("formatted")).alias("turns"), chat.loss_text(F.col("formatted"), F.col("loss_spans")).alias("loss"))
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(said, 256).alias("turns_sha256"), F.length("loss").cast("long").alias("loss_chars"),
        F.sha2("loss", 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"),
    )


def op2_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import ngram_join

    return ngram_join.join_components(table(spark, sf_dir, "documents"), size=4, percent=85)


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import warc

    archives, index = storage.fresh_path(spark, "archives"), storage.fresh_path(spark, "capture_index")
    pages = table(spark, sf_dir, "pages")
    warc.write_archives(pages, archives, min_bytes=0)
    warc.write_index(spark, archives, index)
    return warc.read_captures(spark, archives, index, pages.select("url")).drop("payload", "url")


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import quality

    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    rows = storage.saved(quality.measured(docs).drop("text"), "measured")
    found = quality.judged(rows, storage.saved(quality.host_verdicts(rows), "hosts"))
    return found.select("doc_id", *[f"_q.{c}" for c in quality.MEASURES], "_q.base_failed", found["_kept"].alias("kept"))


def op5_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from . import html_extract

    return html_extract.extracted(table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("long"))


def op6_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import mixing

    documents = mixing.mix(table(spark, sf_dir, "documents"))[0]
    return documents.select("doc_id", "size", "source_size", "target", "taken")


def op7_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import context_mixing

    return context_mixing.scored(table(spark, sf_dir, "documents"))


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from . import token_files

    path = storage.fresh_path(spark, "token_files")
    token_files.write_token_files(table(spark, sf_dir, "documents"), path, public_tokenizers.path("word_bpe_49k.json"), end_id=2)
    return token_files.token_digests(spark, path)


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from . import line_dedup

    found = line_dedup.deduplicated(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "text", F.length("text").cast("long").alias("n_chars"), "n_lines", F.size("removed_lines").cast("long").alias("n_removed"))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import decontaminate

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return decontaminate.digest(decontaminate.scan(docs, table(spark, sf_dir, "benchmark"), window=10, keep=["doc_id"]))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("op") and name[2].isdigit()}


def oracle_sql() -> dict[str, str]:
    from . import oracles

    return oracles.SQL
