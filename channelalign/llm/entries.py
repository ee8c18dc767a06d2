"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from channelalign.sources.tables import load

TOKENIZER = "word_bpe_49k.json"
UNIGRAM = "piece_bpe_32k.model"


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from channelalign.llm.exact_dedup import exact_duplicates

    return exact_duplicates(load(spark, sf_dir, "documents"))


def op4_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from channelalign.llm.token_files import token_output

    return token_output(load(spark, sf_dir, "documents"), public_tokenizers.path(TOKENIZER)).select("doc_id", "start", "n_tokens", "ids_crc32")


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from channelalign.llm.decontam import decontaminate

    return decontaminate(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark")).drop("hits")


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from channelalign.llm.licenses import scan_licenses

    return scan_licenses(load(spark, sf_dir, "documents")).drop("expressions")


def op7_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    from channelalign.llm.mixing import mix_report

    return mix_report(load(spark, sf_dir, "documents"))


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from channelalign.llm.toxicity import fit, held_out, score_toxicity

    docs = load(spark, sf_dir, "documents")
    scored = score_toxicity(docs, fit(docs, load(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out().alias("held_out"), "score", "predicted", "spans")


def op8_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from channelalign.llm.near_dup import near_duplicates

    return near_duplicates(load(spark, sf_dir, "documents"))


def op6_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    from channelalign.llm.pii import find_personal_data

    return find_personal_data(load(spark, sf_dir, "documents"))


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from channelalign.llm.token_counts import count_tokens

    return count_tokens(load(spark, sf_dir, "documents"), public_tokenizers.path(UNIGRAM))


def op5_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from channelalign.llm.html_text import extract_text

    return extract_text(load(spark, sf_dir, "pages"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f) and name[2].isdigit()}


def oracle_sql() -> dict[str, str]:
    from channelalign.llm import decontam, exact_dedup

    return {"op9_exact_dedup": exact_dedup.SQL, "op3_decontaminate": decontam.SQL}
