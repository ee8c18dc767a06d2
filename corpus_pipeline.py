"""The corpus pipeline: five stages over documents, each on what the stage before it kept.

Stages take (spark, docs, sf_dir) and return a DataFrame; each result is written as Parquet and read again. All
but the last return the columns of documents. Toxic documents go, one document of each near-duplicate group
stays, contaminated documents go, the rest is mixed to the target weights and written as token files.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from channelalign.llm.decontam import decontaminate
from channelalign.llm.mixing import mixed_documents
from channelalign.llm.near_dup import near_duplicates
from channelalign.llm.store import fresh_dir
from channelalign.llm.token_files import token_output
from channelalign.llm.toxicity import fit, score_toxicity
from channelalign.sources.tables import load


def _apart(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """docs with columns d_0, d_1, ... and the new name of each: whatever they were called, they clash with nothing."""
    at = {c: f"d_{i}" for i, c in enumerate(docs.columns)}
    return docs.select(*[F.col(f"`{c}`").alias(n) for c, n in at.items()]), at


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model predicts as clean, with their columns. The model is fitted on labelled rows of the input."""
    model = fit(docs, load(spark, sf_dir, "labels"))
    renamed, at = _apart(docs)
    scored = score_toxicity(renamed, model, id_col=at["doc_id"], text_col=at["text"], keep=tuple(at.values()))
    return scored.where("predicted = 0").select(*[F.col(at[c]).alias(c) for c in docs.columns])


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of documents connected by a Jaccard similarity of 0.8 or more of word 5-grams, the document of the least id; of rows that share that id, one."""
    groups = near_duplicates(docs)
    # An id is kept if it is its group's least; ids that are null keep their rows' own groups by the text's hash.
    chosen = groups.where(F.col("class_id") == F.col("row_id")).select("row_id").distinct()
    renamed, at = _apart(docs)
    row_id = F.coalesce(F.col(at["doc_id"]).cast("long"), -F.shiftrightunsigned(F.xxhash64(F.coalesce(at["text"], F.lit(""))), 2) - 2)
    kept = renamed.withColumn("row_id", row_id).join(chosen, "row_id", "left_semi").dropDuplicates(["row_id"])
    return kept.select(*[F.col(n).alias(c) for c, n in at.items()])


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no window of ten consecutive words of a benchmark item occurs."""
    renamed, at = _apart(docs)
    found = decontaminate(renamed, load(spark, sf_dir, "benchmark"), id_col=at["doc_id"], text_col=at["text"], keep=tuple(at.values()))
    return found.where("NOT contaminated").select(*[F.col(at[c]).alias(c) for c in docs.columns])


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix by source weights: documents, once for every epoch that takes words of them."""
    return mixed_documents(docs)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files of all documents and, read back from them, a row per document."""
    import public_tokenizers

    return token_output(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("mixing", mix),
    ("token_files", write_tokens),
]

#: No stage but decontamination can be said in SQL; tests hold the pipeline against brute force on small tables.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result goes through the shared folder."""
    docs = load(spark, sf_dir, "documents")
    for n, (name, stage) in enumerate(STAGES):
        result = stage(spark, docs, sf_dir)
        if n == len(STAGES) - 1:
            return result
        path = fresh_dir(spark, f"stage-{name}")
        result.write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
