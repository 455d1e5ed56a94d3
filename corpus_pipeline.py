"""A training-data pipeline over the documents table: quality, near duplicates, repeated passages, leaks, token ids.

Each stage works on all that the stage before kept. The first four return the columns of documents; the last returns the
encoding of every document that is left.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltahop.llm import decontaminate, near_dup, quality_rules, sentence_pieces, suffix_dedup
from deltahop.llm.workdir import drop_path, stored


def reserved(docs: DataFrame) -> dict[str, str]:
    """A name for each further column that no operator uses for a column of its own."""
    return {c: f"carried_{k}" for k, c in enumerate(docs.columns) if c not in ("doc_id", "text")}


def carried(docs: DataFrame) -> DataFrame:
    return docs.withColumnsRenamed(reserved(docs))


def restored(out: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of docs, under their names again."""
    names = reserved(docs)
    return out.select(*[F.col(names.get(c, c)).alias(c) for c in docs.columns])


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rule ensemble predicts to be of low quality go."""
    model = quality_rules.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return restored(quality_rules.score_documents(carried(docs), model).where("predicted = 1"), docs)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates (five-word shingles, similarity 0.8) stays, that of the smallest id."""
    verdicts = near_dup.near_duplicates(docs.select("doc_id", "text"))
    dropped = verdicts.where(~F.col("kept") & F.col("doc_id").isNotNull()).select("doc_id").distinct()
    return docs.join(dropped, "doc_id", "left_anti").select(*docs.columns)


def repeated_passage_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 50 bytes or more that an earlier document holds too are cut out; only whole characters are left."""
    cut = suffix_dedup.remove_repeats(carried(docs), with_text=True)
    whole = cut.withColumn("text", F.col("kept_text"))
    if "n_chars" in docs.columns:
        n_chars = reserved(docs)["n_chars"]
        whole = whole.withColumn(n_chars, F.when(F.col("n_removed") > 0, F.length("text")).otherwise(F.col(n_chars)).cast(docs.schema["n_chars"].dataType))
    return restored(whole, docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item, even with other numbers, names or units, go."""
    return decontaminate.without_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids_crc32, round_trip) of every document left."""
    return sentence_pieces.encode_documents(docs)


STAGES = [
    ("quality classifier", quality_stage),
    ("MinHash near-dedup", near_duplicate_stage),
    ("suffix-array dedup", repeated_passage_stage),
    ("benchmark decontamination", decontamination_stage),
    ("SentencePiece encoding and decoding", encoding_stage),
]

#: Trees, MinHash, suffix order and merges aren't expressible in SQL; the stages are tested against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages applied to documents; each result is written and read again as the next one's input."""
    docs, held = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for k, (_, stage) in enumerate(STAGES[:-1]):
        docs, path = stored(stage(spark, docs, sf_dir), f"stage-{k}")
        if held:
            drop_path(spark, held)  # the next stages read the table just written
        held = path
    return STAGES[-1][1](spark, docs, sf_dir)
