"""The corpus pipeline: toxicity, near-duplicates, decontamination, secrets, tokens.

Each stage takes (spark, docs, sf_dir), works on all that its predecessor kept and returns the columns of documents; the last
adds the piece ids. run() writes each stage's result to the shared checkpoint folder and reads it again.

Defined results: a document that toxicity rejects goes; of each group of near copies (SimHash fingerprints within 24 bits and a five-word Jaccard similarity of 0.8 or more, transitive) the row with the smallest id stays (of rows that share it the one with
the smaller text hash, of equal texts the least by its JSON); rows without an id can't be named by a group and stay; a document that holds a benchmark window goes; secrets are masked and n_chars follows the
text where that changes it; null texts stay null. Extra columns pass through; ids and n_ids are the last stage's. An empty table gives an empty one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgeloc.llm import decontaminate, near_copies, piece_codec, secrets_scan, toxicity
from edgeloc.llm.common import checkpointed, fresh, read_table, text_key


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = toxicity.learn(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
    (score,) = fresh(docs, "score")
    return toxicity.score(docs, model, out_col=score).where(F.col(score) < model.threshold).select(docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    named = docs.where("doc_id is not null")
    k1, k2 = fresh(docs, "k1", "k2")
    copies = near_copies.near_copies(named).groupBy("label", "id", "k1", "k2").agg(F.count("*").alias("copies"))
    kept = copies.groupBy("label").agg(F.min(F.struct("id", "k1", "k2", "copies")).alias("r")).select(F.col("r.id").alias("doc_id"), F.col("r.k1").alias(k1), F.col("r.k2").alias(k2), F.col("r.copies").alias("copies"))
    kept = checkpointed(kept)
    keyed = named.withColumns(dict(zip((k1, k2), text_key(F.coalesce(F.col("text").cast("string"), F.lit(""))))))
    rows = keyed.join(kept.where("copies = 1").drop("copies"), ["doc_id", k1, k2], "left_semi").select(docs.columns)
    equal = keyed.join(kept.where("copies > 1").drop("copies"), ["doc_id", k1, k2], "left_semi")  # rare: rows with the same id and text, of which the least by its JSON stays
    equal = equal.groupBy("doc_id", k1, k2).agg(F.min_by(F.struct(*docs.columns), F.to_json(F.struct(*docs.columns))).alias("r")).select("r.*")
    return rows.union(equal).union(docs.where("doc_id is null"))


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_contaminated(docs, read_table(spark, sf_dir, "benchmark"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    (masked,) = fresh(docs, "masked")
    out = secrets_scan.redact(docs.withColumn(masked, F.col("text")), text_col=masked)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col(masked).eqNullSafe(F.col("text")), F.col("n_chars")).otherwise(F.char_length(masked)).cast(docs.schema["n_chars"].dataType))
    return out.withColumn("text", F.col(masked)).select(docs.columns)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return piece_codec.encode(docs, out_col="ids").withColumn("n_ids", F.size("ids"))


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash", drop_near_copies),
    ("decontamination", drop_benchmark),
    ("secrets", mask_secrets),
    ("pieces", encode_pieces),
]

ORACLE_SQL = None  # a learned score, fingerprints and a subword model are beyond SQL; tests/llm/test_pipeline.py compares every stage with plain Python


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = checkpointed(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
