"""From raw documents to packed training sequences, in five stages.

Each stage takes all rows that its predecessor kept. All stages but the last return the columns of
documents; the last returns one row for each piece of a packed sequence.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from approxboot.llm import decontam, jaccard, packing, quality, secrets
from approxboot.llm.common import free_names, prepare, table, written

#: Documents whose quality score is lower are rejected.
LEAST_QUALITY = 0.3


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the compression classifier, fitted on the labelled ones outside its held-out fold, does not reject."""
    model = quality.fit(docs, quality.training_labels(table(spark, sf_dir, "labels").select("doc_id", "quality")))
    scored = quality.score(docs, model, out="__quality_score")
    return scored.where(F.col("__quality_score") >= LEAST_QUALITY).select(docs.columns)


def keep_one_of_similar(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of similar documents: that of the smallest doc_id, null ones last. Of rows equal in doc_id and text one stays; texts without words all stay."""
    prepare(spark)
    members, _ = jaccard.jaccard_components(docs)
    members = written(members.where("root is not null").select("doc_id", "uid", "root"), "pipeline-members")
    first = members.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "uid")).alias("first"))
    own = members.join(first, "root").withColumn("stays", F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("uid") == F.col("first.uid")))
    doc, uid = free_names(docs, "_doc", "_uid")
    dropped = own.where("not stays").select(F.col("doc_id").alias(doc), F.col("uid").alias(uid)).distinct()
    same = F.col("doc_id").eqNullSafe(F.col(doc)) & (F.xxhash64("text") == F.col(uid))
    out = docs.join(dropped, same, "left_anti").select(docs.columns)
    # rows that are there more than once: few, or none
    again = own.where("stays").groupBy(F.col("doc_id").alias(doc), F.col("uid").alias(uid)).agg(F.count(F.lit(1)).alias("_count")).where("_count > 1").select(doc, uid)
    again = written(again, "pipeline-again")
    if again.isEmpty():
        return out
    once = out.join(again, same, "left_semi").dropDuplicates(["doc_id", "text"])
    return out.join(again, same, "left_anti").unionByName(once).select(docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without passages of the benchmark."""
    return decontam.clean(docs, table(spark, sf_dir, "benchmark"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets in their texts replaced by a mark and n_chars brought up to date."""
    findings, _ = secrets.scan(docs)
    return secrets.masked(docs, findings).withColumn("n_chars", F.when(F.col("n_chars").isNull(), F.col("n_chars")).otherwise(F.length("text").cast("long"))).select(docs.columns)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents, packed into sequences of 4096 tokens at most."""
    import public_tokenizers

    prepare(spark)
    # a small cache: executors still hold what the stages before have left in their memory
    return packing.pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"), 1, max_words=250_000)


STAGES = [
    ("quality_classifier", keep_good),
    ("jaccard_join", keep_one_of_similar),
    ("benchmark_decontamination", drop_contaminated),
    ("secret_scan", mask_secrets),
    ("best_fit_packing", pack_sequences),
]

#: Compression, tokenizers and graph components are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows over the documents in sf_dir; every stage's are written and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
