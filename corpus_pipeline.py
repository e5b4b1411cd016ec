"""A pipeline over ``documents``: toxicity, near duplicates, secrets, mixing, packing.

Every stage is a function of (spark, docs, sf_dir); its result is written as Parquet
and read again as the next stage's docs. All but the last return the columns of docs,
whatever further ones there are and whatever they are called.

In every stage null texts count as empty, nulls in other columns are kept, repeated rows
are rows of their own unless a stage says otherwise, and an empty table gives an empty
result. A row is found again by what it holds or by a stored number, never by its
position in a scan, as another scan may number rows otherwise.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

import traincube
from traincube.llm import minmax_dedup, packing, secret_scan, source_mix, toxicity
from traincube.llm.scratch import materialize

#: SQL cannot express the fitted, hashed and packed stages.
ORACLE_SQL = None


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model, trained on the labels, does not reject.

    Without labels of both kinds nothing is rejected. Empty texts stay.
    """
    traincube.importable(spark)
    model = toxicity.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.reject(docs, model)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates, the one with the smallest id, null last.

    Texts without words link with nothing, so all of them stay. Of rows equal in id and
    text, one stays.
    """
    traincube.importable(spark)
    near = minmax_dedup.near_duplicates(docs)
    firsts = F.count_if("first")
    keys = materialize(near.groupBy("id", "print").agg(firsts.alias("firsts"), F.count("*").alias("n")).where("firsts > 0").select("id", "print", (F.col("firsts") < F.col("n")).alias("one")))
    rows = docs.select(F.struct(*docs.columns).alias("doc"), F.col("doc_id").cast("long").alias("own_id"), F.xxhash64(F.coalesce(F.col("text").cast("binary"), F.lit(b""))).alias("own_print"))
    kept = rows.join(keys, F.col("own_id").eqNullSafe(F.col("id")) & (F.col("own_print") == F.col("print")))
    out = kept.where("not one").select("doc.*")
    if keys.where("one").isEmpty():
        return out
    return out.union(kept.where("one").groupBy("id", "print").agg(F.first("doc").alias("doc")).select("doc.*"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with the secrets in their texts replaced, and n_chars, if there is one, counted anew."""
    traincube.importable(spark)
    clean = secret_scan.redact(docs)
    return clean.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else clean


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it.

    Texts without words add nothing to what is taken; passes and draws have them as they
    have others. Rows are numbered once, in a stored table.
    """
    traincube.importable(spark)
    placed = materialize(docs.select(F.struct(*docs.columns).alias("doc"), F.monotonically_increasing_id().alias("place")))
    flat = placed.select(F.col("doc.doc_id").alias("doc_id"), F.col("doc.text").alias("text"), F.col("doc.source").alias("source"), "place")
    sized = materialize(source_mix.measure(flat, F.array("source"), place=F.col("place")))
    copies = source_mix.mix(sized).where("copies > 0").select("place", "copies")
    taken = placed.join(copies, "place").select("doc", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
    return taken.select("doc.*")


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents and their places in sequences; an empty text is its end id alone."""
    traincube.importable(spark)
    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json")).withColumnRenamed("id", "doc_id")


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("secrets", redact_secrets),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = materialize(docs)
    return docs
