"""From raw documents to packed training sequences: five stages, each on all that the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_spark.llm.common import stage, table, tokenizer_path
from subgraph_spark.llm.exact_dedup import duplicate_groups, located
from subgraph_spark.llm.mixing import line_of, plan, sizes_of, word_count
from subgraph_spark.llm.near_texts import near_copies
from subgraph_spark.llm.packing import pack_documents
from subgraph_spark.llm.quality import score, train

#: A document whose score is below this goes.
QUALITY = 0.3
#: Pre-tokens that a worker remembers: fewer than by default, since all stages' work shares its memory.
REMEMBERED = 250_000


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the classifier accepts."""
    weights = train(docs, table(spark, sf_dir, "labels"))
    return score(docs, weights, keep=docs.columns).filter(F.col("__own_score") >= QUALITY).drop("__own_score")


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts."""
    docs = located(docs)
    dropped = stage(duplicate_groups(docs).filter("not kept").select(F.col("file").alias("__own_file"), F.col("row").alias("__own_row")), "dropped")
    return docs.join(dropped, ["__own_file", "__own_row"], "left_anti").drop("__own_file", "__own_row")


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies (five-word shingles, similarity 0.8 or more): the smallest id, none last, then the first by place."""
    docs = located(docs)
    found = stage(near_copies(docs), "near-copies")
    first = found.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "file", "row")).alias("first"))
    stays = (F.col("file") == F.col("first.file")) & (F.col("row") == F.col("first.row"))
    dropped = stage(found.join(first, "root").filter(~stays).select(F.col("file").alias("__own_file"), F.col("row").alias("__own_row")), "dropped")
    return docs.join(dropped, ["__own_file", "__own_row"], "left_anti").drop("__own_file", "__own_row")


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; those without words, of which nothing can be taken, stay once."""
    own = docs.columns
    docs = located(docs)
    mix = plan(sizes_of(docs))
    rows = docs.select(F.struct(*[F.col(f"`{x}`") for x in own]).alias("__own_doc"), "doc_id", F.col("source").cast("string").alias("source"), word_count().alias("size"), line_of().alias("line"), F.col("__own_file").alias("file"), F.col("__own_row").alias("row"))
    times = F.when(F.col("size") == 0, F.lit(1)).otherwise(F.col("copies").cast("int"))
    rows = mix.copies(rows).select("__own_doc", times.alias("__own_copies")).filter("__own_copies > 0")
    return rows.select("__own_doc", F.explode(F.sequence(F.lit(1), F.col("__own_copies"))).alias("__own_copy")).select("__own_doc.*")


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in sequences of 2048 tokens."""
    return pack_documents(docs, tokenizer_path("word_bpe_49k.json"), 0, 2048, REMEMBERED)


STAGES = [("quality classifier", quality), ("exact dedup", exact), ("simhash near-dedup", near), ("mixing", mix), ("best-fit packing", pack)]

#: The classifier and the tokenizer are beyond SQL; the tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages on ``documents``, each written as Parquet and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, step in STAGES:
        docs = stage(step(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
