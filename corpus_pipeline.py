"""A corpus pipeline: language, repeated lines, near duplicates, source mix, packing.

Each stage is a function of (spark, docs, sf_dir) and works on all rows that the
stage before it kept. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulegraph.llm import language_id, line_dedup, mixing, packing, simhash
from rulegraph.llm.common import cut, ship
from rulegraph.llm.queries import TOKENIZER

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: A cosine that random vectors of 1024 places exceed about one time in ten: no evidence of any language.
MIN_SCORE = 0.05


def keep_known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, or unlike every learned language, go."""
    ship(spark)
    docs = docs.select(*COLUMNS)
    found = language_id.predict_language(docs, language_id.train_prototypes(docs))
    return found.where((F.col("lang_pred") != language_id.UNKNOWN) & (F.col("score") >= MIN_SCORE)).select(*COLUMNS)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that occur earlier in the corpus go; documents of which no word is left go with them."""
    ship(spark)
    left = line_dedup.dedup_lines(docs.select(*COLUMNS)).where(F.col("text").rlike("\\S"))
    return left.withColumn("n_chars", F.length("text").cast("bigint")).select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays."""
    ship(spark)
    return simhash.drop_near_duplicates(docs.select(*COLUMNS))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are sampled towards the target weights of source, language and topic."""
    ship(spark)
    return mixing.sample_mix(docs.select(*COLUMNS))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every piece of every document gets its place in a sequence."""
    ship(spark)
    return packing.pack(docs.select(*COLUMNS), tokenizer=TOKENIZER)


STAGES = [
    ("language_id", keep_known_language),
    ("line_dedup", drop_repeated_lines),
    ("simhash_near_dedup", drop_near_duplicates),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: Cosines of random vectors and tokenizers are beyond SQL: tests compare every stage with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
