"""A corpus pipeline of four operators: each stage works on all that the one before it kept.

Stages take (spark, docs, sf_dir) and return a DataFrame; `run` writes each one's
result as Parquet to the shared folder and reads it again. All but the last
return the columns of `documents`; further columns are dropped, whatever they're
named.

Defined results. Language ID drops null, empty and letterless texts, and those of
which fewer than LEAST_KNOWN of the n-grams have a weight in the fitted model
(other languages and scripts, encoded data); without any labelled document it
drops all. Near-duplicates keep one row of each group, of the least id, null ids
last; rows that repeat id and text are one; a text without a word stands alone.
Mixing takes each row on its own, whatever its id; null sources are one source;
what is taken of a row is whole copies and at most one cut to its first words.
BPE gives one row for each row. Empty tables give no row in any stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockbwt.llm import byte_bpe, common, language_id, lsh_forest, mixing

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: The least share of a text's n-grams that a text in a learned language has; see the README for figures.
LEAST_KNOWN = 0.7


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps texts in a language; `lang` becomes the predicted one."""
    kept = docs.select(*COLUMNS)
    model = language_id.learn(kept.where(language_id.remainder(F.col("doc_id"), 3) != 1))
    found = language_id.predict(kept, model, keep=("doc_id", "text", "source", "n_chars"))
    sure = (F.col("lang_pred") != "und") & (F.col("known") >= LEAST_KNOWN)
    return found.where(sure).select("doc_id", "text", F.col("lang_pred").alias("lang"), "source", "n_chars")


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one row of each group, of the smallest id; one with a null id only where its group has no other. Rows that repeat id and text are one."""
    rows = docs.select(*COLUMNS)
    key = lambda h: [F.coalesce("doc_id", F.lit(0)).alias("d"), F.col("doc_id").isNull().alias("z"), h.alias("h")]
    found = lsh_forest.representatives(rows).select(*key(F.col("text_hash")))
    rest = [c for c in COLUMNS if c != "doc_id"]
    once = rows.select(*key(F.xxhash64("text")), F.struct(*rest).alias("row")).groupBy("d", "z", "h").agg(F.min("row").alias("row"))
    return once.join(found, ["d", "z", "h"], "left_semi").select(F.when(~F.col("z"), F.col("d")).alias("doc_id"), "row.*")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; one at a source's edge is cut to its first words."""
    kept = docs.select(*COLUMNS)
    taken = mixing.take(mixing.mix(kept, quality=mixing.labelled_weights(spark, sf_dir), carry=True))
    return taken.withColumn("n_chars", F.length("text").cast("long"))


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return byte_bpe.digests(docs)


STAGES = [
    ("language ID", identify_language),
    ("near-duplicates", drop_near_duplicates),
    ("mixing", mix_sources),
    ("byte-level BPE", encode_tokens),
]

#: SQL can't express the fitted language model nor the tokenizer.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = common.materialise(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
    return docs
