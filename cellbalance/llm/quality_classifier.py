"""Quality classifier: perplexity under a Kneser-Ney model of trusted text, thresholded by quantiles of each language.

Trusted documents are all those labelled quality 1. The half of them with an even crc32 of the id trains the model; the other
half, which the model has not seen, gives each language its threshold: the ``QUANTILE`` of their mean log10 perplexity plus
``MARGIN``, and plus ``SHORT / sqrt(tokens)``, as the mean of a few tokens strays more. A document above it is rejected. Counts lie in hash shards and documents are joined to
them shard by shard (see language_model).

Null and empty texts have one token, the end; they are judged like others. Null languages, and languages with fewer than
``FEW`` documents in the second half, take the threshold of all languages. Without trusted documents nothing is rejected.
Repeated rows are judged alike. Extra columns stay.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, table
from .language_model import score, train

QUANTILE = 0.99
MARGIN = 0.1
SHORT = 1.2
FEW = 20


def _judged(docs: DataFrame, trusted: DataFrame, keep_text: bool) -> DataFrame:
    """The columns of ``docs`` and __n_tokens, __log_perplexity, __threshold, __kept."""
    ids = table(trusted.select(F.col("doc_id").cast("long").alias("doc_id")).filter("doc_id is not null").distinct(), "trusted")
    even = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 2 == 0
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    model = train(rows.join(ids.filter(even), "doc_id", "left_semi"), "trusted-lm")
    log_perplexity = -F.col("__score") / F.col("__n_tokens")
    second = score(rows.join(ids.filter(~even), "doc_id", "left_semi"), model, prefix="__").select("lang", log_perplexity.alias("p"))
    level = F.percentile_approx("p", F.lit(QUANTILE), F.lit(10_000))
    # one row a language
    levels = table(second.groupBy("lang").agg(level.alias("__t"), F.count("*").alias("n")).filter((F.col("n") >= FEW) & F.col("lang").isNotNull()).select(F.col("lang").alias("__lang"), "__t"), "thresholds")
    overall = table(second.agg(level.alias("t")), "threshold")
    scored = score(docs, model, keep_text, "__").join(F.broadcast(levels), F.col("lang") == F.col("__lang"), "left")
    threshold = F.coalesce(F.col("__t"), overall.scalar()) + MARGIN + SHORT / F.sqrt("__n_tokens")
    judged = scored.withColumn("__log_perplexity", log_perplexity).withColumn("__threshold", threshold)
    return judged.withColumn("__kept", F.coalesce(F.col("__log_perplexity") <= F.col("__threshold"), F.lit(True)))


def judge(docs: DataFrame, trusted: DataFrame) -> DataFrame:
    """(doc_id, lang, n_tokens, log_perplexity, threshold, kept) of every document. ``trusted`` has doc_id."""
    judged = _judged(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "lang", "text"), trusted, False)
    return judged.select("doc_id", "lang", *(F.col(f"__{c}").alias(c) for c in ("n_tokens", "log_perplexity", "threshold", "kept")))


def keep_good(docs: DataFrame, trusted: DataFrame) -> DataFrame:
    """The documents that aren't rejected, with all their columns; texts aren't shuffled."""
    return _judged(docs, trusted, True).filter("__kept").select(*docs.columns)


def trusted_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet").filter("quality = 1").select("doc_id")


def op8_kneser_ney_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(documents(spark, sf_dir), trusted_ids(spark, sf_dir))
