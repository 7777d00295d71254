"""Quality rules, native: counts of each document and the hashed n-gram log-likelihood ratio.

Words and word pairs are hashed into ``BUCKETS`` buckets. Two multinomials over the buckets are counted over all documents
in one pass, of the trusted ones (labelled quality 1, a bounded sample of them) and of the raw corpus; with add-one smoothing they give one log ratio
a bucket. A document's score is the mean log ratio of its n-grams, and ``kept`` is ``score >= threshold``: a fixed number,
so the verdict depends on nothing but the text and the two multinomials. Without trusted documents every ratio is 0.

Only DataFrame functions are used. The log ratios (``BUCKETS`` doubles, a fixed size) reach the documents as a scalar
subquery. Null texts are empty: no words, base_failed. Repeated rows and extra columns are kept out of the way: labels are
reduced to distinct ids, and only doc_id and text are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACE_CLASS, SPACES, bounded_sample, documents, let, word_array

BUCKETS = 65_536
THRESHOLD = -0.12
SYMBOLS = "#*$%&|<>"
WINDOW = 5


def ngram_buckets(word_hash: Column, buckets: int) -> Column:
    """Buckets of the words and of the pairs of neighbours, from an array of word hashes."""
    pair = F.transform(F.arrays_zip(F.slice(word_hash, 1, F.greatest(F.size(word_hash) - 1, F.lit(0))).alias("x"), F.slice(word_hash, 2, F.greatest(F.size(word_hash) - 1, F.lit(0))).alias("y")), lambda p: F.pmod(F.xxhash64(p["x"], p["y"]), F.lit(buckets)).cast("int"))
    return F.concat(F.transform(word_hash, lambda h: F.pmod(h, F.lit(buckets)).cast("int")), pair)


def log_ratios(docs: DataFrame, trusted: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    """One row, one array: ln(p_trusted / p_raw) of each bucket. ``trusted`` has doc_id."""
    ids = bounded_sample(trusted)
    marked = docs.select("doc_id", "text").join(F.broadcast(ids.withColumn("good", F.lit(1))), "doc_id", "left")
    grams = marked.select("good", F.explode(let(F.transform(word_array(F.col("text")), lambda w: F.xxhash64(w)), lambda h: ngram_buckets(h, buckets))).alias("bucket"))
    counts = grams.groupBy("bucket").agg(F.count("*").alias("raw"), F.count("good").alias("good"))
    full = docs.sparkSession.range(buckets).select(F.col("id").cast("int").alias("bucket")).join(counts, "bucket", "left").fillna(0, ["raw", "good"])
    both = full.agg(F.array_sort(F.collect_list(F.struct("bucket", "good", "raw"))).alias("b"), F.sum("good").alias("n_good"), F.sum("raw").alias("n_raw"))
    ratio = F.transform("b", lambda x: F.log((x["good"] + 1) / (F.col("n_good") + buckets)) - F.log((x["raw"] + 1) / (F.col("n_raw") + buckets)))
    return both.select(F.when(F.col("n_good") > 0, ratio).otherwise(F.array_repeat(F.lit(0.0), buckets)).alias("ratio"))


def repeat_words(word_hash: Column, k: int = WINDOW) -> Column:
    """Words in windows of ``k`` words that are found twice or more in the text."""

    def of_windows(windows: Column) -> Column:
        ordered = F.array_sort(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

        def starts(s: Column) -> Column:
            again = F.filter(F.transform(s, lambda x, i: F.when((x["h"] == F.get(s, i - 1)["h"]) | (x["h"] == F.get(s, i + 1)["h"]), x["i"])), lambda x: x.isNotNull())
            return let(F.array_sort(again), lambda p: F.aggregate(p, F.struct(F.lit(0).alias("n"), F.lit(-k).alias("last")), lambda a, x: F.struct((a["n"] + F.least(F.lit(k), x - a["last"])).alias("n"), x.alias("last")), lambda a: a["n"].cast("long")))

        return F.when(F.size(F.array_distinct(windows)) == F.size(windows), F.lit(0).cast("long")).otherwise(let(ordered, starts))

    count = F.size(word_hash) - (k - 1)
    windows = F.transform(F.sequence(F.lit(0), count - 1), lambda i: F.xxhash64(*[F.get(word_hash, i + j) for j in range(k)]))
    return F.when(count <= 1, F.lit(0).cast("long")).otherwise(let(windows, of_windows))


def quality(docs: DataFrame, trusted: DataFrame, threshold: float = THRESHOLD, buckets: int = BUCKETS) -> DataFrame:
    """Counts, base verdict, score and verdict of every document."""
    model = log_ratios(docs, trusted, buckets).scalar()
    text = F.coalesce(F.col("text"), F.lit(""))
    has_word = F.filter(F.split(text, "\n"), lambda line: F.translate(line, SPACES, "") != "")
    measured = docs.select("doc_id", "text").withColumn("model", model).select(
        "doc_id",
        let(has_word, lambda lines: F.size(lines) - F.size(F.array_distinct(lines))).cast("long").alias("n_dup_lines"),
        F.char_length(F.regexp_replace(text, SPACE_CLASS, "")).cast("long").alias("word_chars"),
        (F.char_length(text) - F.char_length(F.translate(text, SYMBOLS, ""))).cast("long").alias("n_symbols"),
        let(
            F.transform(word_array(F.col("text")), lambda w: F.xxhash64(w)),
            lambda h: F.struct(
                F.size(h).cast("long").alias("n_words"),
                repeat_words(h).alias("n_repeat_words"),
                let(ngram_buckets(h, buckets), lambda b: F.aggregate(b, F.lit(0.0), lambda s, x: s + F.get(F.col("model"), x)) / F.greatest(F.size(b), F.lit(1))).alias("score"),
            ),
        ).alias("m"),
    )
    counted = measured.select("doc_id", F.col("m.n_words").alias("n_words"), "word_chars", "n_symbols", "n_dup_lines", F.col("m.n_repeat_words").alias("n_repeat_words"), F.col("m.score").alias("score"))
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return counted.withColumn("base_failed", failed).withColumn("kept", ~F.col("base_failed") & (F.col("score") >= F.lit(threshold))).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "score")


def op1_ngram_likelihood_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    trusted = spark.read.parquet(f"{sf_dir}/labels.parquet").filter("quality = 1").select("doc_id")
    return quality(documents(spark, sf_dir), trusted)
