"""Quality rules: hashed n-gram log-likelihood ratio between trusted and raw text (native).

Every word and every word pair of a document is hashed into one of ``buckets`` bins. Two multinomials over
the bins are counted, one from trusted documents and one from the whole corpus; a document's score is the mean
of log p(bin | trusted) - log p(bin | corpus) over its bins. A document is kept when it passes the base rules
and its score is not below ``threshold``, a fixed number, so that equal texts always get equal verdicts.

Results for odd input: null or empty text has no words, fails the base rules and scores 0; repeated rows are
judged each; without trusted documents all scores are 0 and only the base rules decide; an empty table gives
no rows; further columns of the input are left alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settled, words

BUCKETS = 1 << 14
#: Trusted documents used at most; the bound lets their ids be broadcast (8 bytes each).
MAX_TRUSTED = 20_000
THRESHOLD = -0.045
SMOOTHING = 1.0


def trusted_ids(labels: DataFrame, max_trusted: int = MAX_TRUSTED) -> DataFrame:
    """At most ``max_trusted`` ids of documents labelled good and not toxic, spread evenly by hash."""
    good = labels.filter("quality = 1 and toxic = 0 and doc_id is not null").select("doc_id").distinct()
    return good.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_trusted)


def _hashes(text: str) -> Column:
    """One 64-bit hash a word; all grams are built from these."""
    return F.transform(words(F.col(text)), lambda w: F.xxhash64(w))


def _bin(h: Column, buckets: int) -> Column:
    """``buckets`` is a power of two."""
    return h.bitwiseAND(F.lit(buckets - 1).cast("long")).cast("int")


def bin_weights(docs: DataFrame, trusted: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    """One row: array of ``buckets`` log-likelihood ratios, from the whole corpus.

    The grams are counted where they are read, so the shuffle holds at most ``buckets`` rows a task.
    """
    marked = docs.select("doc_id", _hashes("text").alias("h")).join(
        F.broadcast(trusted.select("doc_id", F.lit(1).alias("good"))), "doc_id", "left"
    )
    following = F.slice("h", F.lit(2), F.greatest(F.size("h") - 1, F.lit(0)))
    pairs = marked.select(F.coalesce("good", F.lit(0)).cast("long").alias("good"), F.inline(F.arrays_zip(F.col("h").alias("a"), following.alias("b"))))
    pairs = pairs.toDF("good", "a", "b").select("good", _bin(F.col("a"), buckets).alias("one"), F.when(F.col("b").isNotNull(), _bin(F.xxhash64("a", "b"), buckets)).alias("two"))
    counts = (
        pairs.select("good", F.expr("stack(2, one, two)").alias("bin"))
        .filter("bin is not null")  # a document's last word begins no pair
        .groupBy("bin")
        .agg(F.count(F.lit(1)).alias("raw"), F.sum("good").alias("good"))
    )
    spark = docs.sparkSession
    full = spark.range(buckets).select(F.col("id").cast("int").alias("bin")).join(F.broadcast(counts), "bin", "left")
    ordered = full.groupBy().agg(
        F.array_sort(F.collect_list(F.struct("bin", F.coalesce("raw", F.lit(0)).alias("raw"), F.coalesce("good", F.lit(0)).alias("good")))).alias("c")
    )
    total = lambda name: F.aggregate("c", F.lit(0).cast("long"), lambda a, x: a + x[name])
    sums = ordered.select("c", total("raw").alias("all_raw"), total("good").alias("all_good"))
    rate = lambda x, name: F.log((x[name] + F.lit(SMOOTHING)) / (F.col(f"all_{name}") + F.lit(SMOOTHING * buckets)))
    return sums.select(
        F.transform("c", lambda x: F.when(F.col("all_good") == 0, F.lit(0.0)).otherwise(rate(x, "good") - rate(x, "raw"))).alias("weights")
    )


def _repeat_words(n: str, grams: str) -> Column:
    """Word positions within three-word windows that occur twice or more; sorts only where a window repeats."""
    by_hash = F.sort_array(F.transform(grams, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    twin = lambda s: F.sort_array(
        F.array_compact(
            F.transform(s, lambda x, j: F.when((j > 0) & (F.get(s, j - 1)["h"] == x["h"]) | (F.get(s, j + 1)["h"] == x["h"]), x["i"]))
        )
    )
    start = F.struct(F.lit(-3).alias("last"), F.lit(0).cast("long").alias("covered"))
    step = lambda a, x: F.struct(x.alias("last"), (a["covered"] + F.least(F.lit(3), x - a["last"])).alias("covered"))
    # wrapped in one-element arrays so that each sorted array is computed once
    covered = F.transform(F.array(by_hash), lambda s: F.aggregate(twin(s), start, step)["covered"])
    return F.when((F.col(n) < 3) | (F.size(F.array_distinct(grams)) == F.size(grams)), F.lit(0).cast("long")).otherwise(F.get(covered, F.lit(0)))


def _judged(docs: DataFrame, carried: Column, labels: DataFrame, buckets: int, threshold: float, max_trusted: int) -> DataFrame:
    """``carried`` as column ``row`` beside its verdict.

    Two scans of the text and no shuffle of documents; the weights (``buckets`` doubles) come as a scalar subquery.
    """
    text = F.coalesce("text", F.lit(""))
    lines = F.filter(F.split(F.col("text"), "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    weights = bin_weights(docs, trusted_ids(labels, max_trusted), buckets).scalar()
    base = docs.select(carried.alias("row"), text.alias("text")).select("row", "text", words(F.col("text")).alias("w"), lines.alias("lines"))
    base = base.select("*", F.transform("w", lambda w: F.xxhash64(w)).alias("h"))
    base = base.select(
        "row",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        F.when(F.col("text").rlike(r"[#*$%&|<>]"), F.length("text") - F.length(F.regexp_replace("text", r"[#*$%&|<>]", ""))).otherwise(0).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.slice(F.transform("h", lambda h, i: F.xxhash64(h, F.get("h", i + 1), F.get("h", i + 2))), F.lit(1), F.greatest(F.size("h") - 2, F.lit(0))).alias("grams"),
        "h",
    )
    base = base.withColumn("weights", weights)
    gain = lambda h: F.get("weights", _bin(h, buckets))
    pair = lambda h, i: F.when(i + 1 < F.size("h"), gain(F.xxhash64(h, F.get("h", i + 1)))).otherwise(0.0)
    total = F.aggregate(F.transform("h", lambda h, i: gain(h) + pair(h, i)), F.lit(0.0), lambda a, x: a + x)
    out = base.select(
        "row", "n_words", "word_chars", "n_symbols", "n_dup_lines", _repeat_words("n_words", "grams").alias("n_repeat_words"),
        F.when(F.col("n_words") == 0, F.lit(0.0)).otherwise(total / (2 * F.col("n_words") - 1)).alias("score"),
    )
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return out.withColumn("base_failed", failed).withColumn("kept", ~F.col("base_failed") & (F.col("score") >= threshold))


def judge(docs: DataFrame, labels: DataFrame, buckets: int = BUCKETS, threshold: float = THRESHOLD, max_trusted: int = MAX_TRUSTED) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text): doc_id, the base counts, score, base_failed and kept."""
    out = _judged(docs, F.struct("doc_id"), labels, buckets, threshold, max_trusted)
    return out.select("row.doc_id", *[c for c in out.columns if c != "row"])


def keep_good(docs: DataFrame, labels: DataFrame, buckets: int = BUCKETS, threshold: float = THRESHOLD, max_trusted: int = MAX_TRUSTED) -> DataFrame:
    """The rows of ``docs`` that ``judge`` keeps, with all their columns; each verdict stays beside its row, so nothing is joined."""
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    judged = _judged(docs, whole, labels, buckets, threshold, max_trusted)
    return judged.select("row", settled(F.col("kept")).alias("kept")).filter("kept").select("row.*")
