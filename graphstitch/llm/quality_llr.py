"""Quality rules: hashed n-gram log-likelihood ratio of trusted text against the raw corpus.

Word n-grams up to `order` are hashed to buckets. Two multinomials are estimated over the buckets: the raw one from every
document, the trusted one from a bounded sample of documents labelled as good (`trusted_docs`). A document's score is the
mean over its n-grams of log p_trusted - log p_raw; it is kept when the score reaches `threshold` and no base rule fails.
Everything is built from DataFrame functions; the bucket table (a fixed number of counts) is the only thing on the driver.

Defined results: null and blank texts have no words, score 0 and fail the base rule; repeated rows are each reported;
null doc_id is kept as such; an empty table gives an empty result; further columns of the input are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphstitch.llm.common import blank_words, without

BUCKETS = 1 << 16
#: Bound of the sample of trusted labelled documents.
TRUSTED_DOCS = 20_000
THRESHOLD = -0.08
PRIOR = 20.0
#: Longest n-gram.
ORDER = 2
SYMBOLS = "#*$%&|<>"


def grams_of(words: str, order: int):
    """Native: 64-bit names of the unigrams of an array column, and of the bigrams too when order is 2."""
    one = F.transform(words, lambda w: F.xxhash64(w))
    if order == 1:
        return one
    return F.concat(one, F.transform(F.slice(words, F.lit(1), F.greatest(F.size(words) - 1, F.lit(0))), lambda w, i: F.xxhash64(w, F.get(words, i + 1))))


def trusted_ids(labels: DataFrame, most: int = TRUSTED_DOCS) -> DataFrame:
    """At most `most` ids of documents labelled good, chosen by hash: bounded, so it may be broadcast."""
    ids = labels.where("quality = 1 and doc_id is not null").select("doc_id").distinct()
    return ids.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)


def ratio_table(docs: DataFrame, labels: DataFrame, buckets: int = BUCKETS, trusted_docs: int = TRUSTED_DOCS, order: int = ORDER) -> list[float]:
    """Log ratio of each bucket; `PRIOR` counts at the raw rate draw rare buckets to 0, so a document is not held to be worse
    for n-grams that the trusted sample just happens to lack. Counts are combined before the shuffle: a row per bucket and task."""
    good = trusted_ids(labels, trusted_docs).withColumn("_good", F.lit(1))
    words = docs.select("doc_id", blank_words(F.col("text")).alias("w")).join(F.broadcast(good), "doc_id", "left")
    names = words.select("_good", F.explode("w").alias("g")) if order == 1 else words.select("_good", F.explode(grams_of("w", order)).alias("g"))
    name = F.xxhash64("g") if order == 1 else F.col("g")
    rows = names.groupBy(F.pmod(name, F.lit(buckets)).cast("int").alias("b")).agg(F.count("*").alias("raw"), F.count("_good").alias("good")).collect()
    raw, trusted = sum(r["raw"] for r in rows), sum(r["good"] for r in rows)
    if not trusted:
        return [0.0] * buckets
    table, share = [0.0] * buckets, trusted / raw
    for r in rows:
        table[r["b"]] = math.log((r["good"] + PRIOR) / (r["raw"] * share + PRIOR))
    return table


def table_column(table: list[float]):
    """The table as one constant array in the plan."""
    return F.from_json(F.lit("[" + ",".join(map(repr, table)) + "]"), "array<double>")


def base_columns(docs: DataFrame) -> DataFrame:
    """Adds w (words) and the base counts n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    d = docs.withColumns({"w": blank_words(F.col("text")), "_lines": lines})
    d = d.withColumns(
        {
            "n_words": F.size("w").cast("long"),
            "word_chars": F.char_length(F.array_join("w", "")).cast("long"),
            "n_symbols": (F.octet_length(text) - F.octet_length(without(text, SYMBOLS))).cast("long"),
            "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
            "_x": F.transform("w", lambda w: F.xxhash64(w)),
        }
    ).drop("_lines")
    # a 64-bit name for each window of five words
    windows = F.transform(F.sequence(F.lit(0), F.size("_x") - 5), lambda i: F.xxhash64(*[F.get("_x", i + k) for k in range(5)]))
    d = d.withColumn("_h", F.when(F.size("_x") >= 5, windows).otherwise(F.array().cast("array<bigint>")))
    # only texts with a repeated window pay for the sort that finds the places
    placed = F.sort_array(F.transform("_h", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    d = d.withColumn("_s", F.when(F.size(F.array_distinct("_h")) < F.size("_h"), placed)).drop("_h")
    s = F.col("_s")
    again = F.filter(s, lambda x, j: F.coalesce(F.get(s, j - 1)["h"] == x["h"], F.lit(False)) | F.coalesce(F.get(s, j + 1)["h"] == x["h"], F.lit(False)))
    d = d.withColumn("_p", F.when(s.isNotNull(), F.sort_array(F.transform(again, lambda x: x["i"])))).drop("_s")
    p = F.col("_p")
    # the first window adds five words, each later one what it does not share with the window before
    gaps = F.aggregate(F.transform(p, lambda x, j: F.when(j == 0, 5).otherwise(F.least(F.lit(5), x - F.get(p, j - 1)))), F.lit(0), lambda a, g: a + g)
    return d.withColumn("n_repeat_words", F.coalesce(F.when(F.size(p) > 0, gaps), F.lit(0)).cast("long")).drop("_p")


def _verdict(docs: DataFrame, labels: DataFrame, threshold: float, buckets: int, trusted_docs: int, order: int) -> DataFrame:
    table = table_column(ratio_table(docs.select("doc_id", "text"), labels, buckets, trusted_docs, order))
    d = base_columns(docs)
    d = d.withColumn("_x", grams_of("w", order)) if order > 1 else d
    total = F.aggregate("_x", F.lit(0.0), lambda a, h: a + F.get(table, F.pmod(h, F.lit(buckets)).cast("int")))
    d = d.withColumn("score", F.when(F.size("_x") > 0, total / F.size("_x")).otherwise(0.0))
    d = d.withColumn("base_failed", (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words")))
    d = d.withColumn("kept", ~F.col("base_failed") & (F.col("score") >= threshold)).drop("w", "_x")
    # a generator that a later filter is not pushed through: below it, the filter would make the whole chain of columns anew
    return d.select(F.inline(F.array(F.struct(*d.columns))))


def assess(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, buckets: int = BUCKETS, trusted_docs: int = TRUSTED_DOCS, order: int = ORDER) -> DataFrame:
    """doc_id, text, the base counts, score, base_failed and kept; the other columns of `docs` go."""
    return _verdict(docs.select("doc_id", "text"), labels, threshold, buckets, trusted_docs, order)


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, buckets: int = BUCKETS, trusted_docs: int = TRUSTED_DOCS, order: int = ORDER) -> DataFrame:
    """The documents that pass, with all their columns: the verdict is computed beside the row, without a join."""
    whole = docs.select("doc_id", "text", F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"))
    return _verdict(whole, labels, threshold, buckets, trusted_docs, order).where("kept").select("_row.*")
