"""Benchmark decontamination by winnowing, with DataFrame functions only.

Of the 5-word hashes of a text, the least in each window of nine consecutive ones is kept: 5 + 9 - 1 = 13, so any span of 13
words that a document shares with an item keeps the same fingerprint on both sides. Fingerprints of documents and items are
joined; at each hit the words are compared, up to eight to either side, and a hit counts when 13 or more in a row agree.
The eight are enough: every 13-word window inside a shared span holds a kept fingerprint of its own.
Items of fewer words are one window each; they are found by their first word and compared whole.

Scale: one scan and one exchange of small rows. The items' fingerprints are broadcast below a checked size. Beyond it, keys
and places alone are exchanged, and words are fetched for the documents that met an item; the row that stands for a document
itself takes no part in that join. Hash and place are packed in one number (33 + 30 bits); a chance equality is refused by the comparison.

Defined results: null and blank texts have no words and are clean; blank items have no window; items with a null id count
for hits but not in n_items; rows of one doc_id, or of none, are told apart by a 64-bit hash of their text; items repeated under one id count once; repeated documents are each reported; an empty
benchmark leaves all documents clean; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphstitch.llm.common import term_words

SPAN, GRAM = 13, 5
KEEP = SPAN - GRAM + 1
#: Bytes of item fingerprints and words that may be broadcast.
BROADCAST_BYTES = 64 << 20
_PLACE = (1 << 30) - 1


def fingerprints(texts: DataFrame, words: str, *more: str) -> DataFrame:
    """Native: `more` columns, n (how many words), and a row for each window of the words with key, its least hash, and at, the
    place of it; one more row for each text itself has key -1. A fingerprint comes once for each window that keeps it.

    The hashes are an array that is made once; windows are taken from it row by row, in generated code, so that nothing but
    rows that meet an item is ever written out."""
    n = F.size(words)
    texts = texts.withColumn("_h", F.transform(words, lambda x: F.xxhash64(x)))
    packed = F.transform(
        F.slice("_h", F.lit(1), F.greatest(n - GRAM + 1, F.lit(0))),
        lambda x, i: F.xxhash64(x, *[F.get("_h", i + k) for k in range(1, GRAM)]).bitwiseAND(F.lit(~_PLACE)).bitwiseOR(i.cast("long")),
    )
    none = F.array().cast("array<bigint>")
    texts = texts.withColumn("_f", F.when(n >= SPAN, packed).otherwise(none)).drop("_h")
    texts = texts.select(*more, words, "_f", n.alias("n"), F.explode(F.sequence(F.lit(-1), F.greatest(F.size("_f") - KEEP, F.lit(-1)))).alias("_i"))
    least = F.when(F.col("_i") < 0, F.lit(-1).cast("long")).otherwise(F.least(*[F.get("_f", F.col("_i") + k) for k in range(KEEP)]))
    texts = texts.select(*more, words, "n", least.alias("_m"))
    # packed values have any sign; -1 would mean 30 low bits all set, a place that no text reaches
    key = F.when(F.col("_m") == -1, F.col("_m")).otherwise(F.col("_m").bitwiseAND(F.lit(~_PLACE)))
    return texts.select(*more, words, "n", key.alias("key"), F.col("_m").bitwiseAND(F.lit(_PLACE)).cast("int").alias("at"))


def _reach(sign: int, origin: int):
    """How many words in a row agree, going from `origin` by `sign`, up to eight. Interpreted on the few rows that met: unrolled,
    the comparisons make code whose compilation takes more memory than the data."""
    same = F.transform(
        F.sequence(F.lit(0), F.lit(KEEP - 2)),
        lambda k: F.coalesce(F.get("cw", F.col("c") + origin + sign * k) == F.get("iw", F.col("iat") + origin + sign * k), F.lit(False)),
    )
    first = F.array_position(same, False).cast("int")
    return F.when(first == 0, F.lit(KEEP - 1)).otherwise(first - 1)


def _tokenised(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", F.xxhash64("text").alias("th"), term_words(F.col("text")).alias("w"))


def hits(docs: DataFrame, benchmark: DataFrame, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """A row per document and contaminated span: doc_id, th (the text's hash), n_words, item_id, a, b; and a row with null
    a, b for each document itself."""
    items = benchmark.select("item_id", term_words(F.col("text")).alias("iw")).where("size(iw) > 0").distinct()
    long = fingerprints(items.where(F.size("iw") >= SPAN), "iw", "item_id").where("key <> -1")
    long = long.select("item_id", "iw", "key", F.col("at").alias("iat")).distinct()
    short = items.where(F.size("iw") < SPAN).select("item_id", "iw", F.get("iw", F.lit(0)).alias("key"))
    size = long.agg(F.sum(F.octet_length(F.array_join("iw", " ")) + 64)).union(short.agg(F.sum(F.octet_length(F.array_join("iw", " ")) + 64))).collect()
    small = sum(r[0] or 0 for r in size) <= broadcast_bytes
    hint = F.broadcast if small else (lambda x: x)
    words = _tokenised(docs)
    # of the text, only the words around a fingerprint go on: cw, where the fingerprint starts at c. A long text may hold
    # thousands of hits, and each would carry all of it.
    lead = F.least(F.col("at"), F.lit(KEEP - 1))
    around = F.when(F.col("key") != -1, F.slice("w", F.col("at") - lead + 1, F.lit(2 * (KEEP - 1) + GRAM)))
    near = [F.col("doc_id"), F.col("th"), F.col("n"), F.col("key"), F.col("at"), lead.alias("c"), around.alias("cw")]
    fps = fingerprints(words, "w", "doc_id", "th")
    itself = F.col("key") == -1
    if small:
        # each document also carries one fingerprint, -1, that meets one row of no item: so it comes through the join
        self_row = docs.sparkSession.range(1).select(F.lit(None).cast(items.schema["item_id"].dataType).alias("item_id"), F.lit(None).cast("array<string>").alias("iw"), F.lit(-1).cast("long").alias("key"), F.lit(0).alias("iat"))
        met = fps.select(*near).join(F.broadcast(long.unionByName(self_row)), "key")
    else:
        keys = fps.where(~itself).select("doc_id", "th", "key", "at").distinct().join(long.select("key").distinct(), "key", "left_semi")
        keys = keys.select(F.col("doc_id").alias("_d"), F.col("th").alias("_t"), "key", "at")
        texts = words.select("doc_id", "th", "w", F.size("w").alias("n")).dropDuplicates(["doc_id", "th"])
        met = texts.join(keys, texts["doc_id"].eqNullSafe(keys["_d"]) & (texts["th"] == keys["_t"])).select(*near).join(long, "key")
        own = words.select("doc_id", "th", F.size("w").alias("n"), F.lit(-1).cast("long").alias("key"), F.lit(0).alias("at"), F.lit(0).alias("c"), F.lit(None).cast("array<string>").alias("cw"))
        met = met.unionByName(own, allowMissingColumns=True)
    core = F.slice("cw", F.col("c") + 1, F.lit(GRAM)) == F.slice("iw", F.col("iat") + 1, F.lit(GRAM))
    met = met.where((F.col("key") == -1) | core)
    met = met.withColumns({"l": F.when(F.col("key") == -1, 0).otherwise(_reach(-1, -1)), "r": F.when(F.col("key") == -1, 0).otherwise(_reach(1, GRAM))})
    met = met.where((F.col("key") == -1) | (F.col("l") + F.col("r") + GRAM >= SPAN))
    out = met.select(
        "doc_id", "th", F.col("n").cast("long").alias("n_words"), "item_id",
        F.when(~itself, F.col("at") - F.col("l")).alias("a"), F.when(~itself, F.col("at") + GRAM + F.col("r")).alias("b"),
    )
    if short.isEmpty():
        return out
    # a word carries the few words behind it that an item may have
    starts = words.select("doc_id", "th", "w", F.size("w").cast("long").alias("n_words"), F.explode(F.sequence(F.lit(0), F.size("w") - 1)).alias("at")).where("n_words > 0")
    each = starts.select("doc_id", "th", "n_words", "at", F.get("w", F.col("at")).alias("key"), F.slice("w", F.col("at") + 1, F.lit(SPAN - 1)).alias("cw"))
    met = each.join(hint(short), "key").where(F.slice("cw", F.lit(1), F.size("iw")) == F.col("iw"))
    return out.unionByName(met.select("doc_id", "th", "n_words", "item_id", F.col("at").alias("a"), (F.col("at") + F.size("iw")).alias("b")))


def assess(docs: DataFrame, benchmark: DataFrame, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated, and th."""
    found = hits(docs.select("doc_id", "text"), benchmark.select("item_id", "text"), broadcast_bytes)
    by_doc = found.groupBy("doc_id", "th").agg(
        F.max("n_words").alias("n_words"),
        F.count(F.when(F.col("a").isNull(), 1)).alias("_same"),
        F.sort_array(F.collect_set(F.when(F.col("a").isNotNull(), F.struct("a", "b")))).alias("_s"),
        F.sort_array(F.collect_set(F.col("item_id").cast("string"))).alias("_i"),
    )
    start = F.struct(F.lit(0).alias("n"), F.lit(0).alias("to"))
    merged = F.aggregate(
        "_s", start,
        lambda m, s: F.struct((m["n"] + F.greatest(F.lit(0), s["b"] - F.greatest(s["a"], m["to"]))).alias("n"), F.greatest(m["to"], s["b"]).alias("to")),
    )
    out = by_doc.select("doc_id", "th", "n_words", "_same", merged["n"].cast("long").alias("n_hit"), F.size("_i").cast("long").alias("n_items"), F.sha2(F.array_join("_i", ","), 256).alias("items_sha256"))
    out = out.withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))
    # equal rows of the input are as many again
    return out.withColumn("_k", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_same")))).drop("_k", "_same")


def keep_clean(docs: DataFrame, benchmark: DataFrame, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """The documents that are not contaminated, with all their columns."""
    bad = assess(docs, benchmark, broadcast_bytes).where("contaminated").select(F.col("doc_id").alias("_d"), F.col("th").alias("_t")).distinct()
    return docs.join(bad, docs["doc_id"].eqNullSafe(bad["_d"]) & (F.xxhash64(docs["text"]) == bad["_t"]), "left_anti")
