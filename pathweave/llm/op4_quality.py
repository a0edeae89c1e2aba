"""Quality rules with cross-document line frequency, in DataFrame operations only.

Each document is reduced to counts and to its lines (hash of the normalised line, words in it). A line's frequency is
the number of distinct documents (by text, so that copies count once) of a host that hold it; lines of more than
max_docs documents, and of more than max_share of the host's, are boilerplate and removed. A document whose remaining
words are fewer than min_left of its words is depleted and rejected.

Only hashes and counts are shuffled, never text. Frequencies are pre-aggregated before each shuffle; the line table
meets documents in a join that the adaptive planner may split.

Defined cases: null text has no words (and fails the base rules); null sources are one host; repeated rows stay rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathweave.llm import common as C

MAX_DOCS, MAX_SHARE, MIN_LEFT = 40, 0.001, 0.1
_WS = r"[\x20\x09-\x0D]+"
_BLANKS = " \t\n\x0b\x0c\r"


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, _WS), "")


def bound(value: Column, use) -> Column:
    """use(value) with value computed once for the row."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def repeated_words(words: Column) -> Column:
    """Words in three-word windows that occur at least twice in the text."""

    def count(w: Column) -> Column:
        grams = F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)))
        return F.when(F.size(w) < 4, F.lit(0)).otherwise(bound(grams, of_grams))

    def of_grams(g: Column) -> Column:
        placed = F.sort_array(F.transform(g, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(g)) == F.size(g), F.lit(0)).otherwise(bound(placed, of_sorted))

    def of_sorted(s: Column) -> Column:
        again = F.filter(s, lambda e, k: F.get(s, k - 1)["h"].eqNullSafe(e["h"]) | F.get(s, k + 1)["h"].eqNullSafe(e["h"]))
        return F.size(F.array_distinct(F.flatten(F.transform(again, lambda e: F.array(e["i"], e["i"] + 1, e["i"] + 2)))))

    return bound(words, count)


def normalised(line: Column) -> Column:
    """A line for comparison: lower case, digits as one, blanks run together."""
    return F.trim(F.regexp_replace(F.regexp_replace(C.ascii_lower(line), "[0-9]+", "0"), _WS, " "))


def measures(docs: DataFrame) -> DataFrame:
    """A row for each document: base counts, and its lines with a word as (hash, words)."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    base = docs.select(F.col("doc_id"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("host"), text.alias("text"))
    base = base.withColumn("lines", F.filter(F.split("text", "\n"), lambda x: F.length(F.translate(x, _BLANKS, "")) > 0))
    return base.select(
        "doc_id", "host",
        F.monotonically_increasing_id().alias("row"),
        F.xxhash64("text").alias("copy"),
        F.size(words_of(F.col("text"))).cast("long").alias("n_words"),
        F.length(F.translate("text", _BLANKS, "")).cast("long").alias("word_chars"),
        (F.length("text") - F.length(F.translate("text", "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        repeated_words(words_of(F.col("text"))).cast("long").alias("n_repeat_words"),
        F.transform("lines", lambda x: F.struct(F.xxhash64(normalised(x)).alias("line"), F.size(words_of(x)).alias("words"))).alias("lines"),
    )


def frequent_lines(measured: DataFrame, max_docs: int = MAX_DOCS, max_share: float = MAX_SHARE) -> DataFrame:
    """(host, line, docs): lines that more distinct documents of the host hold than the limits allow."""
    held = measured.select("host", "copy", F.explode(F.array_distinct(F.col("lines.line"))).alias("line")).distinct()
    often = held.groupBy("host", "line").agg(F.count(F.lit(1)).alias("docs")).filter(F.col("docs") > max_docs)
    sizes = measured.select("host", "copy").distinct().groupBy("host").agg(F.count(F.lit(1)).alias("host_docs"))
    return often.join(sizes, "host").filter(F.col("docs") > F.col("host_docs") * max_share).select("host", "line", "docs")


def judged(docs: DataFrame, max_docs: int = MAX_DOCS, max_share: float = MAX_SHARE, min_left: float = MIN_LEFT) -> DataFrame:
    """docs(doc_id, text, source) -> counts, base_failed, n_removed_words, removed_lines (their hashes), kept."""
    measured = C.settle(measures(docs), "quality-lines")
    often = C.settle(frequent_lines(measured, max_docs, max_share), "quality-often")
    lines = measured.select("row", "host", F.explode("lines").alias("l")).select("row", "host", "l.line", "l.words")
    # Words of frequent lines for each document; the sum by document is pre-aggregated before its shuffle.
    lost = lines.join(often.select("host", "line"), ["host", "line"]).groupBy("row").agg(F.sum("words").alias("lost"))
    base_failed = (F.col("n_words") < 50) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 50)
    out = measured.drop("lines").join(lost, "row", "left").withColumn("n_removed_words", F.coalesce("lost", F.lit(0)).cast("long"))
    out = out.withColumn("base_failed", base_failed)
    depleted = (F.col("n_words") - F.col("n_removed_words")) < F.col("n_words") * min_left
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", (~F.col("base_failed") & ~depleted).alias("kept"), "n_removed_words")


def cleaned(docs: DataFrame, max_docs: int = MAX_DOCS, max_share: float = MAX_SHARE) -> DataFrame:
    """docs with frequent lines taken out of text; all other columns and rows stay."""
    often = frequent_lines(measures(docs), max_docs, max_share)
    by_host = docs.withColumn("__row", F.monotonically_increasing_id()).withColumn("__host", F.coalesce(F.col("source").cast("string"), F.lit("")))
    by_host = C.settle(by_host, "quality-docs")
    hashes = F.transform(F.split("text", "\n"), lambda x: F.xxhash64(normalised(x)))
    hit = by_host.select("__row", F.col("__host").alias("host"), F.explode(F.array_distinct(hashes)).alias("line")).join(often, ["host", "line"])
    gone = hit.groupBy("__row").agg(F.collect_set("line").alias("__gone"))
    keep = F.filter(F.split("text", "\n"), lambda x: ~F.array_contains(F.col("__gone"), F.xxhash64(normalised(x))))
    text = F.when(F.col("__gone").isNull(), F.col("text")).otherwise(F.array_join(keep, "\n"))
    return by_host.join(gone, "__row", "left").withColumn("text", text).select(*docs.columns)


#: The counts and the base rule; the method's verdict rests on hashes of lines and is tested against brute force.
