"""Quality rules: hard base rules, then divergence of a text's histograms from its language's.

Two histograms per text: shares of character classes (upper, lower and other letters, digits, blanks, sentence marks,
table and markup symbols, the rest) and shares of its language's common words (with all other words as one class). Each is
compared with the mean histogram of all base-passing texts of the same `lang` by the Jensen-Shannon distance (base 2, 0 to
1). A text is rejected if its character distance is over `chars_limit`, or its word distance is over `words_limit`; texts of
fewer than `least_chars` characters or `least_words` words are not judged on that histogram, as short ones diverge by
chance. The references come from all documents, in one aggregation of a few sums per language.

All columns are native expressions. A null text has no words, so it fails the base rules, as every text under 50 words
does; a null lang is a language of its own with the union of the word lists; rows repeating an id are judged one by one.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from meshcut.llm import common

#: Common function words per language.
COMMON_WORDS = {
    "en": "the of and to in a is that it was for on are as with his they at be this from have or by one had not but what all were when we there can an your which their".split(),
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach wird bei einer um am sind noch wie einem über".split(),
    "fr": "de la le et les des en un du une que est pour qui dans a par plus pas au sur ne se ce il sont avec son sa aux ou elle mais comme nous leur entre deux".split(),
    "es": "de la que el en y a los se del las un por con no una su para es al lo como más o pero sus le ha me si sin sobre este ya entre cuando todo esta ser".split(),
}
#: The symbols that the base rule counts.
SYMBOLS = "#*$%&|<>"


def in_language(words: list[str]) -> tuple[list[str], list[str | None]]:
    """The words in order, and a table that holds each at its XXH64 modulo the table's length (the least that has room)."""
    words = sorted(set(words))
    place = [int(np.uint64(xxhash.xxh64_intdigest(w.encode(), 42)).view(np.int64)) for w in words]
    size = next(n for n in range(len(words), 1 << 30) if len({p % n for p in place}) == len(words))
    table: list[str | None] = [None] * size
    for w, p in zip(words, place):
        table[p % size] = w
    return words, table


def word_counts(lang: str, tokens: str) -> Column:
    """How often each common word of the text's language is among the lower-case tokens, in alphabetical order.

    The hits are sorted together with one of each common word, so each word ends a run there; runs give the counts.
    """
    every = [w for x in COMMON_WORDS.values() for w in x]

    def counts(words: list[str]) -> Column:
        words, table = in_language(words)
        held, size = F.array(*map(F.lit, table)), F.lit(len(table)).cast("long")
        return F.sort_array(F.concat(F.filter(tokens, lambda w: F.get(held, F.pmod(F.xxhash64(w), size).cast("int")) == w), F.array(*map(F.lit, words))))

    out = F.lit(None)
    for k, words in COMMON_WORDS.items():
        out = F.when(F.col(lang) == k, counts(words)).otherwise(out)
    return F.coalesce(out, counts(every))


def measured(docs: DataFrame, *keep: str) -> DataFrame:
    """keep, the base columns, and the two histograms (`_chars`, `_words`, arrays of shares) with the characters' number.

    Each step takes whole arrays or strings at a time where it can: lambdas over words are few and short.
    """
    blanks = " \t\n\x0b\x0c\r"
    one = docs.select(*keep, F.col("lang").alias("_lang"), F.coalesce(F.col("text"), F.lit("")).alias("_text"))
    one = one.withColumn("_bare", F.btrim("_text", F.lit(blanks)))
    two = one.select(
        "*",
        F.when(F.col("_bare") == "", F.array().cast("array<string>")).otherwise(F.split("_bare", common.BLANK + "+")).alias("_w"),
        F.when(F.col("_bare") == "", F.array().cast("array<string>")).otherwise(F.split(F.lower("_bare"), f"[,.;:!?]*(?:{common.BLANK}+|$)")).alias("_lower"),
        F.filter(F.split("_text", "\n"), lambda x: F.btrim(x, F.lit(blanks)) != "").alias("_lines"),
        F.length("_text").alias("_n"), F.regexp_count("_text", F.lit(r"\p{Lu}")).alias("_upper"),
        F.regexp_replace("_text", r"\p{L}+", "").alias("_rest"),
    ).withColumns({"_marks": F.regexp_replace("_rest", common.BLANK + "+", ""), "_size": F.size("_w")})
    rest = F.lit(1 << 30)
    three = two.select(
        "*", word_counts("_lang", "_lower").alias("_runs"),
        F.transform(F.arrays_zip("_w", F.slice("_w", 2, rest).alias("b"), F.slice("_w", 3, rest).alias("c")), lambda x: F.xxhash64(x)).alias("_all"),
    ).withColumn("_t", F.slice("_all", F.lit(1), F.greatest(F.lit(0), F.col("_size") - 2)))
    # a triple repeats if a neighbour in hash order equals it
    order = three.withColumn("_order", F.when(F.size("_t") > F.size(F.array_distinct("_t")), F.sort_array(F.arrays_zip(F.col("_t").alias("h"), F.sequence(F.lit(0), F.size("_t") - 1).alias("i")))))
    twice = F.filter("_order", lambda x, k: (x["h"] == F.get("_order", k + 1)["h"]) | (x["h"] == F.get("_order", k - 1)["h"]))
    four = order.withColumn("_again", F.sort_array(F.transform(twice, lambda x: x["i"])))
    gaps = F.transform("_again", lambda i, k: F.least(F.lit(3), F.coalesce(F.get("_again", k + 1) - i, F.lit(3))))
    covered = F.when(F.size("_again") > 0, F.aggregate(gaps, F.lit(0), lambda a, x: a + x)).otherwise(0)
    ends = F.filter(F.transform("_runs", lambda w, k: F.when(w.eqNullSafe(F.get("_runs", k + 1)), -1).otherwise(k)), lambda k: k >= 0)
    five = four.select(
        *keep, "_lang", F.col("_size").cast("long").alias("n_words"), F.length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        F.regexp_count("_marks", F.lit(f"[{SYMBOLS}]")).cast("long").alias("n_symbols"),
        (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"),
        covered.cast("long").alias("n_repeat_words"), ends.alias("_ends"), "_n", "_upper", "_rest", "_marks",
    )
    only = lambda chars: F.regexp_count("_marks", F.lit(chars))
    n, rest, marks = F.col("_n"), F.length("_rest"), F.length("_marks")
    classes = [F.col("_upper"), n - rest - F.col("_upper"), only("[0-9]"), rest - marks, only(r"[.,;:!?'\"()-]"), only(r"[#*$%&|<>=_{}/\\\[\]~^@+]")]
    hits = F.transform("_ends", lambda e, k: e - F.coalesce(F.get("_ends", k - 1), F.lit(-1)) - 1)
    six = five.select(
        *keep, "_lang", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "_n",
        F.array(*classes, only(r"[^0-9.,;:!?'\"()#*$%&|<>=_{}/\\\[\]~^@+-]")).alias("_classes"),
        F.concat(hits, F.array(F.col("n_words").cast("int") + F.size("_ends") - 1 - F.element_at("_ends", -1))).alias("_hits"),
    )
    share = lambda counts, total: F.transform(counts, lambda x: F.when(F.col(total) > 0, x / F.col(total)).otherwise(0.0))
    return six.select(
        *keep, "_lang", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        share("_classes", "_n").alias("_chars"), share("_hits", "n_words").alias("_words"), F.col("_n").alias("_total"),
        ((F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))).alias("base_failed"),
    )


def divergence(p: str, q: str) -> Column:
    """Jensen-Shannon distance, base 2."""
    side = lambda a, b: F.when(a > 0, a * F.log2(2 * a / (a + b))).otherwise(0.0)
    part = F.zip_with(p, q, lambda a, b: side(a, b) + side(b, a))
    return F.sqrt(F.greatest(F.lit(0.0), F.aggregate(part, F.lit(0.0), lambda a, x: a + x) / 2))


def references(rows: DataFrame) -> DataFrame:
    """(_lang, _char_ref, _word_ref): mean shares of base-passing texts, a row per language."""
    n, m = 7, 1 + len({w for x in COMMON_WORDS.values() for w in x})
    good = rows.where("not base_failed")
    sums = good.groupBy("_lang").agg(*(F.avg(F.get("_chars", F.lit(k))).alias(f"c{k}") for k in range(n)), *(F.avg(F.get("_words", F.lit(k))).alias(f"w{k}") for k in range(m)))
    rounded = lambda names: F.array_compact(F.array(*(F.round(x, 9) for x in names)))
    return sums.select("_lang", rounded([f"c{k}" for k in range(n)]).alias("_char_ref"), rounded([f"w{k}" for k in range(m)]).alias("_word_ref"))


def judged(docs: DataFrame, *keep: str, chars_limit: float = 0.24, words_limit: float = 0.27, least_chars: int = 200, least_words: int = 100) -> DataFrame:
    common.prepare(docs.sparkSession)
    rows = common.written(measured(docs, *keep), "quality")
    ref = references(rows)
    out = rows.join(ref, rows["_lang"].eqNullSafe(ref["_lang"]), "left").drop(ref["_lang"])
    out = out.withColumns({"char_distance": F.round(divergence("_chars", "_char_ref"), 6), "word_distance": F.round(divergence("_words", "_word_ref"), 6)})
    odd = ((F.col("_total") >= least_chars) & (F.col("char_distance") > chars_limit)) | ((F.col("n_words") >= least_words) & (F.col("word_distance") > words_limit))
    return out.withColumn("kept", ~F.col("base_failed") & ~F.coalesce(odd, F.lit(False))).drop("_lang", "_chars", "_words", "_total", "_char_ref", "_word_ref")


def quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(common.table(spark, sf_dir, "documents"), "doc_id")
