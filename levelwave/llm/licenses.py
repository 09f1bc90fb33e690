"""Licence scan by ordered signature rules behind a keyword prefilter (DataFrame operations only).

A cheap test on the raw text finds the few documents that can hold a statement. Only these are normalised, joined with
the rules whose keyword they contain, and held against those patterns. Overlapping detections are resolved by priority:
one that lies within another of a higher priority, or within a longer or earlier one of its own, is dropped.
"""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .license_rules import BASE_PHRASES, rules
from .shared import documents, stored

QUERY = "op3_license_rules"
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"  # of a text with A-Z lower-cased
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Letters of a word from which on it is looked for anywhere in a text. A shorter one stands in too many other words, so it
#: must stand by itself, or before a version.
PLAIN = 6
#: Strength of a detection by priority.
WEIGHT = {3: 1.0, 2: 0.8, 1: 0.5}


def ascii_lower(text: Column) -> Column:
    """A-Z to lower case and nothing else."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def needed(pattern: str) -> str:
    """The pattern without its alternatives and optional groups: what every match has."""
    while m := re.search(r"\(\?:([^()]*)\)(\??)", pattern):
        pattern = pattern[: m.start()] + ("\0" if m[2] or "|" in m[1] else m[1]) + pattern[m.end() :]
    return pattern


def gate() -> tuple[set[tuple[str, ...]], set[str]]:
    """(sets of words that a text has anywhere, words that it has by themselves), of which each rule and base phrase needs
    one: the licence word if all its matches have it, else the words of its keyword."""
    anywhere, alone = set(), set()
    for keyword, pattern in [r[2:4] for r in rules()] + [(phrase, phrase) for phrase, _ in BASE_PHRASES]:
        core, words = needed(pattern), keyword.split()
        long = tuple(w for w in words if len(w) >= PLAIN)
        if "licen" in core:
            anywhere.add(("licen",))
        elif long or not re.search(rf"(?<![^ \0]){words[0]}(?![a-uw-z])", core):
            anywhere.add(long or tuple(words))
        else:
            alone.add(words[0])
    return anywhere, alone


def gated(low: Column) -> Column:
    """Whether any rule or base phrase may match; never false where one does. Lower-casing other letters than A-Z can't
    hide one, and can only let more through. low is the lower-cased text, as a column of its own so that it is made once.
    Plain substring tests cost far less than a pattern, so they come first."""
    anywhere, alone = gate()
    plain = [reduce(lambda a, b: a & b, [F.contains(low, F.lit(w)) for w in words]) for words in sorted(anywhere, key=lambda w: (w != ("licen",), w))]
    heads = sorted({w[0] for w in alone})
    by_head = "|".join(f"{h}(?:{'|'.join(sorted(w[1:] for w in alone if w[0] == h))})" for h in heads)
    return reduce(lambda a, b: a | b, plain) | low.rlike(rf"(?<![0-9a-z])(?:{by_head})(?![a-uw-z])")


def word_count(text: Column) -> Column:
    """Words of a text: what lies between gaps, less an empty piece at either end."""
    gap = r"^[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]"  # capitals belong to words; lower-casing moves no bounds
    ends = F.substring(text, 1, 1).rlike(gap).cast("long") + F.substring(text, -1, 1).rlike(gap).cast("long")
    return F.when(text == "", F.lit(0)).otherwise(F.size(F.split(text, gap[1:] + "+", -1)) - ends).cast("long")


def scan(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(documents, detections), both stored.

    documents: _row, doc_id, n_words, and for each base phrase the places where it stands (word numbers from 0).
    detections: _row, label, rule, priority, first, last (words from 0, both ends within) that suppression left.
    """
    spark, found = docs.sparkSession, rules()
    keywords = sorted({r[2] for r in found})
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("_text")).withColumn("_row", F.monotonically_increasing_id())
    norm = F.trim(F.regexp_replace(ascii_lower(F.col("_text")), BETWEEN, " "))
    rows = rows.select("_row", "doc_id", "_text", F.lower("_text").alias("_low"))
    rows = rows.select("_row", "doc_id", word_count(F.col("_text")).alias("n_words"), F.when(gated(F.col("_low")), norm).alias("norm"))
    padded = F.concat(F.lit(" "), F.col("norm"), F.lit(" "))
    places = [F.when(F.contains(padded, F.lit(f" {phrase} ")), _places(phrase)).otherwise(F.array().cast("array<int>")).alias(f"at_{i}") for i, (phrase, _) in enumerate(BASE_PHRASES)]
    rows = stored(rows.select("*", *places), "license-words")

    table = spark.createDataFrame([(i, label, key, rf"(?<![^ ])(?:{pattern})(?![^ ])", priority) for i, label, key, pattern, priority in found], "rule int, label string, keyword string, pattern string, priority int")
    texts = rows.where("norm is not null and norm <> ''").select("_row", "norm")
    keys = F.filter(F.array(*[F.lit(k) for k in keywords]), lambda k: F.contains(F.col("norm"), k))
    tried = texts.select("_row", "norm", F.explode(keys).alias("keyword")).join(F.broadcast(table), "keyword")  # a fixed number of rules
    tried = tried.withColumn("hits", F.regexp_extract_all("norm", F.col("pattern"), F.lit(0))).where(F.size("hits") > 0)
    words = lambda s: F.when(F.length(F.trim(s)) == 0, F.lit(0)).otherwise(F.size(F.split(F.trim(s), " ")))
    gaps = F.transform(F.split("norm", F.col("pattern"), -1), words)
    spans = F.transform("hits", words)
    # Numbered pieces: the words before a hit are those of all earlier gaps and hits, and of its own gap.
    pieces = tried.select("_row", "rule", "label", "priority", F.posexplode(F.arrays_zip(gaps.alias("gap"), spans.alias("n"))).alias("nth", "s"))
    pieces = pieces.select("_row", "rule", "label", "priority", "nth", F.col("s.gap").alias("gap"), F.col("s.n").alias("n")).where("n is not null").repartition("_row")
    before = Window.partitionBy("_row", "rule").orderBy("nth").rowsBetween(Window.unboundedPreceding, -1)
    first = (F.col("gap") + F.coalesce(F.sum(F.col("gap") + F.col("n")).over(before), F.lit(0))).cast("int")
    each = pieces.withColumn("first", first).select("_row", "rule", "label", "priority", "first", (F.col("first") + F.col("n") - 1).alias("last")).where("last >= first")
    order = Window.partitionBy("_row").orderBy("first", F.desc("last"), F.desc("priority"), "rule").rowsBetween(Window.unboundedPreceding, -1)
    held = reduce(lambda a, b: a | b, [(F.col("priority") <= p) & (F.coalesce(F.max(F.when(F.col("priority") >= p, F.col("last"))).over(order), F.lit(-1)) >= F.col("last")) for p in (1, 2, 3)])
    # Rows of equal span come with the higher priority first, so whatever holds a detection stands before it.
    return rows, stored(each.withColumn("_held", held).where("not _held").drop("_held"), "license-detections")


def _places(phrase: str) -> Column:
    """Word numbers at which the phrase stands in norm. The words are bound once, as the one element of an array: an
    expression inside a lambda would split the text anew at every word."""
    wanted = phrase.split()

    def within(parts: Column) -> Column:
        match = lambda i: reduce(lambda a, b: a & b, [F.coalesce(F.get(parts, i + k) == w, F.lit(False)) for k, w in enumerate(wanted)])
        return F.filter(F.sequence(F.lit(0), F.size(parts) - 1), match)

    return F.get(F.transform(F.array(F.split("norm", " ")), within), F.lit(0))


def license_scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score and n_detections of every row.

    n_base counts the places of all base phrases; first_word and last_word are the least and greatest of them, null if
    there are none. labels has the base labels too. A null or empty text has no words, empty label lists and score 0;
    repeated rows are scanned alike; other columns aren't read.
    """
    rows, detections = scan(docs)
    every = F.concat(*[F.col(f"at_{i}") for i in range(len(BASE_PHRASES))])
    base = F.array_compact(F.array(*[F.when(F.size(f"at_{i}") > 0, F.lit(label)) for i, (_, label) in enumerate(BASE_PHRASES)]))
    best = reduce(lambda a, b: F.greatest(a, b), [F.when(F.col("priority") == p, F.lit(w)).otherwise(0.0) for p, w in WEIGHT.items()])
    more = detections.groupBy("_row").agg(F.collect_set("label").alias("extra"), F.max(best).alias("strength"), F.count("*").alias("n_detections"))
    out = rows.drop("norm").join(more, "_row", "left")
    labels = F.array_sort(F.array_union(base, F.coalesce("extra", F.array().cast("array<string>"))))
    score = F.greatest(F.coalesce("strength", F.lit(0.0)), F.when(F.size(every) > 0, F.lit(0.8)).otherwise(0.0))
    return out.select(
        "doc_id", "n_words", F.size(every).cast("long").alias("n_base"), F.array_min(every).cast("long").alias("first_word"), F.array_max(every).cast("long").alias("last_word"),
        F.array_join(F.array_sort(base), ",").alias("base_labels"), F.array_join(labels, ",").alias("labels"), score.alias("score"), F.coalesce("n_detections", F.lit(0)).alias("n_detections"))


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(documents(spark, sf_dir))
