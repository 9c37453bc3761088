"""Quality rules: base counts, and divergence from language references. DataFrame functions only.

References per language, from all documents: shares of six character classes, and shares of the `TOP_WORDS` most
frequent words plus the rest. A document is compared with its language's reference by Jensen-Shannon distance (base 2,
0 to 1). Guards, by length: the character test needs MIN_CHARS code points of the document, the word test MIN_WORDS of its
words, and both need a reference of MIN_REF_WORDS words, however rare the language is among the documents; a document
behind a guard is judged by the base rules alone.

A lack of the language's words is judged by each reference's own scale: `none`, the distance of a text without any of
its top words, and `share`, the part of its words that they make up. A document with a smaller share must stay below
none * (NONE_PART + NONE_SLACK / sqrt(expected top words)), and its number of top words must not lie so far below the
expected one that chance explains it with fewer than 2^-RARE_BITS (Chernoff's bound). Both give way for short texts
and for languages whose top words are rare. Rows without a language (null or empty) have no such words to lack.

Texts are read twice: once to count words by language, once for everything about a document, which is written as one
short row; the rest works on those rows.

Edge cases: null text has no words (base_failed); null lang is a language of its own; ties between frequent words go
by the word; repeated rows are judged alike; empty table: empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..runtime import fits_broadcast
from .common import SPACE, let, packed, unpacked, words, written

TOP_WORDS = 32
MIN_CHARS, MIN_WORDS, MIN_REF_WORDS = 200, 40, 2_000
MIN_WORD_SHARE = 0.001
MOST_CHAR_DISTANCE, MOST_WORD_DISTANCE = 0.30, 0.45
NONE_PART, NONE_SLACK, RARE_BITS = 0.4, 2.7, 17
SYMBOLS = "#*$%&|<>"
#: References (one row of TOP_WORDS words for each language) that may be broadcast.
BROADCAST_LANGS = 10_000


def _left(text: Column, drop: str) -> Column:
    return F.char_length(F.regexp_replace(text, drop, "")).cast("double")


def _repeat_words(w: Column) -> Column:
    """Words inside 5-word windows that occur twice or more. A hash finds candidates, the windows' text decides."""
    n = F.size(w)
    starts = F.sequence(F.lit(0), n - 5)
    hashes = let(w, lambda a: F.transform(starts, lambda i: F.xxhash64(*[F.get(a, i + k) for k in range(5)])))
    clash = let(hashes, lambda h: F.size(F.array_distinct(h)) < F.size(h))

    def covered(a: Column) -> Column:
        windows = F.sort_array(F.transform(starts, lambda i: F.struct(F.array_join(F.slice(a, i + 1, 5), " ").alias("s"), i.alias("i"))))
        same = lambda p, j, k: F.coalesce(F.get(p, j)["s"] == F.get(p, k)["s"], F.lit(False))
        at = let(windows, lambda p: F.sort_array(F.transform(F.filter(F.sequence(F.lit(0), F.size(p) - 1), lambda j: same(p, j, j - 1) | same(p, j, j + 1)), lambda j: F.get(p, j)["i"])))
        return let(at, lambda r: F.aggregate(F.sequence(F.lit(0), F.size(r) - 1), F.lit(0), lambda s, j: s + F.least(F.lit(5), F.coalesce(F.get(r, j + 1) - F.get(r, j), F.lit(5)))))

    return F.when((n >= 6) & clash, let(w, covered)).otherwise(0).cast("long")


def _classes(text: Column, word_chars: Column) -> Column:
    """Code points that are white space, capitals, digits, punctuation, symbols, and the rest."""
    # Plain small letters and blanks are most of a text: what is left without them is searched for the classes.
    odd = F.regexp_replace(text, f"[a-z{SPACE}]+", "")
    some = let(odd, lambda x: F.array(*[_left(x, drop) for drop in (r"\P{Lu}+", "[^0-9]+", r"""[^.,;:!?'"()-]+""", f"[^{SYMBOLS}]+")]))
    blank = (F.char_length(text) - word_chars).cast("double")
    return let(some, lambda x: F.concat(F.array(blank), x, F.array(F.char_length(text) - blank - F.aggregate(x, F.lit(0.0), lambda s, y: s + y))))


def _same_lang(rows: DataFrame, facts: DataFrame) -> DataFrame:
    """rows with the columns of facts (one row for each language); sent to all executors behind a count."""
    facts = facts.withColumnRenamed("lang", "ref_lang")
    side = F.broadcast(facts) if fits_broadcast(facts, BROADCAST_LANGS) else facts
    return rows.join(side, F.col("lang").eqNullSafe(F.col("ref_lang")), "left").drop("ref_lang")


def distance(p: Column, q: Column) -> Column:
    """Jensen-Shannon distance of two arrays of counts or shares."""
    share = lambda a: let(a, lambda x: F.transform(x, lambda v: v / F.aggregate(x, F.lit(0.0), lambda s, y: s + y)))
    part = lambda v, m: F.when(v > 0, v * F.log2(v / m)).otherwise(0.0)
    terms = F.zip_with(share(p), share(q), lambda a, b: (part(a, (a + b) / 2) + part(b, (a + b) / 2)) / 2)
    return F.sqrt(F.greatest(F.aggregate(terms, F.lit(0.0), lambda s, x: s + x), F.lit(0.0)))


def references(docs: DataFrame, text_column: str = "text", lang_column: str = "lang") -> DataFrame:
    """(lang, top array<string>, shares array<double>, share, none), from the words of all documents."""
    counts = docs.select(F.col(lang_column).alias("lang"), F.explode(words(F.col(text_column))).alias("word")).groupBy("lang", "word").agg(F.count(F.lit(1)).cast("double").alias("n"))
    totals = counts.groupBy("lang").agg(F.sum("n").alias("n_words")).withColumnRenamed("lang", "of_lang")
    ranked = counts.withColumn("k", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "word"))).where(F.col("k") <= TOP_WORDS)
    ranked = ranked.join(totals, F.col("lang").eqNullSafe(F.col("of_lang"))).where(F.col("n") >= MIN_WORD_SHARE * F.col("n_words"))
    tops = ranked.groupBy("lang").agg(F.sort_array(F.collect_list(F.struct("k", "word", "n"))).alias("t")).withColumnRenamed("lang", "top_lang")
    both = totals.join(tops, F.col("of_lang").eqNullSafe(F.col("top_lang")), "left").withColumnRenamed("of_lang", "lang")
    n = F.coalesce(F.col("t.n"), F.array().cast("array<double>"))
    both = both.select("lang", "n_words", F.coalesce(F.col("t.word"), F.array().cast("array<string>")).alias("top"), F.concat(n, F.array(F.col("n_words") - F.aggregate(n, F.lit(0.0), lambda s, x: s + x))).alias("shares"))
    none = distance(F.concat(F.transform("top", lambda x: F.lit(0.0)), F.array(F.lit(1.0))), F.col("shares"))
    return written(both.select("lang", "n_words", "top", "shares", (1 - F.element_at("shares", -1) / F.col("n_words")).alias("share"), none.alias("none")), "lang-references")


def _hist(top: Column) -> Column:
    """How many of a text's words w are each of the top words, and how many none of them."""
    known = F.filter("w", lambda x: F.array_contains(top, x))
    hits = lambda k: F.transform(top, lambda r: (F.size(k) - F.size(F.array_remove(k, r))).cast("double"))
    return let(known, lambda k: F.concat(hits(k), F.array((F.size("w") - F.size(k)).cast("double"))))


def text_facts(docs: DataFrame, refs: DataFrame, id_column: str = "doc_id", text_column: str = "text", lang_column: str = "lang", carry: Column | None = None) -> DataFrame:
    """One row per document: doc_id, lang, the base rules' counts, n_chars, classes, hist; `carry` is handed through."""
    rows = docs.select(F.col(id_column).alias("doc_id"), F.col(lang_column).alias("lang"), F.coalesce(F.col(text_column), F.lit("")).alias("text"), (F.lit(0) if carry is None else carry).alias("carry"))
    rows = _same_lang(rows, refs.select("lang", "top")).withColumn("w", words(F.col("text")))
    rows = rows.withColumn("word_chars", F.char_length(F.array_join("w", "")).cast("long")).withColumn("classes", _classes(F.col("text"), F.col("word_chars")))
    lines = F.filter(F.split("text", "\n", -1), lambda x: F.rlike(x, F.lit(f"[^{SPACE}]")))
    return rows.select(
        "doc_id",
        "lang",
        "carry",
        F.size("w").cast("long").alias("n_words"),
        "word_chars",
        F.get("classes", F.lit(4)).cast("long").alias("n_symbols"),
        let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
        _repeat_words(F.col("w")).alias("n_repeat_words"),
        F.char_length("text").alias("n_chars"),
        "classes",
        F.when(F.size("w") >= MIN_WORDS, _hist(F.col("top"))).alias("hist"),
    )


def _lacks_words(n: Column, hits: Column, far: Column) -> Column:
    """Whether n words with `hits` top words, at distance `far`, lack the words of the reference (share, none)."""
    share, p = F.col("share"), hits / n
    bits = n * (F.when(p > 0, p * (F.log2(p) - F.log2(share))).otherwise(0.0) + (1 - p) * (F.log2(1 - p) - F.log2(1 - share)))
    strange = far > F.col("none") * (NONE_PART + NONE_SLACK / F.sqrt(n * share))
    return F.when((share > 0) & (p < share), strange | F.coalesce(bits > RARE_BITS, F.lit(False))).otherwise(False)


def kept_documents(docs: DataFrame, **columns: str) -> DataFrame:
    """The rows of docs that the rules keep, unchanged."""
    rows = judged(docs, carry=packed(docs), **columns).where("kept")
    return unpacked(rows.withColumnRenamed("carry", "row"), docs.columns)


def judged(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", lang_column: str = "lang", carry: Column | None = None) -> DataFrame:
    """One row per document: the base counts, both distances (null behind a guard), base_failed, kept."""
    refs = references(docs, text_column, lang_column)
    facts = written(text_facts(docs, refs, id_column, text_column, lang_column, carry), "text-facts")
    all_classes = facts.groupBy("lang").agg(F.array(*[F.sum(F.get("classes", F.lit(k))) for k in range(6)]).alias("all_classes"))
    about = refs.withColumnRenamed("lang", "l").join(all_classes, F.col("l").eqNullSafe(F.col("lang"))).where(F.col("n_words") >= MIN_REF_WORDS)
    both = _same_lang(facts, about.select("lang", "shares", "share", "none", "all_classes"))
    chars = F.when(F.col("n_chars") >= MIN_CHARS, distance(F.col("classes"), F.col("all_classes")))
    out = both.withColumns({"char_distance": chars, "word_distance": distance(F.col("hist"), F.col("shares"))})
    lacks = F.col("word_distance").isNotNull() & (F.coalesce("lang", F.lit("")) != "")
    lacks = F.when(lacks, _lacks_words(F.col("n_words"), F.col("n_words") - F.element_at("hist", -1), F.col("word_distance"))).otherwise(False)
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    fine = (F.coalesce("char_distance", F.lit(0.0)) <= MOST_CHAR_DISTANCE) & (F.coalesce("word_distance", F.lit(0.0)) <= MOST_WORD_DISTANCE) & ~lacks
    out = out.withColumns({"base_failed": failed, "kept": ~failed & fine})
    return out.select("doc_id", *([] if carry is None else ["carry"]), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "char_distance", "word_distance", "base_failed", "kept")
