"""Quality rules: word and repetition counts, and divergence from language references.

Every text is described by two histograms: its character classes, and the common words of its
language. The reference of a language is the sum of these histograms over all its documents.
A document fails when the Jensen-Shannon distance of a histogram to its reference is too large,
provided the text is long enough for the histogram to mean something. Only built-in column
functions are used. Each verdict is one expression tree in which every part is evaluated once a
row, so a filter on it can be pushed down without doubling the work.

Edge cases: a null text has no words and fails the base rule (fewer than 50 words); a document of
a language without reference (null or not listed) is held against no word histogram and against
the pooled character reference; the references have at most ``len(COMMON_WORDS) + 1`` rows, which
bounds the broadcast; repeated rows are judged each; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulelattice.llm.common import SPACE, cut, let, set_aside, words_of

#: Frequent function words by language.
COMMON_WORDS = {
    "en": ["the", "of", "and", "to", "a", "in", "is", "that", "it", "for", "was", "on", "with", "as", "be", "by"],
    "de": ["der", "die", "und", "in", "den", "von", "zu", "das", "mit", "sich", "im", "des", "für", "auf", "ist", "nicht"],
    "fr": ["de", "la", "le", "et", "les", "des", "en", "un", "du", "que", "une", "est", "pour", "qui", "dans", "par"],
    "es": ["de", "la", "que", "el", "en", "y", "los", "se", "del", "las", "un", "por", "con", "no", "una", "para"],
}
ALL_LISTED = sorted({w for ws in COMMON_WORDS.values() for w in ws})
#: Name of the reference for languages that are not listed.
POOLED = "*"
#: Character classes that are counted by a pattern; then come white space and the rest.
CLASSES = {"upper": "A-Z", "digit": "0-9", "stop": ".,;:!?", "symbol": "#*$%&|<>", "beyond_ascii": r"\u0080-\x{10FFFF}"}


@dataclass(frozen=True)
class Limits:
    min_words: int = 50
    max_repeat_percent: int = 50
    #: A histogram counts from so many characters or words on.
    guard_chars: int = 200
    guard_words: int = 80
    #: Jensen-Shannon distances (0 to 1) from which a document fails.
    max_class_distance: float = 0.26
    max_word_distance: float = 0.295


def _only(text: Column, members: str) -> Column:
    return F.length(F.regexp_replace(text, f"[^{members}]+", "")).cast("long")


def rare_characters(text: Column) -> Column:
    """The text without lower-case ASCII letters and blanks: a short string that the counts below read."""
    return F.regexp_replace(text, "[a-z ]+", "")


def class_histogram(text: Column, words: Column, rare: Column) -> Column:
    """Counts of upper-case letters, digits, stops, symbols, beyond ASCII, white space and the rest."""
    size = F.length(text).cast("long")
    counted = [_only(rare, members) for members in CLASSES.values()]
    blank = size - F.length(F.array_join(words, "")).cast("long")
    return let(F.array(*counted, blank), lambda c: F.concat(c, F.array(size - F.aggregate(c, F.lit(0).cast("long"), lambda a, x: a + x))))


def word_histogram(words: Column, lang: Column) -> Column:
    """Counts of the language's common words, then of all other words; null where none are listed."""
    listed = None
    for name, own in COMMON_WORDS.items():
        row = F.array(*map(F.lit, own))
        listed = F.when(lang == name, row) if listed is None else listed.when(lang == name, row)
    common = F.filter(words, lambda w: w.isin(ALL_LISTED))
    def counted(found: Column) -> Column:
        return F.transform(listed, lambda x: F.size(F.filter(found, lambda y: y == x)).cast("long"))
    def with_rest(bins: Column) -> Column:
        return F.concat(bins, F.array(F.size(words).cast("long") - F.aggregate(bins, F.lit(0).cast("long"), lambda a, x: a + x)))
    return let(common, lambda found: let(counted(found), with_rest))


#: Bits of a packed long that hold a window's place; the others hold the upper part of its hash.
PLACE_BITS = 22


def repeat_words(words: Column) -> Column:
    """Words inside three-word windows that the text holds twice or more; O(n log n) in its words.

    Windows are first compared by hash: a text whose hashes all differ has no repeated window. Else
    the windows of repeated hashes are sorted and compared as strings, so that the count is exact.
    """
    n = F.size(words)
    hashes = F.when(n >= 3, F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)))).otherwise(F.array().cast("array<bigint>"))
    place = F.lit((1 << PLACE_BITS) - 1).cast("long")

    def covered(at: Column) -> Column:
        reach = F.transform(at, lambda v, k: F.least(F.lit(3).cast("long"), F.coalesce(F.get(at, k + 1) - v, F.lit(3).cast("long"))))
        return F.aggregate(reach, F.lit(0).cast("long"), lambda a, x: a + x)

    def beside(ordered: Column, key) -> Column:
        return F.filter(ordered, lambda e, j: (key(F.get(ordered, j + 1)) == key(e)).eqNullSafe(True) | ((j > 0) & (key(F.get(ordered, F.greatest(j - 1, F.lit(0)))) == key(e))))

    def by_string(places: Column) -> Column:
        window = lambda i: F.concat_ws(" ", F.get(words, i.cast("int")), F.get(words, i.cast("int") + 1), F.get(words, i.cast("int") + 2))
        spelt = F.sort_array(F.transform(places, lambda i: F.struct(window(i).alias("w"), i.alias("i"))))
        return let(spelt, lambda s: let(F.sort_array(F.transform(beside(s, lambda e: e["w"]), lambda e: e["i"])), covered))

    def by_hash(hs: Column) -> Column:
        short = F.sort_array(F.transform(hs, lambda h, i: h.bitwiseAND(F.bitwise_not(place)).bitwiseOR(i.cast("long"))))
        long = F.sort_array(F.transform(hs, lambda h, i: F.struct(h.alias("h"), i.cast("long").alias("i"))))
        packed = let(short, lambda s: F.transform(beside(s, lambda e: F.shiftright(e, PLACE_BITS)), lambda e: e.bitwiseAND(place)))
        whole = let(long, lambda s: F.transform(beside(s, lambda e: e["h"]), lambda e: e["i"]))
        return let(F.when(F.size(hs) <= (1 << PLACE_BITS), packed).otherwise(whole), by_string)

    return let(hashes, lambda hs: F.when(F.size(F.array_distinct(hs)) == F.size(hs), F.lit(0).cast("long")).otherwise(by_hash(hs)))


def base_counts(text: Column, words: Column, rare: Column, limits: Limits) -> Column:
    lines = F.filter(F.split(text, "\n"), lambda x: F.rlike(x, F.lit(f"[^{SPACE}]")))
    made = F.struct(
        F.size(words).cast("long").alias("n_words"),
        F.length(F.array_join(words, "")).cast("long").alias("word_chars"),
        _only(rare, CLASSES["symbol"]).alias("n_symbols"),
        let(lines, lambda x: (F.size(x) - F.size(F.array_distinct(x))).cast("long")).alias("n_dup_lines"),
        repeat_words(words).alias("n_repeat_words"),
    )
    def failed(c: Column) -> Column:
        bad = (c["n_words"] < limits.min_words) | (100 * c["n_repeat_words"] > limits.max_repeat_percent * c["n_words"])
        return F.struct(*[c[k].alias(k) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], bad.alias("base_failed"))
    return let(made, failed)


def jensen_shannon(p: Column, q: Column) -> Column:
    """Distance, 0 to 1, of two histograms of equal length; null if one is empty or null."""
    def total(h: Column) -> Column:
        return F.aggregate(h, F.lit(0.0), lambda a, x: a + x)

    def part(x: Column, m: Column) -> Column:
        return F.when(x > 0, x * F.log2(x / m)).otherwise(F.lit(0.0))

    def distance(s: Column) -> Column:
        terms = F.zip_with(p, q, lambda a, b: F.when((s["p"] > 0) & (s["q"] > 0), let(F.struct((a / s["p"]).alias("x"), (b / s["q"]).alias("y")), lambda v: part(v["x"], (v["x"] + v["y"]) / 2) + part(v["y"], (v["x"] + v["y"]) / 2))))
        return F.sqrt(F.greatest(total(terms) / 2, F.lit(0.0)))

    return let(F.struct(total(p).alias("p"), total(q).alias("q")), distance)


def _lang_key(lang: Column) -> Column:
    return F.when(lang.isin(list(COMMON_WORDS)), lang).otherwise(F.lit(POOLED))


BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
CLASS_BINS = len(CLASSES) + 2
WORD_BINS = max(map(len, COMMON_WORDS.values())) + 1


def describe(docs: DataFrame, limits: Limits, id_col: str, text_col: str, lang_col: str) -> DataFrame:
    """One short row per document: id, language of its reference, base counts, both histograms, length."""
    text = F.coalesce(F.col(text_col), F.lit(""))

    def all_of(words: Column) -> Column:
        def with_rare(rare: Column) -> Column:
            return F.struct(base_counts(text, words, rare, limits).alias("b"), class_histogram(text, words, rare).alias("c"), word_histogram(words, F.col(lang_col)).alias("w"))
        return let(rare_characters(text), with_rare)

    return docs.select(F.col(id_col), _lang_key(F.col(lang_col)).alias("_lang"), F.length(text).alias("_chars"), let(words_of(text), all_of).alias("_v")).select(
        id_col, "_lang", "_chars", "_v.b.*", F.col("_v.c").alias("_classes"), F.col("_v.w").alias("_words")
    )


def _sums(rows: DataFrame) -> DataFrame:
    cells = [F.sum(F.get("_classes", F.lit(i))).alias(f"c{i}") for i in range(CLASS_BINS)] + [F.sum(F.get("_words", F.lit(i))).alias(f"w{i}") for i in range(WORD_BINS)]
    return rows.groupBy("_lang").agg(*cells).select(
        F.col("_lang").alias("_ref_lang"),
        F.array(*[F.col(f"c{i}") for i in range(CLASS_BINS)]).alias("_ref_classes"),
        F.when(F.col("w0").isNotNull(), F.array(*[F.col(f"w{i}") for i in range(WORD_BINS)])).alias("_ref_words"),
    )


def language_references(docs: DataFrame, text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Histograms of each listed language and of all others together, summed over every document."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    both = let(words_of(text), lambda w: F.struct(class_histogram(text, w, rare_characters(text)).alias("c"), word_histogram(w, F.col(lang_col)).alias("w")))
    return _sums(docs.select(_lang_key(F.col(lang_col)).alias("_lang"), both.alias("_h")).select("_lang", F.col("_h.c").alias("_classes"), F.col("_h.w").alias("_words")))


def _far(class_distance: Column, word_distance: Column, limits: Limits) -> Column:
    return (F.coalesce(class_distance, F.lit(0.0)) > limits.max_class_distance) | (F.coalesce(word_distance, F.lit(0.0)) > limits.max_word_distance)


def judge(docs: DataFrame, limits: Limits = Limits(), id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """One row per document with its counts, distances (in millionths) and verdict.

    Texts are read once: their short descriptions are written to the checkpoint folder, summed to
    references, and held against them.
    """
    rows = cut(describe(docs, limits, id_col, text_col, lang_col))
    held = rows.join(F.broadcast(_sums(rows)), F.col("_lang") == F.col("_ref_lang"), "left")
    far = held.select(
        id_col,
        *BASE,
        F.when(F.col("_chars") >= limits.guard_chars, jensen_shannon(F.col("_classes"), F.col("_ref_classes"))).alias("_c"),
        F.when(F.col("n_words") >= limits.guard_words, jensen_shannon(F.col("_words"), F.col("_ref_words"))).alias("_w"),
    )
    ppm = lambda c: F.round(F.col(c) * 1_000_000).cast("long")
    return far.select(id_col, *BASE, ppm("_c").alias("class_distance_ppm"), ppm("_w").alias("word_distance_ppm"), (~F.col("base_failed") & ~_far(F.col("_c"), F.col("_w"), limits)).alias("kept"))


def keep_good(docs: DataFrame, limits: Limits = Limits(), text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """The documents whose verdict is good, with all their columns.

    Documents need no usable id: the texts are read twice, for the references and for the verdict.
    """
    own, name = set_aside(docs)
    text_col, lang_col = name(text_col), name(lang_col)
    text = F.coalesce(F.col(text_col), F.lit(""))
    references = language_references(own, text_col, lang_col)  # a row for each listed language and one more at most
    held = own.join(F.broadcast(references), _lang_key(own[lang_col]) == F.col("_ref_lang"), "left")

    def judged(words: Column) -> Column:
        def with_rare(rare: Column) -> Column:
            base = base_counts(text, words, rare, limits)["base_failed"]
            c = F.when(F.length(text) >= limits.guard_chars, jensen_shannon(class_histogram(text, words, rare), F.col("_ref_classes")))
            w = F.when(F.size(words) >= limits.guard_words, jensen_shannon(word_histogram(words, F.col(lang_col)), F.col("_ref_words")))
            return ~base & let(F.struct(c.alias("c"), w.alias("w")), lambda d: ~_far(d["c"], d["w"], limits))
        return let(rare_characters(text), with_rare)

    return held.where(let(words_of(text), judged)).select(*own.columns).toDF(*docs.columns)
