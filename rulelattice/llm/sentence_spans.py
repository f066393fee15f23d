"""Substring deduplication by sliding sentence spans.

Every run of ``span`` consecutive sentences is hashed to 128 bits. Hashes found more than once are
joined back, and each sentence that a non-first occurrence covers is removed; the first occurrence,
by id and position, stays. Sentences end after ``.``, ``!`` or ``?`` with white space, or at a line's end.

Edge cases: a null text has no sentences; sentences without a word stay where they are and do not
interrupt a run; texts of fewer sentences have no span; spans of any length count, so that scripts
without blanks are treated like others; rows repeated with the same id and text are treated alike,
and do not count as copies of each other; a null id ranks first; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulelattice.llm.common import SPACE, cut, let, set_aside

#: Zero-width places between sentences; what they cut keeps every character.
BOUNDARY = rf"(?<=[.!?][{SPACE}])(?=[^{SPACE}])|(?<=\n)(?=[^\n])"
SPAN = 3


def pieces_of(text: Column) -> Column:
    """Sentences with what follows them; joined they give the text."""
    return F.split(F.coalesce(text, F.lit("")), BOUNDARY)


def said(piece: Column) -> Column:
    # The very end only: `$` also stands before a last line separator such as U+0085, which is no white space here.
    return F.regexp_replace(piece, rf"^[{SPACE}]+|[{SPACE}]+\z", "")


def _numbered(text: Column) -> Column:
    """Structs (i, s): place and trimmed sentence, without empty ones."""
    return F.filter(F.transform(pieces_of(text), lambda p, i: F.struct(i.alias("i"), said(p).alias("s"))), lambda x: x["s"] != "")


def spans(docs: DataFrame, span: int, id_col: str, text_col: str) -> DataFrame:
    """One row per span: document key, first and last sentence, 128-bit hash."""
    def windows(xs: Column) -> Column:
        def one(j: Column) -> Column:
            whole = F.array_join(F.transform(F.slice(xs, j + 1, span), lambda x: x["s"]), "\n")
            return let(whole, lambda w: F.struct(F.get(xs, j)["i"].alias("first"), F.get(xs, j + span - 1)["i"].alias("last"), F.xxhash64(w).alias("h1"), F.xxhash64(F.lit(1), w).alias("h2")))
        return F.when(F.size(xs) >= span, F.transform(F.sequence(F.lit(0), F.size(xs) - span), one))

    rows = docs.select(F.col(id_col).alias("_id"), F.xxhash64(text_col).alias("_th"), F.explode(let(_numbered(F.col(text_col)), windows)).alias("_w"))
    return rows.select("_id", "_th", "_w.first", "_w.last", "_w.h1", "_w.h2")


def repeated_sentences(docs: DataFrame, span: int = SPAN, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """For each document with repeats, its key and the places that repeated spans cover, in order; those of sentences without a word too."""
    # Texts are split once: their spans are written, then counted and joined from there.
    all_spans = cut(spans(docs, span, id_col, text_col))
    often = all_spans.groupBy("h1", "h2").count().where("count > 1").select(F.shiftleft("h1", 0).alias("_a"), F.col("h2").alias("_b"))
    again = cut(all_spans.join(often, (F.col("h1") == F.col("_a")) & (F.col("h2") == F.col("_b"))).drop("_a", "_b"))
    at = F.struct(F.col("_id"), F.col("_th"), F.col("first"))
    first = again.groupBy("h1", "h2").agg(F.min(at).alias("_first")).select(F.shiftleft("h1", 0).alias("_a"), F.col("h2").alias("_b"), "_first")
    later = again.join(first, (F.col("h1") == F.col("_a")) & (F.col("h2") == F.col("_b"))).where(~at.eqNullSafe(F.col("_first")))
    return later.groupBy("_id", "_th").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_set(F.sequence("first", "last"))))).alias("_gone"))


def drop_repeats(docs: DataFrame, span: int = SPAN, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All documents with the kept text, ``n_sentences``, ``n_removed`` and ``n_spans`` (removed runs),
    which take the place of columns of these names."""
    own, name = set_aside(docs)
    passed = [c for c in docs.columns if c.lower() not in (text_col.lower(), "n_sentences", "n_removed", "n_spans")]
    kept_as, id_col, text_col = text_col, name(id_col), name(text_col)
    gone = repeated_sentences(own, span, id_col, text_col)
    key = F.xxhash64(own[text_col])
    joined = own.join(gone, own[id_col].eqNullSafe(gone["_id"]) & (key == gone["_th"]), "left")

    def closed(ps: Column) -> Column:
        # Places are taken as whole lists, so that very long texts cost no more than their length.
        full = F.filter(F.transform(ps, lambda p, i: F.when(said(p) != "", i)), lambda i: i.isNotNull())
        # A span covers the sentences without a word inside it; they stay.
        out = lambda f: F.array_intersect(F.coalesce("_gone", F.array().cast("array<int>")), f)
        kept = lambda o: F.transform(F.array_except(F.sequence(F.lit(0), F.size(ps) - 1), o), lambda i: F.get(ps, i))
        # Every sentence's double place, and the odd one behind it where it goes: a run starts
        # at an odd one that follows no other.
        marks = lambda f, o: F.array_sort(F.concat(F.transform(f, lambda i: 2 * i), F.transform(o, lambda i: 2 * i + 1)))
        starts = lambda m: F.size(F.filter(m, lambda x, j: (x % 2 == 1) & ((j < 2) | (F.get(m, F.greatest(j - 2, F.lit(0))) % 2 == 0))))
        made = lambda f, o: F.struct(F.array_join(kept(o), "").alias("kept"), F.size(f).cast("long").alias("n_sentences"), F.size(o).cast("long").alias("n_removed"), let(marks(f, o), starts).cast("long").alias("n_spans"))
        return let(full, lambda f: let(out(f), lambda o: made(f, o)))

    made = joined.select(*[own[name(c)] for c in passed], let(pieces_of(own[text_col]), closed).alias("_r"))
    results = [F.col(f"_r.{c}") for c in ("kept", "n_sentences", "n_removed", "n_spans")]
    return made.select(*[F.col(name(c)) for c in passed], *results).toDF(*passed, kept_as, "n_sentences", "n_removed", "n_spans")
