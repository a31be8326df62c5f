"""Quality rules by distribution divergence, native expressions only.

A document's character-class and common-word histograms are compared with references of its language by
Jensen-Shannon distance; short documents are guarded by a minimum length. Beside it: plain word, symbol, line and
repetition counts.

Edge cases: a null text counts as empty (no words, base_failed); repeated rows are judged one by one and alike; an
empty table gives an empty result; extra columns pass through untouched; null or unknown languages use the pooled
reference of all documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import let, materialise

SPACE = "[\\x20\\x09-\\x0D]+"
CHAR_CLASSES = ("lower", "upper", "digit", "space", "mark", "symbol", "other")
# Frequent function words of each language.
COMMON_WORDS = {
    "de": ("der", "die", "und", "das", "den", "von", "mit", "ein"),
    "en": ("the", "of", "and", "to", "in", "is", "that", "for"),
    "es": ("de", "la", "que", "el", "en", "los", "para", "se"),
    "fr": ("de", "la", "le", "et", "les", "un", "que", "en"),
}
POOLED = "*"
GUARD_WORDS = 50
GUARD_JOINT = 100
MAX_CHAR_DISTANCE = 0.25
MAX_JOINT_DISTANCE = 0.28


# one letter stands for each class; the rest of the characters stay as they are
STAND_INS = (("a", "abcdefghijklmnopqrstuvwxyz"), ("A", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"), ("0", "0123456789"), (" ", " \t\n\x0b\x0c\r"), (".", ".,;:!?'\"()-"), ("#", "#*$%&|<>"))


def _class_string(text: Column) -> Column:
    """The text with each character replaced by its class's stand-in: one pass instead of a pattern for each class."""
    return F.translate(text, "".join(chars for _, chars in STAND_INS), "".join(c * len(chars) for c, chars in STAND_INS))


def _class_counts(stood: Column) -> Column:
    return F.array(*(F.length(stood) - F.length(F.replace(stood, F.lit(c), F.lit(""))) for c, _ in STAND_INS))


def _repeat_words(words: Column) -> Column:
    """Words covered by 3-word windows that occur at least twice in the text, without explode or shuffle.

    Windows are sorted by a 64-bit hash, their words and their position, so that equal ones are neighbours in texts of
    any length; the words decide."""

    def starts(w: Column) -> Column:
        def window(x: Column, i: Column) -> Column:
            second, third = F.get(w, i + 1), F.get(w, i + 2)
            return F.struct(F.xxhash64(x, second, third).alias("h"), x.alias("a"), second.alias("b"), third.alias("c"), i.alias("p"))

        ordered = F.sort_array(F.slice(F.transform(w, window), F.lit(1), F.greatest(F.size(w) - 2, F.lit(0))))

        def same(x: Column, y: Column) -> Column:
            return (x["h"] == y["h"]) & (x["a"] == y["a"]) & (x["b"] == y["b"]) & (x["c"] == y["c"])

        return let(ordered, lambda s: F.sort_array(F.transform(F.filter(s, lambda x, i: same(x, F.get(s, i + 1)) | same(x, F.get(s, i - 1))), lambda x: x["p"])))

    def covered(p: Column) -> Column:
        steps = F.transform(p, lambda x, i: F.least(F.lit(3), F.coalesce(F.get(p, i + 1) - x, F.lit(3))))
        return F.aggregate(steps, F.lit(0).cast("long"), lambda a, x: a + x)

    return let(starts(words), covered)


def measured(df: DataFrame, text_col: str = "text", lang_col: str | None = "lang") -> DataFrame:
    """Adds flat working columns ``__qr_*`` (counts and the two histograms as shares); every other column stays.

    Flat, as the optimiser repeats the parts of a struct for each use, but not a costly column with several uses."""
    text = F.col("__qr_text")
    every = sorted({w for words in COMMON_WORDS.values() for w in words})
    lang = F.lower(F.col(lang_col)) if lang_col else F.lit(None).cast("string")
    lang = F.when(lang.isin(*COMMON_WORDS), lang).otherwise(F.lit(POOLED))
    listed = F.lit(None).cast("array<string>")
    for code, words in COMMON_WORDS.items():
        listed = F.when(F.col("__qr_lang") == code, F.array(*map(F.lit, words))).otherwise(listed)
    listed = F.coalesce(listed, F.array(*map(F.lit, COMMON_WORDS["en"])))
    out = df.withColumns({"__qr_text": F.coalesce(F.col(text_col), F.lit("")), "__qr_lang": lang})
    out = out.withColumns(
        {
            "__qr_w": F.array_remove(F.split(text, SPACE), ""),
            "__qr_l": F.filter(F.split(text, "\n"), lambda x: x.rlike("[^\\x20\\x09-\\x0D]")),
            "__qr_listed": listed,
            "__qr_n_chars": F.length(text).cast("double"),
            "__qr_stood": _class_string(text),
        }
    )
    words, lines = F.col("__qr_w"), F.col("__qr_l")
    out = out.withColumns(
        {
            "__qr_counts": let(F.col("__qr_stood"), _class_counts),
            "__qr_n_words": F.size(words).cast("long"),
            "__qr_n_dup_lines": (F.size(lines) - F.size(F.array_distinct(lines))).cast("long"),
            "__qr_n_repeat_words": _repeat_words(words),
            "__qr_commons": let(
                F.filter(words, lambda w: w.isin(*every)),
                lambda hits: F.transform(F.col("__qr_listed"), lambda c: F.size(F.filter(hits, lambda h: h == c)).cast("double")),
            ),
        }
    )
    counts = F.col("__qr_counts")
    return out.withColumns({"__qr_n_symbols": counts[5].cast("long"), "__qr_word_chars": (F.col("__qr_n_chars") - counts[3]).cast("long"), "__qr_chars": _chars(), "__qr_words": _words()})


def _chars() -> Column:
    """Shares of the seven character classes."""
    n_chars = F.col("__qr_n_chars")
    share = lambda x: F.when(n_chars > 0, x / n_chars).otherwise(F.lit(0.0))
    return let(F.col("__qr_counts"), lambda c: F.concat(F.transform(c, share), F.array(share(n_chars - F.aggregate(c, F.lit(0), lambda a, x: a + x)))))


def _words() -> Column:
    """Shares of the listed words, and of all the rest."""
    n = F.greatest(F.col("__qr_n_words"), F.lit(1)).cast("double")
    commons = F.col("__qr_commons")
    listed = F.aggregate(commons, F.lit(0.0), lambda a, x: a + x)
    return F.concat(F.transform(commons, lambda x: x / n), F.array((n - listed) / n))


def js_distance(p: Column, q: Column) -> Column:
    """Square root of the Jensen-Shannon divergence (base 2) of two arrays of shares: 0 to 1."""
    part = lambda a, m: F.when(a > 0, a * F.log2(a / m)).otherwise(F.lit(0.0))
    terms = F.zip_with(p, q, lambda a, b: (part(a, (a + b) / 2) + part(b, (a + b) / 2)) / 2)
    return F.sqrt(F.greatest(F.aggregate(terms, F.lit(0.0), lambda s, x: s + x), F.lit(0.0)))


def references(scored: DataFrame) -> DataFrame:
    """Mean histograms of each listed language and of all documents together: at most five rows, whatever the input.

    Rounded to 9 digits, so that the order of partial sums cannot show."""
    long_enough = scored.where(F.col("__qr_n_words") >= GUARD_WORDS)
    sums = long_enough.groupBy("__qr_lang").agg(F.count(F.lit(1)).alias("n"), *(F.sum(F.col(c)[i]).alias(f"{c}{i}") for c, k in (("__qr_chars", 7), ("__qr_words", 9)) for i in range(k)))
    mean = lambda c, k, f: F.array(*(F.round(f(f"{c}{i}") / f("n"), 9) for i in range(k)))
    parts = lambda f: (mean("__qr_chars", 7, f).alias("ref_chars"), mean("__qr_words", 9, f).alias("ref_words"))
    each = sums.select(F.col("__qr_lang").alias("ref_lang"), *parts(F.col)).where(F.col("ref_lang") != POOLED)
    return each.unionByName(sums.agg(*parts(F.sum)).select(F.lit(POOLED).alias("ref_lang"), "ref_chars", "ref_words"))


def quality_rules(df: DataFrame, text_col: str = "text", lang_col: str | None = "lang", max_char_distance: float = MAX_CHAR_DISTANCE, max_joint_distance: float = MAX_JOINT_DISTANCE, out: str = "quality", columns: list[str] | None = None) -> DataFrame:
    """``df`` with a struct column ``out`` (it replaces a column of that name): counts, both distances, base_failed and kept.

    A document is rejected if base_failed, if its characters are farther than ``max_char_distance`` from the
    reference, or if both distances together (root of the sum of squares) pass ``max_joint_distance``; words are
    judged from ``GUARD_JOINT`` words on. ``columns`` are the input columns to carry along (all by default). Texts are
    measured once into a shared table; references are gathered from it over all documents, then the table is judged;
    only the five reference rows are broadcast."""
    if lang_col and lang_col not in df.columns:
        lang_col = None
    carried = [c for c in (df.columns if columns is None else columns) if c != out]
    kept_measures = [f"__qr_{c}" for c in ("lang", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "chars", "words")]
    m = materialise(measured(df, text_col, lang_col).select(*carried, *kept_measures), "quality")
    by_lang = references(m).agg(F.map_from_entries(F.collect_list(F.struct("ref_lang", F.struct("ref_chars", "ref_words")))).alias("__qr_refs"))
    joined = m.crossJoin(F.broadcast(by_lang))  # exactly one row, five entries at most
    ref = F.coalesce(F.try_element_at(F.col("__qr_refs"), F.col("__qr_lang")), F.try_element_at(F.col("__qr_refs"), F.lit(POOLED)))
    n = F.col("__qr_n_words")
    char_d = F.coalesce(js_distance(F.col("__qr_chars"), F.col("__qr_ref.ref_chars")), F.lit(0.0))
    word_d = F.coalesce(js_distance(F.col("__qr_words"), F.col("__qr_ref.ref_words")), F.lit(0.0))
    judged = joined.withColumn("__qr_ref", ref).withColumns(
        {
            "__qr_cd": F.round(F.when(n < GUARD_WORDS, F.lit(0.0)).otherwise(char_d), 6),
            # the pooled reference has no word list of its own, so words are judged for listed languages only
            "__qr_wd": F.round(F.when((n < GUARD_JOINT) | (F.col("__qr_lang") == POOLED), F.lit(0.0)).otherwise(word_d), 6),
            "__qr_base": (n < GUARD_WORDS) | (F.col("__qr_n_repeat_words") * 100 > n * 50),
        }
    )
    cd, wd = F.col("__qr_cd"), F.col("__qr_wd")
    fine = (cd <= max_char_distance) & ((wd == 0) | (cd * cd + wd * wd <= max_joint_distance**2))
    return judged.select(
        *carried,
        F.struct(
            *(F.col(f"__qr_{c}").alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")),
            cd.alias("char_distance"),
            wd.alias("word_distance"),
            F.col("__qr_base").alias("base_failed"),
            (~F.col("__qr_base") & fine).alias("kept"),
        ).alias(out),
    )
