"""Quality rules by distribution divergence, in DataFrame functions only.

A document's characters are counted by class and its words by the common words of its language. Both histograms are compared by
Jensen-Shannon distance with those of the language over all documents; texts too short for a histogram are not judged by it. One pass over
the texts makes a narrow table of counts, from which both the references and the verdicts come.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semimul.llm.common import WORD_SPACE, Scratch

# Common words of each language.
COMMON_WORDS = {
    "en": ["the", "of", "and", "to", "a", "in", "is", "that", "it", "was", "for", "on", "are", "with"],
    "de": ["der", "die", "und", "in", "den", "von", "zu", "das", "mit", "sich", "des", "auf", "nicht", "im"],
    "fr": ["de", "la", "le", "et", "les", "des", "en", "un", "du", "une", "que", "est", "pour", "qui"],
    "es": ["de", "la", "que", "el", "en", "y", "a", "los", "del", "se", "las", "por", "un", "para"],
}
#: Classes of characters: small ASCII letters, capitals, digits, white space, marks of prose, symbols, all others.
CLASSES = ("small", "capital", "digit", "space", "prose", "symbol", "other")
#: Greatest distances (0 to 1) from the language's histograms, and the least words of a text that they judge.
MAX_CLASS_DISTANCE, MAX_WORD_DISTANCE, MIN_WORDS = 0.25, 0.28, 100

_SPACES = "[ \\t\\n\\x0b\\x0c\\r]+"


def _sum_counts(name: str, size: int) -> list[Column]:
    return [F.sum(F.get(name, F.lit(i))).alias(f"{name}{i}") for i in range(size)]


def counts(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """(id, lang, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, classes, common) of each whole text. `classes` counts characters
    by class, `common` the words of the language's list and, last, all other words; a language without a list has no common words."""
    source = docs.select(F.col(id_col).alias("id"), F.col(lang_col).alias("lang"), F.coalesce(F.col(text_col), F.lit("")).alias("body"))
    text = F.col("body")
    words = F.array_remove(F.split(text, _SPACES), "")
    size = len(next(iter(COMMON_WORDS.values()))) + 1

    def of(w: Column, t: Column, lang: Column) -> Column:
        n = F.size(w)
        # three-word windows: equal hashes are neighbours after the sort; texts without any need none
        hashes = F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)))
        bound = lambda make, use: F.get(F.transform(F.array(make), use), F.lit(0))
        none = F.expr("CAST(array() AS array<int>)")
        pairs = lambda h: F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
        same = lambda s: F.filter(s, lambda x, k: ((k > 0) & (F.get(s, F.greatest(k - 1, F.lit(0)))["h"] == x["h"])) | (F.get(s, k + 1)["h"] == x["h"]))
        repeats = lambda h: F.when(F.size(F.array_distinct(h)) < F.size(h), bound(pairs(h), lambda s: F.transform(same(s), lambda x: x["i"]))).otherwise(none)
        again = F.when(n < 3, none).otherwise(bound(hashes, repeats))
        # words that windows at sorted places cover: three, or the gap to the next place
        cover = bound(F.sort_array(again), lambda q: F.aggregate(F.transform(q, lambda x, k: F.least(F.lit(3), F.coalesce(F.get(q, k + 1) - x, F.lit(3)))), F.lit(0), lambda a, x: a + x))
        lines = F.filter(F.split(t, "\n", -1), lambda x: F.length(F.btrim(x, F.lit(WORD_SPACE))) > 0)
        dup = bound(lines, lambda ls: F.size(ls) - F.size(F.array_distinct(ls)))
        chars = F.length(F.array_join(w, ""))
        classes = bound(F.regexp_replace(t, "[a-z \\t\\n\\x0b\\x0c\\r]+", ""), lambda r: bound(F.regexp_replace(r, "[^\\x00-\\x7F]+", ""), lambda a: F.struct(
            r.alias("r"), F.length(r).alias("all"), F.length(a).alias("ascii"), F.length(F.regexp_replace(a, "[A-Z]+", "")).alias("no_capital"), F.length(F.regexp_replace(a, "[0-9]+", "")).alias("no_digit"), F.length(F.regexp_replace(a, "[.,;:!?'\"()-]+", "")).alias("no_prose"))))
        common = F.lit(None)
        for code, ws in COMMON_WORDS.items():
            # one pass finds the listed words and their numbers; the counts are over the numbers
            listed = F.filter(F.transform(w, lambda x: F.lower(x)), lambda x: x.isin(ws))
            numbers = F.transform(listed, lambda x: F.array_position(F.array(*map(F.lit, ws)), x))
            number = lambda s, c: F.size(F.filter(s, lambda x: x == c + 1)).cast("long")
            mine = bound(numbers, lambda s: F.array(*[number(s, c) for c in range(len(ws))]))
            common = F.when(lang == code, mine).otherwise(common)
        common = F.coalesce(common, F.array_repeat(F.lit(0).cast("long"), size - 1))
        return bound(classes, lambda c: F.struct(
            n.cast("long").alias("n_words"), chars.cast("long").alias("word_chars"),
            F.length(F.regexp_replace(c["r"], "[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
            dup.cast("long").alias("n_dup_lines"), cover.cast("long").alias("n_repeat_words"), c.alias("c"), (F.length(t) - chars).alias("spaces"), F.length(t).alias("total"), common.alias("common")))

    made = F.transform(F.array(words), lambda w: of(w, text, F.col("lang")))
    # the element is inlined as columns by a generator, so that nothing of it is worked out twice
    flat = source.select("id", "lang", F.inline(made))
    ascii_, all_ = F.col("c.ascii"), F.col("c.all")
    capital, digit, prose = ascii_ - F.col("c.no_capital"), ascii_ - F.col("c.no_digit"), ascii_ - F.col("c.no_prose")
    kinds = [F.col("total") - F.col("spaces") - all_, capital, digit, F.col("spaces"), prose, ascii_ - capital - digit - prose, all_ - ascii_]
    others = F.col("n_words") - F.aggregate("common", F.lit(0).cast("long"), lambda a, x: a + x)
    return flat.select("id", "lang", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", F.array(*[k.cast("long") for k in kinds]).alias("classes"), F.concat("common", F.array(others)).alias("common"))


def references(table: DataFrame, languages: list[str]) -> DataFrame:
    """One row for each language and one for all others (null): the summed histograms. Its size is that of the list."""
    lang = F.when(F.col("lang").isin(languages), F.col("lang"))
    size = len(next(iter(COMMON_WORDS.values()))) + 1
    sums = table.groupBy(lang.alias("ref")).agg(*_sum_counts("classes", len(CLASSES)), *_sum_counts("common", size))
    return sums.select("ref", F.array(*[f"classes{i}" for i in range(len(CLASSES))]).alias("ref_classes"), F.array(*[f"common{i}" for i in range(size)]).alias("ref_common"))


def js_distance(p: Column, q: Column) -> Column:
    """Jensen-Shannon distance (base 2) of two histograms of counts; 0 where either is empty."""
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    share = lambda a: F.transform(a, lambda x: x.cast("double") / F.greatest(total(a), F.lit(1.0)))
    part = lambda x, y: F.when(x > 0, x * F.log2(2 * x / (x + y))).otherwise(F.lit(0.0))
    both = F.get(F.transform(F.array(F.struct(share(p).alias("p"), share(q).alias("q"))), lambda h: total(F.zip_with(h["p"], h["q"], lambda x, y: part(x, y) + part(y, x)))), F.lit(0))
    return F.when((total(p) > 0) & (total(q) > 0), F.sqrt(F.greatest(both / 2, F.lit(0.0)))).otherwise(F.lit(0.0))


def judge(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", min_words: int = MIN_WORDS, max_class: float = MAX_CLASS_DISTANCE, max_word: float = MAX_WORD_DISTANCE) -> DataFrame:
    """The counts of each text with `class_distance`, `word_distance`, `base_failed` and `kept`.

    A text of fewer than 50 words, or with more than half of them in repeated three-word windows, fails; so does one of at least
    `min_words` words whose histograms are farther from its language's than allowed. Null and empty texts have no words and fail; a null
    or unlisted language is compared with all such documents. Repeated rows are judged each and count in the references; other columns
    are not read; an empty table gives an empty result.
    """
    scratch = Scratch(docs.sparkSession, "quality-rules")
    table = scratch.save(counts(docs, id_col=id_col, text_col=text_col, lang_col=lang_col), "counts")
    listed = sorted(COMMON_WORDS)
    refs = F.broadcast(references(table, listed))  # a row for each listed language and one more
    ref = F.when(F.col("lang").isin(listed), F.col("lang"))
    joined = table.join(refs, ref.eqNullSafe(F.col("ref")), "left")
    judged = joined.select(*table.columns, js_distance(F.col("classes"), F.col("ref_classes")).alias("class_distance"), js_distance(F.col("common"), F.col("ref_common")).alias("word_distance"))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    far = (F.col("n_words") >= min_words) & ((F.col("class_distance") > max_class) | (F.col("word_distance") > max_word))
    return judged.withColumn("base_failed", failed).withColumn("kept", ~failed & ~far)
