"""Repeated-line removal, in DataFrame functions only.

Line hashes with their document and position are written once, dealt out by range of (hash, document) so that even a line
held by a third of all documents is spread over many tasks, and sorted by document and position inside a range. Streaming over that
order, the first line of a hash in a document stands for the document; counting those gives the keys that are frequent and the one
document that keeps them. Each document that loses lines gets a keep bitmap: 64 lines a word, words without a loss left out. The text
itself is read again only to apply the bitmaps.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from semimul.llm.common import WORD_SPACE, Scratch, hash128, lower_ascii, spread_join


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def keep_bitmaps(docs: DataFrame, scratch: Scratch, *, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """Documents that lose lines: `id`, `n_dropped` and `words`, an array of (word, bits); bit p % 64 of word p / 64 is set where line p goes."""
    stripped = F.transform(_lines(F.col(text_col)), lambda x: F.trim(x, F.lit(WORD_SPACE)))
    hashed = F.transform(stripped, lambda x: F.when(F.char_length(x) >= min_chars, F.struct(*(h.alias(n) for h, n in zip(hash128(lower_ascii(x)), ("h1", "h2"))))))
    lines = docs.select(F.col(id_col).alias("id"), hashed.alias("hashes"))
    lines = lines.select("id", F.posexplode("hashes").alias("pos", "h")).filter("h is not null").select("h.h1", "h.h2", "id", "pos")
    lines = scratch.save(lines, "lines")

    dealt = lines.repartitionByRange("h1", "h2", "id").sortWithinPartitions("h1", "h2", "id", "pos")
    first = dealt.withColumn("nth", F.row_number().over(Window.partitionBy("h1", "h2", "id").orderBy("pos")))
    held = first.groupBy("h1", "h2").agg(F.count_if(F.col("nth") == 1).alias("n_docs"), F.max("id").alias("keeper"), F.count(F.lit(1)).alias("weight"))
    frequent = scratch.save(held.filter(F.col("n_docs") >= min_docs).select("h1", "h2", "keeper", "weight"), "frequent")

    # a line that very many documents hold is dealt over many tasks
    met = spread_join(lines, frequent.drop("weight"), ["h1", "h2"], frequent.select("h1", "h2", "weight"), lines.count(), ["id", "pos"])
    lost = met.filter(~F.col("id").eqNullSafe(F.col("keeper")))
    bit = F.expr("shiftleft(1L, pos % 64)")
    words = lost.groupBy("id", F.floor(F.col("pos") / 64).cast("int").alias("word")).agg(F.bit_or(bit).alias("bits"))
    return words.groupBy("id").agg(F.sum(F.bit_count("bits")).alias("n_dropped"), F.collect_list(F.struct("word", "bits")).alias("words"))


def drop_repeated_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """`docs` with the text's kept lines in `text_col`, and columns `n_lines` (before) and `n_dropped`.

    A line's key is the line without white space at its ends and with A-Z in lower case. Keys of at least `min_chars` code points that
    at least `min_docs` documents hold lose all their lines but those of the largest id holding them.

    Null and empty texts are one empty line. Rows that share an id count as one document whose losses are pooled by line number; a null
    id is one document, below all others. Repeated rows, ties, very long texts and an empty table need no care from the caller; columns
    named n_lines or n_dropped in the input are replaced, all others pass.
    """
    scratch = Scratch(docs.sparkSession, "line-dedup")
    maps = keep_bitmaps(docs, scratch, id_col=id_col, text_col=text_col, min_chars=min_chars, min_docs=min_docs).withColumnsRenamed({"id": "_lost_id", "n_dropped": "_n_lost", "words": "_lost"})
    old = docs.drop("n_lines", "n_dropped")
    joined = old.join(maps.hint("shuffle_hash"), F.col(id_col).eqNullSafe(F.col("_lost_id")), "left")
    last = F.array_max(F.transform("_lost", lambda x: x["word"]))
    absent = F.array_except(F.sequence(F.lit(0), last), F.transform("_lost", lambda x: x["word"]))
    every = F.concat("_lost", F.transform(absent, lambda w: F.struct(w.alias("word"), F.lit(0).cast("long").alias("bits"))))
    dense = F.transform(F.sort_array(every), lambda x: x["bits"])
    dense = F.when(F.col("_lost").isNotNull(), dense)
    bits = lambda d, i: F.coalesce(F.get(d, F.floor(i / 64).cast("int")), F.lit(0).cast("long"))
    # within transform() over one element the dense bitmap is a bound variable; as a column it would be worked out again for each line
    kept = F.get(F.transform(F.array(dense), lambda d: F.array_join(F.filter(_lines(F.col(text_col)), lambda x, i: F.getbit(bits(d, i), i % 64) == 0), "\n")), F.lit(0))
    text = F.coalesce(F.col(text_col), F.lit(""))
    joined = joined.withColumn("n_lines", F.when(F.col("_lost").isNull(), F.char_length(text) - F.char_length(F.replace(text, F.lit("\n"), F.lit(""))) + 1).otherwise(F.size(_lines(text))).cast("long"))
    return joined.select(
        *[F.when(F.col("_lost").isNull(), text).otherwise(kept).alias(c) if c == text_col else F.col(c) for c in old.columns],
        "n_lines", F.coalesce("_n_lost", F.lit(0)).cast("long").alias("n_dropped"),
    )
