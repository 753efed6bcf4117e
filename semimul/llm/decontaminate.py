"""Benchmark decontamination by a prefix-filtered containment join, in DataFrame functions only.

Each item is cut in windows of `size` words (a shorter item is one window) and each window in shingles. One pass over the documents keeps
the positions whose shingle is one of the benchmark's. Their counts order the shingles by rarity; since a window must be contained
whole, its one rarest shingle is all of the prefix that can be necessary, and a window with a shingle that no document has is dropped.
Documents meet windows on that shingle alone; its offset fixes where the window would start, which must leave room for the whole window.
What is left is verified over all positions of the window.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semimul.llm.common import Scratch, lower_ascii, spread_join

#: Words of a shingle; windows of fewer words are one shingle.
SHINGLE = 4
#: Benchmark shingles that are broadcast at most (about 16 MB); more are joined by a shuffle.
BROADCAST_SHINGLES = 500_000


def words(text: Column) -> Column:
    return F.array_remove(F.split(lower_ascii(F.coalesce(text, F.lit(""))), r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"), "")


def _shingles(w: Column, width: int, whole: bool = False) -> Column:
    """Hash of the shingle at each position of the words; `whole`: 0 at the places where too few words follow."""
    last = F.size(w) - (1 if whole else width)
    made = lambda i: F.xxhash64(F.lit(width), *[F.get(w, i + k) for k in range(width)])
    each = F.transform(F.sequence(F.lit(0), last), lambda i: F.when(i + width <= F.size(w), made(i)).otherwise(F.lit(0).cast("long")))
    return F.when(last >= 0, each).otherwise(F.expr("CAST(array() AS array<bigint>)"))


def windows(items: DataFrame, *, id_col: str = "item_id", text_col: str = "text", size: int = 13) -> DataFrame:
    """(wid, item, len, width, hashes): the windows of the items; equal windows have equal wid."""
    each = lambda w: F.transform(F.sequence(F.lit(0), F.greatest(F.size(w) - size, F.lit(0))), lambda s: F.slice(w, s + 1, F.lit(size)))
    cut = items.select(F.col(id_col).alias("item"), F.explode(F.transform(F.array(words(F.col(text_col))), each)).alias("ws"))
    cut = cut.select("item", F.explode("ws").alias("w")).filter(F.size("w") > 0)
    hashes = F.when(F.size("w") >= SHINGLE, _shingles(F.col("w"), SHINGLE))
    for width in range(1, SHINGLE):
        hashes = hashes.when(F.size("w") == width, _shingles(F.col("w"), width))
    return cut.select(F.sha2(F.array_join("w", " ").cast("binary"), 256).alias("wid"), "item", F.size("w").alias("len"), F.least(F.size("w"), F.lit(SHINGLE)).alias("width"), hashes.alias("hashes"))


def contamination(docs: DataFrame, items: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_id_col: str = "item_id", item_text_col: str = "text", size: int = 13, share: int = 20) -> DataFrame:
    """(id, n_words, n_hit, items, contaminated) for each row of `docs`: words inside occurrences of benchmark windows, and the items whose
    windows occur, sorted as strings. A document is contaminated if at least one in `share` of its words is hit.

    Null and empty texts have no words; items without words have no windows. Rows that share an id are one document with pooled positions
    (each row is returned); rows with a null id are returned without hits. Repeated items count once. Other columns are not read; empty tables on either side give
    documents without hits, or no rows.
    """
    scratch = Scratch(docs.sparkSession, "decontaminate")
    wins = scratch.save(windows(items, id_col=item_id_col, text_col=item_text_col, size=size).distinct(), "windows")
    unique = wins.select("wid", "len", "width", "hashes").distinct()
    needed = scratch.save(unique.select(F.explode("hashes").alias("h")).distinct(), "shingles")
    small = needed.count() <= BROADCAST_SHINGLES
    widths = sorted(r.width for r in unique.select("width").distinct().collect())  # four at most

    # bound as a lambda's variable the words are cut once a document; as a column they would be cut again at each position. Place 0 says that
    # the document is here: its hash is one of its own, so that no task gets the places 0 of all documents.
    made = F.transform(F.array(words(F.col(text_col))), lambda w: F.struct(F.size(w).alias("n"), F.concat(F.array(F.xxhash64(F.lit("document"), F.col(id_col), F.size(w))), *[_shingles(w, width, whole=True) for width in widths]).alias("hs")))
    hashed = docs.select(F.col(id_col).alias("id"), F.inline(made))
    spread = hashed.select("id", "n", F.posexplode("hs").alias("at", "h"))
    wanted = needed.withColumn("wanted", F.lit(True))
    met = spread.join(F.broadcast(wanted) if small else wanted, "h", "left").filter("at = 0 OR wanted")
    met = scratch.save(met.select("id", "n", "at", "h"), "met")
    marks = met.filter("at = 0").select("id", "n")
    # position in the document: shingles of each width stand in a block of n places behind the mark
    hits = met.filter("at > 0").select("id", "n", F.expr("CAST((at - 1) % n AS INT)").alias("pos"), "h")

    counts = scratch.save(hits.groupBy("h").agg(F.count(F.lit(1)).alias("df")), "counts")
    ranked = unique.select("wid", "len", "hashes", F.posexplode("hashes").alias("offset", "h")).join(counts, "h", "left")
    rarest = ranked.groupBy("wid", "len", "hashes").agg(F.min(F.struct(F.coalesce("df", F.lit(0)).alias("df"), "offset", "h")).alias("r")).filter("r.df > 0")
    rarest = scratch.save(rarest.select("wid", "len", "hashes", F.col("r.offset").alias("offset"), F.col("r.h").alias("h")), "rarest")
    placed = spread_join(hits, rarest, ["h"], counts.withColumnRenamed("df", "weight"), met.count(), ["id", "pos"]).withColumn("start", F.expr("pos - offset")).filter("start >= 0 AND start + len <= n")
    # all positions of the window
    laid = placed.select("id", "wid", "len", "start", F.size("hashes").alias("of"), F.posexplode("hashes").alias("k", "h"))
    laid = laid.select("id", "wid", "len", "start", "of", "h", F.expr("start + k").alias("pos"))
    agreed = laid.join(hits.select("id", "pos", "h").distinct(), ["id", "pos", "h"]).groupBy("id", "wid", "len", "start", "of").agg(F.count_distinct("pos").alias("places"))
    sure = scratch.save(agreed.filter("places = of").select("id", "wid", "len", "start"), "sure")

    n_hit = sure.select("id", F.explode(F.expr("sequence(start, start + len - 1)")).alias("pos")).groupBy("id").agg(F.count_distinct("pos").alias("n_hit"))
    found = sure.select("id", "wid").distinct().join(wins.select("wid", "item").distinct(), "wid").groupBy("id").agg(F.collect_set(F.col("item").cast("string")).alias("items"))
    per_doc = n_hit.join(found, "id").withColumnRenamed("id", "hit_id")
    out = marks.join(per_doc, F.col("id").eqNullSafe(F.col("hit_id")), "left")
    n_hit = F.coalesce("n_hit", F.lit(0))
    return out.select(
        "id", F.col("n").cast("long").alias("n_words"), n_hit.cast("long").alias("n_hit"), F.coalesce(F.array_sort("items"), F.expr("CAST(array() AS array<string>)")).alias("items"),
        ((n_hit > 0) & (share * n_hit >= F.col("n"))).alias("contaminated"),
    )
