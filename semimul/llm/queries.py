"""The operators' queries over the given tables, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm.substring_dedup import remove_repeats

    done = remove_repeats(table(spark, sf_dir, "documents"))
    return done.select(F.col("id").alias("doc_id"), "n_words", "n_removed", F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256"))


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm.pii import KINDS, find

    found = find(table(spark, sf_dir, "documents").select("doc_id", "text"))
    told = lambda name: F.array_join(F.transform(name, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    number = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select("doc_id", *[number(k) for k in KINDS[:4]], F.sha2(told("base").cast("binary"), 256).alias("base_sha256"), told("spans").alias("spans"), F.size(F.filter("spans", lambda s: s["kind"] == "secret")).cast("long").alias("n_secret"), (F.size("spans") - F.size("base")).cast("long").alias("n_added"))


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm.line_dedup import drop_repeated_lines

    kept = drop_repeated_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


def op1_compression_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm import quality_classifier as quality
    from semimul.llm.toxicity import held_out

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality.fit(docs, table(spark, sf_dir, "labels"))
    scored = quality.score(docs, model, name="score")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op2_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm.near_dup import near_duplicates

    found = near_duplicates(table(spark, sf_dir, "documents"), width=4, percent=80)
    return found.select(F.col("id").alias("doc_id"), "n_shingles", "component_id", (F.col("id") == F.col("component_id")).alias("kept"))


def op3_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm.html_extract import extract

    done = extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return done.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm.quality_rules import judge

    judged = judge(table(spark, sf_dir, "documents"))
    return judged.select(F.col("id").alias("doc_id"), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm.decontaminate import contamination

    found = contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    items = F.sha2(F.array_join("items", ",").cast("binary"), 256)
    return found.select(F.col("id").alias("doc_id"), "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), items.alias("items_sha256"), "contaminated")


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm import toxicity

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    scored = toxicity.score(docs, model, name="score")
    return scored.select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op9_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from semimul.llm.bpe import round_trip

    done = round_trip(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return done.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


QUERIES = {f.__name__: f for f in (op1_compression_quality, op2_near_dedup, op3_html_text, op4_quality_rules, op5_decontamination, op6_substring_dedup, op7_line_dedup, op8_toxicity, op9_byte_bpe, op10_pii)}


def _rules_sql() -> str:
    from semimul.llm import quality_rules as q

    listed = ", ".join(f"('{lang}', {i}, '{w}')" for lang, ws in q.COMMON_WORDS.items() for i, w in enumerate(ws))
    size = len(next(iter(q.COMMON_WORDS.values())))
    return rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, lang, coalesce(text, '') AS t,
                  list_filter(regexp_split_to_array(coalesce(text, ''), '[ \t\n\x0b\x0c\r]+'), lambda x: x <> '') AS w FROM documents),
x AS (SELECT r, lang, unnest(w) AS word, generate_subscripts(w, 1) AS s FROM d),
tri AS (SELECT r, s, word || ' ' || lead(word, 1) OVER q || ' ' || lead(word, 2) OVER q AS g FROM x WINDOW q AS (PARTITION BY r ORDER BY s)),
again AS (SELECT r, s FROM (SELECT r, s, g, count(*) OVER (PARTITION BY r, g) AS c FROM tri WHERE g IS NOT NULL) WHERE c > 1),
cover AS (SELECT r, count(DISTINCT s + o) AS n FROM again, range(3) z(o) GROUP BY r),
base AS (
  SELECT r, doc_id, lang, t, len(w) AS n_words, coalesce(list_sum(list_transform(w, lambda y: length(y))), 0)::BIGINT AS word_chars,
         length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS n_symbols,
         list_filter(string_split(t, chr(10)), lambda y: regexp_matches(y, '[^ \t\n\x0b\x0c\r]')) AS lines FROM d),
c AS (
  SELECT r, unnest([length(regexp_replace(t, '[^a-z]', '', 'g')), length(regexp_replace(t, '[^A-Z]', '', 'g')), length(regexp_replace(t, '[^0-9]', '', 'g')),
                    length(t) - word_chars, length(regexp_replace(t, '[^-.,;:!?''"()]', '', 'g')),
                    length(regexp_replace(t, '[^\x00-\x08\x0e-\x1f!-/:-@\[-`{{-\x7F]', '', 'g')) - length(regexp_replace(t, '[^-.,;:!?''"()]', '', 'g')),
                    length(regexp_replace(t, '[\x00-\x7F]', '', 'g'))]) AS n, generate_subscripts([1, 2, 3, 4, 5, 6, 7], 1) AS b FROM base),
l(lang, b, word) AS (VALUES {listed}),
hits AS (SELECT x.r, l.b, count(*) AS n FROM x JOIN l ON x.lang = l.lang AND lower(x.word) = l.word GROUP BY ALL),
k AS (SELECT base.r, g.b, coalesce(hits.n, 0) AS n FROM base CROSS JOIN range({size}) g(b) LEFT JOIN hits ON hits.r = base.r AND hits.b = g.b),
h AS (
  SELECT r, 'c' AS kind, b, n FROM c UNION ALL SELECT r, 'k', b, n FROM k
  UNION ALL SELECT r, 'k', {size}, n_words - coalesce((SELECT sum(n) FROM hits WHERE hits.r = base.r), 0) FROM base),
hl AS (SELECT h.*, CASE WHEN lang IN ({", ".join(f"'{x}'" for x in q.COMMON_WORDS)}) THEN lang END AS ref FROM h JOIN base USING (r)),
ref AS (SELECT ref, kind, b, sum(n)::DOUBLE AS m FROM hl GROUP BY ALL),
p AS (
  SELECT hl.r, hl.kind, hl.n / greatest(sum(hl.n) OVER (PARTITION BY hl.r, hl.kind), 1) AS x, ref.m / greatest(sum(ref.m) OVER (PARTITION BY hl.r, hl.kind), 1) AS y,
         sum(hl.n) OVER (PARTITION BY hl.r, hl.kind) AS tn FROM hl JOIN ref ON hl.ref IS NOT DISTINCT FROM ref.ref AND hl.kind = ref.kind AND hl.b = ref.b),
js AS (
  SELECT r, kind, CASE WHEN max(tn) > 0 THEN sqrt(greatest(sum(CASE WHEN x > 0 THEN x * log2(2 * x / (x + y)) ELSE 0 END + CASE WHEN y > 0 THEN y * log2(2 * y / (x + y)) ELSE 0 END) / 2, 0)) ELSE 0 END AS v
  FROM p GROUP BY ALL),
v AS (
  SELECT base.*, len(lines) - len(list_distinct(lines)) AS n_dup_lines, coalesce(cover.n, 0) AS n_repeat_words,
         (SELECT v FROM js WHERE js.r = base.r AND kind = 'c') AS cd, (SELECT v FROM js WHERE js.r = base.r AND kind = 'k') AS wd FROM base LEFT JOIN cover USING (r))
SELECT doc_id, n_words::BIGINT AS n_words, word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words,
       n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
       NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND NOT (n_words >= {q.MIN_WORDS} AND (cd > {q.MAX_CLASS_DISTANCE} OR wd > {q.MAX_WORD_DISTANCE})) AS kept
FROM v"""


ORACLES = {
    "op4_quality_rules": _rules_sql(),
    "op5_decontamination": r"""
WITH tr AS (SELECT 'ABCDEFGHIJKLMNOPQRSTUVWXYZ' AS u, 'abcdefghijklmnopqrstuvwxyz' AS l),
d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), u, l), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents, tr),
b AS (SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), u, l), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark, tr),
bw AS (SELECT DISTINCT item_id, least(len(w), 13) AS n, array_to_string(w[s:s + 12], ' ') AS t
       FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 12, 1) + 1)) AS s FROM b WHERE len(w) > 0)),
dx AS (SELECT doc_id, unnest(w) AS x, generate_subscripts(w, 1) AS s FROM d),
d13 AS (SELECT doc_id, s, string_agg(x, ' ') OVER (PARTITION BY doc_id ORDER BY s ROWS BETWEEN CURRENT ROW AND 12 FOLLOWING) AS t,
        count(*) OVER (PARTITION BY doc_id ORDER BY s ROWS BETWEEN CURRENT ROW AND 12 FOLLOWING) AS c FROM dx),
dw AS (SELECT doc_id, s, m, CASE WHEN m = 13 THEN t ELSE array_to_string(string_split(t, ' ')[1:m], ' ') END AS t
       FROM d13, (SELECT DISTINCT n AS m FROM bw) WHERE c >= m),
h AS (SELECT DISTINCT doc_id, s, m, item_id FROM dw JOIN bw ON dw.t = bw.t AND dw.m = bw.n),
p AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + m)) AS pos FROM h) GROUP BY doc_id),
i AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS items FROM (SELECT DISTINCT doc_id, item_id FROM h) GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN p USING (doc_id) LEFT JOIN i USING (doc_id)""",
    "op7_line_dedup": r"""
WITH l AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents),
k AS (
  SELECT doc_id, pos, line,
         translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
f AS (SELECT key, max(doc_id) AS keeper FROM k WHERE length(key) >= 40 GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
m AS (SELECT k.doc_id, k.pos, k.line, f.keeper IS NOT NULL AND f.keeper <> k.doc_id AS lost FROM k LEFT JOIN f USING (key))
SELECT doc_id, count(*)::BIGINT AS n_lines, sum(lost::INT)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT lost), '')) AS kept_sha256
FROM m GROUP BY doc_id""",
}
