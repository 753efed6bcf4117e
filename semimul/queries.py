"""Queries over the given tables for each method, variant, baseline, measure and operator, with the SQL they are held against."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semimul.functions import exact
from semimul.functions import semiring as sr
from semimul.functions import udf
from semimul.operators import graph, kernels
from semimul.operators import multiply as mul
from semimul.plans import cost, progress
from semimul.plans.staging import dropped, fresh, written
from semimul.plans.store import PartialLog, multiply_into
from semimul.sources import build, generate, select
from semimul.streaming import incremental as inc

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# SQL of the operands, as (k, i, v) and (k, j, v)
_LINE = "lineitem"
_JOINED = "(SELECT * FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"
_Q = "sum(l_quantity::BIGINT)::BIGINT"


def _m(source: str, key: str, other: str, name: str, value: str = "count(*)::BIGINT", where: str = "true") -> str:
    return f"SELECT {key} AS k, {other} AS {name}, {value} AS v FROM {source} WHERE {where} GROUP BY ALL"


_TERMS = "(SELECT {id} AS d, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS term FROM {t})"
_SQL = {
    "W1": (_m(_LINE, "l_orderkey", "l_partkey", "i", _Q), _m(_LINE, "l_orderkey", "l_suppkey", "j", _Q)),
    "W2": (_m(_LINE, "l_orderkey", "l_partkey", "i", _Q), _m(_LINE, "l_orderkey", "l_partkey", "j", _Q)),
    "W3": (_m(_LINE, "l_partkey", "l_suppkey", "i"), _m(_LINE, "l_partkey", "l_suppkey", "j")),
    "W4": (_m(_JOINED, "o_custkey", "l_partkey", "i", _Q), _m(_JOINED, "o_custkey", "l_partkey", "j", _Q)),
    "W5": (_m(_JOINED, "l_partkey", "o_custkey", "i"), _m(_JOINED, "l_partkey", "o_custkey", "j")),
    "W6": (_m(_LINE, "l_partkey", "l_suppkey", "i"), _m(_JOINED, "l_partkey", "o_custkey", "j")),
    "W7": (_m("events", "user_id", "event_type", "i"), _m("events", "user_id", "event_type", "j")),
    "W8": (_m("events", "date_trunc('hour', ts)", "user_id", "i"), _m("events", "date_trunc('hour', ts)", "user_id", "j")),
    "W9": (_m("events", "date_trunc('minute', ts)", "user_id", "i"), _m("events", "date_trunc('minute', ts)", "user_id", "j")),
    "W12": (_m("customer", "c_nationkey", "c_custkey", "i"), _m("nation", "n_nationkey", "n_regionkey", "j")),
    "W13": tuple(f"SELECT DISTINCT k, {n}, 1::BIGINT AS v FROM (SELECT page_id AS {n}, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS k FROM pages)" for n in "ij"),
    "W14": (_m(_TERMS.format(id="doc_id", t="documents"), "term", "d", "i"), _m(_TERMS.format(id="item_id", t="benchmark"), "term", "d", "j")),
    "W15": (_m("conversations", "conv_id", "role", "i"), _m("conversations", "conv_id", "turn", "j")),
}
_SQL["W10"] = tuple(_m(_TERMS.format(id="doc_id", t="documents"), "term", "d", n) for n in "ij")
_SQL["W11"] = tuple(f"SELECT generate_subscripts(embedding, 1) - 1 AS k, vec_id AS {n}, 1::BIGINT AS v FROM embeddings" for n in "ij")
_SQL["W10c"] = tuple(f"SELECT k, {n}, v FROM (SELECT *, count(*) OVER (PARTITION BY k) AS df FROM ({_m(_TERMS.format(id='doc_id', t='documents'), 'term', 'd', n)})) WHERE df <= 20" for n in "ij")


def ab(w: str) -> str:
    return f"WITH a AS ({_SQL[w][0]}), b AS ({_SQL[w][1]})"


def psql(w: str, value: str = "sum(a.v * b.v)::BIGINT", where: str = "true") -> str:
    return f"{ab(w)} SELECT i, j, {value} AS v FROM a JOIN b USING (k) WHERE {where} GROUP BY ALL"


def operands(w: str):
    return lambda spark, d: build.workload(spark, d, w)


def numbered(spark: SparkSession, d: str, w: str, n_of: str = "i") -> tuple[DataFrame, DataFrame]:
    return build.workload(spark, d, w)


# ---------------------------------------------------------------- products
def _product(name: str, w: str, make, value: str = "sum(a.v * b.v)::BIGINT", where: str = "true") -> None:
    query(name, psql(w, value, where))(lambda spark, d: make(*build.workload(spark, d, w)))


def _weighted(a: DataFrame, b: DataFrame) -> DataFrame:
    """Four bands of equal products, of written operands: these are read for the bounds and for the product."""
    return mul.hybrid_product(a, b, bands=4, bounds=cost.band_bounds_weighted(cost.partial_products_by_row(a, b), 4))


_product("outer_basket", "W2", lambda a, b: mul.outer_product(a, b))
_product("outer_part_supplier", "W1", lambda a, b: mul.outer_product(a, b))
_product("outer_supplier_pairs", "W3", lambda a, b: mul.outer_product(a, b))
_product("outer_parts_by_customer", "W4", lambda a, b: mul.outer_product(a, b))
_product("outer_customer_graph", "W5", lambda a, b: mul.outer_product(a, b))
_product("outer_by_minute", "W9", lambda a, b: mul.outer_product(a, b))
_product("outer_rare_terms", "W10c", lambda a, b: mul.outer_product(a, b))
_product("outer_terms", "W10", lambda a, b: mul.outer_product(a, b))
_product("outer_links", "W13", lambda a, b: mul.outer_product(a, b))
_product("outer_items", "W14", lambda a, b: mul.outer_product(a, b))
_product("outer_turns", "W15", lambda a, b: mul.outer_product(a, b))
_product("outer_presum_cached", "W2", lambda a, b: mul.fold(mul.outer_product(a, b, emit="presum", cache_entries=1000)))
_product("outer_blocks", "W1", lambda a, b: mul.outer_product(a, b, expand="blocks"))
_product("outer_by_hour", "W8", lambda a, b: mul.outer_product(a, b))
_product("outer_skewed", "W8", lambda a, b: mul.outer_product(a, b, tile=(16, 16)))
_product("outer_join", "W2", lambda a, b: mul.outer_product(a, b, expand="join"))
_product("outer_tiled", "W8", lambda a, b: mul.outer_product(a, b, expand="tiled", tile=(16, 16)))
_product("outer_cogroup", "W1", lambda a, b: mul.outer_product(a, b, expand="cogroup"))
_product("outer_build_a", "W6", lambda a, b: mul.outer_product(a, b, build_side="a"))
_product("outer_merge_join", "W6", lambda a, b: mul.outer_product(a, b, build_side="merge"))
_product("inner_ordered", "W1", lambda a, b: mul.inner_product(a, b, form="ordered"))
_product("inner_dot", "W7", lambda a, b: mul.inner_product(a, b, form="dot"))
_product("inner_multipass", "W7", lambda a, b: mul.inner_product(a, b, form="multipass"))
for _p in (1, 2, 8):
    _product(f"hybrid_p{_p}", "W6", lambda a, b, p=_p: mul.hybrid_product(a, b, bands=p))
_product("hybrid_replicated", "W6", lambda a, b: mul.hybrid_product(a, b, bands=4, execution="replicated"))
_product("hybrid_bounded_cache", "W6", lambda a, b: mul.hybrid_product(a, b, bands=4, cache_entries=500))
_product("hybrid_minplus", "W6", lambda a, b: mul.hybrid_product(a, b, sr.MIN_PLUS, bands=4), "min(a.v + b.v)")
_product("hybrid_weighted", "W6", lambda a, b: _weighted(written(a, "step"), written(b, "step")))
_product("hybrid_sequential", "W6", lambda a, b: mul.hybrid_product(a, b, bands=4, execution="sequential"))
_product("hybrid_broadcast", "W6", lambda a, b: mul.hybrid_product(a, b, bands=4, execution="broadcast"))
_product("rowwise", "W2", lambda a, b: mul.rowwise_product(a, b))
_product("grid_2x2", "W2", lambda a, b: mul.grid_product(a, b))
_product("multiply_partials", "W1", lambda a, b: mul.multiply(a, b, method="partials"))
_product("inner_minplus", "W1", lambda a, b: mul.inner_product(a, b, sr.MIN_PLUS), "min(a.v + b.v)")
_product("dense_brute_force", "W15", lambda a, b: mul.dense_product(a, b).filter("v <> 0"))
_product("any_first", "W7", lambda a, b: mul.outer_product(a, b, sr.ANY_FIRST), "min(a.v)")
_product("any_second", "W7", lambda a, b: mul.outer_product(a, b, sr.ANY_SECOND), "min(b.v)")
_product("subset_cols_filter", "W2", lambda a, b: mul.outer_product(select.select_cols(a, "10..50"), b), where="i BETWEEN 10 AND 50")
_product("multiply_auto", "W3", lambda a, b: mul.multiply(a, b))
_product("naive_join", "W1", lambda a, b: mul.naive_product(a, b))
_product("client_product", "W1", lambda a, b: mul.client_product(a, b, mode="auto")[0])
_product("client_streaming", "W1", lambda a, b: mul.client_product(a, b, mode="streaming", flush=50_000)[0])
_product("minplus_two_hop", "W1", lambda a, b: mul.outer_product(a, b, sr.MIN_PLUS), "min(a.v + b.v)")
_product("maxplus", "W1", lambda a, b: mul.outer_product(a, b, sr.MAX_PLUS), "max(a.v + b.v)")
_product("maxmin", "W2", lambda a, b: mul.outer_product(a, b, sr.MAX_MIN), "max(least(a.v, b.v))")
_product("minmax", "W2", lambda a, b: mul.outer_product(a, b, sr.MIN_MAX), "min(greatest(a.v, b.v))")
_product("maxtimes", "W1", lambda a, b: mul.outer_product(a, b, sr.MAX_TIMES), "max(a.v * b.v)")
_product("count_pairs", "W2", lambda a, b: mul.outer_product(a, b, sr.COUNT), "count(*)")
_product("gather_fold_median", "W6", lambda a, b: mul.outer_product(a, b, sr.gather(lambda vs: F.get(vs, F.floor((F.size(vs) - 1) / 2).cast("int")))), "list_sort(list(a.v * b.v))[(count(*) - 1) // 2 + 1]")
_product("arrow_mul", "W7", lambda a, b: mul.outer_product(a, b, udf.with_arrow_mul(lambda x, y: x * y)))
_product("udaf_fold", "W7", lambda a, b: udf.udaf_fold(mul.outer_product(a, b, emit="partials"), lambda v: int(v.max() - v.min())), "(max(a.v * b.v) - min(a.v * b.v))::BIGINT")
_product("reduce_fold", "W7", lambda a, b: udf.reduce_fold(mul.outer_product(a, b, emit="partials"), F.lit(0).cast("long"), lambda x, v: x + v))
_product("arrow_presum", "W1", lambda a, b: udf.arrow_presum(mul.outer_product(a, b, emit="partials")))
_product("subset_ranges", "W2", lambda a, b: mul.outer_product(select.select_rows(a, "1..5000;7001;9000..9500"), b), where="k BETWEEN 1 AND 5000 OR k = 7001 OR k BETWEEN 9000 AND 9500")


@query("semiring_bool", f"{ab('W6')} SELECT DISTINCT i, j, true AS v FROM a JOIN b USING (k)")
def _bool(spark, d):
    a, b = build.workload(spark, d, "W6")
    yes = lambda t: t.withColumn("v", F.col("v") > 0)
    return mul.outer_product(yes(a), yes(b), sr.OR_AND)


@query("argmin_witness", f"{ab('W1')} SELECT i, j, min(a.v + b.v) AS v, min_by(k, (a.v + b.v) * 1000000000 + k) AS via FROM a JOIN b USING (k) GROUP BY ALL")
def _argmin(spark, d):
    a, b = build.workload(spark, d, "W1")
    boxed = lambda t: t.withColumn("v", F.struct("v", F.col("k").alias("via")))
    return mul.outer_product(boxed(a), boxed(b), sr.ARG_MIN).select("i", "j", F.col("v.v").alias("v"), F.col("v.via").alias("via"))


#: Semiring, the samples it is tried on as an expression over the line numbers of the items, and its number of laws.
_LAWS = {
    "plus_times": (sr.PLUS_TIMES, "l_linenumber - 3", 5), "min_plus": (sr.MIN_PLUS, "l_linenumber - 3", 3), "max_plus": (sr.MAX_PLUS, "l_linenumber - 3", 3), "max_times": (sr.MAX_TIMES, "l_linenumber - 1", 5),
    "max_min": (sr.MAX_MIN, "l_linenumber - 3", 3), "min_max": (sr.MIN_MAX, "l_linenumber - 3", 3), "or_and": (sr.OR_AND, "l_linenumber > 3", 5), "any_first": (sr.ANY_FIRST, "l_linenumber - 1", 3),
}


@query("semiring_laws", "WITH l(law, nth) AS (VALUES ('sum commutes', 1), ('sum associates', 2), ('product distributes', 3), ('zero is neutral', 4), ('zero annihilates', 5)), s(semiring, laws, n) AS (" + " UNION ALL ".join(f"SELECT '{n}', {k}, count(DISTINCT {x}) FROM lineitem" for n, (_, x, k) in _LAWS.items()) + ") SELECT semiring, law, true AS holds, (n ** 3)::BIGINT AS cases FROM s, l WHERE nth <= laws")
def _laws(spark, d):
    line = written(build.table(spark, d, "lineitem").select(F.col("l_linenumber").cast("long").alias("l_linenumber")).distinct(), "samples")
    out = None
    for name, (s, samples, _) in _LAWS.items():
        one = sr.check_semiring(spark, s, line.select(F.expr(samples).alias("v")).distinct()).select(F.lit(name).alias("semiring"), "law", "holds", "cases")
        out = one if out is None else out.unionByName(one)
    return out


@query("subset_points", psql("W2", where="k IN (SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT')"))
def _points(spark, d):
    a, b = build.workload(spark, d, "W2")
    keys = build.table(spark, d, "orders").filter("o_orderpriority = '1-URGENT'").select(F.col("o_orderkey").alias("key"))
    return mul.outer_product(select.select_rows(a, keys), b)


@query("subset_range_table", psql("W2", where="EXISTS (SELECT 1 FROM (SELECT n_nationkey * 500 AS lo, n_nationkey * 500 + 100 AS hi FROM nation) WHERE k BETWEEN lo AND hi)"))
def _range_table(spark, d):
    a, b = build.workload(spark, d, "W2")
    ranges = build.table(spark, d, "nation").select((F.col("n_nationkey").cast("long") * 500).alias("low"), (F.col("n_nationkey").cast("long") * 500 + 100).alias("high"))
    return mul.outer_product(select.select_rows(a, ranges), b)


@query("subset_cols_transpose", psql("W2", where="i BETWEEN 10 AND 50"))
def _cols(spark, d):
    a, b = build.workload(spark, d, "W2")
    path = fresh(spark, "by-column")
    a.repartitionByRange("i").sortWithinPartitions("i", "k").write.parquet(path)
    return mul.outer_product(select.select_cols(a, "10..50", transposed=spark.read.parquet(path)), b)


@query("exact_decimal_product", "WITH a AS (SELECT l_orderkey AS k, l_partkey AS i, sum(round(l_extendedprice * 100)::BIGINT)::BIGINT AS v FROM lineitem GROUP BY ALL), b AS (SELECT l_orderkey AS k, l_suppkey AS j, sum(round(l_discount * 10000)::BIGINT)::BIGINT AS v FROM lineitem GROUP BY ALL) SELECT i, j, sum(a.v::HUGEINT * b.v)::VARCHAR AS v FROM a JOIN b USING (k) WHERE b.v <> 0 AND a.v <> 0 GROUP BY ALL")
def _exact(spark, d):
    line = build.table(spark, d, "lineitem")
    a = build.from_columns(line, F.col("l_orderkey"), F.col("l_partkey"), F.round(F.col("l_extendedprice") * 100).cast("long"))
    b = build.from_columns(line, F.col("l_orderkey"), F.col("l_suppkey"), F.round(F.col("l_discount") * 10000).cast("long"), "j")
    kind = lambda t, s: t.withColumn("v", (F.col("v").cast("decimal(18,0)") / F.lit(10**s)).cast(T.DecimalType(18, s)))
    a, b = kind(a, 2), kind(b, 4)
    out = exact.plan(T.DecimalType(18, 2), T.DecimalType(18, 4), 10) or T.DecimalType(38, 6)
    s = sr.Semiring("exact", F.sum, lambda x, y: exact.exact_mul(x.cast("decimal(18,2)"), y.cast("decimal(18,4)"), T.DecimalType(out.precision - 10 if out.precision > 28 else out.precision, 6)), 0)
    got = mul.outer_product(a, b, s)
    return got.select("i", "j", (F.col("v") * 1000000).cast("decimal(38,0)").cast("string").alias("v"))


@query("exact_limbs", f"{ab('W7')} SELECT i, j, (sum((a.v::HUGEINT * 1000000000000) * (b.v::HUGEINT * 1000000000000)))::VARCHAR AS v FROM a JOIN b USING (k) GROUP BY ALL")
def _limbs(spark, d):
    a, b = build.workload(spark, d, "W7")
    big = lambda t: t.withColumn("v", (F.col("v").cast("decimal(20,0)") * F.lit(10**12).cast("decimal(17,0)")).cast("decimal(38,0)"))
    return exact.limb_product(big(a), big(b), 0, 0)


# ---------------------------------------------------------------- log of partials
def _log(spark, s=sr.PLUS_TIMES) -> PartialLog:
    return PartialLog(spark, fresh(spark, "log"), s)


@query("outer_partials_then_scan", psql("W1"))
def _scan(spark, d):
    log = _log(spark)
    multiply_into(log, *build.workload(spark, d, "W1"), "w1")
    return log.scan()


def _four(spark, d) -> PartialLog:
    a, b = build.workload(spark, d, "W1")
    log = _log(spark)
    for q in range(4):
        log.append(mul.outer_product(a.filter(F.col("k") % 4 == q), b, emit="partials"), f"r{q}")
    log.append(mul.outer_product(a, b, emit="partials"), "r0")  # a run that is tried again changes nothing
    return log


@query("compact_minor", psql("W1"))
def _minor(spark, d):
    log = _four(spark, d)
    log.minor_compact(["r0", "r1"])
    return log.scan()


@query("compact_major", psql("W1"))
def _major(spark, d):
    log = _four(spark, d)
    log.major_compact()
    return log.live()


@query("scan_rows_pushed", psql("W1", where="i <= 20"))
def _pushed(spark, d):
    return _four(spark, d).scan(F.col("i") <= 20)


@query("transpose_written", "SELECT j AS i, i AS j, v FROM (" + psql("W6") + ")")
def _ct(spark, d):
    log = _log(spark)
    multiply_into(log, *build.workload(spark, d, "W6"), "w6", write="ct")
    return log.scan(orient="ct")


@query("write_both", f"WITH c AS ({psql('W1')}) SELECT 'c' AS orient, i, j, v FROM c UNION ALL SELECT 'ct', j, i, v FROM c")
def _both(spark, d):
    log = _log(spark)
    multiply_into(log, *build.workload(spark, d, "W1"), "w1", write="both")
    return log.scan(orient="c").select(F.lit("c").alias("orient"), "i", "j", "v").unionByName(log.scan(orient="ct").select(F.lit("ct").alias("orient"), "i", "j", "v"))


@query("write_both_compacted", f"WITH c AS ({psql('W1')}) SELECT 'c' AS orient, i, j, v FROM c UNION ALL SELECT 'ct', j, i, v FROM c")
def _both_compacted(spark, d):
    a, b = build.workload(spark, d, "W1")
    log = _log(spark)
    for q in range(3):
        log.append(mul.outer_product(a.filter(F.col("k") % 3 == q), b, emit="partials"), f"r{q}", "both")
    log.minor_compact(["r0", "r1"])
    log.major_compact()
    return log.live("c").select(F.lit("c").alias("orient"), "i", "j", "v").unionByName(log.live("ct").select(F.lit("ct").alias("orient"), "i", "j", "v"))


@query("transpose_compacted", "SELECT j AS i, i AS j, v FROM (" + psql("W6") + ")")
def _ct_compacted(spark, d):
    a, b = map(written, build.workload(spark, d, "W6"))
    log = _log(spark)
    for q in range(2):
        c = mul.outer_product(a.filter(F.col("k") % 2 == q), b, emit="presum", cache_entries=None, by="j")
        log.append(c, f"r{q}", "ct")
        dropped(c, "packs")
    dropped(a.crossJoin(b), "step")
    minor = log.minor_compact(["r0", "r1"])
    log.vacuum(["r0", "r1"])
    log.major_compact()
    log.vacuum([minor])
    return log.live("ct")


@query("accumulate_into", psql("W2", "2 * sum(a.v * b.v)::BIGINT"))
def _accumulate(spark, d):
    a, b = build.workload(spark, d, "W2")
    log = _log(spark)
    log.append(mul.outer_product(a, b), "first")
    multiply_into(log, a, b, "second")
    return log.scan()


@query("gather_by_compaction", psql("W7", "list_sort(list(a.v * b.v))[1]"))
def _gather(spark, d):
    log = _log(spark, sr.gather(lambda vs: F.get(vs, F.lit(0))))
    log.append(mul.outer_product(*build.workload(spark, d, "W7"), emit="partials"), "r")
    log.major_compact()
    return log.live()


# ---------------------------------------------------------------- monitoring, splits
_RUN = f"{ab('W1')}, p AS (SELECT k, da * db AS n FROM (SELECT k, count(*) AS da FROM a GROUP BY k) JOIN (SELECT k, count(*) AS db FROM b GROUP BY k) USING (k)), r AS (SELECT k, n, (sum(n) OVER (ORDER BY k))::BIGINT AS upto FROM p)"


@query("monitor_points", f"{_RUN} SELECT 1::BIGINT AS shard, k AS last_k, upto AS entries FROM r WHERE upto // 1000 > (upto - n) // 1000")
def _monitor(spark, d):
    return progress.monitor(*build.workload(spark, d, "W1"), 1000)


@query("monitor_inputs", f"{ab('W1')}, p AS (SELECT k, da + db AS n FROM (SELECT k, count(*) AS da FROM a GROUP BY k) JOIN (SELECT k, count(*) AS db FROM b GROUP BY k) USING (k)), r AS (SELECT k, n, (sum(n) OVER (ORDER BY k))::BIGINT AS upto FROM p) SELECT 1::BIGINT AS shard, k AS last_k, upto AS entries FROM r WHERE upto // 1000 > (upto - n) // 1000")
def _monitor_inputs(spark, d):
    return progress.monitor(*build.workload(spark, d, "W1"), 1000, unit="inputs")


_STEPS = f"{ab('W1')}, e AS (SELECT a.k, a.i, d AS n FROM a JOIN (SELECT k, count(*) AS d FROM b GROUP BY k) USING (k)), m AS (SELECT sum(n)::BIGINT // 5 + 1 AS every FROM e), r AS (SELECT k, i, n, (sum(n) OVER (ORDER BY k, i))::BIGINT AS upto FROM e)"


@query("monitor_run", f"{_STEPS} SELECT k AS last_k, i AS last_i, upto AS entries FROM r, m WHERE upto // every > (upto - n) // every")
def _monitor_run(spark, d):
    """Progress as counted while a run makes its products, one entry a step."""
    a, b = (written(t, "operand") for t in build.workload(spark, d, "W1"))
    got = progress.run_monitored(_log(spark), a, b, cost.partial_products(a, b).first()[0] // 5 + 1)
    return spark.createDataFrame([(e["last_k"], e["last_i"], e["entries"]) for e in got], "last_k long, last_i long, entries long")


@query("monitor_run_resumed", psql("W1"))
def _monitor_resumed(spark, d):
    """A run that stops after two steps, within a key, and is taken up again."""
    a, b = (written(t, "operand") for t in build.workload(spark, d, "W1"))
    log, every = _log(spark), cost.partial_products(a, b).first()[0] // 5 + 1
    progress.run_monitored(log, a, b, every, stop_after=2)
    progress.run_monitored(log, a, b, every)
    return log.scan()


@query("resume_within_key", psql("W1"))
def _resume_within(spark, d):
    a, b = build.workload(spark, d, "W1")
    log = _log(spark)
    log.append(mul.outer_product(a.filter("k < 3000 or (k = 3000 and i <= 100)"), b, emit="partials"), "head")
    log.append(progress.resume_after(a, b, 3000, i_after=100, emit="partials"), "tail")
    return log.scan()


@query("scan_uncommitted", psql("W1"))
def _uncommitted(spark, d):
    """An early look: half of the product is live, the other half is written and not committed."""
    a, b = build.workload(spark, d, "W1")
    log = _log(spark)
    log.append(mul.outer_product(a.filter("k % 2 = 0"), b, emit="partials"), "even")
    log.write_run(mul.outer_product(a.filter("k % 2 = 1"), b, emit="partials"), "odd")
    return log.scan(allow_uncommitted=True)


@query("resume_after_key", psql("W1"))
def _resume(spark, d):
    a, b = build.workload(spark, d, "W1")
    log = _log(spark)
    log.append(mul.outer_product(a.filter("k < 3000 or (k = 3000 and i <= 100)"), b, emit="partials"), "head")
    log.append(progress.resume_after(a, b, 3000, i_after=None, emit="partials"), "tail")
    log.append(mul.outer_product(a.filter("k = 3000 and i > 100"), b, emit="partials"), "rest")
    return log.scan()


for _n in (2, 4):
    query(f"split_points_{_n}", f"WITH a AS ({_SQL['W1'][0]}), r AS (SELECT k, sum(n) OVER (ORDER BY k) AS upto, sum(n) OVER () AS total FROM (SELECT k, count(*) AS n FROM a GROUP BY k)) SELECT (t + 1)::BIGINT AS shard, min(k) AS first FROM r, range(1, {_n}) s(t) WHERE upto * {_n} >= t * total GROUP BY t")(
        lambda spark, d, n=_n: progress.even_splits(progress.split_weights(build.workload(spark, d, "W1")[0]), n))


@query("split_by_products", f"{_RUN} SELECT (t + 1)::BIGINT AS shard, min(k) AS first FROM (SELECT *, sum(n) OVER () AS total FROM r), range(1, 3) s(t) WHERE upto * 3 >= t * total GROUP BY t")
def _split_pp(spark, d):
    return progress.even_splits(progress.split_weights(*build.workload(spark, d, "W1")), 3)


@query("presplit_layout", f"WITH a AS ({_SQL['W1'][0]}) SELECT CASE WHEN k >= 4000 THEN 2 ELSE 1 END AS shard, count(*) AS entries, min(k) AS first, max(k) AS last FROM a GROUP BY 1")
def _layout(spark, d):
    plan = progress.SplitPlan([4000])
    plan.save(spark, path := fresh(spark, "splits"))
    laid = progress.SplitPlan.load(spark, path).rewrite(build.workload(spark, d, "W1")[0], "k", fresh(spark, "laid"))
    return laid.groupBy("shard").agg(F.count(F.lit(1)).alias("entries"), F.min("k").alias("first"), F.max("k").alias("last"))


# ---------------------------------------------------------------- measures
_MEASURED = ["W1", "W2", "W3", "W4", "W5", "W6", "W7", "W8", "W9", "W10", "W11", "W12", "W13", "W14", "W15"]


def _each(f):
    def run(spark, d):
        out = None
        for w in _MEASURED:
            one = f(*build.workload(spark, d, w)).withColumn("workload", F.lit(w))
            out = one if out is None else out.unionByName(one)
        return out

    return run


_PP = "(SELECT coalesce(sum(da * db), 0)::BIGINT AS pp FROM (SELECT k, count(*) AS da FROM ({0}) GROUP BY k) JOIN (SELECT k, count(*) AS db FROM ({1}) GROUP BY k) USING (k))"
_NC = "(SELECT count(*) AS n_c FROM (SELECT DISTINCT i, j FROM ({0}) a JOIN ({1}) b USING (k)))"
query("pp_total", " UNION ALL ".join(f"SELECT pp, '{w}' AS workload FROM {_PP.format(*_SQL[w])}" for w in _MEASURED))(_each(cost.partial_products))
query("after_sum", " UNION ALL ".join(f"SELECT n_c, '{w}' AS workload FROM {_NC.format(*_SQL[w])}" for w in _MEASURED))(_each(cost.result_entries))
query("write_amplification", " UNION ALL ".join(f"SELECT pp, n_c, pp * 1000 // n_c AS ratio_milli, '{w}' AS workload FROM {_PP.format(*_SQL[w])}, {_NC.format(*_SQL[w])}" for w in _MEASURED))(_each(cost.write_amplification))
query("pp_by_key", f"{ab('W1')} SELECT k, da * db AS pp FROM (SELECT k, count(*) AS da FROM a GROUP BY k) JOIN (SELECT k, count(*) AS db FROM b GROUP BY k) USING (k)")(lambda spark, d: cost.partial_products_by_key(*build.workload(spark, d, "W1")))
query("pp_by_row", f"{ab('W1')} SELECT i, count(*) AS pp FROM a JOIN b USING (k) GROUP BY i")(lambda spark, d: cost.partial_products_by_row(*build.workload(spark, d, "W1")))
query("cost_profile", f"{ab('W1')}, s AS (SELECT (SELECT count(*) FROM a) AS na, (SELECT count(*) FROM b) AS nb, (SELECT count(DISTINCT i) FROM a) AS r, (SELECT count(*) FROM a JOIN b USING (k)) AS pp, (SELECT count(*) FROM (SELECT DISTINCT i, j FROM a JOIN b USING (k))) AS nc) SELECT * FROM (SELECT 'outer partials' AS method, na + nb AS reads, pp AS least_writes, pp AS most_writes, 1::BIGINT AS passes_b FROM s UNION ALL SELECT 'outer summed', na + nb, nc, pp, 1 FROM s UNION ALL SELECT 'inner', na + r * nb, nc, nc, r FROM s UNION ALL SELECT 'hybrid', na + 4 * nb, nc, pp, 4 FROM s UNION ALL SELECT 'client', na + nb, nc, nc, 1 FROM s)")(lambda spark, d: cost.profile(*build.workload(spark, d, "W1")))


@query("dense_worst_case", "WITH a AS (SELECT generate_subscripts(embedding, 1) AS k, vec_id AS i FROM embeddings WHERE vec_id < 100) SELECT count(*) AS pp, count(DISTINCT (a.i, b.i)) AS n_c, count(*) * 1000 // count(DISTINCT (a.i, b.i)) AS ratio_milli FROM a JOIN a b USING (k)")
def _dense(spark, d):
    return cost.write_amplification(*build.workload(spark, d, "W11c"))


query("dense_worst_case_all", "WITH a AS (SELECT generate_subscripts(embedding, 1) AS k, vec_id AS i FROM embeddings) SELECT count(*) AS pp, count(DISTINCT (a.i, b.i)) AS n_c, count(*) * 1000 // count(DISTINCT (a.i, b.i)) AS ratio_milli FROM a JOIN a b USING (k)")(
    lambda spark, d: cost.write_amplification(*build.workload(spark, d, "W11")))


@query("band_bounds_table", "SELECT n, p, b, ((b - 1) * n // p + 1)::BIGINT AS low, (b * n // p)::BIGINT AS high FROM (SELECT (SELECT count(*) FROM part) AS n), (VALUES (1), (2), (3), (7)) t(p), LATERAL (SELECT unnest(range(1, p + 1)) AS b)")
def _bounds(spark, d):
    n = build.table(spark, d, "part").agg(F.count("p_partkey")).first()[0]  # of the column: a plain count reads no rows
    return spark.createDataFrame([(n, p, q + 1, low, high) for p in (1, 2, 3, 7) for q, (low, high) in enumerate(cost.band_bounds(n, p))], "n long, p int, b long, low long, high long")


_CRITERIA = "(VALUES ('average'), ('strict')) c(criterion)"


@query("choose_bands_table", f"WITH s AS (SELECT count(DISTINCT l_partkey) AS n, count(DISTINCT l_suppkey) AS l FROM lineitem), t AS (SELECT n, l, unnest([l + l // 2, 5 * l, l * 3 // 4]) AS budget FROM s) SELECT n, l, budget, criterion, CASE WHEN l > budget THEN NULL WHEN criterion = 'average' THEN (n * l + budget - 1) // budget ELSE (n + budget // l - 1) // (budget // l) END AS bands FROM t, {_CRITERIA}")
def _choose(spark, d):
    """Bands for the rows and columns that the given table has, under three budgets; the last holds no row."""
    n, l = build.table(spark, d, "lineitem").agg(F.count_distinct("l_partkey"), F.count_distinct("l_suppkey")).first()
    return spark.createDataFrame([(n, l, m, c, cost.choose_bands(n, l, m, c)) for m in (l + l // 2, 5 * l, l * 3 // 4) for c in ("average", "strict")], "n long, l long, budget long, criterion string, bands long")


# ---------------------------------------------------------------- generated graphs
def _g(spark, scale, seed):
    return generate.power_law_graph(spark, scale, seed)


_ORDERS = "SELECT o_orderkey FROM orders"


def _drawn(spark, d, scale, seed):
    """A graph with one edge drawn for each order, by its number."""
    return generate.power_law_graph(spark, scale, seed, numbers=build.table(spark, d, "orders").select(F.col("o_orderkey").cast("long").alias("e")))


query("power_law_edges", f"SELECT row, col, 1::BIGINT AS v FROM ({generate.sql(8, 1, numbers=_ORDERS)})")(lambda spark, d: _drawn(spark, d, 8, 1))
query("power_law_product", f"WITH a AS ({generate.sql(6, 1, numbers=_ORDERS)}), b AS ({generate.sql(6, 2, numbers=_ORDERS)}) SELECT a.col AS i, b.col AS j, count(*) AS v FROM a JOIN b USING (row) GROUP BY ALL")(
    lambda spark, d: mul.outer_product(_drawn(spark, d, 6, 1).select(F.col("row").alias("k"), F.col("col").alias("i"), "v"), kernels.by_row(_drawn(spark, d, 6, 2))))
query("power_law_sizes", f"WITH a AS ({generate.sql(10, 1, numbers=_ORDERS)}), b AS ({generate.sql(10, 2, numbers=_ORDERS)}), p AS (SELECT a.col AS i, b.col AS j, count(*) AS n FROM a JOIN b USING (row) GROUP BY ALL) SELECT sum(n)::BIGINT AS pp, count(*) AS n_c, sum(n)::BIGINT * 1000 // count(*) AS ratio_milli FROM p")(
    lambda spark, d: cost.write_amplification(written(_drawn(spark, d, 10, 1), "graph").select(F.col("row").alias("k"), F.col("col").alias("i"), "v"), kernels.by_row(written(_drawn(spark, d, 10, 2), "graph"))))
_E6 = generate.sql(6, 1)
_TWO = f"WITH a AS (SELECT *, 1::BIGINT AS v FROM ({_E6})), b AS (SELECT *, 1::BIGINT AS v FROM ({generate.sql(6, 2)})), c AS (SELECT a.row, b.col, sum(a.v * b.v)::BIGINT AS v FROM a JOIN b ON a.col = b.row GROUP BY ALL), d AS (SELECT c.row, b.col, sum(c.v * b.v)::BIGINT AS v FROM c JOIN b ON c.col = b.row GROUP BY ALL) SELECT row, col, sum(v)::BIGINT AS v FROM (SELECT * FROM a UNION ALL SELECT * FROM d) GROUP BY ALL"
for _plan in ("staged", "fold_into", "temporary"):
    query(f"two_step_{_plan}", _TWO)(lambda spark, d, plan=_plan: graph.two_step_union(_g(spark, 6, 1), _g(spark, 6, 2), plan=plan))


_LINKS = "SELECT DISTINCT l_partkey AS row, l_suppkey AS col FROM lineitem"


def _links(spark, d):
    """Parts and suppliers as nodes by their numbers: a link from each part to the supplier of each of its items."""
    line = build.table(spark, d, "lineitem").select(F.col("l_partkey").cast("long").alias("row"), F.col("l_suppkey").cast("long").alias("col"))
    return written(line.distinct().withColumn("v", F.lit(1).cast("long")), "links")


_LINES = "SELECT l_suppkey AS row, l_linenumber::BIGINT AS col, count(*)::BIGINT AS v FROM lineitem GROUP BY ALL"


def _lines(spark, d):
    """Suppliers and line numbers as nodes by their numbers, with the count of a supplier's items on each line."""
    line = build.table(spark, d, "lineitem")
    got = build.from_columns(line, F.col("l_suppkey").cast("long"), F.col("l_linenumber").cast("long"))
    return written(got.select(F.col("k").alias("row"), F.col("i").alias("col"), "v"), "lines")


def _start(spark):
    return spark.createDataFrame([(1,)], "node long")


query("bfs_levels", f"WITH RECURSIVE e AS ({_LINKS}), r AS (SELECT 1::BIGINT AS node, 0 AS level UNION SELECT e.col, r.level + 1 FROM r JOIN e ON e.row = r.node WHERE r.level < 8) SELECT node, min(level) AS level FROM r GROUP BY node")(lambda spark, d: graph.bfs(_start(spark), _links(spark, d), 8))
query("even_reach", f"WITH RECURSIVE e AS ({_LINKS}), r AS (SELECT 1::BIGINT AS node UNION SELECT y.col FROM r JOIN e x ON x.row = r.node JOIN e y ON y.row = x.col) SELECT node FROM r")(lambda spark, d: graph.even_reach(_start(spark), _links(spark, d), 40))
query("bool_reach2", f"WITH e AS ({_LINKS}) SELECT DISTINCT y.col AS node FROM e x JOIN e y ON y.row = x.col WHERE x.row = 1")(lambda spark, d: graph.reach2(_start(spark), _links(spark, d)))
query("shortest_paths", f"WITH RECURSIVE e AS (SELECT row, col, (row * 7 + col * 3) % 9 + 1 AS w FROM ({_E6})), r AS (SELECT 1::BIGINT AS node, 0::BIGINT AS dist UNION SELECT e.col, r.dist + e.w FROM r JOIN e ON e.row = r.node WHERE r.dist + e.w < 24) SELECT node, min(dist)::BIGINT AS dist FROM r GROUP BY node")(
    lambda spark, d: graph.sssp(_start(spark), _g(spark, 6, 1).withColumn("v", (F.col("row") * 7 + F.col("col") * 3) % 9 + 1)).filter("dist < 24"))
# all distances: a least path has fewer edges than there are nodes, each of weight 9 at most
query("shortest_paths_all", f"WITH RECURSIVE e AS (SELECT row, col, (row * 7 + col * 3) % 9 + 1 AS w FROM ({_E6})), m AS (SELECT 9 * count(*) AS most FROM (SELECT row FROM e UNION SELECT col FROM e)), r AS (SELECT 1::BIGINT AS node, 0::BIGINT AS dist UNION SELECT e.col, r.dist + e.w FROM r JOIN e ON e.row = r.node, m WHERE r.dist + e.w <= most) SELECT node, min(dist)::BIGINT AS dist FROM r GROUP BY node")(
    lambda spark, d: graph.sssp(_start(spark), _g(spark, 6, 1).withColumn("v", (F.col("row") * 7 + F.col("col") * 3) % 9 + 1)))
query("triangles", f"WITH e AS (SELECT DISTINCT greatest(row, col) AS a, least(row, col) AS b FROM ({_E6}) WHERE row <> col) SELECT count(*) AS n FROM e x JOIN e y ON x.b = y.a JOIN e z ON z.a = x.a AND z.b = y.b")(
    lambda spark, d: kernels.triangles(kernels.ewise_add(_g(spark, 6, 1), kernels.transpose(_g(spark, 6, 1)), sr.COUNT).filter("row <> col")))
query("power_3", f"WITH e AS ({_LINES}), s AS (SELECT x.row, y.col, sum(x.v * y.v)::BIGINT AS v FROM e x JOIN e y ON x.col = y.row GROUP BY ALL) SELECT s.row, e.col, sum(s.v * e.v)::BIGINT AS v FROM s JOIN e ON s.col = e.row GROUP BY ALL")(lambda spark, d: kernels.power(_lines(spark, d), 3))
_RANK = f"WITH e AS ({_E6}), n AS (SELECT row AS node FROM e UNION SELECT col FROM e), m AS (SELECT count(*)::DOUBLE AS m FROM n), w AS (SELECT row, col, 1.0::DOUBLE / count(*) OVER (PARTITION BY row) AS w FROM e), s0 AS (SELECT node, 1.0::DOUBLE / m AS s FROM n, m)"
for _q in range(1, 11):
    _RANK += f", g{_q} AS (SELECT n.node, coalesce(sum(s.s * w.w), 0) AS g FROM n LEFT JOIN w ON w.col = n.node LEFT JOIN s{_q - 1} s ON s.node = w.row GROUP BY n.node), s{_q} AS (SELECT node, 0.15 / m + 0.85 * (1 - (SELECT sum(g) FROM g{_q})) / m + 0.85 * g AS s FROM g{_q}, m)"
query("rank", f"{_RANK} SELECT node, round(s * 100000000)::BIGINT AS score FROM s10")(lambda spark, d: graph.rank(_g(spark, 6, 1)).select("node", F.round(F.col("score") * 100000000).cast("long").alias("score")))
_CH = "WITH a AS (SELECT c_custkey AS row, c_nationkey AS col, 1::BIGINT AS v FROM customer), b AS (SELECT n_nationkey AS row, n_regionkey AS col FROM nation), c AS (SELECT DISTINCT r_regionkey AS row, length(r_name)::BIGINT AS col FROM region) SELECT a.row, c.col, count(*) AS v FROM a JOIN b ON a.col = b.row JOIN c ON b.col = c.row GROUP BY ALL"


def _chain(spark, d, **o):
    one = F.lit(1).cast("long").alias("v")
    t = lambda n: build.table(spark, d, n)
    ms = [t("customer").select(F.col("c_custkey").alias("row"), F.col("c_nationkey").alias("col"), one), t("nation").select(F.col("n_nationkey").alias("row"), F.col("n_regionkey").alias("col"), one), t("region").select(F.col("r_regionkey").alias("row"), F.length("r_name").cast("long").alias("col"), one)]
    return graph.chain(ms, **o)


for _n, _o in {"chain_fused": {}, "chain_unsummed": {"fuse": "unsummed"}, "chain_materialised": {"fuse": "materialise"}, "chain_auto_order": {"order": "auto"}}.items():
    query(_n, _CH)(lambda spark, d, o=_o: _chain(spark, d, **o))


@query("join_as_product", "SELECT c_custkey AS i, n_regionkey AS j, array_to_string(list_sort(list_distinct([c_nationkey::VARCHAR])), ',') AS v FROM customer JOIN nation ON c_nationkey = n_nationkey")
def _jap(spark, d):
    a, b = build.workload(spark, d, "W12")
    got = graph.join_as_product(a.withColumn("v", F.col("k")), b.withColumn("v", F.col("k")))
    return got.select("i", "j", F.array_join("v", ",").alias("v"))


@query("pipeline_rows", f"SELECT i AS row, sum(v)::BIGINT AS total FROM ({psql('W6')}) GROUP BY i")
def _pipe(spark, d):
    import pyarrow as pa

    def consumer(batches):
        for b in batches:
            t = pa.Table.from_batches([b]).group_by("row").aggregate([("v", "sum")])
            yield from pa.table({"row": t["row"], "total": t["v_sum"]}).to_batches()

    a, b = build.workload(spark, d, "W6")
    left = a.select(F.col("i").alias("row"), F.col("k").alias("col"), "v")
    right = b.select(F.col("k").alias("row"), F.col("j").alias("col"), "v")
    return graph.pipeline_rows(left, right, consumer, "row long, total long").groupBy("row").agg(F.sum("total").alias("total"))


@query("pipeline_partials", f"SELECT i, j, 3 * v AS v FROM ({psql('W6')})")
def _pipe_partials(spark, d):
    """Unsummed products through a consumer that distributes over the sum, which is done after it."""
    import pyarrow as pa
    import pyarrow.compute as pc

    def consumer(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b["i"], b["j"], pc.multiply(b["v"], 3)], schema=b.schema)

    a, b = build.workload(spark, d, "W6")
    left = a.select(F.col("i").alias("row"), F.col("k").alias("col"), "v")
    right = b.select(F.col("k").alias("row"), F.col("j").alias("col"), "v")
    return mul.fold(graph.pipeline_partials(left, right, consumer, "i long, j long, v long", distributes=True))


@query("cosine_suppliers", f"WITH a AS ({_SQL['W3'][0]}), c AS (SELECT a.i, b.i AS j, sum(a.v * b.v)::BIGINT AS v FROM a JOIN a b USING (k) GROUP BY ALL), n AS (SELECT i, sqrt(v::DOUBLE) AS norm FROM c WHERE i = j) SELECT c.i, c.j, floor(c.v::DOUBLE / (x.norm * y.norm) * 1000000)::BIGINT AS v FROM c JOIN n x ON x.i = c.i JOIN n y ON y.i = c.j WHERE c.i < c.j")
def _cosine(spark, d):
    return graph.cosine(build.workload(spark, d, "W3")[0])


@query("inner_is_sorted", "SELECT true AS sorted, (SELECT count(*) FROM (" + psql("W1") + ")) AS cells")
def _inner_sorted(spark, d):
    c = written(mul.inner_product(*build.workload(spark, d, "W1")), "ordered")
    return spark.createDataFrame([(mul.is_sorted(mul.inner_product(*build.workload(spark, d, "W1")), ["i", "j"]), c.count())], "sorted boolean, cells long")


# ---------------------------------------------------------------- kernels
_S = "(SELECT l_partkey AS row, l_suppkey AS col, sum(l_quantity::BIGINT)::BIGINT AS v FROM lineitem GROUP BY ALL)"
_R = "(SELECT l_partkey AS row, l_suppkey AS col, count(*)::BIGINT AS v FROM lineitem WHERE l_returnflag = 'R' GROUP BY ALL)"


def _s(spark, d, flag: bool = False):
    line = build.table(spark, d, "lineitem")
    got = build.from_columns(line.filter("l_returnflag = 'R'"), F.col("l_partkey"), F.col("l_suppkey")) if flag else build.from_columns(line, F.col("l_partkey"), F.col("l_suppkey"), F.col("l_quantity").cast("long"))
    return got.select(F.col("k").alias("row"), F.col("i").alias("col"), "v")


query("transpose", f"SELECT col AS row, row AS col, v FROM {_S}")(lambda spark, d: kernels.transpose(_s(spark, d)))
query("apply", f"SELECT row, col, v * v + 1 AS v FROM {_S}")(lambda spark, d: kernels.apply(_s(spark, d), lambda v: v * v + 1))
query("select_tril", f"SELECT * FROM {_S} WHERE row >= col")(lambda spark, d: kernels.tril(_s(spark, d)))
query("select_vals", f"SELECT * FROM {_S} WHERE v > 30")(lambda spark, d: kernels.select_vals(_s(spark, d), F.col("v") > 30))
query("reduce_rows", f"SELECT row, sum(v)::BIGINT AS v FROM {_S} GROUP BY row")(lambda spark, d: kernels.reduce_rows(_s(spark, d)))
query("reduce_cols", f"SELECT col, max(v) AS v FROM {_S} GROUP BY col")(lambda spark, d: kernels.reduce_cols(_s(spark, d), sr.MAX_PLUS))
query("reduce_all", f"SELECT sum(v)::BIGINT AS v FROM {_S}")(lambda spark, d: kernels.reduce_all(_s(spark, d)))
query("ewise_add", f"SELECT row, col, sum(v)::BIGINT AS v FROM (SELECT * FROM {_S} UNION ALL SELECT * FROM {_R}) GROUP BY ALL")(lambda spark, d: kernels.ewise_add(_s(spark, d), _s(spark, d, True)))
query("ewise_mult", f"SELECT s.row, s.col, s.v * r.v AS v FROM {_S} s JOIN {_R} r ON s.row = r.row AND s.col = r.col")(lambda spark, d: kernels.ewise_mult(_s(spark, d), _s(spark, d, True)))
query("extract", f"SELECT * FROM {_S} WHERE row <= 100 AND col IN (SELECT s_suppkey FROM supplier WHERE s_nationkey < 5)")(
    lambda spark, d: kernels.extract(_s(spark, d), F.col("row") <= 100, build.table(spark, d, "supplier").filter("s_nationkey < 5").select("s_suppkey")))
query("assign", f"SELECT * FROM {_S} WHERE NOT (row <= 50 AND col <= 5) UNION ALL SELECT * FROM {_R} WHERE row <= 50 AND col <= 5")(
    lambda spark, d: kernels.assign(_s(spark, d), _s(spark, d, True).filter("row <= 50 and col <= 5"), spark.range(0, 51), spark.range(0, 6)))
query("scale", f"SELECT s.row, s.col, s.v * p.p_size AS v FROM {_S} s JOIN part p ON s.row = p.p_partkey")(
    lambda spark, d: kernels.scale(_s(spark, d), build.table(spark, d, "part").select(F.col("p_partkey").alias("key"), F.col("p_size").cast("long").alias("x"))))
query("kron", f"WITH a AS (SELECT * FROM {_S} WHERE row <= 5), b AS (SELECT * FROM {_R} WHERE row <= 5) SELECT a.row, b.row AS row2, a.col, b.col AS col2, a.v * b.v AS v FROM a, b")(
    lambda spark, d: kernels.kron(_s(spark, d).filter("row <= 5"), _s(spark, d, True).filter("row <= 5")))
query("kron_tables", "SELECT n.n_nationkey AS row, r.r_regionkey AS row2, n.n_regionkey AS col, length(r.r_name)::BIGINT AS col2, (n.n_nationkey + 1) * (r.r_regionkey + 2) AS v FROM nation n, region r")(
    lambda spark, d: kernels.kron(build.table(spark, d, "nation").select(F.col("n_nationkey").alias("row"), F.col("n_regionkey").alias("col"), (F.col("n_nationkey") + 1).alias("v")), build.table(spark, d, "region").select(F.col("r_regionkey").alias("row"), F.length("r_name").cast("long").alias("col"), (F.col("r_regionkey") + 2).alias("v"))))
query("identity_product", f"SELECT * FROM {_S}")(lambda spark, d: kernels.product(_s(spark, d), kernels.identity(_s(spark, d).select("col").distinct())))
query("degrees", f"SELECT row, count(*) AS degree FROM {_S} GROUP BY row")(lambda spark, d: kernels.degrees(_s(spark, d)))


def _diagonal(a: DataFrame, b: DataFrame) -> DataFrame:
    """The cells i = j that a product of these operands can have."""
    return a.select("i").distinct().join(b.select("j").distinct(), F.col("i") == F.col("j"))


def _masked(spark, d, **o):
    a, b = build.workload(spark, d, "W6")
    return mul.multiply(a, b, mask=_diagonal(a, b), **o)


query("masked", psql("W6", where="i = j"))(lambda spark, d: _masked(spark, d))
query("masked_complement", psql("W6", where="i <> j"))(lambda spark, d: _masked(spark, d, complement=True))
query("top_k_cells", f"SELECT row, col, v, rank FROM (SELECT *, row_number() OVER (PARTITION BY row ORDER BY v DESC, col)::INT AS rank FROM {_S}) WHERE rank <= 3")(lambda spark, d: kernels.top_k(_s(spark, d), 3))


@query("label_vector_product", f"WITH c AS ({psql('W10c')}), l AS (SELECT DISTINCT doc_id, quality::BIGINT AS q FROM labels WHERE quality IS NOT NULL AND quality <> 0) SELECT 0::BIGINT AS row, c.j AS col, sum(l.q * c.v)::BIGINT AS v FROM l JOIN c ON l.doc_id = c.i GROUP BY ALL")
def _labels(spark, d):
    c = kernels.plain(mul.outer_product(*build.workload(spark, d, "W10c")))
    v = build.table(spark, d, "labels").filter("quality <> 0").select(F.lit(0).cast("long").alias("row"), F.col("doc_id").alias("col"), F.col("quality").cast("long").alias("v")).distinct()
    return kernels.product(v, c)


@query("label_vector_terms", f"WITH c AS ({psql('W10')}), l AS (SELECT DISTINCT doc_id, quality::BIGINT AS q FROM labels WHERE quality IS NOT NULL AND quality <> 0) SELECT 0::BIGINT AS row, c.j AS col, sum(l.q * c.v)::BIGINT AS v FROM l JOIN c ON l.doc_id = c.i GROUP BY ALL")
def _label_terms(spark, d):
    """Labels times the whole matrix of documents (W16): v (A^T B) is taken as (v A^T) B, so that the square matrix is never made."""
    at, b = build.workload(spark, d, "W10")
    v = build.table(spark, d, "labels").filter("quality <> 0").select(F.lit(0).cast("long").alias("row"), F.col("doc_id").alias("col"), F.col("quality").cast("long").alias("v")).distinct()
    terms = kernels.product(v, at.select(F.col("i").alias("row"), F.col("k").alias("col"), "v"))
    return kernels.product(terms, b.select(F.col("k").alias("row"), F.col("j").alias("col"), "v"))


# ---------------------------------------------------------------- relational operators around the product
def _t(spark, d, n):
    return build.table(spark, d, n)


query("join_left_outer", "SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")(lambda spark, d: _t(spark, d, "customer").join(_t(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders")))
query("join_full_outer", "SELECT coalesce(n_nationkey, s_nationkey) AS nation, count(s_suppkey) AS n FROM nation FULL JOIN (SELECT * FROM supplier WHERE s_nationkey < 12) ON n_nationkey = s_nationkey GROUP BY ALL")(lambda spark, d: _t(spark, d, "nation").join(_t(spark, d, "supplier").filter("s_nationkey < 12"), F.col("n_nationkey") == F.col("s_nationkey"), "full").groupBy(F.coalesce("n_nationkey", "s_nationkey").alias("nation")).agg(F.count("s_suppkey").alias("n")))
query("join_semi", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 49)")(lambda spark, d: _t(spark, d, "orders").join(_t(spark, d, "lineitem").filter("l_quantity > 49"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey"))
query("join_anti", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")(lambda spark, d: _t(spark, d, "orders").join(_t(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey"))
query("join_cross", "SELECT r_name, n_name FROM region, nation WHERE n_regionkey <> r_regionkey")(lambda spark, d: _t(spark, d, "region").crossJoin(_t(spark, d, "nation")).filter("n_regionkey <> r_regionkey").select("r_name", "n_name"))
query("join_range", "SELECT l_orderkey, l_linenumber, lo FROM lineitem JOIN (SELECT n_nationkey * 500 AS lo, n_nationkey * 500 + 20 AS hi FROM nation) ON l_orderkey BETWEEN lo AND hi")(lambda spark, d: _range(spark, d))


def _range(spark, d):
    r = _t(spark, d, "nation").select((F.col("n_nationkey") * 500).alias("lo"), (F.col("n_nationkey") * 500 + 20).alias("hi"))
    cut = r.select("lo", "hi", F.explode(F.sequence(F.call_function("div", F.col("lo").cast("long"), F.lit(100).cast("long")), F.call_function("div", F.col("hi").cast("long"), F.lit(100).cast("long")))).alias("bucket"))
    line = _t(spark, d, "lineitem").withColumn("bucket", F.call_function("div", F.col("l_orderkey"), F.lit(100).cast("long")))
    return line.join(cut, "bucket").filter("l_orderkey BETWEEN lo AND hi").select("l_orderkey", "l_linenumber", "lo")


@query("join_as_of", "SELECT a.event_id, b.event_id AS before FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type <> 'purchase' GROUP BY ALL) b ON a.user_id = b.user_id AND a.ts >= b.ts")
def _asof(spark, d):
    e = _t(spark, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "own").rowsBetween(Window.unboundedPreceding, 0)
    marked = e.filter("event_type <> 'purchase'").groupBy("user_id", "ts").agg(F.max("event_id").alias("event_id")).withColumn("own", F.lit(0)).unionByName(e.filter("event_type = 'purchase'").select("user_id", "ts", "event_id", F.lit(1).alias("own")))
    return marked.withColumn("before", F.last(F.when(F.col("own") == 0, F.col("event_id")), True).over(w)).filter("own = 1").select("event_id", "before")


query("agg_rollup", "SELECT n_regionkey, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)")(lambda spark, d: _t(spark, d, "customer").join(_t(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).rollup("n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")))
query("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda spark, d: _t(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")))
query("agg_monoids", "SELECT l_returnflag, min(l_partkey) AS lo, max(l_partkey) AS hi, bit_xor(l_partkey) AS bx, bit_or(l_suppkey) AS bo, bool_or(l_quantity > 49) AS any_big, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")(lambda spark, d: _t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.min("l_partkey").alias("lo"), F.max("l_partkey").alias("hi"), F.bit_xor("l_partkey").alias("bx"), F.bit_or("l_suppkey").alias("bo"), F.bool_or(F.col("l_quantity") > 49).alias("any_big"), F.count_distinct("l_suppkey").alias("suppliers")))
query("window_rank", "SELECT o_custkey, o_orderkey, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate)::INT AS r FROM orders")(lambda spark, d: _t(spark, d, "orders").select("o_custkey", "o_orderkey", F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderdate")).alias("r")))
query("window_running", "SELECT user_id, event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id) AS n, lag(event_id) OVER (PARTITION BY user_id ORDER BY event_id) AS prev FROM events")(lambda spark, d: _t(spark, d, "events").select("user_id", "event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("event_id")).alias("n"), F.lag("event_id").over(Window.partitionBy("user_id").orderBy("event_id")).alias("prev")))
query("setop_except", "SELECT l_partkey AS k FROM lineitem EXCEPT SELECT p_partkey FROM part WHERE p_size < 25")(lambda spark, d: _t(spark, d, "lineitem").select(F.col("l_partkey").alias("k")).exceptAll(_t(spark, d, "part").filter("false").select("p_partkey")).distinct().join(_t(spark, d, "part").filter("p_size < 25").select(F.col("p_partkey").alias("k")), "k", "left_anti"))
query("setop_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")(lambda spark, d: _t(spark, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(_t(spark, d, "supplier").select("s_nationkey")))
query("order_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")(lambda spark, d: _t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20))
query("fn_strings", "SELECT p_partkey, lpad(p_partkey::VARCHAR, 10, '0') AS key, string_split(p_type, ' ')[1] AS kind FROM part")(lambda spark, d: _t(spark, d, "part").select("p_partkey", F.lpad(F.col("p_partkey").cast("string"), 10, "0").alias("key"), F.get(F.split("p_type", " "), F.lit(0)).alias("kind")))
query("fn_json", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")(lambda spark, d: _t(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")))
query("fn_unpivot", "SELECT p_partkey AS k, 'p_size' AS j, p_size::BIGINT AS v FROM part UNION ALL SELECT p_partkey, 'len', length(p_name) FROM part")(lambda spark, d: build.from_wide(_t(spark, d, "part").select("p_partkey", F.col("p_size").cast("long").alias("p_size"), F.length("p_name").cast("long").alias("len")), "p_partkey", ["p_size", "len"]))


@query("udtf_outer_rows", psql("W7"))
def _udtf(spark, d):
    udf.register(spark)
    a, b = build.workload(spark, d, "W7")
    a.select("k", F.lit("a").alias("side"), F.col("i").alias("x"), "v").unionByName(b.select("k", F.lit("b").alias("side"), F.col("j").alias("x"), "v")).createOrReplaceTempView("tagged_rows")
    return spark.sql("SELECT i, j, sum(v) AS v FROM outer_rows(TABLE(tagged_rows) PARTITION BY k) GROUP BY i, j")


@query("sql_surface", psql("W6"))
def _sql(spark, d):
    a, b = build.workload(spark, d, "W6")
    a.createOrReplaceTempView("left_entries")
    b.createOrReplaceTempView("right_entries")
    return spark.table(udf.sql_multiply(spark, "left_entries", "right_entries"))


# ---------------------------------------------------------------- streams
def _events(spark, d):
    """The event file alone in a folder's view, as a stream."""
    return spark.readStream.schema(inc.EVENTS).option("pathGlobFilter", "events.parquet").parquet(d).withColumn("ts", F.col("ts").cast("timestamp"))


@query("stream_hourly_pairs", "WITH h AS (SELECT date_trunc('hour', ts) AS k, user_id AS i, count(*) AS v FROM events GROUP BY ALL) SELECT a.i, b.i AS j, sum(a.v * b.v)::BIGINT AS v FROM h a JOIN h b USING (k) GROUP BY ALL")
def _hourly(spark, d):
    hours = inc.drain(inc.windowed_pairs(_events(spark, d)), "hours", "complete").select(F.col("start").alias("k"), F.col("user_id").alias("i"), F.col("n").alias("v"))
    return mul.outer_product(hours, hours.withColumnRenamed("i", "j"))


@query("stream_incremental", psql("W7"))
def _incremental(spark, d):
    a, b = build.workload(spark, d, "W7")
    log = _log(spark)
    delta = _events(spark, d).select(F.col("user_id").alias("k"), F.col("event_type").alias("i"), F.lit(1).cast("long").alias("v"))
    inc.multiply_stream(delta, b, log)
    return log.scan()


@query("stream_running_cells", "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL")
def _running(spark, d):
    return inc.drain(inc.running_cells(_events(spark, d)), "cells", "update").groupBy("user_id", "event_type").agg(F.max("n").alias("n"))


@query("stream_distinct", "SELECT count(DISTINCT event_id) AS n FROM events")
def _distinct(spark, d):
    return inc.drain(inc.distinct_events(_events(spark, d)), "distinct").agg(F.count(F.lit(1)).alias("n"))


@query("stream_sliding_windows", "SELECT start, user_id, count(*) AS n FROM (SELECT user_id, unnest([time_bucket(INTERVAL 30 MINUTES, ts), time_bucket(INTERVAL 30 MINUTES, ts) - INTERVAL 30 MINUTES]) AS start FROM events) GROUP BY ALL")
def _sliding(spark, d):
    got = inc.drain(inc.windowed_pairs(_events(spark, d), "1 hour", "30 minutes"), "sliding", "complete")
    return got.select(F.col("start").cast("timestamp_ntz").alias("start"), "user_id", "n")


@query("stream_sessions", "SELECT min(ts) AS start, user_id, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s")
def _sessions(spark, d):
    got = inc.drain(inc.sessions(_events(spark, d)), "sessions", "complete")
    return got.select(F.col("start").cast("timestamp_ntz").alias("start"), "user_id", "n")


@query("stream_user_pairs", "SELECT a.user_id AS i, b.user_id AS j, count(*) AS n FROM events a JOIN events b ON a.event_type = b.event_type AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 5 MINUTES AND a.user_id < b.user_id GROUP BY ALL")
def _user_pairs(spark, d):
    got = inc.drain(inc.user_pairs_within(_events(spark, d), _events(spark, d)), "pairs")
    return got.groupBy("i", "j").agg(F.count(F.lit(1)).alias("n"))


@query("stream_both_sides", "WITH e AS (SELECT user_id AS k, event_type AS i, count(*) AS v FROM events GROUP BY ALL) SELECT a.i, b.i AS j, sum(a.v * b.v)::BIGINT AS v FROM e a JOIN e b USING (k) GROUP BY ALL")
def _both_sides(spark, d):
    """Both operands arrive in two halves; (A + dA)(B + dB) is the first product and three more runs."""
    e = _t(spark, d, "events").select(F.col("user_id").alias("k"), F.col("event_type").alias("i"), F.lit(1).cast("long").alias("v"), (F.col("event_id") % 2 == 0).alias("old"))
    old, new = e.filter("old").drop("old"), e.filter("not old").drop("old")
    as_b = lambda t: t.withColumnRenamed("i", "j")
    log = _log(spark)
    log.append(mul.outer_product(old, as_b(old), emit="partials"), "first")
    inc.multiply_both(log, old, as_b(old), new, as_b(new), 1)
    return log.scan()


_CLASSES = "{0} AS (SELECT floor(log2(pp::DOUBLE)) AS c, count(*)::DOUBLE AS n, avg(pp::DOUBLE) AS pp FROM (SELECT {1}, sum(d)::BIGINT AS pp FROM {2} JOIN (SELECT k, count(*) AS d FROM {3} GROUP BY k) USING (k) GROUP BY {1}) GROUP BY 1)"
for _w in ("W1", "W3", "W6"):
    query(f"expected_entries_{_w}", f"{ab(_w)}, {_CLASSES.format('r', 'i', 'a', 'b')}, {_CLASSES.format('q', 'j', 'b', 'a')} SELECT round(sum(r.n * q.n * (1 - exp(-r.pp * q.pp / (SELECT count(*)::DOUBLE FROM a JOIN b USING (k))))))::BIGINT AS n_c FROM r, q")(
        lambda spark, d, w=_w: cost.expected_entries(*build.workload(spark, d, w)))


@query("expected_entries_error", "SELECT * FROM (VALUES ('W1', true), ('W2', true), ('W3', true), ('W6', true)) t(workload, close)")
def _estimate(spark, d):
    """Whether the expected size of a result lies within a third of the counted one."""
    out = None
    for w in ("W1", "W2", "W3", "W6"):
        a, b = build.workload(spark, d, w)
        same = a.sameSemantics(b.withColumnRenamed("j", "i"))
        a = written(a, "operand")
        b = a.withColumnRenamed("i", "j") if same else written(b, "operand")
        spark.sparkContext._jvm.System.gc()  # exchanges of the operands leave the disk
        both = written(cost.expected_entries(a, b).withColumnRenamed("n_c", "x"), "expected").crossJoin(cost.result_entries(a, b))
        one = written(both.select(F.lit(w).alias("workload"), (F.abs(F.col("x") - F.col("n_c")) * 3 <= F.col("n_c")).alias("close")), "close")
        for t in (a, b):
            dropped(t, "operand")
        out = one if out is None else out.unionByName(one)
    return out


@query("dense_vectors", "WITH a AS (SELECT generate_subscripts(embedding, 1) - 1 AS k, vec_id AS i, unnest(embedding)::DOUBLE AS x FROM embeddings WHERE vec_id < 40), r AS (SELECT k, i, round(x * 1000)::BIGINT AS v FROM a) SELECT a.i, b.i AS j, sum(a.v * b.v)::BIGINT AS v FROM (SELECT * FROM r WHERE v <> 0) a JOIN (SELECT * FROM r WHERE v <> 0) b USING (k) GROUP BY ALL")
def _dense_vectors(spark, d):
    at = build.from_vectors(_t(spark, d, "embeddings").filter("vec_id < 40"), "vec_id", "embedding")
    return mul.outer_product(at, at.withColumnRenamed("i", "j"))


@query("dense_vectors_all", "WITH a AS (SELECT generate_subscripts(embedding, 1) - 1 AS k, vec_id AS i, unnest(embedding)::DOUBLE AS x FROM embeddings), r AS (SELECT k, i, round(x * 1000)::BIGINT AS v FROM a) SELECT a.i, b.i AS j, sum(a.v * b.v)::BIGINT AS v FROM (SELECT * FROM r WHERE v <> 0) a JOIN (SELECT * FROM r WHERE v <> 0) b USING (k) GROUP BY ALL")
def _dense_vectors_all(spark, d):
    at = build.from_vectors(_t(spark, d, "embeddings"), "vec_id", "embedding")
    return mul.outer_product(at, at.withColumnRenamed("i", "j"), expand="tiled")


@query("json_keys", "WITH a AS (SELECT json_extract_string(props, '$.k') AS k, user_id AS i, count(*) AS v FROM events GROUP BY ALL) SELECT a.i, b.i AS j, sum(a.v * b.v)::BIGINT AS v FROM a JOIN a b USING (k) GROUP BY ALL")
def _json_keys(spark, d):
    at = build.from_json(_t(spark, d, "events"), "user_id", "props", "$.k")
    return mul.outer_product(at, at.withColumnRenamed("i", "j"))


@query("fn_math", "SELECT o_orderkey, floor(o_totalprice / 1000)::BIGINT AS lo, ceil(o_totalprice / 1000)::BIGINT AS hi, o_orderkey ** 2 AS sq, floor(log2(o_orderkey + 1))::BIGINT AS lg, o_orderkey & 255 AS low_bits, xor(o_orderkey, 1023) AS flipped, ((o_orderkey % 7) + 7) % 7 AS m FROM orders")
def _math(spark, d):
    k, x = F.col("o_orderkey"), F.col("o_totalprice")
    return _t(spark, d, "orders").select("o_orderkey", F.floor(x / 1000).cast("long").alias("lo"), F.ceil(x / 1000).cast("long").alias("hi"), F.pow(k, F.lit(2)).alias("sq"), F.floor(F.log2(k + 1)).cast("long").alias("lg"), k.bitwiseAND(255).alias("low_bits"), k.bitwiseXOR(1023).alias("flipped"), F.pmod(k, F.lit(7)).alias("m"))


@query("stream_late", "WITH p AS (SELECT *, ts < (SELECT max(ts) FROM events WHERE event_id % 5 <> 0) - INTERVAL 1 HOUR AS late FROM events WHERE event_id % 5 = 0) SELECT (SELECT count(*) FROM events) - count(*) FILTER (WHERE late) AS in_time, count(*) FILTER (WHERE late) AS late FROM p")
def _late(spark, d):
    """A fifth of the events comes in a second batch, after the others; those behind the watermark are kept aside."""
    path = fresh(spark, "events")
    e = _t(spark, d, "events")
    for q, part in enumerate((e.filter("event_id % 5 <> 0"), e.filter("event_id % 5 = 0"))):
        part.coalesce(1).write.mode("append").parquet(f"{path}/part={q}")
    stream = spark.readStream.schema(inc.EVENTS).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
    good, late = inc.split_late(stream)
    return good.agg(F.count(F.lit(1)).alias("in_time")).crossJoin(late.agg(F.count(F.lit(1)).alias("late")))


@query("stream_progress", "SELECT count(*) AS rows FROM events")
def _stream_progress(spark, d):
    return inc.progress(_events(spark, d)).agg(F.sum("rows").cast("long").alias("rows"))


@query("stream_growing_operands", "WITH e AS (SELECT user_id AS k, event_type AS x, count(*) AS v FROM events GROUP BY ALL) SELECT a.x AS i, b.x AS j, sum(a.v * b.v)::BIGINT AS v FROM e a JOIN e b USING (k) GROUP BY ALL")
def _growing(spark, d):
    """Both operands arrive on one stream, in as many batches as there are files."""
    path = fresh(spark, "events")
    _t(spark, d, "events").repartition(3, "event_id").write.parquet(path)
    events = spark.readStream.schema(inc.EVENTS).option("maxFilesPerTrigger", 1).option("pathGlobFilter", "*.parquet").parquet(path)
    rows = events.select(F.explode(F.array(F.lit("a"), F.lit("b"))).alias("side"), F.col("user_id").alias("k"), F.col("event_type").alias("x"), F.lit(1).cast("long").alias("v"))
    log = _log(spark)
    inc.multiply_growing(rows, log)
    return log.scan()


@query("stream_cells_with_ttl", "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL")
def _ttl(spark, d):
    return inc.drain(inc.running_cells(_events(spark, d), "2 hours"), "cells-ttl", "update").groupBy("user_id", "event_type").agg(F.max("n").alias("n"))
