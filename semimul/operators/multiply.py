"""Generalised sparse matrix products: outer, inner, banded and blocked, and the client-side baselines."""

from __future__ import annotations

import math
import time
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from semimul.functions.semiring import PLUS_TIMES, Semiring
from semimul.operators.blockwise import kept_if_large, sum_in_blocks, sum_in_groups
from semimul.plans import cost


def stored(t: DataFrame, s: Semiring) -> DataFrame:
    """The entries that count: keys and value present, and not the semiring's zero. The filter is pushed to the scan."""
    keep = F.col("k").isNotNull() & F.col("v").isNotNull()
    return t.filter(keep if s.zero is None else keep & (F.col("v") != F.lit(s.zero)))


def _sides(at: DataFrame, b: DataFrame, s: Semiring) -> tuple[DataFrame, DataFrame]:
    return stored(at, s).select("k", "i", F.col("v").alias("av")), stored(b, s).select("k", "j", F.col("v").alias("bv"))


def fold(partials: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """(i, j, v): the sum of each cell; sums that parts can be made of are begun before the exchange."""
    return partials.groupBy("i", "j").agg(s.add(F.col("v")).alias("v"))


#: Entries of either side that meet in one tile of a heavy key, and keys that can be heavy at most (one in so many of all products).
TILE, HEAVY_KEYS = (2000, 2000), 10_000


def outer_product(at: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, *, emit: str = "summed", expand: str = "auto", build_side: str = "auto", cache_entries: int | None = 10_000, tile: tuple[int, int] | None = None, by: str = "i") -> DataFrame:
    """C = A B from A's transpose (k, i, v) and B (k, j, v), in one pass over both.

    emit: `partials` gives every product, `presum` sums in a cache of each task on the way (without a bound on it, a large product in blocks, as below),
    `summed` gives the cells. A large product's cells come in each task in the order of `by`: rows (`i`) or columns (`j`).
    expand: `auto` (rows of a key meet in a join that is dealt by products and not by bytes; keys whose product is larger than a tile's and
    than one in HEAVY_KEYS of all products are cut in tiles, light keys are left alone), `tiled` (every key is cut in tiles of about `tile`
    entries), `join` (a plain join), `blocks` (a key's column and row as arrays of about a tile's length) or `cogroup` (Arrow tables of a
    key, in Python). The sums of a large product (`blockwise.FROM_PRODUCTS`) by `auto` or `tiled` are made in blocks of the result, which cut
    every key in a grid of tiles: its products would fill the disk before the sum.
    build_side: which side of a key is held in memory, `a`, `b`, `merge` (neither: sorted and merged) or `auto`.
    """
    left, right = _sides(at, b, s)
    if build_side != "auto" and expand == "auto":
        expand = "join"
    if (emit == "summed" or (emit == "presum" and cache_entries is None)) and expand in ("auto", "tiled") and s is PLUS_TIMES:
        left, right, cells = sum_in_blocks(left, right, by)
        if cells is not None:
            return cells
    if expand == "auto":
        met = _tiled(left, right, tile or TILE, heavy_only=True)
    elif expand == "tiled":
        met = _tiled(left, right, tile or (1000, 1000), heavy_only=False)
    elif expand == "join":
        left = left.hint("shuffle_hash") if build_side == "a" else left.hint("merge") if build_side == "merge" else left
        right = right.hint("shuffle_hash") if build_side == "b" else right
        met = left.join(right, "k")
    elif expand == "blocks":
        met = _blocks(left, right, tile or TILE)
    elif expand == "cogroup":
        met = _cogrouped(left, right)
    else:
        raise ValueError(expand)
    partials = met.select("i", "j", s.mul(F.col("av"), F.col("bv")).alias("v"))
    if emit == "partials":
        return partials
    if emit == "presum":
        return presum(partials, s, cache_entries)
    return fold(partials, s)


def _grid(left: DataFrame, right: DataFrame, tile: tuple[int, int]) -> DataFrame:
    """(k, da, db, ta, tb): entries of each shared key, and tiles along either side."""
    n_a, n_b = left.groupBy("k").agg(F.count(F.lit(1)).alias("da")), right.groupBy("k").agg(F.count(F.lit(1)).alias("db"))
    return n_a.join(n_b, "k").select("k", "da", "db", F.ceil(F.col("da") / tile[0]).cast("int").alias("ta"), F.ceil(F.col("db") / tile[1]).cast("int").alias("tb"))


def _tiled(left: DataFrame, right: DataFrame, tile: tuple[int, int], heavy_only: bool) -> DataFrame:
    """A grid over each heavy key: either side is cut in tiles by a hash, and each tile is copied once for every tile across. With `heavy_only`
    the grid has at most HEAVY_KEYS rows, since a heavy key holds more than one in so many of all products, and is broadcast; light keys are
    then one tile. Both sides are dealt by tile into the session's number of shuffle partitions, which stays as it is although the bytes are
    few: what a task does grows with its products."""
    grid = _grid(left, right, tile)
    if heavy_only:
        total = grid.agg(F.sum(F.col("da").cast("double") * F.col("db")).alias("pp"))
        bound = F.greatest(F.lit(float(tile[0] * tile[1])), F.col("pp") / HEAVY_KEYS)
        grid = F.broadcast(grid.crossJoin(F.broadcast(total)).filter(F.col("da").cast("double") * F.col("db") > bound).select("k", "ta", "tb"))
    ta, tb = F.coalesce("ta", F.lit(1)), F.coalesce("tb", F.lit(1))
    how, parts = "left" if heavy_only else "inner", int(left.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    l = left.join(grid.select("k", "ta", "tb"), "k", how).select("k", "i", "av", F.pmod(F.xxhash64("i"), ta).cast("int").alias("x"), F.explode(F.sequence(F.lit(0), tb - 1)).alias("y"))
    r = right.join(grid.select("k", "ta", "tb"), "k", how).select("k", "j", "bv", F.explode(F.sequence(F.lit(0), ta - 1)).alias("x"), F.pmod(F.xxhash64("j"), tb).cast("int").alias("y"))
    return l.repartition(parts, "k", "x", "y").join(r.repartition(parts, "k", "x", "y"), ["k", "x", "y"])


def _blocks(left: DataFrame, right: DataFrame, tile: tuple[int, int]) -> DataFrame:
    """A key's column and row as arrays, a long one as several of about a tile's length."""
    grid = _grid(left, right, tile)
    columns = left.join(grid.select("k", "ta"), "k").groupBy("k", F.pmod(F.xxhash64("i"), F.col("ta")).alias("x")).agg(F.collect_list(F.struct("i", "av")).alias("column"))
    rows = right.join(grid.select("k", "tb"), "k").groupBy("k", F.pmod(F.xxhash64("j"), F.col("tb")).alias("y")).agg(F.collect_list(F.struct("j", "bv")).alias("row"))
    return columns.join(rows, "k").select("row", F.inline("column")).select("i", "av", F.inline("row"))


def _cogrouped(left: DataFrame, right: DataFrame) -> DataFrame:
    schema = left.select("i", "av").schema.add(right.schema["j"]).add(right.schema["bv"])

    def product(a: pa.Table, b: pa.Table) -> pa.Table:
        n, m = a.num_rows, b.num_rows
        x, y = np.repeat(np.arange(n), m), np.tile(np.arange(m), n)
        return pa.table({"i": a["i"].take(x), "av": a["av"].take(x), "j": b["j"].take(y), "bv": b["bv"].take(y)})

    return left.groupBy("k").cogroup(right.groupBy("k")).applyInArrow(product, schema)


#: Sums that Arrow and numpy know, by semiring, and the products that numpy knows.
_ADD = {"plus_times": "sum", "count": "sum", "min_plus": "min", "max_plus": "max", "max_times": "max", "max_min": "max", "min_max": "min"}
_FOLD = {"sum": np.add, "min": np.minimum, "max": np.maximum}
_MUL = {"plus_times": np.multiply, "max_times": np.multiply, "min_plus": np.add, "max_plus": np.add, "max_min": np.minimum, "min_max": np.maximum, "count": lambda a, b: np.ones(len(a), np.int64)}


class _Cache:
    """A task's table of sums by key columns. It is given out whole when a batch has left more than `entries` keys in it, and at the end. Without a bound,
    new sums wait until they are as many as the table's, so that the work of merging grows with the rows and not with their square."""

    def __init__(self, keys: list[str], how: str, schema: pa.Schema, entries: int | None):
        self.keys, self.how, self.schema, self.entries, self.held, self.waiting = keys, how, schema, entries, None, []

    def _sum(self, tables: list[pa.Table]) -> pa.Table:
        got = pa.concat_tables(tables).group_by(self.keys).aggregate([("v", self.how)])
        return pa.table({c: got[c] for c in self.keys} | {"v": got[f"v_{self.how}"].cast(self.schema.field("v").type)}).cast(self.schema)

    def _merge(self) -> None:
        if self.waiting:
            self.held, self.waiting = self._sum(([] if self.held is None else [self.held]) + self.waiting), []

    def add(self, rows: pa.Table):
        if self.entries is None:
            self.waiting.append(self._sum([rows]))
            if self.held is None or sum(t.num_rows for t in self.waiting) >= self.held.num_rows:
                self._merge()
            return
        self.waiting.append(rows)
        self._merge()
        if self.held.num_rows > self.entries:
            yield from self.rest()

    def rest(self):
        self._merge()
        if self.held is not None:
            yield from self.held.to_batches()
            self.held = None


def presum(partials: DataFrame, s: Semiring = PLUS_TIMES, cache_entries: int | None = 10_000) -> DataFrame:
    """Partials summed in a table of at most about `cache_entries` cells that each task keeps from batch to batch (None: of any size): between
    n_C and PP entries. Sum, min and max are known to it; other sums are begun by the engine's own partial aggregate."""
    if s.name not in _ADD:
        return fold(partials, s)

    def run(batches):
        cache = None
        for batch in batches:
            cache = cache or _Cache(["i", "j"], _ADD[s.name], batch.schema, cache_entries)
            yield from cache.add(pa.Table.from_batches([batch]))
        if cache:
            yield from cache.rest()

    return partials.select("i", "j", "v").mapInArrow(run, partials.select("i", "j", "v").schema)


def run_fold(partials: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """Neighbouring rows of one cell summed, over partitions that are sorted by cell: what the deferred sum of an ordered product does. Nothing
    is held but the last cell."""
    add, schema = _FOLD[_ADD[s.name]], partials.select("i", "j", "v").schema

    def run(batches):
        last = None
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = pa.Table.from_batches([batch])
            rows = rows if last is None else pa.concat_tables([last, rows])
            new = np.ones(rows.num_rows, dtype=bool)
            i, j = (rows[c].combine_chunks() for c in ("i", "j"))
            new[1:] = pc.or_(pc.not_equal(i[1:], i[:-1]), pc.not_equal(j[1:], j[:-1])).to_numpy(zero_copy_only=False)
            starts = np.flatnonzero(new)
            done = rows.select(["i", "j"]).take(starts).append_column("v", pa.array(add.reduceat(rows["v"].to_numpy(), starts)).cast(rows.schema.field("v").type))
            last = done.slice(len(starts) - 1)
            yield from done.slice(0, len(starts) - 1).combine_chunks().to_batches()
        if last is not None:
            yield from last.combine_chunks().to_batches()

    return partials.select("i", "j", "v").mapInArrow(run, schema)


def inner_product(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, *, form: str = "ordered", max_rows: int = 64, max_pairs: int = 10_000_000) -> DataFrame:
    """The product cell by cell, in order of (i, j). Operands are laid out as for the outer product.

    `ordered` sorts products by (i, j, k) over ranges of cells and sums each run of one cell as it passes; `dot` pairs every row of A with every column of B as maps
    (at most `max_pairs` pairs); `multipass` scans B once for each row of A (at most `max_rows` rows, to show its cost). The latter two are
    refused beyond their bounds.
    """
    left, right = _sides(a, b, s)
    if form == "ordered":
        met = left.join(right, "k").select("i", "j", "k", s.mul(F.col("av"), F.col("bv")).alias("v"))
        laid = met.repartitionByRange("i", "j").sortWithinPartitions("i", "j", "k")
        if s.name in _ADD:
            return run_fold(laid, s)
        return laid.groupBy("i", "j").agg(s.add(F.col("v")).alias("v")).sortWithinPartitions("i", "j")
    if form == "dot":
        rows = left.groupBy("i").agg(F.map_from_entries(F.collect_list(F.struct("k", "av"))).alias("row"))
        columns = right.groupBy("j").agg(F.map_from_entries(F.collect_list(F.struct("k", "bv"))).alias("column"))
        if rows.count() * columns.count() > max_pairs:
            raise ValueError(f"more than {max_pairs} pairs of a row and a column")
        pairs = rows.crossJoin(columns).select("i", "j", F.explode(F.array_intersect(F.map_keys("row"), F.map_keys("column"))).alias("k"), "row", "column")
        return pairs.select("i", "j", s.mul(F.element_at("row", F.col("k")), F.element_at("column", F.col("k"))).alias("v")).groupBy("i", "j").agg(s.add(F.col("v")).alias("v")).orderBy("i", "j")
    if form == "multipass":
        keys = [r.i for r in left.select("i").distinct().orderBy("i").limit(max_rows + 1).collect()]
        if len(keys) > max_rows:
            raise ValueError(f"more than {max_rows} rows")
        out = None
        for key in keys:
            row = fold(left.filter(F.col("i") == F.lit(key)).join(right, "k").select("i", "j", s.mul(F.col("av"), F.col("bv")).alias("v")), s)
            out = row if out is None else out.unionByName(row)
        return out.orderBy("i", "j") if out is not None else fold(left.join(right, "k").select("i", "j", s.mul(F.col("av"), F.col("bv")).alias("v")), s)
    raise ValueError(form)


def band_of(i: Column, n: int, bands: int) -> Column:
    """Number from 1 of the band that holds row `i` of 1 to `n`."""
    return F.call_function("div", i.cast("long") * bands + (n - 1), F.lit(n).cast("long")).cast("int")


def local_product(left: DataFrame, right: DataFrame, group: list[str], s: Semiring = PLUS_TIMES, *, parts: int, cache_entries: int | None = None, part: Column | None = None) -> DataFrame:
    """Products of (group, k, i, av) and (group, k, j, bv) within each group, one group in one task: the two sides pass sorted by k, and what
    they make is summed in the task's cache. With no bound on the cache the sums are complete and no second exchange is needed; with one,
    they are folded afterwards. A task holds its cache, a batch, and the rows of one k. `part` numbers the groups' tasks from 0 on; without it
    they are dealt by hash."""
    if s.name not in _MUL:
        raise ValueError(f"no vectorised product for {s.name}")
    mul, add = _MUL[s.name], _ADD[s.name]
    kinds = {f.name: f.dataType for f in [*left.schema, *right.schema]}
    null = lambda c: F.lit(None).cast(kinds[c]).alias(c)
    both = left.select(*group, "k", F.lit(0).alias("side"), "i", "av", null("j"), null("bv")).unionByName(right.select(*group, "k", F.lit(1).alias("side"), null("i"), null("av"), "j", "bv"))
    laid = (both.repartition(parts, *group) if part is None else both.repartitionById(parts, part)).sortWithinPartitions(*group, "k", "side")
    schema = left.select(*group, "i").schema.add(right.schema["j"]).add("v", kinds["av"])

    def expand(t: pa.Table, starts: np.ndarray):
        """Tables of the products of whole (group, k) runs that begin at `starts`, of bounded size each."""
        side = t["side"].to_numpy()
        run = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, t.num_rows)))
        n_b = np.bincount(run, weights=side, minlength=len(starts)).astype(np.int64)
        b_start = np.append(starts[1:], t.num_rows) - n_b
        rows = np.flatnonzero((side == 0) & (n_b[run] > 0))
        ends = np.cumsum(n_b[run[rows]])
        at = 0
        while at < len(rows):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + 1_000_000)))
            some = rows[at:to]
            reps = n_b[run[some]]
            x = np.repeat(some, reps)
            y = np.repeat(b_start[run[some]] - np.cumsum(reps) + reps, reps) + np.arange(reps.sum())
            v = mul(t["av"].take(x).to_numpy(), t["bv"].take(y).to_numpy())
            yield pa.table({c: t[c].take(x) for c in [*group, "i"]} | {"j": t["j"].take(y), "v": pa.array(v)})
            at = to

    def run(batches):
        cache = held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = pa.Table.from_batches([batch])
            if cache is None:
                names = {f.name: f.type for f in rows.schema}
                cache = _Cache([*group, "i", "j"], add, pa.schema([(c, names["av" if c == "v" else c]) for c in [*group, "i", "j", "v"]]), cache_entries)
            rows = (rows if held is None else pa.concat_tables([held, rows])).combine_chunks()
            new = np.zeros(rows.num_rows, dtype=bool)
            new[0] = True
            for c in [*group, "k"]:
                col = rows[c].combine_chunks()
                new[1:] |= pc.not_equal(col[1:], col[:-1]).to_numpy(zero_copy_only=False)
            starts = np.flatnonzero(new)
            held = rows.slice(starts[-1])
            if len(starts) > 1:
                for made in expand(rows.slice(0, starts[-1]), starts[:-1]):
                    yield from cache.add(made.cast(cache.schema))
        if held is not None:
            for made in expand(held, np.array([0])):
                yield from cache.add(made.cast(cache.schema))
            yield from cache.rest()

    done = laid.mapInArrow(run, schema)
    if cache_entries is not None:
        done = done.groupBy(*group, "i", "j").agg(s.add(F.col("v")).alias("v"))
    return done.select("i", "j", "v")


#: Products that a task makes of a band; larger bands are cut in blocks.
BAND_PRODUCTS = 8_000_000


def hybrid_product(at: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, *, bands: int, n: int | None = None, first: int | None = None, execution: str = "local", broadcast_entries: int = 100_000, cache_entries: int | None = None, bounds: list[tuple[int, int]] | None = None) -> DataFrame:
    """Between outer (one band) and inner (a band for each row): the rows of C are cut in bands, and each band is one pass over B with its sums
    complete. Rows are `n` whole numbers from `first` on (by default those from the least to the greatest that occur); `bounds` gives the
    bands' first and last rows where they are not to be of equal length (`cost.band_bounds_weighted`).

    `local` sends B once to each band that has rows and keeps a band in one task, whose sums are complete as far as `cache_entries` cells hold
    them (None: all, for bands chosen to fit by `cost.choose_bands`); a band of more than BAND_PRODUCTS products is a grid of blocks, a task for
    each, of which every one reads the written entries of its own rows and columns; with `cache_entries` it makes whole rows, some at a time, so that
    the sums it gives out are complete. `replicated` copies B for every band and joins on (band, k),
    `sequential` runs a job with a scan of B for each band, one after the other, and `broadcast` sends B to the tasks (if it has at most
    `broadcast_entries` entries, else it replicates) so that no second exchange is needed.
    """
    left, right = _sides(at, b, s)
    made: list[DataFrame] = []
    if execution == "local":
        left, right, made = kept_if_large(left, right)  # read several times below
    if bounds is None:
        if n is None or first is None:
            low, high = left.agg(F.min("i"), F.max("i")).first()
            first, n = (1, 1) if low is None else (low, high - low + 1)
        tagged = left.withColumn("band", band_of(F.col("i") - (first - 1), n, bands))
        bounds = [(low + first - 1, high + first - 1) for low, high in cost.band_bounds(n, bands)]
    else:
        band = F.lit(1)
        for q, (low, _) in enumerate(bounds[1:]):
            band = F.when(F.col("i") >= low, F.lit(q + 2)).otherwise(band)
        tagged, bands = left.withColumn("band", band), len(bounds)
    product = s.mul(F.col("av"), F.col("bv")).alias("v")
    if execution == "broadcast" and right.limit(broadcast_entries + 1).count() <= broadcast_entries:
        return tagged.repartition(bands, "band").join(F.broadcast(right), "k").select("band", "i", "j", product).groupBy("band", "i", "j").agg(s.add(F.col("v")).alias("v")).drop("band")
    if execution == "sequential":
        from semimul.plans.staging import fresh

        path = fresh(left.sparkSession, "bands")
        for q, (low, high) in enumerate(bounds):
            if low <= high:
                fold(left.filter(F.col("i").between(low, high)).join(right, "k").select("i", "j", product), s).write.parquet(f"{path}/band={q}")
        out = fold(left.join(right, "k").select("i", "j", product), s)
        return left.sparkSession.read.schema(out.schema).option("basePath", path).parquet(path).select("i", "j", "v")
    copies = right.withColumn("band", F.explode(F.sequence(F.lit(1), F.lit(bands))))
    if execution == "local" and s.name in _MUL:
        used = tagged.select("band").distinct()
        copies = right.crossJoin(F.broadcast(used))  # at most `bands` rows
        pp = cost.partial_products(left, right).first()[0]
        blocks = max(1, -(-pp // (bands * BAND_PRODUCTS)))
        if blocks == 1:
            return local_product(tagged, copies, ["band"], s, parts=bands, cache_entries=cache_entries)
        cells = sum_in_groups(tagged, right, s.name, _MUL[s.name], _FOLD[_ADD[s.name]], pp, (F.col("band") - 1, bands), (F.lit(0), 1), even=False, cache_entries=cache_entries)
        if cells is not None:
            _drop(made)
            return cells
        rows = math.isqrt(blocks)
        columns = -(-blocks // rows)
        tagged = tagged.withColumn("x", F.pmod(F.xxhash64("i"), F.lit(rows)).cast("int")).withColumn("y", F.explode(F.sequence(F.lit(0), F.lit(columns - 1))))
        copies = copies.withColumn("x", F.explode(F.sequence(F.lit(0), F.lit(rows - 1)))).withColumn("y", F.pmod(F.xxhash64("j"), F.lit(columns)).cast("int"))
        part = (((F.col("band") - 1) * rows + F.col("x")) * columns + F.col("y")).cast("int")
        return local_product(tagged, copies, ["band", "x", "y"], s, parts=bands * rows * columns, cache_entries=cache_entries, part=part)
    met = tagged.join(copies, ["band", "k"]).select("band", "i", "j", product)
    return met.groupBy("band", "i", "j").agg(s.add(F.col("v")).alias("v")).drop("band")


def _drop(made: list[DataFrame]) -> None:
    """Deletes operands that were written for this product and are in its packs now."""
    from semimul.plans.staging import dropped

    for t in made:
        dropped(t, "operand")


def rowwise_product(at: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, *, broadcast_entries: int = 100_000) -> DataFrame:
    """Row by row: B is sent to the tasks that hold A's rows where it is small (its entries are counted), and joined by a shuffle otherwise."""
    left, right = _sides(at, b, s)
    small = right.limit(broadcast_entries + 1).count() <= broadcast_entries
    met = left.repartition("i").join(F.broadcast(right), "k") if small else left.join(right, "k")
    return fold(met.select("i", "j", s.mul(F.col("av"), F.col("bv")).alias("v")), s)


def grid_product(at: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, *, grid: tuple[int, int] = (2, 2)) -> DataFrame:
    """A grid of blocks of C: A is copied for each column of blocks and B for each row of blocks; the sum stays inside a block, which is one
    task's, so that there is no second exchange. Blocks of more than BAND_PRODUCTS products are cut in smaller ones, a task for each, that read the
    written entries of their rows and columns."""
    left, right = _sides(at, b, s)
    rows, columns = grid
    if s.name in _MUL:
        left, right, made = kept_if_large(left, right)  # read several times below
        pp = cost.partial_products(left, right).first()[0]
        if pp > rows * columns * BAND_PRODUCTS:
            x, y = F.pmod(F.xxhash64("i"), F.lit(rows)), F.pmod(F.xxhash64("j"), F.lit(columns))
            cells = sum_in_groups(left, right, s.name, _MUL[s.name], _FOLD[_ADD[s.name]], pp, (x, rows), (y, columns), even=True, mirrored=rows == columns)
            if cells is not None:
                _drop(made)
                return cells
    l = left.withColumn("x", F.pmod(F.xxhash64("i"), F.lit(rows)).cast("int")).withColumn("y", F.explode(F.sequence(F.lit(0), F.lit(columns - 1))))
    r = right.withColumn("y", F.pmod(F.xxhash64("j"), F.lit(columns)).cast("int")).withColumn("x", F.explode(F.sequence(F.lit(0), F.lit(rows - 1))))
    if s.name in _MUL:
        return local_product(l, r, ["x", "y"], s, parts=rows * columns)
    blocks = l.join(r, ["x", "y", "k"]).select("x", "y", "i", "j", s.mul(F.col("av"), F.col("bv")).alias("v"))
    return blocks.groupBy("x", "y", "i", "j").agg(s.add(F.col("v")).alias("v")).select("i", "j", "v")


def multiply(at: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, *, method: str = "auto", mask: DataFrame | None = None, complement: bool = False, prune_zero: bool = False, **options) -> DataFrame:
    """C = A B by any method (`auto`: by cost). A mask keeps only, or drops, its cells before the sum. Zeros that the sum leaves are kept unless
    `prune_zero`."""
    if not s.lazy and method in ("auto", "summed"):
        method = "summed"  # a gathered sum takes all partials of a cell at once
    elif method == "auto":
        method = cost.choose(at, b)["method"] if mask is None else "summed"
    if mask is not None:
        kept = outer_product(at, b, s, emit="partials").join(mask.select("i", "j"), ["i", "j"], "left_anti" if complement else "left_semi")
        out = fold(kept, s)
    elif method == "rowwise":
        out = rowwise_product(at, b, s)
    elif method == "summed":
        out = outer_product(at, b, s, emit="summed", **options)
    elif method == "partials":
        # every product is appended to a log, and summed when the result is read
        from semimul.plans.staging import fresh
        from semimul.plans.store import PartialLog, multiply_into

        log = PartialLog(at.sparkSession, fresh(at.sparkSession, "partials"), s)
        multiply_into(log, at, b, "all")
        out = log.scan()
    elif method == "inner":
        out = inner_product(at, b, s, **options)
    elif method == "hybrid":
        out = hybrid_product(at, b, s, **options)
    elif method == "grid":
        out = grid_product(at, b, s, **options)
    else:
        raise ValueError(method)
    return out.filter(F.col("v") != F.lit(s.zero)) if prune_zero and s.zero is not None else out


#: Cells of a flush of a client that goes on beyond its memory; a flush passes through the driver's heap whole.
AUTO_FLUSH = 200_000
#: Flushes that are written at a time.
AT_A_TIME = 4


class ClientMemoryExceeded(RuntimeError):
    """The client would have to hold more entries than it may."""


def _expand_client(left: dict, right: dict, budget: int = 4_000_000):
    """Tables (i, j, v) of the products of two sides sorted by k (numpy arrays k, x, v), of bounded size each."""
    lo, hi = np.searchsorted(right["k"], left["k"], "left"), np.searchsorted(right["k"], left["k"], "right")
    reps, at = hi - lo, 0
    ends = np.cumsum(reps)
    while at < len(reps):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + budget)))
        n = reps[at:to]
        x = np.repeat(np.arange(at, to), n)
        y = np.repeat(lo[at:to] - np.cumsum(n) + n, n) + np.arange(n.sum())
        yield pa.table({"i": left["x"].take(x), "j": right["x"].take(y), "v": left["v"][x] * right["v"][y]})
        at = to


def client_product(at: DataFrame, b: DataFrame, *, max_entries: int = 5_000_000, mode: str = "whole", flush: int = 1_000_000) -> tuple[DataFrame, dict]:
    """The baseline that takes both tables out: scan, decode strings, multiply in the client's memory, encode, and insert into a result table.
    Returns that table and the seconds of each phase. `whole` holds the operands and the result, and is refused where operands and products
    could exceed `max_entries`; `auto` is `whole` where that is not refused, and else `streaming`. `streaming` merges the two sorted tables key by key; it holds the rows of one key and at most about `flush`
    cells, and AT_A_TIME flushes that are being written; a flush is inserted as a run of partial sums and summed when the result is read."""
    from semimul.plans.staging import fresh
    from semimul.plans.store import PartialLog

    spark, times = at.sparkSession, {}
    text = lambda t, c: stored(t, PLUS_TIMES).select("k", F.col(c).alias("x"), F.col("v").cast("string").alias("v"))
    schema = at.select("i").schema.add(b.schema["j"]).add("v", "string")
    mark = time.perf_counter()

    def lap(name):
        nonlocal mark
        now = time.perf_counter()
        times[name], mark = times.get(name, 0.0) + now - mark, now

    def encoded(cells: pa.Table | None) -> DataFrame:
        out = spark.createDataFrame(cells.set_column(2, "v", cells["v"].cast(pa.string())), schema) if cells is not None and cells.num_rows else spark.createDataFrame([], schema)
        lap("encode")
        return out

    sum_up = lambda t: pa.table((g := t.group_by(["i", "j"]).aggregate([("v", "sum")])).select(["i", "j", "v_sum"]).columns, names=["i", "j", "v"])
    if mode in ("whole", "auto"):
        n, pp = at.count() + b.count(), cost.partial_products(at, b).first()[0]
        if n + pp > max_entries and n + cost.expected_entries(at, b).first()[0] * 1.1 > max_entries:
            if mode == "auto":
                return client_product(at, b, mode="streaming", flush=min(flush, AUTO_FLUSH))
            raise ClientMemoryExceeded(f"{n} entries and {pp} products; at most {max_entries} entries")
        mark = time.perf_counter()
        tables = [text(t, c).toArrow() for t, c in ((at, "i"), (b, "j"))]
        lap("scan")
        keys = pa.chunked_array([c for t in tables for c in t["k"].chunks], type=tables[0]["k"].type).unique()
        sides = []
        for t in tables:
            k = pc.index_in(t["k"], keys).combine_chunks().to_numpy(zero_copy_only=False)
            order = np.argsort(k, kind="stable")
            sides.append({"k": k[order], "x": t["x"].combine_chunks().take(order), "v": t["v"].cast(pa.int64()).combine_chunks().to_numpy()[order]})
        lap("decode")
        cells = None
        for made in _expand_client(*sides):
            cells = sum_up(made if cells is None else pa.concat_tables([cells, made]))
        lap("multiply")
        path = fresh(spark, "client")
        encoded(cells).write.parquet(path)
        lap("insert")
        done = spark.read.schema(schema).parquet(path)
        return done.select("i", "j", F.col("v").cast("long").alias("v")), times

    log, held, runs = PartialLog(spark, fresh(spark, "client")), None, 0

    def pieces(t, c):
        """Tables of the entries in order of k, some thousands of rows each."""
        for r in text(t, c).orderBy("k").mapInArrow(_packed, "rows binary").toLocalIterator():
            got = pa.ipc.open_stream(r.rows).read_all()
            yield got.set_column(2, "v", got["v"].cast(pa.int64()))

    def insert():
        nonlocal runs, held
        lap("multiply")
        out = encoded(held).coalesce(1).select("i", "j", F.col("v").cast("long").alias("v"))
        if len(writing) == AT_A_TIME:
            writing.pop(0).result()
        writing.append(pool.submit(log.write_run, out, f"flush-{runs}"))
        lap("insert")
        runs, held = runs + 1, None

    # some flushes are written at a time; they become live together once all are there
    writing: list = []
    with ThreadPoolExecutor(AT_A_TIME) as pool:
        for one, two in _merged(pieces(at, "i"), pieces(b, "j")):
            lap("scan")
            keys, sides = one["k"].unique(), []
            for t in (one, two):
                t = t.filter(pc.is_in(t["k"], keys))
                k = pc.index_in(t["k"], keys).to_numpy().astype(np.int64)
                order = np.argsort(k, kind="stable")
                sides.append({"k": k[order], "x": t["x"].take(order), "v": t["v"].to_numpy()[order]})
            lap("decode")
            for made in _expand_client(*sides, budget=flush):
                held = sum_up(made if held is None else pa.concat_tables([held, made]))
                while held.num_rows >= flush:
                    held, rest = held.slice(0, flush), held.slice(flush)
                    insert()
                    held = rest
        insert()
        for done in writing:
            done.result()
    log.commit_runs([f"flush-{q}" for q in range(runs)], encoded(None).select("i", "j", F.col("v").cast("long").alias("v")).schema)
    lap("insert")
    return log.scan(), times


def _packed(batches):
    """Each batch as one row of bytes."""
    for batch in batches:
        if batch.num_rows:
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, batch.schema) as out:
                out.write_batch(batch)
            yield pa.RecordBatch.from_arrays([pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["rows"])


def _merged(one, two):
    """Pairs of tables (k, ...) with all the rows of some keys, from two sides that come as tables in order of k. The rows of a key are held until
    a later key has been seen on its side."""
    sides, held, ended = (one, two), [None, None], [False, False]
    while True:
        for q in (0, 1):
            while not ended[q] and (held[q] is None or held[q]["k"][0] == held[q]["k"][-1]):
                more = next(sides[q], None)
                ended[q] = more is None
                held[q] = held[q] if more is None else more if held[q] is None else pa.concat_tables([held[q], more])
        if held[0] is None or held[1] is None:
            return
        # keys before the least of the last keys are there whole; the last keys of a side that has ended, too
        open_ends = [held[q]["k"][-1] for q in (0, 1) if not ended[q]]
        if open_ends:
            end = open_ends[0] if len(open_ends) == 1 else pc.min(pa.chunked_array([pa.array([x.as_py() for x in open_ends], held[0]["k"].type)]))
            done = [int(np.searchsorted(pc.less(h["k"], end).to_numpy() == 0, True)) for h in held]
        else:
            done = [h.num_rows for h in held]
        if all(done):
            yield tuple(h.slice(0, n) for h, n in zip(held, done))
        held = [h.slice(n) if n < h.num_rows else None for h, n in zip(held, done)]
        if any(h is None and ended[q] for q, h in enumerate(held)):
            return


def naive_product(at: DataFrame, b: DataFrame) -> DataFrame:
    """Join and aggregate on defaults, with no layout and no zero rule."""
    return at.select("k", "i", F.col("v").alias("av")).join(b.select("k", "j", F.col("v").alias("bv")), "k").groupBy("i", "j").agg(F.sum(F.col("av") * F.col("bv")).alias("v"))


def dense_product(at: DataFrame, b: DataFrame) -> DataFrame:
    """Brute force over all of N x M x L, absent entries as zeros; for tiny tables."""
    i, j = at.select("i").distinct(), b.select("j").distinct()
    k = at.select("k").union(b.select("k")).distinct()
    cube = i.crossJoin(j).crossJoin(k)
    cube = cube.join(at.select("k", "i", F.col("v").alias("av")), ["k", "i"], "left").join(b.select("k", "j", F.col("v").alias("bv")), ["k", "j"], "left")
    return cube.groupBy("i", "j").agg(F.sum(F.coalesce("av", F.lit(0)) * F.coalesce("bv", F.lit(0))).alias("v"))


def is_sorted(df: DataFrame, by: list[str]) -> bool:
    """Whether each partition's rows come in order."""
    keyed = df.select(F.struct(*by).alias("x"), F.spark_partition_id().alias("p"), F.monotonically_increasing_id().alias("n"))
    back = keyed.withColumn("before", F.lag("x").over(Window.partitionBy("p").orderBy("n"))).filter("before > x")
    return back.isEmpty()
