"""Cost measures, from degree tables: no product is enumerated to count it. Only `result_entries` counts cells."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def degrees(t: DataFrame, by: str = "k") -> DataFrame:
    return t.groupBy(by).agg(F.count(F.lit(1)).alias("degree"))


def partial_products_by_key(at: DataFrame, b: DataFrame) -> DataFrame:
    """(k, pp): products that each shared key makes."""
    left, right = degrees(at).withColumnRenamed("degree", "da"), degrees(b).withColumnRenamed("degree", "db")
    return left.join(right, "k").select("k", (F.col("da") * F.col("db")).alias("pp"))


def partial_products(at: DataFrame, b: DataFrame) -> DataFrame:
    """One row (pp)."""
    return partial_products_by_key(at, b).agg(F.coalesce(F.sum("pp"), F.lit(0)).cast("long").alias("pp"))


def partial_products_by_row(at: DataFrame, b: DataFrame) -> DataFrame:
    """(i, pp): products that each row of the result is made of."""
    return at.join(degrees(b), "k").groupBy("i").agg(F.sum("degree").cast("long").alias("pp"))


def partial_products_by_column(at: DataFrame, b: DataFrame) -> DataFrame:
    """(j, pp): products that each column of the result is made of."""
    return b.join(degrees(at), "k").groupBy("j").agg(F.sum("degree").cast("long").alias("pp"))


#: Cells of a block whose hits are marked in a table of flags; products that a block is to have at most where it has more cells.
BLOCK_CELLS, BLOCK_PRODUCTS = 1 << 26, 16_000_000
#: Entries of a key's row in a block from which on a whole row of flags is joined at a time.
WIDE = 32


def _codes(values: pa.ChunkedArray) -> tuple[np.ndarray, int]:
    """Numbers from 0 on for the values, and how many there are."""
    found = values.unique()
    return pc.index_in(values, found).to_numpy().astype(np.int64), len(found)


def _cells(k_a: np.ndarray, i: np.ndarray, n_i: int, k_b: np.ndarray, j: np.ndarray, n_j: int) -> int:
    """Distinct (i, j) that share a k, of numbers from 0 on; a key that the left side lacks has the number -1."""
    a, b = np.argsort(k_a, kind="stable"), np.argsort(k_b, kind="stable")
    k_a, i, k_b, j = k_a[a], i[a], k_b[b], j[b]
    keys, first, da = np.unique(k_a, return_index=True, return_counts=True)
    low, high = np.searchsorted(k_b, keys, "left"), np.searchsorted(k_b, keys, "right")
    flags = n_i * n_j <= BLOCK_CELLS
    wide = (high - low >= WIDE) & flags
    packed = np.zeros((n_i if wide.any() else 0, -(-n_j // 8)), np.uint8)
    for q in np.flatnonzero(wide):
        row = np.zeros(n_j, np.uint8)
        row[j[low[q]:high[q]]] = 1
        packed[i[first[q]:first[q] + da[q]]] |= np.packbits(row)
    seen, held, waiting, more = np.zeros(n_i * n_j if flags else 0, bool), np.zeros(0, np.int64), [], 0
    rest = np.flatnonzero(~wide & (high > low))
    at = np.repeat(first[rest] - (np.cumsum(da[rest]) - da[rest]), da[rest]) + np.arange(da[rest].sum())
    start, reps = np.repeat(low[rest], da[rest]), np.repeat((high - low)[rest], da[rest])
    ends = np.cumsum(reps)
    done = 0
    while done < len(at):
        to = max(done + 1, int(np.searchsorted(ends, (ends[done - 1] if done else 0) + 2_000_000)))
        n = reps[done:to]
        made = np.repeat(i[at[done:to]] * n_j, n) + j[np.repeat(start[done:to] - np.cumsum(n) + n, n) + np.arange(n.sum())]
        done = to
        if flags:
            seen[made] = True
            continue
        waiting.append(np.unique(made))
        more += len(waiting[-1])
        if more >= max(len(held), 4_000_000):
            held, waiting, more = np.unique(np.concatenate([held, *waiting])), [], 0
    if not flags:
        return len(np.unique(np.concatenate([held, *waiting])))
    if not len(packed):
        return int(np.count_nonzero(seen))
    seen = seen.reshape(n_i, n_j)
    return sum(int(np.count_nonzero(np.unpackbits(packed[q:q + 256], axis=1, count=n_j).view(bool) | seen[q:q + 256])) for q in range(0, n_i, 256))


def _count_block(batches):
    """(n): cells of a task's block, whose rows (side, k, list of i, list of j) are those of both operands."""
    keys: dict[int, list] = {0: [], 1: []}
    ids: dict[int, list] = {0: [], 1: []}
    many: dict[int, list] = {0: [], 1: []}
    for batch in batches:
        for side, name in ((0, "i"), (1, "j")):
            t = pa.Table.from_batches([batch.filter(pc.equal(batch["side"], side))])
            if t.num_rows:
                keys[side].append(t["k"])
                ids[side].append(pc.list_flatten(t[name]))
                many[side].append(pc.list_value_length(t[name]).to_numpy())
    if not keys[0] or not keys[1]:
        return
    join = lambda parts: pa.chunked_array([c for x in parts for c in x.chunks])
    found = join(keys[0]).unique()
    k_a, k_b = (np.repeat(pc.index_in(join(keys[q]), found).fill_null(-1).to_numpy().astype(np.int64), np.concatenate(many[q])) for q in (0, 1))
    yield pa.RecordBatch.from_arrays([pa.array([_cells(k_a, *_codes(join(ids[0])), k_b, *_codes(join(ids[1])))], pa.int64())], names=["n"])


def result_entries(at: DataFrame, b: DataFrame) -> DataFrame:
    """One row (n_c): cells of the result, counted exactly. The result is cut in a grid of blocks, each one task's, by hashes of i and j; a block
    gets the entries of its rows and columns and keeps the set of its cells, as flags where it has at most BLOCK_CELLS and as sorted numbers
    otherwise. So no pair passes an exchange, and the grid is as coarse as the lesser of cells and products allows. More blocks than one are
    counted at once, from entries that are packed by ranges of rows and of columns and read by each block, not copied to it; only the count is kept."""
    from semimul.operators.blockwise import _scanned, count_in_blocks
    from semimul.plans.staging import dropped, written

    # read several times below
    left, right = at.select("k", "i").filter("k is not null and i is not null"), b.select("k", "j").filter("k is not null and j is not null")
    same = left.sameSemantics(as_left := right.withColumnRenamed("j", "i")) and left.schema == as_left.schema
    kept = lambda t, name: t if _scanned(t) else written(t, name)
    left = kept(left, "left")
    right = left.withColumnRenamed("i", "j") if same else kept(right, "right")
    pp = partial_products(left, right).first()[0]
    cells = left.agg(F.approx_count_distinct("i")).first()[0] * right.agg(F.approx_count_distinct("j")).first()[0]
    blocks = max(1, math.ceil(min(1.3 * cells / BLOCK_CELLS, pp / BLOCK_PRODUCTS)))
    total = F.coalesce(F.sum("n"), F.lit(0)).alias("n_c")
    if blocks > 1:
        left.sparkSession.sparkContext._jvm.System.gc()  # so that exchanges of the counts leave the disk
        counted = count_in_blocks(left, right, pp)
        out = written(counted.agg(total), "cells")
        for t, name in ((left, "left"), (right, "right"), (counted, "packs")):
            dropped(t, name)
        return out
    # a key goes to the block once, with the list of its rows or columns
    l, r = left.groupBy("k").agg(F.collect_list("i").alias("i")), right.groupBy("k").agg(F.collect_list("j").alias("j"))
    l = l.select(F.lit(0).alias("side"), "k", "i", F.lit(None).cast(r.schema["j"].dataType).alias("j"))
    r = r.select(F.lit(1).alias("side"), "k", F.lit(None).cast(l.schema["i"].dataType).alias("i"), "j")
    laid = l.unionByName(r).repartitionById(1, F.lit(0))
    return laid.mapInArrow(_count_block, "n long").agg(total)


def expected_entries(at: DataFrame, b: DataFrame) -> DataFrame:
    """One row (n_c): cells of the result to expect if the products of a row fell on the columns by their weights. Rows and columns are first
    put in classes by the binary logarithm of their products, so that the sum has some thousands of terms at most and no product is made. Of large
    operands each step is written, so that its exchanges leave the disk before the next."""
    from semimul.operators.blockwise import LARGE, _estimate
    from semimul.plans.staging import written

    large = _estimate(at) + _estimate(b) >= LARGE

    def step(t: DataFrame, name: str) -> DataFrame:
        if large:
            t = written(t, name)
            t.sparkSession.sparkContext._jvm.System.gc()
        return t

    def classes(t: DataFrame, name: str) -> DataFrame:
        return t.groupBy(F.floor(F.log2(F.col("pp").cast("double"))).alias("class")).agg(F.count(F.lit(1)).cast("double").alias(f"n_{name}"), F.avg(F.col("pp").cast("double")).alias(f"pp_{name}"))

    rows, columns = step(classes(partial_products_by_row(at, b), "row"), "rows"), step(classes(partial_products_by_column(at, b), "col"), "columns")
    total = step(partial_products(at, b).select(F.col("pp").cast("double").alias("pp")), "total")
    met = rows.crossJoin(columns.select("n_col", "pp_col")).crossJoin(total)  # a class for each power of two on either side
    hit = F.col("n_row") * F.col("n_col") * (1 - F.exp(-F.col("pp_row") * F.col("pp_col") / F.col("pp")))
    return met.agg(F.coalesce(F.round(F.sum(hit)), F.lit(0)).cast("long").alias("n_c"))


def write_amplification(at: DataFrame, b: DataFrame) -> DataFrame:
    """One row: products, cells, and their ratio in thousandths (rounded down)."""
    pp, n = partial_products(at, b), result_entries(at, b)
    return pp.crossJoin(n).select("pp", "n_c", F.when(F.col("n_c") > 0, F.floor(F.col("pp") * 1000 / F.col("n_c"))).otherwise(F.lit(0)).cast("long").alias("ratio_milli"))


def profile(at: DataFrame, b: DataFrame, bands: int = 4) -> DataFrame:
    """(method, reads, least_writes, most_writes, passes_b) by the formulas: a band reads all of the right table and its part of the left
    one; the inner product reads the right table once for each row of the left."""
    a = at.agg(F.count(F.lit(1)).alias("n_a"), F.count_distinct("i").alias("rows"))
    one = a.crossJoin(b.agg(F.count(F.lit(1)).alias("n_b"))).crossJoin(partial_products(at, b)).crossJoin(result_entries(at, b))
    n_a, n_b, rows, pp, n_c = (F.col(x).cast("long") for x in ("n_a", "n_b", "rows", "pp", "n_c"))
    row = lambda name, reads, low, high, passes: F.struct(F.lit(name).alias("method"), reads.alias("reads"), low.alias("least_writes"), high.alias("most_writes"), passes.alias("passes_b"))
    one_pass, p = F.lit(1).cast("long"), F.lit(bands).cast("long")
    return one.select(F.inline(F.array(
        row("outer partials", n_a + n_b, pp, pp, one_pass), row("outer summed", n_a + n_b, n_c, pp, one_pass), row("inner", n_a + rows * n_b, n_c, n_c, rows), row("hybrid", n_a + p * n_b, n_c, pp, p), row("client", n_a + n_b, n_c, n_c, one_pass))))


def band_bounds(n: int, bands: int) -> list[tuple[int, int]]:
    """First and last row (from 1) of each band; a band may be empty (last < first) where there are more bands than rows."""
    return [((p - 1) * n // bands + 1, p * n // bands) for p in range(1, bands + 1)]


def band_bounds_weighted(by_row: DataFrame, bands: int) -> list[tuple[int, int]]:
    """First and last row of bands of about equal weight, from (i, pp): a band ends at the first row where the running weight has reached its
    share. A band may be empty (last < first) where one row outweighs a share."""
    from semimul.plans.progress import even_splits
    from semimul.plans.staging import written

    by_row = written(by_row.select("i", "pp"), "by-row")  # read several times below
    by_row.sparkSession.sparkContext._jvm.System.gc()
    low, high = by_row.agg(F.min("i"), F.max("i")).first()
    if low is None:
        return [(1, 0)] * bands
    splits = {r["shard"]: r["first"] for r in even_splits(by_row.select(F.col("i").alias("key"), F.col("pp").alias("w")), bands).collect()}  # one row a band
    starts = [low, *[splits[q] for q in range(2, bands + 1)]]
    return [(a, z - 1) for a, z in zip(starts, [*starts[1:], high + 1])]


def choose_bands(n: int, l: int, budget: int, criterion: str = "average", n_c: int | None = None) -> int | None:
    """The least number of bands whose accumulators fit: `average` asks ceil(n l / p) entries to fit, `strict` the largest band,
    `sparse` the same share of `n_c` expected entries. None if a single row does not fit (or, sparse, nothing does)."""
    if criterion == "sparse":
        return max(1, math.ceil((n_c or 0) / budget)) if math.ceil((n_c or 0) / max(n, 1)) <= budget else None
    if l > budget:
        return None
    for p in range(max(1, math.ceil(n * l / budget) - 1), n + 1):
        need = -(-n * l // p) if criterion == "average" else -(-n // p) * l
        if need <= budget:
            return p
    return None


def choose(at: DataFrame, b: DataFrame, *, broadcast_entries: int = 100_000, fold_from: float = 1.3) -> dict:
    """Picks a method by cost, from degree tables alone: the row-wise product with a copy of the right table where that is small (its size is
    counted), the summed outer product where the sum is expected to fold at least `fold_from` products into one, and partials that are
    folded later otherwise."""
    n_b = b.limit(broadcast_entries + 1).count()
    pp = partial_products(at, b).first()[0]
    n_c = min(expected_entries(at, b).first()[0], pp) or 1
    method = "rowwise" if n_b <= broadcast_entries else "summed" if pp / n_c >= fold_from else "partials"
    return {"method": method, "pp": pp, "n_c": n_c, "n_b": n_b}
