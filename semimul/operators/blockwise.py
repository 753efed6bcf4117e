"""The outer product summed in blocks of the result. The entries of a range of rows, and of one of columns, are written together as a pack; each
pair of packs meets in one task, which makes the products of a block and sums them by itself: no product passes an exchange, and no entry more than one.
Bands and grids of blocks are made of packs that lie within a band, or within a row or column of the grid."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semimul.plans import cost

#: Products from which on a product is summed in blocks, and bytes (by the plan's estimate) from which on operands are written before they are counted.
FROM_PRODUCTS, LARGE = 50_000_000, 64 << 20
#: Entries of a side and products that a block is to have about, and ranges of rows or columns at least and at most.
TASK_ENTRIES, TASK_PRODUCTS, LEAST_RANGES, MOST_RANGES = 2_500_000, 2_500_000_000, 4, 64
#: The same entries for blocks within groups.
GROUP_ENTRIES = 1_500_000
#: Cells and products that a task has in hand at a time; cells of the dense keys' table.
CELLS, AT_ONCE, DENSE_CELLS = 1_000_000, 500_000, 4_000_000
#: Products whose cells are counted at a time.
COUNTED = 2_000_000

_WHOLE = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)
_PLAIN = (*_WHOLE, T.StringType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType)


def _range(t: DataFrame, c: str, n: int) -> Column:
    """Number from 0 to n - 1 of the range that a row or column falls in: ranges of about equally many entries for whole numbers, which keep
    neighbours together, and hashes for all else."""
    if not isinstance(t.schema[c].dataType, _WHOLE):
        return F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
    ends = t.agg(F.percentile_approx(c, [q / n for q in range(1, n)], 10_000)).first()[0] if n > 1 else []
    ends = sorted(set(ends or []))

    def search(low: int, high: int) -> Column:
        if low == high:
            return F.lit(low)
        mid = (low + high) // 2
        return F.when(F.col(c) <= ends[mid], search(low, mid)).otherwise(search(mid + 1, high))

    return search(0, len(ends))


def _estimate(t: DataFrame) -> int:
    return int(t._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())


def _scanned(t: DataFrame) -> bool:
    """Whether the table comes out of a scan by selections and filters only, so that writing it would save nothing."""
    plan = t._jdf.queryExecution().optimizedPlan()
    while plan.nodeName() in ("Project", "Filter"):
        plan = plan.children().head()
    return plan.nodeName().startswith(("LogicalRelation", "Relation"))


def sum_in_blocks(left: DataFrame, right: DataFrame, by: str = "i") -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """Both operands (k, i, av) and (k, j, bv), written if they are large, and (i, j, v) if their product is to be summed in blocks: if it has
    FROM_PRODUCTS products, whole numbers for values and sums that cannot leave their range. A task's cells come in the order of its rows, or of
    its columns (`by` j)."""
    if by == "j":
        r, l, cells = sum_in_blocks(right.select("k", F.col("j").alias("i"), F.col("bv").alias("av")), left.select("k", F.col("i").alias("j"), F.col("av").alias("bv")))
        l, r = l.select("k", F.col("j").alias("i"), F.col("bv").alias("av")), r.select("k", F.col("i").alias("j"), F.col("av").alias("bv"))
        return l, r, cells and cells.select(F.col("j").alias("i"), F.col("i").alias("j"), "v")
    kinds = [left.schema[c].dataType for c in ("k", "i")] + [right.schema["j"].dataType]
    if not all(isinstance(x, _PLAIN) for x in kinds) or {left.schema["av"].dataType, right.schema["bv"].dataType} != {T.LongType()}:
        return left, right, None
    same = _same(left, right)
    large = _estimate(left) + _estimate(right) >= LARGE
    if large:
        left, right = _keep(left, right, same)
    pp = cost.partial_products(left, right).first()[0]
    if pp < FROM_PRODUCTS:
        return left, right, None
    if not large:
        left, right = _keep(left, right, same)
    (n_a, most_a, kind_i, kind_va), (n_b, most_b, kind_j, kind_vb) = _narrow(left, "i", "av"), _narrow(right, "j", "bv")
    if most_a * most_b * pp >= 2**63 or not kind_i or not kind_j:
        return left, right, None
    a = _packs(left, "i", "av", _ranges(n_a, pp), kind_i, kind_va)
    b = a if same else _packs(right, "j", "bv", _ranges(n_b, pp), kind_j, kind_vb)
    return left, right, _cells_of(a, b, left, right, kind_i, kind_j, _block)


def _ranges(n: int, pp: int, entries: int | None = None) -> int:
    return min(MOST_RANGES, max(LEAST_RANGES, math.ceil(n / (entries or TASK_ENTRIES)), math.ceil(math.sqrt(pp / TASK_PRODUCTS))))


def _met_packs(a: DataFrame, b: DataFrame) -> DataFrame:
    """Every pair of packs meets in a task that reads both: a pack is written once, however many blocks it takes part in."""
    return a.toDF(*(f"a_{c}" for c in PACK)).crossJoin(b.toDF(*(f"b_{c}" for c in PACK)).hint("shuffle_replicate_nl"))


def _cells_of(a: DataFrame, b: DataFrame, left: DataFrame, right: DataFrame, kind_i: T.DataType, kind_j: T.DataType, block) -> DataFrame:
    cells = _met_packs(a, b).mapInArrow(block, T.StructType([T.StructField("i", kind_i), T.StructField("j", kind_j), T.StructField("v", T.LongType())]))
    return cells.select(F.col("i").cast(left.schema["i"].dataType).alias("i"), F.col("j").cast(right.schema["j"].dataType).alias("j"), "v")


def _same(left: DataFrame, right: DataFrame) -> bool:
    """Whether (k, i, av) and (k, j, bv) are one table by two names."""
    as_left = right.select("k", F.col("j").alias("i"), F.col("bv").alias("av"))
    return left.sameSemantics(as_left) and as_left.schema == left.schema


def _keep(left: DataFrame, right: DataFrame, same: bool) -> tuple[DataFrame, DataFrame]:
    x = _kept(left)
    return x, x.select("k", F.col("i").alias("j"), F.col("av").alias("bv")) if same else _kept(right)


def kept_if_large(left: DataFrame, right: DataFrame) -> tuple[DataFrame, DataFrame, list[DataFrame]]:
    """Both operands, written if they are large and no plain scans, and the tables that were written."""
    if _estimate(left) + _estimate(right) < LARGE:
        return left, right, []
    same = _same(left, right)
    l, r = _keep(left, right, same)
    return l, r, [x for x, t in ((l, left), (r, right)) if x is not t and not (same and l is left)]


#: The greatest value that a product, or a sum of `pp` products, of values up to `a` and `b` may have, by semiring.
_BOUND = {
    "plus_times": lambda a, b, pp: a * b * pp, "max_times": lambda a, b, pp: a * b, "min_plus": lambda a, b, pp: a + b, "max_plus": lambda a, b, pp: a + b,
    "max_min": lambda a, b, pp: max(a, b), "min_max": lambda a, b, pp: max(a, b), "count": lambda a, b, pp: pp,
}


def sum_in_groups(left: DataFrame, right: DataFrame, name: str, mul, add, pp: int, rows: tuple[Column, int], columns: tuple[Column, int], *, even: bool, mirrored: bool = False, cache_entries: int | None = None) -> DataFrame | None:
    """(i, j, v) of (k, i, av) and (k, j, bv) with `pp` products in all, in blocks that lie within a group of rows and one of columns, given as their
    number from 0 on and how many there are (`even`: about equally large, as by hashes; `mirrored`: the same for both sides, so that one table by two names is packed once). `mul` and `add` are numpy's for the semiring `name`. Sums are
    complete in their block. With `cache_entries` a task makes its products by whole rows, some at a time, and holds at most so many cells besides.
    None if values, rows or columns are of other types, or sums may leave their range."""
    kinds = [left.schema[c].dataType for c in ("k", "i")] + [right.schema["j"].dataType]
    if not all(isinstance(x, _PLAIN) for x in kinds) or {left.schema["av"].dataType, right.schema["bv"].dataType} != {T.LongType()}:
        return None
    left.sparkSession.sparkContext._jvm.System.gc()  # so that exchanges of the counts leave the disk
    (n_a, most_a, kind_i, kind_va), (n_b, most_b, kind_j, kind_vb) = _narrow(left, "i", "av"), _narrow(right, "j", "bv")
    if _BOUND[name](most_a, most_b, pp) >= 2**63 or not kind_i or not kind_j:
        return None
    in_group = lambda n, groups: _ranges(n // groups if even else n, pp // groups**2 if even else pp, GROUP_ENTRIES)
    a = _packs(left, "i", "av", in_group(n_a, rows[1]), kind_i, kind_va, rows)
    b = a if mirrored and _same(left, right) else _packs(right, "j", "bv", in_group(n_b, columns[1]), kind_j, kind_vb, columns)

    def block(batches):
        return _block(batches, mul, add, name == "plus_times" and cache_entries is None, cache_entries or 0)

    return _cells_of(a, b, left, right, kind_i, kind_j, block)


#: Of a range of rows or columns: keys and how many entries each has; the rows or columns; by key, the entries' places among these, and their values.
PACK = ("keys", "many", "ids", "at", "values")


def _packs(t: DataFrame, c: str, v: str, n: int, kind: T.DataType, kind_v: T.DataType, groups: tuple[Column, int] | None = None) -> DataFrame:
    """A row of arrays for each of `n` ranges of rows or columns, or for what of it lies in a group, written."""
    from semimul.plans.staging import written

    group, many = groups or (F.lit(0), 1)
    at = (group.cast("int") * n + _range(t, c, n)).alias("x")
    laid = t.select("k", F.col(c).cast(kind).alias("i"), F.col(v).cast(kind_v).alias("v"), at).repartitionById(n * many, "x").select("k", "i", "v")
    kinds = (t.schema["k"].dataType, T.IntegerType(), kind, T.IntegerType(), kind_v)
    out = written(laid.mapInArrow(_pack, T.StructType([T.StructField(x, T.ArrayType(y)) for x, y in zip(PACK, kinds)])), "packs")
    t.sparkSession.sparkContext._jvm.System.gc()
    return out


def _narrow(t: DataFrame, c: str, v: str) -> tuple:
    """Entries, the greatest value, and the least types that rows (None: some are missing) and values fit."""
    kind = t.schema[c].dataType
    whole = isinstance(kind, _WHOLE)
    far = lambda x: F.coalesce(F.max(F.greatest(F.col(x), -1 - F.col(x))), F.lit(0)).cast("long")
    n, there, wide, most, high = t.agg(F.count(F.lit(1)), F.count(c), far(c) if whole else F.lit(0), F.max(F.abs(F.col(v).cast("double"))), far(v)).first()
    least = lambda x: next(k for top, k in ((2**7, T.ByteType()), (2**15, T.ShortType()), (2**31, T.IntegerType()), (2**63, T.LongType())) if x < top)
    return n, most or 0.0, None if there < n else least(wide) if whole else kind, least(high)


def _kept(t: DataFrame) -> DataFrame:
    """The table written, if it is not a plain scan; the driver is then asked to collect its garbage, so that the exchanges it came from leave the disk."""
    from semimul.plans.staging import written

    if _scanned(t):
        return t

    out = written(t, "operand")
    t.sparkSession.sparkContext._jvm.System.gc()
    return out


def _pack(batches):
    """One row of PACK from a task's entries (k, i, v); none without entries."""
    got = [b for b in batches if b.num_rows]
    if not got:
        return
    t = pa.Table.from_batches(got)
    del got
    keys, ids = t["k"].unique(), t["i"].unique()
    if pa.types.is_integer(keys.type):
        keys = keys.take(pc.sort_indices(keys))
    ids = ids.take(pc.sort_indices(ids))
    k = pc.index_in(t["k"], keys).to_numpy()
    order = np.argsort(k, kind="stable")
    columns = (keys, np.bincount(k).astype(np.int32), ids, pc.index_in(t["i"], ids).to_numpy()[order], t["v"].to_numpy()[order])
    lists = [pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x if isinstance(x, pa.Array) else pa.array(x)) for x in columns]
    yield pa.RecordBatch.from_arrays(lists, names=list(PACK))


def _met(many: np.ndarray, key: np.ndarray, at: np.ndarray, v: np.ndarray, ids: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, pa.Array]:
    """Numbers of key and row (or column) and the value of each entry whose key is known (not below 0), and the rows by number."""
    known = key >= 0
    k, known = np.repeat(key[known], many[known]), np.repeat(known, many)
    at = at[known]
    there = np.bincount(at, minlength=len(ids)) > 0
    return k, (np.cumsum(there) - 1)[at], v[known].astype(np.int64), ids.filter(pa.array(there))


def _found(some: pa.Array, among: pa.Array) -> np.ndarray:
    """The place of each key among others, or -1; whole numbers are sorted in packs."""
    if not pa.types.is_integer(some.type):
        return pc.index_in(some, among).fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)
    x, y = some.to_numpy(), among.to_numpy()
    of = np.minimum(np.searchsorted(y, x), len(y) - 1)
    of[y[of] != x] = -1
    return of


def _operands(batches):
    """Of each block, from rows of two packs: keys, rows and values of the left entries by number, the rows, the same of the right entries, and
    how many keys there are."""
    for batch in batches:
        for q in range(batch.num_rows):
            (ka, na, i_of, i, va), (kb, nb, j_of, j, vb) = ([batch[f"{side}_{c}"][q].values for c in PACK] for side in "ab")
            of = _found(kb, ka)
            there = np.full(len(ka), -1, np.int64)
            there[of[of >= 0]] = of[of >= 0]
            n_k = len(ka)
            ka, i, va, i_of = _met(na.to_numpy(), there, i.to_numpy(), va.to_numpy(), i_of)
            kb, j, vb, j_of = _met(nb.to_numpy(), of, j.to_numpy(), vb.to_numpy(), j_of)
            yield (ka, i, va, i_of), (kb, j, vb, j_of), n_k


def _block(batches, mul=np.multiply, add=np.add, tables: bool = True, hold: int = 0):
    """The cells of blocks, from rows of two packs. Up to `hold` cells are kept back until there are more, or the block ends."""
    for (ka, i, va, i_of), (kb, j, vb, j_of), n_k in _operands(batches):
        for x, y, v in _held(block_cells(ka, i, va, len(i_of), kb, j, vb, len(j_of), n_k, mul, add, tables), hold):
            for low in range(0, len(v), 50_000):
                to = low + 50_000
                yield pa.RecordBatch.from_arrays([i_of.take(pa.array(x[low:to])), j_of.take(pa.array(y[low:to])), pa.array(v[low:to])], names=["i", "j", "v"])


def count_in_blocks(left: DataFrame, right: DataFrame, pp: int) -> DataFrame:
    """(n): how many distinct cells (k, i) and (k, j) have, a row for each pair of packs. None of these may be missing."""
    one = F.lit(1).cast("byte")
    l, r = left.select("k", "i", one.alias("v")), right.select("k", "j", one.alias("v"))
    (n_a, _, kind_i, kind_v), (n_b, _, kind_j, _) = _narrow(l, "i", "v"), _narrow(r, "j", "v")
    a = _packs(l, "i", "v", _ranges(n_a, pp, GROUP_ENTRIES), kind_i, kind_v)
    same = l.sameSemantics(as_left := r.withColumnRenamed("j", "i")) and l.schema == as_left.schema
    return _met_packs(a, a if same else _packs(r, "j", "v", _ranges(n_b, pp, GROUP_ENTRIES), kind_j, kind_v)).mapInArrow(_count, "n long")


def _count(batches):
    """The cells of each block, by as many rows at a time as have few products or are marked in a table of flags."""
    for (ka, i, _, i_of), (kb, j, _, j_of), n_k in _operands(batches):
        if not len(ka) or not len(kb):
            continue
        order = np.argsort(kb, kind="stable")
        kb, j = kb[order], j[order]
        order = np.argsort(i, kind="stable")
        ka, i = ka[order], i[order]
        n_i, n_j, n, row = len(i_of), len(j_of), 0, 0
        start = np.append(0, np.cumsum(np.bincount(i, minlength=n_i)))
        ends = np.append(0, np.cumsum(np.bincount(kb, minlength=n_k)[ka]))[start]
        while row < n_i:
            to = min(n_i, max(row + 1, row + cost.BLOCK_CELLS // n_j, int(np.searchsorted(ends, ends[row] + COUNTED, "right")) - 1))
            of = slice(start[row], start[to])
            n += cost._cells(ka[of], i[of] - row, to - row, kb, j, n_j)
            row = to
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])


def _held(cells, hold: int):
    """The cells, given out when more than `hold` are there and at the end."""
    waiting, n = [], 0
    for some in cells:
        waiting.append(some)
        n += len(some[2])
        if n > hold:
            yield tuple(map(np.concatenate, zip(*waiting)))
            waiting, n = [], 0
    if n:
        yield tuple(map(np.concatenate, zip(*waiting)))


def block_cells(ka, i, va, n_i, kb, j, vb, n_j, n_k, mul=np.multiply, add=np.add, tables: bool = True):
    """(rows, columns, sums) of the product of entries (k, i, v) and (k, j, v), given as numbers from 0 on; every cell comes once. Without `tables`,
    which know sums of products only, products are sorted by cell and summed, for whole rows, some at a time.

    Keys whose products would fill a good part of the block go through one matrix product of floating-point tables, which is exact where sums
    stay below 2 ** 53; the others' products are made one by one, and added to a table of the cells or, where the block is nearly empty, sorted."""
    known = kb >= 0
    kb, j, vb = kb[known], j[known], vb[known]
    order = np.argsort(kb, kind="stable")
    kb, j, vb = kb[order], j[order], vb[order]
    order = np.argsort(i, kind="stable")
    ka, i, va = ka[order], i[order], va[order]
    da, db = np.bincount(ka, minlength=n_k), np.bincount(kb, minlength=n_k)
    b_start, a_start = np.append(0, np.cumsum(db)), np.append(0, np.cumsum(np.bincount(i, minlength=n_i)))
    if not len(kb):
        return
    most = lambda v: float(max(abs(int(v.min())), abs(int(v.max()))))
    # products of a cell: a row's entries, times how often an entry of the right side may repeat
    repeats = int(np.unique(kb * n_j + j, return_counts=True)[1].max())
    exact = tables and most(va) * most(vb) * int(np.diff(a_start).max()) * repeats < 2**53
    positive = va.min() > 0 and vb.min() > 0
    products, cells = da.astype(np.float64) * db, float(n_i) * n_j
    heavy = np.flatnonzero(products * 100 >= cells) if exact else np.zeros(0, np.int64)
    heavy = heavy[np.argsort(-products[heavy], kind="stable")][: DENSE_CELLS // n_j]
    if len(heavy) * cells < 20_000:
        heavy = heavy[:0]
    h_of = np.full(n_k, -1)
    h_of[heavy] = np.arange(len(heavy))
    reps = np.where(h_of[ka] < 0, db[ka], 0)
    ends = np.append(0, np.cumsum(reps))
    made = int(ends[-1])

    def expand(low: int, high: int):
        """(row, column, left value, right value) of the products of the entries from `low` to `high`, some at a time."""
        while low < high:
            to = min(high, max(low + 1, int(np.searchsorted(ends, ends[low] + AT_ONCE, "right")) - 1))
            n = reps[low:to]
            x = np.repeat(np.arange(low, to), n)
            y = np.arange(len(x)) + np.repeat(b_start[ka[low:to]] - (ends[low:to] - ends[low]), n)
            if len(x):
                yield i[x], j[y], va[x], vb[y]
            low = to

    if not len(heavy) and (not exact or cells > 32.0 * made):
        row = 0
        while row < n_i:
            to = min(n_i, max(row + 1, int(np.searchsorted(ends[a_start], ends[a_start[row]] + AT_ONCE, "right")) - 1))
            sums, code = [], []
            for x, y, v, w in expand(a_start[row], a_start[to]):
                sums.append(mul(v, w))
                code.append((x - row) * n_j + y)
                if sum(map(len, code)) > 2 * AT_ONCE:
                    code, sums = ([c] for c in _summed(code, sums, add))
            if code:
                code, sums = _summed(code, sums, add)
                yield code // n_j + row, code % n_j, sums
            row = to
        return

    dense_b = np.zeros((len(heavy), n_j))
    if len(heavy):
        mine = h_of[kb] >= 0
        np.add.at(dense_b, (h_of[kb[mine]], j[mine]), vb[mine])
    there_b = None if positive else _flags(len(heavy), n_j, h_of[kb], j)
    for row in range(0, n_i, step := max(1, CELLS // n_j)):
        to = min(n_i, row + step)
        low, high = a_start[row], a_start[to]
        n = (to - row) * n_j
        acc, seen = np.zeros(n), None if positive else np.zeros(n, bool)
        if len(heavy):
            of = slice(low, high)
            mine = h_of[ka[of]] >= 0
            at = (i[of][mine] - row, h_of[ka[of]][mine])
            dense_a = np.zeros((to - row, len(heavy)))
            np.add.at(dense_a, at, va[of][mine])
            acc = (dense_a @ dense_b).ravel()
            if not positive:
                seen = (_flags(to - row, len(heavy), *at) @ there_b).ravel() > 0.5
        for x, y, v, w in expand(low, high):
            code, v = (x - row) * n_j + y, v.astype(np.float64) * w
            if len(code) * 4 > n:
                acc += np.bincount(code, v, n)
            else:
                np.add.at(acc, code, v)
            if not positive:
                seen[code] = True
        full = np.flatnonzero(acc if positive else seen)
        yield full // n_j + row, full % n_j, acc[full].astype(np.int64)


def _flags(n: int, m: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    out = np.zeros((n, m), np.float32)
    out[x[x >= 0], y[x >= 0]] = 1
    return out


def _summed(code: list, v: list, add) -> tuple[np.ndarray, np.ndarray]:
    code, v = np.concatenate(code), np.concatenate(v)
    order = np.argsort(code)
    code = code[order]
    starts = np.flatnonzero(np.append(True, code[1:] != code[:-1]))
    return code[starts], add.reduceat(v[order], starts)
