"""Graph searches and product chains."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semimul.functions.semiring import MIN_PLUS, PLUS_TIMES, SET_UNION, Semiring
from semimul.operators.kernels import by_col, by_row, ewise_add, plain, product
from semimul.operators.multiply import outer_product
from semimul.plans import cost
from semimul.plans.staging import fresh, written
from semimul.plans.store import PartialLog


def bfs(start: DataFrame, edges: DataFrame, max_depth: int = 10) -> DataFrame:
    """(node, level) of every node within `max_depth` steps of the nodes in `start` (node). Each level is one vector-matrix product over the
    frontier, less what has been seen; levels are written tables, and only whether a frontier is empty comes to the driver."""
    seen = written(start.select("node").distinct().withColumn("level", F.lit(0)), "bfs")
    steps = edges.select(F.col("row").alias("node"), F.col("col").alias("next"))
    for depth in range(1, max_depth + 1):
        new = seen.filter(F.col("level") == depth - 1).join(steps, "node").select(F.col("next").alias("node")).distinct().join(seen, "node", "left_anti")
        new = written(new.withColumn("level", F.lit(depth)), "bfs")
        if new.isEmpty():
            break
        seen = seen.unionByName(new)
    return seen


def _within(i: int, max_iter: int | None) -> None:
    if max_iter is not None and i > max_iter:
        raise RuntimeError(f"no fixpoint after {max_iter} rounds")


def even_reach(start: DataFrame, edges: DataFrame, max_iter: int | None = None) -> DataFrame:
    """(node) within an even number of steps of `start`, to a fixpoint; an error where `max_iter` double steps do not reach it."""
    seen = written(start.select("node").distinct(), "even")
    front = seen
    one = edges.select(F.col("row").alias("node"), F.col("col").alias("next")).distinct()
    step = lambda f: f.join(one, "node").select(F.col("next").alias("node")).distinct()
    for i in count(1):
        _within(i, max_iter)
        front = written(step(step(front)).join(seen, "node", "left_anti"), "even")
        if front.isEmpty():
            return seen
        seen = seen.unionByName(front)


def two_step_union(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, plan: str = "staged") -> DataFrame:
    """A + A B B, by plan: `staged` writes both products, `temporary` holds the first in the executors' memory, `fold_into` appends the
    partials of the second to A's log and sums once."""
    if plan == "staged":
        c = written(product(a, b, s), "c")
        d = written(product(c, b, s), "d")
        return ewise_add(a, d, s)
    if plan == "temporary":
        c = product(a, b, s).persist()
        return ewise_add(a, product(c, b, s), s)
    c = written(product(a, b, s), "c")
    log = PartialLog(a.sparkSession, fresh(a.sparkSession, "two-step"), s)
    log.append(a.select(F.col("row").alias("i"), F.col("col").alias("j"), "v"), "a")
    log.append(outer_product(by_col(c), by_row(b), s, emit="partials"), "cb")
    return plain(log.scan())


def sssp(start: DataFrame, edges: DataFrame, max_iter: int | None = None) -> DataFrame:
    """(node, dist): least distances from `start` (node) by relaxation over the min-plus semiring, until nothing changes; an error where
    `max_iter` rounds do not get there, or where a cycle of negative weight keeps distances falling."""
    best = written(start.select("node").distinct().withColumn("dist", F.lit(0).cast("long")), "sssp")
    steps = edges.select(F.col("row").alias("node"), F.col("col").alias("next"), "v")
    for i in count(1):
        _within(i, max_iter)
        more = best.join(steps, "node").select(F.col("next").alias("node"), MIN_PLUS.mul(F.col("dist"), F.col("v")).alias("dist"))
        new = best.withColumn("old", F.col("dist")).unionByName(more.withColumn("old", F.lit(None).cast("long"))).groupBy("node").agg(F.min("dist").alias("dist"), F.min("old").alias("old"))
        new = written(new, "sssp")
        best = new.select("node", "dist")
        if new.filter("old is null or dist < old").isEmpty():
            return best
        # a least path has fewer edges than there are nodes
        if i >= best.count():
            raise ValueError("a cycle of negative weight")


def rank(edges: DataFrame, damping: float = 0.85, iterations: int = 10) -> DataFrame:
    """(node, score): degree-normalised ranking; nodes without links out share theirs among all."""
    out = edges.groupBy("row").agg(F.sum("v").cast("double").alias("total"))
    moves = written(edges.join(out, "row").select("row", "col", (F.col("v") / F.col("total")).alias("w")), "moves")
    nodes = written(edges.select(F.col("row").alias("node")).union(edges.select("col")).distinct(), "nodes")
    n = nodes.count()
    score = nodes.withColumn("score", F.lit(1.0 / max(n, 1)))
    for _ in range(iterations):
        got = score.join(moves, score.node == moves.row).groupBy("col").agg(F.sum(F.col("score") * F.col("w")).alias("got"))
        kept = nodes.join(got, nodes.node == got.col, "left").select("node", F.coalesce("got", F.lit(0.0)).alias("got"))
        lost = 1.0 - (kept.agg(F.sum("got")).first()[0] or 0.0)
        score = written(kept.select("node", (F.lit((1 - damping) / max(n, 1) + damping * lost / max(n, 1)) + damping * F.col("got")).alias("score")), "rank")
    return score


def join_as_product(a: DataFrame, b: DataFrame) -> DataFrame:
    """A table join as a product over the set-union semiring of two incidence tables: (i, j, v) with the witnesses of each pair."""
    return outer_product(a.withColumn("v", F.col("v").cast("string")), b.withColumn("v", F.col("v").cast("string")), SET_UNION)


def chain(matrices: list[DataFrame], s: Semiring = PLUS_TIMES, *, order: str = "left", fuse: str = "presum") -> DataFrame:
    """Product of several (row, col, v) tables. order: `left` to right, or `auto` by dynamic programming over estimated products.
    fuse: `presum` sums each step in the one plan, `unsummed` leaves the sum to the last step (which needs a product that distributes over
    the sum), `materialise` writes each step."""
    def step(x: DataFrame, y: DataFrame, last: bool) -> DataFrame:
        if fuse == "unsummed" and not last:
            return plain(outer_product(by_col(x), by_row(y), s, emit="partials"))
        out = product(x, y, s)
        return written(out, "chain") if fuse == "materialise" and not last else out

    if order == "left":
        out = matrices[0]
        for q, m in enumerate(matrices[1:]):
            out = step(out, m, q == len(matrices) - 2)
        return out

    def build(tree, last: bool) -> DataFrame:
        return matrices[tree] if isinstance(tree, int) else step(build(tree[0], False), build(tree[1], False), last)

    return build(chain_order(matrices), True)


def chain_order(matrices: list[DataFrame]):
    """The cheapest bracketing as nested pairs of numbers. A product's entries are estimated from entries and distinct keys."""
    stats = [m.agg(F.count(F.lit(1)), F.approx_count_distinct("row"), F.approx_count_distinct("col")).first() for m in matrices]
    n = len(matrices)
    best = {(q, q): (0.0, q, tuple(max(1, x) for x in stats[q])) for q in range(n)}
    for size in range(2, n + 1):
        for a in range(n - size + 1):
            z = a + size - 1
            for cut in range(a, z):
                (ca, ta, (na, ra, ka)), (cb, tb, (nb, rb, kb)) = best[a, cut], best[cut + 1, z]
                pp = na * nb / max(ka, rb)
                total = ca + cb + pp
                if (a, z) not in best or total < best[a, z][0]:
                    best[a, z] = (total, (ta, tb), (min(pp, ra * kb), ra, kb))
    return best[0, n - 1][1]


def pipeline_rows(a: DataFrame, b: DataFrame, consumer, schema, s: Semiring = PLUS_TIMES) -> DataFrame:
    """Sends finished rows of A B to `consumer` (an iterator of Arrow batches to one of such) in the stage that makes them: rows are dealt by
    `row` and sorted, so a consumer sees each row whole. An unsummed outer product cannot be consumed this way."""
    done = product(a, b, s).repartition("row").sortWithinPartitions("row", "col")
    return done.mapInArrow(consumer, schema)


def pipeline_partials(a: DataFrame, b: DataFrame, consumer, schema, s: Semiring = PLUS_TIMES, *, distributes: bool = False) -> DataFrame:
    """Sends unsummed products (i, j, v) of A B to `consumer` in the stage that makes them. Each cell may come in any number of parts, so this is
    right only for a consumer that distributes over the sum, as the caller must say; any other has to wait for the sum."""
    if not distributes:
        raise AssertionError("unsummed products may only be piped to a consumer that distributes over the sum")
    return outer_product(by_col(a), by_row(b), s, emit="partials").mapInArrow(consumer, schema)


def cosine(at: DataFrame) -> DataFrame:
    """(i, j, v): cosine similarity of the columns i of a matrix (k, i, v), in millionths, for pairs i < j that share a key."""
    c = written(outer_product(at, at.withColumnRenamed("i", "j")), "gram")
    norm = c.filter("i = j").select("i", F.sqrt(F.col("v").cast("double")).alias("norm"))
    pairs = c.filter("i < j").join(norm.withColumnRenamed("norm", "ni"), "i").join(norm.select(F.col("i").alias("j"), F.col("norm").alias("nj")), "j")
    return pairs.select("i", "j", F.floor(F.col("v").cast("double") / (F.col("ni") * F.col("nj")) * 1000000).cast("long").alias("v"))


def reach2(start: DataFrame, edges: DataFrame) -> DataFrame:
    """(node) reached in exactly two steps."""
    v = start.select(F.lit(0).cast("long").alias("row"), F.col("node").alias("col"), F.lit(1).cast("long").alias("v"))
    return product(product(v, edges), edges).select(F.col("col").alias("node")).distinct()


def plan_cost(matrices: list[DataFrame]) -> DataFrame:
    return cost.partial_products(by_col(matrices[0]), by_row(matrices[1]))


