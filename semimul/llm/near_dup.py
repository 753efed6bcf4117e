"""Near-duplicate detection by one-permutation hashing.

One pass over the texts gives each document its set's size and 128-bit fingerprint and, from a single permutation of its shingles cut in
bins, a densified sketch hashed into band keys. Documents with equal sets collapse to one representative first, so that copies cost no
candidates. In each bucket the smallest representative is the centre, and only the star of (centre, member) edges is made; edges are
confirmed on full sets. A star can miss a link between two members that are both too far from the centre. Buckets that still hold more
than one component after the confirmed edges are therefore finished exactly: their documents go through a prefix-filtered join on
their rarest shingles with size and positional bounds, and those pairs are confirmed in the same way.
"""

from __future__ import annotations

from itertools import count

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semimul.llm.common import HOT_SHARE, Scratch, WordHashes, chunks, mix64, spread_join

#: Rows a band and bands: a pair at similarity 0.8 shares no bucket once in two million pairs, and is then not linked.
ROWS, BANDS = 6, 48
#: Draws a bin makes before it takes the next full bin in a circle.
DRAWS = 64
#: 64-bit words of a set's parity bitmap.
WORDS = 4

#: Edges of a graph whose components one task finds by itself, and the types of ids that Python orders as Spark does.
LOCAL_EDGES, LOCAL_IDS = 200_000, {"tinyint", "smallint", "int", "bigint", "string", "date", "binary"}

_EMPTY = np.uint64(0xFFFFFFFFFFFFFFFF)


def shingle_set(words: np.ndarray, width: int) -> np.ndarray:
    """Sorted distinct hashes of the `width`-word shingles; of the whole sequence where there are fewer words."""
    if len(words) == 0:
        return words
    width = min(width, len(words))
    h = np.full(len(words) - width + 1, width, dtype=np.uint64)
    for i in range(width):
        h = mix64(h + words[i : len(words) - width + 1 + i])
    h.sort()
    return h[np.concatenate(([True], h[1:] != h[:-1]))] if len(h) > 1 else h


def probe_table(bins: int) -> np.ndarray:
    """The bins that an empty bin draws from, the same for every document (optimal densification)."""
    i, t = np.meshgrid(np.arange(bins, dtype=np.uint64), np.arange(DRAWS, dtype=np.uint64))
    return (mix64(mix64(i + np.uint64(1)) + t * np.uint64(0x9E3779B97F4A7C15)) % np.uint64(bins)).astype(np.int64)


def sketches(sets: list[np.ndarray], bins: int, probes: np.ndarray) -> np.ndarray:
    """One row of bins for each set (none may be empty): the least hash of each bin, empty bins filled from a full one of the same set."""
    out = np.full(len(sets) * bins, _EMPTY, dtype=np.uint64)
    flat = mix64(np.concatenate(sets) + np.uint64(0x5851F42D4C957F2D))
    owner = np.repeat(np.arange(len(sets), dtype=np.int64) * bins, [len(s) for s in sets])
    np.minimum.at(out, owner + (flat % np.uint64(bins)).astype(np.int64), flat >> np.uint64(1))
    out = out.reshape(len(sets), bins)
    empty = out == _EMPTY
    row, col = np.nonzero(empty)
    for t in range(DRAWS):
        if not len(row):
            break
        source = probes[t, col]
        hit = ~empty[row, source]
        out[row[hit], col[hit]] = out[row[hit], source[hit]]
        row, col = row[~hit], col[~hit]
    step = 1
    while len(row):
        source = (col + step) % bins
        hit = ~empty[row, source]
        out[row[hit], col[hit]] = out[row[hit], source[hit]]
        row, col, step = row[~hit], col[~hit], step + 1
    return out


def band_keys(sketch: np.ndarray, rows: int) -> np.ndarray:
    """64-bit keys, one for each band of `rows` bins; the band's number is part of the key."""
    bands = sketch.shape[1] // rows
    keys = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64), (len(sketch), bands)).copy()
    for j in range(rows):
        keys = mix64(keys + sketch[:, j::rows])
    return keys


def _words(text: bytes | None) -> list[bytes]:
    return (text or b"").lower().split()


def _sketch(batches, width: int, rows: int, bands: int):
    hashes, bins = WordHashes(), rows * bands
    probes = probe_table(bins)
    for batch in batches:
        ids, texts = batch.column(0), batch.column(1).to_pylist()
        for start, end in chunks(texts):
            sets = [shingle_set(hashes.of(_words(t)), width) for t in texts[start:end]]
            prints = [xxhash.xxh3_128_intdigest(s.tobytes()) for s in sets]
            full = [s for s in sets if len(s)]
            keys = band_keys(sketches(full, bins, probes), rows) if full else np.zeros((0, bands), np.uint64)
            sizes = np.array([len(s) for s in sets], dtype=np.int64)
            ends = np.concatenate(([0], np.cumsum(np.where(sizes > 0, bands, 0)))).astype(np.int32)
            low = np.array([p & 0xFFFFFFFFFFFFFFFF for p in prints], dtype=np.uint64).view(np.int64)
            high = np.array([p >> 64 for p in prints], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays(
                [ids.slice(start, end - start), pa.array(sizes), pa.array(low), pa.array(high), pa.ListArray.from_arrays(pa.array(ends), pa.array(keys.ravel().view(np.int64)))],
                names=["id", "n", "f1", "f2", "keys"],
            )


def _source(docs: DataFrame, id_col: str, text_col: str) -> tuple[DataFrame, str]:
    """(id, text) with the text as bytes, and the id's type."""
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("binary").alias("text")), docs.schema[id_col].dataType.simpleString()


def sketch_table(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 4, rows: int = ROWS, bands: int = BANDS) -> DataFrame:
    """(id, n, f1, f2, keys): set size, fingerprint and band keys of each document."""
    source, kind = _source(docs, id_col, text_col)
    return source.mapInArrow(lambda b: _sketch(b, width, rows, bands), f"id {kind}, n long, f1 long, f2 long, keys array<long>")


def _sets(batches, width: int):
    hashes = WordHashes()
    for batch in batches:
        ids, texts = batch.column(0), batch.column(1).to_pylist()
        for start, end in chunks(texts):
            sets = [shingle_set(hashes.of(_words(t)), width).view(np.int64) for t in texts[start:end]]
            ends = np.concatenate(([0], np.cumsum([len(s) for s in sets]))).astype(np.int32)
            yield pa.RecordBatch.from_arrays([ids.slice(start, end - start), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(sets)))], names=["id", "set"])


def _union(batches):
    """(id, comp) of all edges of the batches, by union-find with the least id as root."""
    over: dict = {}

    def root(x):
        while over[x] != x:
            over[x] = x = over[over[x]]
        return x

    kind = None
    for batch in batches:
        kind = batch.schema.field(0).type
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            over.setdefault(a, a)
            over.setdefault(b, b)
            a, b = root(a), root(b)
            over[max(a, b)] = min(a, b)
    if over:
        yield pa.RecordBatch.from_arrays([pa.array(list(over), kind), pa.array([root(x) for x in list(over)], kind)], names=["id", "comp"])


def components(edges: DataFrame, scratch: Scratch, name: str) -> DataFrame:
    """(id, comp) for each end of the undirected edges (a, b): the least id reachable. A node takes the least label next to it and hands it to
    the node whose id was its label, so that whole trees are hooked at once, and labels jump through their labels' labels. Rounds go on
    until no label moves and grow with the logarithm of a component's width, whatever the order of its ids (a simulated path of a million nodes
    took 20 to 25); each round is a written table. Nodes with very many links are dealt over tasks. A graph of at most LOCAL_EDGES edges takes
    one task and no rounds, each of which costs the driver some plans and a few hundred task reports."""
    both = scratch.save(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), f"{name}-both", few=True)
    held, kind = both.count(), both.schema["a"].dataType.simpleString()
    if held <= 2 * LOCAL_EDGES and kind in LOCAL_IDS:
        labels = scratch.save(both.filter("a <= b").coalesce(1).mapInArrow(_union, f"id {kind}, comp {kind}"), f"{name}-0", few=True)
        scratch.drop(f"{name}-both")
        return labels
    # links to a node of very many are dealt over salts once; its label is then copied for each in every round
    share = F.lit(HOT_SHARE / max(1, held))
    labels = both.groupBy("a").agg(F.least("a", F.min("b")).alias("comp"), F.ceil(F.count(F.lit(1)) * share).cast("int").alias("salts"))
    labels = scratch.save(labels.select(F.col("a").alias("id"), "comp", "salts"), f"{name}-0", few=True)
    hot = F.broadcast(labels.filter("salts > 1").select(F.col("id").alias("b"), "salts"))  # fewer than HOT_SHARE
    both = scratch.save(both.join(hot, "b", "left").select("a", "b", F.coalesce(F.pmod(F.xxhash64("a"), "salts").cast("int"), F.lit(0)).alias("salt")), f"{name}-edges", few=True)
    scratch.drop(f"{name}-both")
    none = F.lit(None).cast(labels.schema["id"].dataType)
    for i in count(1):
        copied = labels.select(F.col("id").alias("b"), "comp", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"))
        near = both.join(copied, ["b", "salt"]).groupBy("a").agg(F.min("comp").alias("near"))
        low = labels.join(near, labels.id == near.a).select("id", "comp", "salts", F.least("comp", "near").alias("low"))
        # to the node itself and, where the label falls, to the old label's node
        own = F.struct("id", "comp", "salts", "low")
        root = F.struct(F.col("comp").alias("id"), none.alias("comp"), F.lit(None).cast("int").alias("salts"), "low")
        told = low.select(F.explode(F.when(F.col("low") < F.col("comp"), F.array(own, root)).otherwise(F.array(own))).alias("x")).select("x.*")
        low = told.groupBy("id").agg(F.max("comp").alias("comp"), F.max("salts").alias("salts"), F.min("low").alias("low"))
        jump = labels.select(F.col("id").alias("low"), F.col("comp").alias("far"))
        new = low.join(jump, "low", "left").withColumn("far", F.coalesce("far", "low"))
        new = new.select("id", "salts", F.least("low", "far").alias("new"), (F.least("low", "far") != F.col("comp")).alias("moved"))
        new = scratch.save(new, f"{name}-{i}", few=True)
        moved = not new.filter("moved").isEmpty()
        scratch.drop(f"{name}-{i - 1}")
        labels = new.select("id", F.col("new").alias("comp"), "salts")
        if not moved:
            scratch.drop(f"{name}-edges")
            return labels.select("id", "comp")


def _similar(inter: Column, n: Column, m: Column, percent: int) -> Column:
    return 100 * inter >= percent * (n + m - inter)


def confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b), a written table, whose full sets are similar. The set of a centre of very many pairs is copied to many tasks."""
    ends = pairs.groupBy("a").agg(F.count(F.lit(1)).alias("weight"))
    left = sets.join(ends, sets.id == ends.a).select("a", F.col("set").alias("left"))
    right = pairs.join(sets, F.col("b") == F.col("id")).select("a", "b", F.col("set").alias("right"))
    inter = F.size(F.array_intersect("left", "right"))
    met = spread_join(right, left, ["a"], ends, pairs.count(), ["b"])
    return met.filter(_similar(inter, F.size("left"), F.size("right"), percent)).select("a", "b")


def _finish(members: DataFrame, sets: DataFrame, percent: int, scratch: Scratch) -> DataFrame:
    """Pairs of documents of different components among `members` (id, comp) that may be similar: they share one of their rarest shingles
    at positions, and have sizes and parity bitmaps, that leave room for the overlap. No similar pair is missed."""
    t = percent / 100
    rows = sets.join(members, "id").select("id", "comp", F.size("set").alias("n"), F.explode("set").alias("tok"))
    df = scratch.save(rows.groupBy("tok").agg(F.count(F.lit(1)).alias("df")).filter("df > 1"), "df", few=True)
    weights, total = df.select("tok", F.col("df").alias("weight")), sets.agg(F.sum(F.size("set"))).first()[0] or 0
    # parity bitmap: two sets differ in at least as many shingles as their bitmaps differ in bits
    parity = [F.bit_xor(F.expr(f"IF(pmod(tok, {WORDS}) = {q}, shiftleft(1L, CAST(pmod(shiftright(tok, 8), 64) AS INT)), 0L)")).alias(f"x{q}") for q in range(WORDS)]
    toks = F.sort_array(F.collect_list(F.struct(F.coalesce("df", F.lit(0)).alias("df"), "tok"))).alias("toks")
    near = spread_join(rows, df, ["tok"], weights, total, ["id"], "left").groupBy("id", "comp", "n").agg(toks, *parity)
    # shingles of one document only come first and have no partner, yet they fill the prefix
    room = F.col("n") - F.ceil(F.col("n") * t - 1e-9) + 1
    bits = [f"x{q}" for q in range(WORDS)]
    prefix = near.select("id", "comp", "n", *bits, F.posexplode(F.slice("toks", F.lit(1), room.cast("int"))).alias("pos", "x")).filter("x.df > 0").select("id", "comp", "n", *bits, "pos", F.col("x.tok").alias("tok"))
    need = lambda n, m: F.ceil((n + m) * (t / (1 + t)) - 1e-9)
    names = lambda p: [F.col(c).alias(f"{p}_{c}") for c in ("id", "comp", "n", "pos", *bits)]
    long_, short = prefix.select("tok", *names("l")), prefix.filter(F.col("n") - F.col("pos") >= need(F.col("n"), F.col("n"))).select("tok", *names("s"))
    n, m = F.col("l_n"), F.col("s_n")
    bound = (m < n) | ((m == n) & (F.col("s_id") < F.col("l_id")))
    fits = (m >= n * t - 1e-9) & (n - F.col("l_pos") >= need(n, m)) & (m - F.col("s_pos") >= need(n, m))
    apart = sum((F.bit_count(F.col(f"l_{x}").bitwiseXOR(F.col(f"s_{x}"))) for x in bits), F.lit(0))
    fits = fits & (apart <= n + m - 2 * need(n, m))
    found = long_.join(short, "tok").filter((F.col("l_comp") != F.col("s_comp")) & bound & fits)
    return found.select(F.least("l_id", "s_id").alias("a"), F.greatest("l_id", "s_id").alias("b")).distinct()


def near_duplicates(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 80, rows: int = ROWS, bands: int = BANDS) -> DataFrame:
    """(id, n_shingles, component_id) for each row: documents whose sets of `width`-word shingles have a Jaccard similarity of at least
    `percent` / 100 are linked, and component_id is the least id reachable over links. Ids may be of any type that can be ordered.

    Words are parted by ASCII white space, with A-Z in lower case. A document of fewer than `width` words has its whole sequence as its one
    shingle; null, empty and blank texts have none and are linked with nothing. Rows that share an id are one node (linked if either text
    is); a null id is left out of links and gets a null component. Other columns are not read. An empty table gives an empty result.
    """
    scratch = Scratch(docs.sparkSession, "near-dup")
    sketch = scratch.save(sketch_table(docs, id_col=id_col, text_col=text_col, width=width, rows=rows, bands=bands), "sketch")
    usable = sketch.filter("n > 0 and id is not null")
    same = ["f1", "f2", "n"]
    # equal sets: one representative, which alone takes part from here on
    copies = scratch.save(usable.groupBy(*same).agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("weight")), "copies", few=True)
    reps = usable.join(copies.select("f1", "f2", F.col("rep").alias("id")), ["f1", "f2", "id"], "left_semi")

    keyed = reps.select(F.explode("keys").alias("key"), "id", "n")
    stars = keyed.groupBy("key").agg(F.min("id").alias("centre"), F.max("id").alias("last"), F.count(F.lit(1)).alias("weight")).filter("centre <> last")
    stars = scratch.save(stars.select("key", "centre", "weight"), "stars", few=True)
    sizes = copies.select(F.col("rep").alias("centre"), F.col("n").alias("m"))
    centres = stars.join(sizes.groupBy("centre").agg(F.collect_set("m").alias("ms")), "centre").select("key", "centre", "ms")
    shared = scratch.save(spread_join(keyed, centres, ["key"], stars.select("key", "weight"), bands * copies.count(), ["id"]), "shared", few=True)
    fits = F.exists("ms", lambda m: 100 * F.least("n", m) >= percent * F.greatest("n", m))
    pairs = shared.filter((F.col("id") != F.col("centre")) & fits)
    pairs = scratch.save(pairs.select(F.col("centre").alias("a"), F.col("id").alias("b")).distinct(), "pairs", few=True)

    held = shared.select("id").distinct()
    source, kind = _source(docs, id_col, text_col)
    sets = scratch.save(source.join(held, "id", "left_semi").mapInArrow(lambda b: _sets(b, width), f"id {kind}, set array<long>"), "sets")
    links = scratch.save(confirm(pairs, sets, percent), "links", few=True)
    found = components(links, scratch, "star")

    # buckets with more than one component are finished exactly, on top of what the stars have linked
    lab = shared.select("key", "id").join(found, "id", "left").select("key", "id", F.coalesce("comp", "id").alias("comp"))
    mixed = lab.groupBy("key").agg(F.min("comp").alias("c1"), F.max("comp").alias("c2")).filter("c1 <> c2").select("key")
    mixed = scratch.save(mixed, "mixed", few=True)
    members = scratch.save(lab.join(mixed, "key", "left_semi").select("id", "comp").distinct(), "members", few=True)
    more = scratch.save(_finish(members, sets.join(members.select("id"), "id", "left_semi"), percent, scratch), "more", few=True)
    comp_of = members.groupBy("id").agg(F.min("comp").alias("comp"))
    linked = confirm(more, sets, percent).join(comp_of.select(F.col("id").alias("a"), F.col("comp").alias("ca")), "a").join(comp_of.select(F.col("id").alias("b"), F.col("comp").alias("cb")), "b")
    edges = linked.select(F.col("ca").alias("a"), F.col("cb").alias("b"))
    # rows that share an id but not a text tie their representatives together
    twice = usable.groupBy("id").agg(F.count(F.lit(1)).alias("rows")).filter("rows > 1").select("id")
    tied = usable.join(twice, "id", "left_semi").select("id", *same).distinct().join(copies, same).join(found.withColumnRenamed("id", "rep"), "rep", "left")
    tied = tied.groupBy("id").agg(F.collect_set(F.coalesce("comp", "rep")).alias("c")).filter(F.size("c") > 1).select(F.array_min("c").alias("a"), F.explode("c").alias("b")).filter("a <> b")
    above = components(edges.unionByName(tied), scratch, "all")

    first = copies.join(found.withColumnRenamed("id", "rep"), "rep", "left").select(*same, "weight", F.coalesce("comp", "rep").alias("c1"))
    final = scratch.save(first.join(above.select(F.col("id").alias("c1"), F.col("comp").alias("c2")), "c1", "left").select(*same, "weight", F.coalesce("c2", "c1").alias("component_id")), "final", few=True)
    for name in ("copies", "stars", "shared", "pairs", "sets", "links", "mixed", "members", "df", "more"):
        scratch.drop(name)
    done = spread_join(usable.select("id", *same), final.drop("weight"), same, final.select(*same, "weight"), usable.count(), ["id"])
    rest = sketch.filter("n = 0 or id is null").select("id", "n", F.col("id").alias("component_id"))
    done = done.select("id", "n", "component_id").unionByName(rest)
    blank = rest.filter("id is not null").select("id").join(usable.select("id"), "id", "left_semi")
    if not blank.isEmpty():
        # a blank row whose id has words in another row goes with that row
        own = done.filter("n > 0").join(blank.distinct(), "id", "left_semi").groupBy("id").agg(F.min("component_id").alias("own"))
        done = done.join(own, "id", "left").select("id", "n", F.coalesce("own", "component_id").alias("component_id"))
    return done.select("id", F.col("n").alias("n_shingles"), "component_id")
