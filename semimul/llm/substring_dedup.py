"""Repeated passages by recompression.

Each text is a string of words. Every round of recompression names runs of one symbol, with their length, and then pairs of neighbours;
which symbols open a pair and which close one is drawn from a hash of the symbol under several coins. A name is a hash of what it stands
for, so the names of all documents agree without a table of names, and equal stretches get equal symbols but near their ends. Each round is
one step of the plan over all documents; its symbols stand for about three times as many words as those of the round before.

Symbols of the first round are small against the wanted window. Such a symbol depends on a stretch of words around it that is known (`low` to
`high`; a run depends on the symbols that end it, however far they are), so a window that holds the stretch holds the symbol wherever
it stands. The least of a window's symbols is its anchor; a window that is all one repetition and so holds none is its own. Anchors, named
with their stretch, are counted over all documents. Only windows at anchors that occur twice can repeat.

Symbols of the last round stand for passages. A row of `SPAN` neighbours that occurs twice, by name and by a second hash of its words, is a
long repeat: all windows in it repeat. These need no count of their own, but for one occurrence of each such passage, the least by id
and place, whose windows stand in for the rest. All other windows at repeated anchors are verified by counting their own hashes.

Equal keys within a batch of documents are settled there and only one of them goes on to where the key is counted, so that a passage held
by very many documents reaches one task no more often than there are batches.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from semimul.llm.common import WordHashes, chunks, mix64

#: Rounds of naming, coins drawn in a round, and neighbours of the last round that make a passage.
ROUNDS, COINS, SPAN = 3, 4, 3

_U = np.uint64
_BASE = _U(0x9E3779B97F4A7C15 | 1)
_BASE2 = _U(0xC2B2AE3D27D4EB4F | 1)
#: Flags of a row's code: the key's first row in its batch, a key that the batch holds again, a passage of the last round.
_FIRST, _TWICE, _PASSAGE, _BITS = 1, 2, 4, 3


def _powers(n: int, base: np.uint64) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd number and of its inverse, modulo 2 ** 64."""
    inverse = _U(pow(int(base), -1, 1 << 64))
    up, down = np.full(n + 1, base, dtype=_U), np.full(n + 1, inverse, dtype=_U)
    up[0] = down[0] = 1
    return np.cumprod(up, dtype=_U), np.cumprod(down, dtype=_U)


class Rolling:
    """Hash of any stretch of a sequence of word hashes."""

    def __init__(self, words: np.ndarray, base: np.uint64 = _BASE):
        up, self.down = _powers(len(words), base)
        self.sums = np.concatenate((np.zeros(1, _U), np.cumsum(words * up[: len(words)], dtype=_U)))

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix64((self.sums[end] - self.sums[start]) * self.down[start] + (end - start).astype(_U))


class Symbols:
    """The symbols of some texts in a row: names, hashes of the words (`h`, which compose), first words, and which symbols begin a text. For the
    first round also the stretch of words [low, high) that decides on each symbol; what depends on a text's end reaches beyond it."""

    def __init__(self, names: np.ndarray, h: np.ndarray, starts: np.ndarray, begins: np.ndarray, n_words: int, stretches: bool):
        self.names, self.h, self.starts, self.begins, self.n_words = names, h, starts, begins, n_words
        self.low, self.high = (starts.copy(), self.ends()) if stretches else (None, None)

    def ends(self) -> np.ndarray:
        return np.append(self.starts[1:], self.n_words) if len(self.starts) else self.starts

    def _neighbours(self) -> tuple[np.ndarray, np.ndarray]:
        """`low` of the symbol before and `high` of the one after each symbol; one word beyond the text where there is none."""
        before = np.where(self.begins, self.starts - 1, np.append(self.low[:1], self.low[:-1]))
        last = np.append(self.begins[1:], True)
        after = np.where(last, self.ends() + 1, np.append(self.high[1:], self.high[-1:]))
        return before, after

    def _keep(self, keep: np.ndarray) -> None:
        self.names, self.h, self.starts, self.begins = self.names[keep], self.h[keep], self.starts[keep], self.begins[keep]
        if self.low is not None:
            self.low, self.high = self.low[keep], self.high[keep]

    def name_runs(self, level: int) -> None:
        """Each maximal run of one symbol becomes one symbol, named by it and the run's length."""
        n = len(self.names)
        if not n:
            return
        new = np.ones(n, dtype=bool)
        new[1:] = (self.names[1:] != self.names[:-1]) | self.begins[1:]
        first = np.flatnonzero(new)
        length = np.diff(np.append(first, n))
        if self.low is not None:
            before, after = self._neighbours()
            self.low[first], self.high[first] = before[first], after[first + length - 1]
        many = first[length > 1]
        if len(many):
            k, p = length[length > 1].astype(_U), _power(self.ends()[many] - self.starts[many])
            total, step = np.zeros(len(many), _U), np.ones(len(many), _U)
            for bit in range(int(k.max()).bit_length() - 1, -1, -1):
                total, step = total + total * step, step * step
                odd = (k >> _U(bit)) & _U(1) == 1
                total, step = np.where(odd, total * p + _U(1), total), np.where(odd, step * p, step)
            self.h[many] = self.h[many] * total
            self.names[many] = mix64(mix64(self.names[many] + _U(1000 + level)) + k)
        self._keep(new)

    def name_pairs(self, coin: int) -> None:
        """Each opening symbol that a closing one follows becomes a pair with it."""
        if len(self.names) < 2:
            return
        opens = (mix64(self.names + _U(coin)) & _U(1)) == 0
        merge = np.append(opens[:-1] & ~opens[1:] & ~self.begins[1:], False)
        left = np.flatnonzero(merge)
        if self.low is not None:
            before, after = self._neighbours()
            closed = np.append(False, merge[:-1])
            lone = ~opens & ~closed
            self.high = np.where(opens, after, self.high)
            self.low = np.where(lone, before, self.low)
        self.h[left] = self.h[left] * _power(self.ends()[left + 1] - self.starts[left + 1]) + self.h[left + 1]
        self.names[left] = mix64(mix64(self.names[left] + _U(17 + coin)) + self.names[left + 1])
        keep = np.ones(len(self.names), dtype=bool)
        keep[left + 1] = False
        self._keep(keep)

    def round(self, level: int) -> Symbols:
        self.name_runs(level)
        for coin in range(COINS):
            self.name_pairs(1 + level * COINS + coin)
        return self


def _power(lengths: np.ndarray) -> np.ndarray:
    """The base to each length."""
    table = np.full(int(lengths.max()) + 1 if len(lengths) else 1, _BASE, dtype=_U)
    table[0] = 1
    return np.cumprod(table, dtype=_U)[lengths]


def first_symbols(words: np.ndarray, breaks: np.ndarray) -> Symbols:
    """The words of texts in a row as symbols; `breaks` are the first words of the texts that have any."""
    begins = np.zeros(len(words), dtype=bool)
    begins[breaks[breaks < len(words)]] = True
    return Symbols(words.copy(), mix64(words), np.arange(len(words)), begins, len(words), True)


def _range_min(values: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Place of the least value (leftmost of equals) in each range [low, high], none of which is empty."""
    longest = int((high - low).max()) + 1 if len(low) else 1
    table = [np.arange(len(values))]
    span = 1
    while 2 * span <= longest:
        a = table[-1][:-span] if span else table[-1]
        b = table[-1][span:]
        table.append(np.where(values[b] < values[a], b, a))
        span *= 2
    level = np.frexp((high - low + 1).astype(float))[1] - 1
    out = np.empty(len(low), dtype=np.int64)
    for k in np.unique(level):
        at = level == k
        a, b = table[k][low[at]], table[k][high[at] - (1 << int(k)) + 1]
        out[at] = np.where(values[b] < values[a], b, np.where(values[a] < values[b], a, np.minimum(a, b)))
    return out


def anchors(words: np.ndarray, breaks: np.ndarray, size: int, symbols: Symbols | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Windows (first words), and for each the first word and the end of its anchor's stretch, which is the whole window where that holds no
    symbol. `breaks` holds the texts' first words."""
    bounds = np.append(breaks, len(words))
    counts = np.maximum(np.diff(bounds) - size + 1, 0)
    if not counts.sum():
        empty = np.zeros(0, dtype=np.int64)
        return empty, empty, empty
    windows = np.repeat(bounds[:-1] - np.concatenate(([0], np.cumsum(counts)[:-1])), counts) + np.arange(counts.sum())
    found = symbols or first_symbols(words, breaks).round(0)
    low = np.searchsorted(found.low, windows, side="left")
    high = np.searchsorted(found.high, windows + size, side="right") - 1
    first, last = windows.copy(), windows + size
    sure = low <= high
    at = _range_min(mix64(found.names + _U(99)), low[sure], high[sure])
    first[sure], last[sure] = found.low[at], found.high[at]
    return windows, first, last


def _settle(keys: np.ndarray, second: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each key its first place, and whether each row's key occurs more than once."""
    order = np.lexsort((second, keys))
    new = np.ones(len(keys), dtype=bool)
    new[1:] = (keys[order][1:] != keys[order][:-1]) | (second[order][1:] != second[order][:-1])
    group = np.cumsum(new) - 1
    many = np.bincount(group, minlength=group[-1] + 1 if len(group) else 0)[group] > 1
    repeated = np.empty(len(keys), dtype=bool)
    repeated[order] = many
    first = np.zeros(len(keys), dtype=bool)
    first[order[new]] = True
    return first, repeated


def _joined(texts: list[bytes | None], hashes: WordHashes) -> tuple[np.ndarray, np.ndarray]:
    parts = [hashes.of((t or b"").split()) for t in texts]
    return np.concatenate(parts) if parts else np.zeros(0, _U), np.concatenate(([0], np.cumsum([len(p) for p in parts]))).astype(np.int64)


def _blobs(values: np.ndarray, bounds: np.ndarray) -> pa.Array:
    """Binary values that hold the stretches of an array between the bounds."""
    data, step = np.ascontiguousarray(values), values.dtype.itemsize
    return pa.Array.from_buffers(pa.binary(), len(bounds) - 1, [None, pa.py_buffer((bounds * step).astype(np.int32)), pa.py_buffer(data)])


def _unblob(column: pa.Array, dtype) -> tuple[np.ndarray, np.ndarray]:
    """The values of all rows in a row, and where each row begins."""
    step = np.dtype(dtype).itemsize
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int32)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    values = np.frombuffer(data, dtype=np.uint8)[offsets[0] : offsets[-1]].view(dtype) if data is not None and offsets[-1] > offsets[0] else np.zeros(0, dtype)
    return values, ((offsets - offsets[0]) // step).astype(np.int64)


_NAMED = ("id", "n", "names", "h", "starts", "anchors")


def _named(ids: pa.Array, symbols: Symbols, bounds: np.ndarray, anchor_rows: np.ndarray, anchor_bounds: np.ndarray) -> pa.RecordBatch:
    cut = np.searchsorted(symbols.starts, bounds)
    owner = np.repeat(np.arange(len(bounds) - 1), np.diff(cut))
    starts = (symbols.starts - bounds[owner]).astype(np.int32)
    return pa.RecordBatch.from_arrays([ids, pa.array(np.diff(bounds)), _blobs(symbols.names, cut), _blobs(symbols.h, cut), _blobs(starts, cut), _blobs(anchor_rows.ravel(), 3 * anchor_bounds)], names=list(_NAMED))


def _first_round(batches, size: int):
    """Words, their names after one round, and the anchors: for each run of windows with one anchor its name, first window and number."""
    hashes = WordHashes()
    for batch in batches:
        texts = batch.column(1).to_pylist()
        for start, end in chunks(texts):
            words, bounds = _joined(texts[start:end], hashes)
            symbols = first_symbols(words, bounds[:-1]).round(0)
            windows, first, last = anchors(words, bounds[:-1], size, symbols)
            new = np.ones(len(windows), dtype=bool)
            new[1:] = (first[1:] != first[:-1]) | (last[1:] != last[:-1]) | (windows[1:] != windows[:-1] + 1)
            head = np.flatnonzero(new)
            doc = np.searchsorted(bounds, windows[head], side="right") - 1
            names = Rolling(words).of(first[head], last[head])
            rows = np.stack([names.view(np.int64), windows[head] - bounds[doc], np.diff(np.append(head, len(windows)))], axis=1) if len(head) else np.zeros((0, 3), np.int64)
            yield _named(batch.column(0).slice(start, end - start), symbols, bounds, rows, np.searchsorted(doc, np.arange(end - start + 1)))


def _read_named(batch: pa.RecordBatch) -> tuple[Symbols, np.ndarray, np.ndarray, np.ndarray]:
    """Symbols of a batch, the texts' first words, and the anchors with their bounds."""
    bounds = np.concatenate(([0], np.cumsum(batch.column(1).to_numpy()))).astype(np.int64)
    (names, cut), (h, _), (starts, _) = (_unblob(batch.column(k), t) for k, t in ((2, _U), (3, _U), (4, np.int32)))
    owner = np.repeat(np.arange(batch.num_rows), np.diff(cut))
    begins = np.zeros(len(names), dtype=bool)
    begins[cut[:-1][np.diff(cut) > 0]] = True
    found, at = _unblob(batch.column(5), np.int64)
    return Symbols(names.copy(), h.copy(), starts + bounds[owner], begins, int(bounds[-1]), False), bounds, found.reshape(-1, 3), at // 3


def _next_round(batches, level: int):
    for batch in batches:
        symbols, bounds, rows, at = _read_named(batch)
        yield _named(batch.column(0), symbols.round(level), bounds, rows, at)


def _last_round(batches, level: int, size: int):
    """(name, check, id, code): anchors and passages; the code holds the first window, the number of windows, and the flags."""
    for batch in batches:
        symbols, bounds, rows, at = _read_named(batch)
        symbols.round(level)
        cut, ends = np.searchsorted(symbols.starts, bounds), symbols.ends()
        doc = np.repeat(np.arange(batch.num_rows), np.diff(cut))
        # a passage begins at each symbol that SPAN - 1 others of its text follow, or at the first of a text with fewer
        place = np.arange(len(doc)) - cut[doc]
        number = np.diff(cut)[doc] if len(doc) else np.zeros(0, np.int64)
        begin = np.flatnonzero((place + SPAN <= number) | ((place == 0) & (number < SPAN)))
        name, check, end = np.full(len(begin), 7, _U), np.zeros(len(begin), _U), symbols.starts[begin]
        for k in range(SPAN):
            here = np.minimum(begin + k, len(doc) - 1)
            more = place[begin] + k < number[begin]
            name = np.where(more, mix64(name + symbols.names[here]), name)
            check = np.where(more, check * _power(ends[here] - symbols.starts[here]) + symbols.h[here], check)
            end = np.where(more, ends[here], end)
        windows = end - symbols.starts[begin] - size + 1
        held, begin = windows > 0, begin[windows > 0]
        owner = np.concatenate((np.repeat(np.arange(batch.num_rows), np.diff(at)), doc[begin]))
        names = np.concatenate((rows[:, 0].view(_U), name[held]))
        checks = np.concatenate((np.zeros(len(rows), _U), mix64(check[held]) | _U(1)))
        first = np.concatenate((rows[:, 1], symbols.starts[begin] - bounds[doc[begin]]))
        code = first << 32 | np.concatenate((rows[:, 2], windows[held])) << _BITS | np.concatenate((np.zeros(len(rows), np.int64), np.full(len(begin), _PASSAGE)))
        yield from _settled(batch.column(0), owner, names, checks, code)


def _settled(ids: pa.Array, owner: np.ndarray, names: np.ndarray, checks: np.ndarray, code: np.ndarray, always: np.ndarray | None = None):
    """Rows by the order of their ids and places, so that the first of equal keys is the least, with the flags of the batch. `always` marks rows
    that are known to repeat."""
    if not len(owner):
        return
    rank = np.empty(len(ids), dtype=np.int64)
    rank[pc.sort_indices(ids).to_numpy()] = np.arange(len(ids))
    order = np.lexsort((code, rank[owner]))
    owner, names, checks, code = owner[order], names[order], checks[order], code[order]
    first, twice = _settle(names, checks)
    if always is not None:
        first, twice = first & ~always[order], twice | always[order]
    code = code | first * _FIRST | twice * _TWICE
    yield pa.RecordBatch.from_arrays([pa.array(names.view(np.int64)), pa.array(checks.view(np.int64)), ids.take(pa.array(owner)), pa.array(code)], names=["name", "check", "id", "code"])


def _window_rows(batches, size: int):
    """(name, check, id, code): hashes of the windows at repeated anchors, one occurrence for those inside known passages; and, as rows that are
    known to repeat, the stretches of windows that repeated passages or the batch itself settle."""
    hashes = WordHashes()
    for batch in batches:
        texts, held = batch.column(1).to_pylist(), batch.column(2).to_pylist()
        for start, end in chunks(texts, 8_000_000):
            words, bounds = _joined(texts[start:end], hashes)
            places = [np.array(p or [], dtype=np.int64) for p in held[start:end]]
            base = np.repeat(bounds[:-1], [len(p) for p in places])
            code = np.concatenate(places) if places else np.zeros(0, np.int64)
            # rows that share an id share their places, of which only those that fit a text are its own
            number = np.minimum((code & 0xFFFFFFFF) >> _BITS, np.repeat(np.diff(bounds), [len(p) for p in places]) - size + 1 - (code >> 32))
            code, base, number = code[number > 0], base[number > 0], number[number > 0]
            first = (code >> 32) + base
            inside = lambda some: np.cumsum(np.bincount(first[some], minlength=len(words) + 1) - np.bincount((first + number)[some], minlength=len(words) + 1))[:-1] > 0
            passage, own = code & _PASSAGE > 0, code & _FIRST > 0
            known = inside(passage)
            ask = np.flatnonzero(inside(~passage) & (~known | inside(passage & own)))
            h1, h2 = Rolling(words).of(ask, ask + size), Rolling(words, _BASE2).of(ask, ask + size)
            # what the batch itself settles is told as stretches, but for the first of each key
            once, twice = _settle(h1, h2)
            known[ask[twice & ~once]] = True
            ask, h1, h2 = (x[~twice | once] for x in (ask, h1, h2))
            edge = np.diff(np.concatenate(([0], known.astype(np.int8), [0])))
            run, stop = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
            owner = np.searchsorted(bounds, np.concatenate((ask, run)), side="right") - 1
            at = np.concatenate((ask, run)) - bounds[owner]
            always = np.concatenate((np.zeros(len(ask), bool), np.ones(len(run), bool)))
            again = np.concatenate((twice[~twice | once], np.zeros(len(run), bool)))
            rows = at << 32 | np.concatenate((np.ones(len(ask), np.int64), stop - run)) << _BITS | again * _TWICE
            names = np.concatenate((h1, mix64(run.astype(_U))))
            ids = batch.column(0).slice(start, end - start)
            yield from _flagged(ids, owner, names, np.concatenate((h2, np.zeros(len(run), _U))), rows | np.where(always, _TWICE, _FIRST))


def _flagged(ids: pa.Array, owner: np.ndarray, names: np.ndarray, checks: np.ndarray, code: np.ndarray):
    if len(owner):
        yield pa.RecordBatch.from_arrays([pa.array(names.view(np.int64)), pa.array(checks.view(np.int64)), ids.take(pa.array(owner)), pa.array(code)], names=["name", "check", "id", "code"])


def _cut(batches, size: int):
    for batch in batches:
        ids, texts, held = batch.column(0), batch.column(1).to_pylist(), batch.column(2).to_pylist()
        for start, end in chunks(texts):
            total, gone, kept = [], [], []
            for text, at in zip(texts[start:end], held[start:end]):
                words = (text or b"").split()
                if at:
                    step = np.zeros(len(words) + 1, dtype=np.int64)
                    at = np.array(at, dtype=np.int64)
                    first, last = at >> 32, (at >> 32) + ((at & 0xFFFFFFFF) >> _BITS) + size - 1
                    fits = last <= len(words)
                    np.add.at(step, first[fits], 1)
                    np.add.at(step, last[fits], -1)
                    drop = np.cumsum(step[:-1]) > 0
                    left = [w for w, d in zip(words, drop.tolist()) if not d]
                else:
                    left = words
                total.append(len(words))
                gone.append(len(words) - len(left))
                kept.append(b" ".join(left))
            yield pa.RecordBatch.from_arrays([ids.slice(start, end - start), pa.array(total, pa.int64()), pa.array(gone, pa.int64()), pa.array([k.decode(errors="replace") for k in kept], pa.string())], names=["id", "n_words", "n_removed", "kept"])


def _repeated(rows: DataFrame, least: bool = False) -> DataFrame:
    """(id, code) of the rows whose key occurs more than once; with `least`, the first flag stays on the least of all. Rows whose key their batch
    has settled and already sent on are dealt at random, since nothing has to be counted for them."""
    first = F.expr(f"code & {_FIRST} = {_FIRST}")
    salt = F.when(first, F.lit(0).cast("long")).otherwise(F.xxhash64("id", "code"))
    key = Window.partitionBy("name", "check", "salt")
    found, code = [F.count(F.lit(1)).over(key).alias("n")], F.expr(f"code & ~{_FIRST | _TWICE}")
    if least:
        found.append(F.min(F.struct("id", "code")).over(key).alias("least"))
        code = code.bitwiseOR(F.when(first & (F.col("least") == F.struct("id", "code")), F.lit(_FIRST)).otherwise(F.lit(0)))
    # both over one window: a second one would be dealt anew
    counted = rows.withColumn("salt", salt).select("id", "code", *found)
    return counted.filter(f"n > 1 or code & {_TWICE} = {_TWICE}").select("id", code.cast("long").alias("code"))


def remove_repeats(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", size: int = 35) -> DataFrame:
    """(id, n_words, n_removed, kept): each document's words without those inside a window of `size` words that also starts elsewhere, in the
    same or another document; kept words are joined by one space. Windows are judged on the input. Ids may be of any type that can be
    ordered.

    Words are parted by ASCII white space. Null and empty texts have no words; texts of fewer than `size` words keep all. Rows that share an
    id are pooled by word position (repeated rows repeat each other's windows); a null id takes no part and keeps its words. Other columns
    are not read; an empty table gives an empty result.
    """
    spark, kind = docs.sparkSession, docs.schema[id_col].dataType.simpleString()
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("binary").alias("text"))
    # dealt by id once: both joins read the same exchange. A key that is never null keeps the first join from filtering below it.
    key = F.coalesce(F.concat(F.lit("="), F.col("id").cast("string")), F.lit("")).alias("key")
    keyed = source.select(key, "id", "text").repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "key")
    rows_type = f"name long, check long, id {kind}, code long"
    named_type = f"id {kind}, n long, names binary, h binary, starts binary, anchors binary"
    named = source.filter("id is not null").mapInArrow(lambda b: _first_round(b, size), named_type)
    for level in range(1, ROUNDS - 1):
        named = named.mapInArrow(lambda b, level=level: _next_round(b, level), named_type)
    rows = named.mapInArrow(lambda b: _last_round(b, ROUNDS - 1, size), rows_type)
    met = lambda found, name: found.groupBy(key).agg(F.collect_set("code").alias(name)).hint("shuffle_hash")
    dealt = keyed.join(met(_repeated(rows, least=True), "places"), "key").select("id", "text", "places")
    windows = dealt.mapInArrow(lambda b: _window_rows(b, size), rows_type)
    done = keyed.join(met(_repeated(windows), "starts"), "key", "left").select("id", "text", "starts")
    return done.mapInArrow(lambda b: _cut(b, size), f"id {kind}, n_words long, n_removed long, kept string")
