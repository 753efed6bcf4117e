"""Byte-level BPE encoding and decoding with a rank queue.

A pre-token's parts stand in a doubly linked list of byte positions. Every adjacent pair that the vocabulary can merge lies in the bucket
of its rank, and a two-level bitmap tells the lowest rank whose bucket is not empty by two find-first-set steps. A merge changes two
pairs at most; entries of pairs that have changed meanwhile are left where they are and skipped when they come up. A pre-token of n
bytes takes O(n log n), so a pre-token of megabytes is no trouble. Pre-tokens seen before come from a bounded memory.
"""

from __future__ import annotations

import base64
import re
import sys
from array import array
from heapq import heappop, heappush

import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semimul.llm.common import release, text_chunks, with_text

#: Ranks a bitmap word covers, as a power of two.
WORD_BITS = 8
#: Pre-tokens of a generation; two generations are remembered.
REMEMBERED = 350_000

# The public pattern over texts of ASCII characters alone, where its character classes are these ranges.
_ASCII = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[A-Za-z]+| ?[0-9]+| ?[^\t-\r A-Za-z0-9]+|[\t-\r ]+(?![^\t-\r ])|[\t-\r ]+")


def read_ranks(data: bytes) -> dict[bytes, int]:
    """Ranks of a vocabulary file: a base64 token and its rank in each line."""
    return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in data.splitlines() if line)}


#: Bits of a bitmap word.
_BITS = tuple(1 << i for i in range(1 << WORD_BITS))
_LOW = (1 << WORD_BITS) - 1


def merge(piece: bytes, ranks: dict[bytes, int], longest: int) -> list[int]:
    """Ids of one pre-token: the pair of lowest rank is merged until no pair is in the vocabulary. The queue's steps stand in the loop
    itself, since most pre-tokens are short and calls would take most of the time. Ranks up to 65,535 take two levels of 256 bits; the
    upper level is an integer of any length, so larger vocabularies only make it longer."""
    n, get = len(piece), ranks.get
    after, before = list(range(1, n + 2)), list(range(-1, n))
    pair = [get(piece[i : i + 2], -1) for i in range(n - 1)]
    pair += (-1, -1)
    buckets: dict[int, list[int]] = {}
    words: dict[int, int] = {}
    top = 0
    for i, rank in enumerate(pair):
        if rank >= 0:
            if rank in buckets:
                buckets[rank].append(i)  # ascending, so still a heap
            else:
                buckets[rank] = [i]
                word = rank >> WORD_BITS
                if word in words:
                    words[word] |= _BITS[rank & _LOW]
                else:
                    words[word] = _BITS[rank & _LOW]
                    top |= 1 << word
    while top:
        # find first set: word, then rank
        word = (top & -top).bit_length() - 1
        bits = words[word]
        low = bits & -bits
        rank = (word << WORD_BITS) + low.bit_length() - 1
        bucket = buckets[rank]
        i = heappop(bucket)
        if not bucket:
            del buckets[rank]
            if bits == low:
                del words[word]
                top ^= 1 << word
            else:
                words[word] = bits ^ low
        if pair[i] != rank:
            continue  # the pair has changed since
        gone = after[i]
        follows = after[gone]
        after[i] = follows
        pair[gone] = pair[i] = -1
        if follows < n:
            before[follows] = i
            end = after[follows]
            new = get(piece[i:end], -1) if end - i <= longest else -1
            if new >= 0:
                pair[i] = new
                if new in buckets:
                    heappush(buckets[new], i)
                else:
                    buckets[new] = [i]
                    word = new >> WORD_BITS
                    if word in words:
                        words[word] |= _BITS[new & _LOW]
                    else:
                        words[word] = _BITS[new & _LOW]
                        top |= 1 << word
        left = before[i]
        if left >= 0:
            new = get(piece[left:follows], -1) if follows - left <= longest else -1
            pair[left] = new
            if new >= 0:
                if new in buckets:
                    heappush(buckets[new], left)
                else:
                    buckets[new] = [left]
                    word = new >> WORD_BITS
                    if word in words:
                        words[word] |= _BITS[new & _LOW]
                    else:
                        words[word] = _BITS[new & _LOW]
                        top |= 1 << word
    out, i = [], 0
    while i < n:
        end = after[i]
        out.append(ranks[piece[i:end]])
        i = end
    return out


class Encoder(dict):
    """Packed ids (little-endian, 32 bits) of each pre-token; as a dict it remembers a bounded number of them. When it is full its entries
    become the older generation, from which those that come up again are taken back."""

    def __init__(self, data: bytes, pattern: str = public_tokenizers.PATTERN):
        super().__init__()
        self.older: dict[str, bytes] = {}
        self.ranks = read_ranks(data)
        self.longest = max(map(len, self.ranks), default=0)
        self.pattern = regex.compile(pattern)
        self.ascii = _ASCII if pattern == public_tokenizers.PATTERN else self.pattern

    def __missing__(self, token: str) -> bytes:
        known = self.older.get(token)
        if known is not None:
            self[token] = known
            return known
        piece = token.encode()
        whole = self.ranks.get(piece)
        packed = array("I", [whole] if whole is not None else merge(piece, self.ranks, self.longest))
        if sys.byteorder == "big":
            packed.byteswap()
        packed = packed.tobytes()
        if len(piece) <= 64:
            if len(self) >= REMEMBERED:
                self.older = {}  # goes before its successor is made
                self.older = dict(self)
                self.clear()
            self[token] = packed
        return packed

    def encode(self, text: str) -> bytes:
        return b"".join(map(self.__getitem__, (self.ascii if text.isascii() else self.pattern).findall(text)))


class Decoder:
    def __init__(self, data: bytes):
        ranks = read_ranks(data)
        self.tokens = [b""] * (max(ranks.values(), default=-1) + 1)
        for token, rank in ranks.items():
            self.tokens[rank] = token

    def decode(self, packed: bytes) -> bytes:
        return b"".join(map(self.tokens.__getitem__, np.frombuffer(packed, dtype="<u4").tolist()))


_MADE: dict[tuple, Encoder | Decoder] = {}


def _made(kind, *key):
    """One encoder or decoder a worker process, kept for its later tasks."""
    if (kind, *key) not in _MADE:
        _MADE.clear() if len(_MADE) > 4 else None
        _MADE[(kind, *key)] = kind(*key)
    return _MADE[(kind, *key)]


def _mapped(docs: DataFrame, column: str, new: dict[str, str], make, work, keep: list[str] | None = None) -> DataFrame:
    """`docs` (of it the columns `keep`, if given) with the columns `new` appended, made from the binary form of `column`; the other columns
    pass as Arrow data."""
    rest = [c for c in (docs.columns if keep is None else keep) if c not in new]
    source, place = with_text(docs, rest, column)
    schema = docs.select(*rest).schema
    for name, kind in new.items():
        schema = schema.add(name, kind)

    def run(batches):
        tool = make()
        for batch in batches:
            for start, end, values in text_chunks(batch.column(place)):
                made = work(tool, values)
                yield pa.RecordBatch.from_arrays([batch.column(i).slice(start, end - start) for i in range(len(rest))] + made, names=[*rest, *new])
        release()

    return source.mapInArrow(run, schema)


def encode(docs: DataFrame, *, text_col: str = "text", path: str | None = None, pattern: str = public_tokenizers.PATTERN, keep: list[str] | None = None) -> DataFrame:
    """`docs` with `n_tokens` (long) and `ids` (binary: little-endian unsigned 32-bit integers) appended. `keep` names the columns that are to
    pass; a text that is not among them does not come back from the workers.

    The vocabulary file at `path` is read by the driver and sent to the workers (its size does not depend on the data). Null and empty
    texts have no ids; special tokens are ordinary text. Columns named n_tokens or ids in the input are replaced; repeated rows are
    encoded each; an empty table gives an empty result.
    """
    with open(path or public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as f:
        data = docs.sparkSession.sparkContext.broadcast(f.read())

    def work(encoder, values):
        ids = [encoder.encode(v.decode(errors="replace")) if v else b"" for v in values]
        return [pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary())]

    return _mapped(docs, text_col, {"n_tokens": "long", "ids": "binary"}, lambda: _made(Encoder, data.value, pattern), work, keep)


def decode(encoded: DataFrame, *, ids_col: str = "ids", path: str | None = None) -> DataFrame:
    """`encoded` with `decoded` (binary) appended: the bytes that the ids stand for; a null gives none."""
    with open(path or public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as f:
        data = encoded.sparkSession.sparkContext.broadcast(f.read())
    return _mapped(encoded, ids_col, {"decoded": "binary"}, lambda: _made(Decoder, data.value), lambda decoder, values: [pa.array([decoder.decode(v) if v else b"" for v in values], pa.binary())])


def round_trip(docs: DataFrame, *, text_col: str = "text", path: str | None = None, pattern: str = public_tokenizers.PATTERN) -> DataFrame:
    """`docs` with the columns of `encode` and `decode`, both made by one worker, so that the ids need not go to another and back."""
    with open(path or public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as f:
        data = docs.sparkSession.sparkContext.broadcast(f.read())

    def work(tools, values):
        encoder, decoder = tools
        ids = [encoder.encode(v.decode(errors="replace")) if v else b"" for v in values]
        return [pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary()), pa.array(map(decoder.decode, ids), pa.binary())]

    return _mapped(docs, text_col, {"n_tokens": "long", "ids": "binary", "decoded": "binary"}, lambda: (_made(Encoder, data.value, pattern), _made(Decoder, data.value)), work)
