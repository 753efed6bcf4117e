"""Toxicity scores by non-negative positive-unlabelled learning.

The classifier sees confirmed toxic documents and unlabelled ones, never clean labels. With p the share of toxic documents, the risk on
clean text is estimated from unlabelled text minus p times the toxic text; where that estimate turns negative the model has begun to
overfit, and the step goes the other way. The model is linear in hashed features (words and word beginnings) and is trained in numpy on
a bounded sample; scoring covers whole texts.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semimul.llm.common import release, text_chunks, with_text

#: Documents of each kind that training reads at most (in expectation, for the unlabelled), and the bytes it reads of each.
MAX_TOXIC, MAX_UNLABELLED, MAX_TRAIN_BYTES = 4000, 6000, 16_000
#: Least share of the toxic texts that a feature must be in, how much more frequent it must be there, and by how many standard deviations;
#: chosen by `selection.toxicity` on rows that are not held out.
SUPPORT, LIFT, SURPRISE = 0.005, 2.0, 4.0
#: Dimensions of the hashed features.
DIMENSIONS = 1 << 20
#: Lengths in bytes of the word beginnings that are features.
STEMS = (4, 5, 6)
#: Everything but ASCII letters, digits and bytes of other characters parts words.
_LETTERS = bytes(c if c >= 128 or chr(c).isalnum() else 32 for c in range(256))


def held_out(doc_id: Column) -> Column:
    """The third of the rows whose labels are never learned from."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1


def sampled(text: Column, most: int, block: int = 2000) -> Column:
    """The bytes of a text; of one longer than `most`, blocks from all over it at equal distances, of `most` bytes together. Null is empty."""
    raw = F.coalesce(text.cast("binary"), F.lit(b""))
    n, pieces = F.octet_length(raw), max(2, most // block)
    at = F.transform(F.sequence(F.lit(0), F.lit(pieces - 1)), lambda k: F.substring(raw, (F.floor(k * (n - block) / (pieces - 1)) + 1).cast("int"), F.lit(block)))
    return F.when(n <= most, raw).otherwise(F.aggregate(at, F.lit(b""), lambda a, x: F.concat(a, x)))


def words(text: bytes) -> set[bytes]:
    return set(text.lower().translate(_LETTERS).split())


def features(word: bytes) -> list[int]:
    made = [b"w" + word, *(b"%d" % k + word[:k] for k in STEMS if len(word) >= k)]
    return [xxhash.xxh3_64_intdigest(x) % DIMENSIONS for x in made]


@dataclass
class Model:
    weights: dict[int, float]
    bias: float
    scale: float = 1.0
    known: dict = field(default_factory=dict, repr=False)

    def score(self, text: bytes) -> float:
        """The sum of the weights of the features that occur, each once, as a probability."""
        found: set[int] = set()
        known = self.known
        for word in words(text):
            got = known.get(word)
            if got is None:
                if len(known) >= 300_000:
                    known.clear()
                got = known[word] = tuple(i for i in features(word) if i in self.weights)
            if got:
                found.update(got)
        z = self.bias + sum(self.weights[i] for i in sorted(found))
        return float(1 / (1 + np.exp(-np.clip(z, -30, 30))))


def _matrix(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Feature numbers of all texts in a row, and the text of each."""
    known: dict[bytes, list[int]] = {}
    ids, owner = [], []
    for k, text in enumerate(texts):
        found: set[int] = set()
        for word in words(text):
            got = known.get(word)
            if got is None:
                got = known[word] = features(word)
            found.update(got)
        ids.append(np.fromiter(found, dtype=np.int32, count=len(found)))
        owner.append(np.full(len(found), k, dtype=np.int32))
    empty = np.zeros(0, dtype=np.int32)
    return np.concatenate(ids or [empty]), np.concatenate(owner or [empty])


def train(toxic: list[bytes], unlabelled: list[bytes], prior: float, *, steps: int = 400, rate: float = 0.1, decay: float = 1e-4, support: float = SUPPORT, lift: float = LIFT, surprise: float = SURPRISE) -> Model:
    """Fits the linear model. Features of at least a share `support` of the toxic texts that are `lift` times as frequent in toxic as in unlabelled text at least, and by
    `surprise` standard deviations, get a weight."""
    prior = float(np.clip(prior, 1e-3, 0.9))
    if not toxic or not unlabelled:
        return Model({}, float(np.log(prior / (1 - prior))))
    (pi, po), (ui, uo) = _matrix(toxic), _matrix(unlabelled)
    dp, du = np.bincount(pi, minlength=DIMENSIONS), np.bincount(ui, minlength=DIMENSIONS)
    expected = np.maximum(du, 0.5) * (len(toxic) / len(unlabelled))
    use = (dp >= max(3, support * len(toxic))) & (dp > lift * expected) & ((dp - expected) / np.sqrt(expected) > surprise)
    place = np.full(DIMENSIONS, -1, dtype=np.int64)
    place[use] = np.arange(use.sum())
    pk, uk = place[pi] >= 0, place[ui] >= 0
    pi, po, ui, uo = place[pi[pk]], po[pk], place[ui[uk]], uo[uk]
    n, d = int(use.sum()), (len(toxic), len(unlabelled))
    w, b = np.zeros(n), float(np.log(prior / (1 - prior)))
    m1, m2 = np.zeros(n + 1), np.zeros(n + 1)
    for step in range(1, steps + 1):
        zp = b + np.bincount(po, weights=w[pi], minlength=d[0])
        zu = b + np.bincount(uo, weights=w[ui], minlength=d[1])
        sp, su = 1 / (1 + np.exp(-np.clip(zp, -30, 30))), 1 / (1 + np.exp(-np.clip(zu, -30, 30)))
        clean = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
        # slopes of the three risks: toxic text as toxic, unlabelled text as clean, toxic text as clean
        if clean >= 0:
            gp, gu = prior * (sp - 1) / d[0] - prior * sp / d[0], su / d[1]
        else:
            gp, gu = prior * sp / d[0], -su / d[1]
        g = np.append(np.bincount(pi, weights=gp[po], minlength=n) + np.bincount(ui, weights=gu[uo], minlength=n) + decay * w, gp.sum() + gu.sum())
        m1, m2 = 0.9 * m1 + 0.1 * g, 0.999 * m2 + 0.001 * g * g
        move = rate * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.999**step)) + 1e-8)
        w, b = w - move[:-1], b - move[-1]
    return Model({int(i): float(x) for i, x in zip(np.flatnonzero(use), w)}, float(b))


#: Number of the bias among a trained model's features.
BIAS = -1


def _trained(batches, prior: float):
    """(feature, weight) of the model that the rows (y, text) give, with the bias as a feature of its own."""
    texts = ([], [])
    for batch in batches:
        for y, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            texts[y].append(bytes(text))
    model = train(texts[1], texts[0], prior)
    yield pa.RecordBatch.from_arrays([pa.array([*model.weights, BIAS], pa.int32()), pa.array([*model.weights.values(), model.bias], pa.float64())], names=["feature", "weight"])
    del texts
    release()


def fit(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", max_toxic: int = MAX_TOXIC, max_unlabelled: int = MAX_UNLABELLED, max_bytes: int = MAX_TRAIN_BYTES) -> Model:
    """Trains, in a task, on rows that are not held out: at most `max_toxic` documents whose label is 1, chosen by hash, and about `max_unlabelled`
    documents whatever their label. Of a text longer than `max_bytes`, blocks from all over it are read (`sampled`). The share of toxic
    documents is that of the labels.

    Rows of `labels` whose id or label is null, or whose label is neither 0 nor 1, are left out; repeated rows of a toxic document count
    once, and one that is labelled both ways is toxic. Null texts count as empty. Without toxic or without unlabelled documents (empty
    tables too) every score is the share of toxic labels, at least a thousandth. Other columns are not read. Ties in the hash are broken by id.
    """
    usable = labels.filter(~held_out(F.col(id_col))).select(F.col(id_col).alias("id"), F.col(label_col).alias("y")).filter("id is not null and y in (0, 1)")
    prior = usable.agg(F.avg("y")).first()[0]
    chosen = usable.filter("y = 1").select("id").distinct().orderBy(F.xxhash64("id"), "id").limit(max_toxic)
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).filter(~held_out(F.col("id")))
    rate = min(1.0, max_unlabelled / max(1, docs.count()))
    some = source.filter(F.pmod(F.xxhash64(F.lit("unlabelled"), "id"), F.lit(1 << 20)) < int(rate * (1 << 20)))
    text = sampled(F.col("text"), max_bytes).alias("text")
    rows = source.join(F.broadcast(chosen), "id").select(F.lit(1).alias("y"), "id", text).unionByName(some.select(F.lit(0).alias("y"), "id", text))
    # one task trains, on a sample whose size does not grow with the tables: its texts and features would stand in the driver's memory
    made = rows.repartition(1).sortWithinPartitions("y", "id", "text").select("y", "text").mapInArrow(lambda b: _trained(b, prior or 0.0), "feature int, weight double").collect()
    weights = {r.feature: r.weight for r in made}
    return Model(weights, weights.pop(BIAS)) if weights else train([], [], prior or 0.0)


def score(docs: DataFrame, model: Model, *, text_col: str = "text", name: str = "toxicity") -> DataFrame:
    """`docs` with the double column `name` appended: how likely the whole text is toxic. Null texts count as empty; a column called
    `name` in the input is replaced; repeated rows are scored each; an empty table gives an empty result."""
    rest = [c for c in docs.columns if c != name]
    source, place = with_text(docs, rest, text_col)

    def run(batches):
        for batch in batches:
            for start, end, texts in text_chunks(batch.column(place)):
                made = pa.array([model.score(t or b"") for t in texts], pa.float64())
                yield pa.RecordBatch.from_arrays([batch.column(i).slice(start, end - start) for i in range(len(rest))] + [made], names=[*rest, name])
        model.known.clear()
        release()

    return source.mapInArrow(run, docs.select(*rest).schema.add(name, "double"))
