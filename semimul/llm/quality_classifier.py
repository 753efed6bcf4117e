"""Quality scores from compressed sizes.

One zstandard dictionary is built from good labelled text and one from bad. A text that resembles the good text shrinks more with the good
dictionary; the difference of the two compressed sizes over their sum, and the plain compression ratio, become a probability by a logistic
fit on labelled rows that did not enter the dictionaries. Whole texts are compressed.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semimul.llm.common import chunks
from semimul.llm.toxicity import held_out, sampled

#: Labelled documents of each class that training reads at most, the bytes it reads of each, and the size of a dictionary.
MAX_A_CLASS, MAX_TRAIN_BYTES, DICTIONARY_BYTES = 3000, 16_000, 110_000
#: Texts are compressed in blocks of this size, so that memory stays bounded and a bad passage in a good text shows.
BLOCK = 2000
LEVEL = 3
#: The features that the calibration uses, chosen by `selection.quality` on rows that are not held out: the constant, the difference of the
#: compressed sizes, its least over the blocks, the ratio, how far the ratio and the least ratio of a block fall below a quarter, shortness.
USED = (0, 1, 2, 3, 4, 5, 6)


def build_dictionary(texts: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """Content shared by the texts: zstandard's trainer picks it; where there is too little to train on, the texts themselves."""
    pieces = [t[i : i + 2000] for t in texts for i in range(0, len(t), 2000)]
    if sum(map(len, pieces)) > 20 * size:
        try:
            return zstandard.train_dictionary(size, pieces).as_bytes()
        except zstandard.ZstdError:
            pass
    return b"\n".join(pieces)[-size:]


@dataclass
class Model:
    good: bytes
    bad: bytes
    weights: tuple[float, ...] = (0.0,) * 7
    used: tuple[int, ...] = USED

    def __post_init__(self):
        self._tools = None

    def __getstate__(self):
        return (self.good, self.bad, self.weights, self.used)

    def __setstate__(self, state):
        self.good, self.bad, self.weights, self.used = state
        self._tools = None

    def sizes(self, text: bytes) -> np.ndarray:
        """Length, and compressed sizes with the good and the bad dictionary, of each block."""
        if self._tools is None:
            make = lambda d: zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_content_size=False, write_dict_id=False)
            dicts = [zstandard.ZstdCompressionDict(x) for x in (self.good, self.bad)]
            for d in dicts:
                d.precompute_compress(level=LEVEL)
            self._tools = tuple(map(make, dicts))
        blocks = [text[i : i + BLOCK] for i in range(0, max(1, len(text)), BLOCK)]
        if len(blocks) > 1 and len(blocks[-1]) < BLOCK // 4:
            blocks[-2:] = [blocks[-2] + blocks[-1]]
        good, bad = self._tools
        return np.array([[len(b), len(good.compress(b)), len(bad.compress(b))] for b in blocks], dtype=float)

    def features(self, text: bytes) -> list[float]:
        n, good, bad = (sizes := self.sizes(text)).sum(axis=0)
        apart = (sizes[:, 2] - sizes[:, 1]) / sizes[:, 1:].sum(axis=1)
        ratio = (good + bad) / (2 * n + 20)
        ratios = sizes[:, 1:].sum(axis=1) / (2 * sizes[:, 0] + 20)
        every = [1.0, 10 * (bad - good) / (good + bad), 10 * apart.min(), ratio, max(0.0, 0.25 - ratio), max(0.0, 0.25 - ratios.min()), 1 / (1 + n / 100)]
        return [x if k in self.used else 0.0 for k, x in enumerate(every)]

    def score(self, text: bytes) -> float:
        z = float(np.dot(self.weights, self.features(text)))
        return float(1 / (1 + np.exp(-np.clip(z, -30, 30))))


def calibrate(x: np.ndarray, y: np.ndarray, prior: float, ridge: float = 1e-4) -> tuple[float, ...]:
    """Logistic regression by Newton's steps, with the classes weighted as often as the labels have them."""
    w = np.zeros(x.shape[1])
    share = y.mean()
    weight = np.where(y == 1, prior / max(share, 1e-9), (1 - prior) / max(1 - share, 1e-9))
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (weight * (p - y)) / len(y) + ridge * w
        h = (x * (weight * p * (1 - p))[:, None]).T @ x / len(y) + ridge * np.eye(len(w))
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return tuple(map(float, w))


def train(good: list[bytes], bad: list[bytes], prior: float, used: tuple[int, ...] = USED) -> Model:
    """Dictionaries from two thirds of the texts, calibration on the rest."""
    if not good or not bad:
        return Model(b"x" * 8, b"x" * 8, (10.0 if good else -10.0 if bad else 0.0, *(0.0,) * 6))
    cut = lambda texts: ([t for i, t in enumerate(texts) if i % 3 or len(texts) < 3], [t for i, t in enumerate(texts) if not i % 3 or len(texts) < 3])
    (g, gt), (b, bt) = cut(good), cut(bad)
    model = Model(build_dictionary(g), build_dictionary(b), used=used)
    x = np.array([model.features(t) for t in gt + bt])
    model.weights = calibrate(x, np.array([1.0] * len(gt) + [0.0] * len(bt)), float(np.clip(prior, 0.01, 0.99)))
    return model


def fit(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", max_a_class: int = MAX_A_CLASS, max_bytes: int = MAX_TRAIN_BYTES) -> Model:
    """Trains on at most `max_a_class` labelled rows of each class that are not held out, chosen by hash. Of a text longer than `max_bytes`, blocks
    from all over it, of so many bytes together, are read (`toxicity.sampled`).

    Rows of `labels` whose id or label is null, or whose label is neither 0 nor 1, are left out; repeated rows count once. A document that
    is labelled both ways is in both classes. Null texts count as empty. Without documents of one class every score is that of the other;
    with neither (empty tables) every score is 0.5. Other columns are not read. Ties in the hash are broken by id.
    """
    usable = labels.filter(~held_out(F.col(id_col))).select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("y")).filter("id is not null and y in (0, 1)").distinct()
    prior = usable.agg(F.avg("y")).first()[0]
    order = [F.xxhash64("id"), F.col("id")]
    chosen = usable.filter("y = 1").orderBy(*order).limit(max_a_class).unionByName(usable.filter("y = 0").orderBy(*order).limit(max_a_class))
    source = docs.select(F.col(id_col).alias("id"), sampled(F.col(text_col), max_bytes, BLOCK).alias("text"))
    rows = source.join(F.broadcast(chosen), "id").select("y", "text").toArrow().to_pylist()  # `max_a_class` of either class
    rows.sort(key=lambda r: (r["y"], bytes(r["text"])))
    rng = np.random.default_rng(0)
    rows = [rows[i] for i in rng.permutation(len(rows))]
    return train([bytes(r["text"]) for r in rows if r["y"] == 1], [bytes(r["text"]) for r in rows if r["y"] == 0], prior if prior is not None else 0.5)


def score(docs: DataFrame, model: Model, *, text_col: str = "text", name: str = "quality_score") -> DataFrame:
    """`docs` with the double column `name` appended: how likely the whole text is good. Null texts count as empty and are scored too; a
    column called `name` in the input is replaced; repeated rows are scored each; an empty table gives an empty result."""
    rest = [c for c in docs.columns if c != name]
    source = docs.select(*rest, F.col(text_col).cast("binary").alias("__in"))

    def run(batches):
        for batch in batches:
            texts = batch.column(len(rest)).to_pylist()
            for start, end in chunks(texts):
                made = pa.array([model.score(t or b"") for t in texts[start:end]], pa.float64())
                yield pa.RecordBatch.from_arrays([batch.column(i).slice(start, end - start) for i in range(len(rest))] + [made], names=[*rest, name])

    return source.mapInArrow(run, docs.select(*rest).schema.add(name, "double"))
