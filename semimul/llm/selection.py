"""Settings of the learned operators, chosen by cross-validation on labelled rows that are not held out: python -m semimul.llm.selection SF_DIR

Held-out rows are never read here, neither their labels nor their scores.
"""

from __future__ import annotations

import sys

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semimul.llm import quality_classifier, toxicity

FOLDS = 4
#: Sets of features of the quality calibration that compete.
QUALITY = {"difference": (0, 1), "difference and ratio": (0, 1, 3), "without blocks": (0, 1, 3, 4, 6), "all": (0, 1, 2, 3, 4, 5, 6)}
#: Support, lift and surprise of the toxicity features that compete.
TOXICITY = [(s, l, z) for s in (0.005, 0.01, 0.03) for l in (2.0, 3.0) for z in (4.0, 6.0)]


def rows(docs: DataFrame, labels: DataFrame, label: str, most: int = 8000) -> list[tuple[bytes, int]]:
    """(text, label) of at most `most` labelled documents that are not held out, chosen by hash."""
    usable = labels.filter(~toxicity.held_out(F.col("doc_id"))).select(F.col("doc_id").alias("id"), F.col(label).cast("int").alias("y")).filter("id is not null and y in (0, 1)").distinct()
    chosen = F.broadcast(usable.orderBy(F.xxhash64("id"), "id").limit(most))
    got = docs.select(F.col("doc_id").alias("id"), toxicity.sampled(F.col("text"), toxicity.MAX_TRAIN_BYTES).alias("text")).join(chosen, "id").select("id", "text", "y").toArrow().to_pylist()
    return [(bytes(r["text"]), r["y"]) for r in sorted(got, key=lambda r: (r["id"], r["y"]))]


def log_loss(scores: np.ndarray, y: np.ndarray) -> float:
    """Mean logarithmic loss with both classes weighing the same."""
    p = np.clip(scores, 1e-6, 1 - 1e-6)
    return float(-(np.log(p[y == 1]).mean() + np.log(1 - p[y == 0]).mean()) / 2)


def folds(n: int) -> np.ndarray:
    return np.random.default_rng(11).integers(0, FOLDS, n)


def quality(found: list[tuple[bytes, int]]) -> dict[str, float]:
    """Loss of each set of features."""
    y, fold, out = np.array([l for _, l in found]), folds(len(found)), {}
    for name, used in QUALITY.items():
        scores = np.zeros(len(found))
        for f in range(FOLDS):
            part = [found[i] for i in np.flatnonzero(fold != f)]
            model = quality_classifier.train([t for t, l in part if l == 1], [t for t, l in part if l == 0], float(np.mean([l for _, l in part])), used)
            scores[fold == f] = [model.score(found[i][0]) for i in np.flatnonzero(fold == f)]
        out[name] = log_loss(scores, y)
    return out


def toxic(found: list[tuple[bytes, int]]) -> dict[tuple, float]:
    """Loss of each triple of settings. As in use, training sees the toxic texts and all texts without their labels."""
    y, fold, out = np.array([l for _, l in found]), folds(len(found)), {}
    for support, lift, surprise in TOXICITY:
        scores = np.zeros(len(found))
        for f in range(FOLDS):
            part = [found[i] for i in np.flatnonzero(fold != f)]
            model = toxicity.train([t for t, l in part if l == 1], [t for t, _ in part], float(np.mean([l for _, l in part])), support=support, lift=lift, surprise=surprise)
            scores[fold == f] = [model.score(found[i][0]) for i in np.flatnonzero(fold == f)]
        out[support, lift, surprise] = log_loss(scores, y)
    return out


def main(sf_dir: str) -> None:
    spark = SparkSession.builder.config("spark.ui.showConsoleProgress", "false").getOrCreate()
    docs, labels = (spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in ("documents", "labels"))
    for name, f, label in (("quality", quality, "quality"), ("toxicity", toxic, "toxic")):
        losses = f(rows(docs, labels, label))
        print(name, "least:", min(losses, key=losses.get), {k: round(v, 4) for k, v in losses.items()})


if __name__ == "__main__":
    main(sys.argv[1])
