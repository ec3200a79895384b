"""Operator 3: quality classifier from random Fourier features.

Statistics of each whole text, standardised, go through cosines of random projections, which
approximate a Gaussian kernel.  Ridge scores come from normal equations that every partition sums
for its labelled documents and Spark adds up row by row of the matrix; a fifth of the training
documents is kept for the isotonic calibration of the scores (on 2,048 bins).

Nulls and edge cases: a null or empty text has all statistics 0 and gets a score like any other;
documents without a label, or with a null one, aren't learnt from; several labels of one document
count as their mean; with no labels at all every score is 0.5; a null doc_id hashes as ''.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.llm import shared, textstats

NAMES = [*textstats.BASE, *textstats.MORE]
FEATURES, WIDTH, RIDGE, BINS, SEED = 384, 1.2, 1e-4, 2048, 7


def describe(x: pd.DataFrame) -> np.ndarray:
    """The inputs of a score: ratios and logarithms of a text's counts."""
    c = {k: x[k].to_numpy(float) for k in NAMES}
    over = lambda a, b: c[a] / np.maximum(c[b], 1)
    cols = [np.log1p(c["n_words"]), np.log1p(c["n_lines"]), np.log1p(c["longest_word"]), over("word_chars", "n_words")]
    cols += [np.sqrt(over(a, "n_words")) for a in ("n_symbols", "n_repeat_words", "n_bang", "n_bar", "n_short_words", "n_end_words", "n_capital_words", "n_distinct_words", "n_distinct_pairs", "n_punct")]
    cols += [np.sqrt(over(a, "n_bytes")) for a in ("n_digits", "n_multibyte", "n_alpha")]
    cols += [np.sqrt(over("n_upper", "n_alpha")), np.sqrt(over("n_dup_lines", "n_lines")), np.log1p(over("n_words", "n_lines"))]
    return np.stack(cols, axis=1)


N_INPUTS = 20


def projections(inputs: int, features: int = FEATURES, width: float = WIDTH, seed: int = SEED) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return rng.normal(0, 1 / (width * np.sqrt(inputs)), (inputs, features)), rng.uniform(0, 2 * np.pi, features)


def lifted(z: np.ndarray, w: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Random Fourier features, with a constant and the plain inputs beside them."""
    return np.hstack([np.sqrt(2 / w.shape[1]) * np.cos(z @ w + b), 0.1 * z, np.ones((len(z), 1))])


def pooled(score: np.ndarray, count: np.ndarray, positive: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Isotonic fit of positive/count over rising scores by pooling neighbours that fall; knots and values."""
    blocks: list[list[float]] = []
    for s, n, p in zip(score, count, positive, strict=True):
        blocks.append([p, n, s * n])
        while len(blocks) > 1 and blocks[-2][0] * blocks[-1][1] >= blocks[-1][0] * blocks[-2][1]:
            p1, n1, s1 = blocks.pop()
            blocks[-1] = [blocks[-1][0] + p1, blocks[-1][1] + n1, blocks[-1][2] + s1]
    return np.array([b[2] / b[1] for b in blocks]), np.array([b[0] / b[1] for b in blocks])


class Model:
    """What a worker needs to score: a few arrays of fixed size."""

    def __init__(self, mean, scale, weights, knots, values) -> None:
        self.mean, self.scale, self.weights, self.knots, self.values = mean, scale, weights, knots, values

    def raw(self, x: pd.DataFrame) -> np.ndarray:
        z = np.clip((describe(x) - self.mean) / self.scale, -8, 8)
        return lifted(z, *projections(z.shape[1])) @ self.weights

    def score(self, x: pd.DataFrame) -> np.ndarray:
        raw = self.raw(x)
        if not len(self.knots):
            return np.full(len(raw), 0.5)
        smooth = 1 / (1 + np.exp(-np.clip(4 * (raw - 0.5), -30, 30)))
        # plateaus keep their order by a share too small to move a probability
        return np.clip(0.998 * np.interp(raw, self.knots, self.values) + 0.002 * smooth, 0, 1)


def measured(docs: DataFrame) -> DataFrame:
    """doc_id and the counts of every whole text."""
    keep = docs.select(F.col("doc_id"), F.col("text").cast("string").alias("text"))
    schema = f"doc_id {keep.schema['doc_id'].dataType.simpleString()}, " + ", ".join(f"{x} long" for x in NAMES)
    return keep.mapInArrow(lambda it: textstats.by_batch(it, ["doc_id"], NAMES), schema)


def fit(train: DataFrame) -> Model:
    """A model from rows with the counts, ``y`` (0 to 1) and ``fold`` (0-4; 4 calibrates)."""

    def moments(batches):
        for pdf in batches:
            if len(pdf):
                d = describe(pdf)
                yield pd.DataFrame([(i, float(len(d)), d[:, i].sum(), (d[:, i] ** 2).sum()) for i in range(d.shape[1])], columns=["i", "n", "s", "q"])

    got = train.mapInPandas(moments, "i int, n double, s double, q double").groupBy("i").agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum("q").alias("q")).orderBy("i").collect()
    none = np.zeros(0)
    if not got:
        return Model(np.zeros(N_INPUTS), np.ones(N_INPUTS), np.zeros(FEATURES + N_INPUTS + 1), none, none)
    n, s, q = (np.array([r[k] for r in got]) for k in ("n", "s", "q"))
    mean = s / n
    scale = np.sqrt(np.maximum(q / n - mean**2, 1e-12))
    scale[scale < 1e-6] = 1
    size = FEATURES + len(mean) + 1

    def normal(batches):
        total = np.zeros((size, size + 1))
        rows = 0
        w, b = projections(len(mean))
        for pdf in batches:
            if len(pdf):
                h = lifted(np.clip((describe(pdf) - mean) / scale, -8, 8), w, b)
                total += h.T @ np.hstack([h, pdf["y"].to_numpy(float)[:, None]])
                rows += len(pdf)
        if rows:
            yield pd.DataFrame({"i": np.arange(size), "v": [r.tobytes() for r in total]})

    def added(pdf: pd.DataFrame) -> pd.DataFrame:
        v = np.sum([np.frombuffer(x) for x in pdf["v"]], axis=0)
        return pd.DataFrame({"i": pdf["i"].iloc[:1], "v": [v.tobytes()]})

    rows = train.where("fold < 4").mapInPandas(normal, "i int, v binary").groupBy("i").applyInPandas(added, "i int, v binary").collect()
    if not rows:
        return Model(mean, scale, np.zeros(size), none, none)
    full = np.zeros((size, size + 1))
    for r in rows:
        full[r["i"]] = np.frombuffer(bytes(r["v"]))
    gram, right = full[:, :-1], full[:, -1]
    model = Model(mean, scale, np.linalg.solve(gram + RIDGE * gram[-1, -1] * np.eye(size), right), none, none)

    def binned(batches):
        for pdf in batches:
            if len(pdf):
                at = np.clip(np.floor((model.raw(pdf) + 0.5) / 2 * BINS), 0, BINS - 1).astype(int)
                y = pdf["y"].to_numpy(float)
                used = np.unique(at)
                yield pd.DataFrame({"bin": used, "n": np.bincount(at, minlength=BINS)[used].astype(float), "p": np.bincount(at, y, minlength=BINS)[used]})

    bins = train.where("fold = 4").mapInPandas(binned, "bin int, n double, p double").groupBy("bin").agg(F.sum("n").alias("n"), F.sum("p").alias("p")).orderBy("bin").collect()
    if bins:
        model.knots, model.values = pooled(np.array([(r["bin"] + 0.5) / BINS * 2 - 0.5 for r in bins]), np.array([r["n"] for r in bins]), np.array([r["p"] for r in bins]))
    return model


def hashed(text: Column) -> Column:
    return F.crc32(F.coalesce(text.cast("string"), F.lit("")).cast("binary"))


def scored(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted: learnt only from labelled rows that aren't held out."""
    stats = shared.materialised(measured(docs))
    known = labels.where(F.col("quality").isNotNull()).groupBy(F.col("doc_id").alias("_id")).agg(F.avg(F.col("quality").cast("double")).alias("y"))
    known = known.where(hashed(F.col("_id")) % 3 != 1).withColumn("fold", (hashed(F.concat(F.col("_id").cast("string"), F.lit("/fold"))) % 5).cast("int"))
    train = stats.join(known, stats["doc_id"] == known["_id"])
    model = fit(train.select(*NAMES, "y", "fold"))

    def score(batches):
        for pdf in batches:
            s = model.score(pdf)
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "score": s, "predicted": (s >= 0.5).astype("int32")})

    kind = stats.schema["doc_id"].dataType.simpleString()
    out = stats.mapInPandas(score, f"doc_id {kind}, score double, predicted int")
    return out.select("doc_id", (hashed(F.col("doc_id")) % 3 == 1).alias("held_out"), "score", "predicted")


def op3_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score and predicted of every document."""
    return scored(shared.load(spark, sf_dir, "documents").select("doc_id", "text"), shared.load(spark, sf_dir, "labels"))
