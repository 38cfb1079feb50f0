"""A quality classifier: kernel ridge regression over document statistics, in random Fourier features, with isotonic
calibration.

Statistics of the whole text (no id, source or language) are standardised and mapped to FEATURES random cosines, whose
inner products approximate a Gaussian kernel. Each partition sums its normal equations by fold; the sums of all labelled
training rows (at most MOST_LABELS documents), a matrix of fixed size, solve the ridge regression on the driver. The penalty with the least squared error
on left-out folds wins, which follows from the same sums. The left-out scores of all training rows, counted in BINS
ranges, give the isotonic curve that turns scores into probabilities.

Cases: null texts count as empty, and empty texts get a score like others; labels are averaged where a document has
several, and null labels are ignored; without labels every score is 0.5, and labels all alike give their value; an empty
table gives an empty result; other columns are kept by `keep_good`.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, long_id, share_of, slices

FEATURES, FOLDS, BINS, SEED = 256, 4, 2048, 7
#: The most labelled documents that a model learns from (those with the least hash of the id), and the parts they are summed in.
MOST_LABELS, PARTS = 1 << 18, 32
PENALTIES = (1e-4, 1e-3, 1e-2, 1e-1)
HELD_OUT, KEEP = 5, 0.3

_CLASSES = {
    "lower": b"abcdefghijklmnopqrstuvwxyz",
    "upper": b"ABCDEFGHIJKLMNOPQRSTUVWXYZ",
    "digits": b"0123456789",
    "stops": b".,;:?'\"-()",
    "marks": b"!",
    "bars": b"|/\\<>{}[]=_~^`+",
    "signs": b"#$%&*@",
    "lines": b"\n",
    "high": bytes(range(128, 256)),
}
NAMES = [*_CLASSES, "bytes", "words", "mean_length", "deviation", "longest", "distinct", "commonest", "twins", "alone", "repeated_lines", "line_words", "bare_end", "entropy", "capital"]


def statistics(text: bytes | None) -> list[float]:
    """The statistics of a text, all of moderate size."""
    text = text or b""
    counts = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    n = max(1, len(text))
    out = [float(counts[list(c)].sum()) / n for c in _CLASSES.values()]
    words = text.split()
    m = max(1, len(words))
    lengths = np.fromiter(map(len, words), np.float64, len(words)) if words else np.zeros(1)
    often = Counter(words)
    lines = [x for x in text.split(b"\n") if x.strip()]
    twins = sum(a == b for a, b in zip(words, words[1:]))
    share = counts[counts > 0] / n
    out += [
        np.log1p(len(text)) / 10,
        np.log1p(len(words)) / 10,
        min(lengths.mean(), 50.0) / 10,
        min(lengths.std(), 50.0) / 10,
        np.log1p(lengths.max()) / 5,
        len(often) / m,
        max(often.values(), default=0) / m,
        twins / m,
        sum(len(w) == 1 for w in often) / max(1, len(often)),
        1 - len(set(lines)) / max(1, len(lines)),
        np.log1p(m / max(1, len(lines))) / 5,
        sum(not w[-1:].isalnum() for w in words) / m,
        float(-(share * np.log2(share)).sum()) / 8,
        sum(w[:1].isupper() for w in words) / m,
    ]
    return [float(x) for x in out]


def measured(docs: DataFrame, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """(id, f0, f1, ...): the statistics of every document."""
    names = [f"f{i}" for i in range(len(NAMES))]

    def run(batches):
        for b in slices(batches):
            x = np.array([statistics(t) for t in b.column("text").to_pylist()]).reshape(-1, len(names))
            yield pa.RecordBatch.from_arrays([*[pa.array(c) for c in x.T], b.column("id")], [*names, "id"])

    return docs.select(long_id(docs, id_column).alias("id"), F.col(text).cast("binary").alias("text")).mapInArrow(run, ", ".join(f"{c} double" for c in names) + ", id long")


class Model:
    """Standardisation, random features, weights and the calibration curve."""

    def __init__(self, mean: np.ndarray, scale: np.ndarray, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.mean, self.scale = mean, scale
        self.turn = rng.normal(size=(len(mean), FEATURES - 1)) / np.sqrt(len(mean))
        self.shift = rng.uniform(0, 2 * np.pi, FEATURES - 1)
        self.weights = np.zeros(FEATURES)
        self.folds = np.zeros((FOLDS, FEATURES))
        self.curve = (np.array([0.0]), np.array([0.5]))

    def features(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -8, 8)
        return np.hstack([np.sqrt(2 / FEATURES) * np.cos(z @ self.turn + self.shift), np.ones((len(z), 1))])

    def solve(self, sums: np.ndarray) -> None:
        """sums: for each fold the sums of features' products, of features times labels, and of squared labels."""
        gram, cross, squares = sums[:, :, :FEATURES], sums[:, :, FEATURES], sums[:, 0, FEATURES + 1]
        rows = gram[:, -1, -1]
        eye = np.eye(FEATURES)
        eye[-1, -1] = 1e-6
        used = [k for k in range(FOLDS) if 0 < rows[k] < rows.sum()] or []

        def fit(g, c, n, penalty):
            return np.linalg.solve(g + penalty * max(n, 1.0) * eye / FEATURES * 2, c)

        best = None
        for penalty in PENALTIES:
            left_out = {k: fit(gram.sum(0) - gram[k], cross.sum(0) - cross[k], rows.sum() - rows[k], penalty) for k in used}
            loss = sum(squares[k] - 2 * w @ cross[k] + w @ gram[k] @ w for k, w in left_out.items())
            if best is None or loss < best[0]:
                best = (loss, penalty, left_out)
        self.weights = fit(gram.sum(0), cross.sum(0), rows.sum(), best[1])
        for k in range(FOLDS):
            self.folds[k] = best[2].get(k, self.weights)

    def calibrate(self, at: np.ndarray, good: np.ndarray, count: np.ndarray) -> None:
        """Pool adjacent violators over ranges of scores in ascending order."""
        blocks: list[list[float]] = []
        for x, g, c in zip(at.tolist(), good.tolist(), count.tolist()):
            blocks.append([x * c, g, c])
            while len(blocks) > 1 and blocks[-2][1] * blocks[-1][2] >= blocks[-1][1] * blocks[-2][2]:
                top = blocks.pop()
                blocks[-1] = [a + b for a, b in zip(blocks[-1], top)]
        self.curve = (np.array([b[0] / b[2] for b in blocks]), np.array([b[1] / b[2] for b in blocks]))

    def score(self, x: np.ndarray) -> np.ndarray:
        return np.interp(self.features(x) @ self.weights, *self.curve)


def _bin(raw: np.ndarray) -> np.ndarray:
    return np.clip(np.floor((raw + 0.5) / 2 * BINS), 0, BINS - 1).astype(np.int64)


def train(features: DataFrame, labels: DataFrame) -> Model:
    """features: (id, f0, ...); labels: (id, label), of which `bounded` takes MOST_LABELS ids."""
    names = [f"f{i}" for i in range(len(NAMES))]
    rows = cut(features.join(F.broadcast(bounded(labels)), "id").repartition(PARTS, "id").select(*names, "label", F.pmod(F.crc32(F.concat(F.col("id").cast("string"), F.lit("fold"))), F.lit(FOLDS)).cast("int").alias("fold")), "labelled")
    first = rows.agg(F.count(F.lit(1)), *[F.avg(c) for c in names], *[F.stddev_pop(c) for c in names]).first()
    if not first[0]:
        return Model(np.zeros(len(names)), np.ones(len(names)))
    mean, spread = np.array(first[1 : 1 + len(names)]), np.array(first[1 + len(names) :])
    model = Model(mean, np.where(spread > 1e-9, spread, 1.0))

    def add_up(batches):
        sums = np.zeros((FOLDS, FEATURES, FEATURES + 2))
        for b in batches:
            z, y, fold = model.features(b[names].to_numpy()), b["label"].to_numpy(), b["fold"].to_numpy()
            for k in range(FOLDS):
                zk, yk = z[fold == k], y[fold == k]
                sums[k, :, :FEATURES] += zk.T @ zk
                sums[k, :, FEATURES] += zk.T @ yk
                sums[k, 0, FEATURES + 1] += (yk * yk).sum()
        part = TaskContext.get().partitionId()
        yield pd.DataFrame({"at": np.arange(FOLDS * FEATURES), "part": part, "row": list(sums.reshape(-1, FEATURES + 2))})

    def total(rows):
        return pd.DataFrame({"at": [rows["at"].iloc[0]], "row": [np.sum(rows.sort_values("part")["row"].tolist(), axis=0)]})

    parts = rows.mapInPandas(add_up, "at int, part int, row array<double>")
    summed = parts.groupBy("at").applyInPandas(total, "at int, row array<double>").collect()  # FOLDS * FEATURES rows
    model.solve(np.array([r["row"] for r in sorted(summed, key=lambda r: r["at"])]).reshape(FOLDS, FEATURES, FEATURES + 2))

    def left_out(batches):
        for b in batches:
            raw = (model.features(b[names].to_numpy()) * model.folds[b["fold"].to_numpy()]).sum(1)
            yield pd.DataFrame({"bin": _bin(raw), "raw": raw, "label": b["label"]})

    bins = rows.mapInPandas(left_out, "bin long, raw double, label double").groupBy("bin").agg(F.avg("raw").alias("at"), F.sum("label").alias("good"), F.count(F.lit(1)).alias("n"))
    found = bins.orderBy("bin").toPandas()  # BINS rows at most
    model.calibrate(found["at"].to_numpy(), found["good"].to_numpy(), found["n"].to_numpy(np.float64))
    return model


def scored(features: DataFrame, model: Model) -> DataFrame:
    names = [f"f{i}" for i in range(len(NAMES))]

    def run(batches):
        for b in batches:
            yield pd.DataFrame({"id": b["id"].astype("Int64"), "score": model.score(b[names].to_numpy())})

    return features.mapInPandas(run, "id long, score double")


def _held_out(id_column: str):
    return F.pmod(F.crc32(F.coalesce(F.col(id_column).cast("string"), F.lit(""))), F.lit(HELD_OUT)) == 0


def bounded(labels: DataFrame, most: int = MOST_LABELS) -> DataFrame:
    """(id, label), one row for each of at most `most` ids, with the mean of its labels."""
    known = labels.where("id is not null and label is not null").groupBy("id").agg(F.avg("label").alias("label"))
    n = known.count()
    if n <= most:
        return known
    return known.where(share_of(n, 1.2 * most, F.xxhash64("id"))).orderBy(F.xxhash64("id", F.lit("label")), "id").limit(most)


def training_labels(labels: DataFrame) -> DataFrame:
    return labels.where(~_held_out("doc_id")).select(long_id(labels, "doc_id").alias("id"), F.col("quality").cast("double").alias("label"))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = KEEP, text: str = "text") -> DataFrame:
    """The documents whose score reaches the threshold, unchanged; the model learns from the labelled ones among them.

    Only documents with a label that counts are measured for training: their ids, a bounded number, go to every task.
    """
    known = cut(bounded(training_labels(labels)), "labels")
    mine = docs.join(F.broadcast(known.select(F.col("id").alias("known_id"))), long_id(docs, "doc_id") == F.col("known_id"), "left_semi")
    model = train(measured(mine, text), known)

    def run(batches):
        for b in slices(batches):
            texts = b.column(text).to_pylist()
            x = np.array([statistics(t.encode("utf-8", "surrogatepass") if t else b"") for t in texts]).reshape(-1, len(NAMES))
            yield b.filter(pa.array(model.score(x) >= threshold, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def query(spark, sf_dir):
    from .common import table

    features = cut(measured(table(spark, sf_dir, "documents").select("doc_id", "text")), "statistics")
    model = train(features, training_labels(table(spark, sf_dir, "labels").select("doc_id", "quality")))
    out = scored(features, model)
    return out.select(F.col("id").alias("doc_id"), _held_out("id").alias("held_out"), "score", (F.col("score") >= KEEP).cast("int").alias("predicted"))
